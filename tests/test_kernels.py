"""Encoders, codecs and chunkers against slow references, and their bounds."""

import tracemalloc
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest

from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND, VIEW, WIDTH, bits_of, values_of, with_bits
from paramstore.operators import accuracy, coders, dedup, distance, kernels, redundancy, similarity, unitpack
from paramstore.plans import hybrid

RNG = np.random.default_rng(4)
ODD = [0.0, -0.0, 1.0, -1.0, 1.5, np.inf, -np.inf, np.nan, 5e-324, 1e-45, 1 - 2.0**-24, 1 - 2.0**-53, 1 - 2.0**-11, -0.25, 0.75]


def samples(dtype):
    values = np.concatenate((ODD, RNG.normal(0, 0.3, 500), RNG.choice([0.1, 0.2, 0.3], 300))).astype(VIEW[dtype][0])
    return bits_of(values, dtype)


@pytest.mark.parametrize("dtype", ["float16", "float32", "float64"])
def test_distance_encoding_is_lossless(dtype):
    for bits in (samples(dtype), samples(dtype)[:0], samples(dtype)[:1], np.zeros(50, np.int64)):
        assert (distance.decode(distance.encode(bits, dtype), dtype) == bits).all()


def test_distance_of_a_million():
    assert int(1_000_000).bit_length() == 20
    prev = distance.previous_positions(np.array([5, 7, 5, 5, 7]))
    assert prev.tolist() == [-1, -1, 0, 2, 1]


@pytest.mark.parametrize("dtype", ["float16", "float32", "float64"])
def test_packing_keeps_the_bound_and_the_exceptions(dtype):
    kind, whole = VIEW[dtype]
    for bits in (samples(dtype), samples(dtype)[:0], samples(dtype)[:1]):
        back = unitpack.unpack(unitpack.pack(bits, dtype), dtype)
        v, w = values_of(bits, dtype), values_of(back, dtype)
        with np.errstate(invalid="ignore"):
            inside = (np.abs(v) < 1) & (np.abs(v) + kind(1) < 2)
        assert (bits_of(w[~inside], dtype) == bits[~inside]).all()
        assert (np.abs(v[inside].astype(np.float64) - w[inside].astype(np.float64)) <= BOUND[dtype]).all()
        assert (np.signbit(v[inside]) == np.signbit(w[inside])).all()


def test_packing_example():
    bits = bits_of(np.array([0.1415926069021225]), "float32")
    assert values_of(unitpack.unpack(unitpack.pack(bits, "float32"), "float32"), "float32")[0] == np.float32(0.1415926218032837)


def test_gear_hash_and_cuts():
    data = RNG.integers(0, 256, 5000, dtype=np.uint8)
    slow, h = [], 0
    for i in range(len(data)):
        h = sum(int(dedup.GEAR[data[j]]) << (i - j) for j in range(max(0, i - 63), i + 1)) & 0xFFFFFFFFFFFFFFFF
        slow.append(h)
    assert dedup.gear_hashes(data).tolist() == slow
    ends = dedup.gear_cuts(data, 128, 512, 2048)
    sizes = np.diff([0, *ends])
    assert ends[-1] == len(data) and sizes.max() <= 2048 and (sizes[:-1] >= 128).all()
    assert dedup.gear_cuts(data[:0]) == []
    shifted = set(np.array(dedup.gear_cuts(np.concatenate((data[:1], data)), 128, 512, 2048)) - 1)
    assert len(shifted & set(ends)) > len(ends) / 2  # one byte more at the head moves few cuts


def test_rolling_fingerprint():
    data = RNG.integers(0, 256, 200, dtype=np.uint8)

    def slow(part):
        value = 0
        for b in part.tolist():
            for bit in range(7, -1, -1):
                value = value << 1 | b >> bit & 1
                if value >> similarity.DEGREE:
                    value ^= similarity.POLYNOMIAL
        return value

    assert similarity.rolling(data).tolist() == [slow(data[i : i + 48]) for i in range(200 - 47)]
    assert len(similarity.super_features_of(b"")) == 3


def test_gorilla_counts():
    one = np.array([1.5, 1.5, 1.5], np.float64).tobytes()
    assert kernels.gorilla(one, "float64") == 64 + 2
    assert kernels.gorilla(b"", "float64") == 0


def test_huffman_bits():
    assert kernels.huffman_bits(np.array([1, 1, 1, 1, 2, 2, 3, 4])) == 4 * 1 + 2 * 2 + 3 + 3 + 64


@pytest.mark.parametrize("dtype", ["float32", "float64"])
def test_zfp_keeps_its_tolerance(dtype):
    values = RNG.normal(0, 0.2, 1003).astype(VIEW[dtype][0]).astype(np.float64)
    for tolerance in (2.0**-10, 2.0**-20, BOUND["float32"]):
        bits, back = kernels.zfp(values, dtype, tolerance)
        assert np.abs(back - values).max() <= tolerance
    assert kernels.zfp(np.zeros(8), dtype, 0.1)[0] == 2


def test_lossy_methods_keep_the_bound():
    values = RNG.normal(0, 0.1, 64).astype(np.float32)
    for method in ("hybrid", "predquant", "mp", "gouq"):
        assert np.abs(accuracy.restored(values, method).astype(np.float64) - values).max() <= 2 * BOUND["float32"]
    assert np.abs(accuracy.restored(values, "half") - values).max() > 100 * BOUND["float32"]


def test_two_phase_previous_equals_a_loop(spark):
    bits = RNG.choice([0, 1, 2, 50, 51], 400, p=[0.7, 0.1, 0.1, 0.05, 0.05]).tolist()
    frame = spark.createDataFrame([("m", "float64", i, b) for i, b in enumerate(bits)], "model_id string, dtype string, pos long, bits long")
    got = {r.pos: r.prev for r in redundancy.previous(frame, block=4).collect()}
    last = {}
    for i, b in enumerate(bits):
        assert got[i] == last.get(b)
        last[b] = i


def test_degradation_of_one_in_a_thousand():
    a = np.arange(1000, dtype=np.float32)[None, :]
    b = a.copy()
    b[0, 7] += 1
    assert accuracy.differing(a, b, "bits") == (1, 1000)
    assert accuracy.differing(a, b, "topk") == (0, 1)
    assert accuracy.differing(a, b, "cosine") == (1, 1) and accuracy.differing(a, a * 2, "cosine") == (0, 1)
    assert accuracy.differing(a, -a, "topk") == (1, 1)


def test_outputs_differ_against_numpy(spark):
    rng = np.random.default_rng(2)
    rows = [(f"m{k % 2}", k // 2, rng.normal(0, 0.2, 16 - 5 * (k == 7)).astype(np.float32)) for k in range(10)]
    layers = spark.createDataFrame([(m, s, x.tobytes()) for m, s, x in rows], "model_id string, layer_seq long, payload binary")
    inputs = rng.standard_normal((40, 24)).astype(np.float32)
    frame = spark.createDataFrame([(("a", "b")[i % 2], x.tobytes()) for i, x in enumerate(inputs)], "task string, payload binary").repartition(3)
    wide = inputs[:, :16].copy()
    wide[:, :8] += inputs[:, 16:]
    for most in (64 << 20, 1):  # all heads in one broadcast, and one for each model
        groups = list(accuracy.head_groups(layers, ("half", "mp"), most))
        assert len(groups) == (1 if most > 1 else 2)
    got = {(r.task, r.method, r.model_id): (r.differ, r.n) for r in accuracy.outputs_differ(frame, layers, {"a": "bits", "b": "topk"}, ("half", "mp"), k=2).collect()}
    for model in ("m0", "m1"):
        own = [np.pad(x, (0, 16 - len(x))) for m, _, x in sorted(rows, key=lambda r: r[1]) if m == model]
        for task, part in (("a", wide[::2]), ("b", wide[1::2])):
            before, after = part @ np.stack(own).T, part @ np.stack([x.astype(np.float16).astype(np.float32) for x in own]).T
            if task == "a":
                assert got[task, "half", model] == ((before != after).sum(), before.size)
            else:
                sets = [set(np.argsort(-x, kind="stable")[:2]) for x in before], [set(np.argsort(-x, kind="stable")[:2]) for x in after]
                assert got[task, "half", model] == (sum(x != y for x, y in zip(*sets, strict=True)), len(part))
            assert got[task, "mp", model][0] == 0


def coder_samples(dtype):
    with np.errstate(all="ignore"):
        kinds = [np.array(ODD), RNG.normal(0, 0.3, 1000), RNG.choice([0.1, 0.2, 0.3, 1234.56], 1000), np.zeros(0), np.zeros(300), np.ones(1), RNG.normal(0, 1e4, 700), np.concatenate((ODD, RNG.normal(0, 0.3, 300)))]
        return [x.astype(VIEW[dtype][0]) for x in kinds]


@pytest.mark.parametrize("dtype", ["float16", "float32", "float64"])
@pytest.mark.parametrize("name", list(coders.CODERS))
def test_coders_round_trip(name, dtype):
    encode, decode = coders.CODERS[name]
    for v in coder_samples(dtype):
        back = decode(encode(v.tobytes(), dtype), dtype)
        assert len(back) == v.nbytes
        if name in coders.LOSSLESS:
            assert back == v.tobytes()
        elif name != "half":
            x, y = v.astype(np.float64), np.frombuffer(back, VIEW[dtype][0]).astype(np.float64)
            inside = np.abs(x) < 1
            assert np.abs(x[inside] - y[inside]).max(initial=0.0) <= BOUND[dtype] * (2 if dtype == "float64" else 1)


def test_bit_fields():
    widths = RNG.integers(0, 65, 300)
    values = np.array([int(RNG.integers(0, 1 << 62)) % (1 << int(w)) for w in widths], np.uint64)
    data = coders.put(values, widths)
    text = "".join(format(int(v), "b").zfill(int(w)) if w else "" for v, w in zip(values, widths, strict=True))
    assert "".join(format(b, "08b") for b in data)[: len(text)] == text
    assert (coders.take(data, widths) == values).all()


def slow_gorilla(bits, w):
    """Bits of the XOR coder, one value after the other."""
    total, lead, size = w if len(bits) else 0, None, None
    for a, b in zip(bits, bits[1:], strict=False):
        x = a ^ b
        if not x:
            total += 1
            continue
        leading, trailing = min(w - x.bit_length(), 31), (x & -x).bit_length() - 1
        if lead is not None and leading >= lead and trailing >= w - lead - size:
            total += 2 + size
        else:
            lead, size = leading, w - leading - trailing
            total += 13 + size
    return total


@pytest.mark.parametrize("dtype", ["float32", "float64"])
def test_gorilla_against_a_loop(dtype):
    for v in coder_samples(dtype):
        bits = v.view(coders.UNSIGNED[dtype]).tolist()
        want = slow_gorilla(bits, WIDTH[dtype])
        assert kernels.gorilla(v.tobytes(), dtype) == want
        if len(v):
            head, first, body = coders.split(coders.gorilla_encode(v.tobytes(), dtype))
            assert 0 <= 8 * len(body) - (want - WIDTH[dtype]) < 8


@pytest.mark.parametrize("dtype", ["float32", "float64"])
def test_predquant_against_a_loop(dtype):
    """Residuals, one part and one value after the other; the Huffman code by its textbook definition."""
    v = np.concatenate((RNG.normal(0, 1e-3, 700), [np.inf, 0.0])).astype(VIEW[dtype][0])
    step, w, q, raw = 2 * BOUND[dtype], WIDTH[dtype], [], 0
    for x in v.astype(float):
        fine = np.isfinite(x) and abs(x / step) < 2.0**52
        raw += not fine
        q.append(int(np.floor(x / step + 0.5)) if fine else 0)
    bits = lambda r: sum(abs(x).bit_length() + 1 for x in r)
    total, codes = raw * w, []
    for at in range(0, len(q), 256):
        own = q[at : at + 256]
        last = [b - a for a, b in zip([q[at - 1] if at else 0, *own], own, strict=False)]
        x = [i - (len(own) - 1) / 2 for i in range(len(own))]
        slope = sum(a * b for a, b in zip(x, own, strict=True)) / max(sum(a * a for a in x), 1.0)
        mean = float(np.mean(own))
        line = [b - int(np.floor(mean + slope * a + 0.5)) for a, b in zip(x, own, strict=True)]
        use = bits(line) + 2 * w < bits(last)
        total += 1 + 2 * w * use
        codes += line if use else last
    far = sum(abs(r) > 1 << 15 for r in codes)
    symbols = [r if abs(r) <= 1 << 15 else (1 << 15) + 1 for r in codes]
    assert kernels.predquant(v.tobytes(), dtype) == pytest.approx(total + kernels.huffman_bits(np.array(symbols)) + far * w, rel=2e-3)


@pytest.mark.parametrize("dtype", ["float32", "float64"])
def test_sprintz_lookup_against_a_loop(dtype):
    w, half = WIDTH[dtype], 1 << WIDTH[dtype] - 1
    wrap = lambda x: (x + half) % (2 * half) - half
    for v in coder_samples(dtype):
        bits, table, last, z = [wrap(x) for x in v.view(coders.UNSIGNED[dtype]).tolist()], {}, 0, []
        for a, b in zip(bits, bits[1:], strict=False):
            slot = ((last % (2 * half)) * 0x9E3779B97F4A7C15 % (1 << 64)) >> 56
            d = wrap(b - a)
            r = wrap(d - table.get(slot, 0))
            table[slot] = last = d
            z.append(2 * r if r >= 0 else -2 * r - 1)
        widths = [max(x.bit_length() for x in z[i : i + 8]) for i in range(0, len(z), 8)]
        header = w.bit_length()
        want = sum(header + 8 * x for x in widths if x) + sum((header + 16) for i, x in enumerate(widths) if not x and (not i or widths[i - 1]))
        assert kernels.sprintz_lookup(v.tobytes(), dtype) == (w + want if len(v) else 0)


def test_super_features_find_a_changed_layer():
    data = RNG.integers(0, 256, 4000, dtype=np.uint8)
    near = data.copy()
    near[100] ^= 1
    a, b, c = (similarity.super_features_of(x.tobytes()) for x in (data, near, RNG.integers(0, 256, 4000, dtype=np.uint8)))
    assert a == similarity.super_features_of(data.tobytes()) and set(a) & set(b) and not set(a) & set(c)
    tops = [sorted({int(x) for x in similarity.rolling(part)}, reverse=True)[:3] for part in np.array_split(data, 4)]
    import hashlib

    assert a == [hashlib.sha256(",".join(str(t[k]) for t in tops).encode()).hexdigest() for k in range(3)]


def test_sampled_bytes_are_linear_and_exact(spark):
    import hashlib
    import time

    payloads = [RNG.integers(0, 256, 200_000, dtype=np.uint8).tobytes() for _ in range(4)]
    layers = spark.createDataFrame([(str(i), "uint8", p) for i, p in enumerate(payloads)], "layer_id string, dtype string, payload binary")
    began = time.time()
    got = {r.layer_id: r.fp for r in similarity.sampled_bytes(layers).collect()}
    assert time.time() - began < 15
    assert got == {str(i): hashlib.sha256(p[::32].hex().upper().encode()).hexdigest() for i, p in enumerate(payloads)}


def test_median_distances(spark):
    rows = [("m", "float64", int(x)) for x in RNG.integers(1, 1 << 20, 501)] + [("n", "float64", d) for d in (1, 1, 3, 900)]
    got = {r.model_id: r.median_distance for r in redundancy.medians(spark.createDataFrame(rows, "model_id string, dtype string, d long")).collect()}
    assert got == {m: float(np.median([d for k, _, d in rows if k == m])) for m in "mn"}


def test_store_with_hot_prints_and_one_label(spark):
    """Half of all layers are one layer, ids and floats mixed, empty blocks between; everything comes back, and only prints decide."""
    rows, rng = [], np.random.default_rng(6)
    for k in range(60):
        size = (1, 3, 5000, 64)[k % 4]
        values = np.arange(size, dtype=float) if k % 2 else rng.choice([0.25, -0.5, 7.5, 0.1], size)
        rows += [(f"m{k % 3}", "c", f"l{k}", k, "int64" if k % 2 else "float64", i, i, float(v)) for i, v in enumerate(values)]
    frame = with_bits(spark.createDataFrame(rows, "model_id string, category string, layer_id string, layer_seq long, dtype string, layer_pos long, pos long, value double"))
    layers = hybrid.stage_dedup(frame).collect()
    groups = {}
    for r in sorted(layers, key=lambda r: (r.model_id, r.layer_seq)):
        assert r.canonical == groups.setdefault((r.fp, r.dtype), r.layer_id) and r.copy == (1 if r.canonical == r.layer_id else 2)
    found = {r.dtype: r for r in hybrid.verify(frame).collect()}
    assert all(not r.missing and not r.others_differ for r in found.values())
    assert found["float64"].max_error <= BOUND["float64"] and found["int64"].max_error is None
    assert sum(r.params for r in found.values()) == len(rows)
    again = hybrid.stage_dedup(frame.withColumn("layer_id", F.concat("layer_id", F.lit("x"))), hybrid.stage_dedup(frame).where("copy = 1").select("fp", "dtype", "canonical"))
    assert again.where("copy = 1").count() == 0 and {r.canonical for r in again.collect()} == {r.canonical for r in layers}


def test_byte_store_gives_everything_back(spark):
    payloads = [b"", b"", b"abc" * 1000, b"abc" * 1000, bytes(range(256)), b"x"]
    layers = spark.createDataFrame([(f"l{i}", "uint8", p) for i, p in enumerate(payloads)], "layer_id string, dtype string, payload binary")
    stored, refs = hybrid.store_bytes(layers)
    assert stored.count() == 4 and {r.layer_id: bytes(r.payload) for r in hybrid.restore_bytes(stored, refs).collect()} == {f"l{i}": p for i, p in enumerate(payloads)}


def test_choice_by_blocks_is_what_blocks_have(spark):
    bits = [int(x) for x in RNG.integers(0, 40, 9000)]
    frame = spark.createDataFrame([("m", "c", "l", 0, "float64", i, i, 0.0, b) for i, b in enumerate(bits)], "model_id string, category string, layer_id string, layer_seq long, dtype string, layer_pos long, pos long, value double, bits long")
    sized = distance.sizes(frame, segment=4096).first().compressed
    stream = sum(int(np.frombuffer(distance.encode(np.array(bits[a : a + 4096]), "float64")[8:16], "<i8")[0]) + 64 * len(set(bits[a : a + 4096])) for a in range(0, 9000, 4096))
    assert sized == stream


def test_best_sets_are_compared_as_if_sorted():
    """Ties by place, infinite and missing outputs, fewer outputs than k."""
    rng = np.random.default_rng(8)
    top = lambda x, k: np.sort(np.argsort(-x, axis=1, kind="stable")[:, :k], axis=1)
    for width, k in ((3, 5), (5, 5), (40, 5), (200, 1)):
        a = rng.integers(0, 6, (500, width)).astype(np.float32)
        b = a + (rng.random(a.shape) < 0.02)
        a[::50, 0], b[::40, 1], a[::70, 2] = np.nan, -np.inf, np.inf
        assert accuracy.differing(a, b, "topk", k) == (int((top(a, k) != top(b, k)).any(axis=1).sum()), 500)


def heads_of(rng, n=300, width=12):
    own = (rng.standard_normal((n, width)) * 0.2).astype(np.float32)
    own[7], own[9], own[11] = own[3], own[3], 0  # ties and a layer of zeros
    return {m: own if m == "original" else accuracy.restored_rows(own, m) for m in ("original", *accuracy.METHODS)}


@pytest.mark.parametrize("kind", ["plain", "ties", "missing", "infinite"])
def test_heads_block_by_block_equal_all_outputs(monkeypatch, kind):
    """Margins and forms give what all outputs give, whatever the blocks are."""
    rng = np.random.default_rng(12)
    by = heads_of(rng)
    if kind == "ties":  # half of the layers are one layer, as restored too
        by = {m: np.concatenate([w[:150], np.repeat(w[3:4], 150, axis=0)]) for m, w in by.items()}
    elif kind != "plain":
        by["original"] = by["original"].copy()
        by["original"][5, 0] = np.nan if kind == "missing" else np.inf
        by["mp"] = by["original"]
    x = rng.standard_normal((700, 12)).astype(np.float32)
    x[4] = 0
    for sizes in ((512, 2048), (100, 64), (33, 5)):
        monkeypatch.setattr(accuracy.Head, "ROWS", sizes[0])
        monkeypatch.setattr(accuracy.Head, "LAYERS", sizes[1])
        head = accuracy.Head(by, accuracy.METHODS)
        for compare in ("topk", "cosine", "bits"):
            got = head.differing(x, compare)
            with np.errstate(invalid="ignore"):
                for m in accuracy.METHODS:
                    want = accuracy.differing(x @ by["original"].T, x @ by[m].T, compare)
                    assert got[m][1] == want[1]
                    assert abs(got[m][0] - want[0]) <= (0.002 * want[1] if compare == "bits" else 0), (m, compare, sizes)  # bits of sums depend on blocks


def test_outputs_of_a_large_model_are_never_held_whole(monkeypatch):
    """The kernel of outputs_differ over 4,096 inputs and 10,000 layers: all outputs of one matrix are 164 MB."""
    rng, kernels_, peak = np.random.default_rng(13), [], []
    own = (rng.standard_normal((10_000, 8)) * 0.2).astype(np.float32)
    group = {"m": {"original": own, "half": own.astype(np.float16).astype(np.float32)}}

    class Frame:
        sparkSession = SimpleNamespace(sparkContext=SimpleNamespace(broadcast=lambda x: SimpleNamespace(value=x)))
        select = groupBy = agg = lambda self, *x: self

        def mapInArrow(self, run, schema):
            kernels_.append(run)
            return self

    monkeypatch.setattr(accuracy, "head_groups", lambda layers, methods: [group])
    monkeypatch.setattr(accuracy.F, "sum", lambda c: SimpleNamespace(alias=lambda n: None))
    accuracy.outputs_differ(Frame(), Frame(), {"a": "topk", "b": "cosine"}, ("half",))
    batch = pa.RecordBatch.from_arrays([pa.array(["a", "b"] * 2048), pa.array([x.tobytes() for x in rng.standard_normal((4096, 8)).astype(np.float32)], pa.binary())], ["task", "payload"])
    tracemalloc.start()
    try:
        rows = [r for b in kernels_[0](iter([batch])) for r in b.to_pylist()]
        peak.append(tracemalloc.get_traced_memory()[1])
    finally:
        tracemalloc.stop()
    assert [(r["task"], r["n"]) for r in rows] == [("a", 2048), ("b", 2048)]
    assert peak[0] < 60e6


def test_inputs_of_several_groups_of_heads_are_made_once(spark, monkeypatch):
    rng, made = np.random.default_rng(15), spark.sparkContext.accumulator(0)
    layers = spark.createDataFrame([(f"m{k % 3}", k, rng.normal(0, 0.2, 8).astype(np.float32).tobytes()) for k in range(30)], "model_id string, layer_seq long, payload binary")
    rows = [(("a", "b")[i % 2], rng.standard_normal(8).astype(np.float32).tobytes()) for i in range(60)]

    def counted(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    frame = lambda: spark.createDataFrame(rows, "task string, payload binary").mapInArrow(counted, "task string, payload binary")
    run = lambda: sorted(map(tuple, accuracy.outputs_differ(frame(), layers, {"a": "topk", "b": "cosine"}, ("half", "mp"), k=2).collect()))
    want, whole = run(), accuracy.head_groups
    assert made.value == 60
    monkeypatch.setattr(accuracy, "head_groups", lambda layers, methods: whole(layers, methods, 1))  # a group for each model
    assert run() == want and made.value == 120


def test_text_vectors_equal_one_text_at_a_time():
    rng = np.random.default_rng(14)
    raws = [b"", b"a", b"ab", bytes(rng.integers(0, 256, 5000, np.uint8)), "ä€ text".encode()] * 3
    want = []
    for raw in raws:
        v, data = np.zeros(64), raw + b"\n\n"
        for i in range(len(raw)):
            h = int.from_bytes(data[i : i + 3], "big") * 0x9E3779B97F4A7C15 % 2**64
            v[(h >> 50) % 64] += 1 - 2 * (h >> 40 & 1)
        want.append((v / max(np.linalg.norm(v), 1e-12)).astype(np.float32))
    for rows, size in ((4096, 1 << 20), (2, 1 << 20), (3, 100)):
        assert (accuracy.text_vectors(raws, 64, rows, size) == np.array(want)).all()


def test_restored_rows_equal_single_vectors():
    rng = np.random.default_rng(9)
    for width in (1, 6, 64):
        rows = (rng.standard_normal((50, width)) * rng.choice([1e-9, 0.1, 3.0], (50, 1))).astype(np.float32)
        rows[3], rows[4, 0] = 0, 1.0
        for method in accuracy.METHODS:
            assert (accuracy.restored_rows(rows, method) == np.array([accuracy.restored(r, method) for r in rows])).all(), (width, method)


def test_nearest_centroids_by_any_groups_of_labels(spark, monkeypatch):
    rng = np.random.default_rng(10)
    rows = [("t" + str(i % 2), i, "abcde"[i % 5], rng.standard_normal(8).astype(np.float32).tobytes()) for i in range(300)] + [("t0", 0, "a", np.ones(6, np.float32).tobytes())] * 2
    frame = spark.createDataFrame(rows, "task string, vec_id long, label string, payload binary").repartition(3)
    methods = ("half", "mp")
    got = sorted(map(tuple, accuracy.vector_benchmark(frame, methods).collect()))
    whole = accuracy.label_groups
    monkeypatch.setattr(accuracy, "label_groups", lambda means, m: whole(means, m, 100))  # a label a group
    assert sorted(map(tuple, accuracy.vector_benchmark(frame, methods).collect())) == got
    for task, method, _, before, after, n in got:
        own = [(x, np.pad(np.frombuffer(p, np.float32), (0, 8 - len(p) // 4))) for t, _, x, p in rows if t == task]
        for share, values in ((before, [(x, v) for x, v in own]), (after, [(x, accuracy.restored(v, method)) for x, v in own])):
            means = {c: np.mean([v.astype(float) for x, v in values if x == c], axis=0) for c in "abcde"}
            assert n == len(own) and share == pytest.approx(np.mean([min(means, key=lambda c: ((v - means[c]) ** 2).sum()) == x for x, v in values]))


def test_entropy_sizes_equal_the_encoded_store(spark):
    from paramstore.sources import zoo

    params = zoo.params(spark, "/root/testdata/sf0.001", ("vec", "line", "cust", "key", "posid"))
    want = hybrid.stage_entropy(hybrid.encode(params))
    rows = lambda f: sorted(tuple(r[c] for c in want.columns) for r in f.collect())
    got = rows(hybrid.entropy_sizes(params))
    assert got == rows(want) and {r[2] for r in got} == {"de", "unit", "raw"}
