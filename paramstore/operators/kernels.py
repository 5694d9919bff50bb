"""Baseline codecs that need a state or a byte coder: kernels over blocks, block by block, so that any block is coded alone."""

from __future__ import annotations

import heapq
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND, CODE_BITS, VIEW, WIDTH


def block_bits(blocks: DataFrame, kernel) -> DataFrame:
    """(model_id, dtype, params, original, compressed): kernel(payload, dtype) gives a block's bits."""

    def run(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            bits = [int(kernel(p, d)) for p, d in zip(cols["payload"], cols["dtype"], strict=True)]
            raw = [8 * len(p) for p in cols["payload"]]
            n = [r // WIDTH[d] for r, d in zip(raw, cols["dtype"], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(cols["dtype"]), pa.array(n, pa.int64()), pa.array(raw, pa.int64()), pa.array(bits, pa.int64())], ["model_id", "dtype", "params", "original", "compressed"])

    rows = blocks.select("model_id", "dtype", "payload").mapInArrow(run, "model_id string, dtype string, params long, original long, compressed long")
    return rows.groupBy("model_id", "dtype").agg(*[F.sum(c).alias(c) for c in ("params", "original", "compressed")])


def gzip(level: int = 6):
    return lambda payload, dtype: 8 * len(zlib.compress(payload, level, 31))


def zstd(level: int = 3):
    return lambda payload, dtype: 8 * len(pa.Codec("zstd", compression_level=level).compress(payload, asbytes=True))


def bits_in(payload: bytes, dtype: str) -> np.ndarray:
    return np.frombuffer(payload, {"float16": np.uint16, "float32": np.uint32, "float64": np.uint64}[dtype])


def values_in(payload: bytes, dtype: str) -> np.ndarray:
    return np.frombuffer(payload, VIEW[dtype][0])


def bit_width(x: np.ndarray) -> np.ndarray:
    """Binary digits of unsigned numbers."""
    out, left = np.zeros(len(x), np.int64), x.astype(np.uint64)
    for shift in (32, 16, 8, 4, 2, 1):
        big = left >> np.uint64(shift) > 0
        out[big] += shift
        left = np.where(big, left >> np.uint64(shift), left)
    return out + (left > 0)


def gorilla(payload: bytes, dtype: str) -> int:
    """XOR with the value before; a window of meaningful bits is kept until a new one is needed."""
    w, bits = WIDTH[dtype], bits_in(payload, dtype)
    if not len(bits):
        return 0
    xor = bits[1:] ^ bits[:-1]
    total, lead, size = w, -1, 0
    widths = bit_width(xor)
    low = bit_width(xor & (~xor + xor.dtype.type(1))) - 1
    for digits, trail in zip(widths.tolist(), low.tolist(), strict=True):
        if not digits:
            total += 1
            continue
        leading = min(w - digits, 31)
        if lead >= 0 and leading >= lead and trail >= w - lead - size:
            total += 2 + size
        else:
            lead, size = leading, w - leading - trail
            total += 2 + 5 + 6 + size
    return total


def sprintz_adaptive(payload: bytes, dtype: str) -> int:
    """Blocks of eight, each with the better of two predictors (last value, last slope): one selector bit more than the delta form."""
    w, bits = WIDTH[dtype], bits_in(payload, dtype)
    if not len(bits):
        return 0
    kind = VIEW[dtype][1]
    with np.errstate(over="ignore"):
        x = bits.view(kind)
        first = np.diff(x)
        second = np.concatenate((first[:1], np.diff(first)))

        def widths(d):
            z = ((d << 1) ^ (d >> (w - 1))).view(bits.dtype)
            padded = np.zeros(-(-len(z) // 8) * 8, bits.dtype)
            padded[: len(z)] = z
            return bit_width(padded).reshape(-1, 8).max(axis=1) if len(z) else np.zeros(0, np.int64)

        best = np.minimum(widths(first), widths(second))
    header = int(w).bit_length()
    zero = best == 0
    run_starts = zero & ~np.concatenate(([False], zero[:-1]))
    return w + int((~zero * (header + 1 + 8 * best)).sum() + run_starts.sum() * (header + 16))


def sprintz_lookup(payload: bytes, dtype: str, slots: int = 256) -> int:
    """Blocks of eight under a table of predictions: what followed the last difference of the same hash is what is expected to follow."""
    w, bits = WIDTH[dtype], bits_in(payload, dtype)
    if not len(bits):
        return 0
    kind = VIEW[dtype][1]
    with np.errstate(over="ignore"):
        d = np.diff(bits.view(kind))
        before = np.concatenate((np.zeros(1, kind), d[:-1])).view(bits.dtype).astype(np.uint64)
        slot = (before * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - (slots - 1).bit_length())
        order = np.argsort(slot, kind="stable")
        expected = np.zeros(len(d), kind)  # an entry that was never set predicts no change
        same = slot[order][1:] == slot[order][:-1]
        expected[order[1:][same]] = d[order[:-1][same]]
        r = d - expected
        z = ((r << 1) ^ (r >> (w - 1))).view(bits.dtype)
    padded = np.zeros(-(-len(z) // 8) * 8, bits.dtype)
    padded[: len(z)] = z
    widths = bit_width(padded).reshape(-1, 8).max(axis=1) if len(z) else np.zeros(0, np.int64)
    zero = widths == 0
    run_starts = zero & ~np.concatenate(([False], zero[:-1]))
    header = int(w).bit_length()
    return w + int((~zero * (header + 8 * widths)).sum() + run_starts.sum() * (header + 16))


def huffman_bits(symbols: np.ndarray) -> int:
    """Coded length of the symbols under their own Huffman code, and 16 bits a symbol for the table."""
    counts = list(Counter(symbols.tolist()).values())
    if not counts:
        return 0
    if len(counts) == 1:
        return counts[0] + 16
    total, heap = 0, counts[:]
    heapq.heapify(heap)
    while len(heap) > 1:
        x = heapq.heappop(heap) + heapq.heappop(heap)
        total += x
        heapq.heappush(heap, x)
    return total + 16 * len(counts)


def predquant(payload: bytes, dtype: str, radius: int = 1 << 15, part: int = 256) -> int:
    """Pre-quantized values by the better, for each part, of last-value and line prediction; residuals coded, far ones raw."""
    w, values, eb = WIDTH[dtype], values_in(payload, dtype).astype(np.float64), BOUND[dtype]
    with np.errstate(invalid="ignore", over="ignore"):
        scaled = values / (2 * eb)
        fits = np.isfinite(scaled) & (np.abs(scaled) < 2.0**52)
    q = np.where(fits, np.floor(np.where(fits, scaled, 0) + 0.5), 0).astype(np.int64)
    total, codes = int((~fits).sum()) * w, []
    for at in range(0, len(q), part):
        own = q[at : at + part]
        last = np.diff(own, prepend=q[at - 1] if at else 0)
        x = np.arange(len(own), dtype=np.float64) - (len(own) - 1) / 2
        slope = (x * own).sum() / max((x * x).sum(), 1.0)
        line = own - np.floor(own.mean() + slope * x + 0.5).astype(np.int64)
        cost = lambda r: int((bit_width(np.abs(r)) + 1).sum())
        use_line = cost(line) + 2 * w < cost(last)
        total += 1 + 2 * w * use_line
        codes.append(line if use_line else last)
    residuals = np.concatenate(codes) if codes else q
    far = np.abs(residuals) > radius
    return total + huffman_bits(np.where(far, radius + 1, residuals)) + int(far.sum()) * w


def _planes() -> np.ndarray:
    """Bits and new count of significant values for a plane of four, by the count so far and the plane's bits."""
    out = np.zeros((5, 16, 2), np.int64)
    for n in range(5):
        for x in range(16):
            bits, now, left = n, n, x >> n
            while now < 4:
                bits += 1
                if not left:
                    break
                while now < 3:
                    bits += 1
                    if left & 1:
                        break
                    left >>= 1
                    now += 1
                left >>= 1
                now += 1
            out[n, x] = bits, now
    return out


PLANES = _planes()


def zfp(values: np.ndarray, dtype: str, tolerance: float, count_bits: bool = True) -> tuple[int, np.ndarray]:
    """Bits in fixed-accuracy mode (0 if not asked for), and the values that come back: blocks of four, lifted transform, negabinary planes."""
    total_bits = 32 if dtype != "float64" else 64
    e_bits = {"float16": 5, "float32": 8, "float64": 11}[dtype]
    n = len(values)
    x = np.zeros(-(-n // 4) * 4)
    x[:n] = np.where(np.isfinite(values), values, 0)
    if n % 4:
        x[n:] = x[n - 1]
    x = x.reshape(-1, 4)
    emax = np.frexp(np.abs(x).max(axis=1))[1].astype(np.int64)
    empty = np.abs(x).max(axis=1) == 0
    least = int(np.floor(np.log2(tolerance)))
    precision = np.where(empty, 0, np.clip(emax - least + 4, 0, total_bits))
    q = np.ldexp(x, (total_bits - 2 - emax)[:, None]).astype(np.int64)
    a, b, c, d = q.T
    a = a + d; a >>= 1; d = d - a  # noqa: E702  the forward lifting steps
    c = c + b; c >>= 1; b = b - c  # noqa: E702
    a = a + c; a >>= 1; c = c - a  # noqa: E702
    d = d + b; d >>= 1; b = b - d  # noqa: E702
    d = d + (b >> 1); b = b - (d >> 1)  # noqa: E702
    coded = np.stack([a, b, c, d], axis=1).astype(np.uint64)
    mask = np.uint64(0xAAAAAAAAAAAAAAAA)
    u = (coded + mask) ^ mask
    bits, count = np.where(precision > 0, 2 + e_bits, 1), np.zeros(len(x), np.int64)
    for k in range(total_bits - 1, -1, -1) if count_bits else ():
        live = total_bits - precision <= k
        plane = sum(((u[:, i] >> np.uint64(k)) & np.uint64(1)).astype(np.int64) << i for i in range(4))
        got = PLANES[count, plane]
        bits = bits + np.where(live, got[:, 0], 0)
        count = np.where(live, got[:, 1], count)
    drop = (total_bits - precision).astype(np.uint64)
    kept = np.where((precision > 0)[:, None], (u >> np.minimum(drop, 63)[:, None]) << np.minimum(drop, 63)[:, None], 0).astype(np.uint64)
    a, b, c, d = ((kept ^ mask) - mask).astype(np.int64).T
    b = b + (d >> 1); d = d - (b >> 1)  # noqa: E702
    b = b + d; d = (d << 1) - b  # noqa: E702
    c = c + a; a = (a << 1) - c  # noqa: E702
    b = b + c; c = (c << 1) - b  # noqa: E702
    d = d + a; a = (a << 1) - d  # noqa: E702
    back = np.ldexp(np.stack([a, b, c, d], axis=1).astype(np.float64), (emax - (total_bits - 2))[:, None])
    return int(bits.sum()), np.where(empty[:, None], 0, back).ravel()[:n]


def zfp_bits(payload: bytes, dtype: str) -> int:
    values = values_in(payload, dtype).astype(np.float64)
    return zfp(values, dtype, BOUND[dtype])[0] if len(values) else 0


def half_codes(layers: DataFrame) -> DataFrame:
    """Packing of float16 layers: per layer, parameters, packable ones, code bits, largest error, exceptions."""

    def run(batches):
        for batch in batches:
            ids = batch.column(batch.schema.get_field_index("layer_id")).to_pylist()
            out = []
            for payload in batch.column(batch.schema.get_field_index("payload")).to_pylist():
                v = np.frombuffer(payload, np.float16)
                up = np.abs(v) + np.float16(1)
                inside = (np.abs(v) < 1) & (up < 2)
                back = (up - np.float16(1)).astype(np.float64)
                off = np.abs(back - np.abs(v.astype(np.float64)))[inside]
                out.append((len(v), int(inside.sum()), CODE_BITS["float16"] * int(inside.sum()), float(off.max(initial=0.0)), int((~inside).sum())))
            cols = list(zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(ids), *[pa.array(c) for c in cols]], ["layer_id", "params", "packed", "bits", "max_error", "exceptions"])

    return layers.mapInArrow(run, "layer_id string, params long, packed long, bits long, max_error double, exceptions long")


def half_error(blocks: DataFrame) -> DataFrame:
    """Per model: largest error of the cast to 16 bits, among finite results."""

    def run(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            errors = []
            for p, d in zip(cols["payload"], cols["dtype"], strict=True):
                v = values_in(p, d).astype(np.float64)
                with np.errstate(over="ignore"):
                    h = v.astype(np.float16).astype(np.float64)
                errors.append(float(np.abs(h - v)[np.isfinite(h)].max(initial=0.0)))
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(errors)], ["model_id", "e"])

    return blocks.select("model_id", "dtype", "payload").mapInArrow(run, "model_id string, e double").groupBy("model_id").agg(F.max("e").alias("max_error"))
