"""The hybrid store: layer deduplication, the better of distance encoding and unit packing for each float model, then a general compressor.

Layers of whole numbers and bytes go from deduplication straight to the compressor. Sizes come before encoding: both arms are sized by
aggregates and only the winner is encoded. Prints are shuffled for deduplication, payloads never are, and a print's first layer is an
aggregate that is joined back, so that a print of very many copies is no task's. Blocks of `zoo.BLOCK` values decode alone; what decides
an arm for the store are the sizes that blocks have.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from paramstore.functions.bits import BOUND, CODE_BITS, STORED, VIEW, WIDTH, is_float, width_of
from paramstore.operators import distance, similarity, unitpack
from paramstore.sources import runs as packed
from paramstore.sources.shared import kept
from paramstore.sources.zoo import BLOCK, to_blocks

REF_BITS = 256
#: Rows of a counted table (of layers or of layers in blocks) that is still broadcast; a larger one is joined by shuffling.
FEW = 1 << 17
#: Values of a model's stream for each bucket of different values; places of a layer that are compared together.
BUCKET, WIDE = 1 << 19, 1 << 16


def prints_of(params: DataFrame) -> DataFrame:
    """(model_id, layer_id, layer_seq, dtype, n, fp) of every layer."""
    prints = similarity.sampled(params, stride=1).select("layer_id", "n", "fp")
    return params.select("model_id", "layer_id", "layer_seq", "dtype").where("layer_pos = 0").join(prints, "layer_id")


def stage_dedup(params: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """(model_id, layer_id, layer_seq, dtype, n, fp, copy, canonical): the first layer of a print by (model_id, layer_seq) is stored (copy 1).

    known: (fp, dtype, canonical) of a store that there is; layers of its prints refer to what it holds.
    """
    return first_copies(prints_of(params), known)


def first_copies(layers: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """stage_dedup of layers with prints."""
    first = layers.groupBy("fp", "dtype").agg(F.min(F.struct("model_id", "layer_seq", "layer_id")).alias("first"))
    owner = F.col("first.layer_id")
    if known is not None:
        held = known.groupBy("fp", "dtype").agg(F.min("canonical").alias("held"))
        first = first.join(held, ["fp", "dtype"], "left")
        owner = F.coalesce("held", owner)
    named = layers.join(first.withColumn("canonical", owner).drop("first", "held"), ["fp", "dtype"])
    return named.withColumn("copy", F.when(F.col("layer_id") == F.col("canonical"), 1).otherwise(2).cast("long"))


def dedup_sizes(layers: DataFrame) -> DataFrame:
    w = width_of(F.col("dtype"))
    first = F.col("copy") == 1
    return layers.groupBy("model_id").agg(F.count("*").alias("layers"), F.count_if(first).alias("stored"), F.sum(F.col("n") * w).alias("original"), F.sum(F.when(first, F.col("n") * w).otherwise(REF_BITS)).alias("compressed"))


def route(params: DataFrame, layers: DataFrame) -> DataFrame:
    """The stored parameters, flattened anew by model and dtype: offsets are a window over layer rows."""
    of = W.partitionBy("model_id", "dtype").orderBy("layer_seq").rowsBetween(W.unboundedPreceding, -1)
    stored = layers.where("copy = 1").withColumn("offset", F.coalesce(F.sum("n").over(of), F.lit(0))).select("layer_id", "offset")
    return params.join(stored, "layer_id").withColumn("pos", F.col("offset") + F.col("layer_pos")).drop("offset")


def prints_of_runs(runs: DataFrame) -> DataFrame:
    """prints_of() from runs: 128 bits of sums over a layer's values by place, the same however it is cut into runs."""
    total = lambda h: F.pmod(F.sum(F.col(h).cast("decimal(20,0)")), F.lit(str(1 << 64)).cast("decimal(20,0)")).cast("string")
    return runs.groupBy("model_id", "layer_id", "layer_seq", "dtype").agg(F.sum("n").alias("n"), F.concat_ws(":", total("h1"), total("h2")).alias("fp"))


def routes(layers: DataFrame) -> DataFrame:
    """(layer_id, offset) of stored layers: where they begin in the stream of their model and dtype."""
    of = W.partitionBy("model_id", "dtype").orderBy("layer_seq").rowsBetween(W.unboundedPreceding, -1)
    return layers.where("copy = 1").select("layer_id", "model_id", "dtype", F.coalesce(F.sum("n").over(of), F.lit(0)).alias("offset"))


def few(table: DataFrame, rows: int) -> DataFrame:
    """table, to be broadcast if its counted rows are few."""
    return F.broadcast(table) if rows <= FEW else table


def route_runs(runs: DataFrame, layers: DataFrame, extra: DataFrame | None = None, count: int | None = None) -> DataFrame:
    """The stored runs with pos, their first place in the stream, and the columns that extra has for each model and dtype."""
    to = routes(layers)
    to = to if extra is None else to.join(extra, ["model_id", "dtype"])
    return runs.join(few(to.drop("model_id", "dtype"), layers.count() if count is None else count), "layer_id").withColumn("pos", F.col("offset") + F.col("layer_pos"))


def over_blocks(routed: DataFrame, of_block, schema: str, extra: tuple = ()) -> DataFrame:
    """of_block(row, block_no, first_pos, bits) -> values of schema, for every block of routed runs; row has model_id, dtype and extra.

    A block that lies within one run is worked on where the run is. Only the pieces at the ends of runs are shuffled.
    """
    keys = ["model_id", "dtype", *extra]
    names = [f.split()[0] for f in schema.split(", ")]
    types = [pa.type_for_alias({"string": "string", "long": "int64", "binary": "binary"}[f.split()[1]]) for f in schema.split(", ")]
    out = lambda rows: pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names)

    def cut(batch, whole: bool):
        """(row, block_no, first_pos, bits) of the whole blocks within runs, or of the pieces at their ends."""
        rows = batch.to_pylist()
        for row in rows:
            low, high = row["pos"], row["pos"] + row["n"]
            edges = sorted({low, *range(-(-low // BLOCK) * BLOCK, high, BLOCK), high})
            mine = [(a, b) for a, b in zip(edges, edges[1:]) if (b - a == BLOCK) == whole]
            if mine:
                bits = packed.expand(row["data"], row["n"], row["dtype"])
                for a, b in mine:
                    yield row, a // BLOCK, a, bits[a - low : b - low]

    def inside(batches):
        for batch in batches:
            rows = [of_block(*x) for x in cut(batch, True)]
            if rows:
                yield out(rows)

    def ends(batches):
        for batch in batches:
            rows = [(*(row[k] for k in keys), no, first, len(bits), packed.squeeze(bits, row["dtype"])) for row, no, first, bits in cut(batch, False)]
            yield pa.RecordBatch.from_arrays([*[pa.array([r[i] for r in rows], pa.string()) for i in range(len(keys))], *[pa.array([r[len(keys) + i] for r in rows], pa.int64()) for i in range(3)], pa.array([r[-1] for r in rows], pa.binary())], [*keys, "block_no", "first_pos", "n", "data"])

    def joined(batches):
        for batch in batches:
            rows = []
            for row in batch.to_pylist():
                own = sorted(row["own"], key=lambda x: x["first_pos"])
                rows.append(of_block(row, row["block_no"], own[0]["first_pos"], np.concatenate([packed.expand(x["data"], x["n"], row["dtype"]) for x in own])))
            yield out(rows)

    routed = routed.select(*keys, "pos", "n", "data")
    pieces = routed.mapInArrow(ends, ", ".join(f"{k} string" for k in keys) + ", block_no long, first_pos long, n long, data binary")
    grouped = pieces.groupBy(*keys, "block_no").agg(F.collect_list(F.struct("first_pos", "n", "data")).alias("own"))
    return routed.mapInArrow(inside, schema).unionByName(grouped.mapInArrow(joined, schema))


def stream_distances(routed: DataFrame) -> DataFrame:
    """(model_id, dtype, de): bits of float models by distances over their whole streams, as distance.sizes has them, from routed runs with buckets.

    Repeats within a run are counted where it is. What goes on from there is each different value of a run with its first and last place,
    packed by buckets of values; a bucket joins a value's runs.
    """
    long = lambda d, w: np.where((k := np.frexp(d.astype(np.float64))[1]) <= distance.LONGEST, k + distance.LENGTH_BITS + 1, w + 1).sum()

    def of_runs(batches):
        for batch in batches:
            rows = []
            for row in batch.to_pylist():
                dtype, n = row["dtype"], row["n"]
                bits = packed.expand(row["data"], n, dtype)
                order = np.argsort(bits, kind="stable")
                new = np.flatnonzero(np.concatenate(([True], bits[order][1:] != bits[order][:-1])))
                last = order[np.append(new[1:], n) - 1]
                first, values = order[new], bits[order[new]]
                steps = np.delete(np.diff(order, prepend=0), new)
                own = int(long(steps, WIDTH[dtype]))
                number = (packed.mixed(values.view(np.uint64)) >> np.uint64(1)).astype(np.int64) % row["buckets"]
                by = np.argsort(number, kind="stable")
                for part in np.split(by, np.flatnonzero(np.diff(number[by])) + 1):
                    data = [packed.squeeze(values[part], dtype, rising=True), packed.squeeze(first[part]), packed.squeeze(last[part] - first[part])]
                    rows.append((row["model_id"], dtype, int(number[part[0]]), row["pos"], len(part), data, own))
                    own = 0
            kinds = [pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.binary()), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], ["model_id", "dtype", "bucket", "pos", "n", "data", "de"])

    def of_buckets(batches):
        for batch in batches:
            de = []
            for row in batch.to_pylist():
                own, dtype = row["own"], row["dtype"]
                values = np.concatenate([packed.expand(x["data"][0], x["n"], dtype, rising=True) for x in own])
                inside = np.concatenate([packed.expand(x["data"][1], x["n"]) for x in own])
                first = inside + np.repeat([x["pos"] for x in own], [x["n"] for x in own])
                last = first + np.concatenate([packed.expand(x["data"][2], x["n"]) for x in own])
                order = np.lexsort((first, values))
                same = values[order][1:] == values[order][:-1]
                back = (first[order][1:] - last[order][:-1])[same]
                de.append(row["de"] + int(long(back, WIDTH[dtype])) + (WIDTH[dtype] + 1) * (len(values) - len(back)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(de, pa.int64())], ["model_id", "dtype", "de"])

    floats = routed.where(is_float(F.col("dtype"))).select("model_id", "dtype", "pos", "n", "data", "buckets")
    chunks = floats.mapInArrow(of_runs, "model_id string, dtype string, bucket long, pos long, n long, data array<binary>, de long")
    grouped = chunks.groupBy("model_id", "dtype", "bucket").agg(F.sum("de").alias("de"), F.collect_list(F.struct("pos", "n", "data")).alias("own"))
    sums = grouped.select("model_id", "dtype", "de", "own").mapInArrow(of_buckets, "model_id string, dtype string, de long")
    return sums.groupBy("model_id", "dtype").agg(F.sum("de").alias("de"))


def unit_bits(runs: DataFrame) -> DataFrame:
    """(model_id, dtype, original, unit): bits by packing, of runs."""
    w, code = width_of(F.col("dtype")), F.lit(None).cast("long")
    for dtype, c in CODE_BITS.items():
        code = F.when(F.col("dtype") == dtype, F.lit(c).cast("long")).otherwise(code)
    sums = runs.groupBy("model_id", "dtype").agg(F.sum("n").alias("n"), F.sum("out_of_unit").alias("out"))
    return sums.select("model_id", "dtype", (F.col("n") * w).alias("original"), ((F.col("n") - F.col("out")) * code + F.col("out") * (w + 32)).alias("unit"))


def choose(params: DataFrame, allow_raw: bool = False, segment: int | None = None) -> DataFrame:
    """Per model and dtype: original bits, both arms' bits, the better one and its name; whole numbers have the arm 'raw' and no other.

    segment: distances stay within segments of so many positions, as blocks store them.
    """
    floats = params.where(is_float(F.col("dtype")))
    de = distance.sizes(floats, segment=segment).select("model_id", "dtype", "original", F.col("compressed").alias("de"))
    unit = unitpack.sizes(floats).select("model_id", "dtype", F.col("compressed").alias("unit"))
    arm, best = F.when(F.col("de") < F.col("unit"), "de").otherwise("unit"), F.least("de", "unit")
    if allow_raw:
        arm, best = F.when(F.col("original") <= best, "raw").otherwise(arm), F.least(F.col("original"), best)
    both = de.join(unit, ["model_id", "dtype"]).withColumns({"arm": arm, "compressed": best})
    w, none = width_of(F.col("dtype")), F.lit(None).cast("long")
    other = params.where(~is_float(F.col("dtype"))).groupBy("model_id", "dtype").agg(F.sum(w).alias("original"))
    return both.unionByName(other.select("model_id", "dtype", "original", none.alias("de"), none.alias("unit"), F.lit("raw").alias("arm"), F.col("original").alias("compressed")))


def encoded_block(bits: np.ndarray, dtype: str, arm: str) -> bytes:
    return distance.encode(bits, dtype) if arm == "de" else unitpack.pack(bits, dtype) if arm == "unit" else bits.astype(STORED[dtype]).tobytes()


def encode(params: DataFrame, choice: DataFrame | None = None) -> DataFrame:
    """Blocks with data, each encoded by its model's arm; a block decodes alone."""
    choice = choose(params, segment=BLOCK) if choice is None else choice
    blocks = to_blocks(params).join(choice.select("model_id", "dtype", "arm"), ["model_id", "dtype"])

    def kernel(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            data = []
            for payload, dtype, arm in zip(cols["payload"], cols["dtype"], cols["arm"], strict=True):
                data.append(encoded_block(np.frombuffer(payload, STORED[dtype]).astype(np.int64), dtype, arm))
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(cols["dtype"]), pa.array(cols["block_no"], pa.int64()), pa.array(cols["first_pos"], pa.int64()), pa.array(cols["n"], pa.int64()), pa.array(cols["arm"]), pa.array(data, pa.binary())], ["model_id", "dtype", "block_no", "first_pos", "n", "arm", "data"])

    return blocks.mapInArrow(kernel, "model_id string, dtype string, block_no long, first_pos long, n long, arm string, data binary")


def compress(encoded: DataFrame, level: int = 3, column: str = "data") -> DataFrame:
    """Stage 3: the column data through zstd, row by row, with the bytes before as raw_bytes."""

    def kernel(batches):
        codec = pa.Codec("zstd", compression_level=level)
        for batch in batches:
            at = batch.schema.get_field_index(column)
            raw = [x or b"" for x in batch.column(at).to_pylist()]
            out = batch.set_column(at, column, pa.array([codec.compress(x, asbytes=True) for x in raw], pa.binary()))
            yield pa.RecordBatch.from_arrays([*out.columns, pa.array(list(map(len, raw)), pa.int64())], [*out.schema.names, "raw_bytes"])

    return encoded.mapInArrow(kernel, T.StructType([*encoded.schema.fields, T.StructField("raw_bytes", T.LongType())]))


def stage_entropy(encoded: DataFrame, level: int = 3) -> DataFrame:
    """Per model: bits before and after stage 3."""
    return compress(encoded, level).groupBy("model_id", "dtype", "arm").agg(F.sum("n").alias("params"), (8 * F.sum("raw_bytes")).alias("before"), (8 * F.sum(F.length("data"))).alias("compressed"))


ARM_SUMS = ["de", "unit", *[f"{arm}_{what}" for arm in ("de", "unit", "raw") for what in ("before", "after")]]


def block_de_bits(bits: np.ndarray, dtype: str) -> int:
    """Bits of a block by distances within it."""
    back = np.arange(len(bits)) - distance.previous_positions(bits)
    length = np.frexp(back[back <= np.arange(len(bits))].astype(np.float64))[1]
    return int(length.sum()) + (distance.LENGTH_BITS + 1) * len(length) + (WIDTH[dtype] + 1) * (len(bits) - len(length))


def block_sums(bits: np.ndarray, dtype: str, level: int) -> list:
    """ARM_SUMS of a block: both arms' sizes, and bytes of each encoding before and after zstd."""
    row, codec = dict.fromkeys(ARM_SUMS), pa.Codec("zstd", compression_level=level)
    if dtype in VIEW:
        arms = ("de", "unit")
        row["de"] = block_de_bits(bits, dtype)
        out = int(packed.out_of_unit(bits, dtype).sum())
        row["unit"] = CODE_BITS[dtype] * (len(bits) - out) + (WIDTH[dtype] + 32) * out
    else:
        arms = ("raw",)
    for arm in arms:
        x = encoded_block(bits, dtype, arm)
        row[f"{arm}_before"], row[f"{arm}_after"] = len(x), len(codec.compress(x, asbytes=True))
    return [row[n] for n in ARM_SUMS]


def entropy_sizes(params: DataFrame, level: int = 3) -> DataFrame:
    """stage_entropy(encode(params)) from one pass over the blocks: distances of the store stay within a block, so a block has all that both arms' sizes need.

    Each block is encoded by both arms where it is, only sums leave it, and a model's totals choose the arm whose sums count.
    """

    def kernel(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            out = [block_sums(np.frombuffer(payload, STORED[dtype]).astype(np.int64), dtype, level) for payload, dtype in zip(cols["payload"], cols["dtype"], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(cols["dtype"]), pa.array(cols["n"], pa.int64()), *[pa.array([r[i] for r in out], pa.int64()) for i in range(len(ARM_SUMS))]], ["model_id", "dtype", "n", *ARM_SUMS])

    blocks = to_blocks(params).select("model_id", "dtype", "n", "payload")
    return chosen_sums(blocks.mapInArrow(kernel, SUMS_SCHEMA))


SUMS_SCHEMA = "model_id string, dtype string, n long, " + ", ".join(f"{n} long" for n in ARM_SUMS)


def chosen_sums(sums: DataFrame) -> DataFrame:
    """Per model what its chosen arm has, of blocks' sums."""
    sums = sums.groupBy("model_id", "dtype").agg(*[F.sum(n).alias(n) for n in ("n", *ARM_SUMS)])
    arm = F.when(F.col("de").isNull(), "raw").when(F.col("de") < F.col("unit"), "de").otherwise("unit")
    chosen = lambda what: 8 * F.when(arm == "de", F.col(f"de_{what}")).when(arm == "unit", F.col(f"unit_{what}")).otherwise(F.col(f"raw_{what}"))
    return sums.select("model_id", "dtype", arm.alias("arm"), F.col("n").alias("params"), chosen("before").alias("before"), chosen("after").alias("compressed"))


def entropy_sizes_of_runs(routed: DataFrame, level: int = 3) -> DataFrame:
    """entropy_sizes() from routed runs."""
    return chosen_sums(over_blocks(routed, lambda row, no, first, bits: (row["model_id"], row["dtype"], len(bits), *block_sums(bits, row["dtype"], level)), SUMS_SCHEMA))


def structure(layers: DataFrame, rows: int = 4096, level: int = 3) -> DataFrame:
    """(model_id, part, layers, data, raw_bytes): the models' structure, a line of JSON for each layer with what it refers to, through stage 3."""
    line = F.to_json(F.struct("layer_id", "layer_seq", "dtype", "n", "canonical"))
    parts = layers.select("model_id", F.floor(F.col("layer_seq") / rows).alias("part"), F.struct("layer_seq", line.alias("line")).alias("x"))
    text = F.array_join(F.transform(F.sort_array(F.collect_list("x")), lambda x: x["line"]), "\n")
    return compress(parts.groupBy("model_id", "part").agg(F.count("*").alias("layers"), F.encode(text, "UTF-8").alias("data")), level)


def read_structure(stored: DataFrame) -> DataFrame:
    """(model_id, layer_id, layer_seq, dtype, n, canonical, copy) of structure()'s rows."""

    def kernel(batches):
        codec = pa.Codec("zstd")
        for batch in batches:
            rows = []
            for model, data, size in zip(*(batch.column(n).to_pylist() for n in ("model_id", "data", "raw_bytes")), strict=True):
                for line in codec.decompress(data, size, asbytes=True).decode().split("\n"):
                    x = json.loads(line)
                    rows.append({"model_id": model, "copy": 1 if x["canonical"] == x["layer_id"] else 2, **x})
            fields = [("model_id", pa.string()), ("layer_id", pa.string()), ("layer_seq", pa.int64()), ("dtype", pa.string()), ("n", pa.int64()), ("canonical", pa.string()), ("copy", pa.int64())]
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema(fields))

    return stored.mapInArrow(kernel, "model_id string, layer_id string, layer_seq long, dtype string, n long, canonical string, copy long")


def restored_pieces(stored: DataFrame, layers: DataFrame) -> DataFrame:
    """(canonical, dtype, layer_pos, n, data): packed runs of the stored layers' values, a row for each layer of each block, from layer_pos on.

    A block meets only the layers that lie in it: the layers' ranges are dealt to blocks by their numbers.
    """
    of = W.partitionBy("model_id", "dtype").orderBy("layer_seq")
    owned = layers.where("copy = 1 and n > 0").withColumn("end", F.sum("n").over(of)).withColumn("first", F.col("end") - F.col("n"))
    numbers = F.sequence(F.floor(F.col("first") / BLOCK), F.floor((F.col("end") - 1) / BLOCK))
    inside = owned.select("model_id", "dtype", F.explode(numbers).alias("block_no"), F.struct("first", "end", F.col("layer_id").alias("id")).alias("own"))
    inside = inside.groupBy("model_id", "dtype", "block_no").agg(F.collect_list("own").alias("own"))  # no more than a block has values

    def kernel(batches):
        codec = pa.Codec("zstd")
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            ids, kinds, places, sizes, parts = [], [], [], [], []
            for k in range(batch.num_rows):
                data, dtype, arm, base = codec.decompress(cols["data"][k], cols["raw_bytes"][k], asbytes=True), cols["dtype"][k], cols["arm"][k], cols["first_pos"][k]
                bits = distance.decode(data, dtype) if arm == "de" else unitpack.unpack(data, dtype) if arm == "unit" else np.frombuffer(data, STORED[dtype]).astype(np.int64)
                for own in cols["own"][k]:
                    low, high = max(own["first"], base), min(own["end"], base + len(bits))
                    ids.append(own["id"])
                    kinds.append(dtype)
                    places.append(low - own["first"])
                    sizes.append(high - low)
                    parts.append(packed.squeeze(bits[low - base : high - base], dtype))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.string()), pa.array(kinds, pa.string()), pa.array(places, pa.int64()), pa.array(sizes, pa.int64()), pa.array(parts, pa.binary())], ["canonical", "dtype", "layer_pos", "n", "data"])

    size = owned.agg(F.sum(F.floor(F.col("n") / BLOCK) + 2)).first()[0] or 0
    both = stored.join(few(inside, size), ["model_id", "dtype", "block_no"])
    return both.mapInArrow(kernel, "canonical string, dtype string, layer_pos long, n long, data binary")


def restore(stored: DataFrame, layers: DataFrame) -> DataFrame:
    """(layer_id, dtype, layer_pos, n, data): packed runs of every layer: float, whole, or a reference that takes what it points to."""
    own = few(layers.select("layer_id", "canonical"), layers.count())
    return restored_pieces(stored, layers).join(own, "canonical").select("layer_id", "dtype", "layer_pos", "n", "data")


def store_bytes(layers: DataFrame, level: int = 3) -> tuple[DataFrame, DataFrame]:
    """Byte layers (layer_id, payload): the compressed payloads of the first layer of each print (canonical, data, raw_bytes), and (layer_id, canonical) of all."""
    prints = layers.select("layer_id", F.sha2("payload", 256).alias("fp"))
    refs = prints.join(prints.groupBy("fp").agg(F.min("layer_id").alias("canonical")), "fp").select("layer_id", "canonical")
    packed = compress(layers.select(F.col("layer_id").alias("canonical"), F.col("payload").alias("data")), level)  # where it is read
    return packed.join(refs.where("layer_id = canonical").select("canonical"), "canonical", "left_semi"), refs


def restore_bytes(stored: DataFrame, refs: DataFrame) -> DataFrame:
    """(layer_id, payload) of every byte layer."""

    def kernel(batches):
        codec = pa.Codec("zstd")
        for batch in batches:
            out = [codec.decompress(x, n, asbytes=True) if n else b"" for x, n in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["layer_id", "payload"])

    return refs.join(stored, "canonical").select("layer_id", "data", "raw_bytes").mapInArrow(kernel, "layer_id string, payload binary")


def store(runs: DataFrame, layers: DataFrame, level: int = 3) -> DataFrame:
    """(model_id, dtype, block_no, first_pos, n, arm, data, raw_bytes): the stored layers' blocks by their models' arms, through stage 3."""
    count = layers.count()
    sized = lambda row, no, first, bits: (row["model_id"], row["dtype"], block_de_bits(bits, row["dtype"]) if row["dtype"] in VIEW else None)
    de = over_blocks(route_runs(runs, layers, count=count), sized, "model_id string, dtype string, de long").groupBy("model_id", "dtype").agg(F.sum("de").alias("de"))
    stored = runs.join(few(layers.where("copy = 1").select("layer_id"), count), "layer_id", "left_semi")
    arm = F.when(~is_float(F.col("dtype")), "raw").when(F.col("de") < F.col("unit"), "de").otherwise("unit")
    choice = kept(de.join(unit_bits(stored), ["model_id", "dtype"]).select("model_id", "dtype", arm.alias("arm")))

    def encoded(row, no, first, bits):
        data = encoded_block(bits, row["dtype"], row["arm"])
        return row["model_id"], row["dtype"], no, first, len(bits), row["arm"], pa.Codec("zstd", compression_level=level).compress(data, asbytes=True), len(data)

    return over_blocks(route_runs(runs, layers, choice, count), encoded, "model_id string, dtype string, block_no long, first_pos long, n long, arm string, data binary, raw_bytes long", ("arm",))


def compared(values: DataFrame, back: DataFrame) -> DataFrame:
    """Per dtype how packed runs of layers (layer_id, dtype, layer_pos, n, data) came back: see verify. Values are met by their places."""

    def cut(batches):
        """Runs cut at every WIDE places of a layer."""
        for batch in batches:
            rows = []
            for row in batch.to_pylist():
                low, high = row["layer_pos"], row["layer_pos"] + row["n"]
                if low // WIDE == (high - 1) // WIDE:
                    rows.append({**row, "part": low // WIDE})
                    continue
                bits = packed.expand(row["data"], row["n"], row["dtype"])
                edges = [low, *range((low // WIDE + 1) * WIDE, high, WIDE), high]
                rows += [{**row, "part": a // WIDE, "layer_pos": a, "n": b - a, "data": packed.squeeze(bits[a - low : b - low], row["dtype"])} for a, b in zip(edges, edges[1:])]
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("layer_id", pa.string()), ("dtype", pa.string()), ("part", pa.int64()), ("layer_pos", pa.int64()), ("n", pa.int64()), ("data", pa.binary()), ("back", pa.bool_())]))

    def kernel(batches):
        for batch in batches:
            rows = []
            for dtype, part, own in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                size = max(x["layer_pos"] + x["n"] for x in own) - part * WIDE
                bits, times = np.zeros((2, size), np.int64), np.zeros((2, size), np.int64)
                for x in own:
                    at = slice(x["layer_pos"] - part * WIDE, x["layer_pos"] - part * WIDE + x["n"])
                    bits[int(x["back"])][at] = packed.expand(x["data"], x["n"], dtype)
                    times[int(x["back"])][at] += 1
                there, stray = (times > 0).all(axis=0), times[1] > times[0]  # stray: given back twice, or never put in
                off, inside = None, np.zeros(size, bool)
                if dtype in VIEW:
                    kind, whole = VIEW[dtype]
                    was, now = (b.astype(whole).view(kind).astype(np.float64) for b in bits)
                    inside = there & (np.abs(was) < 1)
                    off = float(np.abs(now[inside] - was[inside]).max()) if inside.any() else None
                rows.append((dtype, int(times[0].sum()), int((times[0] > times[1]).sum()), off, int((there & ~inside & (bits[0] != bits[1]) | stray).sum())))
            kinds = [pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], ["dtype", "params", "missing", "off", "differ"])

    names = ["layer_id", "dtype", "layer_pos", "n", "data"]
    both = values.select(*names, F.lit(False).alias("back")).unionByName(back.select(*names, F.lit(True).alias("back")))
    parts = both.mapInArrow(cut, "layer_id string, dtype string, part long, layer_pos long, n long, data binary, back boolean")
    grouped = parts.groupBy("layer_id", "dtype", "part").agg(F.collect_list(F.struct("layer_pos", "n", "data", "back")).alias("own"))
    got = grouped.select("dtype", "part", "own").mapInArrow(kernel, "dtype string, params long, missing long, off double, differ long")
    return got.groupBy("dtype").agg(F.sum("params").alias("params"), F.sum("missing").alias("missing"), F.max("off").alias("max_error"), F.sum("differ").alias("others_differ"))


def verify_runs(runs: DataFrame) -> DataFrame:
    """verify() of runs."""
    layers = kept(first_copies(prints_of_runs(runs)))
    back = restore(store(runs, layers), kept(read_structure(structure(layers))))
    return compared(runs, back)


def verify(params: DataFrame) -> DataFrame:
    """Per dtype: parameters, how many did not come back, largest error of floats within the unit interval, and how many others differ.

    The layers are read back from their stored structure.
    """
    return verify_runs(kept(packed.of_params(params)))


def verify_bytes(layers: DataFrame) -> DataFrame:
    """The same of byte layers, in bytes."""
    back = restore_bytes(*store_bytes(layers)).withColumnRenamed("payload", "back")
    both = layers.select("layer_id", "dtype", F.length("payload").cast("long").alias("n"), F.sha2("payload", 256).alias("fp")).join(back.select("layer_id", F.sha2("back", 256).alias("back")), "layer_id", "left")
    gone, size = F.col("back").isNull(), F.col("n")
    return both.groupBy("dtype").agg(F.sum(size).alias("params"), F.sum(F.when(gone, size).otherwise(0)).alias("missing"), F.lit(None).cast("double").alias("max_error"), F.sum(F.when(~gone & (F.col("fp") != F.col("back")), size).otherwise(0)).alias("others_differ"))


def within_bound(verified: DataFrame) -> DataFrame:
    """verified with a verdict in the place of the largest error."""
    bound = F.lit(None).cast("double")
    for dtype, b in BOUND.items():
        bound = F.when(F.col("dtype") == dtype, b).otherwise(bound)
    return verified.withColumn("within_bound", F.coalesce(F.col("max_error") <= bound, F.lit(True))).drop("max_error")


def ablation(runs: DataFrame, with_entropy: bool = False) -> DataFrame:
    """(model_id, original, stage, compressed) of runs: dedup alone, with each arm, with the better one, and with stage 3 on top.

    Arms are sized over a model's whole stream; the last stage is what the blocks of the store have.
    """
    layers = kept(first_copies(prints_of_runs(runs)))
    buckets = layers.groupBy("model_id", "dtype").agg(F.ceil(F.sum("n") / BUCKET).alias("buckets"))
    routed = route_runs(runs, layers, buckets)
    arms = unit_bits(routed).join(stream_distances(routed), ["model_id", "dtype"], "left")
    arms = arms.withColumn("best", F.when(is_float(F.col("dtype")), F.least("de", "unit")).otherwise(F.col("original")))
    refs = F.sum(F.when(F.col("copy") > 1, REF_BITS).otherwise(0)).alias("refs")
    w = width_of(F.col("dtype"))
    base = layers.groupBy("model_id").agg(F.sum(F.col("n") * w).alias("original"), F.sum(F.when(F.col("copy") == 1, F.col("n") * w).otherwise(REF_BITS)).alias("dedup"), refs)
    m = base.join(arms.groupBy("model_id").agg(F.sum(F.coalesce("de", "original")).alias("de"), F.sum(F.coalesce("unit", "original")).alias("unit"), F.sum("best").alias("best")), "model_id", "left").fillna(0, ["de", "unit", "best"])
    stages = [("1_dedup", F.col("dedup")), ("2_dedup_de", F.col("refs") + F.col("de")), ("3_dedup_unit", F.col("refs") + F.col("unit")), ("4_dedup_both", F.col("refs") + F.col("best"))]
    if with_entropy:
        last = entropy_sizes_of_runs(routed).groupBy("model_id").agg(F.sum("compressed").alias("zstd"))
        m = m.join(last, "model_id", "left").fillna(0, ["zstd"])
        stages.append(("5_all_zstd", F.col("refs") + F.col("zstd")))
    long = F.explode(F.array(*[F.struct(F.lit(s).alias("stage"), c.cast("long").alias("compressed")) for s, c in stages])).alias("x")
    return m.select("model_id", "original", long).select("model_id", "original", "x.stage", "x.compressed")


def shares(ablation_: DataFrame) -> DataFrame:
    """Overall ratio after each stage of the ladder, and what it adds to the one before."""
    each = ablation_.groupBy("stage").agg((F.sum("original") / F.sum("compressed")).alias("cr"))
    before = F.coalesce(F.lag("cr").over(W.partitionBy(F.lit(1)).orderBy("stage")), F.lit(1.0))  # a row for each stage
    return each.select("stage", F.round("cr", 9).alias("cr"), F.round(F.col("cr") - before, 9).alias("step"))
