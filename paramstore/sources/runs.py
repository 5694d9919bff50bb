"""Runs: up to some ten thousand values of a layer in one row, packed, for what must not move a row a value.

A run is (model_id, layer_id, layer_seq, dtype, layer_pos, n, out_of_unit, h1, h2, data): layer_pos is the place of its first value, h1 and
h2 are sums over its values, by place, of which a layer's print is made, and data is squeeze()'s.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import STORED, VIEW, bits_of
from paramstore.sources import zoo

#: Keys of a table that are sorted together, and rows that are packed together before that.
SPAN, HELD = 1 << 16, 1 << 18
SCHEMA = "model_id string, layer_id string, layer_seq long, dtype string, layer_pos long, n long, out_of_unit long, h1 long, h2 long, data binary"
NAMES = ["model_id", "layer_id", "layer_seq", "dtype", "layer_pos", "n", "out_of_unit", "h1", "h2", "data"]
#: Floats that are whole multiples of 1 / scale, bit by bit, go as these multiples.
SCALES = (1.0, 100.0)
ZSTD = pa.Codec("zstd", compression_level=1)


def squeeze(bits: np.ndarray, dtype: str = "int64", rising: bool = False) -> bytes:
    """Values without loss: bytes of the same weight side by side, through zstd. rising: differences instead, for sorted ones."""
    own, how = bits.astype(STORED[dtype]), 0
    if dtype == "float64" and len(own):
        values = own.view(np.float64)
        for k, scale in enumerate(SCALES, 1):
            with np.errstate(invalid="ignore", over="ignore"):
                whole = np.rint(values * scale)
            if (np.abs(whole) < 2.0**53).all() and ((whole.astype(np.int64) / scale).view(np.int64) == own).all():
                own, how = whole.astype(np.int64), k
                break
    if rising:
        own = np.diff(own, prepend=own[:1] * 0)
    planes = np.ascontiguousarray(own.view(np.uint8).reshape(-1, own.itemsize).T)
    return bytes([how]) + ZSTD.compress(planes, asbytes=True)


def expand(data: bytes, n: int, dtype: str = "int64", rising: bool = False) -> np.ndarray:
    """The n values' bits of squeeze()'s data."""
    kind = np.dtype(STORED[dtype])
    planes = np.frombuffer(ZSTD.decompress(data[1:], n * kind.itemsize, asbytes=True), np.uint8) if n else np.zeros(0, np.uint8)
    own = np.ascontiguousarray(planes.reshape(kind.itemsize, n).T).view(kind).ravel()
    if rising:
        own = np.cumsum(own, dtype=kind)
    if data[0]:
        own = (own / SCALES[data[0] - 1]).view(np.int64)
    out = own.astype(np.int64)
    return out & 0xFFFF if dtype == "float16" else out


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


def out_of_unit(bits: np.ndarray, dtype: str) -> np.ndarray:
    """Which values unit packing takes as exceptions; none of whole numbers."""
    if dtype not in VIEW:
        return np.zeros(len(bits), bool)
    kind, whole = VIEW[dtype]
    with np.errstate(invalid="ignore", over="ignore"):
        size = np.abs(bits.astype(whole).view(kind))
        return ~((size < 1) & (size + kind(1) < 2))


def rows_of(models: list, layers: list, seqs: list, dtype: str, places: list, bits: np.ndarray, sizes: list) -> pa.RecordBatch:
    """Runs of sizes values each (none is empty), end to end in bits."""
    sizes, places = np.array(sizes, np.int64), np.array(places, np.int64)
    starts = np.cumsum(sizes) - sizes
    at = mixed((np.arange(len(bits)) + np.repeat(places - starts, sizes)).astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15))
    raw = bits.astype(np.int64).view(np.uint64)
    first = mixed(raw + at)
    second = mixed((raw ^ np.uint64(0xD6E8FEB86659FD93)) * np.uint64(0x9FB21C651E98DF25) + mixed(at ^ np.uint64(0xA0761D6478BD642F)))
    total = lambda x, kind: np.add.reduceat(x, starts, dtype=kind).view(np.int64) if len(starts) else np.zeros(0, np.int64)
    data = [squeeze(bits[a : a + n], dtype) for a, n in zip(starts.tolist(), sizes.tolist(), strict=True)]
    columns = [pa.array(models, pa.string()), pa.array(layers, pa.string()), pa.array(seqs, pa.int64()), pa.array([dtype] * len(data), pa.string()), pa.array(places), pa.array(sizes), pa.array(total(out_of_unit(bits, dtype), np.int64)), pa.array(total(first, np.uint64)), pa.array(total(second, np.uint64)), pa.array(data, pa.binary())]
    return pa.RecordBatch.from_arrays(columns, NAMES)


def of_params(params: DataFrame) -> DataFrame:
    """Runs of params rows with bits."""
    key = ["model_id", "layer_id", "layer_seq", "dtype"]
    own = F.sort_array(F.collect_list(F.struct("layer_pos", "bits")))
    parts = params.groupBy(*key, F.floor(F.col("layer_pos") / zoo.BLOCK)).agg(own.alias("own"))
    parts = parts.select(*key, F.col("own")[0]["layer_pos"].alias("layer_pos"), F.transform("own", lambda x: x["bits"]).alias("bits"))

    def kernel(batches):
        for batch in batches:
            models, layers, seqs, dtypes, places, bits = (batch.column(i) for i in range(6))
            for k in range(batch.num_rows):
                own = bits[k].values.to_numpy()
                yield rows_of([models[k].as_py()], [layers[k].as_py()], [seqs[k].as_py()], dtypes[k].as_py(), [places[k].as_py()], own, [len(own)])

    return parts.mapInArrow(kernel, SCHEMA)


def _tables(spark: SparkSession, sf_dir: str, names: list[str]) -> list[DataFrame]:
    """Runs of tables whose columns are layers; a table is read, and its rows sorted, once for all of its families."""
    out, tables = [], {}
    for name in names:
        tables.setdefault(zoo.FLAT[name].table, []).append(zoo.FLAT[name])
    for table, flats in tables.items():
        flats = sorted(flats, key=lambda f: -len(f.ties))
        key, ties = flats[0].key, flats[0].ties
        assert all(f.key == key and f.ties == ties[: len(f.ties)] for f in flats)
        columns = list(dict.fromkeys([*ties, *(c for f in flats for c in f.columns)]))
        models = [f"__model{i}" for i in range(len(flats))]
        rows = zoo.table(spark, sf_dir, table).withColumns({m: f.model() for m, f in zip(models, flats, strict=True)})
        rows = rows.where(F.col(key).isNotNull()).withColumn("part", F.floor(F.col(key) / SPAN))
        packed = rows.select("part", F.col(key).cast("long").alias("key"), *models, *[F.col(c).cast("double").alias(c) for c in columns])
        counts = None
        for i, m in enumerate(models):
            each = rows.where(F.col(m).isNotNull()).groupBy(F.lit(i).alias("slot"), F.col(m).alias("model_id"), "part").agg(F.count("*").alias("size"))
            counts = each if counts is None else counts.unionByName(each)
        before = F.coalesce(F.sum("size").over(W.partitionBy("slot", "model_id").orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
        offsets = counts.withColumn("before", before).groupBy("part").agg(F.collect_list(F.struct("slot", "model_id", "before")).alias("offsets"))
        grouped = packed.mapInArrow(_packer(len(models), len(columns)), "part long, models array<array<string>>, n long, data array<binary>").groupBy("part").agg(F.collect_list(F.struct("models", "n", "data")).alias("own"))
        targets = [(f.dtype, [(c, columns.index(c)) for c in f.columns]) for f in flats]
        out.append(grouped.join(offsets, "part").select("own", "offsets").mapInArrow(_sorter(targets, len(ties)), SCHEMA))
    return out


def _packer(slots: int, columns: int):
    """Rows (part, key, models, columns) by part: keys and models' numbers as whole numbers, columns as doubles."""

    def flush(held):
        table = pa.Table.from_batches(held).combine_chunks()
        part, key = table.column(0).to_numpy(), table.column(1).to_numpy()
        coded = [table.column(2 + i).combine_chunks().dictionary_encode() for i in range(slots)]
        names = [c.dictionary.to_pylist() for c in coded]
        codes = [c.indices.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64) for c in coded]
        values = [table.column(2 + slots + i).to_numpy().astype(np.float64, copy=False) for i in range(columns)]
        order = np.lexsort((key, part))
        edges = np.flatnonzero(np.diff(part[order])) + 1
        parts, sizes, data = [], [], []
        for own in np.split(order, edges):
            parts.append(int(part[own[0]]))
            sizes.append(len(own))
            data.append([squeeze(key[own], rising=True), *[squeeze(c[own]) for c in codes], *[squeeze(bits_of(v[own], "float64"), "float64") for v in values]])
        return pa.RecordBatch.from_arrays([pa.array(parts, pa.int64()), pa.array([names] * len(parts), pa.list_(pa.list_(pa.string()))), pa.array(sizes, pa.int64()), pa.array(data, pa.list_(pa.binary()))], ["part", "models", "n", "data"])

    def kernel(batches):
        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= HELD:
                yield flush(held)
                held, n = [], 0
        if n:
            yield flush(held)

    return kernel


def _sorter(targets: list, ties: int):
    """A part's packed rows in order, as runs of each model's layers from the model's place on."""
    slots = len(targets)

    def of_part(own, offsets):
        before = {(x["slot"], x["model_id"]): x["before"] for x in offsets}
        names = [[x["model_id"] for x in offsets if x["slot"] == i] for i in range(slots)]
        keys, codes, values = [], [[] for _ in range(slots)], None
        for x in own:
            keys.append(expand(x["data"][0], x["n"], rising=True))
            for i in range(slots):
                number = {m: k for k, m in enumerate(names[i])}
                codes[i].append(np.array([*(number.get(m, -1) for m in x["models"][i]), -1], np.int64)[expand(x["data"][1 + i], x["n"])])
            each = [expand(d, x["n"], "float64") for d in x["data"][1 + slots :]]
            values = [[v] for v in each] if values is None else [[*a, v] for a, v in zip(values, each, strict=True)]
        values = [np.concatenate(v) for v in values]
        order = np.lexsort((*[v.view(np.float64) for v in reversed(values[:ties])], np.concatenate(keys)))
        for i, (dtype, layers) in enumerate(targets):
            code = np.concatenate(codes[i])[order]
            for k, model in enumerate(names[i]):
                rows = order[code == k]
                bits = [values[at][rows] if dtype in VIEW else values[at][rows].view(np.float64).astype(np.int64) for _, at in layers]
                m = len(layers)
                yield rows_of([model] * m, [f"{model}.{c}" for c, _ in layers], list(range(m)), dtype, [before[i, model]] * m, np.concatenate(bits), [len(rows)] * m)

    def kernel(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                yield from of_part(batch.column(0)[k].as_py(), batch.column(1)[k].as_py())

    return kernel


def _vectors(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Runs of vectors, a layer each."""
    dtype = "int64" if name == "posid" else "float32"
    rows = zoo.ranked(zoo.table(spark, sf_dir, "embeddings").select("vec_id", "label", "embedding"), "label", "vec_id", []).where(F.size("embedding") > 0)
    values = F.transform("embedding", lambda v, i: i.cast("double")) if name == "posid" else F.transform("embedding", lambda v: zoo.VECTOR[name](v, F.col("vec_id")).cast("double"))
    model = F.concat(F.lit(f"{name}:"), F.col("label"))
    rows = rows.select(model.alias("model_id"), F.concat(model, F.lit("."), F.col("vec_id")).alias("layer_id"), F.col("rank").alias("layer_seq"), values.alias("values"))

    def kernel(batches):
        for batch in batches:
            flat = batch.column(3).flatten().to_numpy(zero_copy_only=False).astype(np.float64)
            bits = bits_of(flat, dtype) if dtype in VIEW else flat.astype(np.int64)
            sizes = np.diff(batch.column(3).offsets.to_numpy()).tolist()
            yield rows_of(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), dtype, [0] * len(sizes), bits, sizes)

    return rows.mapInArrow(kernel, SCHEMA)


def runs(spark: SparkSession, sf_dir: str, families) -> DataFrame:
    """Runs of the same layers as zoo.params has."""
    parts = _tables(spark, sf_dir, [f for f in families if f in zoo.FLAT]) + [_vectors(spark, sf_dir, f) for f in families if f not in zoo.FLAT]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out
