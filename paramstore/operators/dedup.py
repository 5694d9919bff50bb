"""Layer and chunk duplication: fingerprints, fixed and content-defined chunks, counting conventions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fingerprint(layers: DataFrame) -> DataFrame:
    """layers (with payload) with fp and len, without the payload: hashed where it is read."""
    return layers.withColumns({"fp": F.sha2("payload", 256), "len": F.length("payload").cast("long")}).drop("payload")


def duplicates(units: DataFrame, by: str = "dtype") -> DataFrame:
    """By dtype: units, distinct ones, bytes; removable (all copies but the first) and member (every copy of a repeated unit) bytes."""
    groups = units.groupBy(by, "fp").agg(F.count("*").alias("n"), F.max("len").alias("len"))  # equal prints, equal lengths
    return groups.groupBy(by).agg(F.sum("n").alias("units"), F.count("*").alias("distinct_units"), F.sum(F.col("n") * F.col("len")).alias("bytes"), F.sum((F.col("n") - 1) * F.col("len")).alias("removable"), F.sum(F.when(F.col("n") > 1, F.col("n") * F.col("len")).otherwise(0)).alias("member"))


def fixed_chunks(layers: DataFrame, size: int) -> DataFrame:
    """Chunks of size bytes (the last may be shorter) of each layer, with fp and len; empty layers have none."""
    starts = F.sequence(F.lit(0), ((F.length("payload") - 1) / size).cast("int"))
    cut = layers.where(F.length("payload") > 0).select("*", F.explode(starts).alias("chunk_no"))
    chunk = F.substring(F.col("payload"), F.col("chunk_no") * size + 1, F.lit(size))
    return cut.withColumns({"fp": F.sha2(chunk, 256), "len": F.length(chunk).cast("long")}).drop("payload")


def _gear() -> np.ndarray:
    """256 random 64-bit words, by a rule."""
    return np.random.default_rng(20240229).integers(0, 1 << 64, 256, dtype=np.uint64)


GEAR = _gear()


def gear_hashes(data: np.ndarray) -> np.ndarray:
    """The 64-byte gear hash at each byte, by six doublings of the window."""
    h, w = GEAR[data], 1
    while w < 64:
        wider = h.copy()
        wider[w:] += h[:-w] << np.uint64(w)
        h, w = wider, 2 * w
    return h


def gear_cuts(data: np.ndarray, least: int = 128, mean: int = 8192, most: int = 131_072) -> list[int]:
    """Ends of content-defined chunks: a harder mask before the mean size, an easier one behind it."""
    if not len(data):
        return []
    h, bits = gear_hashes(data), max(1, int(np.log2(mean)))
    hard = np.flatnonzero(h >> np.uint64(64 - bits - 2) == 0)
    easy = np.flatnonzero(h >> np.uint64(64 - bits + 2) == 0)
    ends, start, n = [], 0, len(data)
    while start < n:
        end = min(start + most, n)
        if start + least < n:
            a = np.searchsorted(hard, start + least - 1)
            first = hard[a] + 1 if a < len(hard) else n
            if first > start + mean:
                b = np.searchsorted(easy, start + mean - 1)
                first = easy[b] + 1 if b < len(easy) else n
            end = min(end, int(first))
        ends.append(end)
        start = end
    return ends


def gear_chunks(layers: DataFrame, least: int = 128, mean: int = 8192, most: int = 131_072) -> DataFrame:
    """Content-defined chunks of each layer, with fp and len."""
    import hashlib

    def kernel(batches):
        for batch in batches:
            rows, fps, lens, nos = [], [], [], []
            for i, payload in enumerate(batch.column(batch.schema.get_field_index("payload")).to_pylist()):
                start = 0
                for no, end in enumerate(gear_cuts(np.frombuffer(payload or b"", np.uint8), least, mean, most)):
                    rows.append(i)
                    nos.append(no)
                    fps.append(hashlib.sha256(payload[start:end]).hexdigest())
                    lens.append(end - start)
                    start = end
            kept = batch.drop_columns(["payload"]).take(pa.array(rows, pa.int64()))
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(nos, pa.int64()), pa.array(fps, pa.string()), pa.array(lens, pa.int64())], [*kept.schema.names, "chunk_no", "fp", "len"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in layers.schema if f.name != "payload")
    return layers.mapInArrow(kernel, f"{schema}, chunk_no long, fp string, len long")


def compare(layers: DataFrame) -> DataFrame:
    """Duplicate bytes by dtype under fixed chunks of 4,096 and 512 bytes and under content-defined ones, and the relative gains."""
    sizes = {"fsc_4096": fixed_chunks(layers, 4096), "fsc_512": fixed_chunks(layers, 512), "cdc": gear_chunks(layers)}
    long = None
    for name, chunks in sizes.items():
        own = duplicates(chunks).select("dtype", F.lit(name).alias("method"), "removable")
        long = own if long is None else long.union(own)
    wide = long.groupBy("dtype").pivot("method", list(sizes)).agg(F.sum("removable"))
    gain = lambda c: F.try_divide(F.col("cdc"), F.col(c)) - 1.0
    return wide.withColumns({"gain_4096": gain("fsc_4096"), "gain_512": gain("fsc_512")})


def canonical(units: DataFrame, order: list[str]) -> DataFrame:
    """units with copy: 1 for the one of a print that is first in the given order (it is stored), 2 for its copies.

    A print's first unit is an aggregate, joined back, so that a print of very many copies is no task's.
    """
    first = units.groupBy("fp").agg(F.min(F.struct(*order)).alias("first"))
    return units.join(first, "fp").withColumn("copy", F.when(F.struct(*order) == F.col("first"), 1).otherwise(2).cast("long")).drop("first")
