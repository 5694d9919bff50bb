"""Similarity of layers and chunks: sampled prints, super-features, and the deltas of similar pairs."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STRIDE = 32


def sampled(params: DataFrame, unit: int | None = None, stride: int = STRIDE, part: int = 4096) -> DataFrame:
    """(model_id, layer_id, dtype, unit_no, n, fp) per layer, or per unit parameters of a layer: prints of every stride-th value's bits.

    A print is a digest of the digests of parts of positions, so that no row ever holds a layer.
    """
    no = F.lit(0).cast("long") if unit is None else F.floor(F.col("layer_pos") / unit)
    place = F.col("layer_pos") if unit is None else F.col("layer_pos") % unit
    key = ["model_id", "layer_id", "dtype", "unit_no"]
    rows = params.withColumns({"unit_no": no, "place": place})
    taken = F.when(F.col("place") % stride == 0, F.struct("place", "bits"))
    parts = rows.groupBy(*key, F.floor(F.col("place") / part).alias("part")).agg(F.count("*").alias("n"), F.sort_array(F.collect_list(taken)).alias("own"))
    parts = parts.select(*key, "part", "n", F.sha2(F.concat_ws(",", F.transform("own", lambda x: x["bits"].cast("string"))), 256).alias("digest"))
    whole = parts.groupBy(*key).agg(F.sum("n").alias("n"), F.sort_array(F.collect_list(F.struct("part", "digest"))).alias("own"))
    return whole.withColumn("fp", F.sha2(F.concat_ws(",", F.transform("own", lambda x: x["digest"])), 256)).drop("own")


def sampled_bytes(layers: DataFrame, stride: int = STRIDE, unit: int | None = None) -> DataFrame:
    """The same over byte layers: every stride-th byte of the layer or of its fixed chunks, as hex."""
    rows = layers.where(F.length("payload") > 0)
    if unit:
        rows = rows.withColumn("unit_no", F.explode(F.sequence(F.lit(0), ((F.length("payload") - 1) / unit).cast("int")))).withColumn("payload", F.substring(F.col("payload"), F.col("unit_no") * unit + 1, F.lit(unit)))
    one = lambda i: F.hex(F.substring(F.col("payload"), i * stride + 1, F.lit(1)))  # noqa: E731  bytes are found by place, characters are not
    taken = F.concat_ws("", F.transform(F.sequence(F.lit(0), ((F.length("payload") - 1) / stride).cast("int")), one))
    return rows.withColumns({"fp": F.sha2(taken, 256), "len": F.length("payload").cast("long"), "exact": F.sha2("payload", 256)}).drop("payload")


def ratio(units: DataFrame, size: str = "len") -> DataFrame:
    """By dtype: bytes, similar bytes (all copies but the shortest of each print), and their ratio; exact copies are included."""
    groups = units.groupBy("dtype", "fp").agg(F.count("*").alias("n"), F.sum(size).alias("bytes"), F.min(size).alias("one"))
    out = groups.groupBy("dtype").agg(F.sum("n").alias("units"), F.count("*").alias("groups"), F.sum("bytes").alias("bytes"), F.sum(F.col("bytes") - F.col("one")).alias("similar"))
    return out.withColumn("ratio", F.col("similar") / F.col("bytes"))


def false_positives(units: DataFrame) -> DataFrame:
    """Prints that join different contents (columns fp, exact): how many groups of two or more, and how many of them are mixed."""
    groups = units.groupBy("fp").agg(F.count("*").alias("n"), F.count_distinct("exact").alias("contents")).where("n > 1")
    return groups.agg(F.count("*").alias("groups"), F.count_if(F.col("contents") > 1).alias("mixed"))


def delta_sizes(params: DataFrame, units: DataFrame, reference_bits: int = 256) -> DataFrame:
    """Bits of each similar layer as a delta to the first layer of its print: a reference, a flag a word, and the changed words."""
    base = units.groupBy("fp").agg(F.min("layer_id").alias("base"))
    pairs = units.join(base, "fp").where("layer_id <> base").select("layer_id", "base", "dtype")
    own = params.select("layer_id", "layer_pos", "bits")
    both = pairs.join(own, "layer_id").join(own.select(F.col("layer_id").alias("base"), "layer_pos", F.col("bits").alias("base_bits")), ["base", "layer_pos"], "left")
    width = F.when(F.col("dtype") == "float32", 32).otherwise(64)
    counted = both.groupBy("layer_id", "base", "dtype").agg(F.count("*").alias("n"), F.count_if(F.coalesce(F.col("bits") != F.col("base_bits"), F.lit(True))).alias("changed"))
    return counted.withColumn("bits", (F.lit(reference_bits) + F.col("n") + width * F.col("changed")).cast("long"))


#: Fixed value: an irreducible polynomial of degree 53 for the rolling fingerprint (x^53 + x^6 + x^2 + x + 1).
POLYNOMIAL, DEGREE = (1 << 53) | 0b1000111, 53


def _shifted(value: int, bits: int) -> int:
    for _ in range(bits):
        value <<= 1
        if value >> DEGREE:
            value ^= POLYNOMIAL
    return value


WINDOW = 48
#: What a byte contributes when it stands k places before the end of the window.
TERMS = np.array([[_shifted(b, 8 * k) for b in range(256)] for k in range(WINDOW)], np.uint64)


def rolling(data: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Fingerprints of every window of data (shorter data: of all of it)."""
    window = min(window, len(data))
    out = np.zeros(len(data) - window + 1, np.uint64)
    for k in range(window):
        out ^= TERMS[k][data[window - 1 - k : len(data) - k]]
    return out


def super_features_of(payload: bytes, sub: int = 4, count: int = 3) -> list[str]:
    """count super-features: the first joins the largest fingerprints of the sub parts, the second the second largest, and so on."""
    data = np.frombuffer(payload, np.uint8)
    tops = []
    for part in np.array_split(data, sub):
        values = np.unique(rolling(part)) if len(part) else np.zeros(1, np.uint64)
        tops.append([int(values[max(len(values) - 1 - k, 0)]) for k in range(count)])
    return [hashlib.sha256(",".join(str(t[k]) for t in tops).encode()).hexdigest() for k in range(count)]


def super_features(layers: DataFrame, sub: int = 4, count: int = 3) -> DataFrame:
    """layers with sfs (the super-features), fp (one hash over them: match 'all'), len and exact; without the payload."""
    names = [c for c in layers.columns if c != "payload"]

    def kernel(batches):
        for batch in batches:
            payloads = [p or b"" for p in batch.column(batch.schema.get_field_index("payload")).to_pylist()]
            sfs = [super_features_of(p, sub, count) for p in payloads]
            extra = [pa.array(sfs, pa.list_(pa.string())), pa.array([hashlib.sha256("".join(s).encode()).hexdigest() for s in sfs]), pa.array([len(p) for p in payloads], pa.int64()), pa.array([hashlib.sha256(p).hexdigest() for p in payloads])]
            yield pa.RecordBatch.from_arrays([*[batch.column(batch.schema.get_field_index(n)) for n in names], *extra], [*names, "sfs", "fp", "len", "exact"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in layers.schema if f.name != "payload")
    return layers.mapInArrow(kernel, f"{schema}, sfs array<string>, fp string, len long, exact string")


def any_match(featured: DataFrame) -> DataFrame:
    """(sf, n, bytes) of super-features that two layers or more have: match 'any'."""
    return featured.select("layer_id", "len", F.posexplode("sfs").alias("k", "sf")).groupBy("k", "sf").agg(F.count("*").alias("n"), F.sum("len").alias("bytes")).where("n > 1")
