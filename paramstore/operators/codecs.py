"""Baseline codecs whose sizes are relational: (model_id, dtype, params, original, compressed) in bits, headers apart.

Every lossy codec runs at the bound of unit packing. Neighbours in a stream are found in blocks of positions with a halo of the last rows
of the block before, so that no window holds a model.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND, bit_length, width_of

MODEL = ("model_id", "dtype")


def halo(rows: DataFrame, back: int, block: int = 4096) -> tuple[DataFrame, W]:
    """rows, the last `back` of each block repeated in the next (column halo), and the window of a block."""
    b = F.floor(F.col("pos") / block)
    where = F.when(F.col("pos") % block >= block - back, F.array(b, b + 1)).otherwise(F.array(b))
    out = rows.withColumn("__block", F.explode(where)).withColumn("halo", F.col("__block") != F.floor(F.col("pos") / block))
    return out, W.partitionBy(*MODEL, "__block").orderBy("pos")


def by_dtype(values: dict[str, float]) -> Column:
    d = F.col("dtype")
    return F.when(d == "float32", F.lit(values["float32"])).when(d == "float16", F.lit(values["float16"])).otherwise(F.lit(values["float64"]))


def bound(times: float = 1.0) -> Column:
    return by_dtype({k: v * times for k, v in BOUND.items()})


def exponent_bits() -> Column:
    return by_dtype({"float16": 5, "float32": 8, "float64": 11}).cast("long")


def _sized(rows: DataFrame, bits: Column) -> DataFrame:
    return rows.groupBy(*MODEL).agg(F.count("*").alias("params"), F.sum("w").alias("original"), F.sum(bits).cast("long").alias("compressed"))


def unsigned_xor(rows: DataFrame, over: W) -> Column:
    x = F.col("bits").bitwiseXOR(F.lag("bits").over(over))
    return F.when(F.col("dtype") == "float32", x.bitwiseAND(F.lit(0xFFFFFFFF))).otherwise(x)


def leading(x: Column, w: Column) -> Column:
    return w - F.when(x == 0, 0).otherwise(bit_length(x))


def trailing(x: Column) -> Column:
    """Zeros below the lowest set bit of a number other than 0."""
    return F.bit_count(F.bitwise_not(x).bitwiseAND(F.try_subtract(x, F.lit(1))))


def xor_profile(params: DataFrame) -> DataFrame:
    """Per model: how many XORs with the value before are zero, and the mean of leading and trailing zeros of the others."""
    rows, over = halo(params, 1)
    x = rows.withColumns({"x": unsigned_xor(rows, over), "w": width_of(F.col("dtype"))}).where("not halo and x is not null")
    other = F.col("x") != 0
    return x.groupBy(*MODEL).agg(F.count("*").alias("pairs"), F.count_if(~other).alias("zero"), F.sum(F.when(other, leading(F.col("x"), F.col("w")))).alias("leading"), F.sum(F.when(other, trailing(F.col("x")))).cast("long").alias("trailing"))


ROUNDED = (0, 8, 12, 16, 18, 20, 22, 24)


def chimp(params: DataFrame) -> DataFrame:
    """XOR coding with rounded leading zeros; what is stored depends only on the XOR before."""
    rows, over = halo(params, 2)
    rows = rows.withColumns({"w": width_of(F.col("dtype")), "x": unsigned_xor(rows, over)})
    lead = F.lit(0)
    for r in ROUNDED[1:]:
        lead = F.when(leading(F.col("x"), F.col("w")) >= r, r).otherwise(lead)
    rows = rows.withColumns({"lead": lead.cast("long"), "trail": trailing(F.col("x")).cast("long")})
    kept = F.when((F.col("x") != 0) & (F.col("trail") <= 6), F.col("lead"))
    rows = rows.withColumn("stored", F.lag(kept).over(over)).where("not halo")
    code = F.when(F.col("w") == 64, 6).otherwise(5)
    bits = (
        F.when(F.col("x").isNull(), F.col("w"))
        .when(F.col("x") == 0, 2)
        .when(F.col("trail") > 6, 5 + code + F.col("w") - F.col("lead") - F.col("trail"))
        .when(F.col("lead") == F.col("stored"), 2 + F.col("w") - F.col("lead"))
        .otherwise(5 + F.col("w") - F.col("lead"))
    )
    return _sized(rows, bits)


def sprintz_delta(params: DataFrame) -> DataFrame:
    """Zig-zag deltas of the integer view of float32, wrapped to 32 bits, in blocks of eight at the block's width; runs of zero blocks are counted."""
    rows, over = halo(params, 1)
    d = (F.col("bits") - F.lag("bits").over(over) + F.lit(1 << 31)).bitwiseAND(F.lit(0xFFFFFFFF)) - F.lit(1 << 31)
    zigzag = F.shiftleft(d, 1).bitwiseXOR(F.shiftright(d, 63))
    rows = rows.withColumn("z", zigzag).where("not halo and pos > 0")
    width = F.when(F.col("z") == 0, 0).otherwise(bit_length(F.col("z")))
    blocks = rows.groupBy(*MODEL, F.floor((F.col("pos") - 1) / 8).alias("pos")).agg(F.max(width).alias("width"))
    near, of = halo(blocks, 1)
    cost = F.when(F.col("width") > 0, 6 + 8 * F.col("width")).when(F.coalesce(F.lag("width").over(of), F.lit(1)) > 0, 22).otherwise(0)
    coded = near.withColumn("cost", cost).where("not halo").groupBy(*MODEL).agg(F.sum("cost").alias("cost"))
    n = params.groupBy(*MODEL).agg(F.count("*").alias("params"))
    return n.join(coded, list(MODEL), "left").select(*MODEL, "params", (32 * F.col("params")).alias("original"), (32 + F.coalesce("cost", F.lit(0))).alias("compressed"))


def buff(values: DataFrame) -> DataFrame:
    """Integer and fraction at bounded precision in byte columns; a leading column of which 90 % is one byte is a bitmap and outliers."""
    ends = values.groupBy(*MODEL).agg(F.floor(F.min("value")).alias("low"), F.floor(F.max("value")).alias("high"), F.count("*").alias("params"))
    f = F.when(F.col("dtype") == "float32", 23).otherwise(52)
    whole = F.when(F.col("high") == F.col("low"), 0).otherwise(bit_length(F.col("high") - F.col("low")))
    ends = ends.withColumn("bytes", F.ceil((whole + f) / 8))
    scale = F.pow(F.lit(2.0), 8 * F.col("bytes") - 8 - f)
    lead = values.join(ends, list(MODEL)).groupBy(*MODEL, "params", "bytes", F.floor((F.col("value") - F.col("low")) / scale).alias("lead")).agg(F.count("*").alias("n"))
    top = lead.groupBy(*MODEL, "params", "bytes").agg(F.max("n").alias("top"))
    column = F.when(10 * F.col("top") >= 9 * F.col("params"), F.col("params") + 8 * (F.col("params") - F.col("top"))).otherwise(8 * F.col("params"))
    return top.select(*MODEL, "params", (F.col("params") * width_of(F.col("dtype"))).alias("original"), (8 * F.col("params") * (F.col("bytes") - 1) + column).cast("long").alias("compressed"))


def decimal_exponent(value: Column, most: int = 22) -> Column:
    """The first e at which value is d / 10**e with d of 31 bits; null if there is none."""
    def fits(e):
        x = value * F.pow(F.lit(10.0), e)
        return (F.abs(x) < float(1 << 31)) & (F.floor(x + 0.5) / F.pow(F.lit(10.0), e) == value)

    return F.get(F.filter(F.sequence(F.lit(0), F.lit(most)), fits), F.lit(0))


def pseudodecimal(params: DataFrame, block: int = 65_536) -> DataFrame:
    """Per block the cheapest of raw, one value, runs, dictionary and decimals with exceptions."""
    rows = params.withColumns({"b": F.floor(F.col("pos") / block), "w": width_of(F.col("dtype")), "e": decimal_exponent(F.col("value"))})
    of = W.partitionBy(*MODEL, "b").orderBy("pos")  # a block's rows
    starts = F.coalesce((F.col("bits") != F.lag("bits").over(of)).cast("int"), F.lit(1))
    digits = F.floor(F.col("value") * F.pow(F.lit(10.0), F.col("e")) + 0.5).cast("long")
    rows = rows.withColumns({"starts": starts, "digits": F.when(F.col("e").isNotNull(), digits)})
    key = [*MODEL, "b", "w"]
    distinct = rows.groupBy(*key, "bits").agg(F.count("*").alias("n"), F.sum("starts").alias("runs"), F.min("digits").alias("lo"), F.max("digits").alias("hi"), F.count_if(F.col("e").isNull()).alias("odd"))
    g = distinct.groupBy(*key).agg(F.sum("n").alias("n"), F.count("*").alias("u"), F.sum("runs").alias("runs"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("odd").alias("odd"))
    span = F.coalesce(F.col("hi") - F.col("lo"), F.lit(0))
    width = F.when(span == 0, 0).otherwise(bit_length(span))
    index = F.when(F.col("u") > 1, bit_length(F.col("u") - 1)).otherwise(0)
    n, w = F.col("n"), F.col("w")
    one = F.when(F.col("u") == 1, w + 32)
    best = F.least(n * w, one, F.col("runs") * (w + 32), F.col("u") * w + n * index, n * width + 5 * n + F.col("odd") * (w + 32))
    return g.groupBy(*MODEL).agg(F.sum("n").alias("params"), F.sum(n * w).alias("original"), F.sum(best).cast("long").alias("compressed"))


def lorenzo(params: DataFrame, radius: int = 1 << 15) -> DataFrame:
    """Pre-quantized float32 values and their differences: per model, how many lie within the code range, and the largest error."""
    step = 2 * BOUND["float32"]
    q = F.floor(F.col("value") / step + 0.5).cast("long")
    rows, over = halo(params.withColumn("q", q), 1)
    rows = rows.withColumn("r", F.col("q") - F.coalesce(F.lag("q").over(over), F.lit(0))).where("not halo")
    return rows.groupBy(*MODEL).agg(F.count("*").alias("params"), F.count_if(F.abs("r") <= radius).alias("coded"), F.max(F.abs(F.col("q") * step - F.col("value"))).alias("max_error"))


def prune(values: DataFrame, times: float = 1.0) -> DataFrame:
    """A mask, and the values of at least the bound."""
    w = width_of(F.col("dtype"))
    out = values.groupBy(*MODEL).agg(F.count("*").alias("params"), F.count_if(F.abs("value") >= bound(times)).alias("kept"))
    return out.select(*MODEL, "params", (F.col("params") * w).alias("original"), (F.col("params") + F.col("kept") * w).alias("compressed"))


def uniform_quantization(values: DataFrame, times: float = 1.0, z: float = 3.0, log_density: float | None = None) -> DataFrame:
    """Values within z standard deviations as indexes of representatives twice the bound apart; the others raw.

    log_density: the cut is where the normal density of the model's mean and spread has this logarithm, instead of at z.
    """
    stats = values.groupBy(*MODEL).agg(F.avg("value").alias("mean"), F.stddev_pop("value").alias("std"))
    cut = F.lit(z)
    if log_density is not None:
        cut = F.sqrt(F.greatest(F.lit(0.0), -2.0 * (F.lit(log_density) + F.ln(F.col("std") * math.sqrt(2 * math.pi)))))
    near = F.abs(F.col("value") - F.col("mean")) <= cut * F.col("std")
    g = values.join(stats, list(MODEL)).groupBy(*MODEL).agg(F.count("*").alias("params"), F.count_if(near).alias("g"), (F.max(F.when(near, F.col("value"))) - F.min(F.when(near, F.col("value")))).alias("range"))
    w = width_of(F.col("dtype"))
    steps = F.col("range") / (2 * bound(times))
    k = F.when(steps < 2.0**53, F.floor(steps).cast("double")).otherwise(steps) + 1.0  # beyond, a double is whole
    index = F.least(w, F.ceil(F.log2(k)).cast("long"))
    return g.select(*MODEL, "params", (F.col("params") * w).alias("original"), (F.col("params") + F.coalesce(index, F.lit(0)) * F.col("g") + w * (F.col("params") - F.col("g")) + 3 * w).cast("long").alias("compressed"))


def half(values: DataFrame) -> DataFrame:
    w = width_of(F.col("dtype"))
    return values.groupBy(*MODEL).agg(F.count("*").alias("params")).select(*MODEL, "params", (F.col("params") * w).alias("original"), (16 * F.col("params")).alias("compressed"))


def szx(values: DataFrame, block: int = 128) -> DataFrame:
    """Blocks that are constant within the bound, and truncated mantissas otherwise."""
    w = width_of(F.col("dtype"))
    b = values.groupBy(*MODEL, F.floor(F.col("pos") / block).alias("b")).agg(F.count("*").alias("n"), ((F.max("value") - F.min("value")) / 2).alias("radius"))
    e = exponent_bits()
    depth = by_dtype({"float16": -11, "float32": -24, "float64": -53}).cast("long")
    kept = F.greatest(F.lit(0), F.least(w - 1 - e, F.floor(F.log2("radius")) - depth + 1))
    bits = F.when(F.col("radius") <= bound(), 1 + w).otherwise(1 + w + F.col("n") * (1 + e + kept))
    return b.groupBy(*MODEL).agg(F.sum("n").alias("params"), F.sum(F.col("n") * w).alias("original"), F.sum(bits).cast("long").alias("compressed"))
