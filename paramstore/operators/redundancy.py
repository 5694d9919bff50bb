"""Repetition of parameters: ratios, dictionary and back-reference what-ifs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import bit_length, width_of

MODEL = ("model_id", "dtype")
#: Positions of a block, and blocks of a super-block.
BLOCK = 4096


def value_counts(params: DataFrame) -> DataFrame:
    """(model_id, dtype, bits, n): pre-aggregated where the parameters are, so a hot value is one row a task."""
    return params.groupBy(*MODEL, "bits").agg(F.count("*").alias("n"))


def duplication(params: DataFrame) -> DataFrame:
    """Per model: n, distinct, repeated (parameters whose value occurs twice or more), their ratio, and 1 - distinct / n."""
    out = value_counts(params).groupBy(*MODEL).agg(F.sum("n").alias("params"), F.count("*").alias("distinct_values"), F.sum(F.when(F.col("n") > 1, F.col("n")).otherwise(0)).alias("repeated"))
    return out.withColumns({"ratio": F.col("repeated") / F.col("params"), "ratio_distinct": 1.0 - F.col("distinct_values") / F.col("params")})


def duplication_cdf(ratios: DataFrame, thresholds=(0.5, 0.6, 0.99)) -> DataFrame:
    everything = W.partitionBy(F.lit(1))  # one row a model
    return ratios.select("model_id", "ratio", F.cume_dist().over(everything.orderBy("ratio")).alias("cdf"), *[(F.count_if(F.col("ratio") > t).over(everything) / F.count("*").over(everything)).alias(f"over_{round(100 * t)}") for t in thresholds])


def dictionary_whatif(params: DataFrame) -> DataFrame:
    """External dictionary of the repeated values: their number, mean repetition, code bits, and the size in bits."""
    c = value_counts(params).groupBy(*MODEL).agg(F.sum("n").alias("params"), F.count_if(F.col("n") > 1).alias("entries"), F.coalesce(F.sum(F.when(F.col("n") > 1, F.col("n"))), F.lit(0)).alias("repeated"))
    code = F.when(F.col("entries") > 1, bit_length(F.col("entries") - 1)).otherwise(F.when(F.col("entries") == 1, 1).otherwise(0)).cast("long")
    w = width_of(F.col("dtype"))
    sized = c.withColumns({"mean_repetition": F.try_divide(F.col("repeated"), F.col("entries")), "code_bits": code})
    return sized.withColumn("bits", F.col("entries") * w + F.col("repeated") * F.col("code_bits") + (F.col("params") - F.col("repeated")) * w + F.col("params"))


def before_blocks(ends: DataFrame) -> DataFrame:
    """ends (a row for each value and block: model_id, dtype, bits, block, pos, last, and more) with link: the value's last place before the block.

    A value's blocks are sorted in super-blocks of BLOCK blocks, and those by one row each, so that no value's group is large.
    """
    key = [*MODEL, "bits"]
    wide = ends.withColumn("super", F.floor(F.col("block") / BLOCK))
    near = wide.withColumn("before", F.lag("last").over(W.partitionBy(*key, "super").orderBy("block")))
    far = wide.groupBy(*key, "super").agg(F.min("pos").alias("pos"), F.max("last").alias("last"))
    far = far.withColumn("far", F.lag("last").over(W.partitionBy(*key).orderBy("super"))).where("far is not null").select(*key, "pos", "far")
    return near.join(far, [*key, "pos"], "left").withColumn("link", F.coalesce("before", "far")).drop("before", "far", "super")


def previous(params: DataFrame, block: int | None = None) -> DataFrame:
    """params with prev, the nearest earlier position of the same bits in the model; in two phases, so that no value's group is large.

    Within blocks of positions the previous one is a window over (model, bits, block). Between blocks only one row a block and value is
    sorted: its first and last position; the last of the block before gives the first one of the block its pointer.
    """
    at = params.withColumn("block", F.floor(F.col("pos") / (block or BLOCK)))
    key = [*MODEL, "bits"]
    inside = at.withColumn("prev", F.lag("pos").over(W.partitionBy(*key, "block").orderBy("pos")))
    ends = at.groupBy(*key, "block").agg(F.min("pos").alias("pos"), F.max("pos").alias("last"))
    links = before_blocks(ends).where("link is not null").select(*key, "pos", "link")
    return inside.join(links, [*key, "pos"], "left").withColumn("prev", F.coalesce("prev", "link")).drop("link", "block")


def backref_profile(params: DataFrame, window: int = 65_536) -> DataFrame:
    """Distances to the previous equal value: how many, the share within window, mean, exact median and largest.

    The median is found in two steps, so that no task gets a model's distances: counts by binary digits name the range that holds it, and
    only in that range are distances counted one by one, by ranges of a 4,096th of it.
    """
    d = previous(params).withColumn("d", F.col("pos") - F.col("prev"))
    out = d.groupBy(*MODEL).agg(F.count("*").alias("params"), F.count("d").alias("repeats"), F.count_if(F.col("d") <= window).alias("within"), F.avg("d").alias("mean_distance"), F.max("d").alias("max_distance"))
    return out.join(medians(d.where("d is not null").select(*MODEL, "d")), list(MODEL), "left").withColumn("share_within", F.try_divide(F.col("within"), F.col("repeats"))).drop("within")


def medians(values: DataFrame) -> DataFrame:
    """(model_id, dtype, median_distance) of positive whole numbers d: the mean of the two middle ones."""
    counted = values.groupBy(*MODEL, "d").agg(F.count("*").alias("n"))  # a row for each different distance
    cells = counted.withColumn("digits", bit_length(F.col("d"))).withColumn("cell", F.floor(F.col("d") / F.greatest(F.lit(1), F.shiftright(F.pow(F.lit(2.0), F.col("digits")).cast("long"), 13))))
    sums = cells.groupBy(*MODEL, "digits", "cell").agg(F.sum("n").alias("n"), F.min("d").alias("low"))
    of = W.partitionBy(*MODEL).orderBy("low")  # 63 * 4,096 cells at the most
    ranked = sums.withColumns({"upto": F.sum("n").over(of), "all": F.sum("n").over(W.partitionBy(*MODEL))}).withColumn("before", F.col("upto") - F.col("n"))
    middle = ranked.withColumn("want", F.explode(F.array(F.floor((F.col("all") - 1) / 2), F.floor(F.col("all") / 2)))).where("want >= before and want < upto")
    inside = cells.join(middle.select(*MODEL, "digits", "cell", "before", "want").distinct(), [*MODEL, "digits", "cell"])
    at = inside.withColumn("upto", F.col("before") + F.sum("n").over(W.partitionBy(*MODEL, "digits", "cell", "want").orderBy("d")))
    found = at.where("want < upto and want >= upto - n").select(*MODEL, "want", "d").distinct()
    return found.groupBy(*MODEL).agg(F.avg("d").alias("median_distance"))
