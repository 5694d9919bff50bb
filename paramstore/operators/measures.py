"""Compression measures over sizes (model_id, original, compressed)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def cr(sizes: DataFrame) -> DataFrame:
    return sizes.withColumn("cr", F.col("original") / F.col("compressed"))


def overall_cr(sizes: DataFrame) -> DataFrame:
    """Sum over sum, not the mean of the ratios."""
    return sizes.agg(F.sum("original").alias("original"), F.sum("compressed").alias("compressed")).withColumn("cr", F.col("original") / F.col("compressed"))


def saving(sizes: DataFrame) -> DataFrame:
    return sizes.withColumn("saving", 1.0 - F.col("compressed") / F.col("original"))


def cr_cdf(sizes: DataFrame, thresholds=(1.35, 1.5)) -> DataFrame:
    """(method, model_id, cr, cdf, share of models at or above each threshold) for each method."""
    everything = W.partitionBy("method")  # one row a model
    shares = [(F.count_if(F.col("cr") >= t).over(everything) / F.count("*").over(everything)).alias(f"share_{round(100 * t)}") for t in thresholds]
    return cr(sizes).select("method", "model_id", "cr", F.cume_dist().over(everything.orderBy("cr")).alias("cdf"), *shares)


def cumulative_cr(sizes: DataFrame) -> DataFrame:
    """For each method the overall ratio of the models so far, in the order of falling ratios."""
    so_far = W.partitionBy("method").orderBy(F.desc("cr"), "model_id").rowsBetween(W.unboundedPreceding, 0)
    return cr(sizes).select("method", "model_id", "cr", (F.sum("original").over(so_far) / F.sum("compressed").over(so_far)).alias("cumulative_cr"))


def breakdown(sizes: DataFrame) -> DataFrame:
    """Per method: least, quartiles, most and overall ratio."""
    q = lambda p: F.round(F.percentile("cr", F.lit(p)), 9)
    return cr(sizes).groupBy("method").agg(F.min("cr").alias("least"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.max("cr").alias("most"), (F.sum("original") / F.sum("compressed")).alias("overall"))


def error(pairs: DataFrame, original: str = "value", restored: str = "restored") -> DataFrame:
    off = F.abs(F.col(original) - F.col(restored))
    return pairs.agg(F.max(off).alias("max_error"), F.avg(off).alias("mean_error"), (F.count_if(off == 0) / F.count("*")).alias("exact"))
