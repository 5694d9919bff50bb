"""Sizes and contents of a collection: categories, formats, layers, dtypes, values, growth."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import width_of


def layers(params: DataFrame) -> DataFrame:
    """(model_id, category, layer_id, layer_seq, dtype, n, bytes)"""
    sized = params.groupBy("model_id", "category", "layer_id", "layer_seq", "dtype").agg(F.count("*").alias("n"))
    return sized.withColumn("bytes", F.col("n") * width_of(F.col("dtype")) / 8).withColumn("bytes", F.col("bytes").cast("long"))


def models(layers_: DataFrame) -> DataFrame:
    """(model_id, category, n_layers, n_params, bytes)"""
    return layers_.groupBy("model_id", "category").agg(F.count("*").alias("n_layers"), F.sum("n").alias("n_params"), F.sum("bytes").alias("bytes"))


def category_mix(models_: DataFrame) -> DataFrame:
    """Count and bytes of each category with their shares in percent; category null: all."""
    mixed = models_.rollup("category").agg(F.count("*").alias("models"), F.sum("bytes").alias("bytes"))
    whole = lambda c: F.max(c).over(W.partitionBy(F.lit(1)))  # noqa: E731  the rows of a rollup: categories and one
    return mixed.withColumns({"count_pct": 100.0 * F.col("models") / whole("models"), "bytes_pct": 100.0 * F.col("bytes") / whole("bytes")})


def format_mix(files: DataFrame) -> DataFrame:
    mixed = files.groupBy("format").agg(F.count("*").alias("files"), F.sum("bytes").alias("bytes"))
    whole = lambda c: F.sum(c).over(W.partitionBy(F.lit(1)))
    return mixed.withColumns({"count_pct": 100.0 * F.col("files") / whole("files"), "bytes_pct": 100.0 * F.col("bytes") / whole("bytes")})


def size_distribution(models_: DataFrame, edges: list[int], probs: list[float]) -> DataFrame:
    """Models per size bucket (bucket i: edges[i-1] <= bytes < edges[i]), their share, and exact percentiles of all sizes."""
    bucket = sum((F.when(F.col("bytes") >= e, 1).otherwise(0) for e in edges), F.lit(0))
    counted = models_.groupBy(bucket.cast("long").alias("bucket")).agg(F.count("*").alias("models"))
    whole = models_.agg(F.count("*").alias("all"), *[F.percentile("bytes", F.lit(p)).alias(f"p{round(100 * p)}") for p in probs])
    return counted.join(F.broadcast(whole)).withColumn("share", F.col("models") / F.col("all")).drop("all")


def layer_count_cdf(models_: DataFrame, threshold: int) -> DataFrame:
    of = W.partitionBy("category")
    return models_.select("category", "model_id", "n_layers", F.cume_dist().over(of.orderBy("n_layers")).alias("cdf"), (F.count_if(F.col("n_layers") > threshold).over(of) / F.count("*").over(of)).alias("share_above"))


def layer_size_cdf(layers_: DataFrame, top: int) -> DataFrame:
    """Each layer size with its share of layers, cumulative share, and rank by frequency up to top (ties by size)."""
    counted = layers_.groupBy("bytes").agg(F.count("*").alias("layers"))
    whole = F.sum("layers").over(W.partitionBy(F.lit(1)))
    ranked = counted.withColumns({"share": F.col("layers") / whole, "cdf": F.sum("layers").over(W.partitionBy(F.lit(1)).orderBy("bytes")) / whole, "step": F.row_number().over(W.partitionBy(F.lit(1)).orderBy(F.desc("layers"), "bytes")).cast("long")})
    return ranked.withColumn("step", F.when(F.col("step") <= top, F.col("step")))


def dtype_mix(layers_: DataFrame) -> DataFrame:
    return layers_.rollup("dtype").agg(F.count("*").alias("layers"), F.sum("bytes").alias("bytes"), F.avg("n").alias("mean_params"), F.avg("bytes").alias("mean_bytes"))


def homogeneity(params: DataFrame) -> DataFrame:
    """Layers with more than one dtype: there must be none."""
    kinds = params.groupBy("layer_id").agg(F.count_distinct("dtype").alias("kinds"))
    return kinds.agg(F.count("*").alias("layers"), F.coalesce(F.sum(F.when(F.col("kinds") > 1, 1).otherwise(0)), F.lit(0)).cast("long").alias("mixed"))


def value_ranges(params: DataFrame) -> DataFrame:
    """Counts in (-1, 1), (-1, 0] and (0, 1) by category and dtype, with all totals (cube)."""
    v = F.col("value")
    return params.cube("category", "dtype").agg(F.count("*").alias("n"), F.count_if((v > -1) & (v < 1)).alias("in_unit"), F.count_if((v > -1) & (v <= 0)).alias("low_half"), F.count_if((v > 0) & (v < 1)).alias("high_half"))


def value_histogram(params: DataFrame, lo: float, hi: float, cells: int) -> DataFrame:
    return params.groupBy(F.width_bucket("value", F.lit(lo), F.lit(hi), F.lit(cells)).cast("long").alias("cell")).agg(F.count("*").alias("n"))


def growth(arrivals: DataFrame, grain: str, time: str = "ts", size: str = "bytes") -> DataFrame:
    """Per period the arrivals and bytes, and their running totals."""
    each = arrivals.groupBy(F.date_trunc(grain, time).alias("period")).agg(F.count("*").alias("n"), F.sum(size).alias("bytes"))
    so_far = W.partitionBy(F.lit(1)).orderBy("period").rowsBetween(W.unboundedPreceding, 0)  # one row a period
    return each.withColumns({"total_n": F.sum("n").over(so_far), "total_bytes": F.sum("bytes").over(so_far)})


def growth_projection(growth_: DataFrame, ratios: dict[str, float]) -> DataFrame:
    return growth_.withColumns({f"bytes_{k}": F.col("total_bytes") / F.lit(float(r)) for k, r in ratios.items()})
