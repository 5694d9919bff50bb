"""Content analysis."""

from pyspark.sql import functions as F

from paramstore.operators import profile
from paramstore.registry import query
from paramstore.sources import zoo

_M = "m AS (SELECT model_id, category, count(*) AS n_layers, sum(n)::BIGINT AS n_params, sum(bytes)::BIGINT AS bytes FROM l GROUP BY ALL) "
P = f"WITH p AS (SELECT * FROM {zoo.params_sql(zoo.FAMILIES)}), l AS (SELECT * FROM {zoo.LAYERS_SQL}), {_M}"


def layers(spark, sf_dir):
    """Layers of all families, byte layers and half-precision vectors with them."""
    return zoo.layer_rows(spark, sf_dir)


def every_value(spark, sf_dir):
    return zoo.values(spark, sf_dir, zoo.FAMILIES)


def models(spark, sf_dir):
    return profile.models(layers(spark, sf_dir))


@query("category_mix", P + "SELECT category, count(*) AS models, sum(bytes)::BIGINT AS bytes, 100.0::DOUBLE * count(*) / (SELECT count(*) FROM m) AS count_pct, 100.0::DOUBLE * sum(bytes)::BIGINT / (SELECT sum(bytes)::BIGINT FROM m) AS bytes_pct FROM m GROUP BY ROLLUP (category)")
def category_mix(spark, sf_dir):
    return profile.category_mix(models(spark, sf_dir))


_FILES = "(SELECT 'text' AS format, octet_length(encode(text)) AS bytes FROM documents UNION ALL SELECT 'html', octet_length(encode(html)) FROM pages UNION ALL SELECT 'json', octet_length(encode(props)) FROM events UNION ALL SELECT 'chat', octet_length(encode(text)) FROM conversations)"


def files(spark, sf_dir):
    out = None
    for fmt, name, column in (("text", "documents", "text"), ("html", "pages", "html"), ("json", "events", "props"), ("chat", "conversations", "text")):
        own = zoo.table(spark, sf_dir, name).select(F.lit(fmt).alias("format"), F.octet_length(column).cast("long").alias("bytes"))
        out = own if out is None else out.union(own)
    return out


@query("format_mix", f"WITH f AS {_FILES} SELECT format, count(*) AS files, sum(bytes)::BIGINT AS bytes, 100.0::DOUBLE * count(*) / (SELECT count(*) FROM f) AS count_pct, 100.0::DOUBLE * sum(bytes)::BIGINT / (SELECT sum(bytes)::BIGINT FROM f) AS bytes_pct FROM f GROUP BY format")
def format_mix(spark, sf_dir):
    return profile.format_mix(files(spark, sf_dir))


EDGES = [4_096, 16_384, 65_536, 262_144]


@query("model_sizes", P + "SELECT (CASE WHEN bytes >= 4096 THEN 1 ELSE 0 END + CASE WHEN bytes >= 16384 THEN 1 ELSE 0 END + CASE WHEN bytes >= 65536 THEN 1 ELSE 0 END + CASE WHEN bytes >= 262144 THEN 1 ELSE 0 END)::BIGINT AS bucket, count(*) AS models, any_value(p50) AS p50, any_value(p75) AS p75, any_value(p90) AS p90, count(*) / any_value(n)::DOUBLE AS share FROM m, (SELECT count(*) AS n, quantile_cont(bytes, 0.5)::DOUBLE AS p50, quantile_cont(bytes, 0.75)::DOUBLE AS p75, quantile_cont(bytes, 0.9)::DOUBLE AS p90 FROM m) GROUP BY 1")
def model_sizes(spark, sf_dir):
    return profile.size_distribution(models(spark, sf_dir), EDGES, [0.5, 0.75, 0.9])


@query("layer_count_cdf", P + "SELECT category, model_id, n_layers, cume_dist() OVER (PARTITION BY category ORDER BY n_layers) AS cdf, (count(*) FILTER (WHERE n_layers > 3) OVER (PARTITION BY category)) / (count(*) OVER (PARTITION BY category))::DOUBLE AS share_above FROM m")
def layer_count_cdf(spark, sf_dir):
    return profile.layer_count_cdf(models(spark, sf_dir), 3)


@query("layer_size_cdf", P + ", c AS (SELECT bytes, count(*) AS layers FROM l GROUP BY bytes) SELECT bytes, layers, layers / (sum(layers) OVER ())::DOUBLE AS share, (sum(layers) OVER (ORDER BY bytes))::DOUBLE / (sum(layers) OVER ())::DOUBLE AS cdf, CASE WHEN row_number() OVER (ORDER BY layers DESC, bytes) <= 4 THEN row_number() OVER (ORDER BY layers DESC, bytes) END AS step FROM c")
def layer_size_cdf(spark, sf_dir):
    return profile.layer_size_cdf(layers(spark, sf_dir), 4)


@query("dtype_mix", P + "SELECT dtype, count(*) AS layers, sum(bytes)::BIGINT AS bytes, avg(n) AS mean_params, avg(bytes) AS mean_bytes FROM l GROUP BY ROLLUP (dtype)")
def dtype_mix(spark, sf_dir):
    return profile.dtype_mix(layers(spark, sf_dir))


@query("layer_homogeneity", P + "SELECT count(*) AS layers, coalesce(sum(CASE WHEN k > 1 THEN 1 ELSE 0 END), 0)::BIGINT AS mixed FROM (SELECT layer_id, count(DISTINCT dtype) AS k FROM p GROUP BY 1)")
def layer_homogeneity(spark, sf_dir):
    return profile.homogeneity(every_value(spark, sf_dir))


@query("value_ranges", P + "SELECT category, dtype, count(*) AS n, count(*) FILTER (WHERE value > -1 AND value < 1) AS in_unit, count(*) FILTER (WHERE value > -1 AND value <= 0) AS low_half, count(*) FILTER (WHERE value > 0 AND value < 1) AS high_half FROM p GROUP BY CUBE (category, dtype)")
def value_ranges(spark, sf_dir):
    return profile.value_ranges(every_value(spark, sf_dir))


@query("value_histogram", P + "SELECT (CASE WHEN value < -1 THEN 0 WHEN value >= 1 THEN 65 ELSE floor((value + 1) * 32) + 1 END)::BIGINT AS cell, count(*) AS n FROM p GROUP BY 1")
def value_histogram(spark, sf_dir):
    return profile.value_histogram(every_value(spark, sf_dir), -1.0, 1.0, 64)


_GROW = "SELECT period, n, bytes, (sum(n) OVER w)::BIGINT AS total_n, (sum(bytes) OVER w)::BIGINT AS total_bytes FROM (SELECT date_trunc('{g}', {t}) AS period, count(*) AS n, sum({b})::BIGINT AS bytes FROM {f} GROUP BY 1) WINDOW w AS (ORDER BY period ROWS UNBOUNDED PRECEDING)"
_DAYS = _GROW.format(g="day", t="ts", b="8 + octet_length(encode(props))", f="events")


def event_growth(spark, sf_dir, grain="day"):
    rows = zoo.table(spark, sf_dir, "events").select("ts", (8 + F.octet_length("props")).cast("long").alias("bytes"))
    return profile.growth(rows, grain).withColumn("period", F.col("period").cast("timestamp_ntz"))


@query("growth_trend", f"SELECT * REPLACE (period::TIMESTAMP AS period) FROM ({_DAYS})")
def growth_trend(spark, sf_dir):
    return event_growth(spark, sf_dir)


@query("growth_trend_orders", "SELECT * REPLACE (period::TIMESTAMP AS period) FROM (" + _GROW.format(g="month", t="o_orderdate", b="8", f="orders") + ")")
def growth_trend_orders(spark, sf_dir):
    rows = zoo.table(spark, sf_dir, "orders").select("o_orderdate", F.lit(8).cast("long").alias("bytes"))
    return profile.growth(rows, "month", "o_orderdate").withColumn("period", F.col("period").cast("timestamp_ntz"))


def _projection_sql() -> str:
    from paramstore.queries import codecs

    ratio = "(SELECT sum(original)::BIGINT / sum(compressed)::BIGINT::DOUBLE FROM s WHERE method = '{}')"
    return f"WITH s AS (SELECT * FROM {codecs._sizes_sql()}) SELECT period::TIMESTAMP AS period, n, bytes, total_n, total_bytes, total_bytes / {ratio.format('hybrid')} AS bytes_hybrid, total_bytes / {ratio.format('unit')} AS bytes_packing FROM ({_DAYS})"


@query("growth_projection", _projection_sql())
def growth_projection(spark, sf_dir):
    """What the arrivals would take at the overall ratios that are measured on these tables."""
    from paramstore.queries import codecs

    rows = codecs.sizes_of_all(spark, sf_dir).where("method in ('hybrid', 'unit')").groupBy("method").agg((F.sum("original") / F.sum("compressed")).alias("cr")).collect()
    cr = {r.method: r.cr for r in rows}
    return profile.growth_projection(event_growth(spark, sf_dir), {"hybrid": cr["hybrid"], "packing": cr["unit"]})


@query("sample_zoo", P + "SELECT category, model_id, bytes FROM (SELECT *, row_number() OVER (PARTITION BY category ORDER BY sha256(model_id), model_id) AS k FROM m) WHERE k <= CASE category WHEN 'vectors' THEN 6 ELSE 3 END")
def sample_zoo(spark, sf_dir):
    """A balanced sample: so many models of each category, in hash order."""
    from pyspark.sql import Window as W

    ranked = models(spark, sf_dir).withColumn("k", F.row_number().over(W.partitionBy("category").orderBy(F.sha2("model_id", 256), "model_id")))
    return ranked.where(F.col("k") <= F.when(F.col("category") == "vectors", 6).otherwise(3)).select("category", "model_id", "bytes")
