"""Parameter redundancy and distance encoding."""

from pyspark.sql import functions as F

from paramstore.functions.bits import bit_length
from paramstore.operators import distance, redundancy
from paramstore.registry import query
from paramstore.sources import zoo

P = f"WITH p AS (SELECT * FROM {zoo.params_sql()}), c AS (SELECT model_id, dtype, bits, count(*) AS n FROM p GROUP BY ALL), d AS (SELECT model_id, dtype, CASE dtype WHEN 'float32' THEN 32 ELSE 64 END AS w, pos, pos - lag(pos) OVER (PARTITION BY model_id, dtype, bits ORDER BY pos) AS d FROM p), e AS (SELECT *, length(bin(d)) AS len FROM d) "
_RATIO = "SELECT model_id, dtype, sum(n)::BIGINT AS params, count(*) AS distinct_values, sum(CASE WHEN n > 1 THEN n ELSE 0 END)::BIGINT AS repeated, sum(CASE WHEN n > 1 THEN n ELSE 0 END)::BIGINT / sum(n)::BIGINT::DOUBLE AS ratio, 1.0::DOUBLE - count(*) / sum(n)::BIGINT::DOUBLE AS ratio_distinct FROM c GROUP BY ALL"


@query("param_duplication", P + _RATIO)
def param_duplication(spark, sf_dir):
    return redundancy.duplication(zoo.params(spark, sf_dir))


@query("param_duplication_cdf", P + f", r AS ({_RATIO}) SELECT model_id, ratio, cume_dist() OVER (ORDER BY ratio) AS cdf, " + ", ".join(f"(count(*) FILTER (WHERE ratio > {t}) OVER ()) / (count(*) OVER ())::DOUBLE AS over_{round(100 * t)}" for t in (0.5, 0.6, 0.99)) + " FROM r")
def param_duplication_cdf(spark, sf_dir):
    return redundancy.duplication_cdf(param_duplication(spark, sf_dir))


@query("dictionary_whatif", P + ", x AS (SELECT model_id, dtype, CASE dtype WHEN 'float32' THEN 32 ELSE 64 END AS w, sum(n)::BIGINT AS params, count(*) FILTER (WHERE n > 1) AS entries, coalesce(sum(n) FILTER (WHERE n > 1), 0)::BIGINT AS repeated FROM c GROUP BY ALL), y AS (SELECT *, (CASE WHEN entries > 1 THEN length(bin(entries - 1)) WHEN entries = 1 THEN 1 ELSE 0 END)::BIGINT AS code_bits FROM x) SELECT model_id, dtype, params, entries, repeated, repeated / nullif(entries, 0)::DOUBLE AS mean_repetition, code_bits, (entries * w + repeated * code_bits + (params - repeated) * w + params)::BIGINT AS bits FROM y")
def dictionary_whatif(spark, sf_dir):
    return redundancy.dictionary_whatif(zoo.params(spark, sf_dir))


@query("backref_profile", P + "SELECT model_id, dtype, count(*) AS params, count(d) AS repeats, avg(d) AS mean_distance, quantile_cont(d, 0.5)::DOUBLE AS median_distance, max(d) AS max_distance, count(*) FILTER (WHERE d <= 65536) / nullif(count(d), 0)::DOUBLE AS share_within FROM d GROUP BY ALL")
def backref_profile(spark, sf_dir):
    return redundancy.backref_profile(zoo.params(spark, sf_dir))


def _sizes_sql(used: str, extra: tuple[int, int] = (1, 6), source: str = "e") -> str:
    u = f"coalesce({used}, false)"
    return f"SELECT model_id, dtype, count(*) AS params, count(*) FILTER (WHERE {u}) AS repeats, sum(w)::BIGINT AS original, sum(CASE WHEN {u} THEN len + {extra[1]} ELSE w + {extra[0]} END)::BIGINT AS compressed FROM {source} GROUP BY ALL"


PRACTICAL, THEORETICAL = _sizes_sql("len <= 31"), _sizes_sql("len <= 31", (0, 0))


@query("de_practical", P + PRACTICAL)
def de_practical(spark, sf_dir):
    return distance.sizes(zoo.params(spark, sf_dir))


@query("de_theoretical", P + THEORETICAL)
def de_theoretical(spark, sf_dir):
    return distance.sizes(zoo.params(spark, sf_dir), overhead=False)


@query("de_savings", P + f", s AS (SELECT model_id, 1.0::DOUBLE - compressed / original::DOUBLE AS saving FROM ({PRACTICAL})) SELECT model_id, saving, cume_dist() OVER (ORDER BY saving) AS cdf, (count(*) FILTER (WHERE saving >= 0.1) OVER ()) / (count(*) OVER ())::DOUBLE AS share_saving, round(avg(saving) FILTER (WHERE saving >= 0.1) OVER (), 9) AS mean_saving FROM s")
def de_savings(spark, sf_dir):
    return distance.savings_cdf(de_practical(spark, sf_dir)).withColumn("mean_saving", F.round("mean_saving", 9))


_SEGMENT = "(SELECT * REPLACE (CASE WHEN pos // 4096 = (pos - d) // 4096 THEN len END AS len) FROM e)"


@query("de_variants", P + f"SELECT 'gated' AS variant, * FROM ({_sizes_sql('len <= 31 AND len + 5 < w')}) UNION ALL SELECT 'segmented', * FROM ({_sizes_sql('len <= 31', source=_SEGMENT)})")
def de_variants(spark, sf_dir):
    p = zoo.params(spark, sf_dir)
    gated = distance.sizes(p, gain_gate=True).withColumn("variant", F.lit("gated"))
    return gated.unionByName(distance.sizes(p, segment=4096).withColumn("variant", F.lit("segmented")))


@query("de_example", "SELECT length(bin(o_orderkey + 1))::BIGINT AS len, (6 + length(bin(o_orderkey + 1)))::BIGINT AS bits, min(o_orderkey + 1)::BIGINT AS least, max(o_orderkey + 1)::BIGINT AS most, count(*) AS n FROM orders GROUP BY 1, 2")
def de_example(spark, sf_dir):
    """What a repeat costs: an order's number is how many positions back the value was; by length, with the distances that have it."""
    d = (F.col("o_orderkey") + 1).cast("long")
    far = zoo.table(spark, sf_dir, "orders").select(d.alias("distance"))
    size = bit_length(F.col("distance"))
    return far.groupBy(size.alias("len"), (size + 6).alias("bits")).agg(F.min("distance").alias("least"), F.max("distance").alias("most"), F.count("*").alias("n"))


@query("de_roundtrip")
def de_roundtrip(spark, sf_dir):
    return distance.roundtrip(zoo.to_blocks(zoo.params(spark, sf_dir)))
