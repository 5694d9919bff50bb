"""Surrounding operators: joins, aggregates, windows, sets, functions, sources and sinks.

Where both engines read the same SQL, one text serves as query and oracle; Spark gets its tables by name as arguments.
"""

from __future__ import annotations

import re
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.operators import dedup, unitpack
from paramstore.registry import query
from paramstore.sources import zoo
from paramstore.sources.shared import shared_folder

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def run_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """text with {table} places, each a table of sf_dir."""
    return spark.sql(text, **{n: zoo.table(spark, sf_dir, n) for n in TABLES if f"{{{n}}}" in text})


def both(name: str, text: str, spark_hint: str = "", duck: str | None = None):
    """Register one SQL text for both engines; spark_hint goes after the first SELECT."""
    query(name, re.sub(r"\{(\w+)\}", r"\1", duck or text))(lambda spark, sf_dir: run_sql(spark, sf_dir, text.replace("SELECT", f"SELECT {spark_hint}", 1) if spark_hint else text))


both("join_broadcast", "SELECT n.n_name, count(*) AS customers, sum(8 * 1) AS bytes FROM {customer} c JOIN {nation} n ON c.c_nationkey = n.n_nationkey GROUP BY n.n_name".replace("sum(8 * 1)", "CAST(count(*) * 8 AS BIGINT)"), "/*+ BROADCAST(n) */")
both("join_sort_merge", "SELECT o.o_orderstatus, count(*) AS n, CAST(count(*) * 32 AS BIGINT) AS bytes FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderstatus", "/*+ MERGE(l, o) */")
_PRINTS = "SELECT doc_id, sha2(text, 256) AS fp FROM {documents}"
_DUCK_PRINTS = "SELECT doc_id, sha256(text) AS fp FROM {documents}"


def prints(name: str, text: str, hint: str = "") -> None:
    both(name, text.replace("PRINTS", f"({_PRINTS})"), hint, text.replace("PRINTS", f"({_DUCK_PRINTS})"))


prints("join_shuffle_hash", "SELECT a.doc_id, f.owner FROM PRINTS a JOIN (SELECT fp, min(doc_id) AS owner FROM PRINTS b GROUP BY fp) f ON a.fp = f.fp", "/*+ SHUFFLE_HASH(f) */")
prints("join_refs", "SELECT a.doc_id, f.owner, CASE WHEN a.doc_id = f.owner THEN 0 ELSE 1 END AS is_ref FROM PRINTS a JOIN (SELECT fp, min(doc_id) AS owner FROM PRINTS b GROUP BY fp) f ON a.fp = f.fp")
_SEMI = "SELECT a.doc_id FROM PRINTS a {} JOIN (SELECT fp FROM PRINTS b GROUP BY fp HAVING count(*) > 1) f ON a.fp = f.fp"
both("join_semi", _SEMI.format("LEFT SEMI").replace("PRINTS", f"({_PRINTS})"), duck=_SEMI.format("SEMI").replace("PRINTS", f"({_DUCK_PRINTS})"))
both("join_semi_in", "SELECT doc_id FROM {documents} WHERE doc_id IN (SELECT doc_id FROM {labels} WHERE quality = 1)")
prints("join_anti", "SELECT a.doc_id FROM PRINTS a WHERE NOT EXISTS (SELECT 1 FROM PRINTS b WHERE b.fp = a.fp AND b.doc_id <> a.doc_id)")
prints("new_layers", "SELECT a.doc_id FROM PRINTS a WHERE a.doc_id % 2 = 1 AND NOT EXISTS (SELECT 1 FROM PRINTS b WHERE b.fp = a.fp AND b.doc_id % 2 = 0)")
prints("self_join_shared_layers", "SELECT x.lang AS a, y.lang AS b, count(*) AS shared FROM (SELECT DISTINCT d.lang, p.fp FROM {documents} d JOIN PRINTS p ON d.doc_id = p.doc_id) x JOIN (SELECT DISTINCT d.source AS lang, p.fp FROM {documents} d JOIN PRINTS p ON d.doc_id = p.doc_id) y ON x.fp = y.fp GROUP BY x.lang, y.lang")
both("join_left_outer", "SELECT d.lang, count(*) AS documents, count(l.doc_id) AS labelled FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id GROUP BY d.lang")
both("join_full_outer", "SELECT count(*) AS n, count(a.k) AS a_side, count(b.k) AS b_side FROM (SELECT DISTINCT o_custkey AS k FROM {orders} WHERE o_orderstatus = 'F') a FULL OUTER JOIN (SELECT DISTINCT o_custkey AS k FROM {orders} WHERE o_orderstatus = 'O') b ON a.k = b.k")
both("join_theta", "SELECT e.lo, count(*) AS n FROM {lineitem} l JOIN (SELECT 0.0 AS lo, 0.02 AS hi UNION ALL SELECT 0.02, 0.05 UNION ALL SELECT 0.05, 1.0) e ON l.l_discount >= e.lo AND l.l_discount < e.hi GROUP BY e.lo".replace("0.0 AS lo, 0.02 AS hi", "CAST(0.0 AS DOUBLE) AS lo, CAST(0.02 AS DOUBLE) AS hi").replace("SELECT 0.02, 0.05", "SELECT CAST(0.02 AS DOUBLE), CAST(0.05 AS DOUBLE)").replace("SELECT 0.05, 1.0", "SELECT CAST(0.05 AS DOUBLE), CAST(1.0 AS DOUBLE)"))
_BLOCKS = "SELECT DISTINCT CAST(floor(event_id / 4096) AS BIGINT) AS block_no, CAST(floor(event_id / 4096) AS BIGINT) * 4096 AS first_pos FROM {events}"
both("join_range_block", f"SELECT b.block_no, count(*) AS n, min(e.event_id - b.first_pos) AS lo, max(e.event_id - b.first_pos) AS hi FROM {{events}} e JOIN ({_BLOCKS}) b ON CAST(floor(e.event_id / 4096) AS BIGINT) = b.block_no AND e.event_id >= b.first_pos AND e.event_id < b.first_pos + 4096 GROUP BY b.block_no")
both("pos_to_block", f"SELECT e.event_id, b.block_no FROM {{events}} e JOIN ({_BLOCKS}) b ON CAST(floor(e.event_id / 4096) AS BIGINT) = b.block_no AND e.event_id >= b.first_pos AND e.event_id < b.first_pos + 4096 WHERE e.event_type = 'purchase'")


@query("join_interval_events", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000")
def join_interval_events(spark, sf_dir):
    """Pairs of one user's events within ten minutes: equal user and time bin, neighbouring bins by a doubled side, then the residual."""
    e = zoo.table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    bin_ = F.floor(F.col("us") / 600_000_000)
    a = e.withColumn("bin", F.explode(F.array(bin_ - 1, bin_, bin_ + 1))).alias("a")
    b = e.withColumn("bin", bin_).alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.bin") == F.col("b.bin")) & (F.col("a.event_id") < F.col("b.event_id"))
    return a.join(b, on).where(F.abs(F.col("a.us") - F.col("b.us")) <= 600_000_000).select(F.col("a.event_id").alias("first_id"), F.col("b.event_id").alias("second_id"))


@query("join_asof_events", "SELECT event_id, v FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS v FROM events) WHERE event_type = 'purchase'")
def join_asof_events(spark, sf_dir):
    """For each purchase the user's last view before it."""
    e = zoo.table(spark, sf_dir, "events")
    before = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return e.select("event_id", "event_type", seen.alias("v")).where("event_type = 'purchase'").select("event_id", "v")


@query("asof_version", "SELECT o_custkey, max_by(o_orderkey, (o_orderdate, o_orderkey)) AS version FROM orders WHERE o_orderdate <= TIMESTAMP '1996-01-01' GROUP BY 1")
def asof_version(spark, sf_dir):
    o = zoo.table(spark, sf_dir, "orders").where(F.col("o_orderdate") <= F.lit("1996-01-01").cast("timestamp_ntz"))
    return o.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("version"))


both("join_lateral", "SELECT n.n_name, t.c_custkey FROM {nation} n CROSS JOIN LATERAL (SELECT c.c_custkey FROM {customer} c WHERE c.c_nationkey = n.n_nationkey ORDER BY c.c_acctbal DESC, c.c_custkey LIMIT 3) t".replace("CROSS JOIN LATERAL (", "JOIN LATERAL (").replace(") t", ") t ON true"))


@query("pair_similarity", "SELECT vec_id AS a, other AS b, round(list_sum(list_transform(range(64), lambda i: embedding[i + 1]::DOUBLE * next[i + 1]::DOUBLE)), 6) AS dot FROM (SELECT *, lead(vec_id) OVER w AS other, lead(embedding) OVER w AS next FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY vec_id)) WHERE other IS NOT NULL")
def pair_similarity(spark, sf_dir):
    """Every vector with the next one of its label: a chain through each bucket, so that pairs are as many as vectors."""
    v = zoo.ranked(zoo.table(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("e")), "label", "vec_id", [])
    dot = F.aggregate(F.zip_with("a.e", "b.e", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    pairs = v.alias("a").join(v.alias("b"), (F.col("a.label") == F.col("b.label")) & (F.col("a.rank") + 1 == F.col("b.rank")))
    return pairs.select(F.col("a.vec_id").alias("a"), F.col("b.vec_id").alias("b"), F.round(dot, 6).alias("dot"))


both("subquery_scalar", "SELECT doc_id, n_chars FROM {documents} WHERE n_chars > (SELECT avg(n_chars) * 3 FROM {documents})")
both("subquery_exists", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
both("subquery_in", "SELECT o_orderkey FROM {orders} WHERE o_orderkey IN (SELECT l_orderkey FROM {lineitem} WHERE l_discount > 0.09 AND l_quantity > 45)")
both("agg_partial_final", "SELECT l_returnflag, count(*) AS n, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, round(avg(l_extendedprice), 4) AS mean, round(stddev_pop(l_discount), 6) AS sd FROM {lineitem} GROUP BY l_returnflag")
both("agg_distinct_multi", "SELECT l_returnflag, count(DISTINCT l_discount) AS discounts, count(DISTINCT l_tax) AS taxes, count(DISTINCT l_partkey) AS parts FROM {lineitem} GROUP BY l_returnflag")
both("agg_filter", "SELECT event_type, count(*) AS n, count(*) FILTER (WHERE value > -1 AND value < 1) AS in_unit FROM {events} GROUP BY event_type")
both("agg_percentile", "SELECT lang, percentile(n_chars, 0.5) AS p50, percentile(n_chars, 0.75) AS p75, percentile(n_chars, 0.9) AS p90 FROM {documents} GROUP BY lang", duck="SELECT lang, quantile_cont(n_chars, 0.5)::DOUBLE AS p50, quantile_cont(n_chars, 0.75)::DOUBLE AS p75, quantile_cont(n_chars, 0.9)::DOUBLE AS p90 FROM {documents} GROUP BY lang")
both("agg_mode_top", "SELECT l_returnflag, l_quantity, n FROM (SELECT l_returnflag, l_quantity, count(*) AS n, row_number() OVER (PARTITION BY l_returnflag ORDER BY count(*) DESC, l_quantity) AS r FROM {lineitem} GROUP BY l_returnflag, l_quantity) t WHERE r = 1")
both("agg_grouping_sets", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, CAST(grouping(lang) AS INT) AS g1, CAST(grouping(source) AS INT) AS g2 FROM {documents} GROUP BY GROUPING SETS ((lang, source), (lang), ())")
both("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)")
both("agg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)")
prints("dup_cube", "SELECT d.lang, d.source, count(*) AS n, count(*) - count(DISTINCT p.fp) AS removable FROM {documents} d JOIN PRINTS p ON d.doc_id = p.doc_id GROUP BY CUBE (lang, source)".replace("CUBE (lang, source)", "CUBE (d.lang, d.source)"))
both("agg_listagg", "SELECT c_nationkey, sha2(listagg(CAST(c_custkey AS STRING), ',') WITHIN GROUP (ORDER BY c_custkey), 256) AS digest FROM {customer} GROUP BY c_nationkey", duck="SELECT c_nationkey, sha256(string_agg(c_custkey::VARCHAR, ',' ORDER BY c_custkey)) AS digest FROM {customer} GROUP BY c_nationkey")
both("distinct_params", "SELECT count(DISTINCT l_extendedprice) AS prices, count(DISTINCT l_discount) AS discounts FROM {lineitem}")


@query("distinct_params_approx")
def distinct_params_approx(spark, sf_dir):
    return zoo.table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_extendedprice", 0.02).alias("prices"), F.approx_count_distinct("l_discount", 0.02).alias("discounts"))


@query("agg_hll")
def agg_hll(spark, sf_dir):
    e = zoo.table(spark, sf_dir, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s"))
    return e.select("event_type", F.hll_sketch_estimate("s").alias("users"))


@query("agg_kll")
def agg_kll(spark, sf_dir):
    return zoo.table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.expr("kll_sketch_agg_double(l_extendedprice)").alias("s")).select("l_returnflag", F.expr("kll_sketch_get_quantile_double(s, 0.5D)").alias("median"))


@query("agg_theta")
def agg_theta(spark, sf_dir):
    """Overlap of the customers of two statuses."""
    o = zoo.table(spark, sf_dir, "orders").groupBy().agg(F.expr("theta_sketch_agg(CASE WHEN o_orderstatus = 'F' THEN o_custkey END)").alias("a"), F.expr("theta_sketch_agg(CASE WHEN o_orderstatus = 'O' THEN o_custkey END)").alias("b"))
    return o.select(F.expr("theta_sketch_estimate(theta_intersection(a, b))").alias("shared"), F.expr("theta_sketch_estimate(theta_union(a, b))").alias("all_customers"))


_B = "CAST({} AS BIGINT)".format
both("win_rank", "SELECT doc_id, " + ", ".join(f"{_B(f + ' OVER w')} AS {n}" for f, n in (("rank()", "r"), ("dense_rank()", "dr"))) + ", CAST(row_number() OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS BIGINT) AS rn, CAST(ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS BIGINT) AS quartile, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM {documents} WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")


@query("win_lag_xor", "WITH x AS (SELECT event_type, event_id, xor(value::BIT::BIGINT, lag(value::BIT::BIGINT) OVER (PARTITION BY event_type ORDER BY event_id)) AS x FROM events) SELECT event_type, event_id, CASE WHEN x = 0 THEN 64 ELSE 64 - length(bin(x)) END::BIGINT AS leading FROM x WHERE x IS NOT NULL")
def win_lag_xor(spark, sf_dir):
    from paramstore.operators import codecs

    p = zoo.params(spark, sf_dir, ("event",)).withColumn("event_type", F.substring("model_id", 7, 100))
    ids = zoo.ranked(zoo.table(spark, sf_dir, "events").select("event_type", "event_id"), "event_type", "event_id", []).select("event_type", "event_id", F.col("rank").alias("pos"))
    rows, over = codecs.halo(p, 1)
    x = rows.withColumn("x", codecs.unsigned_xor(rows, over)).where("not halo and x is not null")
    return x.join(ids, ["event_type", "pos"]).select("event_type", "event_id", codecs.leading(F.col("x"), F.lit(64)).cast("long").alias("leading"))


both("win_rows_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 63 PRECEDING AND CURRENT ROW), 9) AS mean64 FROM {events}")
both("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT event_id, user_id, unix_seconds(CAST(ts AS TIMESTAMP)) AS s FROM {events}) t", duck="SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT event_id, user_id, floor(epoch(ts))::BIGINT AS s FROM {events}) t")
both("win_first_last", "SELECT l_discount, CAST(floor(l_orderkey / 4096) AS BIGINT) AS block_no, min(l_orderkey) AS first_key, max(l_orderkey) AS last_key, count(*) AS n FROM {lineitem} GROUP BY l_discount, CAST(floor(l_orderkey / 4096) AS BIGINT)")
both("win_running_share", "SELECT lang, CAST(b AS BIGINT) AS b, CAST(sum(b) OVER (ORDER BY b DESC, lang ROWS UNBOUNDED PRECEDING) AS DOUBLE) / sum(b) OVER () AS share FROM (SELECT lang, CAST(sum(n_chars) AS BIGINT) AS b FROM {documents} GROUP BY lang) t")
both("sort_global", "SELECT lang, n FROM (SELECT lang, count(*) AS n FROM {documents} GROUP BY lang) t ORDER BY n DESC, lang")
both("limit_offset", "SELECT doc_id, n_chars FROM {documents} ORDER BY n_chars DESC, doc_id LIMIT 10 OFFSET 20")
both("top_layers", "SELECT doc_id, n_chars FROM {documents} ORDER BY n_chars DESC, doc_id LIMIT 20")
both("topk_per_group", "SELECT lang, doc_id, n_chars FROM (SELECT lang, doc_id, n_chars, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM {documents}) t WHERE r <= 3")
both("top_values", "SELECT l_returnflag, l_discount, n FROM (SELECT *, row_number() OVER (PARTITION BY l_returnflag ORDER BY n DESC, l_discount) AS r FROM (SELECT l_returnflag, l_discount, count(*) AS n FROM {lineitem} GROUP BY l_returnflag, l_discount) t) u WHERE r <= 3")
_SET_A, _SET_B = "SELECT o_custkey AS k FROM {orders} WHERE o_orderstatus = 'F'", "SELECT o_custkey AS k FROM {orders} WHERE o_orderstatus = 'O'"
for _name, _op in (("set_union_all", "UNION ALL"), ("set_union", "UNION"), ("set_intersect", "INTERSECT"), ("set_except", "EXCEPT"), ("set_except_all", "EXCEPT ALL")):
    both(_name, f"SELECT k, count(*) AS n FROM (({_SET_A}) {_op} ({_SET_B})) t GROUP BY k")


def _long_sizes(spark, sf_dir):
    from paramstore.registry import QUERIES

    out = None
    for name in ("unit_sizes", "half_sizes", "prune_1x"):
        own = QUERIES[name](spark, sf_dir).select("model_id", F.lit(name).alias("codec"), "compressed")
        out = own if out is None else out.union(own)
    return out


def _wide_sql() -> str:
    from paramstore.registry import ORACLES

    return "SELECT a.model_id, a.compressed AS unit_sizes, b.compressed AS half_sizes, c.compressed AS prune_1x FROM (" + ORACLES["unit_sizes"] + ") a JOIN (" + ORACLES["half_sizes"] + ") b USING (model_id) JOIN (" + ORACLES["prune_1x"] + ") c USING (model_id)"


def _pivot(spark, sf_dir):
    return _long_sizes(spark, sf_dir).groupBy("model_id").pivot("codec", ["unit_sizes", "half_sizes", "prune_1x"]).agg(F.first("compressed"))


def _unpivot(spark, sf_dir):
    return _pivot(spark, sf_dir).unpivot("model_id", ["unit_sizes", "half_sizes", "prune_1x"], "codec", "compressed")


def _register_pivots() -> None:
    from paramstore.queries import codecs, pipeline  # noqa: F401  their oracles come first

    wide = _wide_sql()
    query("pivot_codec", wide)(_pivot)
    query("unpivot_codec", f"SELECT model_id, codec, compressed FROM ({wide}) UNPIVOT (compressed FOR codec IN (unit_sizes, half_sizes, prune_1x))")(_unpivot)


_register_pivots()
both("str_bytes", "SELECT lang, CAST(sum(octet_length(text)) AS BIGINT) AS bytes, CAST(sum(length(text)) AS BIGINT) AS chars FROM {documents} GROUP BY lang", duck="SELECT lang, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes, CAST(sum(length(text)) AS BIGINT) AS chars FROM {documents} GROUP BY lang")
both("str_regex", "SELECT regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, count(*) AS n FROM {pages} GROUP BY 1")
both("str_split_lines", "SELECT doc_id, count(*) AS line_count, count(*) - count(DISTINCT line) AS repeated FROM (SELECT doc_id, explode(split(text, '\\n')) AS line FROM {documents}) t GROUP BY doc_id", duck="SELECT doc_id, count(*) AS line_count, count(*) - count(DISTINCT line) AS repeated FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM {documents}) t GROUP BY doc_id")
both("date_trunc_month", "SELECT CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS m, count(*) AS n FROM {orders} GROUP BY 1")
both("date_diff_days", "SELECT CAST(datediff(l.l_shipdate, o.o_orderdate) AS BIGINT) AS days, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY 1", duck="SELECT CAST(date_diff('day', o.o_orderdate::DATE, l.l_shipdate::DATE) AS BIGINT) AS days, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY 1")
both("date_parts", "SELECT CAST(year(ts) AS BIGINT) AS y, CAST(month(ts) AS BIGINT) AS m, CAST(hour(ts) AS BIGINT) AS h, count(*) AS n FROM {events} GROUP BY 1, 2, 3")


@query("math_bits", "SELECT event_id, CASE WHEN b < 0 THEN 1 ELSE 0 END::BIGINT AS sign, ((b >> 52) & 2047)::BIGINT AS exponent, b & 4503599627370495 AS mantissa FROM (SELECT event_id, value::BIT::BIGINT AS b FROM events)")
def math_bits(spark, sf_dir):
    from paramstore.functions.bits import with_bits

    e = with_bits(zoo.table(spark, sf_dir, "events").select("event_id", "value", F.lit("float64").alias("dtype")))
    b = F.col("bits")
    return e.select("event_id", F.when(b < 0, 1).otherwise(0).cast("long").alias("sign"), F.shiftright(b, 52).bitwiseAND(F.lit(2047)).cast("long").alias("exponent"), b.bitwiseAND(F.lit((1 << 52) - 1)).alias("mantissa"))


_EMB = "embeddings"


@query("arr_transform", "SELECT vec_id, list_transform(embedding, lambda x: (((1::FLOAT + abs(x)) - 1::FLOAT)::DOUBLE * 8388608)::BIGINT) AS codes FROM embeddings")
def arr_transform(spark, sf_dir):
    one = F.lit(1.0).cast("float")
    return zoo.table(spark, sf_dir, _EMB).select("vec_id", F.transform("embedding", lambda x: ((((one + F.abs(x)) - one).cast("double")) * 8388608.0).cast("long")).alias("codes"))


both("arr_zip_xor", "SELECT doc_id, zip_with(array(doc_id, n_chars), array(n_chars, 7), (a, b) -> a ^ b) AS x FROM {documents}", duck="SELECT doc_id, [xor(doc_id, n_chars), xor(n_chars, 7)] AS x FROM {documents}")


@query("arr_aggregate", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm FROM embeddings")
def arr_aggregate(spark, sf_dir):
    return zoo.table(spark, sf_dir, _EMB).select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")), 6).alias("norm"))


@query("arr_slice_sample", "SELECT vec_id, list_transform(range(2), lambda i: embedding[32 * i + 1]) AS sample FROM embeddings")
def arr_slice_sample(spark, sf_dir):
    return zoo.table(spark, sf_dir, _EMB).select("vec_id", F.filter("embedding", lambda x, i: i % 32 == 0).alias("sample"))


both("arr_filter_out_of_unit", "SELECT o_orderkey, size(filter(array(o_totalprice, 0.5D), x -> abs(x) >= 1)) AS n FROM {orders}".replace("size(", "CAST(size(").replace(") AS n", ") AS BIGINT) AS n"), duck="SELECT o_orderkey, len(list_filter([o_totalprice, 0.5::DOUBLE], lambda x: abs(x) >= 1))::BIGINT AS n FROM {orders}")
both("map_props", "SELECT event_id, from_json(props, 'map<string,int>')['k'] AS k FROM {events}", duck="SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM {events}")
both("json_get", "SELECT CAST(get_json_object(props, '$.k') AS INT) AS k, count(*) AS n FROM {events} GROUP BY 1", duck="SELECT json_extract_string(props, '$.k')::INTEGER AS k, count(*) AS n FROM {events} GROUP BY 1")


@query("dot_topk", "WITH q AS (SELECT vec_id AS q, embedding AS e FROM embeddings WHERE vec_id % 50 = 0), s AS (SELECT q, vec_id, round(list_sum(list_transform(range(64), lambda i: e[i + 1]::DOUBLE * embedding[i + 1]::DOUBLE)) / sqrt(list_sum(list_transform(e, lambda x: x::DOUBLE * x::DOUBLE)) * list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS cosine FROM q, embeddings WHERE vec_id <> q) SELECT q, vec_id, cosine FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY cosine DESC, vec_id) AS r FROM s) WHERE r <= 5")
def dot_topk(spark, sf_dir):
    """The five nearest of all vectors to every vector whose id is divisible by 50, the queries in blocks that all vectors meet."""
    v = zoo.table(spark, sf_dir, _EMB).select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    unit = v.withColumn("norm", F.sqrt(dot("e", "e")))
    asked = unit.where("vec_id % 50 = 0")
    blocks = -(-max(asked.count(), 1) // 1000)
    q = asked.select(F.col("vec_id").alias("q"), F.col("e").alias("qe"), F.col("norm").alias("qn"), F.pmod(F.col("vec_id") / 50, F.lit(blocks)).cast("int").alias("block"))
    s = unit.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).join(q, "block").where("vec_id <> q").select("q", "vec_id", F.round(dot("qe", "e") / F.sqrt(F.pow("qn", F.lit(2.0)) * F.pow("norm", F.lit(2.0))), 6).alias("cosine"))
    return s.withColumn("r", F.row_number().over(W.partitionBy("q").orderBy(F.desc("cosine"), "vec_id"))).where("r <= 5").drop("r")


both("filter_in_unit", "SELECT event_id, value FROM {events} WHERE value > -1 AND value < 1")
both("scan_zoo", "SELECT 'lineitem' AS t, count(*) AS n FROM {lineitem} UNION ALL SELECT 'embeddings', count(*) FROM {embeddings} UNION ALL SELECT 'events', count(*) FROM {events} UNION ALL SELECT 'documents', count(*) FROM {documents}")


@query("sql_surface", "SELECT count(*) AS n, CAST(sum((((1::FLOAT + abs(x)) - 1::FLOAT)::DOUBLE * 8388608)::BIGINT) AS BIGINT) AS codes FROM (SELECT unnest(embedding) AS x FROM embeddings)")
def sql_surface(spark, sf_dir):
    """Packing as a SQL function, whose body the analyzer expands to plain arithmetic."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION unit_mantissa(x FLOAT) RETURNS BIGINT RETURN CAST(CAST((1.0F + abs(x)) - 1.0F AS DOUBLE) * 8388608D AS BIGINT)")
    return spark.sql("SELECT count(*) AS n, sum(unit_mantissa(x)) AS codes FROM (SELECT explode(embedding) AS x FROM {e})", e=zoo.table(spark, sf_dir, _EMB))


@query("sql_functions", "SELECT event_id, code, (code & 4503599627370495) / 4503599627370496::DOUBLE * CASE WHEN code & 4503599627370496 <> 0 THEN -1 ELSE 1 END AS back, (6 + length(bin(event_id + 1)))::BIGINT AS bits FROM (SELECT event_id, (((1::DOUBLE + abs(value)) - 1::DOUBLE) * 4503599627370496)::BIGINT + CASE WHEN value < 0 THEN 4503599627370496 ELSE 0 END AS code FROM events WHERE value > -1 AND value < 1)")
def sql_functions(spark, sf_dir):
    """Packing, unpacking and the size of a distance as SQL functions of one session, expanded to plain expressions."""
    for body in (
        "unit_code(x DOUBLE) RETURNS BIGINT RETURN CAST(((1D + abs(x)) - 1D) * 4503599627370496D AS BIGINT) + CASE WHEN x < 0 THEN 4503599627370496 ELSE 0 END",
        "unit_value(c BIGINT) RETURNS DOUBLE RETURN (c & 4503599627370495) / 4503599627370496D * CASE WHEN (c & 4503599627370496) <> 0 THEN -1 ELSE 1 END",
        "distance_bits(d BIGINT) RETURNS BIGINT RETURN CAST(6 + length(bin(d)) AS BIGINT)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")
    return spark.sql("SELECT event_id, unit_code(value) AS code, unit_value(unit_code(value)) AS back, distance_bits(event_id + 1) AS bits FROM {e} WHERE value > -1 AND value < 1", e=zoo.table(spark, sf_dir, "events"))


@query("udf_bits", "SELECT event_id, value::BIT::BIGINT AS bits FROM events")
def udf_bits(spark, sf_dir):
    @F.pandas_udf("long")
    def fp_bits(v: pd.Series) -> pd.Series:
        return pd.Series(v.to_numpy("float64").view("int64"))

    return zoo.table(spark, sf_dir, "events").select("event_id", fp_bits("value").alias("bits"))


@query("udaf_entropy", "WITH c AS (SELECT event_type, floor(value / 10) AS b, count(*) AS n FROM events GROUP BY ALL) SELECT event_type, round(-sum(n / t::DOUBLE * log2(n / t::DOUBLE)), 6) AS entropy FROM (SELECT *, sum(n) OVER (PARTITION BY event_type) AS t FROM c) GROUP BY event_type")
def udaf_entropy(spark, sf_dir):
    @F.pandas_udf("double")
    def entropy(n: pd.Series) -> float:
        p = n.to_numpy(float) / n.sum()
        return float(-(p * np.log2(p)).sum())

    c = zoo.table(spark, sf_dir, "events").groupBy("event_type", F.floor(F.col("value") / 10).alias("b")).count()  # histograms: small groups
    return c.groupBy("event_type").agg(F.round(entropy("count"), 6).alias("entropy"))


@query("udtf_chunks")
def udtf_chunks(spark, sf_dir):
    @F.udtf(returnType="chunk_no: int, len: int")
    class GearChunks:
        def eval(self, payload: bytes):
            start = 0
            for no, end in enumerate(dedup.gear_cuts(np.frombuffer(payload or b"", np.uint8), 128, 1024, 131_072)):
                yield no, end - start
                start = end

    spark.udtf.register("gear_chunks", GearChunks)
    return spark.sql("SELECT d.doc_id, c.chunk_no, c.len FROM {docs} d, LATERAL gear_chunks(encode(d.text, 'UTF-8')) c", docs=zoo.table(spark, sf_dir, "documents"))


@query("udf_from_bits", "SELECT event_id, value AS back, value::BIT::BIGINT AS bits FROM events")
def udf_from_bits(spark, sf_dir):
    """The inverse of udf_bits."""
    @F.pandas_udf("long")
    def fp_bits(v: pd.Series) -> pd.Series:
        return pd.Series(v.to_numpy("float64").view("int64"))

    @F.pandas_udf("double")
    def fp_from_bits(b: pd.Series) -> pd.Series:
        return pd.Series(b.to_numpy("int64").view("float64"))

    return zoo.table(spark, sf_dir, "events").select("event_id", fp_bits("value").alias("bits")).withColumn("back", fp_from_bits("bits"))


@query("udf_half_bits")
def udf_half_bits(spark, sf_dir):
    """Patterns of values cast to 16 bits."""
    @F.pandas_udf("int")
    def half_bits(v: pd.Series) -> pd.Series:
        with np.errstate(over="ignore"):
            return pd.Series(v.to_numpy("float64").astype(np.float16).view(np.uint16).astype(np.int32))

    return zoo.table(spark, sf_dir, "events").select("event_id", "value", half_bits("value").alias("half"))


@query("udtf_unpack", "SELECT vec_id, i, (((1::FLOAT + abs(x)) - 1::FLOAT)::DOUBLE * CASE WHEN signbit(x) THEN -1 ELSE 1 END) AS value FROM (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings)")
def udtf_unpack(spark, sf_dir):
    """Packed vectors as rows of their values."""
    from paramstore.functions.bits import values_of

    @F.udtf(returnType="i: bigint, value: double")
    class Unpack:
        def eval(self, data: bytes):
            yield from enumerate(values_of(unitpack.unpack(data, "float32"), "float32").astype(float).tolist())

    @F.pandas_udf("binary")
    def packed(v: pd.Series) -> pd.Series:
        return v.map(lambda x: unitpack.pack(np.asarray(x, np.float32).view(np.int32), "float32"))

    spark.udtf.register("unpack_unit", Unpack)
    vectors = zoo.table(spark, sf_dir, _EMB).select("vec_id", packed("embedding").alias("data"))
    return spark.sql("SELECT v.vec_id, u.i, u.value FROM {v} v, LATERAL unpack_unit(v.data) u", v=vectors)


@query("scan_flat_arrays", "SELECT label, count(*) AS layers, sum(len(embedding))::BIGINT AS params, round(sum(list_sum(list_transform(embedding, lambda x: x::DOUBLE))), 6) AS total FROM embeddings GROUP BY label")
def scan_flat_arrays(spark, sf_dir):
    """Flat files of numbers, as weights are kept: written a file for some vectors, read back as binary files with the shape in the name."""
    from paramstore.sources import flat

    path = shared_folder(spark, "flat")
    flat.write(zoo.vector_layers(spark, sf_dir).select("layer_id", "dtype", "payload"), path)
    layers = flat.read(spark, path).withColumn("label", F.regexp_extract("layer_id", "vec:([0-9-]+)[.]", 1).cast("int"))
    each = layers.select("label", "layer_id", F.posexplode("values").alias("i", "x"))
    return each.groupBy("label").agg(F.count_distinct("layer_id").alias("layers"), F.count("*").alias("params"), F.round(F.sum("x"), 6).alias("total"))


@query("scan_configs", "SELECT event_type, count(*) AS n, count(json_extract_string(props, '$.k')) AS with_k, max(json_extract_string(props, '$.k')::INTEGER) AS most_k FROM events GROUP BY event_type")
def scan_configs(spark, sf_dir):
    """Model configurations as JSON lines with a stated schema: what does not parse is null, not an error."""
    path = shared_folder(spark, "configs")
    zoo.table(spark, sf_dir, "events").select(F.to_json(F.struct("event_type", F.col("props").alias("config"))).alias("value")).write.text(path)
    rows = spark.read.schema("event_type string, config string").option("mode", "PERMISSIVE").json(path)
    k = F.from_json("config", "k int")["k"]
    return rows.groupBy("event_type").agg(F.count("*").alias("n"), F.count(k).alias("with_k"), F.max(k).alias("most_k"))


@query("sink_roundtrip")
def sink_roundtrip(spark, sf_dir):
    path = shared_folder(spark, "sink")
    zoo.to_blocks(zoo.params(spark, sf_dir)).write.option("compression", "zstd").parquet(path)
    return spark.read.parquet(path).groupBy("model_id", "dtype").agg(F.count("*").alias("blocks"), F.sum("n").alias("params"), F.sum(F.length("payload")).alias("bytes"))


@query("sink_partitioned")
def sink_partitioned(spark, sf_dir):
    path = shared_folder(spark, "sink")
    zoo.to_blocks(zoo.params(spark, sf_dir)).write.partitionBy("category").parquet(path)
    return spark.read.parquet(path).groupBy("category", "model_id").agg(F.sum("n").alias("params"))


@query("sink_bucketed")
def sink_bucketed(spark, sf_dir):
    name = f"prints_{uuid.uuid4().hex[:12]}"
    dedup.fingerprint(zoo.byte_layers(spark, sf_dir)).write.bucketBy(8, "fp").sortBy("fp").mode("overwrite").saveAsTable(name)
    return spark.table(name).groupBy("fp").agg(F.count("*").alias("n")).agg(F.count("*").alias("prints"), F.max("n").alias("most"))


both("store_manifest", "SELECT lang AS part, count(*) AS layers, CAST(sum(octet_length(text)) AS BIGINT) AS bytes, CAST(min(octet_length(text)) AS BIGINT) AS least, CAST(max(octet_length(text)) AS BIGINT) AS most FROM {documents} GROUP BY lang", duck="SELECT lang AS part, count(*) AS layers, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes, CAST(min(octet_length(encode(text))) AS BIGINT) AS least, CAST(max(octet_length(encode(text))) AS BIGINT) AS most FROM {documents} GROUP BY lang")


@query("pushdown_probe")
def pushdown_probe(spark, sf_dir):
    """What of the unit test reaches the scan: the plain comparisons in PushedFilters, two columns in ReadSchema; n rows pass it."""
    rows = zoo.table(spark, sf_dir, "events").where(unitpack.packable(F.col("value"), F.lit("float64"))).select("event_id", "value")
    plan = rows._jdf.queryExecution().executedPlan().toString()
    pushed, read = re.search(r"PushedFilters: \[([^\]]*)", plan), re.search(r"ReadSchema: (\S+)", plan)
    said = [F.lit(found[1] if found else "").alias(name) for found, name in ((pushed, "pushed"), (read, "read_schema"))]
    return rows.agg(F.count(F.struct("event_id", "value")).alias("n")).select(*said, "n")


@query("scan_files")
def scan_files(spark, sf_dir):
    """Weight files as binary files, by pattern."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load(f"{sf_dir}/embeddings.parquet")
    return files.select(F.regexp_extract("path", r"([^/]+)$", 1).alias("name"), "length", F.sha2("content", 256).alias("fp"))
