"""Layer and chunk duplication and similarity."""

from pyspark.sql import functions as F

from paramstore.operators import dedup, similarity
from paramstore.registry import query
from paramstore.sources import zoo

DOC = zoo.BYTES_SQL["documents"]
PAGE = zoo.BYTES_SQL["pages"]
_DUP = "SELECT dtype, sum(n)::BIGINT AS units, count(*) AS distinct_units, sum(n * len)::BIGINT AS bytes, sum((n - 1) * len)::BIGINT AS removable, sum(CASE WHEN n > 1 THEN n * len ELSE 0 END)::BIGINT AS member FROM (SELECT dtype, fp, count(*) AS n, max(len) AS len FROM u GROUP BY 1, 2) GROUP BY 1"
_LAYER = "SELECT model_id, layer_id, dtype, sha256(text) AS fp, octet_length(encode(text)) AS len FROM {f}"
_CHUNK = "SELECT model_id, layer_id, dtype, substr(h, 2 * {k} * i + 1, 2 * {k}) AS fp, length(substr(h, 2 * {k} * i + 1, 2 * {k})) // 2 AS len FROM (SELECT *, unnest(range((length(h) // 2 + {k} - 1) // {k})) AS i FROM (SELECT *, hex(encode(text)) AS h FROM {f}))"
P = zoo.params_sql(("vec", "tuned", "line"))


def both(spark, sf_dir):
    return zoo.byte_layers(spark, sf_dir).union(zoo.byte_layers(spark, sf_dir, "pages"))


def fixed(f: str, k: int) -> str:
    return f"WITH u AS ({_CHUNK.format(f=f, k=k)}) {_DUP}"


@query("layer_dedup", f"WITH u AS ({_LAYER.format(f=DOC)}) {_DUP}")
def layer_dedup(spark, sf_dir):
    return dedup.duplicates(dedup.fingerprint(zoo.byte_layers(spark, sf_dir)))


@query("layer_dedup_floats", f"WITH u AS (SELECT layer_id, dtype, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) AS fp, count(*) * CASE dtype WHEN 'float32' THEN 4 ELSE 8 END AS len FROM {P} GROUP BY layer_id, dtype) {_DUP}")
def layer_dedup_floats(spark, sf_dir):
    """Float layers: prints of all bits (stride 1)."""
    units = similarity.sampled(zoo.params(spark, sf_dir, ("vec", "tuned", "line")), stride=1)
    return dedup.duplicates(units.withColumn("len", F.col("n") * F.when(F.col("dtype") == "float32", 4).otherwise(8)))


_EVERY = zoo.params_sql(("vec", "tuned", "line", "part", "supp", "key", "posid"))


@query("layer_dedup_dtypes", f"WITH u AS (SELECT layer_id, dtype, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) AS fp, count(*) * CASE dtype WHEN 'float32' THEN 4 ELSE 8 END AS len FROM {_EVERY} GROUP BY layer_id, dtype) {_DUP}")
def layer_dedup_dtypes(spark, sf_dir):
    """Duplicate layers by dtype over floats and integers: position indexes are nearly all copies."""
    units = similarity.sampled(zoo.params(spark, sf_dir, ("vec", "tuned", "line", "part", "supp", "key", "posid")), stride=1)
    return dedup.duplicates(units.withColumn("len", F.col("n") * F.when(F.col("dtype") == "float32", 4).otherwise(8)))


for _k in (4096, 512):

    @query(f"fsc_{_k}", fixed(DOC, _k))
    def _fsc(spark, sf_dir, k=_k):
        return dedup.duplicates(dedup.fixed_chunks(zoo.byte_layers(spark, sf_dir), k))

    @query(f"fsc_{_k}_pages", fixed(PAGE, _k))
    def _fsc_pages(spark, sf_dir, k=_k):
        return dedup.duplicates(dedup.fixed_chunks(zoo.byte_layers(spark, sf_dir, "pages"), k))


@query("cdc_gear")
def cdc_gear(spark, sf_dir):
    return dedup.duplicates(dedup.gear_chunks(both(spark, sf_dir), 128, 1024, 131_072), "model_id")


@query("chunking_compare")
def chunking_compare(spark, sf_dir):
    return dedup.compare(both(spark, sf_dir))


@query("dedup_conventions", f"WITH u AS ({_LAYER.format(f=DOC)}), d AS ({_DUP}) SELECT 'removable' AS convention, removable AS bytes, removable / bytes::DOUBLE AS share FROM d UNION ALL SELECT 'member', member, member / bytes::DOUBLE FROM d")
def dedup_conventions(spark, sf_dir):
    d = layer_dedup(spark, sf_dir)
    pick = F.explode(F.array(*[F.struct(F.lit(c).alias("convention"), F.col(c).alias("b")) for c in ("removable", "member")])).alias("x")
    return d.select("bytes", pick).select("x.convention", F.col("x.b").alias("bytes"), (F.col("x.b") / F.col("bytes")).alias("share"))


@query("incremental_dedup", f"WITH u AS ({_LAYER.format(f=DOC)}), s AS (SELECT DISTINCT fp FROM u WHERE CAST(substr(layer_id, 5) AS BIGINT) % 2 = 0), x AS (SELECT DISTINCT fp, len FROM u WHERE CAST(substr(layer_id, 5) AS BIGINT) % 2 = 1) SELECT count(*) AS new_units, coalesce(sum(len), 0)::BIGINT AS new_bytes FROM x WHERE fp NOT IN (SELECT fp FROM s)")
def incremental_dedup(spark, sf_dir):
    """A second arrival (odd ids) against the fingerprints of the first (even ids)."""
    prints = dedup.fingerprint(zoo.byte_layers(spark, sf_dir)).withColumn("odd", F.substring("layer_id", 5, 20).cast("long") % 2)
    return prints.where("odd = 1").select("fp", "len").distinct().join(prints.where("odd = 0").select("fp"), "fp", "left_anti").agg(F.count("*").alias("new_units"), F.coalesce(F.sum("len"), F.lit(0)).alias("new_bytes"))


_SIM = "SELECT dtype, sum(n)::BIGINT AS units, count(*) AS groups, sum(b)::BIGINT AS bytes, sum(b - one)::BIGINT AS similar, sum(b - one)::BIGINT / sum(b)::BIGINT::DOUBLE AS ratio FROM (SELECT dtype, fp, count(*) AS n, sum(len) AS b, min(len) AS one FROM u GROUP BY 1, 2) GROUP BY 1"
_TAKE = "list_aggregate(list_transform(range((length(h) // 2 + 31) // 32), lambda j: substr(h, 64 * j + 1, 2)), 'string_agg', '')"
_BYTE_UNIT = f"SELECT model_id, layer_id, dtype, {_TAKE} AS fp, length(h) // 2 AS len, h AS exact FROM (SELECT *, hex(encode(text)) AS h FROM {{f}}) WHERE length(h) > 0"
_BYTE_CHUNK = f"SELECT layer_id, dtype, {_TAKE} AS fp, length(h) // 2 AS len, h AS exact FROM (SELECT layer_id, dtype, substr(hh, 2 * {{k}} * i + 1, 2 * {{k}}) AS h FROM (SELECT *, unnest(range((length(hh) // 2 + {{k}} - 1) // {{k}})) AS i FROM (SELECT *, hex(encode(text)) AS hh FROM {{f}})))"


@query("similar_layer", f"WITH u AS ({_BYTE_UNIT.format(f=DOC)}) {_SIM}")
def similar_layer(spark, sf_dir):
    return similarity.ratio(similarity.sampled_bytes(zoo.byte_layers(spark, sf_dir)))


for _k in (4096, 512):

    @query(f"similar_{_k}", f"WITH u AS ({_BYTE_CHUNK.format(f=DOC, k=_k)}) {_SIM}")
    def _similar(spark, sf_dir, k=_k):
        return similarity.ratio(similarity.sampled_bytes(zoo.byte_layers(spark, sf_dir), unit=k))


_PARAM_UNIT = f"SELECT layer_id, dtype, layer_pos // 64 AS unit_no, count(*) * CASE dtype WHEN 'float32' THEN 4 ELSE 8 END AS len, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) FILTER (WHERE layer_pos % 64 % 32 = 0) AS fp, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) AS exact FROM {P} GROUP BY layer_id, dtype, layer_pos // 64"


def param_units(spark, sf_dir):
    p = zoo.params(spark, sf_dir, ("vec", "tuned", "line"))
    units = similarity.sampled(p, 64)
    exact = similarity.sampled(p, 64, stride=1).select("layer_id", "unit_no", F.col("fp").alias("exact"))
    return units.join(exact, ["layer_id", "unit_no"]).withColumn("len", F.col("n") * F.when(F.col("dtype") == "float32", 4).otherwise(8))


@query("similarity_ratio", f"WITH u AS ({_PARAM_UNIT}) {_SIM}")
def similarity_ratio(spark, sf_dir):
    return similarity.ratio(param_units(spark, sf_dir))


@query("similarity_fp", f"WITH u AS ({_PARAM_UNIT}), g AS (SELECT fp, count(*) AS n, count(DISTINCT exact) AS c FROM u GROUP BY fp HAVING count(*) > 1) SELECT count(*) AS groups, count(*) FILTER (WHERE c > 1) AS mixed FROM g")
def similarity_fp(spark, sf_dir):
    return similarity.false_positives(param_units(spark, sf_dir))


_VT = zoo.params_sql(("vec", "tuned"))


@query("delta_sizes", f"WITH p AS (SELECT * FROM {_VT}), u AS (SELECT layer_id, dtype, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) FILTER (WHERE layer_pos % 32 = 0) AS fp FROM p GROUP BY 1, 2), b AS (SELECT fp, min(layer_id) AS base FROM u GROUP BY fp), x AS (SELECT layer_id, base, dtype FROM u JOIN b USING (fp) WHERE layer_id <> base) SELECT x.layer_id, x.base, x.dtype, count(*) AS n, count(*) FILTER (WHERE q.bits IS DISTINCT FROM p.bits) AS changed, (256 + count(*) + 32 * count(*) FILTER (WHERE q.bits IS DISTINCT FROM p.bits))::BIGINT AS bits FROM x JOIN p ON p.layer_id = x.layer_id LEFT JOIN p q ON q.layer_id = x.base AND q.layer_pos = p.layer_pos GROUP BY ALL")
def delta_sizes(spark, sf_dir):
    p = zoo.params(spark, sf_dir, ("vec", "tuned"))
    return similarity.delta_sizes(p, similarity.sampled(p))


@query("super_features")
def super_features(spark, sf_dir):
    return similarity.ratio(similarity.super_features(zoo.byte_layers(spark, sf_dir)))


@query("super_features_any")
def super_features_any(spark, sf_dir):
    return similarity.any_match(similarity.super_features(zoo.byte_layers(spark, sf_dir))).groupBy("k").agg(F.count("*").alias("groups"), F.sum("n").alias("members"), F.sum("bytes").alias("bytes"))
