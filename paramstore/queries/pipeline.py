"""Unit-interval packing, the hybrid store pipeline, its ablation, and the measures."""

from pyspark.sql import functions as F

from paramstore.operators import measures, unitpack
from paramstore.plans import hybrid
from paramstore.queries import parameters
from paramstore.registry import query
from paramstore.sources import runs, zoo
from paramstore.sources.shared import kept

VALUES = zoo.params_sql()
_IN = "(value > -1 AND value < 1 AND CASE dtype WHEN 'float32' THEN (1::FLOAT + abs(value)::FLOAT) < 2 ELSE (1::DOUBLE + abs(value)) < 2 END)"
_CODE = "CASE dtype WHEN 'float32' THEN (((1::FLOAT + abs(value)::FLOAT) - 1::FLOAT)::DOUBLE * 8388608)::BIGINT + CASE WHEN signbit(value) THEN 8388608 ELSE 0 END ELSE (((1::DOUBLE + abs(value)) - 1::DOUBLE) * 4503599627370496)::BIGINT + CASE WHEN signbit(value) THEN 4503599627370496 ELSE 0 END END"
_DEC = "(CASE dtype WHEN 'float32' THEN (code & 8388607) / 8388608::DOUBLE * CASE WHEN code & 8388608 <> 0 THEN -1 ELSE 1 END ELSE (code & 4503599627370495) / 4503599627370496::DOUBLE * CASE WHEN code & 4503599627370496 <> 0 THEN -1 ELSE 1 END END)"
U = f"WITH p AS (SELECT * FROM {VALUES}), u AS (SELECT *, {_CODE} AS code FROM p WHERE {_IN}) "
SIZES = f"SELECT model_id, dtype, count(*) AS params, count(*) FILTER (WHERE NOT {_IN}) AS exceptions, (count(*) * CASE dtype WHEN 'float32' THEN 32 ELSE 64 END)::BIGINT AS original, (count(*) FILTER (WHERE {_IN}) * CASE dtype WHEN 'float32' THEN 24 ELSE 53 END + count(*) FILTER (WHERE NOT {_IN}) * CASE dtype WHEN 'float32' THEN 64 ELSE 96 END)::BIGINT AS compressed FROM p GROUP BY model_id, dtype"


def codes(spark, sf_dir, families=zoo.FLOAT_FAMILIES):
    return unitpack.encode(zoo.values(spark, sf_dir, families))


@query("unit_encode32", U + "SELECT model_id, pos, code FROM u WHERE dtype = 'float32'")
def unit_encode32(spark, sf_dir):
    return codes(spark, sf_dir, ("vec",)).select("model_id", "pos", "code")


@query("unit_decode32", U + f"SELECT model_id, pos, {_DEC} AS value FROM u WHERE dtype = 'float32'")
def unit_decode32(spark, sf_dir):
    return codes(spark, sf_dir, ("vec",)).select("model_id", "pos", unitpack.decoded(F.col("code"), F.col("dtype")).alias("value"))


@query("unit_encode64", U + "SELECT model_id, pos, code FROM u WHERE dtype = 'float64'")
def unit_encode64(spark, sf_dir):
    return codes(spark, sf_dir, ("line", "order", "cust", "event")).select("model_id", "pos", "code")


@query("unit_encode16")
def unit_encode16(spark, sf_dir):
    from paramstore.operators import kernels

    return kernels.half_codes(zoo.vector_layers(spark, sf_dir, "half"))


@query("unit_exceptions", U + f"SELECT model_id, dtype, pos, bits FROM p WHERE NOT {_IN}")
def unit_exceptions(spark, sf_dir):
    return unitpack.split(zoo.params(spark, sf_dir))


#: Distances below 1: around the edge of float32 and of float64, and others to inside and outside.
_EDGE = [("float32", 2.0**-24), ("float32", 2.0**-23), ("float64", 2.0**-53), ("float64", 2.0**-52), ("float64", 1.0), ("float32", 1.5), ("float64", 0.0), ("float64", 2.5)]


@query("unit_edge", "WITH p AS (SELECT dtype, off, (1 - value % 1) - off AS value FROM events, (VALUES " + ", ".join(f"('{d}', {v!r}::DOUBLE)" for d, v in _EDGE) + f") t(dtype, off)) SELECT dtype, off, count(*) AS n, count(*) FILTER (WHERE {_IN}) AS packable, max(value) AS largest FROM p GROUP BY ALL")
def unit_edge(spark, sf_dir):
    """Each event's value, less its whole part, taken from 1: whole values come to lie on the edge itself."""
    edges = F.explode(F.array(*[F.struct(F.lit(d).alias("dtype"), F.lit(off).alias("off")) for d, off in _EDGE])).alias("x")
    rows = zoo.table(spark, sf_dir, "events").select("value", edges).select("x.dtype", "x.off", ((1.0 - F.col("value") % 1) - F.col("x.off")).alias("value"))
    return rows.groupBy("dtype", "off").agg(F.count("*").alias("n"), F.count_if(unitpack.packable(F.col("value"), F.col("dtype"))).alias("packable"), F.max("value").alias("largest"))


@query("unit_sizes", U + SIZES)
def unit_sizes(spark, sf_dir):
    return unitpack.sizes(zoo.values(spark, sf_dir))


@query("unit_error_bound", U + f", e AS (SELECT *, abs({_DEC} - value) AS off FROM u) SELECT model_id, dtype, max(off) AS max_error, count(*) FILTER (WHERE off = 0) / count(*)::DOUBLE AS exact, CASE dtype WHEN 'float32' THEN pow(2::DOUBLE, -24) ELSE pow(2::DOUBLE, -53) END AS bound, max(off) <= CASE dtype WHEN 'float32' THEN pow(2::DOUBLE, -24) ELSE pow(2::DOUBLE, -53) END AS holds FROM e GROUP BY model_id, dtype")
def unit_error_bound(spark, sf_dir):
    return unitpack.error(zoo.values(spark, sf_dir)).drop("mean_error")


@query("unit_roundtrip")
def unit_roundtrip(spark, sf_dir):
    return unitpack.roundtrip(zoo.to_blocks(zoo.params(spark, sf_dir)))


@query("unit_example", "SELECT event_id, (1::FLOAT + x)::DOUBLE AS moved, (((1::FLOAT + x) - 1::FLOAT)::DOUBLE * 8388608)::BIGINT AS code, ((1::FLOAT + x) - 1::FLOAT)::DOUBLE AS decoded FROM (SELECT event_id, (abs(value) % 1)::FLOAT AS x FROM events)")
def unit_example(spark, sf_dir):
    """Every event's value, less its whole part, step by step: moved, coded, decoded."""
    rows = zoo.table(spark, sf_dir, "events").select("event_id", F.lit("float32").alias("dtype"), (F.abs("value") % 1).cast("float").cast("double").alias("value"))
    c = unitpack.code(F.col("value"), F.col("dtype"))
    return rows.select("event_id", unitpack._one_more(F.col("value"), "float32").cast("double").alias("moved"), c.alias("code"), unitpack.decoded(c, F.col("dtype")).alias("decoded"))


@query("unit_idempotent", U + f", v AS (SELECT dtype, code AS first, {_DEC} AS value FROM u), w AS (SELECT *, {_CODE} AS again FROM v) SELECT count(*) AS codes, count(*) FILTER (WHERE again <> first AND value <> 0) AS changed FROM w")
def unit_idempotent(spark, sf_dir):
    d = F.col("dtype")
    twice = codes(spark, sf_dir).select("dtype", F.col("code").alias("first"), unitpack.decoded(F.col("code"), d).alias("value"))
    return twice.withColumn("again", unitpack.code(F.col("value"), d)).agg(F.count("*").alias("codes"), F.count_if((F.col("again") != F.col("first")) & (F.col("value") != 0)).alias("changed"))


@query("unit_pushdown", U + f"SELECT count(*) FILTER (WHERE abs({_DEC}) < 0.125) AS by_value, count(*) FILTER (WHERE (code & 8388607) < 1048576) AS by_code FROM u WHERE dtype = 'float32'")
def unit_pushdown(spark, sf_dir):
    c = codes(spark, sf_dir, ("vec",))
    return c.agg(F.count_if(F.abs(unitpack.decoded(F.col("code"), F.col("dtype"))) < 0.125).alias("by_value"), F.count_if(unitpack.push_predicate(F.col("code"), "float32", 0.125)).alias("by_code"))


FAMILIES = ("vec", "tuned", "line", "order", "cust", "event", "key", "posid")
_ALL = zoo.params_sql(FAMILIES)
#: Layers with their prints; the owner of a print is its first layer by (model_id, layer_seq).
STORE = f"WITH q AS (SELECT * FROM {_ALL}), a AS (SELECT model_id, layer_id, layer_seq, dtype, count(*) AS n, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) AS fp FROM q GROUP BY ALL), b AS (SELECT *, row_number() OVER (PARTITION BY fp, dtype ORDER BY model_id, layer_seq) AS copy, CASE dtype WHEN 'float32' THEN 32 ELSE 64 END AS w FROM a) "


def all_params(spark, sf_dir):
    """Written once: prints, offsets, sizes and blocks all start from them."""
    return kept(zoo.params(spark, sf_dir, FAMILIES))


def all_runs(spark, sf_dir):
    """The same layers as packed runs."""
    return kept(runs.runs(spark, sf_dir, FAMILIES))


@query("stage_dedup", STORE + "SELECT model_id, count(*) AS layers, count(*) FILTER (WHERE copy = 1) AS stored, sum(n * w)::BIGINT AS original, sum(CASE WHEN copy = 1 THEN n * w ELSE 256 END)::BIGINT AS compressed FROM b GROUP BY 1")
def stage_dedup(spark, sf_dir):
    return hybrid.dedup_sizes(hybrid.stage_dedup(all_params(spark, sf_dir)))


@query("stage_route", STORE + "SELECT b.model_id, b.dtype, count(*) AS params FROM b JOIN q USING (layer_id) WHERE copy = 1 GROUP BY 1, 2")
def stage_route(spark, sf_dir):
    p = all_params(spark, sf_dir)
    return hybrid.route(p, hybrid.stage_dedup(p)).groupBy("model_id", "dtype").agg(F.count("*").alias("params"))


#: Stored parameters, their positions without the layers that became references.
ROUTED = STORE + ", r AS (SELECT model_id, layer_id, layer_seq, n, sum(n) OVER (PARTITION BY model_id, dtype ORDER BY layer_seq) - n AS o FROM b WHERE copy = 1), p AS (SELECT q.* REPLACE ((r.o + q.layer_pos)::BIGINT AS pos) FROM q JOIN r USING (layer_id)), d AS (SELECT model_id, dtype, CASE dtype WHEN 'float32' THEN 32 ELSE 64 END AS w, pos, pos - lag(pos) OVER (PARTITION BY model_id, dtype, bits ORDER BY pos) AS d FROM p), e AS (SELECT *, length(bin(d)) AS len FROM d) "
_ARMS = f"SELECT s.model_id, s.dtype, s.original, s.compressed AS de, t.compressed AS unit, least(s.compressed, t.compressed) AS compressed, CASE WHEN s.compressed < t.compressed THEN 'de' ELSE 'unit' END AS arm FROM ({parameters.PRACTICAL}) s JOIN ({SIZES}) t USING (model_id, dtype)"
_CHOOSE = f"SELECT model_id, dtype, original, CASE WHEN dtype LIKE 'float%' THEN de END AS de, CASE WHEN dtype LIKE 'float%' THEN unit END AS unit, CASE WHEN dtype LIKE 'float%' THEN compressed ELSE original END AS compressed, CASE WHEN dtype LIKE 'float%' THEN arm ELSE 'raw' END AS arm FROM ({_ARMS})"


@query("stage_choose", ROUTED + _CHOOSE)
def stage_choose(spark, sf_dir):
    p = all_params(spark, sf_dir)
    return hybrid.choose(hybrid.route(p, hybrid.stage_dedup(p)))


@query("stage_choose_layer", f"WITH p AS (SELECT * REPLACE (layer_id AS model_id, layer_pos AS pos) FROM {VALUES}), d AS (SELECT model_id, dtype, CASE dtype WHEN 'float32' THEN 32 ELSE 64 END AS w, pos, pos - lag(pos) OVER (PARTITION BY model_id, dtype, bits ORDER BY pos) AS d FROM p), e AS (SELECT *, length(bin(d)) AS len FROM d) SELECT model_id AS layer_id, dtype, original, de, unit, least(original, de, unit) AS compressed, CASE WHEN original <= least(de, unit) THEN 'raw' ELSE arm END AS arm FROM ({_CHOOSE})")
def stage_choose_layer(spark, sf_dir):
    p = zoo.params(spark, sf_dir).withColumns({"model_id": F.col("layer_id"), "pos": F.col("layer_pos")})
    return hybrid.choose(p, allow_raw=True).withColumnRenamed("model_id", "layer_id")


@query("stage_zstd")
def stage_zstd(spark, sf_dir):
    p = all_params(spark, sf_dir)
    return hybrid.entropy_sizes(hybrid.route(p, hybrid.stage_dedup(p)))


_BYTES = " UNION ALL ".join(f"SELECT * FROM {x}" for x in zoo.BYTES_SQL.values())


@query("hybrid_roundtrip", f"SELECT dtype, count(*) AS params, 0::BIGINT AS missing, 0::BIGINT AS others_differ, true AS within_bound FROM {_ALL} GROUP BY dtype UNION ALL SELECT dtype, sum(octet_length(encode(text)))::BIGINT, 0, 0, true FROM ({_BYTES}) GROUP BY dtype")
def hybrid_roundtrip(spark, sf_dir):
    """Everything that the store gives back, against what went in: floats, whole numbers, texts and pages."""
    layers = zoo.byte_layers(spark, sf_dir).union(zoo.byte_layers(spark, sf_dir, "pages"))
    return hybrid.within_bound(hybrid.verify_runs(all_runs(spark, sf_dir)).unionByName(hybrid.verify_bytes(layers)))


_PRINTS = "SELECT model_id, layer_id, layer_seq, dtype, count(*) AS n, string_agg(bits::VARCHAR, ',' ORDER BY layer_pos) AS fp FROM {p} GROUP BY ALL"


@query("store_increment", f"WITH a AS ({_PRINTS.format(p=zoo.params_sql(('vec', 'posid')))}), b AS ({_PRINTS.format(p=zoo.params_sql(('tuned', 'posid')))}), c AS (SELECT b.*, fp IN (SELECT fp FROM a) AS held, row_number() OVER (PARTITION BY fp, dtype ORDER BY model_id, layer_seq) AS r FROM b) SELECT model_id, count(*) AS layers, count(*) FILTER (WHERE NOT held AND r = 1) AS stored, sum(n * CASE dtype WHEN 'float32' THEN 32 ELSE 64 END)::BIGINT AS original, sum(CASE WHEN NOT held AND r = 1 THEN n * CASE dtype WHEN 'float32' THEN 32 ELSE 64 END ELSE 256 END)::BIGINT AS compressed FROM c GROUP BY model_id")
def store_increment(spark, sf_dir):
    """A second arrival against a store's prints: tuned models and positions over the vectors' models."""
    first = hybrid.stage_dedup(zoo.params(spark, sf_dir, ("vec", "posid"))).where("copy = 1")
    renamed = zoo.params(spark, sf_dir, ("tuned", "posid"))
    renamed = renamed.withColumn("layer_id", F.concat("layer_id", F.lit("'")))  # another file of the same name
    return hybrid.dedup_sizes(hybrid.stage_dedup(renamed, first.select("fp", "dtype", "canonical")))


@query("store_structure", f"SELECT model_id, count(*) AS layers, count(*) FILTER (WHERE copy = 1) AS stored, sum(n)::BIGINT AS params FROM ({STORE} SELECT * FROM b) GROUP BY model_id")
def store_structure(spark, sf_dir):
    """The models' structure, compressed and read back."""
    back = hybrid.read_structure(hybrid.structure(hybrid.stage_dedup(all_params(spark, sf_dir))))
    return back.groupBy("model_id").agg(F.count("*").alias("layers"), F.count_if(F.col("copy") == 1).alias("stored"), F.sum("n").alias("params"))


_DEDUP_ALL = "SELECT model_id, sum(n * w)::BIGINT AS original, sum(CASE WHEN copy = 1 THEN n * w ELSE 256 END)::BIGINT AS compressed, sum(CASE WHEN copy > 1 THEN 256 ELSE 0 END)::BIGINT AS refs FROM b GROUP BY 1"
ABLATION = ROUTED + f", x AS ({_CHOOSE}), z AS ({_DEDUP_ALL}), m AS (SELECT z.*, coalesce(x.de, x.original, 0) AS de, coalesce(x.unit, x.original, 0) AS unit, coalesce(x.compressed, 0) AS best FROM z LEFT JOIN x USING (model_id)), long AS (SELECT model_id, original, unnest(['1_dedup', '2_dedup_de', '3_dedup_unit', '4_dedup_both']) AS stage, unnest([compressed, refs + de, refs + unit, refs + best])::BIGINT AS compressed FROM m) "


@query("ablation_sizes", ABLATION + "SELECT * FROM long")
def ablation_sizes(spark, sf_dir):
    return hybrid.ablation(all_runs(spark, sf_dir))


@query("ablation_full")
def ablation_full(spark, sf_dir):
    return hybrid.ablation(all_runs(spark, sf_dir), with_entropy=True)


@query("ablation_shares", ABLATION + ", s AS (SELECT stage, sum(original)::BIGINT / sum(compressed)::BIGINT::DOUBLE AS cr FROM long GROUP BY stage) SELECT stage, round(cr, 9) AS cr, round(cr - coalesce(lag(cr) OVER (ORDER BY stage), 1.0), 9) AS step FROM s")
def ablation_shares(spark, sf_dir):
    return hybrid.shares(ablation_sizes(spark, sf_dir))


SZ = U + ", s AS (" + SIZES + ") "


@query("cr_per_model", SZ + "SELECT model_id, original, compressed, original / compressed::DOUBLE AS cr FROM s")
def cr_per_model(spark, sf_dir):
    return measures.cr(unit_sizes(spark, sf_dir)).select("model_id", "original", "compressed", "cr")


@query("overall_cr", SZ + "SELECT sum(original)::BIGINT AS original, sum(compressed)::BIGINT AS compressed, sum(original)::BIGINT / sum(compressed)::BIGINT::DOUBLE AS cr FROM s")
def overall_cr(spark, sf_dir):
    return measures.overall_cr(unit_sizes(spark, sf_dir))


@query("storage_saving", SZ + "SELECT model_id, 1.0::DOUBLE - compressed / original::DOUBLE AS saving FROM s")
def storage_saving(spark, sf_dir):
    return measures.saving(unit_sizes(spark, sf_dir)).select("model_id", "saving")
