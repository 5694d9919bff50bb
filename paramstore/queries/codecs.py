"""Baselines."""

from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND, width_of
from paramstore.operators import coders, codecs, distance, kernels, measures, throughput, unitpack
from paramstore.registry import ORACLES, query
from paramstore.sources import zoo
from paramstore.sources.shared import cut, kept, shared_folder

W_ = "CASE dtype WHEN 'float32' THEN 32 ELSE 64 END"
EB = "CASE dtype WHEN 'float32' THEN pow(2::DOUBLE, -24) ELSE pow(2::DOUBLE, -53) END"
P = f"WITH p AS (SELECT *, {W_} AS w FROM {zoo.params_sql()}) "
XOR = P + ", x AS (SELECT *, xor(bits, lag(bits) OVER o) & CASE dtype WHEN 'float32' THEN 4294967295 ELSE -1 END AS x FROM p WINDOW o AS (PARTITION BY model_id, dtype ORDER BY pos)), y AS (SELECT *, CASE WHEN x = 0 THEN w ELSE w - length(bin(x)) END AS lead, length(bin(x)) - length(rtrim(bin(x), '0')) AS trail FROM x) "


def values(spark, sf_dir):
    return zoo.values(spark, sf_dir)


def params(spark, sf_dir):
    return zoo.params(spark, sf_dir)


def blocks(spark, sf_dir, families=zoo.FLOAT_FAMILIES):
    return zoo.to_blocks(zoo.params(spark, sf_dir, families))


@query("xor_profile", XOR + "SELECT model_id, dtype, count(*) AS pairs, count(*) FILTER (WHERE x = 0) AS zero, sum(lead) FILTER (WHERE x <> 0)::BIGINT AS leading, sum(trail) FILTER (WHERE x <> 0)::BIGINT AS trailing FROM y WHERE x IS NOT NULL GROUP BY ALL")
def xor_profile(spark, sf_dir):
    return codecs.xor_profile(params(spark, sf_dir))


_ROUND = "CASE WHEN lead >= 24 THEN 24 WHEN lead >= 22 THEN 22 WHEN lead >= 20 THEN 20 WHEN lead >= 18 THEN 18 WHEN lead >= 16 THEN 16 WHEN lead >= 12 THEN 12 WHEN lead >= 8 THEN 8 ELSE 0 END"


@query("chimp_sizes", XOR + f", z AS (SELECT *, {_ROUND} AS r FROM y), s AS (SELECT *, lag(CASE WHEN x <> 0 AND trail <= 6 THEN r END) OVER (PARTITION BY model_id, dtype ORDER BY pos) AS stored FROM z) SELECT model_id, dtype, count(*) AS params, sum(w)::BIGINT AS original, sum(CASE WHEN x IS NULL THEN w WHEN x = 0 THEN 2 WHEN trail > 6 THEN 5 + CASE w WHEN 64 THEN 6 ELSE 5 END + w - r - trail WHEN r = stored THEN 2 + w - r ELSE 5 + w - r END)::BIGINT AS compressed FROM s GROUP BY ALL")
def chimp_sizes(spark, sf_dir):
    return codecs.chimp(params(spark, sf_dir))


@query("sprintz_delta", "WITH p AS (SELECT * FROM " + zoo.params_sql(("vec", "tuned")) + "), d AS (SELECT model_id, dtype, pos, ((bits - lag(bits) OVER (PARTITION BY model_id, dtype ORDER BY pos) + 2147483648) & 4294967295) - 2147483648 AS d FROM p), z AS (SELECT model_id, dtype, pos, CASE WHEN d >= 0 THEN 2 * d ELSE -2 * d - 1 END AS z FROM d WHERE pos > 0), b AS (SELECT model_id, dtype, (pos - 1) // 8 AS b, max(CASE WHEN z = 0 THEN 0 ELSE length(bin(z)) END) AS width FROM z GROUP BY ALL), c AS (SELECT model_id, dtype, sum(CASE WHEN width > 0 THEN 6 + 8 * width WHEN coalesce(before, 1) > 0 THEN 22 ELSE 0 END)::BIGINT AS cost FROM (SELECT *, lag(width) OVER (PARTITION BY model_id, dtype ORDER BY b) AS before FROM b) GROUP BY ALL) SELECT p.model_id, p.dtype, count(*) AS params, 32 * count(*) AS original, 32 + any_value(cost) AS compressed FROM p JOIN c USING (model_id, dtype) GROUP BY ALL")
def sprintz_delta(spark, sf_dir):
    return codecs.sprintz_delta(zoo.params(spark, sf_dir, ("vec", "tuned")))


@query("buff_sizes", P + f", e AS (SELECT model_id, dtype, count(*) AS params, floor(min(value)) AS low, floor(max(value)) AS high, CASE dtype WHEN 'float32' THEN 23 ELSE 52 END AS f FROM p GROUP BY ALL), g AS (SELECT *, ceil((CASE WHEN high = low THEN 0 ELSE length(bin((high - low)::BIGINT)) END + f) / 8::DOUBLE)::BIGINT AS bytes FROM e), l AS (SELECT model_id, dtype, any_value(params) AS params, any_value(bytes) AS bytes, floor((value - low) / pow(2::DOUBLE, 8 * bytes - 8 - f)) AS lead, count(*) AS n FROM p JOIN g USING (model_id, dtype) GROUP BY model_id, dtype, lead), t AS (SELECT model_id, dtype, params, bytes, max(n) AS top FROM l GROUP BY ALL) SELECT model_id, dtype, params, params * {W_} AS original, (8 * params * (bytes - 1) + CASE WHEN 10 * top >= 9 * params THEN params + 8 * (params - top) ELSE 8 * params END)::BIGINT AS compressed FROM t")
def buff_sizes(spark, sf_dir):
    return codecs.buff(values(spark, sf_dir))


_E = "list_filter(range(23), lambda e: abs(value * pow(10::DOUBLE, e)) < 2147483648::DOUBLE AND floor(value * pow(10::DOUBLE, e) + 0.5) / pow(10::DOUBLE, e) = value)[1]"


@query("pseudodecimal_sizes", P + f", q AS (SELECT *, pos // 65536 AS b, {_E} AS e FROM p), r AS (SELECT *, CASE WHEN e IS NOT NULL THEN floor(value * pow(10::DOUBLE, e) + 0.5)::BIGINT END AS digits, CASE WHEN lag(bits) OVER (PARTITION BY model_id, dtype, b ORDER BY pos) = bits THEN 0 ELSE 1 END AS starts FROM q), g AS (SELECT model_id, dtype, b, w, count(*) AS n, count(DISTINCT bits) AS u, sum(starts) AS runs, min(digits) AS lo, max(digits) AS hi, count(*) FILTER (WHERE e IS NULL) AS odd FROM r GROUP BY model_id, dtype, b, w) SELECT model_id, dtype, sum(n)::BIGINT AS params, sum(n * w)::BIGINT AS original, sum(least(n * w, CASE WHEN u = 1 THEN w + 32 END, runs * (w + 32), u * w + n * CASE WHEN u > 1 THEN length(bin(u - 1)) ELSE 0 END, n * CASE WHEN coalesce(hi - lo, 0) = 0 THEN 0 ELSE length(bin(hi - lo)) END + 5 * n + odd * (w + 32)))::BIGINT AS compressed FROM g GROUP BY ALL")
def pseudodecimal_sizes(spark, sf_dir):
    return codecs.pseudodecimal(params(spark, sf_dir))


@query("pseudodecimal_example", f"SELECT value, {_E}::BIGINT AS e, floor(value * pow(10::DOUBLE, {_E}) + 0.5)::BIGINT AS digits, count(*) AS n FROM events GROUP BY ALL")
def pseudodecimal_example(spark, sf_dir):
    """Exponent and digits of every different value of the events."""
    e = codecs.decimal_exponent(F.col("value"))
    rows = zoo.table(spark, sf_dir, "events").groupBy("value").agg(F.count("*").alias("n"))
    return rows.withColumn("e", e.cast("long")).withColumn("digits", F.floor(F.col("value") * F.pow(F.lit(10.0), F.col("e")) + 0.5).cast("long"))


@query("predquant_codes", "WITH q AS (SELECT *, floor(value / pow(2::DOUBLE, -23) + 0.5)::BIGINT AS q FROM " + zoo.params_sql(("vec", "tuned")) + "), r AS (SELECT *, q - coalesce(lag(q) OVER (PARTITION BY model_id, dtype ORDER BY pos), 0) AS r FROM q) SELECT model_id, dtype, count(*) AS params, count(*) FILTER (WHERE abs(r) <= 32768) AS coded, max(abs(q * pow(2::DOUBLE, -23) - value)) AS max_error FROM r GROUP BY ALL")
def predquant_codes(spark, sf_dir):
    return codecs.lorenzo(zoo.values(spark, sf_dir, ("vec", "tuned")))


for _times, _name in ((1, "1x"), (2, "2x")):

    @query(f"prune_{_name}", P + f"SELECT model_id, dtype, count(*) AS params, sum(w)::BIGINT AS original, (count(*) + any_value(w) * count(*) FILTER (WHERE abs(value) >= {_times} * {EB}))::BIGINT AS compressed FROM p GROUP BY ALL")
    def _prune(spark, sf_dir, times=_times):
        return codecs.prune(values(spark, sf_dir), times)

    @query(f"gouq_{_name}", P + f", s AS (SELECT model_id, dtype, avg(value) AS mean, stddev_pop(value) AS std FROM p GROUP BY ALL), g AS (SELECT model_id, dtype, any_value(w) AS w, count(*) AS n, count(*) FILTER (WHERE abs(value - mean) <= 3 * std) AS g, max(value) FILTER (WHERE abs(value - mean) <= 3 * std) - min(value) FILTER (WHERE abs(value - mean) <= 3 * std) AS range FROM p JOIN s USING (model_id, dtype) GROUP BY model_id, dtype) SELECT model_id, dtype, n AS params, n * w AS original, (n + least(w, ceil(log2(floor(range / (2 * {_times} * {EB})) + 1.0))::BIGINT) * g + w * (n - g) + 3 * w)::BIGINT AS compressed FROM g")
    def _gouq(spark, sf_dir, times=_times):
        return codecs.uniform_quantization(values(spark, sf_dir), times)


@query("gouq_density", P + f", s AS (SELECT model_id, dtype, avg(value) AS mean, stddev_pop(value) AS std, sqrt(greatest(0.0::DOUBLE, -2.0::DOUBLE * (-4.0::DOUBLE + ln(stddev_pop(value) * sqrt(2 * pi()))))) AS z FROM p GROUP BY ALL), g AS (SELECT model_id, dtype, any_value(w) AS w, count(*) AS n, count(*) FILTER (WHERE abs(value - mean) <= z * std) AS g, max(value) FILTER (WHERE abs(value - mean) <= z * std) - min(value) FILTER (WHERE abs(value - mean) <= z * std) AS range FROM p JOIN s USING (model_id, dtype) GROUP BY model_id, dtype) SELECT model_id, dtype, n AS params, n * w AS original, (n + coalesce(least(w, ceil(log2(floor(range / (2 * {EB})) + 1.0))::BIGINT), 0) * g + w * (n - g) + 3 * w)::BIGINT AS compressed FROM g")
def gouq_density(spark, sf_dir):
    """Outliers told by the logarithm of their density, below -4."""
    return codecs.uniform_quantization(values(spark, sf_dir), log_density=-4.0)


@query("half_sizes", P + "SELECT model_id, dtype, count(*) AS params, sum(w)::BIGINT AS original, 16 * count(*) AS compressed FROM p GROUP BY ALL")
def half_sizes(spark, sf_dir):
    return codecs.half(values(spark, sf_dir))


@query("szx_sizes", P + f", b AS (SELECT model_id, dtype, any_value(w) AS w, pos // 128 AS b, count(*) AS n, (max(value) - min(value)) / 2 AS radius FROM p GROUP BY model_id, dtype, pos // 128) SELECT model_id, dtype, sum(n)::BIGINT AS params, sum(n * w)::BIGINT AS original, sum(CASE WHEN radius <= {EB} THEN 1 + w ELSE 1 + w + n * (1 + CASE w WHEN 32 THEN 8 ELSE 11 END + greatest(0, least(w - 1 - CASE w WHEN 32 THEN 8 ELSE 11 END, floor(log2(radius))::BIGINT + CASE w WHEN 32 THEN 24 ELSE 53 END + 1))) END)::BIGINT AS compressed FROM b GROUP BY model_id, dtype")
def szx_sizes(spark, sf_dir):
    return codecs.szx(values(spark, sf_dir))


KERNELS = {"gzip_sizes": kernels.gzip(), "zstd_sizes": kernels.zstd(), "gorilla_sizes": kernels.gorilla, "sprintz_adaptive": kernels.sprintz_adaptive, "sprintz_lookup": kernels.sprintz_lookup, "predquant_sizes": kernels.predquant, "zfp_sizes": kernels.zfp_bits}
for _name, _kernel in KERNELS.items():

    @query(_name)
    def _coded(spark, sf_dir, kernel=_kernel):
        return kernels.block_bits(blocks(spark, sf_dir), kernel)


@query("pgzip_sizes")
def pgzip_sizes(spark, sf_dir):
    """Independent small blocks, as parallel compressors make them."""
    return kernels.block_bits(zoo.to_blocks(params(spark, sf_dir), 1024), kernels.gzip())


@query("zstd_levels")
def zstd_levels(spark, sf_dir):
    held, out = kept(blocks(spark, sf_dir)), None
    for level in (3, 9, 19):
        own = kernels.block_bits(held, kernels.zstd(level)).groupBy().agg(F.lit(level).alias("level"), F.sum("original").alias("original"), F.sum("compressed").alias("compressed"))
        out = own if out is None else out.union(own)
    return out


@query("half_error")
def half_error(spark, sf_dir):
    return kernels.half_error(blocks(spark, sf_dir))


#: The methods whose sizes are relational, over parameters with their bits, and the query of the same sizes.
RELATIONAL = {
    "chimp": (codecs.chimp, "chimp_sizes"),
    "buff": (codecs.buff, "buff_sizes"),
    "pseudodecimal": (codecs.pseudodecimal, "pseudodecimal_sizes"),
    "szx": (codecs.szx, "szx_sizes"),
    "mp": (codecs.prune, "prune_1x"),
    "mp2e": (lambda p: codecs.prune(p, 2), "prune_2x"),
    "gouq": (codecs.uniform_quantization, "gouq_1x"),
    "gouq2e": (lambda p: codecs.uniform_quantization(p, 2), "gouq_2x"),
    "half": (codecs.half, "half_sizes"),
    "de": (distance.sizes, "de_practical"),
    "unit": (unitpack.sizes, "unit_sizes"),
}


def _sizes_sql() -> str:
    from paramstore.queries import parameters, pipeline  # noqa: F401  they register the queries that are named here

    parts = [f"SELECT '{m}' AS method, model_id, dtype, original, compressed FROM ({ORACLES[q]})" for m, (_, q) in RELATIONAL.items()]
    both = f"SELECT 'hybrid', d.model_id, d.dtype, d.original, least(d.compressed, u.compressed) FROM ({ORACLES['de_practical']}) d JOIN ({ORACLES['unit_sizes']}) u USING (model_id, dtype)"
    return f"({' UNION ALL '.join([*parts, both])})"


def sizes_of_all(spark, sf_dir):
    """(method, model_id, dtype, original, compressed) of all relational methods and the better of both arms; parameters are built once."""
    p, out = kept(params(spark, sf_dir)), None
    named = ["model_id", "dtype", "original", "compressed"]
    for method, (size, _) in RELATIONAL.items():
        own = size(p).select(F.lit(method).alias("method"), *named)
        out = own if out is None else out.union(own)
    out = cut(out)
    best = out.where("method in ('de', 'unit')").groupBy(F.lit("hybrid").alias("method"), "model_id", "dtype").agg(F.max("original").alias("original"), F.min("compressed").alias("compressed"))
    return out.union(best)


def sizes_of_coders(spark, sf_dir):
    """The same of the byte and state coders, and of the whole pipeline with its last stage."""
    from paramstore.plans import hybrid

    p, out = kept(params(spark, sf_dir)), None
    b = kept(zoo.to_blocks(p))
    for name, kernel in KERNELS.items():
        own = kernels.block_bits(b, kernel).select(F.lit(name.removesuffix("_sizes")).alias("method"), "model_id", "dtype", "original", "compressed")
        out = own if out is None else out.union(own)
    whole = hybrid.stage_entropy(hybrid.encode(p)).select(F.lit("pipeline").alias("method"), "model_id", "dtype", (F.col("params") * width_of(F.col("dtype"))).alias("original"), "compressed")
    return out.union(whole)


_CR = "r AS (SELECT *, original / compressed::DOUBLE AS cr FROM s)"


def _with(sql: str):
    return f"WITH s AS (SELECT * FROM {_sizes_sql()}), {_CR} {sql}"


query("codec_sizes", _with("SELECT method, model_id, dtype, original, compressed FROM s"))(sizes_of_all)
query("codec_sizes_coders")(sizes_of_coders)


@query("cr_cdf", _with("SELECT method, model_id, cr, cume_dist() OVER (PARTITION BY method ORDER BY cr) AS cdf, (count(*) FILTER (WHERE cr >= 1.0) OVER (PARTITION BY method)) / (count(*) OVER (PARTITION BY method))::DOUBLE AS share_100, (count(*) FILTER (WHERE cr >= 1.3) OVER (PARTITION BY method)) / (count(*) OVER (PARTITION BY method))::DOUBLE AS share_130 FROM r"))
def cr_cdf(spark, sf_dir):
    return measures.cr_cdf(sizes_of_all(spark, sf_dir), (1.0, 1.3))


@query("cr_cumulative", _with("SELECT method, model_id, cr, (sum(original) OVER w)::BIGINT / (sum(compressed) OVER w)::BIGINT::DOUBLE AS cumulative_cr FROM r WINDOW w AS (PARTITION BY method ORDER BY cr DESC, model_id ROWS UNBOUNDED PRECEDING)"))
def cr_cumulative(spark, sf_dir):
    return measures.cumulative_cr(sizes_of_all(spark, sf_dir))


@query("cr_breakdown", _with("SELECT method, min(cr) AS least, round(quantile_cont(cr, 0.25), 9) AS q1, round(quantile_cont(cr, 0.5), 9) AS median, round(quantile_cont(cr, 0.75), 9) AS q3, max(cr) AS most, sum(original)::BIGINT / sum(compressed)::BIGINT::DOUBLE AS overall FROM r GROUP BY method"))
def cr_breakdown(spark, sf_dir):
    return measures.breakdown(sizes_of_all(spark, sf_dir))


@query("cr_breakdown_coders")
def cr_breakdown_coders(spark, sf_dir):
    return measures.breakdown(sizes_of_coders(spark, sf_dir))


@query("codec_table")
def codec_table(spark, sf_dir):
    """All baselines, both arms, their better one and the whole pipeline: overall sizes and ratio of each."""
    every = sizes_of_all(spark, sf_dir).union(sizes_of_coders(spark, sf_dir))
    return every.groupBy("method").agg(F.sum("original").alias("original"), F.sum("compressed").alias("compressed")).withColumn("cr", F.col("original") / F.col("compressed"))


_CODERS = ", ".join(f"('{c}')" for c in coders.CODERS)


@query("coder_round_trips", f"SELECT coder, dtype, true AS kept FROM (SELECT DISTINCT dtype FROM {zoo.params_sql()}), (VALUES {_CODERS}) t(coder)")
def coder_round_trips(spark, sf_dir):
    """Every coder over all blocks: all bits back for lossless ones, else within the bound (half: its own) inside the unit interval."""
    tried = coders.round_trips(blocks(spark, sf_dir))
    bound = F.lit(0.0)
    for dtype, b in BOUND.items():
        bound = F.when(F.col("dtype") == dtype, b).otherwise(bound)
    near = F.col("max_error") <= F.when(F.col("coder") == "half", BOUND["float16"]).otherwise(2 * bound)
    return tried.select("coder", "dtype", F.when(F.col("coder").isin(*coders.LOSSLESS), F.col("exact")).otherwise(near).alias("kept"))


@query("codec_throughput")
def codec_throughput(spark, sf_dir):
    """MB/s of all coders, reading and writing included, over the vectors so often again with perturbed values."""
    return throughput.table(spark, zoo.vector_layers(spark, sf_dir), shared_folder(spark, "speed"))
