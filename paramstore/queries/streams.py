"""Windows over event time in batch form, and streaming replays."""

from pyspark.sql import functions as F

from paramstore.registry import query
from paramstore.sources import zoo
from paramstore.streaming import ingest


def events(spark, sf_dir):
    return zoo.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _ntz(rows, *names):
    return rows.withColumns({n: F.col(n).cast("timestamp_ntz") for n in names})


@query("win_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n, CAST(sum(octet_length(encode(props))) AS BIGINT) AS bytes FROM events GROUP BY 1")
def win_tumbling(spark, sf_dir):
    w = events(spark, sf_dir).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"), F.sum(F.octet_length("props")).alias("bytes"))
    return _ntz(w.select(F.col("w.start").alias("start"), "n", "bytes"), "start")


@query("win_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01') - INTERVAL 30 MINUTE]) AS start FROM events) GROUP BY 1")
def win_sliding(spark, sf_dir):
    w = events(spark, sf_dir).groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return _ntz(w.select(F.col("w.start").alias("start"), "n"), "start")


@query("win_session", "WITH m AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER o IS NULL OR ts >= lag(ts) OVER o + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS first FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(first) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def win_session(spark, sf_dir):
    w = events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return _ntz(w.select("user_id", F.col("w.start").alias("start"), "n"), "start")


@query("stream_ingest", "SELECT lang AS part, count(*) AS layers FROM documents GROUP BY lang")
def stream_ingest(spark, sf_dir):
    docs = zoo.byte_layers(spark, sf_dir)
    arrived = ingest.replay(spark, docs, lambda rows: rows.withColumnsRenamed({}), "append")
    return arrived.groupBy(F.substring("model_id", 6, 10).alias("part")).agg(F.count("*").alias("layers"))


@query("stream_dedup", "SELECT count(*) AS layers, count(DISTINCT sha256(text)) AS stored, count(*) - count(DISTINCT sha256(text)) AS refs FROM documents")
def stream_dedup(spark, sf_dir):
    return ingest.dedup_stream(spark, zoo.byte_layers(spark, sf_dir)).agg(F.count("*").alias("layers"), F.count_if("stored").alias("stored"), F.count_if(~F.col("stored")).alias("refs"))


@query("stream_dedup_wm")
def stream_dedup_wm(spark, sf_dir):
    e = events(spark, sf_dir)
    once = lambda rows: rows.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return ingest.replay(spark, e, once, "append").groupBy("event_type").agg(F.count("*").alias("n"))


@query("late_audit")
def late_audit(spark, sf_dir):
    """Arrivals in id order: how many events a watermark of one hour keeps in hourly windows, and how many came too late."""
    e = events(spark, sf_dir)
    hourly = lambda rows: rows.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).count()
    kept = ingest.replay(spark, e, hourly, "update").groupBy("w").agg(F.max("count").alias("n"))
    return kept.agg(F.count("*").alias("windows"), F.sum("n").alias("kept")).join(e.agg(F.count("*").alias("arrived"))).withColumn("late", F.col("arrived") - F.col("kept"))


@query("late_observed", "SELECT count(*) AS arrived, max(ts) AS latest, true AS some_late FROM events")
def late_observed(spark, sf_dir):
    """Observed counts of the same stream: what arrived in all, the latest time, and whether the state dropped late rows."""
    hourly = lambda rows: rows.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).count()
    seen = ingest.audited(spark, events(spark, sf_dir), hourly)
    return _ntz(seen.agg(F.sum("arrived").alias("arrived"), F.max("latest").alias("latest"), (F.sum("dropped") > 0).alias("some_late")), "latest")


@query("stream_enrich", "SELECT l.quality, count(*) AS n FROM documents d JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def stream_enrich(spark, sf_dir):
    labels = zoo.table(spark, sf_dir, "labels")
    docs = zoo.table(spark, sf_dir, "documents").select("doc_id", "lang")
    return ingest.replay(spark, docs, lambda rows: rows.join(labels, "doc_id"), "append").groupBy("quality").agg(F.count("*").alias("n"))


@query("stream_growth", "SELECT event_type, count(*) AS n, CAST(sum(octet_length(encode(props))) AS BIGINT) AS bytes FROM events GROUP BY 1")
def stream_growth(spark, sf_dir):
    total = lambda rows: rows.groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.octet_length("props")).alias("bytes"))
    return ingest.replay(spark, events(spark, sf_dir), total, "complete")
