"""Arrival of new layers as a stream: replay of a table in micro-batches, first-seen deduplication against a table of fingerprints."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.operators.dedup import fingerprint
from paramstore.sources.shared import shared_folder as folder


def arrivals(spark: SparkSession, rows: DataFrame, files: int = 3, files_a_batch: int = 1) -> DataFrame:
    """rows as a stream of files."""
    path = folder(spark, "arrivals")
    rows.repartition(files).write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def replay(spark: SparkSession, rows: DataFrame, transform: Callable[[DataFrame], DataFrame], mode: str) -> DataFrame:
    """What transform over the stream of rows gives, all micro-batches in one table ('complete': the last one alone)."""
    out = folder(spark, "replayed")
    stream = transform(arrivals(spark, rows))

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(out if mode == "complete" else f"{out}/batch={batch_id}")

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", folder(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def audited(spark: SparkSession, rows: DataFrame, transform: Callable[[DataFrame], DataFrame], time: str = "ts") -> DataFrame:
    """(batch, arrived, latest, dropped) of every micro-batch of transform over the stream of rows: what observe() saw arrive, and what came too late for the state."""
    seen = arrivals(spark, rows).observe("seen", F.count("*").alias("arrived"), F.unix_micros(F.max(time)).alias("latest"))
    query = transform(seen).writeStream.outputMode("update").foreachBatch(lambda batch, _: batch.write.format("noop").mode("overwrite").save()).option("checkpointLocation", folder(spark, "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    out = []
    for p in query.recentProgress:
        got = p.observedMetrics.get("seen")
        out.append((p.batchId, got.arrived if got else 0, got.latest if got else None, sum(x.numRowsDroppedByWatermark for x in p.stateOperators)))
    return spark.createDataFrame(out, "batch long, arrived long, latest long, dropped long").withColumn("latest", F.timestamp_micros("latest"))


def dedup_stream(spark: SparkSession, layers: DataFrame) -> DataFrame:
    """(layer_id, fp, len, stored) of all arrivals: stored is true for the first of each print, over all micro-batches.

    The history lives in a table of fingerprints, not in state; a batch meets it by an anti-join on prints and then adds its own. A batch
    that is run again finds its own id in the table and leaves it out, so that a restart gives the same result.
    """
    known, out = folder(spark, "prints"), folder(spark, "refs")
    stream = fingerprint(arrivals(spark, layers)).select("layer_id", "fp", "len")

    def put(batch: DataFrame, batch_id: int) -> None:
        history = spark.read.schema("fp string, batch long").parquet(known).where(F.col("batch") < batch_id) if batch_id else spark.createDataFrame([], "fp string, batch long")
        first = batch.groupBy("fp").agg(F.min("layer_id").alias("first_id")).join(history.select("fp"), "fp", "left_anti")
        first.select("fp").write.mode("overwrite").parquet(f"{known}/batch={batch_id}")
        marked = batch.join(first, "fp", "left").withColumn("stored", F.coalesce(F.col("layer_id") == F.col("first_id"), F.lit(False)))
        marked.select("layer_id", "fp", "len", "stored").write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    stream.writeStream.foreachBatch(put).option("checkpointLocation", folder(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("layer_id string, fp string, len long, stored boolean").parquet(out)
