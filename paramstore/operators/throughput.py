"""Throughput of block coders: bytes of the data set by wall time, reading and writing included."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.operators.coders import CODERS


def replicated(spark: SparkSession, vectors: DataFrame, times: int, path: str, block: int = 1 << 16) -> int:
    """Blocks of the vectors, so often again with perturbed values, as Parquet under path in some files for each core; their bytes."""
    files = 2 * spark.sparkContext.defaultParallelism
    copies = vectors.select("model_id", "payload", F.explode(F.sequence(F.lit(1), F.lit(times))).alias("copy")).repartition(files)

    def run(batches):
        held = b""
        for batch in batches:
            rows = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.float32)
            width = len(rows) // max(batch.num_rows, 1)
            scale = np.repeat(1 + 1e-4 * np.array(batch.column(2).to_pylist(), np.float32), width)
            held += (rows * scale).astype(np.float32).tobytes()
            whole = len(held) // (4 * block) * 4 * block
            parts, held = [held[i : i + 4 * block] for i in range(0, whole, 4 * block)], held[whole:]
            yield pa.RecordBatch.from_arrays([pa.array(["float32"] * len(parts), pa.string()), pa.array(parts, pa.binary())], ["dtype", "payload"])
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(["float32"]), pa.array([held], pa.binary())], ["dtype", "payload"])

    copies.mapInArrow(run, "dtype string, payload binary").write.mode("overwrite").option("compression", "none").parquet(path)
    return spark.read.parquet(path).agg(F.sum(F.length("payload"))).first()[0]


def code(spark: SparkSession, src: str, dst: str, codec: str, decode: bool = False) -> float:
    """Seconds for reading src, coding its blocks and writing them to dst."""
    f = CODERS[codec][1 if decode else 0]

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):  # some blocks at a time go on to the writer
                part = batch.slice(at, 64)
                out = [f(p, d) for p, d in zip(part.column(1).to_pylist(), part.column(0).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out, pa.binary())], ["dtype", "payload"])

    began = time.time()
    spark.read.parquet(src).select("dtype", "payload").mapInArrow(run, "dtype string, payload binary").write.mode("overwrite").option("compression", "none").parquet(dst)
    return time.time() - began


def measure(spark: SparkSession, vectors: DataFrame, folder: str, times: int = 400, codecs=("unit", "zstd"), warm: bool = True) -> dict[str, float]:
    """MB/s of compression and decompression by each codec."""
    size, out = replicated(spark, vectors, times, f"{folder}/raw") / 1e6, {"mb": 0.0}
    out["mb"] = round(size, 1)
    for codec in codecs:
        if warm:
            code(spark, f"{folder}/raw", f"{folder}/{codec}", codec)  # once before, so that workers are there
        out[f"{codec}_compress_mb_s"] = round(size / code(spark, f"{folder}/raw", f"{folder}/{codec}", codec), 1)
        out[f"{codec}_decompress_mb_s"] = round(size / code(spark, f"{folder}/{codec}", f"{folder}/{codec}-back", codec, decode=True), 1)
    return out


def table(spark: SparkSession, vectors: DataFrame, folder: str, times: int = 20, codecs=tuple(CODERS)) -> DataFrame:
    """(codec, mb, compress_mb_s, decompress_mb_s) of all codecs."""
    speed = measure(spark, vectors, folder, times, codecs, warm=False)
    return spark.createDataFrame([(c, speed["mb"], speed[f"{c}_compress_mb_s"], speed[f"{c}_decompress_mb_s"]) for c in codecs], "codec string, mb double, compress_mb_s double, decompress_mb_s double")
