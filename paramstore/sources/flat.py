"""Flat files of numbers: layers one after the other as they are in memory, with an index of their places beside them."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.functions.bits import STORED, VIEW


def write(layers: DataFrame, path: str) -> None:
    """Layers (layer_id, dtype, payload) as Parquet rows of whole arrays: a part's layers end to end, and where each lies in them."""

    def run(batches):
        for batch in batches:
            ids, kinds, payloads = (batch.column(k).to_pylist() for k in range(3))
            ends = np.cumsum([len(p) for p in payloads]).tolist()
            index = [{"layer_id": i, "dtype": d, "from": e - len(p), "to": e} for i, d, e, p in zip(ids, kinds, ends, payloads, strict=True)]
            shape = pa.list_(pa.struct([("layer_id", pa.string()), ("dtype", pa.string()), ("from", pa.int64()), ("to", pa.int64())]))
            yield pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().hex]), pa.array([b"".join(payloads)], pa.binary()), pa.array([index], shape)], ["file", "content", "index"])

    rows = layers.select("layer_id", "dtype", "payload").mapInArrow(run, "file string, content binary, index array<struct<layer_id:string,dtype:string,from:long,to:long>>")
    rows.write.parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """(layer_id, dtype, values) of every layer under path."""
    cut = spark.read.parquet(path).select("content", F.explode("index").alias("x"))
    layers = cut.select("x.layer_id", "x.dtype", F.substring(F.col("content"), (F.col("x.from") + 1).cast("int"), (F.col("x.to") - F.col("x.from")).cast("int")).alias("payload"))

    def run(batches):
        for batch in batches:
            out = [np.frombuffer(p, VIEW[d][0] if d in VIEW else STORED[d]).astype(np.float64) for p, d in zip(batch.column(2).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.list_(pa.float64()))], ["layer_id", "dtype", "values"])

    return layers.mapInArrow(run, "layer_id string, dtype string, values array<double>")
