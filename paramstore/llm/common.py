"""Helpers shared by the operators: table reads, cut lineage, Arrow iteration over whole texts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.sources.shared import cut, shared_folder  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def raw_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text, null as empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def per_batch(kernel: Callable[[pa.RecordBatch], pa.RecordBatch], most_bytes: int = 16 << 20) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A mapInArrow function that gives kernel slices of about most_bytes, however large the incoming batches are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            step = max(1, int(batch.num_rows * most_bytes / max(batch.nbytes, 1)))
            for start in range(0, batch.num_rows, step):
                yield kernel(batch.slice(start, step))

    return run


def gathered(batches: Iterator[pa.RecordBatch], most_rows: int = 100_000, most_bytes: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """The batches, small ones joined up to about most_rows or most_bytes: for kernels with a cost for each batch."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
        if sum(b.num_rows for b in held) >= most_rows or sum(b.nbytes for b in held) >= most_bytes:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
            held = []
    if held:
        yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def texts_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more: str) -> DataFrame:
    """Only the columns a kernel reads, under fixed names, so that further columns of docs never clash."""
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), *[F.col(x) for x in more])


KEY = "struct<a:long,b:long>"


def row_key(doc_id: str, *columns: str):
    """A 128-bit digest that, beside the id, tells rows of equal id apart: two rows of 3e10 share it with a probability below 1e-17."""
    own = [F.col(doc_id), *[F.col(c) for c in columns]]
    return F.struct(F.xxhash64(*own).alias("a"), F.xxhash64(F.lit("b"), *reversed(own)).alias("b"))


def bucket(doc_id, n: int):
    """crc32 of the id as text modulo n; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % n


def concat_texts(raws: list[bytes], pad: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All texts in one byte array, each after pad; starts of the texts and their lengths."""
    lengths = np.fromiter(map(len, raws), np.int64, len(raws))
    data = np.frombuffer(b"".join(x for raw in raws for x in (pad, raw)), np.uint8)
    starts = np.cumsum(lengths + len(pad)) - lengths
    return data, starts, lengths


class Held:
    """What a broadcast carries, and what a worker makes of it: once for each worker, however many tasks it runs.

    build is a function of a module, so that it can be pickled by name.
    """

    def __init__(self, build: Callable, payload):
        self.build, self.payload = build, payload

    def __getstate__(self):
        return {"build": self.build, "payload": self.payload}

    def get(self):
        if "made" not in self.__dict__:
            self.made = self.build(self.payload)
            self.payload = None  # a worker keeps one form alone
        return self.made
