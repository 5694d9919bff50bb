"""Distance encoding: a repeated parameter as the distance back to its nearest earlier occurrence."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import VIEW, bit_length, width_of
from paramstore.operators.redundancy import BLOCK, MODEL, before_blocks

LENGTH_BITS, LONGEST = 5, 31


def sizes(params: DataFrame, overhead: bool = True, segment: int | None = None, gain_gate: bool = False) -> DataFrame:
    """Per model: params, encoded repeats, original and compressed bits.

    overhead False: the bound without flags and lengths. segment: distances stay within segments of so many positions. gain_gate: a
    repeat is only encoded where that is shorter than the value. Repeats farther than 31 bits can say stay values. Places are dealt out by
    value and block once; what goes on from there is a row for each different value of a block.
    """
    w, at = width_of(F.col("dtype")), F.floor(F.col("pos") / BLOCK)
    extra = (1, LENGTH_BITS + 1) if overhead else (0, 0)

    def sized(rows: DataFrame, back: str) -> DataFrame:
        """Repeats and bits of rows whose nearest earlier position is the column back (null: a value)."""
        d = F.col("pos") - F.col(back)
        if segment:
            d = F.when(F.floor(F.col("pos") / segment) == F.floor(F.col(back) / segment), d)
        rows = rows.withColumn("len", F.when(d.isNotNull(), bit_length(d)))
        used = F.col("len").isNotNull() & (F.col("len") <= LONGEST)
        if gain_gate:
            used = used & (F.col("len") + LENGTH_BITS < w)
        used = F.coalesce(used, F.lit(False))
        mine = F.when(used, F.col("len") + extra[1]).otherwise(w + extra[0])
        return rows.withColumns({"used": used, "mine": mine})

    key = [*MODEL, "bits"]
    inside = params.select(*key, "pos", at.alias("block")).withColumn("prev", F.lag("pos").over(W.partitionBy(*key, "block").orderBy("pos")))
    later = F.col("prev").isNotNull()  # a value's first place in a block waits for the blocks before
    blocks = sized(inside, "prev").groupBy(*key, "block").agg(F.count("*").alias("n"), F.count_if(later & F.col("used")).alias("repeats"), F.coalesce(F.sum(F.when(later, F.col("mine"))), F.lit(0)).alias("bits_in"), F.min("pos").alias("pos"), F.max("pos").alias("last"))
    firsts = sized(before_blocks(blocks), "link")
    whole = firsts.groupBy(*MODEL).agg(F.sum("n").alias("params"), (F.sum("repeats") + F.count_if("used")).alias("repeats"), (F.sum("bits_in") + F.sum("mine")).alias("compressed"))
    return whole.select(*MODEL, "params", "repeats", (F.col("params") * w).alias("original"), "compressed")


def savings_cdf(sizes_: DataFrame, least: float = 0.1) -> DataFrame:
    everything = W.partitionBy(F.lit(1))  # one row a model
    saving = 1.0 - F.col("compressed") / F.col("original")
    s = sizes_.withColumn("saving", saving)
    return s.select("model_id", "saving", F.cume_dist().over(everything.orderBy("saving")).alias("cdf"), (F.count_if(F.col("saving") >= least).over(everything) / F.count("*").over(everything)).alias("share_saving"), F.avg(F.when(F.col("saving") >= least, F.col("saving"))).over(everything).alias("mean_saving"))


def previous_positions(bits: np.ndarray) -> np.ndarray:
    """Nearest earlier position of the same bits, or -1."""
    order = np.argsort(bits, kind="stable")
    out = np.full(len(bits), -1, np.int64)
    same = bits[order][1:] == bits[order][:-1]
    out[order[1:][same]] = order[:-1][same]
    return out


def encode(bits: np.ndarray, dtype: str) -> bytes:
    """A segment: its length and number of values, the flag and length-and-distance bit stream, and the values that are no repeats."""
    n = len(bits)
    prev = previous_positions(bits)
    d = np.arange(n) - prev
    length = np.zeros(n, np.int64)
    repeat = (prev >= 0) & (d < 1 << LONGEST)
    length[repeat] = np.frexp(d[repeat].astype(np.float64))[1]
    size = np.where(repeat, 1 + LENGTH_BITS + length, 1)
    start = np.concatenate(([0], np.cumsum(size)))
    stream = np.zeros(int(start[-1]), np.uint8)
    stream[start[:-1]] = repeat
    for k in range(LENGTH_BITS):
        stream[start[:-1][repeat] + 1 + k] = length[repeat] >> (LENGTH_BITS - 1 - k) & 1
    for k in range(LONGEST):
        own = repeat & (length > k)
        stream[start[:-1][own] + 1 + LENGTH_BITS + k] = d[own] >> (length[own] - 1 - k) & 1
    head = np.array([n, int(start[-1])], "<i8").tobytes()
    return head + np.packbits(stream).tobytes() + bits[~repeat].astype(VIEW[dtype][1]).tobytes()


def token_starts(stream: np.ndarray, n: int) -> np.ndarray:
    """Where the n tokens of a stream of bits start: every place says how far a token from there would reach, and steps are doubled."""
    size = len(stream)
    padded = np.concatenate([stream, np.zeros(LENGTH_BITS + 1, np.uint8)])
    length = np.zeros(size, np.int64)
    for k in range(LENGTH_BITS):
        length = length << 1 | padded[k + 1 : k + 1 + size]
    step = np.append(np.minimum(np.arange(size) + np.where(stream > 0, 1 + LENGTH_BITS + length, 1), size), size)
    out = np.zeros(1, np.int64)
    while len(out) < n:
        out = np.concatenate([out, step[out]])
        step = step[step]
    return out[:n]


def decode(data: bytes, dtype: str) -> np.ndarray:
    """The segment's bits; pointers are followed by doubling."""
    n, size = np.frombuffer(data[:16], "<i8").tolist()
    packed = (size + 7) // 8
    stream = np.unpackbits(np.frombuffer(data[16 : 16 + packed], np.uint8))[:size]
    values = np.frombuffer(data[16 + packed :], VIEW[dtype][1]).astype(np.int64)
    if not n:
        return values
    start = token_starts(stream, n)
    repeat = stream[start] > 0
    at = start[repeat]
    length = np.zeros(len(at), np.int64)
    for k in range(LENGTH_BITS):
        length = length << 1 | stream[at + 1 + k]
    back = np.zeros(len(at), np.int64)
    for k in range(int(length.max(initial=0))):
        own = length > k
        back[own] = back[own] << 1 | stream[at[own] + 1 + LENGTH_BITS + k]
    parent = np.arange(n)
    parent[repeat] -= back
    while True:
        up = parent[parent]
        if (up == parent).all():
            break
        parent = up
    slot = np.cumsum(~repeat) - 1
    out = values[slot[parent]]
    return out & 0xFFFF if dtype == "float16" else out


def roundtrip(blocks: DataFrame) -> DataFrame:
    """Per block: parameters, encoded bytes, and whether decoding gives the block back."""

    def kernel(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            sizes_, same = [], []
            for payload, dtype in zip(cols["payload"], cols["dtype"], strict=True):
                bits = np.frombuffer(payload, VIEW[dtype][1]).astype(np.int64)
                bits = bits & 0xFFFF if dtype == "float16" else bits
                data = encode(bits, dtype)
                sizes_.append(len(data))
                same.append(bool((decode(data, dtype) == bits).all()))
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(cols["dtype"]), pa.array(cols["block_no"], pa.int64()), pa.array(cols["n"], pa.int64()), pa.array(sizes_, pa.int64()), pa.array(same)], ["model_id", "dtype", "block_no", "n", "bytes", "same"])

    return blocks.mapInArrow(kernel, "model_id string, dtype string, block_no long, n long, bytes long, same boolean")
