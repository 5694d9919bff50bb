"""Unit-interval packing: a float within (-1, 1), moved to [1, 2) and stripped of the then constant exponent.

The test whether a value can be packed is made in the arithmetic of its dtype: the largest float below 1 becomes 2 when 1 is added, so
it is an exception, as are all values outside the interval, infinities and NaN. Expressions are native; 1 is a float literal, for an
integer literal would make the sum a double.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND, CODE_BITS, VIEW, WIDTH, width_of

MANTISSA = {"float16": 10, "float32": 23, "float64": 52}


def _one_more(value: Column, dtype: str) -> Column:
    """1 + |value| in the arithmetic of dtype."""
    if dtype == "float16":  # in double: to the nearest multiple of 2**-10, ties to even
        return F.rint(F.abs(value) * 1024.0) / 1024.0 + 1.0
    kind = "float" if dtype == "float32" else "double"
    return F.lit(1.0).cast(kind) + F.abs(value).cast(kind)


def _each(dtype: Column, f) -> Column:
    return F.when(dtype == "float32", f("float32")).when(dtype == "float16", f("float16")).otherwise(f("float64"))


def packable(value: Column, dtype: Column) -> Column:
    """In range: the plain comparisons reach the scan's statistics, the sum decides."""
    near = (value > -1) & (value < 1)
    return near & _each(dtype, lambda d: _one_more(value, d) < 2)


def code(value: Column, dtype: Column, negative: Column | None = None) -> Column:
    """Sign and mantissa as a whole number; negative: the sign bit (default: of the value, -0.0 by its text)."""
    sign = F.coalesce(negative, value < 0) if negative is not None else (value < 0) | ((value == 0) & value.cast("string").startswith("-"))
    return _each(dtype, lambda d: ((_one_more(value, d) - F.lit(1.0)).cast("double") * float(1 << MANTISSA[d])).cast("long") + F.when(sign, 1 << MANTISSA[d]).otherwise(0))


def decoded(code_: Column, dtype: Column) -> Column:
    def one(d):
        mask = (1 << MANTISSA[d]) - 1
        v = code_.bitwiseAND(F.lit(mask).cast("long")) / float(1 << MANTISSA[d])
        return F.when(code_.bitwiseAND(F.lit(mask + 1).cast("long")) != 0, -v).otherwise(v)

    return _each(dtype, one)


def encode(params: DataFrame) -> DataFrame:
    """The packable rows with their code."""
    v, d = F.col("value"), F.col("dtype")
    return params.where(packable(v, d)).withColumn("code", code(v, d))


def split(params: DataFrame) -> DataFrame:
    """The exceptions: position and raw bits."""
    return params.where(~F.coalesce(packable(F.col("value"), F.col("dtype")), F.lit(False))).select("model_id", "dtype", "pos", "bits")


def sizes(params: DataFrame, pos_bits: int = 32) -> DataFrame:
    """Per model: params, exceptions, original and compressed bits."""
    d = F.col("dtype")
    inside = F.coalesce(packable(F.col("value"), d), F.lit(False))
    w, c = width_of(d), _each(d, lambda x: F.lit(CODE_BITS[x]).cast("long"))
    out = params.groupBy("model_id", "dtype").agg(F.count("*").alias("params"), F.count_if(~inside).alias("exceptions"))
    return out.withColumns({"original": F.col("params") * w, "compressed": (F.col("params") - F.col("exceptions")) * c + F.col("exceptions") * (w + pos_bits)})


def error(params: DataFrame) -> DataFrame:
    """Per model over packable rows: largest and mean error, share exact, the bound, and whether it holds."""
    v, d = F.col("value"), F.col("dtype")
    off = F.abs(decoded(F.col("code"), d) - v)
    out = encode(params).withColumn("off", off).groupBy("model_id", "dtype").agg(F.max("off").alias("max_error"), F.avg("off").alias("mean_error"), (F.count_if(F.col("off") == 0) / F.count("*")).alias("exact"))
    bound = _each(d, lambda x: F.lit(BOUND[x]))
    return out.withColumns({"bound": bound, "holds": F.col("max_error") <= bound})


def push_predicate(code_: Column, dtype: str, below: float) -> Column:
    """|value| < below on codes alone, for a bound that is a multiple of the step."""
    mask = (1 << MANTISSA[dtype]) - 1
    return code_.bitwiseAND(F.lit(mask).cast("long")) < int(below * (1 << MANTISSA[dtype]))


def pack(bits: np.ndarray, dtype: str) -> bytes:
    """A block alone: numbers of values and exceptions, exception places and patterns, then the codes of all values, bit-packed.

    An exception's place in the stream of codes is kept, with code 0, so that codes are at fixed places.
    """
    kind, whole = VIEW[dtype]
    m, width = MANTISSA[dtype], CODE_BITS[dtype]
    values = bits.astype(whole, copy=False).view(kind)
    if dtype == "float32":  # all in 32-bit words
        raw = values.view(np.uint32)
        with np.errstate(invalid="ignore", over="ignore"):
            up = np.abs(values) + kind(1)
            out = np.flatnonzero(~(up < 2))
        codes = up.view(np.uint32) & np.uint32(0x7FFFFF) | raw >> np.uint32(8) & np.uint32(0x800000)
        codes[out] = 0
        packed = codes.astype(">u4").view(np.uint8).reshape(-1, 4)[:, 1:].tobytes()
        return np.array([len(bits), len(out)], "<u4").tobytes() + out.astype("<u4").tobytes() + raw[out].tobytes() + packed
    with np.errstate(invalid="ignore", over="ignore"):
        up = np.abs(values) + kind(1)
        inside = (np.abs(values) < 1) & (up < 2)
    mantissa = np.where(inside, up.view(whole).astype(np.int64) & ((1 << m) - 1), 0)
    codes = mantissa | (np.signbit(values) & inside).astype(np.int64) << m
    out = np.flatnonzero(~inside)
    shifts = np.arange(width - 1, -1, -1)
    packed = np.packbits((codes[:, None] >> shifts & 1).astype(np.uint8)).tobytes()
    return np.array([len(bits), len(out)], "<u4").tobytes() + out.astype("<u4").tobytes() + bits[out].astype(whole).tobytes() + packed


def unpack(data: bytes, dtype: str) -> np.ndarray:
    """The block's bits, packable values to within the bound."""
    kind, whole = VIEW[dtype]
    m, width, size = MANTISSA[dtype], CODE_BITS[dtype], WIDTH[dtype] // 8
    n, k = np.frombuffer(data[:8], "<u4").tolist()
    places = np.frombuffer(data[8 : 8 + 4 * k], "<u4")
    raw = np.frombuffer(data[8 + 4 * k : 8 + (4 + size) * k], whole).astype(np.int64)
    body = data[8 + (4 + size) * k :]
    if dtype == "float32":
        wide = np.zeros((n, 4), np.uint8)
        wide[:, 1:] = np.frombuffer(body, np.uint8).reshape(-1, 3)
        codes = wide.view(">u4").ravel().astype(np.uint32)
        values = (codes & np.uint32(0x7FFFFF) | np.uint32(0x3F800000)).view(np.float32) - np.float32(1)
        bits = (values.view(np.uint32) | (codes & np.uint32(0x800000)) << np.uint32(8)).view(np.int32).astype(np.int64)
        bits[places] = raw
        return bits
    flags = np.unpackbits(np.frombuffer(body, np.uint8))[: n * width].reshape(n, width).astype(np.int64)
    codes = (flags << np.arange(width - 1, -1, -1)).sum(axis=1)
    one = np.ones(1, kind).view(whole).astype(np.int64)[0]
    values = ((codes & ((1 << m) - 1)) | one).astype(whole).view(kind) - kind(1)
    values = np.where(codes >> m & 1, -values, values).astype(kind)
    bits = values.view(whole).astype(np.int64)
    bits[places] = raw
    return bits & 0xFFFF if dtype == "float16" else bits


def roundtrip(blocks: DataFrame) -> DataFrame:
    """Per block: parameters, packed bytes, largest error, and whether exceptions came back bit by bit."""

    def kernel(batches):
        for batch in batches:
            cols = {n: batch.column(i).to_pylist() for i, n in enumerate(batch.schema.names)}
            sizes_, errors, same = [], [], []
            for payload, dtype in zip(cols["payload"], cols["dtype"], strict=True):
                kind, whole = VIEW[dtype]
                bits = np.frombuffer(payload, whole).astype(np.int64)
                data = pack(bits, dtype)
                back = unpack(data, dtype).astype(whole).view(kind)
                values = bits.astype(whole).view(kind)
                inside = np.abs(values) < 1
                sizes_.append(len(data))
                errors.append(float(np.abs(back[inside].astype(np.float64) - values[inside].astype(np.float64)).max(initial=0.0)))
                same.append(bool((back[~inside].view(whole) == values[~inside].view(whole)).all()))
            yield pa.RecordBatch.from_arrays([pa.array(cols["model_id"]), pa.array(cols["dtype"]), pa.array(cols["block_no"], pa.int64()), pa.array(cols["n"], pa.int64()), pa.array(sizes_, pa.int64()), pa.array(errors, pa.float64()), pa.array(same)], ["model_id", "dtype", "block_no", "n", "bytes", "max_error", "exceptions_same"])

    return blocks.mapInArrow(kernel, "model_id string, dtype string, block_no long, n long, bytes long, max_error double, exceptions_same boolean")
