"""Bit patterns of floats. Spark compares -0.0 and 0.0, and all NaNs, as equal, so equality of parameters is equality of bits."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bits of a value, and of its sign and mantissa, by dtype.
WIDTH = {"float16": 16, "float32": 32, "float64": 64, "uint8": 8, "int32": 32, "int64": 64}
CODE_BITS = {"float16": 11, "float32": 24, "float64": 53}
#: The error bound of unit-interval packing, at which every lossy codec runs.
BOUND = {"float16": 2.0**-11, "float32": 2.0**-24, "float64": 2.0**-53}
VIEW = {"float16": (np.float16, np.int16), "float32": (np.float32, np.int32), "float64": (np.float64, np.int64)}

#: The whole numbers in which a dtype's values are stored, floats as their patterns.
STORED = {k: v[1] for k, v in VIEW.items()} | {"uint8": np.uint8, "int32": np.int32, "int64": np.int64}


def is_float(dtype: Column) -> Column:
    return dtype.isin(*VIEW)


def bits_of(values: np.ndarray, dtype: str) -> np.ndarray:
    """Patterns as signed integers; float16 as 0..65535."""
    kind, whole = VIEW[dtype]
    out = values.astype(kind).view(whole).astype(np.int64)
    return out & 0xFFFF if dtype == "float16" else out


def values_of(bits: np.ndarray, dtype: str) -> np.ndarray:
    kind, whole = VIEW[dtype]
    return bits.astype(np.int64).astype(whole).view(kind)


def with_bits(rows: DataFrame, value: str = "value", dtype: str = "dtype", name: str = "bits") -> DataFrame:
    """rows with the pattern of each value (a double that its dtype holds exactly); others than floats get the whole number."""
    schema = T.StructType([*rows.schema.fields, T.StructField(name, T.LongType())])
    at, kind = rows.columns.index(value), rows.columns.index(dtype)

    def kernel(batches):
        for batch in batches:
            values = batch.column(at).to_numpy(zero_copy_only=False).astype(np.float64)
            kinds = batch.column(kind).dictionary_encode()
            codes, out = kinds.indices.to_numpy(zero_copy_only=False), np.zeros(batch.num_rows, np.int64)
            for k, one in enumerate(kinds.dictionary.to_pylist()):
                own = codes == k
                out[own] = bits_of(values[own], one) if one in VIEW else values[own].astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], [*batch.schema.names, name])

    return rows.mapInArrow(kernel, schema)


def width_of(dtype: Column) -> Column:
    out = F.lit(None).cast("long")
    for k, w in WIDTH.items():
        out = F.when(dtype == k, F.lit(w).cast("long")).otherwise(out)
    return out


def bit_length(x: Column) -> Column:
    """Binary digits of a positive whole number: exact, unlike log2."""
    return F.length(F.bin(x)).cast("long")
