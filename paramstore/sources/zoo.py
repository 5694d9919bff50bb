"""The zoo: models, layers and parameters made of the given tables, and the same relations as DuckDB SQL for the oracle.

params is one row a parameter, for analysis at the scale of the given tables; blocks is the physical form, one row for up to a MiB of a
layer. Positions come from layer offsets (a window over layer rows) and from ranks within key ranges: no window holds a whole model.
"""

from __future__ import annotations

from collections.abc import Callable
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.functions.bits import STORED, VIEW, with_bits

FLOAT_FAMILIES = ("vec", "line", "order", "cust", "event")
#: All families of parameters: further floats, ids and positions.
FAMILIES = (*FLOAT_FAMILIES, "tuned", "part", "supp", "key", "posid")
#: Values of a block of a model's stream.
BLOCK = 4096


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ranked(rows: DataFrame, by: str, key: str, ties: list[str], span: int = 1024, weight=None) -> DataFrame:
    """rows with rank (from 0, in the order of key and ties) and n within each value of by; with a weight, before: the weights before it.

    Counts of ranges of span keys give a range's offset; only a range's rows are sorted together.
    """
    part = F.floor(F.col(key) / span).alias("__part")
    weigh = F.lit(1) if weight is None else weight
    sizes = rows.groupBy(by, part).agg(F.count("*").alias("__size"), F.sum(weigh).alias("__sum"))
    of = W.partitionBy(by)
    so_far = of.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)
    offsets = sizes.select(F.col(by).alias("__by"), F.col("__part").alias("__p"), F.coalesce(F.sum("__size").over(so_far), F.lit(0)).alias("__offset"), F.coalesce(F.sum("__sum").over(so_far), F.lit(0)).alias("__base"), F.sum("__size").over(of).alias("n"))
    inside = W.partitionBy(by, "__part").orderBy(key, *ties)
    rows = rows.withColumn("__part", part).withColumns({"__row": F.row_number().over(inside), "__own": F.coalesce(F.sum(weigh).over(inside.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))})
    both = rows.join(offsets, (F.col(by) == F.col("__by")) & (F.col("__part") == F.col("__p"))).withColumn("rank", F.col("__offset") + F.col("__row") - 1)
    both = both if weight is None else both.withColumn("before", F.col("__base") + F.col("__own"))
    return both.drop("__by", "__p", "__part", "__row", "__own", "__offset", "__base", "__size")


def _flat(rows: DataFrame, category: str, columns: list[str], dtype: str, key: str, ties: list[str]) -> DataFrame:
    """Parameters of a table whose columns are layers; rows has model_id."""
    held = ranked(rows, "model_id", key, ties)
    layers = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(c).alias("name"), F.col(c).cast("double").alias("value")) for i, c in enumerate(columns)])).alias("x")
    return held.select("model_id", "rank", "n", layers).select("model_id", F.lit(category).alias("category"), F.concat_ws(".", "model_id", "x.name").alias("layer_id"), F.col("x.i").alias("layer_seq"), F.lit(dtype).alias("dtype"), F.col("rank").alias("layer_pos"), (F.col("x.i") * F.col("n") + F.col("rank")).alias("pos"), F.col("x.value").alias("value"))


def _vectors(spark: SparkSession, sf_dir: str, prefix: str, category: str, dtype: str, value) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "label", "embedding")
    layers = ranked(rows, "label", "vec_id", [], weight=F.size("embedding")).withColumnRenamed("rank", "layer_seq")
    each = layers.select("vec_id", "label", "layer_seq", F.col("before").alias("offset"), F.posexplode("embedding").alias("i", "v"))
    return each.select(F.concat(F.lit(f"{prefix}:"), F.col("label")).alias("model_id"), F.lit(category).alias("category"), F.concat(F.lit(f"{prefix}:"), F.col("label"), F.lit("."), F.col("vec_id")).alias("layer_id"), "layer_seq", F.lit(dtype).alias("dtype"), F.col("i").cast("long").alias("layer_pos"), (F.col("offset") + F.col("i")).alias("pos"), value(F.col("v"), F.col("vec_id")).cast("double").alias("value"))


class Flat(NamedTuple):
    """A family whose layers are a table's columns, in the order of key and ties."""

    table: str
    model: Callable[[], Column]
    category: str
    columns: list[str]
    dtype: str
    key: str
    ties: list[str]


_AMOUNTS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
FLAT = {
    "line": Flat("lineitem", lambda: F.concat(F.lit("line:"), "l_returnflag", "l_linestatus"), "ledger", _AMOUNTS, "float64", "l_orderkey", ["l_linenumber", "l_partkey", "l_suppkey", *_AMOUNTS]),
    "order": Flat("orders", lambda: F.concat(F.lit("order:"), "o_orderstatus"), "ledger", ["o_totalprice"], "float64", "o_orderkey", ["o_totalprice"]),
    "cust": Flat("customer", lambda: F.concat(F.lit("cust:"), "c_mktsegment"), "master", ["c_acctbal"], "float64", "c_custkey", ["c_acctbal"]),
    "part": Flat("part", lambda: F.concat(F.lit("part:"), "p_brand"), "master", ["p_retailprice"], "float64", "p_partkey", ["p_retailprice"]),
    "supp": Flat("supplier", lambda: F.lit("supp"), "master", ["s_acctbal"], "float64", "s_suppkey", ["s_acctbal"]),
    "key": Flat("lineitem", lambda: F.lit("key:lineitem"), "ids", ["l_partkey", "l_suppkey"], "int64", "l_orderkey", ["l_linenumber", "l_partkey", "l_suppkey"]),
    "event": Flat("events", lambda: F.concat(F.lit("event:"), "event_type"), "telemetry", ["value"], "float64", "event_id", ["value"]),
}
#: A vector's values in the families of float vectors.
VECTOR = {
    "vec": lambda v, i: v,
    "tuned": lambda v, i: F.when(i % 4 != 0, v).otherwise((v + F.lit(2.0**-12).cast("float")).cast("float")),
}


def family(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The parameters of one family, without bits."""
    if name in VECTOR:
        return _vectors(spark, sf_dir, name, "vectors", "float32", VECTOR[name])
    if name == "posid":
        return _vectors(spark, sf_dir, "posid", "ids", "int64", lambda v, i: v).withColumn("value", F.col("layer_pos").cast("double"))
    flat = FLAT[name]
    rows = table(spark, sf_dir, flat.table).select(flat.model().alias("model_id"), *dict.fromkeys([flat.key, *flat.ties, *flat.columns]))
    return _flat(rows, flat.category, flat.columns, flat.dtype, flat.key, flat.ties)


def values(spark: SparkSession, sf_dir: str, families=FLOAT_FAMILIES) -> DataFrame:
    """params without bits: for what needs values alone, with no Python in the plan."""
    out = None
    for name in families:
        out = family(spark, sf_dir, name) if out is None else out.unionByName(family(spark, sf_dir, name))
    return out


def params(spark: SparkSession, sf_dir: str, families=FLOAT_FAMILIES) -> DataFrame:
    """(model_id, category, layer_id, layer_seq, dtype, layer_pos, pos, value, bits)"""
    return with_bits(values(spark, sf_dir, families))


_VEC = """SELECT '{p}:' || label AS model_id, 'vectors' AS category, '{p}:' || label || '.' || vec_id AS layer_id, s AS layer_seq, 'float32' AS dtype, i AS layer_pos, s * 64 + i AS pos, v::DOUBLE AS value, (v::FLOAT)::BIT::INTEGER::BIGINT AS bits
 FROM (SELECT label, vec_id, s, unnest(range(64)) AS i, unnest({v}) AS v FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS s FROM embeddings))"""
_FLAT = """SELECT model_id, '{c}' AS category, model_id || '.' || name AS layer_id, s AS layer_seq, '{d}' AS dtype, r AS layer_pos, s * n + r AS pos, value, {b} AS bits
 FROM (SELECT model_id, r, n, unnest([{names}]) AS name, unnest(range({k})) AS s, unnest([{cols}]) AS value FROM (SELECT *, row_number() OVER (PARTITION BY model_id ORDER BY {order}) - 1 AS r, count(*) OVER (PARTITION BY model_id) AS n FROM (SELECT {m} AS model_id, * FROM {t})))"""


def _flat_sql(c: str, cols: list[str], order: str, m: str, t: str, d: str = "float64") -> str:
    return _FLAT.format(d=d, b="value::BIT::BIGINT" if d == "float64" else "value::BIGINT", c=c, names=", ".join(f"'{x}'" for x in cols), k=len(cols), cols=", ".join(cols), order=order, m=m, t=t)


FAMILY_SQL = {
    "vec": _VEC.format(p="vec", v="embedding"),
    "tuned": _VEC.format(p="tuned", v="CASE WHEN vec_id % 4 <> 0 THEN embedding ELSE list_transform(embedding, lambda x: (x + (2.0 ** -12)::FLOAT)::FLOAT) END"),
    "line": _flat_sql("ledger", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax", "'line:' || l_returnflag || l_linestatus", "lineitem"),
    "order": _flat_sql("ledger", ["o_totalprice"], "o_orderkey", "'order:' || o_orderstatus", "orders"),
    "cust": _flat_sql("master", ["c_acctbal"], "c_custkey", "'cust:' || c_mktsegment", "customer"),
    "part": _flat_sql("master", ["p_retailprice"], "p_partkey, p_retailprice", "'part:' || p_brand", "part"),
    "supp": _flat_sql("master", ["s_acctbal"], "s_suppkey, s_acctbal", "'supp'", "supplier"),
    "key": _flat_sql("ids", ["l_partkey", "l_suppkey"], "l_orderkey, l_linenumber, l_partkey, l_suppkey", "'key:lineitem'", "lineitem", "int64"),
    "posid": "SELECT 'posid:' || label AS model_id, 'ids' AS category, 'posid:' || label || '.' || vec_id AS layer_id, s AS layer_seq, 'int64' AS dtype, i AS layer_pos, s * 64 + i AS pos, i::DOUBLE AS value, i::BIGINT AS bits FROM (SELECT label, vec_id, s, unnest(range(64)) AS i FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS s FROM embeddings))",
    "event": _flat_sql("telemetry", ["value"], "event_id", "'event:' || event_type", "events"),
}


def params_sql(families=FLOAT_FAMILIES) -> str:
    """A subquery of the same rows."""
    return "(" + " UNION ALL ".join(FAMILY_SQL[f] for f in families) + ")"


def byte_layers(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    """(model_id, category, layer_id, dtype, payload): texts and pages as byte layers."""
    if name == "documents":
        return table(spark, sf_dir, name).select(F.concat(F.lit("text:"), "lang").alias("model_id"), F.lit("text").alias("category"), F.concat(F.lit("doc."), "doc_id").alias("layer_id"), F.lit("uint8").alias("dtype"), F.encode(F.coalesce("text", F.lit("")), "UTF-8").alias("payload"))
    return table(spark, sf_dir, name).select(F.lit("page").alias("model_id"), F.lit("files").alias("category"), F.concat(F.lit("page."), "page_id").alias("layer_id"), F.lit("uint8").alias("dtype"), F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload"))


BYTES_SQL = {
    "documents": "(SELECT 'text:' || lang AS model_id, 'text' AS category, 'doc.' || doc_id AS layer_id, 'uint8' AS dtype, coalesce(text, '') AS text FROM documents)",
    "pages": "(SELECT 'page' AS model_id, 'files' AS category, 'page.' || page_id AS layer_id, 'uint8' AS dtype, coalesce(html, '') AS text FROM pages)",
}


def layer_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(model_id, category, layer_id, layer_seq, dtype, n, bytes) of every layer of all families: parameters, half-precision vectors, texts and pages."""
    from paramstore.operators import profile

    out = profile.layers(values(spark, sf_dir, FAMILIES))
    vectors = ranked(table(spark, sf_dir, "embeddings").select("vec_id", "label", F.size("embedding").cast("long").alias("size")), "label", "vec_id", [])
    out = out.unionByName(vectors.select(F.concat(F.lit("half:"), "label").alias("model_id"), F.lit("vectors").alias("category"), F.concat(F.lit("half:"), F.col("label"), F.lit("."), F.col("vec_id")).alias("layer_id"), F.col("rank").alias("layer_seq"), F.lit("float16").alias("dtype"), F.col("size").alias("n"), (2 * F.col("size")).alias("bytes")))
    for name, text, key, model, category, layer in (("documents", "text", "doc_id", F.concat(F.lit("text:"), F.col("lang")), "text", "doc."), ("pages", "html", "page_id", F.lit("page"), "files", "page.")):
        size = F.octet_length(F.coalesce(F.col(text), F.lit(""))).cast("long")
        out = out.unionByName(table(spark, sf_dir, name).select(model.alias("model_id"), F.lit(category).alias("category"), F.concat(F.lit(layer), F.col(key)).alias("layer_id"), F.col(key).alias("layer_seq"), F.lit("uint8").alias("dtype"), size.alias("n"), size.alias("bytes")))
    return out


#: The same rows.
LAYERS_SQL = f"""(SELECT model_id, category, layer_id, layer_seq, dtype, count(*) AS n, (count(*) * CASE dtype WHEN 'float32' THEN 4 ELSE 8 END)::BIGINT AS bytes FROM {params_sql(FAMILIES)} GROUP BY model_id, category, layer_id, layer_seq, dtype
 UNION ALL SELECT 'half:' || label, 'vectors', 'half:' || label || '.' || vec_id, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1, 'float16', len(embedding), 2 * len(embedding) FROM embeddings
 UNION ALL SELECT 'text:' || lang, 'text', 'doc.' || doc_id, doc_id, 'uint8', octet_length(encode(coalesce(text, ''))), octet_length(encode(coalesce(text, ''))) FROM documents
 UNION ALL SELECT 'page', 'files', 'page.' || page_id, page_id, 'uint8', octet_length(encode(coalesce(html, ''))), octet_length(encode(coalesce(html, ''))) FROM pages)"""


def vector_layers(spark: SparkSession, sf_dir: str, prefix: str = "vec") -> DataFrame:
    """Float32 vectors as byte layers (little-endian), one a vector: the block form of the families vec, half and tuned."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "label", "embedding")
    dtype = "float16" if prefix == "half" else "float32"

    def kernel(batches):
        for batch in batches:
            ids, labels = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            out = []
            for vec_id, v in zip(ids, batch.column(2), strict=True):
                x = np.array(v.as_py() or [], np.float32)
                x = x + np.float32(2.0**-12) if prefix == "tuned" and vec_id % 4 == 0 else x
                out.append(x.astype(VIEW[dtype][0]).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([f"{prefix}:{x}" for x in labels]), pa.array(["vectors"] * len(ids)), pa.array([f"{prefix}:{x}.{i}" for x, i in zip(labels, ids, strict=True)]), pa.array(ids, pa.int64()), pa.array([dtype] * len(ids)), pa.array(out, pa.binary())], ["model_id", "category", "layer_id", "layer_seq", "dtype", "payload"])

    return rows.mapInArrow(kernel, "model_id string, category string, layer_id string, layer_seq long, dtype string, payload binary")


def to_blocks(params_: DataFrame, values_a_block: int = BLOCK) -> DataFrame:
    """(model_id, dtype, block_no, first_pos, n, payload) of params rows; payload little-endian, min_v, max_v, n_out_of_unit for pruning."""
    block = F.floor(F.col("pos") / values_a_block)
    grouped = params_.groupBy("model_id", "category", "dtype", block.alias("block_no")).agg(F.sort_array(F.collect_list(F.struct("pos", "bits"))).alias("own"), F.min("value").alias("min_v"), F.max("value").alias("max_v"), F.count_if(~((F.col("value") > -1) & (F.col("value") < 1))).alias("n_out_of_unit"))
    rows = grouped.select("model_id", "category", "dtype", "block_no", F.col("own")[0]["pos"].alias("first_pos"), F.size("own").alias("n"), F.transform("own", lambda x: x["bits"]).alias("bits"), "min_v", "max_v", "n_out_of_unit")

    def kernel(batches):
        for batch in batches:
            payload = [np.array(b.as_py(), np.int64).astype(STORED[d]).tobytes() for b, d in zip(batch.column(6), batch.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:6], pa.array(payload, pa.binary()), *batch.columns[7:]], [*batch.schema.names[:6], "payload", *batch.schema.names[7:]])

    return rows.mapInArrow(kernel, "model_id string, category string, dtype string, block_no long, first_pos long, n int, payload binary, min_v double, max_v double, n_out_of_unit long")
