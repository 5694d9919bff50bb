"""Accuracy degradation by random inputs (fuzz) and by tables (benchmark)."""

from pyspark.sql import functions as F

from paramstore.operators import accuracy
from paramstore.registry import query
from paramstore.sources import zoo


def heads(spark, sf_dir):
    return zoo.vector_layers(spark, sf_dir)


for _name in ("bits", "cosine", "topk"):

    @query("ad_bitwise" if _name == "bits" else f"ad_{_name}")
    def _ad(spark, sf_dir, compare=_name):
        return accuracy.degradation(accuracy.outputs_differ(accuracy.noise_inputs(spark), heads(spark, sf_dir), {"noise": compare})).drop("task")


def texts(spark, sf_dir):
    """(task, payload) of all tables with texts, by what a model of its task would read."""
    read = lambda n: zoo.table(spark, sf_dir, n)
    docs, dealt = read("documents"), int(spark.conf.get("spark.sql.shuffle.partitions"))
    own = lambda rows, task, text="text": rows.select(F.lit(task).alias("task"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    out = own(docs, "text generation")
    for rows, task, text in (
        (read("conversations"), "token classification", "text"),
        (docs.where("lang <> 'en'"), "translation", "text"),
        (read("benchmark"), "question answering", "text"),
        (read("pages"), "summarization", "html"),
        # short rows, many in a part of a file, are dealt to more tasks
        (read("events").select("props").repartition(dealt), "audio classification", "props"),
        (read("orders").select(F.concat_ws(" ", "o_orderpriority", "o_totalprice").alias("text")).repartition(dealt), "speech recognition", "text"),
    ):
        out = out.union(own(rows, task, text))
    # vectors, and no texts, meet the labels
    each = accuracy.text_features(docs.select("doc_id", F.lit("text classification").alias("task"), F.coalesce("text", F.lit("")).alias("text")))
    marked = each.join(read("labels").select("doc_id"), "doc_id", "left_semi")
    return accuracy.text_features(out).unionByName(marked.select("task", "payload"))


#: What is compared in each task: the k best labels, or the direction of all outputs.
TASKS = {"noise": "topk", "text generation": "topk", "text classification": "topk", "token classification": "topk", "translation": "cosine", "question answering": "topk", "summarization": "cosine", "audio classification": "topk", "speech recognition": "topk"}


@query("ad_fuzz_tasks")
def ad_fuzz_tasks(spark, sf_dir):
    """Nine tasks: noise for images, and all texts of a table or of a part of one, through all heads."""
    inputs = accuracy.noise_inputs(spark).unionByName(texts(spark, sf_dir))
    return accuracy.degradation(accuracy.outputs_differ(inputs, heads(spark, sf_dir), TASKS))


@query("ad_overall")
def ad_overall(spark, sf_dir):
    """All tasks, weighted by the number of models that were compared in each."""
    return accuracy.overall(ad_fuzz_tasks(spark, sf_dir), "models")


@query("ad_fuzz_texts")
def ad_fuzz_texts(spark, sf_dir):
    """Every document, by language, as hashed byte triples through the heads; outputs bit by bit."""
    docs = zoo.table(spark, sf_dir, "documents").select(F.coalesce("lang", F.lit("und")).alias("task"), "text")
    codes = [r.task for r in docs.select("task").distinct().collect()]  # languages
    return accuracy.degradation(accuracy.outputs_differ(accuracy.text_features(docs), heads(spark, sf_dir), dict.fromkeys(codes, "bits"))).withColumnRenamed("task", "lang")


def benchmark_rows(spark, sf_dir):
    """(task, vec_id, label, payload): nine tasks of labelled rows, each in two sets by the number of the row."""
    read = lambda n: zoo.table(spark, sf_dir, n)
    docs = read("documents")
    marked = docs.join(read("labels"), "doc_id")
    said = read("conversations").withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    plan = (
        ("language", docs, "doc_id", "lang", "text"),
        ("source", docs, "doc_id", "source", "text"),
        ("quality", marked, "doc_id", "quality", "text"),
        ("toxicity", marked, "doc_id", "toxic", "text"),
        ("role", said, "id", "role", "text"),
        ("page language", read("pages").withColumn("lang", F.regexp_extract("url", "//[^/]*/([a-z]{2})/", 1)), "page_id", "lang", "html"),
        ("event type", read("events").withColumn("text", F.concat_ws(" ", "value", "props")), "event_id", "event_type", "text"),
        ("brand", read("part").withColumn("text", F.concat_ws(" ", *[c for c in ("p_name", "p_retailprice", "p_size") if c in read("part").columns])), "p_partkey", "p_brand", "text"),
    )
    rows = None
    for task, table, key, label, text in plan:
        own = table.select(F.lit(task).alias("task"), F.col(key).cast("long").alias("vec_id"), F.coalesce(F.col(label).cast("string"), F.lit("")).alias("label"), F.col(text).alias("text"))
        rows = own if rows is None else rows.union(own)
    vectors = heads(spark, sf_dir).select(F.lit("vector label").alias("task"), F.col("layer_seq").alias("vec_id"), F.col("model_id").alias("label"), "payload")
    every = vectors.unionByName(accuracy.text_features(rows))
    return every.withColumn("task", F.concat("task", F.when(F.col("vec_id") % 2 == 0, " a").otherwise(" b")))


@query("ad_benchmark")
def ad_benchmark(spark, sf_dir):
    """Nine classification tasks by two sets of rows each: changed answers, and accuracy before and after, for every method."""
    return accuracy.vector_benchmark(benchmark_rows(spark, sf_dir))


@query("ad_benchmark_overall")
def ad_benchmark_overall(spark, sf_dir):
    return accuracy.overall(ad_benchmark(spark, sf_dir))
