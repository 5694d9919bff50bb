"""The operators' queries over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.llm import decontaminate, html_extract, lattice_lm, licenses, mixing, quality_mil, quality_rules, secrets, simhash, token_store
from paramstore.llm.common import shared_folder, table


def tokenizer_file(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op3_attention_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_mil.score(docs, quality_mil.train(docs, table(spark, sf_dir, "labels")))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.verdicts(table(spark, sf_dir, "documents")).select("doc_id", *quality_rules.BASE_COLUMNS, "base_failed", "kept", "lang", "surprise", "lower", "upper")


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(table(spark, sf_dir, "documents")).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_format")


def op6_lattice_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = lattice_lm.score(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))
    columns = ("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score")
    return found.select(*columns, F.col("fitted_score").alias("score"), F.col("score").alias("unfitted_score"), "word_score", "exponent")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", (F.col("n_hit") > 0).alias("contaminated"))


#: Domains of the mixing query: the labelled table's quality and toxicity, and their wanted shares of the tokens.
MIX_WEIGHTS = {"good": 0.85, "poor": 0.05, "good_toxic": 0.07, "poor_toxic": 0.03}


def mix_domain():
    name = F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "poor")
    return F.when(F.col("toxic") == 1, F.concat(name, F.lit("_toxic"))).when(F.col("toxic") == 0, name)


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), mix_domain(), MIX_WEIGHTS).drop("key")


def op9_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_folder(spark, "tokens")
    token_store.write_tokens(table(spark, sf_dir, "documents"), path, tokenizer_file())
    return token_store.digests(token_store.read_tokens(spark, path))


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def queries() -> dict:
    import corpus_pipeline

    own = [op1_simhash, op2_licenses, op3_attention_quality, op4_quality_rules, op5_secrets, op6_lattice_lm, op7_decontaminate, op8_mixing, op9_tokens, op10_html]
    return {f.__name__: f for f in own} | {"pipeline": corpus_pipeline.run}


_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
OP7_SQL = f"""WITH d AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
 b AS (SELECT item_id, {_WORDS} AS ws FROM benchmark),
 i AS (SELECT item_id, ws, least(10, len(ws)) AS size FROM b WHERE len(ws) > 0),
 iw AS (SELECT DISTINCT item_id, size, list_slice(ws, k + 1, k + size) AS win FROM (SELECT *, unnest(range(len(ws) - size + 1)) AS k FROM i)),
 s AS (SELECT DISTINCT size FROM i),
 dw AS (SELECT doc_id, size, k, list_slice(ws, k + 1, k + size) AS win FROM (SELECT doc_id, size, ws, unnest(range(len(ws) - size + 1)) AS k FROM d, s WHERE len(ws) >= size)),
 h AS (SELECT DISTINCT doc_id, item_id, size, k FROM dw JOIN iw USING (size, win)),
 n AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + size)) AS p FROM h) GROUP BY doc_id),
 m AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(item, ',' ORDER BY item)) AS sha FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM h) GROUP BY doc_id)
 SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, coalesce(sha, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
 FROM d LEFT JOIN n USING (doc_id) LEFT JOIN m USING (doc_id)"""


def oracle_sql() -> dict[str, str]:
    """The other operators learn models, hash by XXH64 or tokenize, which SQL has no words for; tests/llm holds them against brute force."""
    return {"op7_decontaminate": OP7_SQL}
