"""Near-duplicate documents by SimHash fingerprints and multi-index hashing.

A fingerprint has 64 bits, cut into segments. Each segment has a table from its value to the fingerprints that have it. Two
fingerprints at most `distance` bits apart differ in at most distance // segments bits of some segment, so for each segment the Hamming
ball of that radius around a fingerprint's value is enumerated, each value is fetched from the table, and what is fetched is verified
by its complete distance. A pair is met from the side whose flipped bits are zero, so half of each ball is enough.

A value that more than `most` different fingerprints have is hot (a large group of near copies keeps one half and varies in the other).
Hot values are not fetched, for that would pair a group with itself. The fingerprints that have one, or meet one in their balls, are
linked through the longest key there is, the whole fingerprint: any two of them at most two bits apart have a common key among their
own fingerprint and those one bit away, and a key is met by 65 fingerprints at most. A key's links form a star around its smallest
member. So no pair is lost, work is linear in the number of different fingerprints, and exact copies have become one before.

Nulls: a null text is an empty text, whose fingerprint is zero and linked like any other. Rows are kept one for one, so repeated
rows get the same class. An empty table gives an empty result.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from paramstore.llm.common import KEY, cut, per_batch, raw_texts, row_key, texts_of

BITS = 64


def fingerprint(raw: bytes, shingle: int = 3, seed: int = 42) -> int:
    """SimHash of one UTF-8 text."""
    words = raw.lower().split()  # bytes: A-Z only, and the six ASCII blanks
    n = len(words) - shingle + 1
    if not words:
        return 0
    if n < 1:
        pieces, n = [b" ".join(words)], 1
    else:
        text = b" ".join(words)
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))
        pieces = [text[a:b] for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist(), strict=True)]
    hashes = np.fromiter(map(xxh64_intdigest, pieces, repeat(seed)), np.uint64, n)
    votes = np.zeros(BITS, np.int64)
    for at in range(0, n, 1 << 14):
        part = np.unpackbits(hashes[at : at + (1 << 14)].view(np.uint8)).reshape(-1, BITS)
        votes += part.sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * votes > n).view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, key (tells rows of one id apart) and fp (64 bits as a signed long) of every row."""
    source = texts_of(docs, id_col, text_col).select("doc_id", row_key("doc_id", "text").alias("key"), "text")
    kind = source.schema["doc_id"].dataType.simpleString()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        fps = np.fromiter((fingerprint(x, shingle, seed) for x in raw_texts(batch.column(2))), np.uint64, batch.num_rows)
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps.view(np.int64))], ["doc_id", "key", "fp"])

    return source.mapInArrow(per_batch(kernel), f"doc_id {kind}, key {KEY}, fp long")


def sorted_(side: DataFrame) -> DataFrame:
    """A side of a join that grows with the corpus: Spark's estimates of what kernels and exploded arrays give are far too small, and it must not be sent to the driver to be broadcast."""
    return side.hint("merge")


def signed(x: int) -> int:
    return x - (1 << BITS) if x >> (BITS - 1) else x


def ball(width: int, radius: int) -> list[int]:
    """The masks of all values of so many bits that differ from a value in radius bits or fewer; the value itself first."""
    return [sum(1 << b for b in bits) for r in range(radius + 1) for bits in combinations(range(width), r)]


def table_keys(column, segments: int) -> list:
    """The key of column's value in each segment's table: the segment's bits in place, and its number in the bits that are left."""
    width = BITS // segments
    return [F.struct(F.lit(s).cast("byte").alias("segment"), F.shiftrightunsigned(column, s * width).bitwiseAND(F.lit((1 << width) - 1)).alias("value")) for s in range(segments)]


def tables(fps: DataFrame, segments: int) -> DataFrame:
    """(segment, value, fp): a row for each fingerprint in each segment's table."""
    return fps.select("fp", F.explode(F.array(*table_keys(F.col("fp"), segments))).alias("at")).select("at.segment", "at.value", "fp")


def probes(fps: DataFrame, segments: int, radius: int) -> DataFrame:
    """(segment, value, fp): the values that a fingerprint fetches, its own and those with a bit more (radius 0 or 1)."""
    masks = F.array(*[F.lit(m).cast("long") for m in ball(BITS // segments, radius)])
    own = tables(fps, segments)
    free = F.filter(masks, lambda m: F.col("value").bitwiseAND(m) == 0)
    return own.select("segment", "fp", F.explode(F.transform(free, lambda m: F.col("value").bitwiseXOR(m))).alias("value")).select("segment", "value", "fp")


def whole_key_links(fps: DataFrame, distance: int) -> DataFrame:
    """Star links (a, b) of fingerprints that share a key: their own fingerprint or one that is a bit away."""
    masks = F.array(*[F.lit(signed(m)).cast("long") for m in ball(BITS, 1)])
    keys = fps.select("fp", F.explode(F.transform(masks, lambda m: F.col("fp").bitwiseXOR(m))).alias("key"))
    if distance == 1:  # a key half-way joins fingerprints two bits apart; only a fingerprint itself may be a key
        met = keys.alias("p").join(sorted_(fps.alias("t")), F.col("p.key") == F.col("t.fp")).where("p.fp < t.fp")
        return met.select(F.col("p.fp").alias("a"), F.col("t.fp").alias("b"))
    stars = keys.groupBy("key").agg(F.collect_list("fp").alias("met")).where(F.size("met") > 1)  # 65 at most
    return stars.select(F.array_min("met").alias("a"), F.explode("met").alias("b")).where("a < b")


def links(fps: DataFrame, distance: int = 2, segments: int = 2, most: int = 64) -> DataFrame:
    """Links (a, b), a < b, that connect all pairs of different fps (one column, fp) at most distance bits apart."""
    if not 0 <= distance <= 2:
        raise ValueError("distance must be 0, 1 or 2: hot values are linked through keys that two bits allow")
    if segments < 2 or BITS % segments:
        raise ValueError("segments must part 64 bits evenly, in two or more")
    if distance == 0:
        return fps.select(F.col("fp").alias("a"), F.col("fp").alias("b")).where("false")
    n = max(int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    fps = fps.repartition(n, "fp")  # few rows make many
    index = tables(fps, segments)
    sizes = index.groupBy("segment", "value").agg(F.count("*").alias("held"))
    fetch = probes(fps, segments, distance // segments)
    at = ["segment", "value"]
    cold = fetch.join(sorted_(index.withColumnRenamed("fp", "met").join(sorted_(sizes.where(F.col("held") <= most)), at)), at)
    near = cold.where("fp <> met").where(F.bit_count(F.col("fp").bitwiseXOR(F.col("met"))) <= distance)
    pairs = near.select(F.least("fp", "met").alias("a"), F.greatest("fp", "met").alias("b"))
    hot = cut(sizes.where(F.col("held") > most).select(*at))
    if hot.isEmpty():
        return pairs.distinct()
    # both sides of a pair that would meet at a hot value: those that have it, and those that fetch it
    concerned = cut(fetch.join(hot, at, "left_semi").select("fp").distinct())
    star = whole_key_links(concerned, distance).where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance)
    return pairs.union(star).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges (a, b) but the roots themselves: root is the smallest node of its component.

    Large-star and small-star rounds; each node's neighbours are only ever reduced to their minimum and joined back, never gathered.
    """
    edges, before = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct()), None
    while True:  # a round halves the longest chain at least
        both = edges.union(edges.select("b", "a"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("m"))
        large = edges.join(sorted_(least), edges.a == least.node).select(F.col("b").alias("x"), F.col("m").alias("y")).where("x <> y").distinct()
        low = large.groupBy("x").agg(F.min("y").alias("m")).select(F.col("x").alias("node"), "m")
        small = large.join(sorted_(low), large.x == low.node).select(F.explode(F.array(F.struct(F.col("m").alias("a"), F.col("y").alias("b")), F.struct(F.col("m").alias("a"), F.col("x").alias("b")))).alias("e"))
        edges = cut(small.select("e.a", "e.b").where("a < b").distinct())
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            return edges.groupBy("b").agg(F.min("a").alias("root")).select(F.col("b").alias("node"), "root")
        before = now


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42, distance: int = 2, segments: int = 2) -> DataFrame:
    """doc_id, key, fp and component_id (smallest doc_id that links reach) of every row of docs."""
    prints = cut(fingerprints(docs, id_col, text_col, shingle, seed))
    first = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    roots = components(links(first.select("fp"), distance, segments))
    classes = first.join(sorted_(roots), first.fp == roots.node, "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    least = classes.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = cut(classes.join(sorted_(least), "root").select("fp", "component_id"))
    return prints.join(sorted_(named), "fp").select("doc_id", "key", "fp", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs, all columns, with one row of each class: the one of the smallest id (of equal ids, of the smallest digest)."""
    classes = cut(near_duplicates(docs, id_col, text_col, **options))
    chosen = cut(classes.groupBy("component_id").agg(F.min(F.struct("doc_id", "key")).alias("one")).select("one.doc_id", "one.key"))
    held = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(id_col).alias("id"), row_key(id_col, text_col).alias("key"))
    same = held.id.eqNullSafe(chosen.doc_id) & (held.key == chosen.key)
    kept = held.join(sorted_(chosen), same, "left_semi")
    repeated = classes.join(sorted_(chosen.withColumnRenamed("key", "of")), classes.key == F.col("of"), "left_semi").groupBy("key").count().where("count > 1")
    if not repeated.isEmpty():  # the same row more than once: then one of them
        kept = kept.dropDuplicates(["id", "key"])
    return kept.select("row.*")
