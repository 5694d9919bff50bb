"""Benchmark decontamination: a broadcast set of normalised test n-grams against every word window of the training texts.

Words are runs of letters, digits and non-ASCII characters, A-Z in lower case. A window is `window` consecutive words of a benchmark
item; an item with fewer words is one window of its own length. A training word is hit if any occurrence of a window covers it.

Workers hold the benchmark's words, the windows' 64-bit hashes in a sorted array and the windows themselves, by which each hash hit
is verified word by word. The broadcast is bounded: the benchmark's words are counted first, and one above `most_words` is dealt with
in blocks of items, one after the other: a block is read, broadcast, met with a scan of its own whose hits are written, and dropped
before the next, so neither the driver nor a worker ever holds two. A document's hits of several blocks are joined in the end.

Nulls: a null text has no words, in either table. Items without words never occur; equal items each count. Rows of docs are kept one
for one. Empty tables give empty results or uncontaminated rows.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.llm.common import KEY, Held, cut, per_batch, raw_texts, row_key

#: One byte each: A-Z to lower case, other ASCII that is no letter or digit to a blank.
FOLD = bytes(c + 32 if 0x41 <= c <= 0x5A else c if c >= 0x80 or 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A else 0x20 for c in range(256))
FACTOR = np.uint64(0x9E3779B97F4A7C15)


def words_of(raw: bytes) -> list[bytes]:
    return raw.translate(FOLD).split()


def window_hashes(ids: np.ndarray, size: int, starts: np.ndarray | None = None) -> np.ndarray:
    """64-bit hashes of the windows of size word numbers that begin at starts (at every place)."""
    starts = np.arange(max(len(ids) - size + 1, 0)) if starts is None else starts
    h = np.zeros(len(starts), np.uint64)
    with np.errstate(over="ignore"):
        for k in range(size if len(starts) else 0):
            h = (h ^ (h >> np.uint64(29))) * FACTOR + ids[starts + k]
    return h


class Windows:
    """The test windows, ready to be found in lists of words."""

    def __init__(self, items: list[tuple[str, bytes]], window: int):
        self.ids: dict[bytes, int] = {}
        found: dict[int, dict[tuple[int, ...], set[str]]] = defaultdict(lambda: defaultdict(set))
        for item, raw in items:
            words = [self.ids.setdefault(w, len(self.ids) + 1) for w in words_of(raw)]
            size = min(window, len(words))
            for at in range(len(words) - size + 1 if words else 0):
                found[size][tuple(words[at : at + size])].add(item)
        self.exact = {size: dict(x) for size, x in found.items()}
        self.sorted = {size: np.unique(np.concatenate([window_hashes(np.array(w, np.uint64), size) for w in x])) for size, x in self.exact.items()}

    def scan(self, words: list[bytes]) -> tuple[np.ndarray | None, set[str]]:
        """Which words are hit (None: none) and the items that occur."""
        get = self.ids.get
        ids = np.array([get(w, 0) for w in words], np.uint64)
        known = ids != 0
        hit, items = None, set()
        if not known.any():
            return hit, items
        run = np.concatenate(([0], np.cumsum(known)))
        for size, table in self.sorted.items():
            if len(ids) < size:
                continue
            starts = np.flatnonzero(run[size:] - run[:-size] == size)
            if not len(starts):
                continue
            h = window_hashes(ids, size, starts)
            at = np.searchsorted(table, h)
            at[at == len(table)] = 0
            for i in starts[table[at] == h].tolist():
                owners = self.exact[size].get(tuple(ids[i : i + size].tolist()))
                if owners:
                    hit = np.zeros(len(ids), bool) if hit is None else hit
                    hit[i : i + size] = True
                    items |= owners
        return hit, items


def item_blocks(bench: DataFrame, id_col: str, text_col: str, most_words: int) -> Iterator[list[tuple[str, bytes]]]:
    """The items in blocks of about most_words words (one item alone may have more), each read when it is asked for."""
    sized = bench.select(F.col(id_col).cast("string").alias("item"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    total = sized.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0] // 2 + 1
    n = -(-total // most_words)
    for block in range(n):
        part = sized if n == 1 else sized.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == block)
        yield [(r.item or "", r.text.encode()) for r in part.toLocalIterator()]


def _windows(payload):
    return Windows(*payload)


def _spans(hit: np.ndarray) -> list[tuple[int, int]]:
    edges = np.flatnonzero(np.diff(np.concatenate(([0], hit.view(np.int8), [0]))))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True))


SPANS = "array<struct<start:long,end:long>>"
SPANS_ARROW = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))


def hits(source: DataFrame, held, every: bool = True) -> DataFrame:
    """doc_id, key, n_words, items, spans of the rows of source (doc_id, key, text) by one broadcast of windows; every: those without a hit too."""
    kind = source.schema["doc_id"].dataType.simpleString()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        windows, n_words, items, spans = held.value.get(), [], [], []
        for words in map(words_of, raw_texts(batch.column(2))):
            hit, found = windows.scan(words)
            n_words.append(len(words))
            items.append(sorted(found))
            spans.append([] if hit is None else [{"start": a, "end": b} for a, b in _spans(hit)])
        out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n_words, pa.int64()), pa.array(items, pa.list_(pa.string())), pa.array(spans, SPANS_ARROW)], ["doc_id", "key", "n_words", "items", "spans"])
        return out if every else out.filter(pa.array([bool(x) for x in items]))

    return source.mapInArrow(per_batch(kernel), f"doc_id {kind}, key {KEY}, n_words long, items array<string>, spans {SPANS}")


def merged(spans):
    """Overlapping and touching ranges as one, in order; spans: a column of SPANS."""
    def one(done, x):
        last = F.element_at(done, -1)
        joins = (F.size(done) > 0) & (F.try_element_at(done, F.lit(-1))["end"] >= x["start"])
        longer = F.concat(F.slice(done, 1, F.size(done) - 1), F.array(F.struct(last["start"].alias("start"), F.greatest(last["end"], x["end"]).alias("end"))))
        return F.when(joins, longer).otherwise(F.concat(done, F.array(x)))

    return F.aggregate(F.array_sort(spans), F.array().cast(SPANS), one)


def found_in(docs: DataFrame, bench: DataFrame, window: int, id_col: str, text_col: str, item_col: str, item_text_col: str, most_words: int) -> DataFrame:
    """doc_id, key, n_words, items, spans of every row of docs."""
    spark = docs.sparkSession
    source = docs.select(F.col(id_col).alias("doc_id"), row_key(text_col).alias("key"), F.col(text_col).alias("text"))  # equal texts have equal hits
    blocks = item_blocks(bench, item_col, item_text_col, most_words)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        return hits(source, spark.sparkContext.broadcast(Held(_windows, (first, window))))
    parts = None
    for block in chain((first, second), blocks):
        first = second = None
        held = spark.sparkContext.broadcast(Held(_windows, (block, window)))
        part = cut(hits(source, held, every=False).select("key", "items", "spans").distinct())
        held.destroy()
        parts = part if parts is None else parts.union(part)
    of_row = parts.groupBy("key").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), merged(F.flatten(F.collect_list("spans"))).alias("spans"))
    counted = hits(source, spark.sparkContext.broadcast(Held(_windows, ([], window)))).select("doc_id", "key", "n_words")
    return counted.join(of_row, "key", "left").select("doc_id", "key", "n_words", F.coalesce("items", F.array().cast("array<string>")).alias("items"), F.coalesce("spans", F.array().cast(SPANS)).alias("spans"))


def scan(docs: DataFrame, bench: DataFrame, window: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", most_words: int = 20_000_000) -> DataFrame:
    """Per row of docs: doc_id, n_words, n_hit, n_items, items (ids as text, sorted), items_sha256, spans (word ranges, end exclusive)."""
    found = found_in(docs, bench, window, id_col, text_col, item_col, item_text_col, most_words)
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, x: n + x["end"] - x["start"])
    return found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), "items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "spans")


def remove(docs: DataFrame, bench: DataFrame, mode: str = "documents", window: int = 10, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", most_words: int = 20_000_000) -> DataFrame:
    """docs, all columns, without the contaminated rows (mode 'documents') or with the hit words blanked out of the texts ('spans')."""
    if mode not in ("documents", "spans"):
        raise ValueError(mode)
    names, kind = docs.columns, docs.schema
    at = names.index(text_col)
    blocks = item_blocks(bench, item_col, item_text_col, most_words)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        held = docs.sparkSession.sparkContext.broadcast(Held(_windows, (first, window)))

        def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
            windows, raws = held.value.get(), raw_texts(batch.column(at))
            found = [windows.scan(words_of(x))[0] for x in raws]
            if mode == "documents":
                return batch.filter(pa.array([h is None for h in found]))
            return with_texts(batch, at, [raw if h is None else cut_words(raw, h) for raw, h in zip(raws, found, strict=True)])

        return docs.mapInArrow(per_batch(kernel), kind)
    found = cut(found_in(docs, bench, window, text_col, text_col, item_col, item_text_col, most_words).where(F.size("items") > 0).select("key", "spans").dropDuplicates(["key"]))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), row_key(text_col).alias("key"))
    if mode == "documents":
        return rows.join(found, "key", "left_anti").select("row.*")

    def blank(batch: pa.RecordBatch) -> pa.RecordBatch:
        raws, spans = raw_texts(batch.column(at)), batch.column(batch.num_columns - 1).to_pylist()
        out = []
        for raw, own in zip(raws, spans, strict=True):
            hit = np.zeros(own[-1]["end"] if own else 0, bool)
            for x in own or ():
                hit[x["start"] : x["end"]] = True
            out.append(cut_words(raw, hit))
        return with_texts(batch.select(list(range(batch.num_columns - 1))), at, out)

    return rows.join(found, "key", "left").select("row.*", F.col("spans").alias("spans of hits")).mapInArrow(per_batch(blank), kind)


def with_texts(batch: pa.RecordBatch, at: int, raws: list[bytes]) -> pa.RecordBatch:
    """batch with other texts in column at; nulls stay."""
    old, field = batch.column(at), batch.schema.field(at)
    texts = [None if gone else raw.decode() for raw, gone in zip(raws, old.is_null().to_pylist(), strict=True)]
    return batch.set_column(at, field, pa.array(texts, pa.string()).cast(field.type))


def cut_words(raw: bytes, hit: np.ndarray) -> bytes:
    """raw without the words that are hit."""
    folded = np.frombuffer(raw.translate(FOLD), np.uint8) != 0x20
    edges = np.flatnonzero(np.diff(np.concatenate(([0], folded.view(np.int8), [0]))))
    keep = np.ones(len(raw), bool)
    for i in np.flatnonzero(hit).tolist():
        keep[edges[2 * i] : edges[2 * i + 1]] = False
    return np.frombuffer(raw, np.uint8)[keep].tobytes()
