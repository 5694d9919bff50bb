"""Token ids in ORC files: integer run-length encoding, row indexes and Bloom filters on document ids.

Documents are dealt by ranges of doc_id, and equal ids by their place in the input, so files, and the rows in them, are in ascending
order of doc_id and no id fills a task. Each range is tokenized where it is written. A row holds the id of its range (part), the ids
before the document in that range (offset), n_tokens and the ids. Stripes are read in parallel; doc_id predicates prune files, stripes
and row groups by their statistics and Bloom filters. Ids may be of any type that ORC and Spark can order.

Tokenization. The tokenizers library encodes. Its byte-level pieces are independent of each other, so whole batches are cut into pieces
by array operations on character classes, and the ids of a piece that has been met come from a bounded hash table of pieces. Pieces
are known by 128 bits of polynomial hashes; those above 64 characters always go to the library. Texts with characters whose class may
differ between regular-expression libraries, and texts with the string of a special token, are encoded whole by the library.

Nulls: a null text is an empty text and has the end id alone; a null doc_id sorts first. Repeated rows are written as often as they
come. An empty table gives a folder without rows.
"""

from __future__ import annotations

import json
import zlib
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from paramstore.llm.common import Held, texts_of

#: Character classes; characters of UNKNOWN go to the library with their whole text.
BLANK, SPACE, LETTER, NUMBER, OTHER, UNKNOWN = range(6)


def _classes() -> np.ndarray:
    """The class of each character up to U+2028, whose place stands for all from there on."""
    out = np.full(0x2029, UNKNOWN, np.uint8)
    out[0x21:0x7F] = out[0xA1:0x250] = out[0x2010:0x2028] = OTHER
    out[[0x09, 0x0A, 0x0D]], out[0x20] = BLANK, SPACE
    for a, b in ("AZ", "az", "ªª", "µµ", "ºº", "ÀÖ", "Øö", "øɏ"):
        out[ord(a) : ord(b) + 1] = LETTER
    for a, b in ("09", "²³", "¹¹", "¼¾"):
        out[ord(a) : ord(b) + 1] = NUMBER
    return out


CLASS = _classes()
#: The endings that the public byte-level vocabulary's pattern parts from their word, by first letter.
ENDINGS = {"s": "", "t": "", "m": "", "d": "", "r": "e", "v": "e", "l": "l"}


def piece_starts(chars: np.ndarray, kind: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Whether a piece starts at each character; first: whether a text does."""
    n = len(chars)
    blank = kind <= SPACE
    change = first.copy()
    change[1:] |= kind[1:] != kind[:-1]
    before = np.zeros(n, np.uint8)  # class of the character before in the same text
    before[1:] = kind[:-1]
    before[first] = UNKNOWN
    after_blank, after_space = before <= SPACE, before == SPACE
    starts = first | blank & ~after_blank | ~blank & change & ~after_space
    last = np.zeros(n, bool)  # the last of a run of blanks goes with what follows, or stands alone
    last[:-1] = blank[:-1] & ~blank[1:] & ~first[1:]
    starts |= last
    at = np.flatnonzero((chars == 0x27) & starts & ~blank)
    at = at[at + 1 < n]
    at = at[~first[at + 1] & (kind[at + 1] == LETTER)]
    for a, b in ENDINGS.items():
        own = at[chars[at + 1] == ord(a)]
        size = 2 + len(b)
        if b:
            own = own[own + 2 < n]
            own = own[~first[own + 2] & (chars[own + 2] == ord(b))]
        starts[own + 1] = False
        end = own[own + size < n] + size
        starts[end[~first[end] & (kind[end] == LETTER)]] = True
    return starts


class PieceTable:
    """Ids of pieces by 128-bit keys, in a table of slots with four places for a key; a full table stays as it is.

    Entries beyond `used` are those of the last call that found no place.
    """

    SLOTS, PLACES, MOST = 20, 4, 600_000

    def __init__(self):
        self.slots = [np.full(1 << self.SLOTS, -1, np.int32) for _ in range(self.PLACES)]
        self.used = self.ids = 0
        self.keys, self.offset, self.count, self.flat = [np.zeros(0, np.uint64), np.zeros(0, np.uint64)], np.zeros(0, np.int32), np.zeros(0, np.int32), np.zeros(0, np.int32)

    def _slot(self, key: np.ndarray, place: int) -> np.ndarray:
        return (key * np.uint64((0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)[place])) >> np.uint64(64 - self.SLOTS)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The entry of each key (a column), or -1."""
        out, left = np.full(keys.shape[1], -1, np.int32), np.arange(keys.shape[1])
        for place, slots in enumerate(self.slots if self.used else []):
            if not len(left):
                break
            own = keys[:, left]
            entry = slots[self._slot(own[0], place)]
            met = (entry >= 0) & (self.keys[0][entry] == own[0]) & (self.keys[1][entry] == own[1])
            out[left[met]] = entry[met]
            left = left[~met]
        return out

    @staticmethod
    def _put(held: np.ndarray, at: int, new: np.ndarray) -> np.ndarray:
        """held with new from at on, in room that doubles."""
        if at + len(new) > len(held):
            held = np.concatenate([held, np.zeros(max(len(held), at + len(new) - len(held), 1024), held.dtype)])
        held[at : at + len(new)] = new
        return held

    def add(self, keys: np.ndarray, count: np.ndarray, ids: np.ndarray, may_stay: np.ndarray) -> np.ndarray:
        """The entries of new keys with so many of ids each; those that may stay and find a free place are kept."""
        left, kept = np.flatnonzero(may_stay), []
        for place, slots in enumerate(self.slots):
            room = self.MOST - self.used - sum(map(len, kept))
            slot = self._slot(keys[0][left], place)
            free = np.flatnonzero(slots[slot] < 0)
            free = free[np.unique(slot[free], return_index=True)[1]][: max(room, 0)]
            slots[slot[free]] = self.used + sum(map(len, kept)) + np.arange(len(free))
            kept.append(left[free])
            left = np.delete(left, free)
        stay = np.concatenate(kept)
        order = np.concatenate([stay, np.setdiff1d(np.arange(len(count)), stay)])
        starts, sizes = (np.cumsum(count) - count)[order], count[order]
        ends = np.cumsum(sizes)
        self.flat = self._put(self.flat, self.ids, ids[np.repeat(starts - ends + sizes, sizes) + np.arange(len(ids))])
        self.offset = self._put(self.offset, self.used, self.ids + ends - sizes)
        self.count = self._put(self.count, self.used, sizes)
        self.keys = [self._put(self.keys[k], self.used, keys[k][order]) for k in range(2)]
        entry = np.empty(len(order), np.int32)
        entry[order] = self.used + np.arange(len(order))
        self.used += len(stay)
        self.ids += int(sizes[: len(stay)].sum())
        return entry


class Encoder:
    """Ids of texts; one for each worker."""

    BATCH, LONGEST = 1 << 18, 64

    def __init__(self, json_text: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(json_text)
        self.special = [x["content"] for x in json.loads(json_text).get("added_tokens", [])]
        self.table = PieceTable()
        r = np.random.default_rng(11)
        self.values = r.integers(0, 1 << 63, (2, len(CLASS)), np.uint64) * np.uint64(2) + np.uint64(1)
        factor = int(self.values[0, 0])
        inverse = pow(factor, -1, 1 << 64)
        self.powers, self.inverses = (self._powers(x) for x in (factor, inverse))
        self.split = self._splits_as_known()

    def _powers(self, factor: int) -> np.ndarray:
        out = np.ones(self.BATCH + 1, np.uint64)
        out[1:] = np.uint64(factor)
        return np.cumprod(out, dtype=np.uint64)

    def _splits_as_known(self) -> bool:
        if "ByteLevel" not in str(self.tokenizer.pre_tokenizer) or self.tokenizer.normalizer:
            return False
        probes = ["It's  a\n\n test 12x é… don't!?  ", "'tis we'll 'S you're'd \t'm ''s x 've\n'let", " \n ", "a\r\nb  3²½c"]
        flat, counts = self._by_pieces(probes)
        return counts is not None and flat.tolist() == [i for p in probes for i in self._whole(p)]

    def _whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _by_pieces(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray | None]:
        """All ids, and each text's number of them, of texts of known characters, BATCH in all at the most."""
        joined = "".join(texts)
        chars = np.minimum(np.frombuffer(joined.encode("utf-32-le"), np.uint32), len(CLASS) - 1)
        bounds = np.concatenate(([0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))))
        n = len(chars)
        if not n:
            return np.zeros(0, np.int32), np.zeros(len(texts), np.int64)
        first = np.zeros(n, bool)
        first[bounds[:-1][bounds[:-1] < n]] = True
        begin = np.flatnonzero(piece_starts(chars, CLASS[chars], first))
        end = np.append(begin[1:], n)
        keys = np.empty((2, len(begin)), np.uint64)
        for k in range(2):
            sums = np.zeros(n + 1, np.uint64)
            np.cumsum(self.values[k][chars] * self.powers[:n], out=sums[1:])
            keys[k] = (sums[end] - sums[begin]) * self.inverses[begin]
        entry = self.table.find(keys)
        missing = np.flatnonzero(entry < 0)
        if len(missing):
            long = end[missing] - begin[missing] > self.LONGEST
            _, one, which = np.unique(np.where(long, np.arange(len(missing), dtype=np.uint64), keys[0][missing]), return_index=True, return_inverse=True)
            if (~long & ((keys[1][missing] != keys[1][missing[one]][which]) | long[one][which])).any():
                return np.zeros(0, np.int32), None  # two pieces with one hash: the library takes them all
            new = missing[one]
            done = self.tokenizer.encode([joined[a:b] for a, b in zip(begin[new].tolist(), end[new].tolist(), strict=True)], is_pretokenized=True, add_special_tokens=False)
            ids, sizes = np.array(done.ids, np.int32), np.bincount(np.array(done.word_ids), minlength=len(new))
            entry[missing] = self.table.add(keys[:, new], sizes, ids, ~long[one])[which]
        count = self.table.count[entry].astype(np.int64)
        ends = np.cumsum(count)
        out = self.table.flat[np.repeat(self.table.offset[entry] - ends + count, count) + np.arange(int(ends[-1]))]
        of_text = np.concatenate(([0], ends))[np.searchsorted(begin, bounds)]
        return out, np.diff(of_text)

    def _parts(self, text: str) -> list[str]:
        """A long text in parts that begin with a space between two words, where a piece begins."""
        out, at = [], 0
        while len(text) - at > self.BATCH:
            place = text.rfind(" ", at + 1, at + self.BATCH)
            while place > at and not (text[place - 1].isalpha() and text[place + 1].isalpha()):
                place = text.rfind(" ", at + 1, place)
            if place <= at:
                return []
            out.append(text[at:place])
            at = place
        return [*out, text[at:]]

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All texts' ids in one array, and each text's number of them."""
        counts, ids = np.zeros(len(texts), np.int64), []
        held: list[int] = []

        def flush() -> None:
            own = [texts[i] for i in held]
            flat, n = self._by_pieces(own) if own else (np.zeros(0, np.int32), np.zeros(0, np.int64))
            if n is None:
                lists = [self._whole(x) for x in own]
                flat, n = np.array([i for x in lists for i in x], np.int32), [len(x) for x in lists]
            counts[held] = n
            ids.append(flat)
            held.clear()

        size = 0
        for i, text in enumerate(texts):
            known = self.split and not any(x in text for x in self.special) and (text.isascii() and text.isprintable() or self._known(text))
            if known and len(text) <= self.BATCH:
                if size + len(text) > self.BATCH:
                    flush()
                    size = 0
                held.append(i)
                size += len(text)
                continue
            flush()
            size = 0
            parts = [self._by_pieces([x]) for x in self._parts(text)] if known else []
            if parts and all(n is not None for _, n in parts):
                ids += [x for x, _ in parts]
                counts[i] = sum(len(x) for x, _ in parts)
            else:
                ids.append(np.array(self._whole(text), np.int32))
                counts[i] = len(ids[-1])
        flush()
        return np.concatenate(ids), counts

    @staticmethod
    def _known(text: str) -> bool:
        return not (CLASS[np.minimum(np.frombuffer(text.encode("utf-32-le"), np.uint32), len(CLASS) - 1)] == UNKNOWN).any()


def write_tokens(docs: DataFrame, path: str, tokenizer_file: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = 0, row_group: int = 1000) -> None:
    """Write the ids of all rows of docs to ORC files under path (a folder that all executors share)."""
    spark = docs.sparkSession
    source = texts_of(docs, id_col, text_col).withColumn("place", F.monotonically_increasing_id()).repartitionByRange("doc_id", "place").sortWithinPartitions("doc_id", "place").drop("place")
    held = spark.sparkContext.broadcast(Held(Encoder, Path(tokenizer_file).read_text()))
    kind = source.schema["doc_id"].dataType.simpleString()

    def encode(batches):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        part, offset, encoder = TaskContext.get().partitionId(), 0, held.value.get()
        for batch in batches:
            step = max(1, int(batch.num_rows * (4 << 20) / max(batch.nbytes, 1)))
            for at in range(0, batch.num_rows, step):
                piece = batch.slice(at, step)
                ids, counts = encoder([x or "" for x in piece.column(1).to_pylist()])
                lengths = counts + 1
                ends = np.cumsum(lengths)
                flat = np.full(int(ends[-1]), end_id, np.int32)
                body = np.ones(len(flat), bool)
                body[ends - 1] = False
                flat[body] = ids
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)).astype(np.int32)), pa.array(flat))
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(np.full(len(lengths), part, np.int32)), pa.array(offset + ends - lengths), pa.array(lengths), lists], ["doc_id", "part", "offset", "n_tokens", "ids"])
                offset += int(ends[-1])

    rows = source.mapInArrow(encode, f"doc_id {kind}, part int, offset long, n_tokens long, ids array<int>")
    options = {"orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.create.index": "true", "orc.row.index.stride": str(row_group), "compression": "zstd"}
    rows.write.options(**options).orc(path)
    _schema_file(spark, path, rows.schema.json())


def _schema_file(spark: SparkSession, path: str, text: str | None = None) -> str:
    """Write, or read, the schema beside the files: a folder without rows has it in no file."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(f"{path}/_schema.json")
    store = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if text is not None:
        out = store.create(where, True)
        out.write(text.encode())
        out.close()
        return text
    stream = store.open(where)
    text = bytes(stream.readAllBytes()).decode()
    stream.close()
    return text


def read_tokens(spark: SparkSession, path: str, doc_ids: list | None = None) -> DataFrame:
    """doc_id, part, offset, n_tokens, ids, start (ids of all documents before it); of the given documents alone if doc_ids is given."""
    from pyspark.sql.types import StructType

    every = spark.read.schema(StructType.fromJson(json.loads(_schema_file(spark, path)))).orc(path)
    rows = every if doc_ids is None else every.where(F.col("doc_id").isin(doc_ids))
    totals = every.groupBy("part").agg(F.sum("n_tokens").alias("n"))  # a row for each file, of two pruned columns
    bases = totals.select(F.col("part").alias("of"), F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return rows.join(F.broadcast(bases), rows.part == bases.of).withColumn("start", F.col("base") + F.col("offset")).drop("of", "base")


def digests(tokens: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of rows of read_tokens, all but start from the ids themselves."""

    def kernel(batches):
        for batch in batches:
            ids = batch.column(2)
            values, ends = ids.values.to_numpy(zero_copy_only=False).astype("<u4"), ids.offsets.to_numpy()
            crc = [zlib.crc32(values[a:b]) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.diff(ends).astype(np.int64)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    kind = tokens.schema["doc_id"].dataType.simpleString()
    return tokens.select("doc_id", "start", "ids").mapInArrow(kernel, f"doc_id {kind}, start long, n_tokens long, ids_crc32 long")
