"""Language-model scoring by the likelihood of subword lattices.

Text model. A text is its words, A-Z in lower case, and one end. A word is written as a word mark and its bytes; the pieces of an
existing public vocabulary, and its 256 byte pieces, are the arcs of a lattice over it. Every segmentation of a word is weighted by the
product of its pieces' unigram probabilities, and a log-space forward recursion sums over all segmentations. Pieces with the word mark
only start words, so words part and their sums multiply. The score of a text is the log10 of that marginal probability of all its
words and its end.

Weights. The vocabulary's own scores weigh the pieces and are never fitted one by one: a piece's log probability is its score by one
exponent (a rank r, as vocabularies of merges have it, scores -log(r + 10)), normalised. The training texts choose the exponent, of
`EXPONENTS`, by the likelihood of all their words, and give the probability of the end.

word_score is the same text under the words that were counted: (c + M * lattice) / (N + M), c the word's count in N training tokens and
the lattice the base measure of a Dirichlet prior of strength M, the number of different training words.

fitted_score has two things more that are learnt. The pieces' probabilities are fitted to the training words, each different word once,
by `FITS` rounds of expectation-maximisation over the same lattices, from the chosen exponent on (a word that a text brings new is like
the words that were new once). And a word's lattice has one arc more, the whole word as it was counted: the arc and the paths of pieces
weigh as in word_score.

Corpus counts. Spark counts every word of every text; nothing is pruned. The most frequent words, `most_words` at the most, go to the
workers as one broadcast; occurrences of all other words are joined to the counted words by a shuffle, so scores are exact at any
size of the corpus. The lattice of a word is summed once, where it has been counted.

Base: sum of log10((c + k) / (N + k * (V + 1))) over the tokens. Nulls: a null text is empty: the end alone. A null id counts as held out
(crc32 of the empty text). Rows are kept one for one; empty tables give empty results.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.llm.common import KEY, Held, bucket, cut, gathered, per_batch, raw_texts, row_key

MARK = 0x20  # stands for the word mark: words hold no blanks
FACTOR = np.uint64(0x9E3779B97F4A7C15)
#: The exponents that training texts choose from.
EXPONENTS = (0.5, 0.7, 0.9, 1.1, 1.3)
#: Rounds of expectation-maximisation, and what each piece counts besides what is expected of it.
FITS, LEAST = 2, 0.1


class Pieces:
    """The lattice arcs: a hash table of all pieces and their beginnings, and the pieces' log weights, a row for each exponent."""

    SLOTS = 1 << 19

    def __init__(self, pieces: list[bytes], logp: np.ndarray):
        self.logp = np.atleast_2d(logp)
        numbers: dict[int, int] = {}
        for i, piece in enumerate(pieces):
            h = 0
            for k, c in enumerate(piece):
                h = ((h ^ (h >> 29)) * int(FACTOR) + c + 1) & 0xFFFFFFFFFFFFFFFF
                if k + 1 < len(piece):
                    numbers.setdefault(h, -1)
            numbers[h] = i
        self.keys = np.array(list(numbers), np.uint64)
        self.numbers = np.array(list(numbers.values()), np.int64)
        self.most = max(map(len, pieces))
        self.tables, left = [], np.arange(len(self.keys))  # a key that finds its place taken goes to the next table
        while len(left):
            slots, table = self._slots(self.keys[left], len(self.tables)), np.zeros(self.SLOTS, np.int32)
            table[slots[::-1]] = left[::-1]
            self.tables.append(table)
            left = left[table[slots] != left]

    @staticmethod
    def _slots(h: np.ndarray, table: int) -> np.ndarray:
        return (h if not table else (h ^ (h >> np.uint64(16 + table))) * FACTOR) >> np.uint64(45)

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each hash is of a piece or a beginning of one, and the piece's number or -1."""
        at = self.tables[0][self._slots(h, 0)]
        there = self.keys[at] == h
        for k, table in enumerate(self.tables[1:], 1):
            other = np.flatnonzero(~there)
            again = table[self._slots(h[other], k)]
            met = self.keys[again] == h[other]
            at[other[met]] = again[met]
            there[other[met]] = True
        return there, self.numbers[at]

    def arcs(self, words: np.ndarray) -> list[tuple[int, int, np.ndarray, np.ndarray]]:
        """(i, j, rows, numbers): the rows of words (equal lengths, the mark first) that have a piece from i to j, by i, then j."""
        m, size = words.shape
        columns, out = np.ascontiguousarray(words.T.astype(np.uint64) + np.uint64(1)), []
        for i in range(size):
            rows, h = np.arange(m), np.zeros(m, np.uint64)
            for j in range(i + 1, min(size, i + self.most) + 1):
                h = step(h, columns[j - 1][rows])
                there, numbers = self.find(h)
                piece = np.flatnonzero(there & (numbers >= 0))
                if len(piece):
                    out.append((i, j, rows[piece].astype(np.int32), numbers[piece].astype(np.int32)))
                rows, h = rows[there], h[there]
                if not len(rows):
                    break
        return out

    def forward(self, words: np.ndarray, row: int = 0, arcs=None) -> np.ndarray:
        """Log sums over all segmentations up to each place."""
        m, size = words.shape
        logp, alpha = self.logp[row], np.full((size + 1, m), -np.inf)
        alpha[0] = 0.0
        for i, j, rows, numbers in self.arcs(words) if arcs is None else arcs:
            alpha[j, rows] = np.logaddexp(alpha[j, rows], alpha[i, rows] + logp[numbers])
        return alpha


def step(h: np.ndarray, symbol: np.ndarray) -> np.ndarray:
    return (h ^ (h >> np.uint64(29))) * FACTOR + symbol


def read_vocabulary(model_file: str) -> tuple[list[bytes], np.ndarray]:
    """Pieces as bytes (the word mark as MARK) and their own scores as logs.

    Scores that are ranks become -log(rank + 10). The 256 byte pieces cover every text; those without a score have the least one.
    """
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=model_file)
    found: dict[bytes, float] = {}
    for i in range(model.get_piece_size()):
        if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i)):
            piece, score = model.id_to_piece(i).replace("▁", " ").encode(), model.get_score(i)
            if b" " not in piece[1:] and score > -1e8:
                found[piece] = max(found.get(piece, -np.inf), score)
    least = min(found.values())
    for c in range(256):
        found.setdefault(bytes([c]), least)
    pieces = sorted(found)
    scores = np.array([found[p] for p in pieces])
    return pieces, -np.log(scores.max() - scores + 10.0) if (scores == np.rint(scores)).all() else scores


def weights(scores: np.ndarray, exponents=EXPONENTS) -> np.ndarray:
    """Normalised log probabilities of the pieces, a row for each exponent."""
    rows = np.outer(exponents, scores)
    rows -= rows.max(axis=1, keepdims=True)
    return rows - np.log(np.exp(rows).sum(axis=1, keepdims=True))


def by_length(words: list[bytes], most_cells: int = 250_000):
    """(places, rows of equal length with the mark first) over words, in bounded parts."""
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    order = np.argsort(lengths, kind="stable")
    at = 0
    while at < len(order):
        n = int(lengths[order[at]])
        end = min(int(np.searchsorted(lengths[order], n, side="right")), at + max(1, most_cells // (n + 1)))
        own = order[at:end]
        body = np.frombuffer(b"".join(words[i] for i in own.tolist()), np.uint8).reshape(len(own), n)
        yield own, np.concatenate([np.full((len(own), 1), MARK, np.uint8), body], axis=1)
        at = end


def word_log10(model: Pieces, words: list[bytes], longest: int = 1024) -> np.ndarray:
    """log10 of each word's sum over all segmentations, a column for each exponent."""
    out = np.zeros((len(words), len(model.logp)))
    short = np.array([i for i, w in enumerate(words) if len(w) <= longest], np.int64)
    for own, rows in by_length([words[i] for i in short.tolist()]):
        arcs = model.arcs(rows)
        for k in range(out.shape[1]):
            out[short[own], k] = model.forward(rows, k, arcs)[-1]
    for i, w in enumerate(words):
        if len(w) > longest:
            out[i] = [long_word(model, w, k) for k in range(out.shape[1])]
    return out / math.log(10)


def long_word(model: Pieces, word: bytes, row: int = 0, block: int = 1024) -> float:
    """The same recursion in blocks, of which only the last places go over into the next."""
    text, logp = bytes([MARK]) + word, model.logp[row]
    alpha, start = {0: 0.0}, 0
    while start < len(text):
        stop = min(start + block, len(text))
        low = max(0, start - model.most + 1)
        for i, j, _, numbers in model.arcs(np.frombuffer(text[low:stop], np.uint8)[None, :]):
            if low + j > start and low + i in alpha:
                alpha[low + j] = np.logaddexp(alpha.get(low + j, -np.inf), alpha[low + i] + logp[numbers[0]])
        alpha = {k: v for k, v in alpha.items() if k > stop - model.most}
        start = stop
    return float(alpha[len(text)])


def expected(model: Pieces, words: list[bytes], longest: int = 1024) -> np.ndarray:
    """How often each piece stands in the segmentations of words, each weighed by its probability; of longer words block by block."""
    out = np.zeros(model.logp.shape[1])
    texts = [bytes([MARK]) + w for w in words]
    blocks = [t[at : at + longest] for t in texts for at in range(0, len(t), longest)]
    marked = [b[1:] for b in blocks if b[0] == MARK]  # words hold no marks
    rest = [(None, np.frombuffer(b, np.uint8)[None, :]) for b in blocks if b[0] != MARK]
    for _, rows in [*by_length(marked), *rest]:
        arcs, size = model.arcs(rows), rows.shape[1]
        before, logp = model.forward(rows, 0, arcs), model.logp[0]
        after = np.full((size + 1, len(rows)), -np.inf)
        after[size] = 0.0
        for i, j, own, numbers in reversed(arcs):
            on = after[j, own] + logp[numbers]
            after[i, own] = np.logaddexp(after[i, own], on)
            out += np.bincount(numbers, np.exp(before[i, own] + on - before[size, own]), minlength=len(out))
    return out


def fitted(words: DataFrame, pieces: list[bytes], logp: np.ndarray, rounds: int = FITS) -> np.ndarray:
    """The pieces' log probabilities after rounds over the training words of words (word, c)."""
    source = words.where("c > 0").select("word")
    for _ in range(rounds):
        held = words.sparkSession.sparkContext.broadcast(Held(_pieces, (pieces, logp)))

        def run(batches, held=held):
            out = np.zeros(len(pieces))
            for batch in gathered(batches, 50_000):
                out += expected(held.value.get(), raw_texts(batch.column(0)))
            seen = np.flatnonzero(out)
            yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(out[seen])], ["piece", "times"])

        times = np.full(len(pieces), LEAST)
        got = source.mapInArrow(run, "piece long, times double").groupBy("piece").agg(F.sum("times").alias("times")).toArrow()  # a row for each piece
        times[got.column(0).to_numpy()] += got.column(1).to_numpy()
        logp = np.log(times / times.sum())
        held.destroy()
    return logp


def count_words(docs: DataFrame, id_col: str, text_col: str, folds: int, most_held: int = 300_000) -> DataFrame:
    """(word, n, c): occurrences in all texts, and in the training texts, of every different word."""
    source = docs.select(F.col(text_col).alias("text"), (bucket(F.col(id_col), folds) != 0).alias("train"))

    def batch_of(other: Counter, train: Counter) -> pa.RecordBatch:
        words = list(other | train)
        c = np.array([train.get(w, 0) for w in words], np.int64)
        n = c + np.array([other.get(w, 0) for w in words], np.int64)
        return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(n), pa.array(c)], ["word", "n", "c"])

    def run(batches):
        counts = Counter(), Counter()
        for batch in batches:
            for raw, k in zip(raw_texts(batch.column(0)), batch.column(1).to_pylist(), strict=True):
                counts[bool(k)].update(raw.lower().split())
                if len(counts[0]) + len(counts[1]) > most_held:
                    yield batch_of(*counts)
                    counts = Counter(), Counter()
        if counts[0] or counts[1]:
            yield batch_of(*counts)

    return source.mapInArrow(run, "word binary, n long, c long").groupBy("word").agg(F.sum("n").alias("n"), F.sum("c").alias("c"))


def frequent(words: DataFrame, most_words: int) -> int:
    """The least count of all words that are at least so frequent, most_words at the most."""
    left = most_words
    least = 1 << 62
    for r in words.groupBy("n").count().orderBy(F.desc("n")).toLocalIterator():  # different counts: few
        left -= r["count"]
        if left < 0:
            break
        least = r.n
    return least


def lattices(counted: DataFrame, pieces: list[bytes], logp: np.ndarray, name: str = "l") -> DataFrame:
    """counted (word first) with l0, l1, ...: log10 of each word's lattice under each row of logp."""
    held = counted.sparkSession.sparkContext.broadcast(Held(_pieces, (pieces, logp)))
    names = [*counted.columns, *[f"{name}{i}" for i in range(len(logp))]]

    def run(batches):
        for batch in gathered(batches, 50_000):
            sums = word_log10(held.value.get(), raw_texts(batch.column(0)))
            yield pa.RecordBatch.from_arrays([*batch.columns, *[pa.array(np.ascontiguousarray(sums[:, i])) for i in range(sums.shape[1])]], names)

    return counted.mapInArrow(run, ", ".join(f"{c} {'binary' if c == 'word' else 'long' if c in ('n', 'c') else 'double'}" for c in names))


def score(docs: DataFrame, vocabulary_file: str, id_col: str = "doc_id", text_col: str = "text", folds: int = 10, k: float = 0.1, most_words: int = 300_000, exponents=EXPONENTS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, word_score, fitted_score, exponent of every row; rows with crc32(id) % folds = 0 are held out."""
    spark = docs.sparkSession
    texts = docs.where(bucket(F.col(id_col), folds) != 0).count()
    pieces, scores = read_vocabulary(vocabulary_file)
    rows_of = weights(scores, exponents)
    every = cut(lattices(count_words(docs, id_col, text_col, folds), pieces, rows_of))
    sums = every.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count_if(F.col("c") > 0).alias("v"), *[F.coalesce(F.sum(F.col("c") * F.col(f"l{i}")), F.lit(0.0)).alias(f"l{i}") for i in range(len(exponents))]).first()
    best = max(range(len(exponents)), key=lambda i: (sums[f"l{i}"], -i))
    n, v, m = sums.n + texts, sums.v + (texts > 0), max(sums.v, 1)
    ends = (texts + 0.5) / (n + 1.0)
    goes_on = math.log10(1.0 - ends)
    own = every.select("word", "n", "c", (F.col(f"l{best}") + goes_on).alias("lattice"))
    words = cut(lattices(own, pieces, fitted(every, pieces, rows_of[best])[None, :], "fit").withColumn("fit", F.col("fit0") + goes_on).drop("fit0"))
    least = frequent(words, most_words)
    head = words.where(F.col("n") >= least).select("word", "c", "lattice", "fit").toArrow()  # most_words rows at most
    known = spark.sparkContext.broadcast(Held(_dictionary, (b"\n".join(head.column(0).to_pylist()), *[head.column(i).to_numpy() for i in (1, 2, 3)], k, n, v, m)))
    floor = n + k * (v + 1)
    end = np.array([float(texts > 0), math.log10((texts + k) / floor), math.log10(ends), *[math.log10((texts + m * ends) / (n + m))] * 2])
    source = docs.select(F.col(id_col).alias("doc_id"), row_key(id_col, text_col).alias("key"), (bucket(F.col(id_col), folds) == 0).alias("held_out"), F.col(text_col).alias("text"))
    kind = source.schema["doc_id"].dataType.simpleString()
    values = ["known", "base", "lattice", "counted", "fitted"]  # of a token; for a text their sums

    def one_pass(batch: pa.RecordBatch) -> pa.RecordBatch:
        place, table = known.value.get()
        lengths, out, rest, times = [], np.zeros((batch.num_rows, len(values))), [], []
        for row, raw in enumerate(raw_texts(batch.column(3))):
            tokens = raw.lower().split()
            at = np.array([place.get(w, -1) for w in tokens], np.int64)
            out[row] = end + table[at[at >= 0]].sum(axis=0)
            other = Counter(tokens[i] for i in np.flatnonzero(at < 0).tolist())
            lengths.append(len(tokens) + 1)
            rest.append(list(other))
            times.append(list(other.values()))
        arrays = [*batch.columns[:3], pa.array(lengths, pa.int64()), *[pa.array(np.ascontiguousarray(out[:, i])) for i in range(len(values))], pa.array(rest, pa.list_(pa.binary())), pa.array(times, pa.list_(pa.int64()))]
        return pa.RecordBatch.from_arrays(arrays, ["doc_id", "key", "held_out", "n_tokens", *values, "rest", "times"])

    rows = cut(source.mapInArrow(per_batch(one_pass), f"doc_id {kind}, key {KEY}, held_out boolean, n_tokens long, {', '.join(f'{c} double' for c in values)}, rest array<binary>, times array<long>"))
    rare = rows.where(F.size("rest") > 0).select("key", F.posexplode(F.arrays_zip("rest", "times")).alias("i", "x")).select("key", "i", F.col("x.rest").alias("word"), F.col("x.times").alias("t"))
    c, lattice = F.col("c"), F.col("lattice")
    with_word = lambda paths: F.when(c > 0, F.log10(c + m * F.pow(F.lit(10.0), paths))).otherwise(math.log10(m) + paths) - math.log10(n + m)
    each = [F.when(c > 0, 1.0).otherwise(0.0), F.log10((c + k) / floor), lattice, with_word(lattice), with_word(F.col("fit"))]
    weighed = rare.join(words, "word").select("key", "i", *[(F.col("t") * e).alias(f"x_{name}") for name, e in zip(values, each, strict=True)])
    of_row = weighed.groupBy("key").agg(F.count_if(F.col("i") == 0).alias("copies"), *[F.sum(f"x_{name}").alias(f"x_{name}") for name in values])
    full = rows.drop("rest", "times").join(of_row, "key", "left")
    total = {name: F.col(name) + F.coalesce(F.col(f"x_{name}") / F.col("copies"), F.lit(0.0)) for name in values}  # the same row twice was summed twice
    return full.select("doc_id", "held_out", "n_tokens", F.round(total["known"]).cast("long").alias("n_known"), F.lit(n).cast("long").alias("train_tokens"), total["base"].alias("base_score"), total["lattice"].alias("score"), total["counted"].alias("word_score"), total["fitted"].alias("fitted_score"), F.lit(float(exponents[best])).alias("exponent"))


def _pieces(payload):
    return Pieces(*payload)


def _dictionary(payload):
    """Places of the words, and what a token of each adds: known, base, the lattice's, the counted and the fitted log10 probability."""
    blob, c, lattice, fit, k, n, v, m = payload
    c = c.astype(np.float64)
    counted, fits = (np.where(c > 0, np.log10(np.maximum(c + m * 10.0**x, 1e-300)), math.log10(m) + x) - math.log10(n + m) for x in (lattice, fit))
    words = blob.split(b"\n") if len(c) else []
    return {w: i for i, w in enumerate(words)}, np.column_stack([c > 0, np.log10((c + k) / (n + k * (v + 1))), lattice, counted, fits])
