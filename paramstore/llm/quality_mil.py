"""Quality classifier by attention-based multiple-instance learning.

A document is a bag of passages: consecutive windows of `PASSAGE` bytes of its text, all of them. A passage is encoded from counts of
neighbouring character classes and a few shares, through a learnt layer; gated attention gives each passage a weight within its
document; the weighted mean of the passages' encodings is the document's, and a logistic layer scores it. Only document labels are
known; encoder, attention and output are fitted together.

Training takes a bounded sample of the labelled rows (`most_docs`, by the hash of the id, and of those so many that their texts have
`most_passages` passages in all) outside the held-out fold; labels, language, source and id are no inputs. Every text is scored whole. Nulls: a null text is empty, one empty passage; a null label trains
nothing; a null id counts as held out. Without labelled rows the score is 0.5. Rows are kept one for one; empty tables give empty results.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.llm.common import bucket, per_batch, raw_texts, texts_of

PASSAGE = 512
#: Character classes: blank, line end, lower vowels and other letters, capitals, digits, stops, quotes, brackets, marks, other, UTF-8 parts.
KINDS = 16


def _classes() -> np.ndarray:
    out = np.full(256, 12, np.uint8)
    groups = (b" \t\r\x0b\x0c", b"\n", b"aeiou", b"bcdfghjklmnpqrstvwxyz", b"AEIOU", b"BCDFGHJKLMNPQRSTVWXYZ", b"0123456789", b".", b",;:", b"!?", b"#", b"$%&*", b"", b"|<>=_~^\\/+", b"\"'()[]{}-`@")
    for k, group in enumerate(groups):
        out[list(group)] = k
    out[128:] = 15
    return out


CLASS = _classes()
EXTRA = 6
FEATURES = KINDS * KINDS + EXTRA


#: Bytes that are taken apart at once, and how far back a feature looks.
PART, BACK = 1 << 22, 12


def passages(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of all passages, and the number of passages of each text; texts longer than PART are taken apart in parts."""
    n = np.array([max(1, -(-len(x) // PASSAGE)) for x in raws], np.int64)
    rows, held, size = [], [], 0
    for raw in raws:
        if held and size + len(raw) > PART:
            rows.append(_features(held))
            held, size = [], 0
        if len(raw) > PART:
            rows += [_features([raw[max(0, at - BACK) : at + PART]], min(at, BACK), len(raw)) for at in range(0, len(raw), PART)]
        else:
            held.append(raw)
            size += len(raw)
    if held:
        rows.append(_features(held))
    return (np.concatenate(rows) if rows else np.zeros((0, FEATURES), np.float32)), n


def _features(raws: list[bytes], before: int = 0, whole: int | None = None) -> np.ndarray:
    """Feature rows of the passages of raws; the first bytes of a part (so many, one text) only stand before its first passage."""
    lengths = np.fromiter(map(len, raws), np.int64, len(raws)) - before
    n = np.maximum(1, -(-lengths // PASSAGE))
    data = np.frombuffer(b"".join(raws), np.uint8)
    first = np.concatenate(([0], np.cumsum(n)[:-1]))
    starts = np.concatenate(([0], np.cumsum(lengths)[:-1]))
    total = int(n.sum())
    place = np.arange(len(data) - before) - np.repeat(starts, lengths)
    owner = np.repeat(first, lengths) + place // PASSAGE
    kind = CLASS[data].astype(np.int64)
    pair = np.empty_like(kind)
    if len(data):
        pair[1:] = kind[:-1] * KINDS + kind[1:]
        pair[0] = kind[0]
        pair[starts[lengths > 0]] = kind[starts[lengths > 0]] + KINDS  # a text starts after a line end
    counts = np.bincount(owner * (KINDS * KINDS) + pair[before:], minlength=total * KINDS * KINDS).reshape(total, KINDS * KINDS).astype(np.float32)
    size = np.maximum(counts.sum(axis=1), 1.0)
    out = np.empty((total, FEATURES), np.float32)
    share = counts / size[:, None]
    np.sqrt(share, out=out[:, : KINDS * KINDS])
    # repetition: equal byte triples at distances that a repeated word, line or list makes
    since = np.repeat(starts, lengths)
    for k, lag in enumerate((3, 5, 9)):
        same = np.zeros(len(data), bool)
        if len(data) > lag + 3:
            eq = data[lag:] == data[:-lag]
            same[lag + 2 :] = eq[2:] & eq[1:-1] & eq[:-2]
        same = same[before:]
        if not before:
            same &= np.arange(len(data)) - since >= lag + 2  # within the text
        out[:, KINDS * KINDS + k] = np.bincount(owner[same], minlength=total) / size
    entropy = -(share * np.log(np.maximum(share, 1e-9))).sum(axis=1)
    out[:, -3] = entropy / 4
    out[:, -2] = (counts > 0).sum(axis=1) / 64
    out[:, -1] = np.repeat(np.log1p(lengths if whole is None else np.array([whole])) / 10, n)
    return out


class AttentionModel:
    """Encoder, gated attention and output layer."""

    def __init__(self, hidden: int = 24, gate: int = 12, seed: int = 7):
        r = np.random.default_rng(seed)
        draw = lambda *shape: (r.standard_normal(shape) / np.sqrt(shape[0])).astype(np.float32)
        self.p = {"w": draw(FEATURES, hidden), "b": np.zeros(hidden, np.float32), "v": draw(hidden, gate), "u": draw(hidden, gate), "a": draw(gate), "c": draw(hidden), "d": np.zeros(1, np.float32)}
        self.mean, self.spread = np.zeros(FEATURES, np.float32), np.ones(FEATURES, np.float32)

    def forward(self, x: np.ndarray, n: np.ndarray) -> tuple:
        p = self.p
        h = np.tanh(((x - self.mean) / self.spread) @ p["w"] + p["b"])
        t, s = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
        e = (t * s) @ p["a"]
        first = np.concatenate(([0], np.cumsum(n)[:-1]))
        bag = np.repeat(np.arange(len(n)), n)
        w = np.exp(e - np.maximum.reduceat(e, first)[bag])
        w /= np.add.reduceat(w, first)[bag]
        z = np.add.reduceat(w[:, None] * h, first)
        y = 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["d"], -30, 30)))
        return h, t, s, w, z, y, bag, first

    def fit(self, x: np.ndarray, n: np.ndarray, label: np.ndarray, rounds: int = 200, rate: float = 0.01, decay: float = 1e-4) -> None:
        self.mean, self.spread = x.mean(axis=0), x.std(axis=0) + 0.01
        p = self.p
        m1, m2 = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}
        xs = (x - self.mean) / self.spread
        for step in range(1, rounds + 1):
            h, t, s, w, z, y, bag, first = self.forward(x, n)
            gy = ((y - label) / len(n)).astype(np.float32)
            gz = gy[:, None] * p["c"]
            gw = (gz[bag] * h).sum(axis=1)
            ge = w * (gw - np.add.reduceat(w * gw, first)[bag])
            gt, gs = ge[:, None] * p["a"] * s * (1 - t * t), ge[:, None] * p["a"] * t * s * (1 - s)
            gh = (w[:, None] * gz[bag] + gt @ p["v"].T + gs @ p["u"].T) * (1 - h * h)
            grad = {"w": xs.T @ gh, "b": gh.sum(axis=0), "v": h.T @ gt, "u": h.T @ gs, "a": (t * s).T @ ge, "c": z.T @ gy, "d": gy.sum(keepdims=True)}
            for k, v in p.items():
                g = grad[k] + decay * v
                m1[k] = 0.9 * m1[k] + 0.1 * g
                m2[k] = 0.999 * m2[k] + 0.001 * g * g
                v -= rate * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.999**step)) + 1e-8)

    def score(self, raws: list[bytes]) -> np.ndarray:
        if not raws:
            return np.zeros(0)
        return self.forward(*passages(raws))[5].astype(np.float64)


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", folds: int = 5, most_docs: int = 3_000, most_passages: int = 150_000, **options) -> AttentionModel | None:
    """The model from at most about most_docs labelled rows whose crc32(id) % folds is not 0; None if there are none."""
    marked = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).alias("label")).where(F.col("label").isNotNull() & (bucket(F.col("doc_id"), folds) != 0))
    share = min(1.0, most_docs / max(marked.count(), 1))
    chosen = marked.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int((1 << 30) * share))
    rows = texts_of(docs, id_col, text_col).join(F.broadcast(chosen), "doc_id").select("text", "label", "doc_id")  # most_docs ids
    size = F.floor(F.coalesce(F.octet_length("text"), F.lit(0)) / PASSAGE) + 1
    sizes = rows.groupBy("doc_id").agg(F.sum(size).alias("size"), F.xxhash64(F.col("doc_id"), F.lit("order")).alias("h")).collect()
    left, fit_ids = most_passages, []
    for r in sorted(sizes, key=lambda r: (r.h, str(r.doc_id))):
        if r.size <= left:
            left -= r.size
            fit_ids.append(r.doc_id)
    if len(fit_ids) < len(sizes):
        rows = rows.where(F.col("doc_id").isin(fit_ids))

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        x, n = passages(raw_texts(batch.column(0)))
        ends = np.cumsum(n)
        return pa.RecordBatch.from_arrays([batch.column(1).cast(pa.int32()), batch.column(2).cast(pa.string()), pa.array(n), pa.array([x[e - k : e].astype(np.float16).tobytes() for e, k in zip(ends.tolist(), n.tolist(), strict=True)], pa.binary())], ["label", "doc_id", "n", "x"])

    got = rows.mapInArrow(per_batch(kernel), "label int, doc_id string, n long, x binary").toArrow()
    if not got.num_rows:
        return None
    got = got.sort_by([("doc_id", "ascending"), ("n", "ascending")])
    x = np.frombuffer(b"".join(got.column("x").to_pylist()), np.float16).astype(np.float32).reshape(-1, FEATURES)
    model = AttentionModel()
    model.fit(x, got.column("n").to_numpy(), got.column("label").to_numpy().astype(np.float32), **options)
    return model


def score(docs: DataFrame, model: AttentionModel | None, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    source = texts_of(docs, id_col, text_col).select("doc_id", (bucket(F.col("doc_id"), folds) == 0).alias("held_out"), "text")
    held = docs.sparkSession.sparkContext.broadcast(model)
    kind = source.schema["doc_id"].dataType.simpleString()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        raws = raw_texts(batch.column(2))
        y = np.full(len(raws), 0.5) if held.value is None else held.value.score(raws)
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(y), pa.array((y >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return source.mapInArrow(per_batch(kernel, 4 << 20), f"doc_id {kind}, held_out boolean, score double, predicted int")
