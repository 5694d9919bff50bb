"""Secret scans: base patterns, and probabilistic automata inferred from labelled credentials.

Base. Three kinds of spans, leftmost and non-overlapping within a kind: `assign` (a keyword, an assignment sign and a value of 12
characters or more), `access` (an access-key prefix, 18 or more in all), `hex` (16 or more). They stay in every result.

Grammar inference. The values that the base patterns label are credentials; other long runs of the same characters are ordinary, but for those with a part
that looks like a credential without a label: more likely under a kind's automaton than under that of all others, and as likely, by
the character, as all but the least twentieth of the kind's labelled values. Each kind, and the ordinary ones, give a frequency prefix tree over character classes; states are merged, red and blue, where the
Hoeffding bound finds their symbol and end frequencies, and those of their followers, compatible. The result is a probabilistic
automaton. Every candidate of a text is scored by its log likelihood under each kind's automaton against the ordinary one. Candidates
are the maximal runs of 16 or more token characters and, within them, the runs between the characters that join fields (`JOINS`), so
that a credential in an address or after an equals sign is scored by itself. A candidate of a log ratio of `threshold` or more is a
further span, of kind `format`, unless it lies within a base span; of candidates within each other the one of the larger ratio is taken.

The training set is a documented bounded sample: of all documents' values, for each kind the `most_examples` of the smallest hashes, those
above `longest` characters left out. Each task keeps that many, so a kind is learnt from as many values at any size of the corpus. The
scan covers every text whole. Nulls: a null text is empty. Rows are kept one for one. Without labelled values there is no automaton
and only base spans come. Empty tables give empty results.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_left
from collections import defaultdict
from heapq import nsmallest
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from paramstore.llm.common import concat_texts, cut, per_batch, raw_texts, texts_of

#: The base patterns.
ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE)
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
KINDS = ("assign", "access", "hex", "format")
LEAST = {"assign": 12, "access": 18, "hex": 16, "format": 16}
KEYWORDS = (b"passw", b"secret", b"token", b"api")

HEX = np.zeros(256, bool)
HEX[list(b"0123456789abcdef")] = True
TOKEN = np.zeros(256, bool)
TOKEN[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")] = True

#: Characters that join fields, between which a credential may stand.
JOINS = b"=/.+"
FIELD = TOKEN.copy()
FIELD[list(JOINS)] = False

#: Character classes: digits, a-f, g-z, A-Z, and each further token character for itself; and each class's size.
CLASS = bytes(0 if 0x30 <= c <= 0x39 else 1 if 0x61 <= c <= 0x66 else 2 if 0x67 <= c <= 0x7A else 3 if 0x41 <= c <= 0x5A else 4 + b"+/_.=-".index(c) if c in b"+/_.=-" else 10 for c in range(256))
CLASS_SIZE = (10, 6, 20, 26, 1, 1, 1, 1, 1, 1, 188)
END = len(CLASS_SIZE)


def runs(mask: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    edges = np.flatnonzero(mask[1:] != mask[:-1]) + 1
    edges = np.concatenate((([0] if len(mask) and mask[0] else []), edges, ([len(mask)] if len(mask) and mask[-1] else []))).astype(np.int64)
    starts, ends = edges[::2], edges[1::2]
    long = ends - starts >= least
    return starts[long], ends[long]


def base_spans(raws: list[bytes], with_candidates: bool = True) -> tuple[list[list[tuple[str, int, int]]], list[list[tuple[int, int]]]]:
    """Byte spans of the base kinds, and the candidates, of each text."""
    found: list[list[tuple[str, int, int]]] = [[] for _ in raws]
    candidates: list[list[tuple[int, int]]] = [[] for _ in raws]
    if not raws:
        return found, candidates
    data, starts, _ = concat_texts(raws, b"\n")
    seen: set[tuple[int, int, int]] = set()
    for mask, kind in ((HEX, "hex"), (TOKEN, ""), (FIELD, "")):
        if not kind and not with_candidates:
            continue
        a, b = runs(mask[data], 16)
        owner = np.searchsorted(starts, a, side="right") - 1
        base = starts[owner]
        for i, s, e in zip(owner.tolist(), (a - base).tolist(), (b - base).tolist(), strict=True):
            if kind:
                found[i].append((kind, s, e))
            elif (i, s, e) not in seen:
                seen.add((i, s, e))
                candidates[i].append((s, e))
    for i, raw in enumerate(raws):
        low = raw.lower()
        if any(k in low for k in KEYWORDS):
            found[i] += [("assign", *m.span()) for m in ASSIGN.finditer(raw) if m.end(2) - m.start(2) >= LEAST["assign"]]
        if b"AKIA" in raw:
            found[i] += [("access", *m.span()) for m in ACCESS.finditer(raw) if m.end() - m.start() >= LEAST["access"]]
    return found, candidates


def value_span(raw: bytes, kind: str, start: int, end: int) -> tuple[int, int]:
    """The credential within a span: the value of an assignment, else all of it."""
    return ASSIGN.match(raw, start, end).span(2) if kind == "assign" else (start, end)


class Reach:
    """Of sorted spans, the farthest end among those that start before a place."""

    def __init__(self, spans: list[tuple[int, int]]):
        spans = sorted(spans)
        self.starts, self.ends = [a for a, _ in spans], list(accumulate((b for _, b in spans), max))

    def before(self, place: int) -> int:
        at = bisect_left(self.starts, place)
        return self.ends[at - 1] if at else -1


class Automaton:
    """A deterministic probabilistic automaton over character classes, merged from a frequency prefix tree."""

    def __init__(self, examples: list[bytes], alpha: float = 0.05):
        self.alpha = math.sqrt(0.5 * math.log(2 / alpha))
        self.next: list[dict[int, int]] = [{}]
        self.count: list[dict[int, int]] = [defaultdict(int)]  # by symbol, END for stopping
        self.total = [0]
        for text in examples:
            state = 0
            for symbol in text.translate(CLASS):
                self.count[state][symbol] += 1
                self.total[state] += 1
                if symbol not in self.next[state]:
                    self.next[state][symbol] = len(self.next)
                    self.next.append({})
                    self.count.append(defaultdict(int))
                    self.total.append(0)
                state = self.next[state][symbol]
            self.count[state][END] += 1
            self.total[state] += 1
        self._merge()
        self._weigh()

    def _differ(self, a: int, b: int) -> bool:
        n, m = self.total[a], self.total[b]
        bound = self.alpha * (1 / math.sqrt(n) + 1 / math.sqrt(m))
        return any(abs(self.count[a].get(s, 0) / n - self.count[b].get(s, 0) / m) > bound for s in {*self.count[a], *self.count[b]})

    def _compatible(self, a: int, b: int) -> bool:
        todo = [(a, b)]
        while todo:
            x, y = todo.pop()
            if not self.total[x] or not self.total[y]:
                continue
            if self._differ(x, y):
                return False
            todo += [(self.next[x][s], self.next[y][s]) for s in self.next[x].keys() & self.next[y].keys() if self.next[x][s] != self.next[y][s]]
        return True

    def _fold(self, into: int, tree: int) -> None:
        todo = [(into, tree)]
        while todo:
            x, y = todo.pop()
            for s, n in self.count[y].items():
                self.count[x][s] += n
            self.total[x] += self.total[y]
            for s, child in self.next[y].items():
                if s in self.next[x]:
                    todo.append((self.next[x][s], child))
                else:
                    self.next[x][s] = child

    def _merge(self) -> None:
        red, known = [0], {0}
        while True:
            blue = [(x, s) for x in red for s in sorted(self.next[x]) if self.next[x][s] not in known]
            if not blue:
                break
            x, s = max(blue, key=lambda e: (self.total[self.next[e[0]][e[1]]], -e[0], -e[1]))
            child = self.next[x][s]
            for r in red:
                if self._compatible(r, child):
                    self.next[x][s] = r
                    self._fold(r, child)
                    break
            else:
                red.append(child)
                known.add(child)
        self.states = red

    def _weigh(self) -> None:
        """Log probabilities of steps, smoothed; a step that was never met leads back to the start."""
        place = {x: i for i, x in enumerate(self.states)}
        self.step, self.to = [], []
        for x in self.states:
            n = self.total[x] + 0.5 * (END + 1)
            size = [*CLASS_SIZE, 1]
            self.step.append([math.log((self.count[x].get(s, 0) + 0.5) / n / size[s]) for s in range(END + 1)])
            self.to.append([place[self.next[x][s]] if s in self.next[x] else 0 for s in range(END)])
        del self.next, self.count, self.total

    def log_likelihood(self, text: bytes) -> float:
        state, out, step, to = 0, 0.0, self.step, self.to
        for symbol in text.translate(CLASS):
            out += step[state][symbol]
            state = to[state][symbol]
        return out + step[state][END]


def smallest(values: set[tuple[str, bytes]], most: int) -> list[tuple[str, bytes, int]]:
    """For each kind the most values of the smallest hashes."""
    by = defaultdict(list)
    for kind, value in values:
        by[kind].append((xxh64_intdigest(value) >> 1, value))
    return [(kind, value, h) for kind, own in by.items() for h, value in nsmallest(most, own)]


def infer(docs: DataFrame, text_col: str = "text", most_examples: int = 1_000, longest: int = 200) -> dict[str, Automaton]:
    """Automata by kind, '' for ordinary runs, from at most most_examples values a kind of all documents."""

    def run(batches):
        held: set[tuple[str, bytes]] = set()
        for batch in batches:
            raws = raw_texts(batch.column(0))
            found, candidates = base_spans(raws)
            for raw, spans, runs_ in zip(raws, found, candidates, strict=True):
                values = [(k, *value_span(raw, k, a, b)) for k, a, b in spans]
                held |= {(k, raw[a:b]) for k, a, b in values if b - a <= longest}
                reach = Reach([(a, b) for _, a, b in values])
                held |= {("", raw[a:b]) for a, b in runs_ if b - a <= longest and reach.before(b) <= a}
            if len(held) > 16 * most_examples:
                held = {(k, v) for k, v, _ in smallest(held, most_examples)}
        if held:
            rows = smallest(held, most_examples)
            yield pa.RecordBatch.from_arrays([pa.array([k for k, *_ in rows], pa.string()), pa.array([v.decode() for _, v, _ in rows], pa.string()), pa.array([h for *_, h in rows], pa.int64())], ["kind", "value", "h"])

    values = cut(docs.select(F.col(text_col).alias("text")).mapInArrow(run, "kind string, value string, h long").distinct())
    taken = {kind: [r.value.encode() for r in values.where(F.col("kind") == kind).orderBy("h", "value").limit(most_examples).collect()] for kind in ("", *KINDS[:3])}
    return automata_of(taken)


def automata_of(taken: dict[str, list[bytes]]) -> dict[str, Automaton]:
    """Automata of labelled values by kind, and of the unlabelled ones ('') without those that look like a credential."""
    out = {kind: Automaton(own) for kind, own in taken.items() if kind and own}
    likely = {kind: float(np.quantile([x.log_likelihood(v) / len(v) for v in taken[kind]], 0.05)) for kind, x in out.items()}
    plain = taken.get("", [])
    if plain and out:
        every = Automaton(plain)
        alike = lambda v: any((y := x.log_likelihood(v)) > every.log_likelihood(v) and y >= likely[kind] * len(v) for kind, x in out.items())
        plain = [v for v in plain if not any(alike(x) for x in {v, *re.split(b"[" + re.escape(JOINS) + b"]", v)} if len(x) >= LEAST["format"])]
    return out | ({"": Automaton(plain)} if plain else {})


def points(raw: bytes, offsets: list[int]) -> dict[int, int]:
    """Code points before each byte offset."""
    if raw.isascii():
        return {x: x for x in offsets}
    out, last, seen = {}, 0, 0
    for x in sorted(set(offsets)):
        seen += len(raw[last:x].decode())
        out[x], last = seen, x
    return out


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda x: (x[1], KINDS.index(x[0]), x[2])))


def scan(docs: DataFrame, automata: dict[str, Automaton] | None = None, threshold: float = 12.0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, n_format, base_sha256, spans, scores (log ratios of the format spans) of every row."""
    automata = infer(docs, text_col) if automata is None else automata
    source = texts_of(docs, id_col, text_col)
    kinds = {k: a for k, a in automata.items() if k}
    held = docs.sparkSession.sparkContext.broadcast((kinds, automata.get("")))
    kind = source.schema["doc_id"].dataType.simpleString()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        raws = raw_texts(batch.column(1))
        found, candidates = base_spans(raws)
        own, ordinary = held.value
        counts, digest, spans_out, scores_out = [], [], [], []
        for raw, spans, runs_ in zip(raws, found, candidates, strict=True):
            scored, reach = [], Reach([(a, b) for _, a, b in spans])
            for a, b in runs_ if own and ordinary else ():
                text = raw[a:b]
                ratio = max(x.log_likelihood(text) for x in own.values()) - ordinary.log_likelihood(text)
                if ratio >= threshold and reach.before(a + 1) < b:
                    scored.append((ratio, a, b))
            taken: list[tuple[int, int, float]] = []
            for ratio, a, b in sorted(scored, key=lambda x: (-x[0], x[1], x[2])):
                at_ = bisect_left(taken, (a, b, ratio))
                if (at_ == 0 or taken[at_ - 1][1] <= a) and (at_ == len(taken) or b <= taken[at_][0]):
                    taken.insert(at_, (a, b, ratio))
            more, scores = [("format", a, b) for a, b, _ in taken], [x for *_, x in taken]
            at = points(raw, [x for _, a, b in [*spans, *more] for x in (a, b)]) if spans or more else {}
            base, extra = [(k, at[a], at[b]) for k, a, b in spans], [(k, at[a], at[b]) for k, a, b in more]
            counts.append([sum(k == name for k, *_ in base) for name in KINDS[:3]] + [len(extra)])
            digest.append(hashlib.sha256(joined(base).encode()).hexdigest())
            spans_out.append(joined(base + extra))
            scores_out.append(scores)
        table = np.array(counts, np.int64).reshape(-1, 4)
        return pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(table[:, k]) for k in range(4)], pa.array(digest, pa.string()), pa.array(spans_out, pa.string()), pa.array(scores_out, pa.list_(pa.float64()))], ["doc_id", "n_assign", "n_access", "n_hex", "n_format", "base_sha256", "spans", "scores"])

    return source.mapInArrow(per_batch(kernel), f"doc_id {kind}, n_assign long, n_access long, n_hex long, n_format long, base_sha256 string, spans string, scores array<double>")
