"""Mixing documents to target weights by soft domain membership; DataFrame functions only.

A classifier learnt from the labelled table (multinomial naive Bayes over hashed different words, every labelled row, a bounded table of
`buckets` words by domains) gives each document a posterior over domains, its log odds tempered by the root of its number of words.
The rates solve a least-squares problem: of all rates r >= least under which each domain's expected token total
sum(r * tokens * posterior) is the wanted one, those nearest to a common level (squares weighted by tokens; where no rates reach the
totals, the totals' relative errors are least squares). They are found by projected gradients: a step adds to every rate its posterior
times the totals' residuals, scaled by the inverse of the rates' second derivatives so that few steps suffice, and projects it on
r >= least. All steps of a row add up to one multiplier a domain, so a step is one aggregate of a few numbers a domain and no row holds
state between steps. They end when every total is within the tolerance. What cannot be reached is reported as a warning with the
totals there are.

A rate becomes a number of copies: its whole part, and one more with the probability of its fraction, drawn by a hash of the row.
Nulls: a null text has no words, no tokens and the prior as its posterior. A null label leaves a row out of the training. Without
labelled rows all posteriors are even. Rows are kept one for one; empty tables give empty results.
"""

from __future__ import annotations

import json
import math
import warnings
from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from paramstore.llm.common import cut, row_key

BLANKS = "\t\n\x0b\x0c\r"


def word_list(column):
    """Words in lower case; blanks become spaces first, for a split by one character needs no regular expression."""
    text = F.lower(F.coalesce(column, F.lit("")))
    for blank in BLANKS:
        text = F.replace(text, F.lit(blank), F.lit(" "))
    return F.array_remove(F.split(text, " "), "")


def features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int = 4096) -> DataFrame:
    """doc_id, key, tokens (words) and the buckets of the different words of every row."""
    words = docs.select(F.col(id_col).alias("doc_id"), row_key(id_col, text_col).alias("key"), word_list(F.col(text_col)).alias("words"))
    return words.select("doc_id", "key", F.size("words").cast("long").alias("tokens"), F.array_distinct(F.transform("words", lambda w: F.pmod(F.xxhash64(w), F.lit(buckets)).cast("int"))).alias("hashed"))


def learn(featured: DataFrame, labels: DataFrame, domain, label_id: str = "doc_id", buckets: int = 4096) -> tuple[list[str], list[float], list[list[float]]]:
    """Domains, log priors and the log likelihood of each bucket by domain."""
    marked = labels.select(F.col(label_id).alias("doc_id"), domain.alias("domain")).where("domain is not null")
    rows = featured.join(marked.hint("merge"), "doc_id").select("domain", "hashed")
    counts = rows.groupBy("domain").agg(F.count("*").alias("n")).collect()
    seen = rows.select("domain", F.explode("hashed").alias("bucket")).groupBy("domain", "bucket").count().collect()  # buckets by domains at most
    names = sorted(r.domain for r in counts)
    n = {r.domain: r.n for r in counts}
    words = {d: 1.0 * buckets for d in names}
    for r in seen:
        words[r.domain] += r["count"]
    table = [[-math.log(words[d]) for d in names] for _ in range(buckets)]
    for r in seen:
        table[r.bucket][names.index(r.domain)] = math.log((r["count"] + 1.0) / words[r.domain])
    total = sum(n.values())
    return names, [math.log(n[d] / total) for d in names], table


def posteriors(featured: DataFrame, names: list[str], priors: list[float], table: list[list[float]]) -> DataFrame:
    """featured with p, the posterior of each domain in the order of names; without the buckets."""
    if not names:
        return featured.withColumn("p", F.array(F.lit(1.0))).drop("hashed")
    even = [[round(x - sum(row) / len(row), 6) for x in row] for row in table]  # only differences between domains count
    weights = F.from_json(F.lit(json.dumps(even)), "array<array<double>>")
    zero = F.array(*[F.lit(0.0) for _ in names])
    odds = F.aggregate("hashed", zero, lambda acc, b: F.zip_with(acc, F.get(weights, b), lambda x, y: x + y))
    scale = F.sqrt(F.greatest(F.size("hashed"), F.lit(1)).cast("double"))
    logits = F.zip_with("odds", F.array(*[F.lit(x) for x in priors]), lambda x, y: x / F.col("scale") + y)
    scored = featured.withColumns({"odds": odds, "scale": scale}).withColumn("logits", logits)
    powers = F.transform("logits", lambda x: F.exp(x - F.array_max("logits")))
    total = F.aggregate("powers", F.lit(0.0), lambda a, x: a + x)
    return scored.withColumn("powers", powers).withColumn("p", F.transform("powers", lambda x: x / total)).drop("hashed", "odds", "scale", "logits", "powers")


class Unreached(UserWarning):
    """Domain totals that no rates reach, or that were not reached in the rounds."""


def projected_rate(multipliers: list[float], level: float, least: float):
    """The rate of a row with the posterior p under one multiplier a domain, before and after its projection on least and above."""
    free = F.lit(float(level))
    for k, x in enumerate(multipliers):
        free = free + F.lit(float(x)) * F.get("p", F.lit(k))
    return free, F.greatest(F.lit(float(least)), free)


def solve(member: DataFrame, target: list[float], level: float = 1.0, least: float = 0.0, tolerance: float = 1e-3, most_rounds: int = 60, pull: float = 1e-6) -> tuple[object, list[float], bool]:
    """The rate as a column over member (tokens, p), the expected domain totals it gives, and whether all are within tolerance.

    target: the wanted totals. pull: weight of the level against the relative errors of the totals. It keeps the multipliers finite
    where no rates reach the totals; then the errors are least squares.
    """
    n, want = len(target), np.array(target, float)
    scale = np.maximum(want, 1.0)
    pairs = [(k, m) for k in range(n) for m in range(k, n)]

    def measure(multipliers: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """The objective's value, the totals, and the totals' derivatives by the multipliers."""
        free, rate = projected_rate(multipliers.tolist(), level, least)
        at = [F.get("p", F.lit(k)) for k in range(n)]
        moving = F.when(F.col("free") > least, F.col("tokens")).otherwise(0)
        sums = [*[F.col("rate") * F.col("tokens") * p for p in at], *[moving * at[k] * at[m] for k, m in pairs], F.col("tokens") * (F.col("rate") * F.col("free") - (F.pow(F.col("rate"), 2) + level**2) / 2)]
        row = [float(x) for x in member.select("tokens", "p", free.alias("free"), rate.alias("rate")).agg(*[F.coalesce(F.sum(x), F.lit(0.0)).alias(f"s{i}") for i, x in enumerate(sums)]).first()]
        slopes = np.diag(pull * scale)
        for (k, m), x in zip(pairs, row[n:-1], strict=True):
            slopes[k, m] += x
            slopes[m, k] = slopes[k, m]
        return float(multipliers @ want - row[-1] - pull / 2 * (scale * multipliers**2).sum()), np.array(row[:n]), slopes

    now = np.zeros(n)
    value, got, slopes = measure(now)
    for _ in range(most_rounds):
        rising = want - got - pull * scale * now
        if (np.abs(got - want) <= tolerance * scale).all() or (np.abs(rising) <= tolerance / 10 * scale).all():
            break
        step, share = np.linalg.solve(slopes, rising), 1.0
        while True:
            tried = measure(now + share * step)
            if tried[0] >= value + 1e-4 * share * float(rising @ step) or share < 1e-6:
                break
            share /= 2
        now, (value, got, slopes) = now + share * step, tried
    return projected_rate(now.tolist(), level, least)[1], got.tolist(), bool((np.abs(got - want) <= tolerance * scale).all())


class Plan(NamedTuple):
    """member: doc_id, key, tokens, p, rate of every row. want, got: the wanted and the expected tokens of each of names."""

    member: DataFrame
    names: list[str]
    want: list[float]
    got: list[float]
    budget: float
    reached: bool


def plan(docs: DataFrame, labels: DataFrame, domain, weights: dict[str, float], budget: float | None = 1.0, least: float = 0.0, id_col: str = "doc_id", text_col: str = "text", label_id: str = "doc_id", buckets: int = 4096, most_growth: float = 4.0) -> Plan:
    """The rates of mix(), with what they give.

    A budget of None is sought from the least that the domains' natural totals allow, up to most_growth times it.
    """
    featured = cut(features(docs, id_col, text_col, buckets))  # texts are taken apart once
    names, priors, table = learn(featured, labels, domain, label_id, buckets)
    member = cut(posteriors(featured, names, priors, table))
    names = names or ["all"]
    given = sum(weights.get(d, 0.0) for d in names)
    rest = [d for d in names if d not in weights]
    share = [weights.get(d, max(0.0, 1.0 - given) / max(len(rest), 1)) for d in names]
    share = [x / (sum(share) or 1.0) for x in share]
    natural = member.agg(F.coalesce(F.sum("tokens"), F.lit(0)), *[F.coalesce(F.sum(F.col("tokens") * F.get("p", F.lit(k))), F.lit(0.0)) for k in range(len(names))]).first()
    total = natural[0]
    size = budget
    if size is None:  # no total may be below least times the natural one; posteriors are soft, so a little more is needed
        size = max(1.0, least, *[least * x / (s * total) for x, s in zip(natural[1:], share, strict=True) if s and total])
    sizes = [size] if budget is not None else [size * 1.2**i for i in range(1 + int(math.log(most_growth, 1.2)))]
    tried = []
    for size in sizes:
        want = [s * total * size for s in share]
        tried.append((size, want, *solve(member, want, max(size, least), least)))
        if tried[-1][-1]:
            break
    size, want, rate, got, reached = tried[-1] if tried[-1][-1] else tried[0]
    if not reached:
        warnings.warn("; ".join(f"{d}: {g:.0f} tokens of {w:.0f}" for d, g, w in zip(names, got, want, strict=True)), Unreached, stacklevel=3)
    return Plan(member.withColumn("rate", rate), names, want, got, size, reached)


def mix(docs: DataFrame, labels: DataFrame, domain, weights: dict[str, float], budget: float | None = 1.0, least: float = 0.0, id_col: str = "doc_id", text_col: str = "text", label_id: str = "doc_id", buckets: int = 4096) -> DataFrame:
    """doc_id, key, tokens, domain (likeliest), posterior (of it), rate, copies of every row of docs.

    domain: a column over labels that names a row's domain. weights: the wanted share of each domain's tokens (others get what is
    left, evenly). budget: wanted tokens in all, as a multiple of the tokens there are; it is also the level rates are pulled to;
    None: as few as reach the weights under least, to a fifth. least: the smallest rate; 1 keeps every document at least once and
    reaches the targets by repeating documents alone, for which the budget must be large enough.
    """
    found = plan(docs, labels, domain, weights, budget, least, id_col, text_col, label_id, buckets)
    draw = F.pmod(F.xxhash64("key.a", "key.b", F.lit("mix")), F.lit(1 << 32)) / float(1 << 32)
    best = F.array_position("p", F.array_max("p")).cast("int")
    named = F.get(F.array(*[F.lit(d) for d in found.names]), best - 1)
    return found.member.select("doc_id", "key", "tokens", named.alias("domain"), F.array_max("p").alias("posterior"), "rate", (F.floor("rate") + (draw < F.col("rate") - F.floor("rate")).cast("long")).alias("copies"))


def apply_copies(docs: DataFrame, mixed: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs, all columns, each row as often as mixed says."""
    times = mixed.select("doc_id", "key", "copies").where("copies <> 1").dropDuplicates(["doc_id", "key"])
    held = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(id_col).alias("id"), row_key(id_col, text_col).alias("of"))
    rows = held.join(times, held.id.eqNullSafe(times.doc_id) & (held.of == times.key), "left")
    n = F.coalesce("copies", F.lit(1)).cast("int")
    return rows.where(n > 0).select("row", F.explode(F.sequence(F.lit(1), n))).select("row.*")
