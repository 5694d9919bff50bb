"""Accuracy degradation: outputs of models with original and with restored parameters, compared.

A model is a linear head whose weight rows are its layers. Heads are restored by each method on the driver and broadcast, in groups of
models of a checked size; inputs of any number (seeded noise, or feature vectors of texts and events) meet them block by block where they
are read, and only counts of comparisons leave a task. Outputs exist in blocks of inputs and layers alone, whatever a model's size. Sets of
best outputs are taken from the original's outputs, and a method's outputs are made for inputs whose set its errors could change;
cosines are quadratic forms of the inputs, by matrices as wide as an input.
"""

from __future__ import annotations

from collections import defaultdict
from itertools import chain, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paramstore.functions.bits import BOUND
from paramstore.operators import kernels, unitpack
from paramstore.sources.shared import cut, kept

METHODS = ("hybrid", "predquant", "zfp", "mp", "mp2e", "gouq", "gouq2e", "half")


def restored(values: np.ndarray, method: str, dtype: str = "float32") -> np.ndarray:
    """float32 values after compression by method and decompression."""
    eb, x = BOUND[dtype], values.astype(np.float64)
    if method == "hybrid":
        bits = values.view(np.int32).astype(np.int64)
        return unitpack.unpack(unitpack.pack(bits, dtype), dtype).astype(np.int32).view(np.float32)
    if method == "predquant":
        return (np.floor(x / (2 * eb) + 0.5) * (2 * eb)).astype(np.float32)
    if method == "zfp":
        return kernels.zfp(x, dtype, eb)[1].astype(np.float32)
    if method in ("mp", "mp2e"):
        return np.where(np.abs(x) < eb * (2 if method == "mp2e" else 1), 0, values).astype(np.float32)
    if method in ("gouq", "gouq2e"):
        step = 2 * eb * (2 if method == "gouq2e" else 1)
        near = np.abs(x - x.mean()) <= 3 * x.std()
        low = x[near].min(initial=0.0)
        return np.where(near, low + np.floor((x - low) / step + 0.5) * step, x).astype(np.float32)
    if method == "half":
        return values.astype(np.float16).astype(np.float32)
    raise ValueError(method)


def restored_rows(rows: np.ndarray, method: str, dtype: str = "float32") -> np.ndarray:
    """restored() of each row of a matrix, all rows at once."""
    if method == "zfp":
        m, width = rows.shape
        wide = np.pad(rows, ((0, 0), (0, -width % 4)), mode="edge") if width else rows  # blocks of four stay within a row
        return kernels.zfp(wide.astype(np.float64).ravel(), dtype, BOUND[dtype], count_bits=False)[1].astype(np.float32).reshape(m, -1)[:, :width]
    if method in ("gouq", "gouq2e"):
        x, step = rows.astype(np.float64), 2 * BOUND[dtype] * (2 if method == "gouq2e" else 1)
        near = np.abs(x - x.mean(axis=1, keepdims=True)) <= 3 * x.std(axis=1, keepdims=True)
        low = np.where(near, x, 0.0).min(axis=1, initial=0.0, keepdims=True)
        return np.where(near, low + np.floor((x - low) / step + 0.5) * step, x).astype(np.float32)
    return restored(np.ascontiguousarray(rows).ravel(), method, dtype).reshape(rows.shape)


def noise_inputs(spark: SparkSession, count: int = 1024, width: int = 64, seed: int = 11) -> DataFrame:
    """(task, payload): count vectors of standard normal noise, each from its own number."""

    def run(batches):
        for batch in batches:
            out = [np.random.default_rng((seed, i)).standard_normal(width).astype(np.float32).tobytes() for i in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(["noise"] * len(out)), pa.array(out, pa.binary())], ["task", "payload"])

    return spark.range(count).mapInArrow(run, "task string, payload binary")


def head_groups(layers: DataFrame, methods=METHODS, most_bytes: int = 64 << 20):
    """Groups of models, each {model: {method: matrix}} with 'original' among the methods, so that a group has about most_bytes."""
    sizes = sorted((r.model_id, r.size) for r in layers.groupBy("model_id").agg(F.sum(F.length("payload")).alias("size")).collect())  # a row for each model
    groups, room = [], 0
    for model, size in sizes:
        size *= len(methods) + 1
        if not groups or size > room:
            groups.append([])
            room = most_bytes
        groups[-1].append(model)
        room -= size
    for own in groups:
        rows: dict[str, list] = {}
        for r in layers.where(F.col("model_id").isin(own)).select("model_id", "layer_seq", "payload").collect():
            rows.setdefault(r.model_id, []).append((r.layer_seq, np.frombuffer(r.payload, np.float32)))
        heads = {}
        for model, parts in rows.items():
            ordered = [x for _, x in sorted(parts, key=lambda p: p[0])]
            width = max(map(len, ordered))
            heads[model] = {m: np.zeros((len(ordered), width), np.float32) for m in ("original", *methods)}  # a shorter row has no weight for the rest
            for size in {len(x) for x in ordered}:
                at = [i for i, x in enumerate(ordered) if len(x) == size]
                own = np.stack([ordered[i] for i in at])
                for m, head in heads[model].items():
                    head[at, :size] = own if m == "original" else restored_rows(own, m)
        yield heads


def folded(x: np.ndarray, width: int) -> np.ndarray:
    """Inputs as wide as a head: further columns are added to the first ones, missing ones are zero."""
    if x.shape[1] == width:
        return x
    out = np.zeros((len(x), width), np.float32)
    for at in range(0, x.shape[1], width):
        part = x[:, at : at + width]
        out[:, : part.shape[1]] += part
    return out


class Compared:
    """The outputs a, that others are held against: 'bits' of each output, 'cosine' of an input's outputs, 'topk' sets of an input."""

    def __init__(self, a: np.ndarray, compare: str, k: int = 5):
        self.compare, self.a, self.k = compare, a, k
        if compare == "cosine":
            self.a = a.astype(np.float64)
            self.square = (self.a * self.a).sum(axis=1)
        elif compare == "topk":
            self.best = self._best(a) if a.shape[1] > k else None
        elif compare != "bits":
            raise ValueError(compare)

    def _sorted(self, x: np.ndarray) -> np.ndarray:
        return np.sort(np.argsort(-x, axis=1, kind="stable")[:, : self.k], axis=1)  # ties by place

    def _best(self, x: np.ndarray) -> np.ndarray:
        best = np.sort(np.argpartition(-x, self.k - 1, axis=1)[:, : self.k], axis=1)
        least = np.take_along_axis(x, best, axis=1).min(axis=1, keepdims=True)
        tied = np.flatnonzero((x >= least).sum(axis=1) != self.k)
        best[tied] = self._sorted(x[tied])
        return best

    def differing(self, b: np.ndarray) -> tuple[int, int]:
        """How many comparisons differ, and how many there are."""
        if self.compare == "bits":
            return int((self.a != b).sum()), b.size
        if self.compare == "cosine":
            b = b.astype(np.float64)
            norm = np.sqrt(self.square * (b * b).sum(axis=1))
            cosine = np.where(norm > 0, (self.a * b).sum(axis=1) / np.where(norm > 0, norm, 1), 1.0)
            return int((np.round(cosine, 9) != 1.0).sum()), len(b)
        if self.best is None:  # all outputs are among the best
            return 0, len(b)
        # the same set if the least of it is above all others; only what doesn't show that is sorted
        inside, others = np.take_along_axis(b, self.best, axis=1).min(axis=1), b.copy()
        np.put_along_axis(others, self.best, -np.inf, axis=1)
        open_ = np.flatnonzero(~(inside > others.max(axis=1)))
        return int((self._sorted(b[open_]) != self.best[open_]).any(axis=1).sum()), len(b)


def differing(a: np.ndarray, b: np.ndarray, compare: str, k: int = 5) -> tuple[int, int]:
    """How many comparisons of a and b differ, and how many there are."""
    return Compared(a, compare, k).differing(b)


class Head:
    """A model's matrices {'original' or method: layers by width}, and how many comparisons of outputs differ for inputs."""

    #: Inputs and layers of a block of outputs; and how many outputs are held at once where whole rows of them are needed.
    ROWS, LAYERS, MOST = 512, 1024, 1 << 20
    #: Of fewer inputs products are summed in another order, so that near ties would fall otherwise than among many.
    FEW = 64
    #: Rounding of a float32, and from what on 1 - cosine is not 0 in nine digits.
    UNIT, APART = 2.0**-24, 5e-10

    def __init__(self, by: dict[str, np.ndarray], methods):
        self.by, self.methods = by, methods
        self.n, self.width = by["original"].shape
        self.forms: dict | None = None
        self.errors: dict[str, float] | None = None

    def _layers(self):
        for at in range(0, self.n, self.LAYERS):
            yield {m: w[at : at + self.LAYERS] for m, w in self.by.items()}

    def _whole(self, x: np.ndarray, method: str, compare: str, k: int) -> int:
        """How many of the inputs x differ, by all outputs."""
        step, out = max(1, self.MOST // self.n), 0
        for at in range(0, len(x), step):
            part = x[at : at + step]
            many = np.concatenate([part, np.zeros((max(0, min(self.FEW, step) - len(part)), self.width), np.float32)])
            a, b = ((many @ self.by[m].T)[: len(part)] for m in ("original", method))
            out += Compared(a, compare, k).differing(b)[0]
        return out

    def _bits(self, x: np.ndarray) -> dict[str, int]:
        out = dict.fromkeys(self.methods, 0)
        for at in range(0, len(x), self.ROWS):
            part = x[at : at + self.ROWS]
            for w in self._layers():
                a = part @ w["original"].T
                for m in self.methods:
                    out[m] += int((a != part @ w[m].T).sum())
        return out

    def _margins(self, x: np.ndarray, k: int) -> np.ndarray:
        """By how much the k-th best output of each input is above the next one."""
        out = np.empty(len(x))
        for at in range(0, len(x), self.ROWS):
            part, best = x[at : at + self.ROWS], None
            for w in self._layers():
                a = part @ w["original"].T
                a = a if best is None else np.concatenate([best, a], axis=1)
                if a.shape[1] > k + 1:
                    a.partition(a.shape[1] - k - 1, axis=1)
                best = a[:, -(k + 1) :].copy()
            best.sort(axis=1)
            with np.errstate(invalid="ignore"):
                out[at : at + len(part)] = best[:, 1].astype(np.float64) - best[:, 0]
        return out

    def _topk(self, x: np.ndarray, k: int) -> dict[str, int]:
        if self.n <= k:  # all outputs are among the best
            return dict.fromkeys(self.methods, 0)
        if self.errors is None:
            norms = lambda f: float(np.max([np.sqrt((f(w) ** 2).sum(axis=1)).max() for w in self._layers()]))
            with np.errstate(invalid="ignore", over="ignore"):
                self.errors = {m: norms(lambda w, m=m: w[m].astype(np.float64) - w["original"]) for m in self.methods}
                self.largest = norms(lambda w: w["original"].astype(np.float64))
        with np.errstate(invalid="ignore", over="ignore"):
            size = np.sqrt(np.einsum("ij,ij->i", x, x, dtype=np.float64))
        margin, out = self._margins(x, k), {}
        for m, error in self.errors.items():
            if error == 0:  # restored as they were
                out[m] = 0
                continue
            # an output is off by the error of its layer and by rounding, of either product; so is the other one it is compared with
            turn, rounding = size * error, (self.width + 2) * self.UNIT * size
            with np.errstate(invalid="ignore"):
                sure = lambda turn, at: np.isfinite(margin[at]) & (margin[at] > 2 * turn + 4 * rounding[at] * (self.largest + error) + 1e-40)  # noqa: E731, B023
                open_ = np.flatnonzero(~(sure(turn, slice(None)) | (size == 0) & np.isfinite(error + self.largest)))
                open_ = open_[~sure(self._turn(x[open_], m) + 2 * rounding[open_] * error, open_)]
            out[m] = self._whole(x[open_], m, "topk", k)
        return out

    def _turn(self, x: np.ndarray, method: str) -> np.ndarray:
        """By how much an output of each input is off at most, before rounding."""
        out = np.zeros(len(x))
        for at in range(0, len(x), self.ROWS):
            part = x[at : at + self.ROWS]
            for w in self._layers():
                off = part @ (w[method] - w["original"]).T
                out[at : at + len(part)] = np.maximum(out[at : at + len(part)], np.maximum(off.max(axis=1), -off.min(axis=1)))
        return out

    def _cosine(self, x: np.ndarray) -> dict[str, int]:
        if self.forms is None:
            self.forms = {m: [np.zeros((self.width, self.width)) for _ in range(2)] for m in self.by}  # with the original, with itself
            with np.errstate(invalid="ignore", over="ignore"):
                for part in self._layers():
                    w = part["original"].astype(np.float64)
                    for m, forms in self.forms.items():
                        own = part[m].astype(np.float64)
                        forms[0] += w.T @ own
                        forms[1] += own.T @ own
        out, wide = {}, x.astype(np.float64)
        with np.errstate(invalid="ignore", over="ignore", divide="ignore"):
            form = lambda g: ((wide @ g) * wide).sum(axis=1)
            square, size = form(self.forms["original"][1]), (wide * wide).sum(axis=1)
            total = np.trace(self.forms["original"][1])
            for m in self.methods:
                norm = np.sqrt(square * form(self.forms[m][1]))
                off = 1 - form(self.forms[m][0]) / norm
                # float32 outputs turn an input's outputs by some such angle; near the limit all outputs are made
                angle = 8 * self.UNIT * np.sqrt(size * max(total, np.trace(self.forms[m][1])) / norm)
                band = angle * (angle + np.sqrt(2 * self.APART))
                sure = np.isfinite(off) & (np.abs(off - self.APART) > band) & (band < self.APART)
                none = (size == 0) & np.isfinite(total) & np.isfinite(np.trace(self.forms[m][1]))
                out[m] = int((sure & (off > self.APART)).sum()) + self._whole(x[~sure & ~none], m, "cosine", 0)
        return out

    def differing(self, x: np.ndarray, compare: str, k: int = 5) -> dict[str, tuple[int, int]]:
        """For each method, how many comparisons of inputs x differ, and how many there are."""
        if compare not in ("bits", "cosine", "topk"):
            raise ValueError(compare)
        x = folded(x, self.width)
        found = self._bits(x) if compare == "bits" else self._cosine(x) if compare == "cosine" else self._topk(x, k)
        return {m: (found[m], len(x) * (self.n if compare == "bits" else 1)) for m in self.methods}


def outputs_differ(inputs: DataFrame, layers: DataFrame, compares: dict[str, str], methods=METHODS, k: int = 5) -> DataFrame:
    """(task, method, model_id, differ, n) over inputs (task, payload) and all models of layers; compares: each task's comparison."""
    groups, out = iter(head_groups(layers, methods)), None
    first = list(islice(groups, 2))
    if len(first) > 1:
        inputs = kept(inputs.select("task", "payload"))  # vectors are made once for all groups
    for group in chain(first, groups):
        held = layers.sparkSession.sparkContext.broadcast(group)

        def run(batches, held=held):
            heads = {model: Head(by, methods) for model, by in held.value.items()}
            counts: dict[tuple[str, str, str], list[int]] = {}
            for batch in batches:
                tasks, payloads = np.array(batch.column(0).to_pylist(), object), batch.column(1).to_pylist()
                for task in sorted(set(tasks)):
                    own = [payloads[i] for i in np.flatnonzero(tasks == task).tolist()]
                    x = np.frombuffer(b"".join(own), np.float32).reshape(len(own), -1)
                    for model, head in heads.items():
                        for method, (differ, n) in head.differing(x, compares[task], k).items():
                            c = counts.setdefault((task, method, model), [0, 0])
                            c[0] += differ
                            c[1] += n
            if counts:
                keys = list(zip(*counts, strict=True))
                yield pa.RecordBatch.from_arrays([*[pa.array(x) for x in keys], *[pa.array(list(x), pa.int64()) for x in zip(*counts.values(), strict=True)]], ["task", "method", "model_id", "differ", "n"])

        part = inputs.select("task", "payload").mapInArrow(run, "task string, method string, model_id string, differ long, n long")
        out = part if out is None else out.union(part)
    if out is None:
        out = layers.sparkSession.createDataFrame([], "task string, method string, model_id string, differ long, n long")
    return out.groupBy("task", "method", "model_id").agg(F.sum("differ").alias("differ"), F.sum("n").alias("n"))


def degradation(counted: DataFrame) -> DataFrame:
    """(task, method, ad, n, models): percent of comparisons that differ, and how many models were compared."""
    return counted.groupBy("task", "method").agg((100.0 * F.sum("differ") / F.sum("n")).alias("ad"), F.sum("n").alias("n"), F.count("*").alias("models"))


def overall(rows: DataFrame, weight: str | None = None) -> DataFrame:
    """Mean degradation of each method over rows, plain or by weight."""
    if weight is None:
        return rows.groupBy("method").agg(F.avg("ad").alias("ad"))
    return rows.groupBy("method").agg((F.sum(F.col("ad") * F.col(weight)) / F.sum(weight)).alias("ad"))


def all_methods(payloads: list[bytes], methods) -> np.ndarray:
    """Vectors as given and as each method restores them, (methods + 1, vectors, width) in double; shorter ones end in zeros."""
    vectors = [np.frombuffer(p, np.float32) for p in payloads]
    out = np.zeros((len(methods) + 1, len(vectors), max(map(len, vectors), default=0)))
    for width in {len(v) for v in vectors}:
        own = [i for i, v in enumerate(vectors) if len(v) == width]
        rows = np.array([vectors[i] for i in own], np.float32).reshape(len(own), width)
        for k, method in enumerate([None, *methods]):
            out[k, own, :width] = rows if method is None else restored_rows(rows, method)
    return out


def added(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The sum of two matrices, the narrower one with zeros at its end."""
    out = np.zeros((len(a), max(a.shape[1], b.shape[1])))
    out[:, : a.shape[1]] += a
    out[:, : b.shape[1]] += b
    return out


def label_groups(means: DataFrame, methods, most_bytes: int = 64 << 20):
    """Groups of labels, each {task: (labels in order, {label: matrix of its centroids by method})}, of about most_bytes."""
    group, room, rows = {}, most_bytes, 0
    for r in means.orderBy("task", "label", "method").toLocalIterator():
        own = group.setdefault(r.task, {}).setdefault(r.label, [])
        own.append(np.array(r.c))
        room -= own[-1].nbytes
        rows += 1
        if room < 0 and rows % (len(methods) + 1) == 0:  # with all methods of a label
            yield group
            group, room = {}, most_bytes
    if group:
        yield group


def nearest(vectors: DataFrame, means: DataFrame, methods) -> DataFrame:
    """(task, label, guesses): the label of the nearest centroid for each row of vectors and each method, the given vectors first; ties go to the first label."""
    out, groups = None, 0
    for group in label_groups(means, methods):
        held, groups = vectors.sparkSession.sparkContext.broadcast(group), groups + 1

        def run(batches, held=held):
            for batch in batches:
                tasks, payloads = batch.column(0).to_pylist(), batch.column(2).to_pylist()
                off, guess = np.full((len(methods) + 1, len(tasks)), np.inf), np.full((len(methods) + 1, len(tasks)), None, object)
                for task in sorted(set(tasks) & set(held.value)):
                    at = np.array([i for i, t in enumerate(tasks) if t == task])
                    every = all_methods([payloads[i] for i in at], methods)
                    for label in sorted(held.value[task]):
                        for k, c in enumerate(held.value[task][label]):
                            d = every[k] - c if len(c) == every.shape[2] else added(every[k], -np.tile(c, (len(at), 1)))
                            far = np.einsum("ij,ij->i", d, d)
                            less = far < off[k, at]
                            off[k, at[less]], guess[k, at[less]] = far[less], label
                found = [[None if g is None else {"off": o, "guess": g} for o, g in zip(off[:, i].tolist(), guess[:, i], strict=True)] for i in range(len(tasks))]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.list_(pa.struct([("off", pa.float64()), ("guess", pa.string())])))], [*batch.schema.names, "found"])

        part = vectors.select("task", "label", "payload", "vec_id").mapInArrow(run, "task string, label string, payload binary, vec_id long, found array<struct<off: double, guess: string>>")
        out = part if out is None else out.union(part)
    if out is None:
        return vectors.sparkSession.createDataFrame([], "task string, label string, guesses array<string>")
    if groups > 1:  # the nearest of all groups: a row of vectors is in each group as often as it is in vectors
        best = F.array(*[F.min(F.col("found")[k]) for k in range(len(methods) + 1)])
        times = (F.count("*") / groups).cast("int")
        out = out.groupBy("task", "label", "payload", "vec_id").agg(best.alias("found"), times.alias("times")).select("task", "label", F.explode(F.array_repeat("found", F.col("times"))).alias("found"))
    return out.select("task", "label", F.transform("found", lambda x: x["guess"]).alias("guesses"))


def vector_benchmark(vectors: DataFrame, methods=METHODS) -> DataFrame:
    """Nearest-centroid labels of (task, vec_id, label, payload) with original and restored vectors: per task and method percent of changed answers, and accuracy of both.

    Vectors stay where they are read: tasks add them up by label, and centroids, labels by methods, are broadcast in groups of a checked size.
    """
    found = nearest(vectors, cut(centroids(vectors, methods)), methods)
    each = found.select("task", "label", F.col("guesses")[0].alias("before"), F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.col("guesses")[k].alias("guess")) for k, m in enumerate(methods, 1)])).alias("x")).select("task", "label", "before", "x.method", "x.guess")
    share = lambda hit: F.avg(hit.cast("double"))
    return each.groupBy("task", "method").agg((100.0 * share(F.col("guess") != F.col("before"))).alias("ad"), share(F.col("before") == F.col("label")).alias("accuracy_original"), share(F.col("guess") == F.col("label")).alias("accuracy_restored"), F.count("*").alias("n"))


def centroids(vectors: DataFrame, methods, most_keys: int = 4096) -> DataFrame:
    """(task, label, method, c): mean vectors, method 0 the given ones. Tasks add up vectors by label and give a row for each."""

    def run(batches):
        sums: dict[tuple[str, str], list] = {}

        def out():
            keys = [(t, x, k) for t, x in sums for k in range(len(methods) + 1)]
            yield pa.RecordBatch.from_arrays([*[pa.array(list(c)) for c in zip(*keys, strict=True)], pa.array([v for s, _ in sums.values() for v in s], pa.list_(pa.float64())), pa.array([n for _, n in sums.values() for _ in range(len(methods) + 1)], pa.int64())], ["task", "label", "method", "s", "n"])

        for batch in batches:
            keys = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
            every, places = all_methods(batch.column(2).to_pylist(), methods), defaultdict(list)
            for i, key in enumerate(keys):
                places[key].append(i)
            for key, own in places.items():
                total, n = sums.get(key, (np.zeros((len(methods) + 1, 0)), 0))
                sums[key] = (added(total, every[:, own].sum(axis=1)), n + len(own))
            if len(sums) > most_keys:
                yield from out()
                sums.clear()
        if sums:
            yield from out()

    parts = vectors.select("task", "label", "payload").mapInArrow(run, "task string, label string, method long, s array<double>, n long")
    key = ["task", "label", "method"]
    size = parts.groupBy(*key).agg(F.sum("n").alias("n"))
    each = parts.select(*key, F.posexplode("s").alias("i", "x")).groupBy(*key, "i").agg(F.sum("x").alias("x"))
    whole = each.groupBy(*key).agg(F.sort_array(F.collect_list(F.struct("i", "x"))).alias("s"))  # as wide as a vector
    return whole.join(size, key).select(*key, F.transform("s", lambda p: p["x"] / F.col("n")).alias("c"))


def text_vectors(raws: list[bytes], width: int = 64, most_rows: int = 4096, most_bytes: int = 1 << 20) -> np.ndarray:
    """Texts as vectors of unit length: their byte triples, hashed, with signs."""
    out, at = np.zeros((len(raws), width)), 0
    while at < len(raws):
        end, size = at + 1, len(raws[at])
        while end < min(len(raws), at + most_rows) and size + len(raws[end]) <= most_bytes:
            size += len(raws[end])
            end += 1
        lengths = np.fromiter(map(len, raws[at:end]), np.int64, end - at) + 2
        data = np.frombuffer(b"".join(x for raw in raws[at:end] for x in (raw, b"\n\n")), np.uint8)
        which, ends = np.repeat(np.arange(end - at, dtype=np.int32), lengths), np.cumsum(lengths)
        inside = np.ones(len(data), bool)  # a triple begins at each byte of a text
        inside[ends - 1] = inside[ends - 2] = False
        for start in range(0, len(data) - 2, most_bytes):
            part = data[start : start + most_bytes + 2].astype(np.uint64)
            h = (part[:-2] << np.uint64(16) | part[1:-1] << np.uint64(8) | part[2:]) * np.uint64(0x9E3779B97F4A7C15)
            own = slice(start, start + len(h))
            sign = (1.0 - 2.0 * (h >> np.uint64(40) & np.uint64(1))) * inside[own]
            out[at:end] += np.bincount(which[own] * width + (h >> np.uint64(50)).astype(np.int64) % width, sign, minlength=(end - at) * width).reshape(-1, width)
        at = end
    return (out / np.maximum(np.sqrt((out * out).sum(axis=1, keepdims=True)), 1e-12)).astype(np.float32)


def text_features(docs: DataFrame, width: int = 64, most_bytes: int = 4 << 20) -> DataFrame:
    """docs with payload, the vector of its text, in place of text."""
    names = [c for c in docs.columns if c != "text"]

    def run(batches):
        for whole in batches:
            step = max(1, int(whole.num_rows * most_bytes / max(whole.nbytes, 1)))
            for at in range(0, whole.num_rows, step):
                batch = whole.slice(at, step)
                vectors = text_vectors([x or b"" for x in batch.column(batch.num_columns - 1).to_pylist()], width)
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array([x.tobytes() for x in vectors], pa.binary())], [*names, "payload"])

    source = docs.select(*names, F.encode("text", "UTF-8").alias("text"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in source.schema if f.name != "text")
    return source.mapInArrow(run, f"{schema}, payload binary")
