"""Packed runs: what they hold, and that the store's plans over them say what the plans over single values say."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from paramstore.plans import hybrid
from paramstore.queries import pipeline
from paramstore.sources import runs, zoo

DATA = "/root/testdata/sf0.001"
ROWS = ["model_id", "layer_id", "layer_seq", "dtype", "layer_pos"]


def test_squeezed_values_come_back():
    rng = np.random.default_rng(3)
    floats = [rng.standard_normal(500), rng.integers(-(10**7), 10**7, 500) / 100, np.array([0.0, -0.0]), np.array([np.nan, np.inf, 1.5]), np.array([2.0**60, 0.01]), np.zeros(0)]
    for bits in [x.view(np.int64) for x in floats]:
        for rising in (False, True):
            assert (runs.expand(runs.squeeze(bits, "float64", rising), len(bits), "float64", rising) == bits).all()
    for dtype, low, high in (("float16", 0, 1 << 16), ("float32", -(1 << 31), 1 << 31), ("int64", -(1 << 63), (1 << 63) - 1), ("uint8", 0, 256)):
        bits = np.sort(rng.integers(low, high, 300))
        for rising in (False, True):
            assert (runs.expand(runs.squeeze(bits, dtype, rising), 300, dtype, rising) == bits).all()


def small_parts(monkeypatch):
    """Many parts, packs, buckets and cuts; nothing is broadcast."""
    for module, name, value in ((runs, "SPAN", 700), (runs, "HELD", 900), (hybrid, "BUCKET", 1000), (hybrid, "WIDE", 500), (hybrid, "FEW", -1)):
        monkeypatch.setattr(module, name, value)


def test_runs_are_the_values(spark, monkeypatch):
    small_parts(monkeypatch)
    families = (*pipeline.FAMILIES, "part", "supp")
    want = sorted(tuple(r) for r in zoo.params(spark, DATA, families).select(*ROWS, "bits").collect())
    got = sorted((*[r[c] for c in ROWS[:4]], r.layer_pos + i, int(b)) for r in runs.runs(spark, DATA, families).collect() for i, b in enumerate(runs.expand(r.data, r.n, r.dtype)))
    assert got == want


def test_ladder_over_runs_is_the_ladder_over_values(spark, monkeypatch):
    small_parts(monkeypatch)
    p = zoo.params(spark, DATA, pipeline.FAMILIES).cache()
    layers = hybrid.stage_dedup(p)
    routed = hybrid.route(p, layers)
    refs = {r.model_id: r.n for r in layers.groupBy("model_id").agg((256 * F.count_if(F.col("copy") > 1)).alias("n")).collect()}
    arms, last = ({r.model_id: r for r in f.collect()} for f in (hybrid.choose(routed), hybrid.entropy_sizes(routed)))
    got = {(r.model_id, r.stage): r.compressed for r in hybrid.ablation(runs.runs(spark, DATA, pipeline.FAMILIES), with_entropy=True).collect()}
    assert len(got) == 5 * len(refs)
    for model, n in refs.items():
        arm = arms.get(model)
        sizes = (0, 0, 0) if arm is None else (arm.de or arm.original, arm.unit or arm.original, arm.compressed)
        assert tuple(got[model, s] for s in ("2_dedup_de", "3_dedup_unit", "4_dedup_both")) == tuple(n + x for x in sizes)
        assert got[model, "5_all_zstd"] == n + (last[model].compressed if model in last else 0)


def disk(spark) -> int:
    """Bytes of shuffle files and of the shared folder."""
    local = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    return sum(os.path.getsize(f"{at}/{f}") for top in (*local, spark.conf.get("spark.checkpoint.dir")) for at, _, files in os.walk(top) for f in files)


def test_comparison_counts_what_is_wrong(spark, monkeypatch):
    """Missing and changed values, values given back twice or never put in, and errors of floats, across cuts."""
    monkeypatch.setattr(hybrid, "WIDE", 7)
    whole, floats = np.arange(40), np.linspace(-0.9, 3.0, 40).view(np.int64)
    piece = lambda bits, dtype, a, b: (dtype, dtype, a, b - a, runs.squeeze(bits[a:b], dtype))
    frame = lambda rows: spark.createDataFrame(rows, "layer_id string, dtype string, layer_pos long, n long, data binary")
    changed, off = whole.copy(), floats.copy()
    changed[[3, 30]] += 1
    off[5], off[39] = np.array([floats[5:6].view(float)[0] + 0.25, 9.0]).view(np.int64)
    values = frame([piece(whole, "int64", 0, 25), piece(whole, "int64", 25, 40), piece(floats, "float64", 0, 40)])
    back = frame([piece(changed, "int64", 0, 36), piece(changed, "int64", 10, 12), piece(off, "float64", 0, 40)])
    got = {r.dtype: r for r in hybrid.compared(values, back).collect()}
    assert (got["int64"].params, got["int64"].missing, got["int64"].others_differ, got["int64"].max_error) == (40, 4, 4, None)
    assert (got["float64"].params, got["float64"].missing, got["float64"].others_differ) == (40, 0, 1) and got["float64"].max_error == pytest.approx(0.25)


def test_store_gives_everything_back_without_broadcasts(spark, monkeypatch):
    small_parts(monkeypatch)
    found = hybrid.within_bound(hybrid.verify_runs(runs.runs(spark, DATA, pipeline.FAMILIES))).collect()
    counts = {r.dtype: r["count"] for r in zoo.params(spark, DATA, pipeline.FAMILIES).groupBy("dtype").count().collect()}
    assert {r.dtype: r.params for r in found} == counts and all(not r.missing and not r.others_differ and r.within_bound for r in found)


@pytest.mark.parametrize(("name", "size"), [("ablation_full", 3_604_000), ("hybrid_roundtrip", 6_902_405)])
def test_no_row_a_value_is_written(spark, name, size):
    """A row a value took some hundred bytes a value."""
    before = disk(spark)
    getattr(pipeline, name)(spark, "/root/testdata/sf0.01").collect()
    assert disk(spark) - before < 2 * size  # bytes of the values themselves
