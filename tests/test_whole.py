"""Examples laid out whole against the grid of cells, and how many jobs a step takes."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridmin import grid, losses, optim, whole, workloads
from gridmin.objective import Linear
from gridmin.vectors import from_expr

N, D, JOBS = 60, 7, 40


@pytest.fixture(scope="module")
def data(spark):
    """Examples with 0 to 3 features of 7, in cells of blocks of 3; every fifth example has none."""
    feats = spark.range(N).where("id % 5 > 0").select(F.col("id").alias("example_id"), F.explode(F.sequence(F.lit(1), F.col("id") % 3 + 1)).alias("j"))
    feats = feats.select("example_id", ((F.col("example_id") * 5 + F.col("j") * 3) % D).alias("feature_id"), (F.col("j") / 2.0 - 0.7).alias("value"))
    labels = spark.range(N).select(F.col("id").alias("example_id"), (F.col("id") % 2).cast("double").alias("label"), (F.col("id") % 4 + 0.5).alias("weight"))
    return grid.build_cells(feats, 3, 3).persist(), labels


def flat(v):
    return np.array([r["value"] for r in v.to_long().orderBy(*v.to_long().columns[:-1]).collect()])


@pytest.mark.parametrize("loss", [losses.Squared(), losses.Squared(True), losses.Quantile(0.3), losses.Logistic(), losses.Softmax(3)], ids=str)
def test_whole_rows_agree_with_cells(spark, data, loss, monkeypatch):
    monkeypatch.setattr(whole, "FEW", 8)
    f, g = Linear(*data, loss, 3), Linear(*data, loss, 3, "broadcast")
    x, d = (from_expr(spark, D, lambda r, i, q=q: ((i + r * 2) % q - 1) / F.lit(4.0), 3, loss.k).cut() for q in (3, 4))
    (a, u), (b, v) = f.evaluate(x), g.evaluate(x)
    assert f.rows_for(x) is not None and g.rows_for(x) is None
    assert f.rows_for(x).rows.count() > 1
    assert np.isclose(a, b, rtol=1e-12) and np.allclose(flat(u), flat(v), rtol=1e-12, atol=1e-15)
    assert np.isclose(f.value(x), b, rtol=1e-12)
    assert np.allclose(f.along(x, d).at([0.0, 0.7]), g.along(x, d).at([0.0, 0.7]), rtol=1e-12)
    u.unpersist()
    f.free()


def test_large_models_stay_on_the_grid(spark, data, monkeypatch):
    monkeypatch.setattr(whole, "SMALL", 8 * D - 1)
    monkeypatch.setattr("gridmin.objective.SMALL", 8 * D - 1)
    assert Linear(*data, losses.Squared(), 3).rows_for(from_expr(spark, D, lambda r, i: i * 1.0, 3)) is None


def test_adaptive_steps_take_few_jobs(spark, data):
    """34 for a start and three steps; 80 with scores and labels joined, and each vector written and measured by itself."""
    f, x = Linear(*data, losses.Squared(), 3), from_expr(spark, D, lambda r, i: i * 0.1, 3)
    f.evaluate(x)
    spark.sparkContext.setJobGroup("steps", "steps")
    log = optim.AdaptiveGradient(0.1, stop=[optim.MaxIter(3)]).run(f, x).log
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("steps"))
    spark.sparkContext.setJobGroup("other", "other")
    assert len(log) == 4 and jobs <= JOBS


def test_planted_labels_follow_the_hashes(spark, tmp_path):
    """Labels of a few events from md5 prefixes alone."""
    spark.range(40).withColumnRenamed("id", "event_id").write.parquet(f"{tmp_path}/events.parquet")
    w = workloads.w2_planted(spark, str(tmp_path), d=11, nnz=4, k=3, batches=1)
    h = lambda *p: int(hashlib.md5(":".join(map(str, p)).encode()).hexdigest()[:8], 16)
    want = {}
    for e in range(40):
        s = np.zeros(3)
        for j in range(4):
            at, value = (h("base", e) % 11 + (h("stride", e) % 10 + 1) * j) % 11, ((e * 7919 + j * 104729) % 2001 - 1000) / 1000
            s += value * np.array([h("w", c, at) / 2**31 - 1 for c in range(3)])
        p = np.exp(s) / np.exp(s).sum()
        want[e] = sum(h("u", e) / 2**32 >= p[:c].sum() for c in (1, 2))
    assert {r["example_id"]: int(r["label"]) for r in w.data["labels"].collect()} == want
    assert w.objective.rows_for(w.x0) is not None


def test_planted_examples_agree_with_the_grid(spark, tmp_path):
    """Value, gradient and line from packed examples and from cells of the long features; one event comes twice, which doubles its features."""
    spark.range(40).union(spark.range(7, 8)).withColumnRenamed("id", "event_id").write.parquet(f"{tmp_path}/events.parquet")
    w = workloads.w2_planted(spark, str(tmp_path), d=11, nnz=4, k=3, batches=1)
    feats = workloads.planted_features(spark.read.parquet(f"{tmp_path}/events.parquet").withColumnRenamed("event_id", "example_id"), 4, 11)
    f, g = w.objective, Linear(grid.build_cells(feats, 2, 1024).persist(), w.data["labels"], losses.Softmax(3), 2, "broadcast")
    x, d = (from_expr(spark, 11, lambda r, i, q=q: ((i + r * 2) % q - 1) / F.lit(4.0), 1024, 3).cut() for q in (3, 4))
    (a, u), (b, v) = f.evaluate(x), g.evaluate(x)
    assert f.rows_for(x) is not None and g.rows_for(x) is None
    assert np.isclose(a, b, rtol=1e-12) and np.allclose(flat(u), flat(v), rtol=1e-12, atol=1e-15)
    assert np.allclose(f.along(x, d).at([0.0, 0.7]), g.along(x, d).at([0.0, 0.7]), rtol=1e-12)
    law = {r["example_id"]: r["p"] for r in w.data["law"].collect()}
    assert len(law) == 40 and all(abs(sum(p) - 1) < 1e-12 for p in law.values())


def test_packed_examples_are_small(spark, tmp_path):
    """Under 6 bytes a non-zero, labels and all; 12 and more before, after a shuffle of 24 for each."""
    spark.range(3000).withColumnRenamed("id", "event_id").write.parquet(f"{tmp_path}/events.parquet")
    w = workloads.w2_planted(spark, str(tmp_path), d=503, nnz=50, k=3, batches=1)
    rows = w.objective.rows_for(w.x0).rows
    size = sum(F.coalesce(F.length(name), F.lit(0)) for name, kind in rows.dtypes if kind == "binary")
    assert rows.agg(F.sum(size)).first()[0] < 6 * 3000 * 50


def test_rows_hold_any_values_and_examples(spark):
    """Values that all differ, features far apart, repeated labels, and work in chunks."""
    rng = np.random.default_rng(1)
    ids, vals, at = rng.integers(0, 10**6, 500), rng.normal(size=500), rng.integers(0, 30, 500)
    ids[:50] = 10**6 - 1
    row = whole._group(np.arange(30), np.zeros(0, np.int64), at, ids, vals, lambda _: (np.zeros(30), np.ones(30)))
    w, d, g, old = rng.normal(size=(2, 10**6)), rng.normal(size=(2, 30)), np.zeros((2, 10**6)), whole.CHUNK
    whole.CHUNK = 64
    try:
        s = whole._scores(w, 30, whole._entries(row, 0))
        whole._add_transposed(g, d, whole._entries(row, 0))
    finally:
        whole.CHUNK = old
    assert np.allclose(s, [np.bincount(at, w[j][ids] * vals, 30) for j in range(2)], rtol=1e-12)
    assert np.allclose(g, [np.bincount(ids, d[j][at] * vals, 10**6) for j in range(2)], rtol=1e-12)


def test_batches_come_back_in_few_jobs(spark, tmp_path):
    """A batch that was written is read, not laid out again: 3 jobs."""
    spark.range(200).withColumnRenamed("id", "event_id").write.parquet(f"{tmp_path}/events.parquet")
    w = workloads.w2_planted(spark, str(tmp_path), d=11, nnz=4, k=3, batches=2)
    f = w.objective
    f.loader = None
    for b in (0, 1):
        f.batch(b)
    spark.sparkContext.setJobGroup("again", "again")
    again = f.batch(0)
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("again"))
    spark.sparkContext.setJobGroup("other", "other")
    assert jobs <= 3 and abs(again.value(w.x0) - np.log(3)) < 1e-12
    f.free()
