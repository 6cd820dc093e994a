"""Entropic transport against dense matrices, and how often its points are copied."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from gridmin import registry, transport
from gridmin.vectors import concat, from_expr, ops


def made(spark, n, m, dim=3, **kw):
    x, y = (np.random.default_rng(s).random((k, dim)) for s, k in ((1, n), (2, m)))
    frames = [spark.createDataFrame([(i, p.tolist()) for i, p in enumerate(a)], "k long, c array<double>") for a in (x, y)]
    f = transport.Transport.of(*frames, "k", "c", eps=0.3, **kw)
    at = [from_expr(spark, k, lambda r, i, q=q: (i % q) / F.lit(10.0), f.size) for k, q in ((n, 5), (m, 3))]
    c = ((x[:, None] - y[None]) ** 2).sum(2)
    return f, concat([("u", at[0]), ("v", at[1])]).cut(), c, np.exp((np.arange(n)[:, None] % 5 / 10 + np.arange(m) % 3 / 10 - c) / 0.3)


def flat(vec):
    return np.array([r["value"] for r in vec.to_long().orderBy("idx").collect()])


def test_points_are_copied_to_few_strips(spark):
    """Blocks of 4 points; tiles of two blocks held 8 * dim bytes a pair."""
    f = made(spark, 600, 500, part_size=4)[0]
    copies = f.tiles.agg(F.sum(F.size("xs")) / (600 * 3), F.sum(F.size("ys")) / (500 * 3)).first()
    assert max(copies) <= 8


def test_strips_agree_with_the_matrix(spark, monkeypatch):
    monkeypatch.setattr(transport, "CHUNK", 8)
    f, p, c, e = made(spark, 87, 103, part_size=4)
    value, g = f.evaluate(p)
    u, v = np.arange(87) % 5 / 10, np.arange(103) % 3 / 10
    assert abs(value - (-u.mean() - v.mean() + 0.3 * e.mean())) < 1e-12
    assert np.abs(flat(g.segment("u")) - (e.mean(1) - 1) / 87).max() < 1e-12
    assert np.abs(flat(g.segment("v")) - (e.mean(0) - 1) / 103).max() < 1e-12
    (a, s), (b, _) = f.along(p, g).at([0.0, 2.0])
    assert abs(a - value) < 1e-12 and abs(s - ops.dot(g, g)) < 1e-12 and abs(b - f.value(ops.lincomb([1.0, 2.0], [p, g]))) < 1e-12
    top = [r.partner for r in f.plan(p, 3).orderBy("pos", F.desc("mass"), "partner").collect()]
    assert top == np.argsort(-e, 1, kind="stable")[:, :3].reshape(-1).tolist()
    got = f.costs().agg(F.min("lo"), F.max("hi"), F.sum("total"), F.sum("pairs")).first()
    assert np.abs(np.array(got[:3]) - [c.min(), c.max(), c.sum()]).max() < 1e-9 and got[3] == c.size
    a, b = np.zeros(87), np.zeros(103)
    for _ in range(2):
        a = -0.3 * np.log(np.exp((b[None] - c) / 0.3).mean(1))
        b = -0.3 * np.log(np.exp((a[:, None] - c) / 0.3).mean(0))
    s = transport.sinkhorn(f, 2)
    assert np.abs(flat(s.segment("u")) - a).max() < 1e-12 and np.abs(flat(s.segment("v")) - b).max() < 1e-12


def test_large_exponents_keep_their_blocks(spark, monkeypatch):
    """Blocks whose exponents are moderate keep exact sums beside one whose exponents overflow, in the same strip."""
    monkeypatch.setattr(transport, "CHUNK", 8)
    f, p, c, _ = made(spark, 40, 40, part_size=4)
    lifted = ops.keyed_zip(p, p, lambda i, x, y: F.when(i < 4, x + 1000.0).otherwise(x))
    sums = {r["block_id"]: (r["shift"], r["values"]) for r in f._sums(lifted).collect()}
    z = np.exp((np.arange(40)[:, None] % 5 / 10 + np.arange(40) % 3 / 10 - c) / 0.3).sum(1)
    assert sums[0][0] > 600
    for block in range(1, 10):
        assert sums[block][0] == 0.0 and np.abs(np.array(sums[block][1]) - z[4 * block : 4 * block + 4]).max() < 1e-9


@pytest.mark.parametrize("eps, weighted, up", [(0.05, False, 0.0), (0.02, True, 0.0), (0.004, False, 3.0)])
def test_points_on_a_line_do_without_pairs(spark, eps, weighted, up):
    """Sums, value, gradient and line searches from moments of cells against the whole matrix; exponents beyond LARGE in the last case."""
    n, m = 700, 900
    x, y = np.random.default_rng(1).random(n) ** 2, np.random.default_rng(2).random(m)
    frames = [spark.createDataFrame([(i, [float(p)]) for i, p in enumerate(a)], "k long, c array<double>") for a in (x, y)]
    masses = [from_expr(spark, k, lambda r, i, k=k: (i % 3 + 1) / F.lit(2.0 * k), 64) for k in (n, m)] if weighted else [None, None]
    f = transport.Transport.of(*frames, "k", "c", eps=eps, part_size=64, a=masses[0], b=masses[1])
    assert isinstance(f, transport.OnLine)
    at = [from_expr(spark, k, lambda r, i, q=q: (i % q) / F.lit(10.0) + up, 64) for k, q in ((n, 5), (m, 3))]
    p = concat([("u", at[0]), ("v", at[1])]).cut()
    u, v = np.arange(n) % 5 / 10 + up, np.arange(m) % 3 / 10 + up
    a, b = ((np.arange(k) % 3 + 1) / (2.0 * k) if weighted else np.full(k, 1.0 / k) for k in (n, m))
    z = (u[:, None] + v[None] - (x[:, None] - y[None]) ** 2) / eps
    top = z.max() if up else 0.0
    e = np.exp(z - top) * a[:, None] * b[None]
    sums = {r["block_id"]: np.array(r["values"]) * np.exp(r["shift"] - top) for r in f._sums(p).collect()}
    got = np.concatenate([sums[k] for k in sorted(sums)])
    want = np.concatenate([e.sum(1), e.sum(0)]) * (1.0 if weighted else n * m)
    assert np.abs(got / want - 1).max() < 1e-11
    value, g = f.evaluate(p)
    if up:
        assert value == float("inf") or value > 1e250
        return
    assert abs(value / (-a @ u - b @ v + eps * e.sum()) - 1) < 1e-12
    assert np.abs(flat(g.segment("u")) - (e.sum(1) - a)).max() < 1e-12 * e.sum()
    step = eps / ops.norm(g, float("inf"))
    (w, s), (t, _) = f.along(p, g).at([0.0, step])
    assert abs(w / value - 1) < 1e-12 and abs(s / ops.dot(g, g) - 1) < 1e-9
    assert abs(t / f.value(ops.lincomb([1.0, step], [p, g]).cut()) - 1) < 1e-12


def test_the_pairs_are_kept_where_cells_are_many(spark):
    assert type(made(spark, 30, 40, dim=1, part_size=8)[0]) is transport.Transport


@pytest.mark.parametrize("weighted", [False, True])
def test_curvature_agrees_with_the_matrix(spark, monkeypatch, weighted):
    monkeypatch.setattr(transport, "CHUNK", 8)
    masses = [from_expr(spark, k, lambda r, i, k=k: (i % 3 + 1) / F.lit(2.0 * k), 4) for k in (37, 43)] if weighted else [None, None]
    f, x, _, e = made(spark, 37, 43, part_size=4, a=masses[0], b=masses[1])
    a, b = ((np.arange(k) % 3 + 1) / (2.0 * k) if weighted else np.full(k, 1.0 / k) for k in (37, 43))
    plan = e * a[:, None] * b[None]
    m = np.concatenate([plan.sum(1), plan.sum(0)])
    h = f.curvature(x, f.gradient(x))
    scale = np.concatenate([flat(h.scale.segment(k)) for k in "uv"])
    assert np.abs(scale - np.sqrt(0.3 / m)).max() < 1e-9
    got = h.times(x, ops.mul(x, h.scale).cut()).cut()
    p = np.concatenate([flat(x.segment(k)) for k in "uv"])
    want = p + scale * np.concatenate([plan @ (scale * p)[37:], (scale * p)[:37] @ plan]) / 0.3
    assert np.abs(np.concatenate([flat(got.segment(k)) for k in "uv"]) - want).max() < 1e-9


def test_fit_ends_on_the_gradient_where_clusters_exchange_mass(spark, tmp_path):
    """Three clusters with other shares on each side: thirteen quasi-Newton steps from the start end on the count of steps, far off."""
    r = np.random.default_rng(7)
    points = [np.eye(4)[r.choice(3, p=[0.7, 0.2, 0.1] if i % 2 == 0 else [0.2, 0.5, 0.3])] + 0.25 * r.normal(size=4) for i in range(240)]
    pd.DataFrame({"vec_id": range(240), "embedding": [p.astype("float32") for p in points]}).to_parquet(tmp_path / "embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet'")
    want = con.execute(registry.oracles()["ot_fit_trace"]).df().iloc[0].to_dict()
    assert registry.queries()["ot_fit_trace"](spark, str(tmp_path)).first().asDict() == want
