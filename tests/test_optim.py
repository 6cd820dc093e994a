"""Objectives by finite differences, minimisers against closed forms."""

import numpy as np
import pytest

from gridmin import grid, losses, optim
from gridmin.objective import Batched, Linear, Machines, Penalised, Quadratic
from gridmin.vectors import from_long, uniform

N, D = 40, 5
RNG = np.random.default_rng(0)
X = RNG.normal(size=(N, D)) * (RNG.random((N, D)) < 0.7)
W = np.array([1, -2, 0.5, 0, 3.0])
Y = X @ W


def vec(spark, a, block=2):
    return from_long(spark.createDataFrame([(i, float(x)) for i, x in enumerate(a)], "idx long, value double"), len(a), block)


def back(v):
    return np.array([r["value"] for r in v.to_long().orderBy("idx").collect()])


@pytest.fixture(scope="module")
def data(spark):
    feats = spark.createDataFrame([(i, j, float(X[i, j])) for i in range(N) for j in range(D) if X[i, j]], "example_id long, feature_id long, value double")
    labels = spark.createDataFrame([(i, float(Y[i])) for i in range(N)], "example_id long, label double")
    return grid.build_cells(feats, 3, 2).persist(), labels, feats


def test_value_and_gradient(spark, data):
    f, w = Linear(data[0], data[1], losses.Squared(), 3), np.full(D, 0.1)
    v, g = f.evaluate(vec(spark, w))
    assert np.isclose(v, ((X @ w - Y) ** 2).mean())
    assert np.allclose(back(g), 2 * X.T @ (X @ w - Y) / N)
    for s in ("replicate", "gather", "broadcast"):
        f.strategy = s
        assert np.isclose(f.value(vec(spark, w)), v)


def test_machine_gradient_and_line(spark, data):
    f, x, d = Machines(data[0], data[1], losses.Squared(), 3), uniform(spark, D, 1, -0.5, 0.5, 2, 2), uniform(spark, D, 2, -0.5, 0.5, 2, 2)
    flat = lambda v: np.array([r["value"] for r in v.to_long().orderBy("row", "idx").collect()])

    def value(z):
        m = z.reshape(2, D)
        return ((0.5 * ((X @ m.T) ** 2 - (X**2) @ (m**2).T).sum(1) - Y) ** 2).mean()

    v, g = f.evaluate(x)
    z, dz = flat(x), flat(d)
    assert np.isclose(v, value(z))
    assert np.allclose(flat(g), [(value(z + 1e-6 * e) - value(z - 1e-6 * e)) / 2e-6 for e in np.eye(2 * D)], atol=1e-6)
    assert np.isclose(f.along(x, d).at([0.5])[0][0], value(z + 0.5 * dz))


def test_quasi_newton_finds_the_planted_weights(spark, data):
    r = optim.LimitedMemory(stop=[optim.GradNorm(1e-7), optim.MaxIter(15)]).run(Linear(data[0], data[1], losses.Squared(), 3), vec(spark, np.zeros(D)))
    assert r.reason == optim.Reason.GRADIENT
    assert np.allclose(back(r.x), W, atol=1e-5)


def test_adaptive_step_by_hand(spark):
    f = Quadratic(vec(spark, [1, 10]), vec(spark, [1, 2]))
    r = optim.AdaptiveGradient(0.5, 1e-8, l1=0.1, l2=0.2, stop=[optim.MaxIter(1)]).run(f, vec(spark, [0, 0]))
    g = np.array([-1.0, -2.0])
    s = np.sqrt(g * g + 1e-8)
    z = -0.5 * g / (s + 0.1)
    assert np.allclose(back(r.x), np.sign(z) * np.maximum(np.abs(z) - 0.05 / s, 0))
    with pytest.raises(ValueError):
        optim.AdaptiveGradient(delta=0.0)


def test_penalty_and_batches(spark):
    f = Quadratic(vec(spark, [1, 10]), vec(spark, [1, 2]))
    p = Penalised(f, 0.5, 0.2)
    assert np.isclose(p.penalty(vec(spark, [1, -2])), 0.5 * 3 + 0.1 * 5)
    with pytest.raises(ValueError):
        Batched([])
    with pytest.raises(ValueError):
        Batched([f], "other")


def test_labels_are_checked(spark, data):
    bad = spark.createDataFrame([(0, None)], "example_id long, label double")
    with pytest.raises(Exception, match="null label"):
        Linear(data[0], bad, losses.Squared(), 3).value(vec(spark, np.zeros(D)))
    zero = data[1].selectExpr("example_id", "label", "0D as weight")
    with pytest.raises(ValueError, match="sum to zero"):
        Linear(data[0], zero, losses.Squared(), 3).value(vec(spark, np.zeros(D)))


def test_features_are_checked(spark):
    odd = spark.createDataFrame([(0, 9, 1.0), (0, 1, None), (0, 1, 2.0), (0, 1, 3.0)], "example_id long, feature_id long, value double")
    with pytest.raises(Exception, match="feature"):
        grid.clean_features(odd, 5).count()
    assert grid.clean_features(odd, 5, "drop", "drop").collect()[0]["value"] == 5.0


def test_strategy_is_the_cheapest():
    s = grid.Stats(10**9, 1, 100, 100, 26 * 10**8, 3 * 10**9, 400)
    assert grid.choose(s) == min(grid.costs(s), key=grid.costs(s).get)
    assert grid.choose(grid.Stats(100, 1, 100, 1, 10**6, 10**6, 4)) == "broadcast"


def test_one_batch_is_cached_at_a_time(spark, data):
    """Batches given as loaders: values as with all in memory, and no more than the current and the coming one loaded."""
    alive, freed = [], []

    class Watched(Linear):
        def free(self):
            freed.append(self.number)
            alive.remove(self.number)

    def load(k):
        f = Watched(data[0], data[1].where(f"example_id % 3 = {k}"), losses.Squared(), 3, "broadcast")
        f.number = k
        alive.append(k)
        assert len(alive) <= 3  # the one before is freed right after
        return f

    plain = [Linear(data[0], data[1].where(f"example_id % 3 = {k}"), losses.Squared(), 3, "broadcast") for k in range(3)]
    x, lazy, eager = vec(spark, np.full(D, 0.2)), Batched([lambda k=k: load(k) for k in range(3)], prefetch=True), Batched(plain)
    for _ in range(4):
        assert np.isclose(lazy.value(x), eager.value(x))
    assert lazy.log == eager.log and freed[:3] == [0, 1, 2]
    lazy.free()
    assert not alive


def test_machine_with_linear_weights_and_bias(spark, data):
    """Value, gradient and line by finite differences; the bias feature's latent weights get no gradient."""
    feats = data[2].unionByName(data[1].selectExpr("example_id", "5L as feature_id", "1D as value"))
    f = Machines(grid.build_cells(feats, 3, 2).persist(), data[1], losses.Squared(), 3, "stationary", linear=True, bias=5)
    flat = lambda v: np.array([r["value"] for r in v.to_long().orderBy("row", "idx").collect()])
    z = RNG.normal(size=(3, 6)) * 0.3
    z[:2, 5] = 0.0
    x = from_long(spark.createDataFrame([(r, i, float(z[r, i])) for r in range(3) for i in range(6)], "row int, idx long, value double"), 6, 2, stack=3)

    def value(m):
        one = np.concatenate([X, np.ones((N, 1))], 1)
        pairs = 0.5 * ((X @ m[:2, :5].T) ** 2 - (X**2) @ (m[:2, :5] ** 2).T).sum(1)
        return ((pairs + one @ m[2] - Y) ** 2).mean()

    v, g = f.evaluate(x)
    assert np.isclose(v, value(z))
    got = flat(g).reshape(3, 6)
    assert (got[:2, 5] == 0).all()
    for r, i in [(0, 0), (1, 3), (2, 2), (2, 5)]:
        up, down = z.copy(), z.copy()
        up[r, i] += 1e-5
        down[r, i] -= 1e-5
        assert np.isclose(got[r, i], (value(up) - value(down)) / 2e-5, rtol=1e-4, atol=1e-7)
    line = f.along(x, g)
    (a, s), (b, _) = line.at([0.0, -0.1])
    assert np.isclose(a, v) and np.isclose(s, (got**2).sum()) and np.isclose(b, value(z - 0.1 * got))
    line.free()
