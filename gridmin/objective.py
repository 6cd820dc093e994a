"""Differentiable functions of a distributed vector: value, gradient, both at once, and the restriction to a line."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import Future, ThreadPoolExecutor
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmin import grid, losses
from gridmin.whole import SMALL, WholeLine, WholeRows
from gridmin.vectors import ops
from gridmin.vectors.vec import Vec


class Line:
    """phi(eta) = f(x + eta d). ``at`` gives [(phi, slope)] for a ladder of steps from one scan; ``free`` drops its cache."""

    def at(self, etas: list[float]) -> list[tuple[float, float]]:
        raise NotImplementedError

    def free(self) -> None:
        pass


class Objective:
    """Subclasses give ``evaluate`` and may give cheaper ``value`` and ``along``, and ``curvature`` and ``balanced``."""

    balancing = 0  # passes over the data that ``balanced`` takes; 0: there is none

    def evaluate(self, x: Vec) -> tuple[float, Vec]:
        raise NotImplementedError

    def value(self, x: Vec) -> float:
        return self.evaluate(x)[0]

    def gradient(self, x: Vec) -> Vec:
        return self.evaluate(x)[1]

    def along(self, x: Vec, d: Vec) -> Line:
        return PlainLine(self, x, d)

    def curvature(self, x: Vec, g: Vec):
        """The second derivative at a point with gradient g, scaled on both sides by ``scale``, its diagonal to the power -1/2:
        ``times(p, scale * p)`` and ``free()``."""
        raise NotImplementedError

    def balanced(self, x: Vec) -> Vec:
        """A point that minimises over one group of variables after another, starting from x."""
        return x

    def free(self) -> None:
        """Let go of what is cached."""

    def hold(self) -> None:
        """Keep the batch for the next evaluations; plain objectives have one batch."""

    def release(self) -> None:
        pass

    @contextmanager
    def held(self):
        self.hold()
        try:
            yield self
        finally:
            self.release()


class PlainLine(Line):
    """Any objective along a line, by full evaluations."""

    def __init__(self, f: Objective, x: Vec, d: Vec):
        self.f, self.x, self.d = f, x, d

    def at(self, etas):
        out = []
        for eta in etas:
            v, g = self.f.evaluate(ops.lincomb([1.0, eta], [self.x, self.d]))
            out.append((v, ops.dot(g, self.d)))
        return out


class ScoreLine(Line):
    """Losses whose scores are polynomials in eta: score = c0 + eta c1 + eta^2 c2, kept a row an example."""

    def __init__(self, rows: DataFrame, loss: losses.Loss, degree: int):
        self.rows, self.loss, self.degree = rows.persist(), loss, degree

    def at(self, etas):
        aggs = []
        for i, eta in enumerate(etas):
            if self.loss.k == 1:
                s, ds = F.col("c0") + eta * F.col("c1"), F.col("c1")
                if self.degree == 2:
                    s, ds = s + eta * eta * F.col("c2"), ds + 2 * eta * F.col("c2")
                slope = self.loss.derivative(s, F.col("label")) * ds
            else:
                s = F.zip_with("c0", "c1", _plus(float(eta)))
                slope = F.aggregate(F.zip_with(self.loss.derivative(s, F.col("label")), F.col("c1"), lambda a, b: a * b), F.lit(0.0), lambda acc, z: acc + z)
            aggs += [F.sum(F.col("weight") * self.loss.value(s, F.col("label"))).alias(f"v{i}"), F.sum(F.col("weight") * slope).alias(f"d{i}")]
        r = self.rows.agg(F.sum("weight").alias("w"), *aggs).first()
        return [(_number(r[f"v{i}"]) / r["w"], _number(r[f"d{i}"]) / r["w"]) for i in range(len(etas))]

    def free(self):
        self.rows.unpersist()


def _plus(eta: float):
    return lambda a, b: a + F.lit(eta) * b


def _number(x) -> float:
    return float("nan") if x is None else float(x)


def check_labels(labels: DataFrame, on_null: str = "error") -> DataFrame:
    """(example_id, label, weight): weight 1 if absent; null labels raise or go; negative weights raise."""
    df = labels if "weight" in labels.columns else labels.withColumn("weight", F.lit(1.0))
    bad = F.col("label").isNull() | F.col("weight").isNull()
    df = df.where(~bad) if on_null == "drop" else df.withColumn("weight", F.when(bad, F.raise_error(F.lit("null label or weight"))).otherwise(F.col("weight")))
    return df.select("example_id", "label", F.when(F.col("weight") < 0, F.raise_error(F.lit("negative weight"))).otherwise(F.col("weight").cast("double")).alias("weight"))


class _OnGrid(Objective):
    """What objectives over cells share."""

    grid: grid.CellGrid

    @property
    def cells(self) -> DataFrame:
        return self.grid.cells

    @property
    def ex_parts(self) -> int:
        return self.grid.ex_parts

    @property
    def strategy(self) -> str | None:
        return self.grid.strategy

    @strategy.setter
    def strategy(self, name: str | None) -> None:
        self.grid.strategy = name

    def free(self) -> None:
        """Unpersist the cells and what was laid out from them."""
        self.grid.free()


class Linear(_OnGrid):
    """Weighted mean loss of linear scores over the grid; k score rows for several classes. Unless a strategy is named, small models are
    evaluated over examples laid out whole (``whole=False``: never), so that nothing but weights and gradients moves. ``packed``: the
    same examples and labels as ``whole.pack`` gives them, where they come so; cells are then made only if a strategy asks for them."""

    def __init__(self, cells: DataFrame, labels: DataFrame, loss: losses.Loss, ex_parts: int, strategy: str | None = None, on_null: str = "error", whole: bool = True, packed: DataFrame | None = None):
        self.grid, self.labels, self.loss = grid.CellGrid(cells, ex_parts, strategy), check_labels(labels, on_null), loss
        self.whole, self.packed, self._rows = whole, packed, {}

    def rows_for(self, x: Vec) -> WholeRows | None:
        """The examples laid out whole, once; None where they are not to be used."""
        if not self.whole or self.strategy is not None or not self.loss.arrays or 8 * x.length * x.stack > SMALL or x.stack != self.loss.k:
            return None
        if x.block_size not in self._rows:
            size = x.block_size
            self._rows[size] = WholeRows.of_cells(self.cells, self.labels, self.loss, size) if self.packed is None else WholeRows(self.packed, self.loss, size)
        return self._rows[x.block_size]

    def ready(self, x: Vec) -> None:
        """Lay out what evaluations at points like ``x`` need."""
        if self.rows_for(x) is None:
            self.cells.count()

    def free(self) -> None:
        super().free()
        for rows in self._rows.values():
            rows.rows.unpersist()
        self._rows = {}

    def scores(self, w: Vec) -> DataFrame:
        """(example_id, s array of k): examples without features are absent."""
        return grid.sum_arrays(grid.multiply(self.grid.attach(w), _score_kernel(w.stack), w.stack), "example_id", "s", w.stack)

    def _labelled(self, w: Vec, name: str = "s") -> DataFrame:
        none = F.array_repeat(F.lit(0.0), w.stack)
        df = self.labels.join(self.scores(w), "example_id", "left").withColumn("s", F.coalesce("s", none))
        return df.withColumn(name, F.col("s")[0] if w.stack == 1 else F.col("s"))

    def value(self, x):
        if whole := self.rows_for(x):
            return whole.value(x)
        r = self._labelled(x).agg(F.sum(F.col("weight") * self.loss.value(F.col("s"), F.col("label"))).alias("v"), F.sum("weight").alias("w")).first()
        return _mean(r)

    def evaluate(self, x):
        if whole := self.rows_for(x):
            return whole.evaluate(x)
        rows = self._labelled(x)
        d = self.loss.derivative(F.col("s"), F.col("label"))
        d = F.array(F.col("weight") * d) if x.stack == 1 else F.transform(d, lambda z: F.col("weight") * z)
        rows = rows.select("example_id", "weight", (F.col("weight") * self.loss.value(F.col("s"), F.col("label"))).alias("l"), d.alias("d")).persist()
        r = rows.agg(F.sum("l").alias("v"), F.sum("weight").alias("w")).first()
        value, total = _mean(r), r["w"]
        summed = self.grid.back(rows.select("example_id", "d"), x.stack, grid.transposed, x, x.stack)
        g = ops.apply(grid.full(summed, x), lambda z: z / F.lit(total)).cut()
        rows.unpersist()
        return value, g

    def along(self, x, d):
        if whole := self.rows_for(x):
            return WholeLine(whole, x, d)
        rows = self._labelled(x).select("example_id", "label", "weight", F.col("s").alias("c0"))
        other = self.scores(d).withColumnRenamed("s", "c1")
        none = F.array_repeat(F.lit(0.0), x.stack)
        joined = rows.join(other, "example_id", "left").withColumn("c1", F.coalesce("c1", none))
        if x.stack == 1:
            joined = joined.withColumn("c1", F.col("c1")[0])
        return ScoreLine(joined, self.loss, 1)


def _score_kernel(k: int):
    def kernel(ptr, ids, vals, w):
        m = w.reshape(k, -1)
        return grid.rows_sum(ptr, vals[:, None] * m[:, ids].T)

    return kernel


def _mean(r) -> float:
    if not r["w"]:
        raise ValueError("the weights sum to zero")
    return _number(r["v"]) / r["w"]


class Machines(_OnGrid):
    """Factorization machines of rank k over the grid, in time linear in the non-zeros.

    With ``linear`` the last row of the stack holds linear weights, and the rows before it the k latent ones. ``bias`` names a
    feature that every example has with value 1: its linear weight is the intercept, its latent weights get no gradient
    and stay as they start (zero, so that it takes no part in the pairs).
    """

    def __init__(self, cells: DataFrame, labels: DataFrame, loss: losses.Loss, ex_parts: int, strategy: str | None = None, ordered_pairs: bool = False, linear: bool = False, bias: int | None = None):
        self.grid, self.labels, self.loss = grid.CellGrid(cells, ex_parts, strategy), check_labels(labels), loss
        self.factor, self.linear, self.bias = (1.0 if ordered_pairs else 0.5), linear, bias

    def rank(self, x: Vec) -> int:
        return x.stack - self.linear

    def sums(self, x: Vec) -> DataFrame:
        """(example_id, s): the k sums of f x, then the k sums of (f x)^2, then the linear sum, if there is one."""
        k, rows = self.rank(x), x.stack

        def kernel(ptr, ids, vals, w):
            fx = vals[:, None] * w.reshape(rows, -1)[:, ids].T
            return np.concatenate([grid.rows_sum(ptr, fx[:, :k]), grid.rows_sum(ptr, fx[:, :k] ** 2), grid.rows_sum(ptr, fx[:, k:])], 1)

        return grid.sum_arrays(grid.multiply(self.grid.attach(x), kernel, k + rows), "example_id", "s", k + rows)

    def score_of(self, s, k: int):
        pair = F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(0.0), lambda acc, r: acc + s[r] * s[r] - s[r + k])
        return self.factor * pair + (s[2 * k] if self.linear else 0.0)

    def scores(self, x: Vec) -> DataFrame:
        """(example_id, score, v): v holds the k linear sums that the backward pass needs again."""
        return self.sums(x).select("example_id", self.score_of(F.col("s"), self.rank(x)).alias("score"), F.slice("s", 1, self.rank(x)).alias("v"))

    def _rows(self, x: Vec) -> DataFrame:
        scored = self.scores(x)
        none = F.array_repeat(F.lit(0.0), self.rank(x))
        df = self.labels.join(scored, "example_id", "left").withColumns({"score": F.coalesce("score", F.lit(0.0)), "v": F.coalesce("v", none)})
        w, y, s = F.col("weight"), F.col("label"), F.col("score")
        return df.select("example_id", "weight", "v", (w * self.loss.value(s, y)).alias("l"), (w * self.loss.derivative(s, y)).alias("ds"))

    def evaluate(self, x):
        rows = self._rows(x).persist()
        r = rows.agg(F.sum("l").alias("v"), F.sum("weight").alias("w")).first()
        value = _mean(r)
        g = self.pull_back(x, rows.select("example_id", "v", "ds"), r["w"]).cut()
        rows.unpersist()
        return value, g

    def pull_back(self, x: Vec, rows: DataFrame, total: float) -> Vec:
        """Gradient from (example_id, v, ds): sum of ds f (v - f x), and of ds f for linear weights, over total."""
        k, linear = self.rank(x), self.linear
        d = rows.select("example_id", F.concat(F.transform("v", lambda z: z * F.col("ds")), F.array("ds")).alias("d"))

        def kernel(entry, ids, vals, mine, size):
            first = [np.bincount(ids, weights=vals * mine[entry, j], minlength=size) for j in range(k)]
            last = [np.bincount(ids, weights=vals * mine[entry, k], minlength=size)] if linear else []
            return np.stack([*first, np.bincount(ids, weights=vals * vals * mine[entry, k], minlength=size), *last])

        rows = k + 1 + linear
        summed = grid.full(self.grid.back(d, k + 1, kernel, x, rows), x, rows)
        scale = 2 * self.factor / total
        both = x.df.withColumnRenamed("values", "w").join(summed.df.withColumnRenamed("values", "b"), "block_id")
        width = (F.size("b") / rows).cast("int")
        pair = lambda p: (F.col("b")[p] - F.col("w")[p] * F.col("b")[width * k + p % width]) * F.lit(scale)
        if self.bias is not None:
            free = lambda p: F.col("block_id").cast("long") * x.block_size + p % width != self.bias
            got = F.transform(F.sequence(F.lit(0), width * k - 1), lambda p: F.when(free(p), pair(p)).otherwise(F.lit(0.0)))
        else:
            got = F.transform(F.sequence(F.lit(0), width * k - 1), pair)
        if linear:
            got = F.concat(got, F.transform(F.slice("b", width * (k + 1) + 1, width), lambda z: z / F.lit(float(total))))
        return x.with_df(both.select("block_id", got.alias("values")))

    def along(self, x, d):
        k, rows = self.rank(x), x.stack

        def kernel(ptr, ids, vals, w, v):
            both = [vals[:, None] * m.reshape(rows, -1)[:, ids].T for m in (w, v)]
            a, b = (m[:, :k] for m in both)
            first = [m[:, k:].sum(1, keepdims=True) for m in both]  # linear parts, zero without linear weights
            return np.concatenate([grid.rows_sum(ptr, z) for z in (a, b, (a * a).sum(1, keepdims=True), (a * b).sum(1, keepdims=True), (b * b).sum(1, keepdims=True), *first)], 1)

        attached = self.grid.attach(d, "v", to=self.grid.attach(x))
        n = 2 * k + 5
        s = grid.sum_arrays(grid.multiply(attached, kernel, n, ("w", "v")), "example_id", "s", n)
        dots = lambda p, q: F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(0.0), lambda acc, r: acc + F.col("s")[r + p] * F.col("s")[r + q])
        h = self.factor
        c = s.select("example_id", (h * (dots(0, 0) - F.col("s")[2 * k]) + F.col("s")[2 * k + 3]).alias("c0"), (2 * h * (dots(0, k) - F.col("s")[2 * k + 1]) + F.col("s")[2 * k + 4]).alias("c1"), (h * (dots(k, k) - F.col("s")[2 * k + 2])).alias("c2"))
        return ScoreLine(self.labels.join(c, "example_id", "left").na.fill(0.0, ["c0", "c1", "c2"]), self.loss, 2)


class Quadratic(Objective):
    """sum of curvature_i x_i^2 / 2 - b_i x_i: a test function with a known minimum."""

    def __init__(self, curvature: Vec, b: Vec):
        self.curvature, self.b = curvature, b

    def evaluate(self, x):
        g = ops.numpy_map([self.curvature, x, self.b], lambda a, z, b: a * z - b).cut()
        m = ops.gram([g, x, self.b])
        return float(0.5 * (m[0, 1] - m[1, 2])), g

    def along(self, x, d):
        bend = ops.numpy_map([self.curvature, x], lambda a, z: a * z), ops.numpy_map([self.curvature, d], lambda a, z: a * z)
        m = ops.gram([x, d, *bend, self.b])

        class Parabola(Line):
            def at(self, etas):
                return [(float(m[0, 2] / 2 + e * m[0, 3] + e * e * m[1, 3] / 2 - m[0, 4] - e * m[1, 4]), float(m[0, 3] + e * m[1, 3] - m[1, 4])) for e in etas]

        return Parabola()


class Penalised(Objective):
    """base + l1 |x| + l2 / 2 x^2. The gradient has the l2 part only; ``mask`` (0/1 Vec) exempts components."""

    def __init__(self, base: Objective, l1: float = 0.0, l2: float = 0.0, mask: Vec | None = None):
        self.base, self.l1, self.l2, self.mask = base, l1, l2, mask

    def _part(self, x: Vec) -> Vec:
        return ops.mul(x, self.mask) if self.mask else x

    def penalty(self, x: Vec) -> float:
        p = self._part(x)
        return (self.l1 * ops.norm(p, 1) if self.l1 else 0.0) + (0.5 * self.l2 * ops.dot(p, p) if self.l2 else 0.0)

    def value(self, x):
        return self.base.value(x) + self.penalty(x)

    def evaluate(self, x):
        v, g = self.base.evaluate(x)
        if self.l2:
            g = ops.lincomb([1.0, self.l2], [g, self._part(x)]).cut()
        return v + self.penalty(x), g

    def along(self, x, d):
        if self.l1:
            return PlainLine(self, x, d)
        line, a, l2 = self.base.along(x, d), ops.gram([self._part(x), self._part(d)]), self.l2

        class Sum(Line):
            def at(self, etas):
                return [(v + l2 * (a[0, 0] / 2 + e * a[0, 1] + e * e * a[1, 1] / 2), s + l2 * (a[0, 1] + e * a[1, 1])) for e, (v, s) in zip(etas, line.at(etas))]

            def free(self):
                line.free()

        return Sum()

    def hold(self):
        self.base.hold()

    def release(self):
        self.base.release()


class Batched(Objective):
    """Rotation over few large batches: the n-th evaluation made while nothing is held uses batch n mod m.

    policy says which batch a line search sees: ``same`` as the gradient before it, the ``next`` one (held through the search),
    or ``rotate`` (a new one each time). ``log`` records (evaluation, batch, purpose).

    A batch may be given as a function that loads it. Then one batch is cached at a time: taking another frees the one before,
    and with ``prefetch`` the batch after it is loaded meanwhile.
    """

    def __init__(self, batches: list[Objective | Callable[[], Objective]], policy: str = "same", prefetch: bool = False):
        if not batches:
            raise ValueError("no batches")
        if policy not in ("same", "next", "rotate"):
            raise ValueError(f"unknown policy {policy!r}")
        self.batches, self.policy, self.n, self.current, self.frozen, self.log = batches, policy, 0, 0, False, []
        self.loaded: dict[int, Objective] = {}
        self.coming: dict[int, Future] = {}
        self.loader = ThreadPoolExecutor(1) if prefetch and len(batches) > 1 else None

    def batch(self, k: int) -> Objective:
        if isinstance(self.batches[k], Objective):
            return self.batches[k]
        if k not in self.loaded:
            self.loaded[k] = self.coming.pop(k).result() if k in self.coming else self.batches[k]()
            for old in [j for j in self.loaded if j != k]:
                self.loaded.pop(old).free()
            if self.loader:
                after = (k + 1) % len(self.batches)
                self.coming[after] = self.loader.submit(self.batches[after])
        return self.loaded[k]

    def again(self, policy: str) -> "Batched":
        """The same batches from the first one on, under another policy."""
        return Batched(self.batches, policy, self.loader is not None)

    def free(self) -> None:
        for f in [*self.loaded.values(), *(c.result() for c in self.coming.values())]:
            f.free()
        self.loaded, self.coming = {}, {}

    def _take(self, purpose: str) -> Objective:
        if not self.frozen:
            self.current = self.n % len(self.batches)
            self.n += 1
        self.log.append((len(self.log), self.current, purpose))
        return self.batch(self.current)

    def evaluate(self, x):
        return self._take("gradient").evaluate(x)

    def value(self, x):
        return self._take("value").value(x)

    def along(self, x, d):
        if self.policy == "rotate":
            return _RotatingLine(self, x, d)
        if self.policy == "next" and not self.frozen:
            self.current = self.n % len(self.batches)
            self.n += 1
        self.log.append((len(self.log), self.current, "line"))
        return self.batch(self.current).along(x, d)

    def hold(self):
        if self.policy == "next":
            self.current = self.n % len(self.batches)
            self.n += 1
        self.frozen = self.policy != "rotate"

    def release(self):
        self.frozen = False


class _RotatingLine(Line):
    def __init__(self, f: Batched, x: Vec, d: Vec):
        self.f, self.x, self.d = f, x, d

    def at(self, etas):
        out = []
        for eta in etas:
            line = self.f._take("line").along(self.x, self.d)
            out += line.at([eta])
            line.free()
        return out


class Accumulated(Objective):
    """Mean over a group of batches, weighted by their total weights: value and gradient of their union."""

    def __init__(self, batches: list[Objective], weights: list[float]):
        total = sum(weights)
        self.batches, self.shares = batches, [w / total for w in weights]

    def evaluate(self, x):
        got = [b.evaluate(x) for b in self.batches]
        return sum(s * v for s, (v, _) in zip(self.shares, got)), ops.lincomb(self.shares, [g for _, g in got]).cut()

    def value(self, x):
        return sum(s * b.value(x) for s, b in zip(self.shares, self.batches))

    def along(self, x, d):
        lines, shares = [b.along(x, d) for b in self.batches], self.shares

        class Sum(Line):
            def at(self, etas):
                each = [line.at(etas) for line in lines]
                return [tuple(sum(s * e[i][j] for s, e in zip(shares, each)) for j in (0, 1)) for i in range(len(etas))]

            def free(self):
                for line in lines:
                    line.free()

        return Sum()


def batch_iter(m: int) -> Iterator[int]:
    n = 0
    while True:
        yield n % m
        n += 1
