"""Minimisers: one iteration skeleton, and gradient descent, adaptive steps, limited-memory quasi-Newton and its orthant-wise form, truncated Newton.

The driver holds numbers and small matrices only. Every vector is a DataFrame: made once, its lineage cut every ``lineage_every``
iterations (cached in between), freed when replaced. The default cuts every time: a new point depends on the old one
several times over, so the text of an uncut plan doubles with each iteration even where all of it is cached.
"""

from __future__ import annotations

import json
import math
import time
from dataclasses import dataclass, field
from enum import Enum

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from gridmin.objective import Line, Objective, Penalised
from gridmin.vectors import Vec, ops


class Reason(Enum):
    GRADIENT = "gradient norm"
    IMPROVEMENT = "improvement"
    MAX_ITERATIONS = "iterations"
    LINE_SEARCH = "line search"
    NON_FINITE = "non-finite"
    CALLBACK = "callback"


LOG = T.StructType([
    T.StructField("iteration", T.IntegerType()), T.StructField("value", T.DoubleType()), T.StructField("grad_norm", T.DoubleType()), T.StructField("improvement", T.DoubleType()),
    T.StructField("step", T.DoubleType()), T.StructField("evaluations", T.IntegerType()), T.StructField("batch_id", T.IntegerType()), T.StructField("seconds", T.DoubleType()), T.StructField("reason", T.StringType()),
])


@dataclass
class State:
    x: Vec
    value: float
    grad: Vec
    norm: float
    iteration: int = 0
    history: object = None
    improvement: float = float("nan")


@dataclass
class Result:
    x: Vec
    value: float
    grad_norm: float
    reason: Reason
    log: list[tuple] = field(default_factory=list)

    def log_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.log, LOG)

    @property
    def iterations(self) -> int:
        return self.log[-1][0] if self.log else 0

    @property
    def evaluations(self) -> int:
        return sum(r[5] for r in self.log)


@dataclass
class GradNorm:
    tol: float = 1e-5
    p: float = 2
    relative: bool = False
    first: float | None = None

    def __call__(self, s: State) -> Reason | None:
        self.first = s.norm if self.first is None or s.iteration == 0 else self.first
        return Reason.GRADIENT if s.norm <= self.tol * (self.first if self.relative else 1.0) else None


@dataclass
class Improvement:
    """Stops when the relative improvement stays below ``tol`` for ``window`` iterations."""

    tol: float = 1e-6
    window: int = 1
    seen: int = 0

    def __call__(self, s: State) -> Reason | None:
        self.seen = self.seen + 1 if s.iteration > 0 and s.improvement < self.tol else 0
        return Reason.IMPROVEMENT if self.seen >= self.window else None


@dataclass
class MaxIter:
    n: int = 10

    def __call__(self, s: State) -> Reason | None:
        return Reason.MAX_ITERATIONS if s.iteration >= self.n else None


def relative_improvement(before: float, after: float) -> float:
    return abs(before - after) / max(abs(before), 1e-6)


class Minimiser:
    """The skeleton. Subclasses say how to adjust the objective, keep history, choose direction and step, and move."""

    def __init__(self, stop: list | None = None, lineage_every: int = 1, cut_mode: str = "auto", callback=None):
        self.stop = stop or [GradNorm(), MaxIter()]
        self.lineage_every, self.cut_mode, self.callback = lineage_every, cut_mode, callback

    def adjust(self, f: Objective) -> Objective:
        return f

    def initial_history(self, f: Objective, x: Vec):
        return None

    def direction(self, s: State, f: Objective) -> Vec:
        return ops.scale(s.grad, -1.0)

    def step_size(self, s: State, f: Objective, d: Vec) -> tuple[float | None, int]:
        """(step or None, evaluations)."""
        raise NotImplementedError

    def take_step(self, s: State, d: Vec, eta: float) -> Vec:
        return ops.lincomb([1.0, eta], [s.x, d])

    def update_history(self, old: State, x: Vec, grad: Vec):
        return old.history

    def criterion_norm(self, x: Vec, grad: Vec) -> float:
        return ops.norm(grad, 2)

    def _settle(self, v: Vec, step: int) -> Vec:
        if v.path:
            return v
        if self.lineage_every and step % self.lineage_every == 0:
            return v.cut(self.cut_mode)
        return v.materialise()

    def iterations(self, objective: Objective, x0: Vec, resume_from: str | None = None):
        """Yields (state, log row, reason or None)."""
        f, t = self.adjust(objective), time.time()
        first = 0
        if resume_from:
            x0, first = load_point(x0.df.sparkSession, resume_from)
        value, grad = f.evaluate(x0)
        grad = self._settle(grad, 0)
        s = State(x0, value, grad, self.criterion_norm(x0, grad), first)
        s.history = self.initial_history(f, x0)
        reason = self._reason(s)
        yield s, self._row(s, 0.0, 1, f, t, reason), reason
        while reason is None:
            t = time.time()
            d = self._settle(self.direction(s, f), s.iteration)
            f.hold()
            eta, used = self.step_size(s, f, d)
            f.release()
            if eta is None:
                reason = Reason.LINE_SEARCH
                yield s, self._row(s, 0.0, used, f, t, reason), reason
                return
            x = self._settle(self.take_step(s, d, eta), s.iteration)
            value, grad = f.evaluate(x)
            grad = self._settle(grad, s.iteration)
            new = State(x, value, grad, self.criterion_norm(x, grad), s.iteration + 1, None, relative_improvement(s.value, value))
            new.history = self.update_history(s, x, grad)
            d.unpersist()
            self.forget(s, new)
            s = new
            reason = self._reason(s)
            yield s, self._row(s, eta, used + 1, f, t, reason), reason

    def forget(self, old: State, new: State) -> None:
        """Free what the next iteration does not need."""
        old.x.unpersist()
        old.grad.unpersist()

    def _reason(self, s: State) -> Reason | None:
        if not (math.isfinite(s.value) and math.isfinite(s.norm)):
            return Reason.NON_FINITE
        if self.callback and self.callback(s):
            return Reason.CALLBACK
        return next((r for r in (c(s) for c in self.stop) if r), None)

    def _row(self, s: State, eta: float, used: int, f, t: float, reason: Reason | None) -> tuple:
        base = f.base if isinstance(f, Penalised) else f
        return (s.iteration, s.value, s.norm, s.improvement, float(eta), used, int(getattr(base, "current", 0)), time.time() - t, reason.value if reason else None)

    def run(self, objective: Objective, x0: Vec, resume_from: str | None = None, save_to: str | None = None) -> Result:
        log: list[tuple] = []
        for s, row, reason in self.iterations(objective, x0, resume_from):
            log.append(row)
            if save_to:
                save_point(s.x, s.iteration, save_to)
        return Result(s.x, s.value, s.norm, reason, log)


def save_point(x: Vec, iteration: int, path: str) -> None:
    """The point as Parquet, then a line of JSON that names it: a lost driver resumes from the last complete pair."""
    spark = x.df.sparkSession
    x.df.write.mode("overwrite").parquet(f"{path}/x-{iteration}")
    meta = {"iteration": iteration, "length": x.length, "block_size": x.block_size, "stack": x.stack, "segments": x.segments}
    spark.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta-{iteration}")
    spark.createDataFrame([(str(iteration),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/last")


def load_point(spark: SparkSession, path: str) -> tuple[Vec, int]:
    last = int(spark.read.text(f"{path}/last").first()[0])
    meta = json.loads(spark.read.text(f"{path}/meta-{last}").first()[0])
    segments = tuple(tuple(s) for s in meta["segments"])
    return Vec(spark.read.parquet(f"{path}/x-{last}"), meta["length"], meta["block_size"], meta["stack"], "double", segments), last


@dataclass
class PowerDecay:
    """eta0 * t ** -p at iteration t = 1, 2, ..."""

    eta0: float
    p: float = 0.5

    def __call__(self, t: int) -> float:
        return self.eta0 * t**-self.p


class GradientDescent(Minimiser):
    """x - eta_t g with a constant or decaying rate."""

    def __init__(self, rate: float | PowerDecay = 0.1, **kw):
        super().__init__(**kw)
        self.rate = rate

    def step_size(self, s, f, d):
        return (self.rate(s.iteration + 1) if callable(self.rate) else self.rate), 0


class AdaptiveGradient(Minimiser):
    """Per-component steps from the history of squared gradients, with closed-form l2 and shrinking l1 steps.

    Every gradient enters the history once: the stretch uses history plus the current square, the history takes the square
    in afterwards. Up to ``memory`` steps squares add up, later they decay. ``history_index='printed'`` reproduces the
    reading in which, past the memory, the current square counts twice.
    """

    def __init__(self, eta: float = 0.1, delta: float = 1e-8, memory: int | None = None, l1: float = 0.0, l2: float = 0.0, prox: str = "printed", history_index: str = "once", **kw):
        super().__init__(**kw)
        if delta <= 0:
            raise ValueError("delta must be positive")
        self.eta, self.delta, self.memory, self.l1, self.l2, self.prox, self.index = eta, delta, memory, l1, l2, prox, history_index

    def adjust(self, f):
        return _ReportsPenalty(f, self.l1, self.l2) if self.l1 or self.l2 else f

    def initial_history(self, f, x):
        return self._settle(ops.scale(x, 0.0), 0)

    def direction(self, s, f):
        return s.grad

    def step_size(self, s, f, d):
        return self.eta, 0

    def _next_history(self, h: np.ndarray, g: np.ndarray, t: int) -> np.ndarray:
        m = self.memory
        return h + g * g if m is None or t <= m else (1 - 1 / m) * h + g * g / m

    def take_step(self, s, d, eta):
        t, delta, l1, l2, exact = s.iteration + 1, self.delta, self.l1, self.l2, self.prox == "exact"
        printed = self.index == "printed" and self.memory is not None and t > self.memory
        ahead = self._next_history

        def move(x, h, g):
            base = ahead(h, g, t) if printed else h
            sigma = np.sqrt(base + g * g + delta)
            z = (sigma * x - eta * g) / (sigma + eta * l2)
            theta = eta * l1 / (sigma + eta * l2 if exact else sigma)
            return np.where(np.abs(z) < theta, 0.0, z - theta * np.sign(z)) if l1 else z

        self.coming = None
        if self.lineage_every and s.iteration % self.lineage_every == 0 and self.cut_mode != "checkpoint":  # both are cut, so one pass writes them
            x, self.coming = ops.numpy_maps([s.x, s.history, s.grad], lambda x, h, g: (move(x, h, g), ahead(h, g, t)), self.cut_mode)
            return x
        return ops.numpy_map([s.x, s.history, s.grad], move)

    def update_history(self, old, x, grad):
        t, ahead = old.iteration + 1, self._next_history
        return self.coming or self._settle(ops.numpy_map([old.history, old.grad], lambda h, g: ahead(h, g, t)), old.iteration)

    def criterion_norm(self, x, grad):
        if not self.l1:
            return ops.norm(ops.lincomb([1.0, self.l2], [grad, x]), 2) if self.l2 else ops.norm(grad, 2)
        return ops.norm(pseudo_gradient(x, ops.lincomb([1.0, self.l2], [grad, x]), self.l1), 2)

    def forget(self, old, new):
        super().forget(old, new)
        old.history.unpersist()


class _ReportsPenalty(Penalised):
    """Value with both penalties, gradient of the smooth unpenalised part: the step handles the penalties itself."""

    def evaluate(self, x):
        v, g = self.base.evaluate(x)
        return v + self.penalty(x), g


def pseudo_gradient(x: Vec, g: Vec, l1: float | Vec) -> Vec:
    """Minimum-norm subgradient of the objective with l1."""

    def pick(x, g, a):
        at_zero = np.where(g + a < 0, g + a, np.where(g - a > 0, g - a, 0.0))
        return np.where(x != 0, g + a * np.sign(x), at_zero)

    if isinstance(l1, Vec):
        return ops.numpy_map([x, g, l1], pick)
    return ops.numpy_map([x, g], lambda x, g: pick(x, g, l1))


@dataclass
class StrongWolfe:
    """Bracket by growing steps, then zoom by safeguarded cubic steps until both conditions hold. Non-finite means too long."""

    c1: float = 1e-4
    c2: float = 0.9
    max_evals: int = 20

    def search(self, line: Line, phi0: float, slope0: float, first: float = 1.0) -> tuple[float | None, int]:
        seen, best = 0, None

        def at(eta: float):
            nonlocal seen, best
            seen += 1
            v, s = line.at([eta])[0]
            if math.isfinite(v) and v <= phi0 + self.c1 * eta * slope0 and (best is None or v < best[1]):
                best = (eta, v)
            return v, s

        if slope0 >= 0:
            return None, 0
        low, eta, high = (0.0, phi0, slope0), first, None
        while seen < self.max_evals:
            v, s = at(eta)
            if not math.isfinite(v) or v > phi0 + self.c1 * eta * slope0 or v >= low[1]:
                high = (eta, v, s)
            elif abs(s) <= -self.c2 * slope0:
                return eta, seen
            elif s >= 0:
                low, high = (eta, v, s), low
            else:
                low = (eta, v, s)
            if high is None:
                eta *= 2.0
            else:
                eta = _between(low, high)
                if abs(high[0] - low[0]) < 1e-14 * max(1.0, low[0]):
                    break
        return (best[0] if best else None), seen


def _between(a: tuple, b: tuple) -> float:
    """Minimum of the cubic through both ends, kept off them; the middle if the far end isn't finite."""
    (x, fx, gx), (y, fy, gy) = a, b
    mid, width = (x + y) / 2, abs(y - x)
    if not all(map(math.isfinite, (fy, gy))):
        return mid
    d1 = gx + gy - 3 * (fx - fy) / (x - y)
    inner = d1 * d1 - gx * gy
    if inner < 0:
        return mid
    d2 = math.copysign(math.sqrt(inner), y - x)
    bottom = gy - gx + 2 * d2
    if bottom == 0:
        return mid
    t = y - (y - x) * (gy + d2 - d1) / bottom
    lo, hi = min(x, y) + 0.1 * width, max(x, y) - 0.1 * width
    return t if lo <= t <= hi else mid


@dataclass
class Backtracking:
    """Armijo on a ladder of shrinking steps, all tried in one scan."""

    c1: float = 1e-4
    shrink: float = 0.5
    rungs: int = 6
    ladders: int = 5

    def search(self, line: Line, phi0: float, slope0: float, first: float = 1.0) -> tuple[float | None, int]:
        if slope0 >= 0:
            return None, 0
        eta = first
        for n in range(self.ladders):
            etas = [eta * self.shrink**r for r in range(self.rungs)]
            for e, (v, _) in zip(etas, line.at(etas)):
                if math.isfinite(v) and v <= phi0 + self.c1 * e * slope0:
                    return e, (n + 1) * self.rungs
            eta = etas[-1] * self.shrink
        return None, self.ladders * self.rungs


@dataclass
class Memory:
    """Pairs (s, y) of the last steps; the oldest is freed when the memory is full."""

    size: int
    s: list[Vec] = field(default_factory=list)
    y: list[Vec] = field(default_factory=list)

    def push(self, s: Vec, y: Vec) -> None:
        self.s.append(s)
        self.y.append(y)
        if len(self.s) > self.size:
            self.s.pop(0).unpersist()
            self.y.pop(0).unpersist()

    def clear(self) -> None:
        for v in (*self.s, *self.y):
            v.unpersist()
        self.s, self.y = [], []


def two_loop(gram: np.ndarray, m: int) -> np.ndarray:
    """Coefficients of the quasi-Newton direction on the basis s_1..s_m, y_1..y_m, g from the basis's dot products alone."""
    c = np.zeros(2 * m + 1)
    c[-1] = -1.0
    alpha = np.zeros(m)
    rho = np.array([gram[i, m + i] for i in range(m)])
    for i in reversed(range(m)):
        alpha[i] = (c @ gram[:, i]) / rho[i]
        c[m + i] -= alpha[i]
    if m:
        c *= rho[-1] / gram[2 * m - 1, 2 * m - 1]
    for i in range(m):
        beta = (c @ gram[:, m + i]) / rho[i]
        c[i] += alpha[i] - beta
    return c


class LimitedMemory(Minimiser):
    """Limited-memory quasi-Newton. One job gives all dot products, the recursion runs on them, one pass builds the direction."""

    def __init__(self, memory: int = 7, line_search=None, l2: float = 0.0, curvature_eps: float = 1e-10, pair_batch: str = "mixed", **kw):
        super().__init__(**kw)
        self.memory, self.search, self.l2, self.eps, self.pair_batch = memory, line_search or StrongWolfe(), l2, curvature_eps, pair_batch

    def adjust(self, f):
        self.f = Penalised(f, 0.0, self.l2) if self.l2 else f
        return self.f

    def initial_history(self, f, x):
        return Memory(self.memory)

    def steer(self, s: State, g: Vec) -> Vec:
        h: Memory = s.history
        basis = [*h.s, *h.y, g]
        gram = ops.gram(basis)
        c = two_loop(gram, len(h.s))
        if h.s and c @ gram[:, -1] >= 0:
            h.clear()
            basis, gram, c = [g], gram[-1:, -1:], np.array([-1.0])
        self.slope, self.size = float(c @ gram[:, -1]), math.sqrt(max(gram[-1, -1], 0.0))
        return ops.lincomb(c.tolist(), basis)

    def direction(self, s, f):
        return self.steer(s, s.grad)

    def first_step(self, s: State) -> float:
        return 1.0 if s.history.s else 1.0 / max(self.size, 1e-300)

    def step_size(self, s, f, d):
        line = f.along(s.x, d)
        base = f.base if isinstance(f, Penalised) else f
        other = getattr(base, "policy", "same") == "next"
        phi, slope = line.at([0.0])[0] if other else (s.value, self.slope)
        eta, used = self.search.search(line, phi, slope, self.first_step(s))
        line.free()
        return eta, used + other

    def update_history(self, old, x, grad):
        h: Memory = old.history
        ds = self._settle(ops.sub(x, old.x), old.iteration)
        before = old.grad
        base = self.f.base if isinstance(self.f, Penalised) else self.f
        if self.pair_batch == "same" and hasattr(base, "batches"):
            base.frozen = True
            before = self.f.evaluate(old.x)[1]
            base.frozen = False
        dy = self._settle(ops.sub(grad, before), old.iteration)
        g = ops.gram([ds, dy])
        if g[0, 1] > self.eps * g[1, 1]:
            h.push(ds, dy)
        else:
            ds.unpersist()
            dy.unpersist()
        return h


class TruncatedNewton(Minimiser):
    """Newton directions by conjugate gradients on the objective's curvature, scaled by its diagonal, until the residual is ``forcing``
    of the gradient or after ``inner`` products. Every step is followed by the objective's own balancing, if it has one; the first
    iteration is only that, twice, as curvature may all but vanish at the start.

    A product is a pass over the data, as an evaluation is: both count as evaluations, and so do the passes of balancing.
    """

    def __init__(self, forcing: float = 0.5, inner: int = 10, line_search=None, **kw):
        super().__init__(**kw)
        self.forcing, self.inner, self.search = forcing, inner, line_search or StrongWolfe()

    def adjust(self, f):
        self.f = f
        return f

    def initial_history(self, f, x):
        return 0

    def update_history(self, old, x, grad):
        return old.history + 1

    def direction(self, s, f):
        self.products = 0
        if f.balancing and not s.history:
            return ops.scale(s.grad, -1.0)
        h = f.curvature(s.x, s.grad)
        y, r, p, z = ops.numpy_maps([s.grad, h.scale], lambda g, c: (0.0 * g, -c * g, -c * g, -c * c * g))  # z: p scaled
        first = rr = ops.gram([r])[0, 0]
        moved = False
        for _ in range(self.inner):
            q = h.times(p, z).cut()
            self.products += 1
            m = ops.gram([p, q, r])
            if not (0.0 < m[0, 1] < math.inf and math.isfinite(m[1, 1])):
                q.unpersist()
                break
            a = rr / m[0, 1]
            left = max(rr - 2.0 * a * m[1, 2] + a * a * m[1, 1], 0.0)
            b = left / rr
            old, rr, moved = (y, r, p, z, q), left, True
            y, r, p, z = ops.numpy_maps([y, r, p, q, h.scale], lambda y, r, p, q, c: _conjugate(y, r, p, q, c, a, b))
            for v in old:
                v.unpersist()
            if rr <= self.forcing**2 * first:
                break
        d = ops.mul(y if moved else p, h.scale).cut()  # p: the scaled gradient, where no product was usable
        for v in (y, r, p, z):
            v.unpersist()
        h.free()
        return d

    def step_size(self, s, f, d):
        if f.balancing and not s.history:
            return 0.0, 2 * f.balancing
        line = f.along(s.x, d)
        eta, used = self.search.search(line, s.value, ops.dot(s.grad, d), 1.0)
        line.free()
        return eta, self.products + used + f.balancing

    def take_step(self, s, d, eta):
        if not self.f.balancing:
            return super().take_step(s, d, eta)
        moved = self._settle(super().take_step(s, d, eta), 0) if eta else self.f.balanced(s.x)
        x = self.f.balanced(moved)
        moved.unpersist()
        return x


def _conjugate(y: np.ndarray, r: np.ndarray, p: np.ndarray, q: np.ndarray, scale: np.ndarray, a: float, b: float) -> tuple:
    """A step of conjugate gradients: the solution, the residual, the next direction, and that one scaled."""
    r_new = r - a * q
    p_new = r_new + b * p
    return y + a * p, r_new, p_new, scale * p_new


class OrthantWise(LimitedMemory):
    """Quasi-Newton for an l1 penalty: directions from the pseudo-gradient, aligned with it, steps projected on the orthant.

    Not guaranteed to converge; an iteration limit is always present. With l1 = 0 it is LimitedMemory on the same code path.
    ``l1`` may be a Vec (per-component weights, 0 for an intercept).
    """

    def __init__(self, l1: float | Vec = 0.0, line_search: Backtracking | None = None, **kw):
        super().__init__(line_search=line_search or Backtracking(), **kw)
        self.l1 = l1
        if not any(isinstance(c, MaxIter) for c in self.stop):
            self.stop = [*self.stop, MaxIter(100)]

    def adjust(self, f):
        smooth = super().adjust(f)
        if isinstance(self.l1, Vec):
            weights = self.l1

            class Weighted(Penalised):
                def penalty(self, x):
                    return ops.norm(ops.mul(x, weights), 1)

            return Weighted(smooth)
        return Penalised(smooth, self.l1)

    def criterion_norm(self, x, grad):
        return ops.norm(pseudo_gradient(x, grad, self.l1), 2)

    def direction(self, s, f):
        if self.l1 == 0:
            self.pseudo = s.grad
            return self.steer(s, s.grad)
        self.pseudo = self._settle(pseudo_gradient(s.x, s.grad, self.l1), s.iteration)
        return ops.numpy_map([self.steer(s, self.pseudo), self.pseudo], lambda d, p: np.where(d * p < 0, d, 0.0))

    def _project(self, s: State, d: Vec, eta: float) -> Vec:
        if self.l1 == 0:
            return ops.lincomb([1.0, eta], [s.x, d])

        def move(x, d, p):
            orthant = np.where(x != 0, np.sign(x), -np.sign(p))
            z = x + eta * d
            return np.where(z * orthant > 0, z, 0.0)

        return ops.numpy_map([s.x, d, self.pseudo], move)

    def take_step(self, s, d, eta):
        return self._project(s, d, eta)

    def step_size(self, s, f, d):
        if self.l1 == 0:
            return super().step_size(s, f, d)
        eta, ls = self.first_step(s), self.search
        for n in range(ls.rungs * ls.ladders):
            trial = self._project(s, d, eta).cut(self.cut_mode)
            v = f.value(trial)
            drop = ops.dot(self.pseudo, ops.sub(trial, s.x))
            trial.unpersist()
            if math.isfinite(v) and v <= s.value + ls.c1 * drop and drop < 0:
                return eta, n + 1
            eta *= ls.shrink
        return None, ls.rungs * ls.ladders


def chain(minimisers: list[Minimiser], objective: Objective, x0: Vec) -> list[Result]:
    """Phases one after another, each from the point of the one before (a warm start)."""
    out = []
    for m in minimisers:
        out.append(m.run(objective, x0))
        x0 = out[-1].x
    return out
