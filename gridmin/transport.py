"""Entropy-regularised optimal transport by minimising the negative dual over a grid of point tiles.

The dual vector is u and v in one block vector. Tiles pair a strip of source points (several blocks) with a strip of target points;
costs are recomputed from coordinates in the tile (``cost='recompute'``, bytes in the points times the strips of the other side) or
kept (``'tiles'``, bytes in the pairs). Tiles are laid out once by (x_part, y_part) and never move again: a strip of u is copied to the
tiles of its row, a strip of v to those of its column. A tile is worked through in chunks of whole blocks, so its matrix is never
held. One pass over the tiles gives row and column sums, hence value and gradient together.

Exponentials that would overflow are kept relative to the largest exponent of their tile, and sums are joined in that form, so
small ``eps`` and long trial steps give a large or infinite value but never a NaN.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin import grid
from gridmin.objective import Line, Objective
from gridmin.order import numbered
from gridmin.session import map_arrow
from gridmin.vectors import Vec, ops
from gridmin.vectors.vec import concat, from_long, zeros


def index_points(points: DataFrame, key: str, coords: str, part_size: int) -> DataFrame:
    """(pos, part, coords) with dense positions in key order."""
    rows = numbered(points.select(key, F.col(coords).cast("array<double>").alias("coords")), key, "pos")
    return rows.select("pos", F.floor(F.col("pos") / part_size).cast("int").alias("part"), "coords")


def strips(indexed: DataFrame, name: str, wide: int) -> DataFrame:
    """(<name>_part, <name>s): the coordinates of ``wide`` blocks, point after point."""
    listed = indexed.groupBy(F.floor(F.col("part") / wide).cast("int").alias("part")).agg(F.sort_array(F.collect_list(F.struct("pos", "coords"))).alias("r"))
    return listed.select(F.col("part").alias(f"{name}_part"), F.flatten("r.coords").alias(f"{name}s"))


def strip_values(v: Vec, name: str, wide: int, out: str) -> DataFrame:
    """(<name>_part, <out>): a vector's blocks put together as ``strips`` does with points."""
    listed = v.df.groupBy(F.floor(F.col("block_id") / wide).cast("int").alias(f"{name}_part")).agg(F.sort_array(F.collect_list(F.struct("block_id", "values"))).alias("r"))
    return listed.select(f"{name}_part", F.flatten("r.values").cast("array<double>").alias(out))


def cost_matrix(x: np.ndarray, y: np.ndarray, metric: str) -> np.ndarray:
    if metric == "cosine":
        return 1.0 - (x @ y.T) / np.maximum(np.linalg.norm(x, axis=1)[:, None] * np.linalg.norm(y, axis=1)[None, :], 1e-300)
    sq = np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None, :] - 2.0 * x @ y.T, 0.0)
    return np.sqrt(sq) if metric == "euclidean" else sq


SUMS = "block_id int, values array<double>, shift double"
#: Points in a strip at most, bytes of its coordinates at most, points where costs are kept, points on a side of a chunk at most (unless a block is longer).
STRIP, STRIP_BYTES, KEPT_STRIP, CHUNK = 1 << 14, 8 << 20, 1 << 10, 512
LARGE = 600.0  # exponents beyond this are kept relative to the largest


def wide_strip(n: int, dim: int, size: int, strips: int, kept: bool) -> int:
    """Blocks in a strip: so few strips, as points are copied to all strips of the other side, more where a strip would be too large."""
    points = min(-(-n // strips), KEPT_STRIP if kept else STRIP, STRIP_BYTES // (8 * max(1, dim)))
    return max(1, points // size)


def chosen(x: np.ndarray, y: np.ndarray, of_10000: int, seed: int) -> np.ndarray:
    """Which pairs of block numbers a hash sample takes."""
    with np.errstate(over="ignore"):
        h = x.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + y.astype(np.uint64)[None, :] * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(seed) * np.uint64(0x165667B19E3779F9)
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return (h ^ (h >> np.uint64(31))) % np.uint64(10_000) < np.uint64(of_10000)


def heaviest(plan: np.ndarray, top: int) -> np.ndarray:
    """Columns of the ``top`` largest entries of each row, the first of equal ones first."""
    top = min(top, plan.shape[1])
    if top > 8:
        return np.argsort(-plan, axis=1, kind="stable")[:, :top]
    left, out, rows = plan.copy(), [], np.arange(len(plan))
    for _ in range(top):
        out.append(left.argmax(1))
        left[rows, out[-1]] = -np.inf
    return np.stack(out, 1)


def shifted_exp(z: np.ndarray) -> tuple[float, np.ndarray]:
    """(shift, exp(z - shift)); shift is 0 unless exponents are so large that sums could overflow."""
    top = float(z.max(initial=0.0))
    shift = top if top > LARGE else 0.0
    return shift, np.exp(z - shift)


def joined(a: tuple[float, np.ndarray] | None, b: tuple[float, np.ndarray]) -> tuple[float, np.ndarray]:
    """Sum of two (shift, values) pairs."""
    if a is None:
        return b
    if a[0] == b[0]:
        return a[0], a[1] + b[1]
    low, high = sorted((a, b), key=lambda s: s[0])
    return high[0], high[1] + low[1] * np.exp(low[0] - high[0])


def _shifted(held: dict[int, tuple[float, np.ndarray]]) -> pa.RecordBatch:
    values = pa.array([v for _, v in held.values()], pa.list_(pa.float64()))
    return pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), values, pa.array([s for s, _ in held.values()], pa.float64())], names=["block_id", "values", "shift"])


def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of the rows of a block."""
    held: dict[int, tuple[float, np.ndarray]] = {}
    for b in batches:
        for i, (block, shift) in enumerate(zip(b.column(0).to_pylist(), b.column(2).to_pylist())):
            held[block] = joined(held.get(block), (shift, b.column(1)[i].values.to_numpy(zero_copy_only=False)))
    if held:
        yield _shifted(held)


def _weigh(e: np.ndarray, a: np.ndarray | None, b: np.ndarray | None, taken: np.ndarray | None) -> np.ndarray:
    """``e`` times the masses of rows and columns, without the pairs that a sample leaves out; in place."""
    if a is not None:
        e *= a[:, None]
        e *= b[None, :]
    if taken is not None:
        e *= taken
    return e


class Transport(Objective):
    """-L(u, v) for uniform masses, or masses ``a`` and ``b`` given as Vecs of the sides' layouts."""

    balancing = 2
    share = 1.0  # of the pairs, where a sample stands for all

    def __init__(self, x: DataFrame, y: DataFrame, n_x: int, n_y: int, dim: int, eps: float = 0.1, part_size: int = 1024, metric: str = "sqeuclidean", cost: str = "recompute", a: Vec | None = None, b: Vec | None = None):
        """``x``, ``y``: (pos, part, coords) as from ``index_points``."""
        self.n_x, self.n_y, self.dim, self.eps, self.size, self.metric, self.cost = n_x, n_y, dim, eps, part_size, metric, cost
        self.spark, self.first_v = x.sparkSession, -(-n_x // part_size)
        self.y_parts = -(-n_y // part_size)
        cores = self.spark.sparkContext.defaultParallelism
        few = min(math.ceil(math.sqrt(4 * cores)), self.first_v, self.y_parts)  # a side with few blocks leaves more strips to the other
        other = -(-4 * cores // few)
        want = (few, other) if self.first_v <= self.y_parts else (other, few)
        self.x_wide, self.y_wide = (wide_strip(n, dim, part_size, k, cost == "tiles") for n, k in zip((n_x, n_y), want))
        self.x_strips, self.y_strips = -(-self.first_v // self.x_wide), -(-self.y_parts // self.y_wide)
        self.sample: tuple[int, int] | None = None
        self.tiles = grid.tile_grid(strips(x, "x", self.x_wide), strips(y, "y", self.y_wide))
        if cost == "tiles":
            self.tiles = self.cost_tiles()
        self.tiles = self.by_tile(self.tiles).persist()
        self.a, self.b = a, b

    @classmethod
    def of(cls, points_x: DataFrame, points_y: DataFrame, key: str, coords: str, part_size: int = 1024, **kw) -> "Transport":
        x, y = (index_points(p, key, coords, part_size).persist() for p in (points_x, points_y))
        dim = x.select(F.size("coords")).first()[0]
        n_x, n_y = x.count(), y.count()
        if cls is Transport and dim == 1 and kw.get("metric", "sqeuclidean") == "sqeuclidean" and kw.get("cost", "recompute") == "recompute":
            low, high = x.select("coords").unionByName(y.select("coords")).agg(F.min(F.col("coords")[0]), F.max(F.col("coords")[0])).first()
            cells = OnLine.cells(low, high, kw.get("eps", 0.1))
            if cells <= MAX_CELLS and (n_x + n_y) * cells * TERMS < n_x * n_y:
                return OnLine(x, y, n_x, n_y, dim, part_size=part_size, low=low, high=high, **kw)
        return cls(x, y, n_x, n_y, dim, part_size=part_size, **kw)

    def start(self) -> Vec:
        return concat([("u", zeros(self.spark, self.n_x, self.size)), ("v", zeros(self.spark, self.n_y, self.size))])

    def cost_tiles(self) -> DataFrame:
        """(x_part, y_part, cost): costs kept row after row."""
        dim, metric = self.dim, self.metric

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for i in range(b.num_rows):
                    x, y = (b.column(k)[i].values.to_numpy().reshape(-1, dim) for k in (2, 3))
                    c = cost_matrix(x, y, metric)
                    yield pa.RecordBatch.from_arrays([b.column(0).slice(i, 1), b.column(1).slice(i, 1), pa.array([c.reshape(-1)], pa.list_(pa.float64()))], names=["x_part", "y_part", "cost"])

        return map_arrow(self.tiles.select("x_part", "y_part", "xs", "ys"), run, "x_part int, y_part int, cost array<double>")

    def by_tile(self, df: DataFrame) -> DataFrame:
        return df.repartition(int(self.spark.conf.get("spark.sql.shuffle.partitions")), "x_part", "y_part")

    def potentials(self, *vectors: Vec, masses: bool = True) -> tuple[DataFrame, list[str]]:
        """(x_part, y_part, u0, v0, ...): the u and v strips of each vector, and the masses, copied to the tiles that need them."""
        sides = [(v.segment("u"), v.segment("v")) for v in vectors]
        if masses and self.a is not None:
            sides.append((self.a, self.b))
        rows, cols, names = None, None, []
        for k, (u, v) in enumerate(sides):
            left, right = strip_values(u, "x", self.x_wide, f"u{k}"), strip_values(v, "y", self.y_wide, f"v{k}")
            rows, cols = (left, right) if rows is None else (rows.join(left, "x_part"), cols.join(right, "y_part"))
            names += [f"u{k}", f"v{k}"]
        rows = self.by_tile(rows.withColumn("y_part", F.explode(F.sequence(F.lit(0), F.lit(self.y_strips - 1)))))
        cols = self.by_tile(cols.withColumn("x_part", F.explode(F.sequence(F.lit(0), F.lit(self.x_strips - 1)))))
        return rows.join(cols, ["x_part", "y_part"]).select("x_part", "y_part", *names), names

    def _attached(self, *vectors: Vec, masses: bool = True) -> tuple[DataFrame, list[str]]:
        """Tiles with the blocks of each vector that they need."""
        return self._with(*self.potentials(*vectors, masses=masses))

    def _with(self, potentials: DataFrame, names: list[str]) -> tuple[DataFrame, list[str]]:
        data = ["cost"] if self.cost == "tiles" else ["xs", "ys"]
        return self.tiles.join(potentials, ["x_part", "y_part"]).select("x_part", "y_part", *data, *names), names

    def _tile(self):
        """A picklable reader of a tile: its numbers, an iterator of its chunks as (rows, columns, costs, taken), and its vectors.
        Chunks hold whole blocks; ``taken`` is None, or 0 where a sample leaves pairs out."""
        kept, dim, metric, size, sample = self.cost == "tiles", self.dim, self.metric, self.size, self.sample
        x_points, y_points, n_x, n_y, x_wide, y_wide = self.x_wide * self.size, self.y_wide * self.size, self.n_x, self.n_y, self.x_wide, self.y_wide
        edge = size * max(1, CHUNK // size)

        def read(b: pa.RecordBatch, i: int) -> tuple[int, int, Iterator[tuple], list[np.ndarray]]:
            p, q = b.column(0)[i].as_py(), b.column(1)[i].as_py()
            arrays = [b.column(k)[i].values.to_numpy(zero_copy_only=False) for k in range(2, b.num_columns)]
            rows, cols = min(x_points, n_x - p * x_points), min(y_points, n_y - q * y_points)
            data = [arrays[0].reshape(rows, cols)] if kept else [arrays[0].reshape(rows, dim), arrays[1].reshape(cols, dim)]

            def chunks() -> Iterator[tuple]:
                for r in (slice(k, min(k + edge, rows)) for k in range(0, rows, edge)):
                    for s in (slice(k, min(k + edge, cols)) for k in range(0, cols, edge)):
                        taken = None
                        if sample:
                            at = [np.arange(c.start // size, -(-c.stop // size)) + first for c, first in ((r, p * x_wide), (s, q * y_wide))]
                            taken = np.repeat(np.repeat(chosen(*at, *sample), size, 0), size, 1)[: r.stop - r.start, : s.stop - s.start].astype(float)
                        yield r, s, data[0][r, s] if kept else cost_matrix(data[0][r], data[1][s], metric), taken

            return p, q, chunks(), arrays[len(data) :]

        return read

    def costs(self) -> DataFrame:
        """(lo, hi, total, pairs) of each tile's costs."""
        read, data = self._tile(), ["cost"] if self.cost == "tiles" else ["xs", "ys"]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    got = [(c.min(), c.max(), c.sum(), c.size) for _, _, c, _ in read(batch, i)[2]]
                    lo, hi, total, pairs = zip(*got)
                    yield pa.RecordBatch.from_arrays([pa.array([min(lo)]), pa.array([max(hi)]), pa.array([math.fsum(total)]), pa.array([sum(pairs)], pa.int64())], names=["lo", "hi", "total", "pairs"])

        return map_arrow(self.tiles.select("x_part", "y_part", *data), run, "lo double, hi double, total double, pairs bigint")

    def _sums(self, x: Vec) -> DataFrame:
        """(block_id, values, shift): row sums of the exponentials under u's blocks, column sums under v's, over exp(shift)."""
        read, eps, first, weighted, size, x_wide, y_wide = self._tile(), self.eps, self.first_v, self.a is not None, self.size, self.x_wide, self.y_wide

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[int, tuple[float, np.ndarray]] = {}

            def put(block: int, shift: float, values: np.ndarray) -> None:
                held[block] = joined(held.get(block), (shift, values))

            for batch in batches:
                for i in range(batch.num_rows):
                    p, q, chunks, (u, v, *m) = read(batch, i)
                    by_row, by_col = np.zeros(len(u)), np.zeros(len(v))
                    for r, s, c, taken in chunks:
                        z = u[r, None] + v[None, s]
                        z -= c
                        z /= eps
                        if z.max(initial=0.0) <= LARGE:
                            e = _weigh(np.exp(z, out=z), m[0][r] if weighted else None, m[1][s] if weighted else None, taken)
                            by_row[r] += e.sum(1)
                            by_col[s] += e.sum(0)
                            continue
                        for k in range(0, z.shape[0], size):  # a shift for each pair of blocks
                            for j in range(0, z.shape[1], size):
                                part = slice(k, k + size), slice(j, j + size)
                                shift, e = shifted_exp(z[part])
                                e = _weigh(e, m[0][r][part[0]] if weighted else None, m[1][s][part[1]] if weighted else None, taken if taken is None else taken[part])
                                put(p * x_wide + (r.start + k) // size, shift, e.sum(1))
                                put(first + q * y_wide + (s.start + j) // size, shift, e.sum(0))
                    for at, values in ((p * x_wide, by_row), (first + q * y_wide, by_col)):
                        for k in range(0, len(values), size):
                            put(at + k // size, 0.0, values[k : k + size])
            if held:
                yield _shifted(held)

        df, _ = self._attached(x)
        return map_arrow(map_arrow(df, run, SUMS).repartition("block_id"), _add, SUMS)

    def evaluate(self, x):
        scale = F.exp(F.least("shift", F.lit(700.0)))  # beyond that the value counts as infinite anyway
        sums = x.with_df(self._sums(x).select("block_id", F.transform("values", lambda z: z * scale).alias("values"))).cut()
        flat = F.aggregate("values", F.lit(0.0), lambda acc, z: acc + z)
        total = sums.df.where(F.col("block_id") < self.first_v).agg(F.sum(flat)).first()[0]
        if self.a is not None:
            mass = concat([("u", self.a), ("v", self.b)])
            value = -ops.dot(mass, x) + self.eps * total
            g = ops.sub(sums, mass)
        else:
            means = x.df.groupBy((F.col("block_id") < self.first_v).alias("u")).agg(F.sum(flat).alias("s"))
            value = -sum(r["s"] / (self.n_x if r["u"] else self.n_y) for r in means.collect()) + self.eps * total / (self.n_x * self.n_y)
            both, one_u, one_v = self.n_x * self.n_y, 1.0 / self.n_x, 1.0 / self.n_y
            one = F.when(F.col("block_id") < self.first_v, F.lit(one_u)).otherwise(F.lit(one_v))
            g = sums.with_df(sums.df.select("block_id", F.transform("values", lambda z: z / both - one).alias("values")))
        g = g.cut()
        sums.unpersist()
        return (float("inf") if value is None or np.isnan(value) else float(value)), g

    def along(self, x, d):
        return _TransportLine(self, x, d)

    def curvature(self, x, g):
        return _TransportCurvature(self, x, g)

    def balanced(self, x):
        """One sweep of scaling: u at its best for v, then v at its best for that u."""
        return _sweep(self, x)

    def read_outs(self, x: Vec, top: int = 1) -> DataFrame:
        """(x_part, y_part, mass, cost, entropy, rows): per tile the plan's mass, transport cost, sum of p (log(p / (a b)) - 1), and
        the ``top`` heaviest partners of each source point as (pos, partner, mass) structs."""
        read, eps, n_x, n_y, weighted = self._tile(), self.eps, self.n_x, self.n_y, self.a is not None
        x_points, y_points = self.x_wide * self.size, self.y_wide * self.size
        schema = "x_part int, y_part int, mass double, cost double, entropy double, pos array<bigint>, partner array<bigint>, share array<double>"

        def run(batches):
            for batch in batches:
                for i in range(batch.num_rows):
                    p, q, chunks, (u, v, *m) = read(batch, i)
                    mass = cost = entropy = 0.0
                    out, at, cols, vals = [], None, None, None  # rows in hand, and their heaviest in the columns seen so far
                    for r, s, c, taken in chunks:
                        if r != at:
                            out += [(at, cols, vals)] if at else []
                            at, cols, vals = r, np.zeros((r.stop - r.start, 0), np.int64), np.zeros((r.stop - r.start, 0))
                        z = (u[r, None] + v[None, s] - c) / eps
                        plan = np.exp(z) * (m[0][r, None] * m[1][None, s] if weighted else 1.0 / (n_x * n_y))
                        plan = plan if taken is None else plan * taken
                        mass, cost, entropy = mass + plan.sum(), cost + (plan * c).sum(), entropy + (plan * (z - 1)).sum()
                        best, rows = heaviest(plan, top), np.arange(len(plan))[:, None]
                        cols, vals = np.concatenate([cols, best + s.start], 1), np.concatenate([vals, plan[rows, best]], 1)
                        again = heaviest(vals, top)
                        cols, vals = cols[rows, again], vals[rows, again]
                    out.append((at, cols, vals))
                    pos = np.concatenate([np.repeat(np.arange(r.start, r.stop), c.shape[1]) for r, c, _ in out]) + p * x_points
                    partner, share = (np.concatenate([o[k].reshape(-1) for o in out]) for k in (1, 2))
                    row = [[p], [q], [mass], [cost], [entropy], [pos], [partner + q * y_points], [share]]
                    kinds = [pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.float64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.float64())]
                    yield pa.RecordBatch.from_arrays([pa.array(a, k) for a, k in zip(row, kinds)], names=["x_part", "y_part", "mass", "cost", "entropy", "pos", "partner", "share"])

        df, _ = self._attached(x)
        return map_arrow(df, run, schema)

    def plan(self, x: Vec, top: int = 1) -> DataFrame:
        """(pos, partner, mass): the ``top`` heaviest partners of each source point."""
        rows = self.read_outs(x, top).select(F.explode(F.arrays_zip("pos", "partner", "share")).alias("r")).select("r.pos", "r.partner", F.col("r.share").alias("mass"))
        best = F.row_number().over(W.partitionBy("pos").orderBy(F.desc("mass"), "partner"))
        return rows.withColumn("_n", best).where(F.col("_n") <= top).drop("_n")

    def marginal_error(self, x: Vec) -> float:
        """Largest deviation of a row or column mass from its target."""
        return ops.norm(self.evaluate(x)[1], float("inf"))

    def summary(self, x: Vec) -> dict[str, float]:
        """Plan mass, transport cost, regularised primal, dual, gap and marginal error."""
        r = self.read_outs(x).agg(F.sum("mass").alias("mass"), F.sum("cost").alias("cost"), F.sum("entropy").alias("h")).first()
        value, g = self.evaluate(x)
        primal = r["cost"] + self.eps * r["h"]
        return {"mass": r["mass"], "cost": r["cost"], "primal": primal, "dual": -value, "gap": primal + value, "marginal_error": ops.norm(g, float("inf"))}

    def solve(self, minimiser, x0: Vec | None = None):
        return minimiser.run(self, x0 or self.start())


#: Terms of the series between two cells of a line (the one after them is below 1e-17 of the first), and cells at most.
TERMS, MAX_CELLS = 17, 64


class OnLine(Transport):
    """Points on a line with squared distances: sums over all pairs from moments of cells, without going through the pairs.

    The line is cut into cells of width sqrt(eps) at most. With x = a + s and y = b + t around the middles a, b of their cells,
    -(x - y)^2 = -(a - y)^2 - 2 s (a - b) - s^2 + 2 s t, and |2 s t| <= eps / 2, so exp(2 s t / eps) is a short series to the last bit
    of a double. Each point adds ``TERMS`` moments for each cell of the other side; a sum over the other side is a sum over its
    cells. Every term of it is positive but for the series, so nothing cancels and small sums are as exact as large ones.
    Everything else (plans, read-outs, scaling, samples) goes through tiles, which nothing lays out before.
    """

    def __init__(self, x, y, n_x, n_y, dim, low: float, high: float, **kw):
        super().__init__(x, y, n_x, n_y, dim, **kw)
        self.low, self.n_cells = low, self.cells(low, high, self.eps)
        self.wide = (high - low) / self.n_cells if high > low else 1.0
        sides = [strips(side, "p", 1).select((F.col("p_part") + first).cast("int").alias("block_id"), F.col("ps").alias("at")) for side, first in ((x, 0), (y, self.first_v))]
        self.points = sides[0].unionByName(sides[1]).repartition(int(self.spark.conf.get("spark.sql.shuffle.partitions")), "block_id").persist()

    @staticmethod
    def cells(low: float, high: float, eps: float) -> int:
        return max(1, math.ceil((high - low) / math.sqrt(eps)))

    def beside(self, *vectors: Vec) -> DataFrame:
        """(block_id, at, v0, v1, ...): coordinates of a block's points, and its part of the vectors (of the masses, last)."""
        vectors = [*vectors, concat([("u", self.a), ("v", self.b)])] if self.a is not None else vectors
        df = self.points
        for k, v in enumerate(vectors):
            df = df.join(v.df.select("block_id", F.col("values").cast("array<double>").alias(f"v{k}")), "block_id")
        return df

    def _cell(self):
        """A picklable function: the cell of each point, and where in it the point lies, from its middle."""
        low, wide, n = self.low, self.wide, self.n_cells

        def of(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            c = np.clip(((at - low) / wide).astype(np.int64), 0, n - 1)
            return c, at - (low + (c + 0.5) * wide)

        return of

    def _moments(self):
        """A picklable function: (cells of the other side, own cells, TERMS) moments of points with exponents ``z`` (over eps) and weights,
        each pair of cells over exp(shift), and the shifts. Powers are of t over half a cell."""
        of, eps, low, wide, n = self._cell(), self.eps, self.low, self.wide, self.n_cells

        def moments(at: np.ndarray, z: np.ndarray, weights: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
            c, t = of(at)
            powers = (t / (wide / 2))[None, :] ** np.arange(TERMS)[:, None]
            out, shifts = np.zeros((len(weights), n, n, TERMS)), np.full((n, n), -np.inf)
            for k in range(n):
                e = z - (low + (k + 0.5) * wide - at) ** 2 / eps
                np.maximum.at(shifts[k], c, e)
                e = np.exp(e - shifts[k][c])
                for w, weight in enumerate(weights):
                    for p in range(TERMS):
                        out[w, k, :, p] = np.bincount(c, weights=powers[p] * e * weight, minlength=n)
            return shifts, out

        return moments

    def _gather(self, df: DataFrame, exponents, kinds: int) -> dict:
        """Moments of both sides over all blocks: {(side, step): (shifts, moments)}. ``exponents(vectors)`` gives for each step the exponents
        over eps and the weights of a block. What comes back are numbers of cells, whose count no input grows."""
        moments, first, n = self._moments(), self.first_v, self.n_cells

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict = {}
            for b in batches:
                for i in range(b.num_rows):
                    side = int(b.column(0)[i].as_py() >= first)
                    at, *vectors = (b.column(k)[i].values.to_numpy(zero_copy_only=False) for k in range(1, b.num_columns))
                    for step, (z, weights) in enumerate(exponents(*vectors)):
                        held[side, step] = _add_moments(held.get((side, step)), moments(at, z, weights))
            if held:
                columns = [pa.array([k[j] for k in held], pa.int32()) for j in (0, 1)]
                columns += [pa.array([v[j].reshape(-1) for v in held.values()], pa.list_(pa.float64())) for j in (0, 1)]
                yield pa.RecordBatch.from_arrays(columns, names=["side", "step", "shifts", "moments"])

        out: dict = {}
        for r in map_arrow(df, run, "side int, step int, shifts array<double>, moments array<double>").collect():  # two rows for each task and step
            got = np.array(r["shifts"]).reshape(n, n), np.array(r["moments"]).reshape(kinds, n, n, TERMS)
            out[r["side"], r["step"]] = _add_moments(out.get((r["side"], r["step"])), got)
        return out

    def _sums(self, x):
        eps, weighted, n, first, of, low, wide = self.eps, self.a is not None, self.n_cells, self.first_v, self._cell(), self.low, self.wide
        found = self._gather(self.beside(x), lambda z, m=None: [(z / eps, [np.ones(len(z)) if m is None else m])], 1)
        other = {0: found[1, 0], 1: found[0, 0]}
        series = np.array([(wide / eps) ** p / math.factorial(p) for p in range(TERMS)])  # 2 s t / eps with t in halves of a cell

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = {}
            for b in batches:
                for i in range(b.num_rows):
                    block = b.column(0)[i].as_py()
                    at, z, *m = (b.column(k)[i].values.to_numpy(zero_copy_only=False) for k in range(1, b.num_columns))
                    shifts, moments = other[int(block >= first)]
                    c, s = of(at)
                    powers = s[None, :] ** np.arange(TERMS)[:, None] * series[:, None]
                    logs, factors = np.full((n, len(at)), -np.inf), np.zeros((n, len(at)))
                    for k in range(n):  # cells of the other side
                        logs[k] = (z - s * s - 2 * s * (c - k) * wide) / eps + shifts[c, k]
                        factors[k] = (powers * moments[0][c, k].T).sum(0)
                    shift = float(logs.max(initial=0.0))
                    shift = shift if shift > LARGE else 0.0
                    total = (np.exp(logs - shift) * factors).sum(0)
                    held[block] = shift, total * m[0] if weighted else total
            if held:
                yield _shifted(held)

        return map_arrow(self.beside(x), run, SUMS)

    def along(self, x, d):
        return _OnLineLine(self, x, d)


def _add_moments(a: tuple | None, b: tuple) -> tuple:
    """Sum of two (shifts, moments)."""
    if a is None:
        return b
    top = np.maximum(a[0], b[0])
    near = np.where(np.isfinite(top), top, 0.0)
    return top, sum(m * np.exp(s - near)[None, :, :, None] for s, m in (a, b))


class _OnLineLine(Line):
    """Along a line, sums and slopes are products of both sides' moments."""

    def __init__(self, f: OnLine, x: Vec, d: Vec):
        self.f, self.df = f, f.beside(x, d).persist()
        first, weighted = f.first_v, f.a is not None
        flat = lambda p, q: F.sum(F.aggregate(F.zip_with(p, q, lambda a, b: a * b), F.lit(0.0), lambda acc, z: acc + z))
        mass = F.col("v2") if weighted else F.transform("v0", lambda _: F.when(F.col("block_id") < first, 1.0 / f.n_x).otherwise(1.0 / f.n_y))
        self.m0, self.m1 = self.df.agg(flat("v0", mass), flat("v1", mass)).first()

    def at(self, etas):
        f, steps = self.f, [float(e) for e in etas]
        eps, wide, n = f.eps, f.wide, f.n_cells

        def exponents(z, dz, m=None):
            one = np.ones(len(z)) if m is None else m
            return [((z + e * dz) / eps, [one, one * dz]) for e in steps]

        found = f._gather(self.df, exponents, 2)
        series = np.array([(wide * wide / (2 * eps)) ** p / math.factorial(p) for p in range(TERMS)])
        mid = f.low + (np.arange(n) + 0.5) * wide
        twice = (mid[:, None] - mid[None, :]) ** 2 / eps  # both sides' moments hold the distance of the middles
        scale, out = 1.0 if f.a is not None else float(f.n_x * f.n_y), []
        for k, e in enumerate(steps):
            (h, p), (g, q) = found[0, k], found[1, k]
            logs = h.T + g + twice  # x's cell by y's cell
            shift = max(float(logs.max()), 0.0)
            shift = shift if shift > LARGE else 0.0
            joint = lambda a, b: float((np.exp(logs - shift) * (series * a.transpose(1, 0, 2) * b).sum(2)).sum())  # noqa: B023, E731
            total, slope = joint(p[0], q[0]), joint(p[1], q[0]) + joint(p[0], q[1])
            by = math.exp(shift) if shift < 700.0 else float("inf")
            out.append((float(-self.m0 - e * self.m1 + eps * total * by / scale), float(-self.m1 + slope * by / scale) if slope else -self.m1))
        return out

    def free(self):
        self.df.unpersist()


class _TransportLine(Line):
    def __init__(self, f: Transport, x: Vec, d: Vec):
        self.f = f
        small, names = f.potentials(x, d)
        self.small = f.by_tile(small).persist()  # four strips a tile; the tiles themselves are not copied
        self.df = f._with(self.small, names)[0]
        sums = []
        flat = F.aggregate("values", F.lit(0.0), lambda acc, z: acc + z)
        if f.a is not None:
            mass = concat([("u", f.a), ("v", f.b)])
            self.m0, self.m1 = ops.dot(mass, x), ops.dot(mass, d)
        else:
            for vec in (x, d):
                got = vec.df.groupBy((F.col("block_id") < f.first_v).alias("u")).agg(F.sum(flat).alias("s")).collect()
                sums.append(sum(r["s"] / (f.n_x if r["u"] else f.n_y) for r in got))
            self.m0, self.m1 = sums

    def at(self, etas):
        f, steps = self.f, [float(e) for e in etas]
        read, eps, weighted = f._tile(), f.eps, f.a is not None

        def run(batches):
            sums: list = [None] * len(steps)
            for batch in batches:
                for i in range(batch.num_rows):
                    _, _, chunks, (u, v, du, dv, *m) = read(batch, i)
                    for r, s, c, taken in chunks:
                        z, dz = (u[r, None] + v[None, s] - c) / eps, du[r, None] + dv[None, s]
                        for k, eta in enumerate(steps):
                            shift, e = shifted_exp(z + eta * dz / eps)
                            e = _weigh(e, m[0][r] if weighted else None, m[1][s] if weighted else None, taken)
                            sums[k] = joined(sums[k], (shift, np.array([e.sum(), (e * dz).sum()])))
            got = [(k, s[0], *s[1].tolist()) for k, s in enumerate(sums) if s]
            if got:
                k, h, t, d = zip(*got)
                yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(h, pa.float64()), pa.array(t, pa.float64()), pa.array(d, pa.float64())], names=["k", "h", "t", "s"])

        parts: dict[int, tuple] = {}
        for r in map_arrow(self.df, run, "k int, h double, t double, s double").collect():  # a row for each task and step
            parts[r["k"]] = joined(parts.get(r["k"]), (r["h"], np.array([r["t"], r["s"]])))
        n, out = 1.0 if weighted else float(f.n_x * f.n_y), []
        for k, e in enumerate(steps):
            h, (t, s) = parts[k]
            scale = np.exp(h) if h < 700.0 else float("inf")
            out.append((float(-self.m0 - e * self.m1 + eps * t * scale / n), float(-self.m1 + s * scale / n) if s else -self.m1))
        return out

    def free(self):
        self.small.unpersist()


class _TransportCurvature:
    """The second derivative at x, from x and the gradient there: (m p + P p) / eps with the masses m of the points and the plan P
    between the sides. Scaled by its diagonal m / eps on both sides it is p + s P (s p) / eps, with s = ``scale``. A product is one pass over the tiles."""

    def __init__(self, f: Transport, x: Vec, g: Vec):
        self.f = f
        small, self.names = f.potentials(x)
        self.small = f.by_tile(small).persist()
        root = lambda m, eps=f.eps: np.sqrt(eps / np.maximum(m, 1e-300))
        if f.a is not None:
            self.scale = ops.numpy_map([g, concat([("u", f.a), ("v", f.b)])], lambda g, m: root(g + m)).cut()
        else:
            one = F.when(F.col("block_id") < f.first_v, F.lit(1.0 / f.n_x)).otherwise(F.lit(1.0 / f.n_y))
            self.scale = ops.numpy_map([g.with_df(g.df.select("block_id", F.transform("values", lambda z: z + one).alias("values")))], root).cut()

    def times(self, p: Vec, scaled: Vec) -> Vec:
        """The scaled curvature times ``p``; ``scaled`` is scale * p."""
        f = self.f
        read, eps, weighted, first, size, x_wide, y_wide = f._tile(), f.eps, f.a is not None, f.first_v, f.size, f.x_wide, f.y_wide

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[int, tuple[float, np.ndarray]] = {}
            for batch in batches:
                for i in range(batch.num_rows):
                    p, q, chunks, (u, v, *m, pu, pv) = read(batch, i)
                    by_row, by_col = np.zeros(len(u)), np.zeros(len(v))
                    for r, s, c, taken in chunks:
                        z = u[r, None] + v[None, s]
                        z -= c
                        z /= eps
                        e = _weigh(np.exp(z, out=z), m[0][r] if weighted else None, m[1][s] if weighted else None, taken)
                        by_row[r] += e @ pv[s]
                        by_col[s] += pu[r] @ e
                    for at, values in ((p * x_wide, by_row), (first + q * y_wide, by_col)):
                        for k in range(0, len(values), size):
                            held[at + k // size] = joined(held.get(at + k // size), (0.0, values[k : k + size]))
            if held:
                yield _shifted(held)

        strip, names = f.potentials(scaled, masses=False)
        strip = strip.withColumnsRenamed({n: f"p{n}" for n in names})
        df, _ = f._with(self.small.join(strip, ["x_part", "y_part"]), [*self.names, *(f"p{n}" for n in names)])
        cross = map_arrow(map_arrow(df, run, SUMS).repartition("block_id"), _add, SUMS).select("block_id", "values")
        by = 1.0 / (eps * f.share * (1.0 if weighted else f.n_x * f.n_y))
        return ops.numpy_map([p, self.scale, p.with_df(cross)], lambda p, s, c: p + by * s * c)

    def free(self) -> None:
        self.small.unpersist()
        self.scale.unpersist()


def sinkhorn(f: Transport, sweeps: int = 20) -> Vec:
    """Reference solution by alternating log-domain scaling: each half sweep sets one side's potential to its fixed point."""
    x = f.start()
    for _ in range(sweeps):
        x = _sweep(f, x)
    return x


def _sweep(f: Transport, x: Vec) -> Vec:
    half = concat([("u", _half_sweep(f, x, "u")), ("v", x.segment("v"))]).cut()
    whole = concat([("u", half.segment("u")), ("v", _half_sweep(f, half, "v"))]).cut()
    half.unpersist()
    return whole


def _half_sweep(f: Transport, x: Vec, side: str) -> Vec:
    read, eps, rows = f._tile(), f.eps, side == "u"
    n, n_other = (f.n_x, f.n_y) if rows else (f.n_y, f.n_x)

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                p, q, chunks, (u, v, *m) = read(batch, i)
                top, total = np.full(len(u if rows else v), -np.inf), np.zeros(len(u if rows else v))
                for r, s, c, taken in chunks:
                    if not rows:
                        r, s, c, taken = s, r, c.T, taken if taken is None else taken.T
                    z = ((v if rows else u)[None, s] - c) / eps
                    z = z if taken is None else np.where(taken > 0, z, -np.inf)
                    mass = m[1 if rows else 0][s] if m else np.full(z.shape[1], 1.0 / n_other)
                    new = np.maximum(top[r], z.max(1))
                    near = np.where(np.isfinite(new), new, 0.0)
                    total[r] = total[r] * np.exp(top[r] - near) + (np.exp(z - near[:, None]) * mass[None, :]).sum(1)
                    top[r] = new
                yield pa.RecordBatch.from_arrays([pa.array([p if rows else q], pa.int32()), pa.array([top], pa.list_(pa.float64())), pa.array([total], pa.list_(pa.float64()))], names=["part", "top", "total"])

    df, _ = f._attached(x)
    tiles = map_arrow(df, run, "part int, top array<double>, total array<double>")
    each = tiles.select("part", F.posexplode(F.arrays_zip("top", "total")).alias("p", "r")).select("part", "p", "r.top", "r.total").where("top > double('-Infinity')")
    peak = each.groupBy("part", "p").agg(F.max("top").alias("peak"), F.collect_list(F.struct("top", "total")).alias("all"))
    lse = F.col("peak") + F.log(F.aggregate("all", F.lit(0.0), lambda acc, s: acc + s["total"] * F.exp(s["top"] - F.col("peak"))))
    points = f.size * (f.x_wide if rows else f.y_wide)
    long = peak.select((F.col("part").cast("long") * points + F.col("p")).alias("idx"), (-eps * (lse - math.log(f.share))).alias("value"))
    return from_long(long, n, f.size)


def sampled(f: Transport, fraction: float, seed: int = 1) -> Transport:
    """The same dual over a hash sample of pairs of blocks, sums rescaled: what an earlier stochastic method sees of the cost matrix."""
    import copy

    part = copy.copy(f)
    part.sample = sample = (int(fraction * 10_000), seed)
    x_wide, y_wide, x_parts, y_parts = f.x_wide, f.y_wide, f.first_v, f.y_parts

    def count(batches):
        for b in batches:
            for p, q in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                at = [np.arange(k * wide, min((k + 1) * wide, n)) for k, wide, n in ((p, x_wide, x_parts), (q, y_wide, y_parts))]
                yield pa.RecordBatch.from_arrays([pa.array([int(chosen(*at, *sample).sum())], pa.int64())], names=["n"])

    share = map_arrow(f.tiles.select("x_part", "y_part"), count, "n bigint").agg(F.sum("n")).first()[0] / (x_parts * y_parts)

    class Scaled(Transport):
        def _sums(self, x):
            return super()._sums(x).withColumn("values", F.transform("values", lambda z: z / share))

    part.__class__, part.share = Scaled, share
    return part


def sorted_coupling(x: DataFrame, y: DataFrame, key: str, value: str) -> DataFrame:
    """(x_pos, y_pos, mass, cost): the optimal plan between points on a line with uniform masses and squared distances. Points
    are paired in order: position i of n holds the quantiles i/n to (i+1)/n, and overlapping stretches are matched. Positions count
    by (value, key); stretches meet on the whole parts of their ends, so nothing is compared with all of the other side."""
    sides = []
    for name, df in (("x", x), ("y", y)):
        order = F.struct(F.col(value).cast("double").alias("v"), F.col(key).alias("k"))
        sides.append(numbered(df.select(order.alias("o")), "o", "pos").select(F.col("pos").alias(f"{name}_pos"), F.col("o.v").alias(f"{name}_value")))
    a, b = sides
    n, m = a.count(), b.count()
    # in units of 1 / (n m): x_pos holds [x_pos m, x_pos m + m), y_pos holds [y_pos n, y_pos n + n); both meet in cells of max(n, m)
    wide = max(n, m)
    cells = lambda name, width: F.explode(F.sequence(F.floor(F.col(f"{name}_pos") * width / wide).cast("long"), F.floor((F.col(f"{name}_pos") * width + width - 1) / wide).cast("long")))
    met = a.withColumn("cell", cells("x", m)).join(b.withColumn("cell", cells("y", n)), "cell")
    low, high = F.greatest(F.col("x_pos") * m, F.col("y_pos") * n), F.least(F.col("x_pos") * m + m, F.col("y_pos") * n + n)
    met = met.where((low < high) & (F.floor(low / wide).cast("long") == F.col("cell")))  # in the first cell of the overlap only
    return met.select("x_pos", "y_pos", ((high - low) / F.lit(float(n * m))).alias("mass"), ((F.col("x_value") - F.col("y_value")) * (F.col("x_value") - F.col("y_value"))).alias("cost"))
