"""The grid that joins parts of the examples with parts (blocks) of the parameters.

A cell holds the sub-matrix of one example part and one feature block in compressed rows; examples without a feature in the
block have no row there. Cells are laid out once and never move again: by (example part, block), or by block beside the
vectors' own buckets for the stationary strategy. What moves in an evaluation are weights (or, stationary, only partial scores)
and, on the way back, the derivatives of an example to just the cells in which it has features. ``choose`` picks the
strategy that moves the fewest bytes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmin.session import map_arrow, ship
from gridmin.vectors import layout
from gridmin.vectors.vec import Vec

CELL = "ex_part int, feat_part int, ex_ids array<bigint>, indptr array<int>, local_ids array<int>, vals array<double>"
MAX_BROADCAST = 256 << 20


#: Examples in a part of the grid, at most about; a cell and the derivatives it is sent are one row each.
EXAMPLES_A_PART = 1 << 17


def example_parts(examples: DataFrame, least: int) -> int:
    """``least`` example parts, more where there are many examples."""
    return example_parts_of(examples.count(), least)


def example_parts_of(examples: int, least: int) -> int:
    return max(least, -(-examples // EXAMPLES_A_PART))


def example_part(example_id: Column, ex_parts: int) -> Column:
    return F.pmod(F.xxhash64(example_id), F.lit(ex_parts)).cast("int")


def clean_features(features: DataFrame, length: int, on_null: str = "error", on_unseen: str = "error") -> DataFrame:
    """(example_id, feature_id, value) with duplicates summed and zeros gone; nulls, non-finite values and ids outside the
    model raise, or go with ``drop``."""
    bad = F.col("feature_id").isNull() | F.col("value").isNull() | F.isnan("value") | (F.abs("value") == float("inf"))
    out = F.col("feature_id").isNotNull() & ((F.col("feature_id") < 0) | (F.col("feature_id") >= length))
    df = features.select("example_id", "feature_id", F.col("value").cast("double").alias("value"))
    df = df.where(~bad) if on_null == "drop" else df.where(F.when(bad, F.raise_error(F.lit("null or non-finite feature"))).otherwise(F.lit(True)))
    df = df.where(~out) if on_unseen == "drop" else df.where(F.when(out, F.raise_error(F.lit("feature outside the model"))).otherwise(F.lit(True)))
    return df.groupBy("example_id", "feature_id").agg(F.sum("value").alias("value")).where("value <> 0")


def build_cells(features: DataFrame, ex_parts: int, block_size: int) -> DataFrame:
    """Cells from long features, laid out by (ex_part, feat_part): one exchange of the features, once a batch, and one of the
    finished cells. Persist the result to keep that layout. Repeated (example, feature) rows are summed, zeros dropped."""
    ship(features.sparkSession)
    block, local = layout.split(F.col("feature_id"), block_size)
    placed = features.select(example_part(F.col("example_id"), ex_parts).alias("ex_part"), block.alias("feat_part"), F.col("example_id").cast("long").alias("example_id"), local.alias("local_id"), F.col("value").cast("double").alias("value"))
    n = int(features.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return placed.groupBy("ex_part", "feat_part").applyInArrow(_csr, CELL).repartition(n, "ex_part", "feat_part")


def _csr(t: pa.Table) -> pa.Table:
    e, c, v = (t.column(k).to_numpy() for k in ("example_id", "local_id", "value"))
    by = np.lexsort((c, e))
    e, c, v = e[by], c[by], v[by]
    first = np.flatnonzero(np.concatenate([[True], (e[1:] != e[:-1]) | (c[1:] != c[:-1])]))
    v, e, c = np.add.reduceat(v, first), e[first], c[first]
    keep = v != 0
    v, e, c = v[keep], e[keep], c[keep]
    ids, start = np.unique(e, return_index=True)
    ptr = np.append(start, len(e)).astype(np.int32)
    one = lambda x, kind: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x, kind))
    return pa.table({"ex_part": pa.array([t.column("ex_part")[0].as_py()], pa.int32()), "feat_part": pa.array([t.column("feat_part")[0].as_py()], pa.int32()),
                     "ex_ids": one(ids, pa.int64()), "indptr": one(ptr, pa.int32()), "local_ids": one(c, pa.int32()), "vals": one(v, pa.float64())})


def routes(cells: DataFrame) -> DataFrame:
    """(example_id, feat_part): the blocks in which an example has features."""
    return cells.select(F.explode("ex_ids").alias("example_id"), "feat_part")


@dataclass(frozen=True)
class Stats:
    """Sizes that decide the exchange: parameters, score rows k, example and feature parts, non-empty (example, block) and
    (example part, feature) pairs, executors."""

    e: int
    k: int
    ex_parts: int
    feat_parts: int
    routes: int
    gathers: int
    executors: int = 1
    cores: int = 1


def stats(cells: DataFrame, w: Vec, ex_parts: int) -> Stats:
    r = cells.agg(F.sum(F.size("ex_ids")), F.sum(F.size(F.array_distinct("local_ids"))), F.countDistinct("feat_part")).first()
    executors = max(1, cells.sparkSession.sparkContext._jsc.sc().getExecutorMemoryStatus().size() - 1)
    return Stats(w.length, w.stack, ex_parts, r[2] or 0, r[0] or 0, r[1] or 0, executors, cells.sparkSession.sparkContext.defaultParallelism)


def costs(s: Stats) -> dict[str, float]:
    """Bytes moved by one evaluation under each strategy: weights, as far as they move, and, alike for all, partial scores to the
    examples and derivatives back to the cells. Cells never move, once they are laid out."""
    row = 8 + 8 * s.k
    both = 2.0 * s.routes * row
    return {
        "replicate": s.ex_parts * s.e * s.k * 8.0 + both,
        "stationary": both,
        "gather": s.gathers * (8.0 + row) + both,
        "broadcast": s.e * s.k * 8.0 * s.executors + both if s.e * s.k * 8 <= MAX_BROADCAST else float("inf"),
    }


def choose(s: Stats) -> str:
    c = costs(s)
    feasible = {k: v for k, v in c.items() if k != "stationary" or s.feat_parts >= max(2, s.cores)}  # beside few blocks, few tasks would work
    return min(feasible, key=feasible.get)


class CellGrid:
    """Cells, persisted by (ex_part, feat_part), with the strategy that brings weights to them (None: the cheapest, by ``choose``)."""

    def __init__(self, cells: DataFrame, ex_parts: int, strategy: str | None = None):
        self.cells, self.ex_parts, self.strategy = cells, ex_parts, strategy
        self._by_block: dict[int, DataFrame] = {}
        self._routes: DataFrame | None = None
        self._chosen: dict[tuple, str] = {}

    def strategy_for(self, w: Vec) -> str:
        key = (w.length, w.stack, w.block_size)
        if self.strategy is None and key not in self._chosen:
            self._chosen[key] = choose(stats(self.cells, w, self.ex_parts))
        return self.strategy or self._chosen[key]

    def by_block(self, w: Vec) -> DataFrame:
        """The cells beside the buckets of vectors laid out like ``w``; made once."""
        n = layout.buckets(self.cells.sparkSession, layout.n_blocks(w.length, w.block_size))
        if n not in self._by_block:
            self._by_block[n] = self.cells.repartition(n, "feat_part").persist()
        return self._by_block[n]

    def attach(self, w: Vec, name: str = "w", to: DataFrame | None = None) -> DataFrame:
        """Cells (or ``to``, cells that already carry something) with the weight block they need as column ``name``."""
        strategy = self.strategy_for(w)
        return attach(to if to is not None else self.by_block(w) if strategy == "stationary" else self.cells, w, strategy, name)

    def routes(self) -> DataFrame:
        """(example_id, feat_parts), persisted: the blocks in which an example has features."""
        if self._routes is None:
            self._routes = routes(self.cells).groupBy("example_id").agg(F.collect_list("feat_part").alias("feat_parts")).persist()
        return self._routes

    def back(self, pulled: DataFrame, width: int, kernel: Callable[..., np.ndarray], w: Vec, rows: int) -> DataFrame:
        """(block_id, values): sum over cells of ``kernel(entry_rows, ids, vals, d, size)``; ``pulled``: (example_id, d of ``width``)."""
        d = pulled.join(self.routes(), "example_id").select(example_part(F.col("example_id"), self.ex_parts).alias("d_ex"), F.explode("feat_parts").alias("d_feat"), "example_id", "d")
        listed = F.sort_array(F.collect_list(F.struct("example_id", "d"))).alias("r")
        beside = self.strategy_for(w) == "stationary"
        if beside:  # buckets are by block alone, so the example part is no key of the join
            cells = self.by_block(w)
            d = d.repartition(layout.buckets(cells.sparkSession, layout.n_blocks(w.length, w.block_size)), "d_feat")
            on = (F.col("feat_part") == F.col("d_feat")) & (F.col("ex_part") - F.col("d_ex") == 0)
        else:
            cells, on = self.cells, (F.col("ex_part") == F.col("d_ex")) & (F.col("feat_part") == F.col("d_feat"))
        by_cell = d.groupBy("d_ex", "d_feat").agg(listed).select("d_ex", "d_feat", F.col("r.example_id").alias("d_ids"), F.flatten("r.d").alias("d"))
        return sum_blocks(_pull(cells.join(by_cell, on), width, kernel, w, rows))

    def free(self) -> None:
        for df in (self.cells, self._routes, *self._by_block.values()):
            if df is not None:
                df.unpersist()
        self._routes, self._by_block = None, {}


def attach(cells: DataFrame, w: Vec, strategy: str, name: str = "w") -> DataFrame:
    """Cells with the weight block they need as column ``name``; only weights move."""
    blocks = w.df.select(F.col("block_id").alias("feat_part"), F.col("values").cast("array<double>").alias(name))
    if strategy == "broadcast":
        if w.length * w.stack * 8 > MAX_BROADCAST:
            raise ValueError("weights are too large to broadcast")
        return cells.join(F.broadcast(blocks), "feat_part")
    if strategy == "replicate":
        copies = cells.select("ex_part", "feat_part").distinct()
        return cells.join(blocks.join(copies, "feat_part"), ["ex_part", "feat_part"])
    if strategy == "gather":
        return _gather(cells, w, name)
    if strategy == "stationary":
        return cells.join(blocks, "feat_part")
    raise ValueError(f"unknown strategy {strategy!r}")


def _gather(cells: DataFrame, w: Vec, name: str) -> DataFrame:
    """Each cell pulls only the elements it names: they come as (local id, k values) and are put into a block of zeros."""
    width = layout.block_length(F.col("feat_part"), w.length, w.block_size)
    named = cells.select("ex_part", "feat_part", F.explode(F.array_distinct("local_ids")).alias("p")).select("ex_part", "feat_part", F.explode(F.transform(F.sequence(F.lit(0), F.lit(w.stack - 1)), lambda r: r * width + F.col("p"))).alias("p"))
    held = w.df.select(F.col("block_id").alias("feat_part"), F.posexplode("values").alias("p", "v"))
    pulled = named.join(held, ["feat_part", "p"]).groupBy("ex_part", "feat_part").agg(F.map_from_entries(F.collect_list(F.struct("p", F.col("v").cast("double")))).alias("m"))
    filled = pulled.select("ex_part", "feat_part", F.transform(F.sequence(F.lit(0), width * w.stack - 1), lambda p: F.coalesce(F.col("m")[p], F.lit(0.0))).alias(name))
    return cells.join(filled, ["ex_part", "feat_part"])


def _arrays(b: pa.RecordBatch, i: int, *names: str) -> list[np.ndarray]:
    return [b.column(b.schema.get_field_index(n))[i].values.to_numpy(zero_copy_only=False) for n in names]


def multiply(attached: DataFrame, kernel: Callable[..., np.ndarray], outputs: int, extra: tuple[str, ...] = ("w",)) -> DataFrame:
    """(example_id, s): per cell row the ``outputs`` numbers of ``kernel(ptr, ids, vals, *extra)``, which gives (rows, outputs)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                ex, ptr, ids, vals, *more = _arrays(b, i, "ex_ids", "indptr", "local_ids", "vals", *extra)
                got = kernel(ptr, ids, vals, *more)
                flat = pa.array(np.ascontiguousarray(got).reshape(-1))
                s = pa.ListArray.from_arrays(pa.array(np.arange(len(ex) + 1) * outputs, pa.int32()), flat)
                yield pa.RecordBatch.from_arrays([pa.array(ex, pa.int64()), s], names=["example_id", "s"])

    return map_arrow(attached.select("ex_ids", "indptr", "local_ids", "vals", *extra), run, "example_id bigint, s array<double>")


def sum_arrays(df: DataFrame, key: str, column: str, width: int) -> DataFrame:
    """Element-wise sum of short arrays by key, as plain sums with partial aggregation."""
    sums = df.groupBy(key).agg(*[F.sum(F.col(column)[k]).alias(f"_{k}") for k in range(width)])
    return sums.select(key, F.array(*[f"_{k}" for k in range(width)]).alias(column))


def rows_sum(ptr: np.ndarray, per_entry: np.ndarray) -> np.ndarray:
    """Sum of entries by row of the compressed matrix (no row is empty)."""
    return np.add.reduceat(per_entry, ptr[:-1], axis=0)


def _pull(joined: DataFrame, width: int, kernel: Callable[..., np.ndarray], w: Vec, rows: int) -> DataFrame:
    """(block_id, values) partial sums, kept by block within a task before anything moves."""
    length, size = w.length, w.block_size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for i in range(b.num_rows):
                block = b.column(b.schema.get_field_index("feat_part"))[i].as_py()
                ex, ptr, ids, vals, d_ids, flat = _arrays(b, i, "ex_ids", "indptr", "local_ids", "vals", "d_ids", "d")
                at = np.searchsorted(d_ids, ex)
                have = (at < len(d_ids)) & (d_ids[np.minimum(at, len(d_ids) - 1)] == ex)
                mine = np.where(have[:, None], flat.reshape(-1, width)[np.minimum(at, len(d_ids) - 1)], 0.0)
                entry = np.repeat(np.arange(len(ex)), np.diff(ptr))
                got = kernel(entry, ids, vals, mine, min(size, length - block * size))
                held[block] = held[block] + got if block in held else got
                if len(held) * size * rows > 1 << 25:
                    yield _blocks(held)
                    held = {}
        if held:
            yield _blocks(held)

    return map_arrow(joined.select("feat_part", "ex_ids", "indptr", "local_ids", "vals", "d_ids", "d"), run, layout.DENSE)


def _blocks(held: dict[int, np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([v.reshape(-1) for v in held.values()], pa.list_(pa.float64()))], names=["block_id", "values"])


def sum_blocks(partial: DataFrame) -> DataFrame:
    """Element-wise sum of blocks by block_id: one exchange by block, then a running sum for each block of the partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for i, block in enumerate(b.column(0).to_pylist()):
                v = b.column(1)[i].values.to_numpy(zero_copy_only=False)
                held[block] = held[block] + v if block in held else v
        if held:
            yield _blocks(held)

    return map_arrow(partial.repartition("block_id"), run, layout.DENSE)


def full(df: DataFrame, like: Vec, stack: int | None = None) -> Vec:
    """A Vec of ``like``'s layout from blocks of which some may be missing (zeros)."""
    rows = stack or like.stack
    width = layout.block_length(F.col("block_id"), like.length, like.block_size)
    every = like.df.select("block_id").join(df.withColumnRenamed("values", "got"), "block_id", "left")
    return Vec(every.select("block_id", F.coalesce("got", F.array_repeat(F.lit(0.0), width * rows)).alias("values")), like.length, like.block_size, rows)


def transposed(entry: np.ndarray, ids: np.ndarray, vals: np.ndarray, d: np.ndarray, size: int) -> np.ndarray:
    """Transposed cell times d, one row for each column of d."""
    return np.stack([np.bincount(ids, weights=vals * d[entry, k], minlength=size) for k in range(d.shape[1])])


def tile_grid(u: DataFrame, v: DataFrame, u_key: str = "x_part", v_key: str = "y_part") -> DataFrame:
    """All pairs of blocks of two sides: each side is copied to the other side's parts and both meet by key, not by product."""
    us, vs = u.select(u_key).distinct(), v.select(v_key).distinct()
    left = u.join(F.broadcast(vs.agg(F.collect_list(v_key).alias("_all"))), how="cross").withColumn(v_key, F.explode("_all")).drop("_all")
    right = v.join(F.broadcast(us.agg(F.collect_list(u_key).alias("_all"))), how="cross").withColumn(u_key, F.explode("_all")).drop("_all")
    return left.join(right, [u_key, v_key])


def salt(df: DataFrame, key: str, n: int, hot: list | None = None) -> DataFrame:
    """A ``salt`` column 0 .. n-1 for hot keys (all, if none are named), else 0."""
    spread = F.pmod(F.xxhash64(*df.columns), F.lit(n)).cast("int")
    return df.withColumn("salt", spread if hot is None else F.when(F.col(key).isin(hot), spread).otherwise(0))
