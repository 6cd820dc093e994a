"""Examples laid out whole: a row holds all features of a group of examples, and their labels.

For models that fit a task's memory a few times. Scores and derivatives then never leave their task: one pass over the rows gives the
value and the gradient, and only weights and summed gradients move. Rows come once, from cells and labels or from a source of whole
examples, and hold about ``ENTRIES`` non-zeros each, by feature and in few bytes. The first row of a partition leads it and is
otherwise empty: models come beside such rows alone, block after block, so that a task gets them once.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin import grid, losses
from gridmin.session import map_arrow, tidy
from gridmin.vectors import layout
from gridmin.vectors.vec import KNOWN, Vec

#: Bytes of a model at most; non-zeros in a row, about; and as many as are not worth another row.
SMALL, ENTRIES, FEW = 128 << 20, 1 << 22, 1 << 14
#: Bytes of a model above which what an evaluation leaves on disk goes before the next one; bytes of a gradient in one batch, about.
LARGE, SENT = 16 << 20, 8 << 20
#: Non-zeros that are worked on at a time, about: what they need stays in a core's cache.
CHUNK = 1 << 17
PART = "piece bigint, ex_ids binary, ptr binary, ids binary, vals binary"
ROW = "ex binary, y binary, weight binary, of binary, first bigint, gaps binary, counts binary, at binary, vals binary, levels binary, total double"
LINE = "y binary, weight binary, c0 binary, c1 binary"
VALUE = -1  # block number under which the value travels with the gradient


def _piece(ids: np.ndarray, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((h >> np.uint64(32)) % np.uint64(n)).astype(np.int64)


def _batch(columns: list[list], schema: str) -> pa.RecordBatch:
    kinds = {"bigint": pa.int64(), "binary": pa.binary(), "double": pa.float64()}
    names = [c.split() for c in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(columns, names)], names=[n for n, _ in names])


def _read(b: pa.RecordBatch, i: int, kinds: str) -> list[np.ndarray]:
    """The first columns of row i as arrays; ``kinds``: d, i or l (64, 32 and 64 bits) for each."""
    return [np.frombuffer(b.column(k)[i].as_buffer(), {"d": np.float64, "i": np.int32, "l": np.int64}[kind]) for k, kind in enumerate(kinds)]


def _shut(a: np.ndarray) -> bytes:
    """An array as compressed bytes, after a letter for its kind and its bytes before; whole numbers from 0 on in as few bytes as hold them."""
    if a.dtype.kind in "iu" and len(a) and a.min() >= 0:
        a = a.astype(np.min_scalar_type(a.max()))
    return a.dtype.char.encode() + a.nbytes.to_bytes(8, "little") + (pa.compress(a.tobytes(), "zstd", asbytes=True) if a.nbytes else b"")


def _open(b: pa.RecordBatch, name: str, i: int) -> np.ndarray:
    held = b.column(name)[i].as_buffer()
    kind, size = np.dtype(held[:1].to_pybytes().decode()), int.from_bytes(held[1:9].to_pybytes(), "little")
    return np.frombuffer(pa.decompress(held[9:], size, "zstd"), kind) if size else np.zeros(0, kind)


def _group(ex: np.ndarray, of: np.ndarray, at: np.ndarray, ids: np.ndarray, vals: np.ndarray, y_of: Callable) -> pa.RecordBatch:
    """A row from examples, the example number of each label (empty where labels are as the examples), entries (example number, feature,
    value), and what gives labels and weights from the entries by feature. Where few values differ, they are kept once and by number."""
    at = at.astype(np.min_scalar_type(max(len(ex) - 1, 0)))
    by = np.sort(ids.astype(np.int64) << 32 | np.arange(len(ids)))
    feats, by = by >> 32, by & 0xFFFFFFFF
    starts = np.flatnonzero(np.append(True, feats[1:] != feats[:-1])) if len(feats) else np.zeros(0, np.int64)
    seen, counts, at, vals = feats[starts], np.diff(np.append(starts, len(feats))), at[by], vals[by]
    first, levels = (int(seen[0]) if len(seen) else 0), np.zeros(0)
    coded = pa.array(vals).dictionary_encode()
    if len(coded.dictionary) <= min(1 << 16, len(vals) // 2):
        vals, levels = coded.indices.to_numpy(), coded.dictionary.to_numpy()
    y, weight = y_of((seen, counts, at, vals, levels))
    shut = [[_shut(a)] for a in (ex.astype(np.int64), y.astype(np.float64), weight.astype(np.float64), of, np.diff(seen, prepend=first), counts, at, vals, levels)]
    return _batch([*shut[:4], [first], *shut[4:], [float(weight.sum())]], ROW)


def _entries(b: pa.RecordBatch, i: int) -> tuple:
    """Features of a row, how many entries each has, the entries' examples and values, and the levels if values are numbers of levels."""
    seen = b.column("first")[i].as_py() + np.cumsum(_open(b, "gaps", i), dtype=np.int64)
    return seen, *(_open(b, name, i) for name in ("counts", "at", "vals", "levels"))


def _chunks(entries: tuple) -> Iterator[tuple]:
    """(features, entries' places among them, their examples, their values): a range of features, or a list of them where most have none."""
    seen, counts, at, vals, levels = entries
    ends = np.cumsum(counts, dtype=np.int64)
    cuts = np.unique([0, *(np.searchsorted(ends, np.arange(CHUNK, len(at), CHUNK)) + 1), len(seen)])
    for a, b in zip(cuts[:-1], cuts[1:]):
        mine, part = seen[a:b], slice(ends[a] - counts[a], ends[b - 1])
        dense = mine[-1] - mine[0] < 2 * len(mine)
        cols, place = (slice(mine[0], mine[-1] + 1), mine - mine[0]) if dense else (mine, np.arange(len(mine)))
        yield cols, np.repeat(place, counts[a:b]), at[part].astype(np.intp), levels[vals[part]] if len(levels) else vals[part]


def _scores(w: np.ndarray, n: int, entries: tuple) -> np.ndarray:
    s = np.zeros((len(w), n))
    for cols, place, at, vals in _chunks(entries):
        z = np.empty(len(at))
        for j, m in enumerate(w):
            s[j] += np.bincount(at, np.multiply(np.take(m[cols], place, out=z, mode="clip"), vals, out=z), n)
    return s


def _add_transposed(g: np.ndarray, d: np.ndarray, entries: tuple) -> None:
    """g += d times the row's entries; d: (k, examples)."""
    for cols, place, at, vals in _chunks(entries):
        z, width = np.empty(len(at)), place[-1] + 1
        for j in range(len(g)):
            g[j, cols] += np.bincount(place, np.multiply(np.take(d[j], at, out=z, mode="clip"), vals, out=z), width)


def led(df: DataFrame) -> DataFrame:
    """The same rows, in each partition after one that leads it, as column ``lead`` says."""
    schema = T.StructType([T.StructField("lead", T.BooleanType()), *[T.StructField(f.name, f.dataType) for f in df.schema.fields]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begun = False
        for b in batches:
            if b.num_rows and not begun:
                begun = True
                yield pa.RecordBatch.from_arrays([pa.array([True]), *[pa.nulls(1, c.type) for c in b.columns]], names=["lead", *b.schema.names])
            yield pa.RecordBatch.from_arrays([pa.array([False] * b.num_rows, pa.bool_()), *b.columns], names=["lead", *b.schema.names])

    return map_arrow(df, run, schema)


def beside(rows: DataFrame, *vectors: Vec) -> DataFrame:
    """Led rows with the blocks of whole models beside those that lead."""
    blocks = None
    for j, v in enumerate(vectors):
        mine = v.df.select(F.lit(j).alias("model"), "block_id", F.col("values").cast("array<double>").alias("values"))
        blocks = mine if blocks is None else blocks.unionByName(mine)
    return rows.join(F.broadcast(blocks), F.col("lead"), "left")


def _following(batches: Iterator[pa.RecordBatch], models: int, like: tuple[int, int, int]) -> Iterator[tuple[list[np.ndarray], pa.RecordBatch]]:
    """The models that came with the leading rows, as (k, length) each, and the batches of the other rows."""
    length, size, k = like
    w = [np.zeros((k, length)) for _ in range(models)]
    for b in batches:
        lead = b.column("lead").to_pylist()
        for i in np.flatnonzero(lead):
            p = b.column("block_id")[i].as_py() * size
            w[b.column("model")[i].as_py()][:, p : p + size] = b.column("values")[i].values.to_numpy(zero_copy_only=False).reshape(k, -1)
        if not all(lead):
            yield w, b.filter(pa.array([not x for x in lead])) if any(lead) else b


def _layout(v: Vec) -> tuple[int, int, int]:
    return v.length, v.block_size, v.stack


def pack(source: DataFrame, read: Callable, truth: Vec, label: Callable) -> DataFrame:
    """Led rows from a source with a row for each example, which stays in its partition. ``read(batch)`` gives (example ids, entries of
    each, features, values, more), and ``label(scores of a group under truth, more)`` its labels."""
    like = _layout(truth)

    def made(w: np.ndarray, held: list[tuple]) -> pa.RecordBatch:
        ex, counts, ids, vals, more = (np.concatenate(c) for c in zip(*held))
        at, keep = np.repeat(np.arange(len(ex)), counts), vals != 0
        return _group(ex, np.zeros(0, np.int64), at[keep], ids[keep], vals[keep], lambda e: (label(_scores(w, len(ex), e), more), np.ones(len(ex))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, entries, examples = [], 0, 0
        for (w,), b in _following(batches, 1, like):
            held.append(read(b))
            entries, examples = entries + len(held[-1][2]), examples + b.num_rows
            if entries >= ENTRIES or examples >= grid.EXAMPLES_A_PART:
                yield made(w, held)
                held, entries, examples = [], 0, 0
        if held:
            yield made(w, held)

    return map_arrow(beside(led(source), truth), run, ROW)


def labels_of(rows: DataFrame) -> DataFrame:
    """(example_id, label) of packed rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                yield pa.RecordBatch.from_arrays([pa.array(_open(b, "ex", i).astype(np.int64)), pa.array(_open(b, "y", i))], names=["example_id", "label"])

    return map_arrow(rows, run, "example_id bigint, label double")


def scores_of(rows: DataFrame, w: Vec) -> DataFrame:
    """(example_id, s array of k) of packed rows."""
    like = _layout(w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (m,), b in _following(batches, 1, like):
            for i in range(b.num_rows):
                ex = _open(b, "ex", i).astype(np.int64)
                s = pa.array(np.ascontiguousarray(_scores(m, len(ex), _entries(b, i)).T).reshape(-1))
                yield pa.RecordBatch.from_arrays([pa.array(ex), pa.ListArray.from_arrays(pa.array(np.arange(len(ex) + 1) * like[2], pa.int32()), s)], names=["example_id", "s"])

    return map_arrow(beside(led(rows), w), run, "example_id bigint, s array<double>")


def _cut_cells(n: int, size: int):
    """Parts of cells by piece of the examples, with the features' own numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                first = b.column(0)[i].as_py() * size
                ex, ptr, ids, vals = (b.column(k)[i].values.to_numpy(zero_copy_only=False) for k in range(1, 5))
                at, counts = _piece(ex, n), np.diff(ptr)
                of = np.repeat(at, counts)
                for p in np.unique(at):
                    mine, entries = at == p, of == p
                    got = np.append(0, np.cumsum(counts[mine])).astype(np.int32)
                    arrays = ex[mine].astype(np.int64), got, (ids[entries] + first).astype(np.int32), vals[entries]
                    yield _batch([[int(p)], *[[a.tobytes()] for a in arrays]], PART)

    return run


def _cut_labels(n: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(_piece(b.column(0).to_numpy(zero_copy_only=False), n)), *b.columns], names=["piece", *b.schema.names])

    return run


def _together(parts: pa.Table, labels: pa.Table) -> pa.Table:
    """One row of a piece."""
    if not labels.num_rows:
        return pa.table(_batch([[] for _ in ROW.split(", ")], ROW).to_pydict(), schema=_batch([[] for _ in ROW.split(", ")], ROW).schema)
    who, y, weight = (labels.column(k).to_numpy() for k in ("example_id", "label", "weight"))
    read = lambda name, kind: [np.frombuffer(v.as_buffer(), kind) for v in parts.column(name)]
    ex, ptr = read("ex_ids", np.int64), read("ptr", np.int32)
    none = np.zeros(0)
    of = np.concatenate([np.repeat(e, np.diff(p)) for e, p in zip(ex, ptr)] or [none.astype(np.int64)])
    ids, vals = np.concatenate(read("ids", np.int32) or [none.astype(np.int32)]), np.concatenate(read("vals", np.float64) or [none])
    have, place = np.unique(who, return_inverse=True)
    if len(have) == len(who):  # else a few labels share an example
        by, place = np.argsort(who), place[:0]
        y, weight = y[by], weight[by]
    at = np.minimum(np.searchsorted(have, of), len(have) - 1)
    labelled = have[at] == of
    return pa.Table.from_batches([_group(have, place, at[labelled], ids[labelled], vals[labelled], lambda _: (y, weight))])


class WholeRows:
    """Rows of a batch, its loss, and its model's block size. ``rows`` are as ``pack`` makes them."""

    def __init__(self, rows: DataFrame, loss: losses.Loss, block_size: int):
        self.loss, self.size = loss, block_size
        self.rows = led(rows).persist()
        self.total = self.rows.agg(F.sum("total")).first()[0] or 0.0

    @classmethod
    def of_cells(cls, cells: DataFrame, labels: DataFrame, loss: losses.Loss, block_size: int) -> "WholeRows":
        spark = cells.sparkSession
        entries, examples = cells.agg(F.sum(F.size("vals"))).first()[0] or 0, labels.count()
        shuffled, cores = int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism
        n = max(1, min(4 * cores, -(-entries // FEW)), -(-entries // ENTRIES), -(-examples // grid.EXAMPLES_A_PART))
        many = min(n, max(shuffled, 2 * cores))
        parts = map_arrow(cells.select("feat_part", "ex_ids", "indptr", "local_ids", "vals"), _cut_cells(n, block_size), PART)
        marked = map_arrow(labels.select(F.col("example_id").cast("long"), F.col("label").cast("double"), "weight"), _cut_labels(n), "piece bigint, example_id bigint, label double, weight double")
        sides = [df.repartition(many, "piece").groupBy("piece") for df in (parts, marked)]
        return cls(sides[0].cogroup(sides[1]).applyInArrow(_together, ROW), loss, block_size)

    def checked(self) -> float:
        if not self.total:
            raise ValueError("the weights sum to zero")
        return self.total

    def _tidy(self, x: Vec) -> None:
        if 8 * x.length * x.stack > LARGE:
            tidy(self.rows.sparkSession)

    def evaluate(self, x: Vec) -> tuple[float, Vec]:
        like, value, slope = _layout(x), self.loss.value_of, self.loss.derivative_of
        (length, size, k), total = like, self.checked()
        self._tidy(x)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            g, v = None, 0.0
            for (w,), b in _following(batches, 1, like):
                g = np.zeros((k, length)) if g is None else g
                for i in range(b.num_rows):
                    y, weight, of, entries = _open(b, "y", i), _open(b, "weight", i), _open(b, "of", i), _entries(b, i)
                    n = len(_open(b, "ex", i))
                    s = _labelled(_scores(w, n, entries), of)
                    with np.errstate(all="ignore"):
                        v += float(weight @ value(s, y))
                        d = slope(s, y) * weight
                    _add_transposed(g, np.stack([np.bincount(of, z, n) for z in d.reshape(k, -1)]) if len(of) else d.reshape(k, -1), entries)
            if g is not None:
                yield grid._blocks({VALUE: np.array([v / total])})
                blocks, many = layout.n_blocks(length, size), max(1, SENT // (8 * k * size))
                for p in range(0, blocks, many):
                    yield grid._blocks({q: g[:, q * size : (q + 1) * size] / total for q in range(p, min(p + many, blocks))})

        both = x.with_df(grid.sum_blocks(map_arrow(beside(self.rows.drop("total"), x), run, layout.DENSE))).cut()
        grad = F.col("block_id") != VALUE
        squares = F.aggregate("values", F.lit(0.0), lambda acc, z: acc + z * z)
        got, square = both.df.agg(F.max(F.when(~grad, F.col("values")[0])), F.sum(F.when(grad, squares))).first()
        if 1e-280 < square < float("inf"):
            KNOWN[both.path] = math.sqrt(square)
        return float(got), replace(both, df=both.df.where(grad))

    def value(self, x: Vec) -> float:
        return WholeLine(self, x).at([0.0])[0][0]


def _labelled(s: np.ndarray, of: np.ndarray) -> np.ndarray:
    return s[:, of] if len(of) else s


class WholeLine:
    """The loss along a line: scores at the start and their slopes are kept, a row for a row."""

    def __init__(self, f: WholeRows, x: Vec, d: Vec | None = None):
        self.f, like = f, _layout(x)
        models = [x] if d is None else [x, d]
        many = len(models)
        f._tidy(x)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for w, b in _following(batches, many, like):
                for i in range(b.num_rows):
                    y, weight, of, entries = _open(b, "y", i), _open(b, "weight", i), _open(b, "of", i), _entries(b, i)
                    scores = [_labelled(_scores(m, len(_open(b, "ex", i)), entries), of) for m in w]
                    arrays = y, weight, scores[0], scores[1] if len(scores) > 1 else np.zeros(0)
                    yield _batch([[a.tobytes()] for a in arrays], LINE)

        self.total = f.checked()
        self.rows = map_arrow(beside(f.rows.drop("total"), *models), run, LINE)
        if d is not None:  # a value alone is read once
            self.rows.persist()

    def at(self, etas: list[float]) -> list[tuple[float, float]]:
        value, slope, steps = self.f.loss.value_of, self.f.loss.derivative_of, [float(e) for e in etas]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums = np.zeros((2, len(steps)))
            for b in batches:
                for i in range(b.num_rows):
                    y, weight, c0, c1 = _read(b, i, "dddd")
                    c0, c1 = (c.reshape(-1, len(y)) for c in (c0, c1))
                    with np.errstate(all="ignore"):
                        for n, eta in enumerate(steps):
                            s = c0 + eta * c1 if len(c1) else c0
                            sums[0, n] += weight @ value(s, y)
                            if len(c1):
                                sums[1, n] += weight @ (slope(s, y) * c1).sum(0)
            yield pa.RecordBatch.from_arrays([pa.array([r], pa.list_(pa.float64())) for r in sums], names=["v", "d"])

        got = np.sum([(r["v"], r["d"]) for r in map_arrow(self.rows, run, "v array<double>, d array<double>").collect()], axis=0)  # a row for each task
        return [(float(v) / self.total, float(d) / self.total) for v, d in got.T]

    def free(self) -> None:
        self.rows.unpersist()
