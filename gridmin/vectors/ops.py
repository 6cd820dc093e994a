"""Operations on vectors. Operands that are partitioned alike meet without an exchange; sums over blocks are two-phase."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmin.session import map_arrow
from gridmin.vectors import layout
from gridmin.vectors.vec import KNOWN, Vec, together

Pair = Callable[[Column, Column], Column]


def _check(*vectors: Vec) -> None:
    if len({(v.length, v.block_size, v.stack) for v in vectors}) > 1:
        raise ValueError("vectors differ in layout: " + str([(v.length, v.block_size, v.stack) for v in vectors]))


def wide(vectors: list[Vec]) -> DataFrame:
    """(block_id, v0, v1, ...): joined by block. Large vectors that were cut meet without an exchange; others move once."""
    df = vectors[0].df.withColumnRenamed("values", "v0")
    for k, v in enumerate(vectors[1:], 1):
        df = df.join(v.df.withColumnRenamed("values", f"v{k}"), "block_id")
    return df


def zip_map(a: Vec, b: Vec, fn: Pair) -> Vec:
    _check(a, b)
    if a is b or a.df is b.df:
        return a.with_df(a.df.select("block_id", F.transform("values", lambda x: fn(x, x)).alias("values")))
    return a.with_df(wide([a, b]).select("block_id", F.zip_with("v0", "v1", fn).alias("values")))


def add(a: Vec, b: Vec) -> Vec:
    return zip_map(a, b, lambda x, y: x + y)


def sub(a: Vec, b: Vec) -> Vec:
    return zip_map(a, b, lambda x, y: x - y)


def mul(a: Vec, b: Vec) -> Vec:
    return zip_map(a, b, lambda x, y: x * y)


def div(a: Vec, b: Vec, div_zero: str = "error") -> Vec:
    """Division by zero raises (ANSI mode), or gives NaN with ``div_zero='nan'``."""
    if div_zero == "nan":
        return zip_map(a, b, lambda x, y: F.when(y == 0, F.lit(float("nan"))).otherwise(F.try_divide(x, y)))
    return zip_map(a, b, lambda x, y: x / y)


def apply(a: Vec, fn: Callable[[Column], Column]) -> Vec:
    return a.with_df(a.df.select("block_id", F.transform("values", fn).alias("values")))


def scale(a: Vec, c: float) -> Vec:
    return apply(a, lambda x: x * F.lit(float(c)))


def shift(a: Vec, c: float) -> Vec:
    return apply(a, lambda x: x + F.lit(float(c)))


def rsub(c: float, a: Vec) -> Vec:
    return apply(a, lambda x: F.lit(float(c)) - x)


def rdiv(c: float, a: Vec) -> Vec:
    return apply(a, lambda x: F.lit(float(c)) / x)


def soft_threshold(a: Vec, by: float) -> Vec:
    return apply(a, lambda x: F.when(F.abs(x) < by, F.lit(0.0)).otherwise(x - F.signum(x) * by))


def sign(a: Vec) -> Vec:
    return apply(a, F.signum)


def clip(a: Vec, low: float, high: float) -> Vec:
    return apply(a, lambda x: F.greatest(F.lit(float(low)), F.least(F.lit(float(high)), x)))


def keyed_zip(a: Vec, b: Vec, fn: Callable[[Column, Column, Column], Column], key: Callable[[Column], Column] = lambda i: i) -> Vec:
    """Element i becomes fn(key(i), a_i, b_i)."""
    _check(a, b)
    start = F.col("block_id").cast("long") * a.block_size
    width = layout.block_length(F.col("block_id"), a.length, a.block_size)
    pairs = F.arrays_zip(F.col("v0").alias("x"), F.col("v1").alias("y"))
    return a.with_df(wide([a, b]).select("block_id", F.transform(pairs, lambda s, i: fn(key(start + i % width), s["x"], s["y"])).alias("values")))


def _total(values: Column, fn: Callable[[Column], Column]) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + fn(x))


def dot(a: Vec, b: Vec) -> float:
    return float(dot_df(a, b).first()[0] or 0.0)


def dot_df(a: Vec, b: Vec) -> DataFrame:
    _check(a, b)
    if a.df is b.df:
        return a.df.select(F.sum(_total(F.col("values"), lambda x: x.cast("double") * x)).alias("dot"))
    return wide([a, b]).select(F.sum(_total(F.zip_with("v0", "v1", lambda x, y: x.cast("double") * y), lambda x: x)).alias("dot"))


def norm(a: Vec, p: float = 2) -> float:
    """p-norm, p >= 1 or infinity; scaled by the largest element where powers overflow or vanish."""
    if p < 1:
        raise ValueError("p must be at least 1")
    if p == 2 and a.path in KNOWN:
        return KNOWN[a.path]
    largest = F.max(F.array_max(F.transform("values", lambda x: F.abs(x.cast("double")))))
    power = lambda x, by: F.pow(F.abs(x.cast("double")) / by, F.lit(float(p)))
    if p == float("inf"):
        return float(a.df.select(largest).first()[0] or 0.0)
    top, total = a.df.select(largest, F.sum(_total(F.col("values"), lambda x: power(x, 1.0)))).first()
    if not top or not np.isfinite(top):
        return float(top or 0.0)
    if 1e-280 < total < float("inf"):
        return float(total ** (1.0 / p))
    total = a.df.select(F.sum(_total(F.col("values"), lambda x: power(x, top)))).first()[0]
    return float(top * total ** (1.0 / p))


def nnz(a: Vec) -> int:
    return int(a.df.select(F.sum(F.size(F.filter("values", lambda x: x != 0)))).first()[0] or 0)


def tree_sum(df: DataFrame, keys: list[str], value: str, depth: int = 2, fan: int = 64) -> DataFrame:
    """Sum by ``keys`` in ``depth`` rounds: salted sums first, so that a hot key never meets in one task at once."""
    salted = df.withColumn("_salt", F.pmod(F.spark_partition_id(), F.lit(fan ** (depth - 1))))
    for _ in range(depth - 1):
        salted = salted.groupBy(*keys, "_salt").agg(F.sum(value).alias(value)).withColumn("_salt", F.floor(F.col("_salt") / fan))
    return salted.groupBy(*keys).agg(F.sum(value).alias(value))


def numpy_map(vectors: list[Vec], fn: Callable[..., np.ndarray]) -> Vec:
    """One fused pass: ``fn`` gets the operands' blocks as arrays and gives the new block."""
    _check(*vectors)
    k = len(vectors)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, out = b.column(0), []
            for i in range(b.num_rows):
                out.append(fn(*[b.column(1 + j)[i].values.to_numpy(zero_copy_only=False) for j in range(k)]))
            yield pa.RecordBatch.from_arrays([ids, pa.array(out, pa.list_(pa.float64()))], names=["block_id", "values"])

    joined = wide(vectors).select("block_id", *[F.col(f"v{j}").cast("array<double>").alias(f"v{j}") for j in range(k)])
    return vectors[0].with_df(map_arrow(joined, run, layout.DENSE))


def numpy_maps(vectors: list[Vec], fn: Callable[..., tuple], mode: str = "auto") -> list[Vec]:
    """As ``numpy_map``, for an ``fn`` that gives several blocks: vectors cut to files together, in one pass."""
    _check(*vectors)
    k, a = len(vectors), vectors[0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [fn(*[b.column(1 + j)[i].values.to_numpy(zero_copy_only=False) for j in range(k)]) for i in range(b.num_rows)]
            if got:
                columns = [pa.array(list(c), pa.list_(pa.float64())) for c in zip(*got)]
                yield pa.RecordBatch.from_arrays([b.column(0), *columns], names=["block_id", *[f"v{j}" for j in range(len(columns))]])

    outs = len(fn(*[np.zeros(1)] * k))
    joined = wide(vectors).select("block_id", *[F.col(f"v{j}").cast("array<double>").alias(f"v{j}") for j in range(k)])
    schema = "block_id int, " + ", ".join(f"v{j} array<double>" for j in range(outs))
    return together(a.with_df(map_arrow(joined, run, schema)).cut(mode), outs)


def lincomb(coefs: list[float], vectors: list[Vec]) -> Vec:
    """Sum of coefs[i] * vectors[i] in one pass."""
    c = [float(x) for x in coefs]
    return numpy_map(vectors, lambda *blocks: sum(x * b for x, b in zip(c, blocks)))


def gram(vectors: list[Vec]) -> np.ndarray:
    """All dot products of a few vectors in one job; a (n, n) array of numbers comes back, no vector does."""
    _check(*vectors)
    n = len(vectors)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n, n))
        for b in batches:
            for i in range(b.num_rows):
                m = np.stack([b.column(j)[i].values.to_numpy(zero_copy_only=False) for j in range(n)])
                total += m @ m.T
        yield pa.RecordBatch.from_arrays([pa.array(range(n * n), pa.int32()), pa.array(total.reshape(-1))], names=["k", "v"])

    rows = map_arrow(wide(vectors).select(*[F.col(f"v{j}").cast("array<double>") for j in range(n)]), run, "k int, v double")
    got = {r["k"]: r["v"] for r in rows.groupBy("k").agg(F.sum("v").alias("v")).collect()}
    return np.array([got.get(k, 0.0) for k in range(n * n)]).reshape(n, n)
