"""The vector handle and its constructors. A Vec never reaches the driver; ``to_long`` gives its elements as rows."""

from __future__ import annotations

from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import dataclass, field, replace
from uuid import uuid4

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin.session import shared_base
from gridmin.vectors import layout


#: 2-norms of cut vectors, by path, where whatever wrote them has found them; and how many vectors are still in use of those written together.
KNOWN: dict[str, float] = {}
_SHARED: dict[str, int] = {}


@dataclass(frozen=True)
class Vec:
    """``stack`` rows of ``length`` elements in blocks of ``block_size``: a block holds stack x block elements, row after row."""

    df: DataFrame
    length: int
    block_size: int = layout.BLOCK
    stack: int = 1
    dtype: str = "double"
    segments: tuple[tuple[str, int, int], ...] = field(default=())
    path: str | None = None
    table: str | None = None

    def with_df(self, df: DataFrame) -> "Vec":
        return replace(self, df=df, path=None, table=None)

    def to_long(self) -> DataFrame:
        """(idx, value), or (row, idx, value) for a stack."""
        width = layout.block_length(F.col("block_id"), self.length, self.block_size)
        rows = self.df.select("block_id", width.alias("w"), F.posexplode("values").alias("p", "value"))
        idx = layout.join(F.col("block_id"), F.col("p") % F.col("w"), self.block_size).alias("idx")
        if self.stack == 1:
            return rows.select(idx, F.col("value").cast("double").alias("value"))
        return rows.select(F.floor(F.col("p") / F.col("w")).cast("int").alias("row"), idx, F.col("value").cast("double").alias("value"))

    def row(self, k: int) -> "Vec":
        """Row k of a stack as a dense vector."""
        width = layout.block_length(F.col("block_id"), self.length, self.block_size)
        return replace(self, df=self.df.select("block_id", F.slice("values", F.lit(k) * width + 1, width).alias("values")), stack=1, path=None, table=None)

    def as_stacked(self, k: int) -> "Vec":
        """A dense vector of k x m elements seen as k rows of m."""
        m = self.length // k
        if m * k != self.length:
            raise ValueError("length is not divisible by the number of rows")
        rows = self.to_long().select(F.floor(F.col("idx") / m).cast("int").alias("row"), (F.col("idx") % m).alias("idx"), "value")
        return from_long(rows, m, self.block_size, stack=k, dtype=self.dtype)

    def as_dense(self) -> "Vec":
        """A stack laid out row after row as one dense vector."""
        if self.stack == 1:
            return self
        rows = self.to_long().select((F.col("row").cast("long") * self.length + F.col("idx")).alias("idx"), "value")
        return from_long(rows, self.length * self.stack, self.block_size, dtype=self.dtype)

    def segment(self, name: str) -> "Vec":
        """A named part of a concatenation; a filter on block numbers, nothing moves."""
        first, length = next((f, n) for s, f, n in self.segments if s == name)
        last = first + layout.n_blocks(length, self.block_size)
        part = self.df.where((F.col("block_id") >= first) & (F.col("block_id") < last)).select((F.col("block_id") - first).cast("int").alias("block_id"), "values")
        return replace(self, df=part, length=length, segments=(), path=None, table=None)

    def persist(self, level: StorageLevel = StorageLevel.MEMORY_AND_DISK) -> "Vec":
        self.df.persist(level)
        return self

    def unpersist(self) -> "Vec":
        """Frees the cache, or the files of a vector that ``cut`` has written."""
        if self.path:
            KNOWN.pop(self.path, None)
            if _SHARED.get(self.path, 1) > 1:
                _SHARED[self.path] -= 1
                return self
            _SHARED.pop(self.path, None)
            spark = self.df.sparkSession
            if self.table:
                spark.sql(f"drop table if exists {self.table}")
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        else:
            self.df.unpersist()
        return self

    def materialise(self) -> "Vec":
        self.persist().df.count()
        return self

    def cut(self, mode: str = "auto") -> "Vec":
        """Lineage cut; all of them survive lost executors and write to the shared folder. ``table``: files bucketed by block, read
        back as a table: equally laid out vectors and cells meet without an exchange. ``files``: Parquet without buckets.
        ``auto``: a table, unless the vector is so small that joins broadcast it anyway. ``checkpoint``: an RDD checkpoint."""
        spark = self.df.sparkSession
        if mode == "auto":
            small = spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
            mode = "table" if 8 * self.length * self.stack > small else "files"
        if mode == "table":
            name = f"gridmin_{uuid4().hex}"
            n, path = layout.buckets(spark, layout.n_blocks(self.length, self.block_size)), f"{shared_dir(spark)}/{name}"
            self.df.repartition(n, "block_id").write.option("path", path).bucketBy(n, "block_id").saveAsTable(name)
            return replace(self, df=spark.table(name), path=path, table=name)
        if mode == "checkpoint":
            return self.with_df(checkpointed(self.df))
        path, schema = f"{shared_dir(spark)}/vec-{uuid4().hex}", self.df.schema
        self.df.write.parquet(path)
        return replace(self, df=spark.read.schema(schema).parquet(path), path=path)


def together(v: Vec, n: int) -> list[Vec]:
    """The vectors in columns v0, v1, ... of files written at once; the files go with the last of them."""
    _SHARED[v.path] = n
    return [replace(v, df=v.df.select("block_id", F.col(f"v{j}").alias("values"))) for j in range(n)]


def shared_dir(spark: SparkSession) -> str:
    """A folder that driver and executors share."""
    return f"{shared_base(spark)}/vectors-{spark.sparkContext.applicationId}"


def checkpointed(df: DataFrame) -> DataFrame:
    """df.checkpoint() in the shared folder."""
    spark = df.sparkSession
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(f"{shared_base(spark)}/checkpoints")
    return df.checkpoint()


@contextmanager
def cached(*vectors: Vec):
    """Persist for a block of code; freed on errors too."""
    try:
        yield [v.persist() for v in vectors]
    finally:
        for v in vectors:
            v.unpersist()


def _blocks(spark: SparkSession, length: int, block_size: int) -> DataFrame:
    n = layout.n_blocks(length, block_size)
    return spark.range(n, numPartitions=max(1, min(n, int(spark.conf.get("spark.sql.shuffle.partitions"))))).select(F.col("id").cast("int").alias("block_id"))


def from_expr(spark: SparkSession, length: int, fn: Callable[[Column, Column], Column], block_size: int = layout.BLOCK, stack: int = 1, dtype: str = "double") -> Vec:
    """Element (row, idx) is ``fn(row, idx)``; no exchange."""
    width = layout.block_length(F.col("block_id"), length, block_size)
    start = F.col("block_id").cast("long") * block_size
    values = F.transform(F.sequence(F.lit(0).cast("long"), width * stack - 1), lambda p: fn(F.floor(p / width).cast("int"), start + p % width).cast(dtype))
    return Vec(_blocks(spark, length, block_size).select("block_id", values.alias("values")), length, block_size, stack, dtype)


def fill(spark: SparkSession, length: int, value: float, block_size: int = layout.BLOCK, stack: int = 1, dtype: str = "double") -> Vec:
    width = layout.block_length(F.col("block_id"), length, block_size)
    return Vec(_blocks(spark, length, block_size).select("block_id", F.array_repeat(F.lit(value).cast(dtype), width * stack).alias("values")), length, block_size, stack, dtype)


def zeros(spark: SparkSession, length: int, block_size: int = layout.BLOCK, stack: int = 1, dtype: str = "double") -> Vec:
    return fill(spark, length, 0.0, block_size, stack, dtype)


def hashed_unit(*parts: Column) -> Column:
    """A number in [0, 1) from the md5 of the joined parts: the same in every engine and every retry."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]).cast("binary")), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def uniform(spark: SparkSession, length: int, seed: int, low: float = -1.0, high: float = 1.0, block_size: int = layout.BLOCK, stack: int = 1) -> Vec:
    """Hash-uniform elements in [low, high)."""
    return from_expr(spark, length, lambda row, idx: low + (high - low) * hashed_unit(F.lit(seed), row, idx), block_size, stack)


def from_long(df: DataFrame, length: int, block_size: int = layout.BLOCK, idx: str = "idx", value: str = "value", stack: int = 1, dtype: str = "double") -> Vec:
    """From rows (idx, value) or (row, idx, value); missing elements are 0, repeated ones an error. One exchange by block."""
    layout.require_schema(df, idx, value)
    block, offset = layout.split(F.col(idx), block_size)
    width = layout.block_length(block, length, block_size)
    row = F.col("row") if stack > 1 else F.lit(0)
    placed = df.select(block.alias("block_id"), (row * width + offset).cast("int").alias("p"), F.col(value).cast(dtype).alias("v"))
    listed = placed.groupBy("block_id").agg(F.map_from_entries(F.collect_list(F.struct("p", "v"))).alias("m"))
    every = _blocks(df.sparkSession, length, block_size).join(listed, "block_id", "left")
    size = layout.block_length(F.col("block_id"), length, block_size) * stack
    empty = F.array_repeat(F.lit(0.0).cast(dtype), size)
    got = F.transform(F.sequence(F.lit(0), size - 1), lambda p: F.coalesce(F.col("m")[p], F.lit(0.0).cast(dtype)))
    return Vec(every.select("block_id", F.when(F.col("m").isNull(), empty).otherwise(got).alias("values")), length, block_size, stack, dtype)


def stack(vectors: list[Vec]) -> Vec:
    """Equal-length dense vectors as the rows of one stack."""
    df = vectors[0].df.withColumnRenamed("values", "v0")
    for k, v in enumerate(vectors[1:], 1):
        df = df.join(v.df.withColumnRenamed("values", f"v{k}"), "block_id")
    return replace(vectors[0], df=df.select("block_id", F.concat(*[f"v{k}" for k in range(len(vectors))]).alias("values")), stack=len(vectors), path=None, table=None)


def concat(vectors: list[tuple[str, Vec]]) -> Vec:
    """Named parts one after another, each starting on a block of its own."""
    first, out, segments = 0, None, []
    for name, v in vectors:
        part = v.df.select((F.col("block_id") + first).cast("int").alias("block_id"), "values")
        out = part if out is None else out.unionByName(part)
        segments.append((name, first, v.length))
        first += layout.n_blocks(v.length, v.block_size)
    last = vectors[-1][1]
    return Vec(out, (first - layout.n_blocks(last.length, last.block_size)) * last.block_size + last.length, last.block_size, 1, last.dtype, tuple(segments))
