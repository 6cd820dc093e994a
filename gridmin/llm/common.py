"""What several operators share: staged tables, skew-proof lookups, stable row hashes, folds, word scores."""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin import session

#: Words everywhere are maximal runs of bytes other than space and \t \n \v \f \r; bytes.split() cuts at just these.
WORD = r"[^\x20\x09-\x0D]+"

#: A key held by more than one row in HEAVY counts as heavy, so there are fewer than HEAVY heavy keys at any size.
HEAVY = 1024


_SCRATCH: list[list[str]] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; refuses machine-local ones on a cluster."""
    return f"{session.shared_base(spark)}/gridmin-{spark.sparkContext.applicationId}"


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Staged tables of the block are deleted at its end: for code that has written its result by then."""
    _SCRATCH.append([])
    try:
        yield
    finally:
        for path in _SCRATCH.pop():
            _delete(spark, path)


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def stage(df: DataFrame, what: str, codec: str = "zstd") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    schema = df.schema
    if _SCRATCH:
        _SCRATCH[-1].append(path)
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(schema).parquet(path)


def drop_staged(spark: SparkSession, df: DataFrame) -> None:
    """Delete the files of a staged table that no later plan reads."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/gridmin-" in folder:
            _delete(spark, folder)


def attach(rows: DataFrame, lookup: DataFrame, key: str, weight: str, total: int) -> DataFrame:
    """Inner join of ``rows`` to ``lookup`` (one row a key; ``weight`` says how many rows hold it), whatever the skew.

    Heavy keys (weight * HEAVY > total, so fewer than HEAVY of them) are broadcast; every other key joins by shuffle
    and no task gets more than total / HEAVY rows of one key. Both inputs should be staged: each is read twice.
    Null keys match null keys.
    """
    heavy = lookup.where(F.col(weight) * HEAVY > F.lit(total)).limit(HEAVY)
    light = lookup.where(F.col(weight) * HEAVY <= F.lit(total))
    flag = heavy.select(F.col(key).alias("_hk"))
    hot = rows.join(F.broadcast(heavy.withColumnRenamed(key, "_hk")), F.col(key).eqNullSafe(F.col("_hk"))).drop("_hk")
    cold = rows.join(F.broadcast(flag), F.col(key).eqNullSafe(F.col("_hk")), "left_anti")
    cold = cold.join(light.withColumnRenamed(key, "_lk"), F.col(key).eqNullSafe(F.col("_lk"))).drop("_lk")
    return hot.unionByName(cold)


def own_columns(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, under the operator's own names: extra columns, clashing or not, never get in."""
    return df.select(*[_named(old).alias(new) for new, old in columns.items()])


def carried(docs: DataFrame, **columns: Column | str) -> DataFrame:
    """The whole input row as one struct ``row``, beside columns under the operator's own names: nothing clashes, whatever the
    input's columns are called. ``restored`` gives the rows back."""
    return docs.select(F.struct(*[_named(c) for c in docs.columns]).alias("row"), *[(_named(c) if isinstance(c, str) else c).alias(k) for k, c in columns.items()])


def restored(df: DataFrame, columns: list[str], *more: str | Column) -> DataFrame:
    return df.select(*[F.col("row").getField(c).alias(c) for c in columns], *more)


def _named(column: str) -> Column:
    return F.col("`" + column.replace("`", "``") + "`")


def mark(text: Column) -> Column:
    """With the id, what names a row among rows that differ: a 64-bit hash of the text."""
    return F.xxhash64(text)


def keep_rows(docs: DataFrame, keepers: DataFrame, seen: DataFrame, doc_id: str, text: str) -> DataFrame:
    """The rows of ``docs`` named by ``keepers`` (doc_id, mark), each once. ``seen``: (doc_id, mark) of all rows, staged.

    Texts move once, to meet the list of rows to keep. Rows alike in id and text can't be told apart by name: where
    ``seen`` shows such rows, one of each is taken.
    """
    tied = stage(seen.groupBy("doc_id", "mark").agg(F.count("*").alias("n")).where("n > 1").select(F.col("doc_id").alias("ti"), F.col("mark").alias("tm")), "tied")
    keys = keepers.select(F.col("doc_id").alias("ki"), F.col("mark").alias("km"))
    marked = carried(docs, own_id=_named(doc_id).cast("long"), own_mark=mark(_named(text)))
    kept = marked.join(keys.hint("shuffle_hash"), F.col("own_id").eqNullSafe(F.col("ki")) & (F.col("own_mark") == F.col("km")), "left_semi")
    if not tied.isEmpty():
        on = F.col("own_id").eqNullSafe(F.col("ti")) & (F.col("own_mark") == F.col("tm"))
        single, several = kept.join(tied, on, "left_anti"), kept.join(tied, on, "left_semi")
        kept = single.select("row").unionByName(several.groupBy("own_id", "own_mark").agg(F.first("row").alias("row")).select("row"))
    return restored(kept, docs.columns)


def in_fold(doc_id: Column) -> Column:
    """True for held-out rows: crc32 of the id as text leaves 1 modulo 3. A null id is held out (it can't be learnt from)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(True))


def texts_of(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """The column as bytes; null counts as empty."""
    col = batch.column(batch.schema.get_field_index(name)).cast(pa.large_string()).cast(pa.large_binary())
    return [t or b"" for t in col.to_pylist()]


def column_of(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def to_batches(rows: Iterable[tuple], schema: pa.Schema, size: int = 8192) -> Iterator[pa.RecordBatch]:
    """Record batches of at most ``size`` rows from tuples in schema order."""
    part: list[tuple] = []
    for r in rows:
        part.append(r)
        if len(part) >= size:
            yield _batch(part, schema)
            part = []
    if part:
        yield _batch(part, schema)


def _batch(part: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    cols = list(zip(*part, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)


def arrow_schema(df_schema) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(df_schema)


def bucket_hash(data: bytes, buckets: int) -> int:
    """Stable hash of a feature, alike in every process."""
    return zlib.crc32(data) % buckets


_CACHES: list = []


def lean() -> None:
    """At the start of a task without a tokenizer: empty the caches that earlier stages left in this reused worker, and give
    free memory back."""
    import ctypes
    import gc

    for clear in _CACHES:
        clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


class WordMemo(dict):
    """word -> value, filled on first use and emptied at ``limit`` entries: a cache, never a filter."""

    def __init__(self, make, limit: int = 500_000):
        super().__init__()
        self.make, self.limit = make, limit

    def __missing__(self, word: bytes):
        if len(self) >= self.limit:
            self.clear()
        value = self[word] = self.make(word)
        return value
