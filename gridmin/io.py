"""Reading tables and writing batches, vectors and feature files."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin.vectors.vec import Vec


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where=None) -> DataFrame:
    """A table with only the named columns; ``where`` reaches the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*columns) if columns else df


def micros(col) -> Column:
    """Microseconds since 1970 of a timestamp without zone."""
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col(col) if isinstance(col, str) else col)


def write_batches(df: DataFrame, path: str, key: str = "batch_id") -> None:
    """One folder a batch, so that a read of one batch lists one folder."""
    df.write.mode("overwrite").partitionBy(key).parquet(path)


def read_batch(spark: SparkSession, path: str, batch: int, key: str = "batch_id") -> DataFrame:
    return spark.read.parquet(path).where(F.col(key) == batch)


def write_blocks(vec: Vec, name: str, buckets: int) -> Vec:
    """A vector as a table bucketed by block: equally bucketed vectors join without an exchange."""
    vec.df.write.mode("overwrite").bucketBy(buckets, "block_id").sortBy("block_id").saveAsTable(name)
    return vec.with_df(vec.df.sparkSession.table(name))


def write_svmlight(df: DataFrame, path: str) -> None:
    """(label, indices, values) as lines 'label index:value ...'."""
    pairs = F.transform(F.arrays_zip("indices", "values"), lambda z: F.concat_ws(":", z["indices"].cast("string"), z["values"].cast("string")))
    df.select(F.concat_ws(" ", F.col("label").cast("string"), F.array_join(pairs, " ")).alias("value")).write.mode("overwrite").text(path)


def read_svmlight(spark: SparkSession, path: str) -> DataFrame:
    """(label, indices, values) from such lines."""
    parts = spark.read.text(path).select(F.split("value", " ").alias("p"))
    pairs = F.slice("p", F.lit(2), F.size("p") - 1)
    return parts.select(F.col("p")[0].cast("double").alias("label"), F.transform(pairs, lambda z: F.split(z, ":")[0].cast("int")).alias("indices"), F.transform(pairs, lambda z: F.split(z, ":")[1].cast("double")).alias("values"))
