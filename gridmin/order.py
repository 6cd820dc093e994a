"""Global order without a global window: dense positions and running sums from ranges that are counted first."""

from __future__ import annotations

from uuid import uuid4

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin.vectors.vec import shared_dir


def ranges(df: DataFrame, *keys: Column | str) -> DataFrame:
    """``df`` in ranges of its keys, numbered by ``_range`` in key order. Range bounds are sampled, so the ranges are written once and
    read back: all later plans see the same ones."""
    spark = df.sparkSession
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    path = f"{shared_dir(spark)}/ranges-{uuid4().hex}"
    made = df.repartitionByRange(n, *keys).withColumn("_range", F.spark_partition_id())
    made.write.parquet(path)
    return spark.read.schema(made.schema).parquet(path)


def numbered(df: DataFrame, key: Column | str, name: str) -> DataFrame:
    """``df`` with dense positions from 0 in the order of ``key`` (distinct). Windows hold one range; one row a range is broadcast."""
    rows = ranges(df, key)
    sizes = rows.groupBy("_range").agg(F.count("*").alias("_n")).select("_range", (F.sum("_n").over(W.orderBy("_range")) - F.col("_n")).alias("_before"))
    place = F.col("_before") + F.row_number().over(W.partitionBy("_range").orderBy(key)) - 1
    return rows.join(F.broadcast(sizes), "_range").withColumn(name, place).drop("_range", "_before")


def running(df: DataFrame, key: Column | str, value: str, name: str) -> DataFrame:
    """``df`` with the sum of ``value`` over all rows up to and with its own, in the order of ``key`` (distinct)."""
    rows = ranges(df, key)
    sums = rows.groupBy("_range").agg(F.sum(value).alias("_n")).select("_range", (F.sum("_n").over(W.orderBy("_range")) - F.col("_n")).alias("_before"))
    total = F.col("_before") + F.sum(value).over(W.partitionBy("_range").orderBy(key).rowsBetween(W.unboundedPreceding, W.currentRow))
    return rows.join(F.broadcast(sums), "_range").withColumn(name, total).drop("_range", "_before")
