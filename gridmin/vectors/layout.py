"""Where a vector's elements live: global index <-> (block, offset), and stable partitioning by block."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

DENSE = T.StructType([T.StructField("block_id", T.IntegerType()), T.StructField("values", T.ArrayType(T.DoubleType()))])
BLOCK = 1 << 16


def split(index: Column, block_size: int) -> tuple[Column, Column]:
    """(block, offset) of a global index."""
    return F.floor(index / block_size).cast("int"), (index % block_size).cast("int")


def join(block: Column, offset: Column, block_size: int) -> Column:
    """Global index of (block, offset)."""
    return block.cast("long") * block_size + offset


def n_blocks(length: int, block_size: int) -> int:
    return -(-length // block_size)


def buckets(spark: SparkSession, blocks: int) -> int:
    """Partitions of a vector of so many blocks: the same for all vectors of one layout, so that they meet without an exchange."""
    return max(1, min(blocks, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def block_length(block: Column, length: int, block_size: int) -> Column:
    """Elements in a block; only the last one may be short."""
    return F.least(F.lit(block_size), F.lit(length) - block.cast("long") * block_size).cast("int")


def copartition(df: DataFrame, n_parts: int, key: str = "block_id") -> DataFrame:
    """Hash-partition by block and cache, so that joins of equally partitioned vectors need no exchange."""
    return df.repartition(n_parts, key).persist()


def require_schema(df: DataFrame, *columns: str) -> None:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; got {df.columns}")
