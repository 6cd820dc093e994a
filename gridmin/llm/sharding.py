"""Proportional stratified interleaving, in DataFrame functions only.

Rows are shuffled by a seeded hash within their source, ranked there, and sorted by fractional rank (2 rank - 1) / (2 n);
that order has every source in its share over any stretch, so cutting it into equal runs gives shards that all match
the mixture. Law ``rows``: shard counts are at most one apart.

Ranks come from two levels: rows per (source, hash bucket) are counted first, so a window never holds more than one bucket
of one source, however hot the source is. The order is by a hash of id and text, id, text digest and a hash of the whole
row, so reruns and other partitionings give the same result: only rows equal in every column may swap, which changes
nothing. Rows equal in id and text share a bucket. Null source: a source of its own, last. Null ids and texts hash as absent.
Empty table: no rows. The input row is carried in a struct: extra columns pass through, but for ``shard`` and ``slot``, which
replace columns of those names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin.llm import common

ROWS_A_BUCKET = 100_000
LEAST_BUCKETS = 256
#: Rows of the table of bucket starts up to which it is broadcast.
MOST_BROADCAST = 1_000_000


def order_key(seed: int, *parts: Column) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[p.cast("string") for p in parts]).cast("binary"))


def hash_bucket(key: Column, buckets: Column) -> Column:
    """Bucket 0 .. buckets - 1, ascending in the key."""
    return F.floor(F.conv(F.substring(key, 1, 8), 16, 10).cast("long") * buckets / F.lit(2.0**32)).cast("int")


def interleave(rows: DataFrame, shards: int = 8, doc_id: str = "doc_id", source: str = "source", digest: str | None = None, seed: int = 7) -> DataFrame:
    """``rows`` with ``shard`` (0 .. shards - 1) and ``slot`` (gapless from 0 in each shard). ``digest``: a hash of the text as text;
    without one, a hash of the row does."""
    total = rows.count()
    buckets = LEAST_BUCKETS + total // ROWS_A_BUCKET
    kept = [c for c in rows.columns if c not in ("shard", "slot")]
    whole = F.xxhash64(*[common._named(c) for c, kind in rows.dtypes if c in kept and "map<" not in kind])
    own = common.carried(rows.select(*[common._named(c) for c in kept]), id=doc_id, source=source, h=whole, digest=digest or whole.cast("string"))
    keyed = own.withColumns({"s": F.coalesce(F.concat(F.lit("="), "source"), F.lit("")), "k": order_key(seed, F.col("id"), F.col("digest"))}).withColumn("b", hash_bucket(F.col("k"), F.lit(buckets)))
    counts = keyed.groupBy("s", "b").agg(F.count("*").alias("c"))
    by_source = W.partitionBy("s")
    offsets = counts.select(F.col("s").alias("os"), F.col("b").alias("ob"), (F.sum("c").over(by_source.orderBy("b")) - F.col("c")).alias("before"), F.sum("c").over(by_source).alias("n"))
    in_bucket = F.row_number().over(W.partitionBy("s", "b").orderBy("k", "id", "digest", "h"))
    ranked = keyed.withColumn("r", in_bucket).join(offsets.hint("merge"), (F.col("s") == F.col("os")) & (F.col("b") == F.col("ob"))).drop("os", "ob")
    rank = F.col("before") + F.col("r")
    ranked = ranked.withColumn("f", (2 * rank - 1) / (2 * F.col("n"))).withColumn("b", F.floor(F.col("f") * buckets).cast("int")).drop("before", "r", "n", "s")
    ranked = common.stage(ranked, "ranked")
    starts = ranked.groupBy("b").agg(F.count("*").alias("c")).select("b", (F.sum("c").over(W.orderBy("b")) - F.col("c")).alias("start"))  # a row for each bucket
    starts = F.broadcast(starts) if buckets <= MOST_BROADCAST else starts.hint("merge")
    order = W.partitionBy("b").orderBy("f", F.col("source").isNull(), "source", "k", "id", "digest", "h")
    placed = ranked.withColumn("p", F.row_number().over(order) - 1).join(starts, "b").withColumn("p", F.col("start") + F.col("p"))
    shard = F.floor(F.col("p") * shards / F.lit(total or 1)).cast("int") if total * shards < 2**53 else F.expr(f"cast(p * {shards} div {total} as int)")
    placed = placed.withColumn("shard", shard)
    first = F.ceil(F.col("shard").cast("long") * total / F.lit(float(shards))).cast("long")
    return common.restored(placed, kept, "shard", (F.col("p") - first).alias("slot"))
