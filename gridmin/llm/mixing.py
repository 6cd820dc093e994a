"""Mixing sources to target weights by capped water-filling.

The mix has ``share`` times all words. Sources get words by weight; a source that would need more than ``most_epochs`` of
itself is clamped there and its excess shared out by weight among the rest, until none is above. The fixed
point is read off one sort by cap / weight. A source's words are then drawn as whole repetitions of all its documents and a
fractional one: the first documents in seeded order whose words come nearest to what is left.

Only a plan with one row a source is made from the corpus; each document finds its repetitions from its own hash, so no
text moves. Null source: a source of its own, last. Null text: size 0. The hash is of id and text, so equal ids are drawn
apart; rows equal in both share one draw. Sources without words: target 0. Empty table: no rows. ``mix`` carries the
whole input row in a struct, so extra columns pass through whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin.llm import common
from gridmin.llm.sharding import hash_bucket, order_key

LEAST_BUCKETS, ROWS_A_BUCKET = 1024, 100_000
BROADCAST_SOURCES = 100_000


def source_key(source: Column) -> Column:
    return F.coalesce(F.concat(F.lit("="), source), F.lit(""))


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(common.WORD)), F.lit(0)).cast("long")


def plan(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most_epochs: float = 2.0) -> DataFrame:
    """One row a source from (draw, source, size), ``draw`` as from ``order_key``: source_size, target, whole repetitions, and where the fractional one ends.

    ``sizes`` is read twice and should be staged. Weights go round the sources in code point order, null last.
    """
    buckets = LEAST_BUCKETS + sizes.count() // ROWS_A_BUCKET
    keyed = sizes.select("size", "source", source_key(F.col("source")).alias("_s"), F.col("draw").alias("_k")).withColumn("_b", hash_bucket(F.col("_k"), F.lit(buckets)))
    sums = keyed.groupBy("_s", "_b").agg(F.sum("size").alias("_w"), F.first("source").alias("source"))
    totals = sums.groupBy("_s").agg(F.sum("_w").alias("source_size"), F.first("source").alias("source"))
    everyone = W.partitionBy()
    turn = (F.row_number().over(W.orderBy(F.col("source").isNull(), "source")) - 1) % len(weights)
    t = totals.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn + 1).cast("int")))
    t = t.withColumn("cap", most_epochs * F.col("source_size")).withColumn("goal", share * F.sum("source_size").over(everyone))
    rising = W.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), "source")
    t = t.withColumn("level", (F.col("goal") - (F.sum("cap").over(rising) - F.col("cap"))) / (F.sum("weight").over(everyone) - (F.sum("weight").over(rising) - F.col("weight"))))
    t = t.withColumn("full", F.col("cap") / F.col("weight") <= F.col("level"))
    t = t.withColumn("water", F.min(F.when(~F.col("full"), F.struct((F.col("cap") / F.col("weight")).alias("r"), "level"))).over(everyone)["level"])
    t = t.withColumn("target", F.when(F.col("full"), F.col("cap")).otherwise(F.col("weight") * F.col("water")))
    t = t.withColumn("whole", F.coalesce(F.floor(F.col("target") / F.nullif("source_size", F.lit(0))), F.lit(0)).cast("long"))
    t = t.withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")).select("_s", "source_size", "target", "whole", "rest")
    t = common.stage(t, "sources")
    in_source = W.partitionBy("_s").orderBy("_b")
    edges = sums.select("_s", "_b", "_w", (F.sum("_w").over(in_source) - F.col("_w")).alias("_before")).join(t, "_s")
    edges = edges.where((F.col("_before") < F.col("rest")) & (F.col("_before") + F.col("_w") >= F.col("rest"))).select(F.col("_s").alias("_es"), F.col("_b").alias("_eb"), "_before", "rest")
    near = keyed.join(edges.hint("merge"), (F.col("_s") == F.col("_es")) & (F.col("_b") == F.col("_eb")))
    tied = near.groupBy("_s", "_b", "_k", "_before", "rest").agg(F.sum("size").alias("size"))
    run = F.sum("size").over(W.partitionBy("_s").orderBy("_k").rowsBetween(W.unboundedPreceding, W.currentRow)) - F.col("size")
    last = tied.withColumn("_run", run).groupBy("_s", "_b").agg(F.max(F.when(2 * (F.col("_before") + F.col("_run")) + F.col("size") <= 2 * F.col("rest"), F.col("_k"))).alias("cut_key"))
    return common.stage(t.join(last.withColumnRenamed("_b", "cut_bucket"), "_s", "left").withColumn("buckets", F.lit(buckets)), "plan")


def sizes_of(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", seed: int = 11) -> DataFrame:
    """(doc_id, source, size, draw): one row a document."""
    own = common.own_columns(docs, doc_id=doc_id, text=text, source=source)
    return own.select("doc_id", "source", words(F.col("text")).alias("size"), order_key(seed, F.col("doc_id"), F.md5("text")).alias("draw"))


def repeats(rows: DataFrame, made: DataFrame) -> DataFrame:
    """``rows`` (source, draw, and others of the caller's own naming) with ``source_size``, ``target`` and ``n_repeats``."""
    side = F.broadcast(made) if made.count() <= BROADCAST_SOURCES else made.hint("merge")
    keyed = rows.withColumns({"_ds": source_key(F.col("source")), "_k": F.col("draw")})
    joined = keyed.join(side, F.col("_ds") == F.col("_s")).withColumn("_b", hash_bucket(F.col("_k"), F.col("buckets")))
    extra = (F.col("_b") < F.col("cut_bucket")) | ((F.col("_b") == F.col("cut_bucket")) & (F.col("_k") <= F.col("cut_key")))
    n = F.col("whole") + F.when(F.col("rest") > 0, F.coalesce(extra, F.lit(False)).cast("int")).otherwise(0)
    return joined.withColumn("n_repeats", n.cast("int")).drop("_ds", "_k", "_b", "_s", "whole", "rest", "cut_bucket", "cut_key", "buckets")


def mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", seed: int = 11, **rules) -> DataFrame:
    """The mixed corpus: each row of ``docs`` as often as the plan says, with the columns of ``docs``."""
    made = plan(common.stage(sizes_of(docs, doc_id, text, source, seed), "sizes"), **rules)
    rows = common.carried(docs, source=source, draw=order_key(seed, common._named(doc_id), F.md5(common._named(text))))
    out = repeats(rows, made).where("n_repeats > 0").withColumn("again", F.explode(F.sequence(F.lit(1), F.col("n_repeats"))))
    return common.restored(out, docs.columns)
