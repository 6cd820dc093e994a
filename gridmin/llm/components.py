"""Connected components of a staged edge table by rounds of contraction, without any driver-side or single-task state."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmin.llm import common


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node with an edge; root is the least node of its component. ``edges``: (a, b) longs, staged.

    A round points each node at its least neighbour; pointers only fall, so they form trees. They are shortened by doubling until each
    leads to its root, and edges become edges between roots. Each root has a neighbour that is none, so at least half of the
    nodes go each round; the rounds end when no edge is left.
    """
    labels = None
    while not edges.isEmpty():
        both = edges.select(F.col("a").alias("v"), F.col("b").alias("u")).unionByName(edges.select(F.col("b").alias("v"), F.col("a").alias("u")))
        point = common.stage(both.groupBy("v").agg(F.min("u").alias("u")).select("v", F.least("v", "u").alias("p")), "point")
        moving = True
        while moving:
            once = _follow(point, "p", point)
            twice = _follow(once, "p", point.select("v", "p")).select(F.col("v").alias("_w"), F.col("p").alias("_q"))
            both = common.stage(point.join(twice, F.col("v") == F.col("_w")).select("v", "p", "_q"), "point")
            moving = not both.where("p <> _q").isEmpty()
            point = both.select("v", F.col("_q").alias("p"))
        named = point.select(F.col("v").alias("node"), F.col("p").alias("root"))
        labels = named if labels is None else common.stage(_relabel(labels, point), "labels")
        moved = _follow(_follow(edges, "a", point), "b", point).where("a <> b")
        edges = common.stage(moved.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    return labels if labels is not None else edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


def _follow(rows: DataFrame, column: str, point: DataFrame) -> DataFrame:
    """``rows`` with ``column`` replaced by its pointer; inner, as every node has one. Skew on ``column`` is split at run time."""
    to = point.select(F.col("v").alias("_v"), F.col("p").alias("_p"))
    return rows.join(to, F.col(column) == F.col("_v")).withColumn(column, F.col("_p")).drop("_v", "_p")


def _relabel(labels: DataFrame, point: DataFrame) -> DataFrame:
    to = point.select(F.col("v").alias("_v"), F.col("p").alias("_p"))
    return labels.join(to, F.col("root") == F.col("_v"), "left").withColumn("root", F.coalesce("_p", "root")).drop("_v", "_p")
