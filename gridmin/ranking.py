"""Ranking by factorization machines: positives, sampled negatives linked to them, and the pairwise objective."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin import grid, losses
from gridmin.objective import Machines, Objective, PlainLine
from gridmin.order import numbered, running
from gridmin.vectors import Vec, ops


def draw(*parts: Column) -> Column:
    """A number in 0 .. 2^32 - 1 from an md5 prefix: alike in every engine, retry and partitioning."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]).cast("binary")), 1, 8), 16, 10).cast("long")


class NegativeSampler:
    """``sample(positives, batch)`` gives (link, draw, item): rows linked to positives (example_id, user_id, query, item)."""

    def __init__(self, items: DataFrame, n_neg: int = 1, seed: int = 0):
        self.items, self.n_neg, self.seed = items, n_neg, seed

    def sample(self, positives: DataFrame, batch: int = 0) -> DataFrame:
        raise NotImplementedError

    def draws(self, positives: DataFrame, batch: int) -> DataFrame:
        rows = positives.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(self.n_neg))))
        return rows.withColumn("_r", draw(F.col("example_id"), F.col("draw"), F.lit(batch), F.lit(self.seed)))


def ranked(items: DataFrame, *group: str) -> DataFrame:
    """Items with dense ranks from 0 by id (within groups)."""
    if not group:
        return numbered(items, "item", "rank")
    return items.withColumn("rank", F.row_number().over(W.partitionBy(*group).orderBy("item")) - 1)


class Uniform(NegativeSampler):
    """Any item but the positive, without rejection: ranks from the positive's on are shifted by one."""

    def sample(self, positives, batch=0):
        known = ranked(self.items.select("item").distinct())
        n = known.count()
        if n < 2:
            return positives.select(F.col("example_id").alias("link"), F.lit(1).alias("draw"), "item").limit(0)
        own = self.draws(positives, batch).join(known.withColumnRenamed("rank", "own"), "item").drop("item")
        r = F.col("_r") % (n - 1)
        return own.withColumn("rank", r + F.when(r >= F.col("own"), 1).otherwise(0)).join(known, "rank").select(F.col("example_id").alias("link"), "draw", "item")


class Within(NegativeSampler):
    """Any other item of the positive's group; positives of single-item groups get none (``skipped`` lists them)."""

    def __init__(self, items, group: str, n_neg=1, seed=0):
        super().__init__(items, n_neg, seed)
        self.group = group

    def _known(self):
        known = ranked(self.items.select("item", self.group).distinct(), self.group)
        return known.withColumn("size", F.count("*").over(W.partitionBy(self.group)))

    def skipped(self, positives: DataFrame) -> DataFrame:
        return positives.join(self._known().where("size = 1").select("item"), "item").select("example_id")

    def sample(self, positives, batch=0):
        known = self._known()
        own = self.draws(positives.select("example_id", "item"), batch).join(known.where("size > 1").withColumnRenamed("rank", "own"), "item").drop("item")
        r = F.col("_r") % (F.col("size") - 1)
        own = own.withColumn("rank", r + F.when(r >= F.col("own"), 1).otherwise(0)).drop("size")
        return own.join(known.select(self.group, "rank", "item"), [self.group, "rank"]).select(F.col("example_id").alias("link"), "draw", "item")


class Popularity(NegativeSampler):
    """Items by their counts: the draw falls into the cumulative counts; a hit on the positive takes the next item."""

    def sample(self, positives, batch=0):
        counts = self.items.groupBy("item").agg(F.count("*").alias("n"))
        cum = running(ranked(counts), "item", "n", "hi").withColumn("lo", F.col("hi") - F.col("n"))
        total, n_items = cum.agg(F.max("hi"), F.count("*")).first()
        step = max(1, total // 1024)  # equi-join on a coarse bin, then the exact bounds
        bins = cum.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / step), F.floor((F.col("hi") - 1) / step)))).drop("n")
        own = self.draws(positives.select("example_id", "item"), batch).withColumnRenamed("item", "own").withColumn("_c", F.col("_r") % total).withColumn("bin", F.floor(F.col("_c") / step))
        hit = own.join(bins, "bin").where((F.col("_c") >= F.col("lo")) & (F.col("_c") < F.col("hi")))
        rank = F.when(F.col("item") == F.col("own"), (F.col("rank") + 1) % n_items).otherwise(F.col("rank"))
        return hit.select(F.col("example_id").alias("link"), "draw", rank.alias("rank")).join(cum.select("rank", "item"), "rank").select("link", "draw", "item")


class Excluding(NegativeSampler):
    """Only items the user never took: the draw is a rank among the user's remaining items. Users who took everything get none.

    With the user's taken items at ascending ranks t_0, t_1, ..., the r-th remaining item stands at r plus the number of i with
    t_i - i <= r, so only what a user took is looked at and no pair of user and item is ever made up."""

    def sample(self, positives, batch=0):
        known = ranked(self.items.select("item").distinct())
        n = known.count()
        taken = positives.select("user_id", "item").distinct().join(known, "item")
        each = taken.groupBy("user_id").agg(F.sort_array(F.collect_list("rank")).alias("t"))
        steps = each.select("user_id", F.transform("t", lambda t, i: t - i).alias("steps")).where(F.size("steps") < n)
        own = self.draws(positives.select("example_id", "user_id"), batch).join(steps, "user_id").withColumn("r", F.col("_r") % (n - F.size("steps")))
        own = own.withColumn("rank", F.col("r") + F.size(F.filter("steps", lambda s: s <= F.col("r"))))
        return own.join(known, "rank").select(F.col("example_id").alias("link"), "draw", "item")


class Pairwise(Objective):
    """Mean over positives and their negatives of -log sigmoid(score+ - score-), with factorization-machine scores.

    ``features(df)`` turns (example_id, user_id, query, item) into long features. Negatives come in ``n_batches`` sampler
    batches; fixed, or drawn anew each time ``resample`` is called (never while a line search holds the function).
    """

    def __init__(self, positives: DataFrame, sampler: NegativeSampler, features, block_size: int, ex_parts: int, n_batches: int = 1):
        self.positives, self.sampler, self.features, self.block_size, self.ex_parts, self.n_batches = positives, sampler, features, block_size, ex_parts, n_batches
        self.round = 0
        self._build()

    def _build(self):
        pos = self.positives.select("example_id", "user_id", "query", "item")
        negs = None
        for b in range(self.n_batches):
            part = self.sampler.sample(pos, self.round * self.n_batches + b).withColumn("b", F.lit(b))
            negs = part if negs is None else negs.unionByName(part)
        per = self.sampler.n_neg * self.n_batches
        named = negs.join(pos.select(F.col("example_id").alias("link"), "user_id", "query"), "link")
        neg_id = -(F.col("link") * per + F.col("b") * self.sampler.n_neg + F.col("draw"))
        self.negatives = named.withColumn("example_id", neg_id).persist()
        self.links = self.negatives.select("example_id", "link").persist()
        everything = pos.unionByName(self.negatives.select(*pos.columns))
        self.cells = grid.build_cells(self.features(everything), self.ex_parts, self.block_size).persist()
        none = everything.select("example_id", F.lit(0.0).alias("label"))
        self.machines = Machines(self.cells, none, losses.Squared(), self.ex_parts)

    def resample(self):
        self.round += 1
        self._build()

    def _pairs(self, x: Vec) -> tuple[DataFrame, DataFrame]:
        scored = self.machines.scores(x).persist()
        s = scored.select("example_id", "score")
        pairs = self.links.join(s.withColumnRenamed("score", "s_neg"), "example_id", "left").join(s.select(F.col("example_id").alias("link"), F.col("score").alias("s_pos")), "link", "left")
        return pairs.na.fill(0.0, ["s_neg", "s_pos"]).withColumn("delta", F.col("s_pos") - F.col("s_neg")), scored

    def value(self, x):
        pairs, scored = self._pairs(x)
        v = pairs.agg(F.avg(losses.Pairwise().value(F.col("delta")))).first()[0]
        scored.unpersist()
        return float(v)

    def evaluate(self, x):
        pairs, scored = self._pairs(x)
        d = losses.Pairwise().derivative(F.col("delta"))
        rows = pairs.select("example_id", "link", losses.Pairwise().value(F.col("delta")).alias("l"), d.alias("d")).persist()
        total = rows.agg(F.count("*").alias("n"), F.avg("l").alias("v")).first()
        ds = rows.groupBy(F.col("link").alias("example_id")).agg(F.sum("d").alias("ds")).unionByName(rows.select("example_id", (-F.col("d")).alias("ds")))
        g = self.machines.pull_back(x, scored.join(ds, "example_id").select("example_id", "v", "ds"), float(total["n"])).cut()
        rows.unpersist()
        scored.unpersist()
        return float(total["v"]), g

    def along(self, x, d):
        return PlainLine(self, x, d)


def exact_loss(positives: DataFrame, items: DataFrame, score) -> DataFrame:
    """(loss): expectation over all other items instead of samples; ``score(df)`` adds ``score`` to (user_id, query, item) rows."""
    pairs = positives.select("example_id", "user_id", "query", F.col("item").alias("own")).join(items.select("item").distinct())
    scored = score(pairs)
    own = scored.where("item = own").select("example_id", F.col("score").alias("s_pos"))
    each = scored.where("item <> own").join(own, "example_id").groupBy("example_id").agg(F.avg(losses.softplus(F.col("score") - F.col("s_pos"))).alias("l"))
    return each.agg(F.avg("l").alias("loss"))


def descend_value(f: Objective, x: Vec, g: Vec, rate: float) -> Vec:
    return ops.lincomb([1.0, -rate], [x, g])
