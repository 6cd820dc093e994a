"""Baselines that the methods are compared with, each runnable on the same workloads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin import grid, losses, optim
from gridmin.objective import Batched, Linear, Objective, Penalised
from gridmin.vectors import Vec, from_long, ops


def single_batch(objective: Objective) -> Batched:
    return Batched([objective])


def line_search_policy(batches: list[Objective], policy: str) -> Batched:
    return Batched(batches, policy)


def _vectors(features: DataFrame, labels: DataFrame, size: int) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    m = features.groupBy("example_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("feature_id").cast("int"), "value"))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0)))
    return m.select("example_id", array_to_vector(dense).alias("features")).join(labels, "example_id")


def broadcast_linear(features: DataFrame, labels: DataFrame, size: int, family: str = "squared", reg: float = 0.0, alpha: float = 0.0) -> list[float]:
    """Quasi-Newton linear models whose weights are broadcast each iteration (Spark ML). For small ``size``."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.regression import LinearRegression

    df = _vectors(features, labels, size)
    if family == "squared":
        m = LinearRegression(fitIntercept=False, standardization=False, regParam=reg, elasticNetParam=alpha, solver="l-bfgs", tol=1e-10, maxIter=100).fit(df)
    else:
        m = LogisticRegression(fitIntercept=False, standardization=False, regParam=reg, elasticNetParam=alpha, tol=1e-10, maxIter=100).fit(df)
    return m.coefficients.toArray().tolist()


def hash_index(col: Column, bits: int) -> Column:
    """Bucket by an md5 prefix modulo 2^bits."""
    return F.conv(F.substring(F.md5(F.concat(F.lit("t:"), col).cast("binary")), 1, 8), 16, 10).cast("long") % (1 << bits)


def hashed_online(objective: Objective, x0: Vec, rate: float, passes: int) -> optim.Result:
    """A hashed-feature learner with one averaged step a pass over all data."""
    return optim.GradientDescent(rate, stop=[optim.MaxIter(passes)]).run(objective, x0)


def bucketed_interactions(df: DataFrame, cols: list[str], buckets: int) -> DataFrame:
    return df.withColumn("bucket", F.conv(F.substring(F.md5(F.concat_ws(":", *cols).cast("binary")), 1, 8), 16, 10).cast("long") % buckets)


def min_count(features: DataFrame, c: int) -> DataFrame:
    """Features seen at least ``c`` times."""
    return features.join(features.groupBy("feature_id").agg(F.count("*").alias("n")).where(F.col("n") >= c), "feature_id", "left_semi")


def topk_levels(df: DataFrame, col: str, k: int) -> DataFrame:
    """The k most frequent levels; the others become 'other'. k bounds what is broadcast."""
    top = df.groupBy(col).agg(F.count("*").alias("_n")).orderBy(F.desc("_n"), col).limit(k).select(F.col(col).alias("_top"))
    return df.join(F.broadcast(top), F.col(col) == F.col("_top"), "left").withColumn(col, F.coalesce("_top", F.lit("other"))).drop("_top")


def pull_push(features: DataFrame, labels: DataFrame, x: Vec, loss: losses.Loss) -> tuple[float, Vec]:
    """Synchronous parameter server: rows pull the weights they name and push summed gradients back."""
    w = x.to_long().withColumnRenamed("idx", "feature_id").withColumnRenamed("value", "w")
    s = features.join(w, "feature_id").groupBy("example_id").agg(F.sum(F.col("value") * F.col("w")).alias("s"))
    rows = labels.join(s, "example_id", "left").na.fill(0.0, ["s"]).select("example_id", loss.value(F.col("s"), F.col("label")).alias("l"), loss.derivative(F.col("s"), F.col("label")).alias("d")).persist()
    v, n = rows.agg(F.avg("l"), F.count("*")).first()
    g = features.join(rows, "example_id").groupBy(F.col("feature_id").alias("idx")).agg((F.sum(F.col("value") * F.col("d")) / n).alias("value"))
    out = from_long(g, x.length, x.block_size).cut()
    rows.unpersist()
    return float(v), out


def uncached(workload) -> Linear:
    """The same objective with nothing kept between evaluations: input is read and cells are built each time."""
    f = workload.objective
    cells = grid.build_cells(workload.data["features"], f.ex_parts, workload.x0.block_size)
    return Linear(cells, workload.data["labels"], f.loss, f.ex_parts, f.strategy, whole=False)


def sgd_vs_lbfgs(workload, evaluations: int) -> tuple[optim.Result, optim.Result]:
    """Gradient descent and quasi-Newton at about equal numbers of evaluations."""
    sgd = workload(optim.GradientDescent(0.1, stop=[optim.MaxIter(evaluations)])).run()
    return sgd, workload(optim.LimitedMemory(stop=[optim.MaxIter(evaluations // 2)])).run()


class _Subgradient(Penalised):
    def evaluate(self, x):
        v, g = super().evaluate(x)
        return v, optim.pseudo_gradient(x, g, self.l1).cut()


def l1_lbfgs_subgradient(objective: Objective, x0: Vec, l1: float, iterations: int) -> optim.Result:
    """Quasi-Newton on the minimum-norm subgradient, without orthants."""
    return optim.LimitedMemory(line_search=optim.Backtracking(), stop=[optim.MaxIter(iterations)]).run(_Subgradient(objective, l1), x0)


def fm_bruteforce(features: DataFrame, x: Vec) -> DataFrame:
    """(example_id, score) by joining all feature pairs of an example: quadratic in its features."""
    w = x.to_long().groupBy(F.col("idx").alias("feature_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("row", "value"))), lambda z: z["value"]).alias("w"))
    rows = features.join(w, "feature_id")
    b = rows.select("example_id", F.col("feature_id").alias("other"), F.col("value").alias("value_b"), F.col("w").alias("w_b"))
    dot = F.aggregate(F.zip_with("w", "w_b", lambda p, q: p * q), F.lit(0.0), lambda acc, z: acc + z)
    return rows.join(b, "example_id").where("feature_id < other").groupBy("example_id").agg(F.sum(F.col("value") * F.col("value_b") * dot).alias("score"))


def sparkml_fm(features: DataFrame, labels: DataFrame, size: int, k: int, iterations: int) -> float:
    """Root mean squared error of Spark ML's factorization machine on its training rows."""
    from pyspark.ml.regression import FMRegressor

    df = _vectors(features, labels, size).persist()
    fitted = FMRegressor(factorSize=k, maxIter=iterations, stepSize=0.05, seed=1).fit(df).transform(df)
    out = fitted.agg(F.sqrt(F.avg((F.col("prediction") - F.col("label")) * (F.col("prediction") - F.col("label"))))).first()[0]
    df.unpersist()
    return float(out)


def rank_levels(df: DataFrame, col: str) -> DataFrame:
    return df.groupBy(col).agg(F.count("*").alias("n")).withColumn("rank", F.row_number().over(W.orderBy(F.desc("n"), col)))


def norm_gap(a: Vec, b: Vec) -> float:
    return ops.norm(ops.sub(a, b))
