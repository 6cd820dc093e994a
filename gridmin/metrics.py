"""Cost and accuracy measures, each over a DataFrame, and figures read off iteration logs."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin.order import running
from gridmin.vectors import Vec, ops


def regression(df: DataFrame, score: str = "score", label: str = "label", tau: float = 0.5) -> DataFrame:
    r, mean = F.col(label) - F.col(score), F.avg(label)
    return df.agg(
        F.avg(r * r).alias("mse"), F.sqrt(F.avg(r * r)).alias("rmse"), F.avg(F.abs(r)).alias("mae"), (1 - F.avg(r * r) / (F.avg(F.col(label) * F.col(label)) - mean * mean)).alias("r2"),
        F.avg(F.when(r >= 0, r * tau).otherwise(r * (tau - 1))).alias("pinball"), F.avg((r <= 0).cast("double")).alias("coverage"))


def classification(df: DataFrame, p: str = "p", label: str = "label", cut: float = 0.5) -> DataFrame:
    """Binary: log-loss, accuracy, confusion counts, precision, recall, F1."""
    y, hit = F.col(label) == 1, F.col(p) >= cut
    q = F.greatest(F.lit(1e-15), F.least(F.lit(1 - 1e-15), F.col(p)))
    c = df.agg(F.avg(-F.when(y, F.log(q)).otherwise(F.log(1 - q))).alias("log_loss"), F.count_if(y & hit).alias("tp"), F.count_if(~y & hit).alias("fp"), F.count_if(y & ~hit).alias("fn"), F.count_if(~y & ~hit).alias("tn"))
    ratio = lambda a, b: F.when(b == 0, F.lit(0.0)).otherwise(F.try_divide(a.cast("double"), b))
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return c.withColumns({"accuracy": ratio(tp + F.col("tn"), tp + fp + fn + F.col("tn")), "precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": ratio(2 * tp, 2 * tp + fp + fn)})


def auc(df: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """Area under the curve with ties at mid-rank. Counts by distinct score first, then running counts over ranges of scores."""
    by = df.groupBy(F.col(score).alias("_score")).agg(F.count_if(F.col(label) == 1).alias("_p"), F.count_if(F.col(label) != 1).alias("_n"))
    below = F.col("_upto") - F.col("_n")
    return running(by, "_score", "_n", "_upto").withColumn("_u", F.col("_p") * (below + F.col("_n") / 2)).agg((F.sum("_u") / (F.sum("_p") * F.sum("_n"))).alias("auc"))


def calibration(df: DataFrame, p: str = "p", label: str = "label", bins: int = 10) -> DataFrame:
    b = F.least(F.floor(F.col(p) * bins), F.lit(bins - 1)).cast("int")
    return df.groupBy(b.alias("bin")).agg(F.count("*").alias("n"), F.avg(p).alias("mean_p"), F.avg(F.col(label).cast("double")).alias("rate"))


def ranking(df: DataFrame, group: str, score: str, relevant: str, k: int = 10, tie: str = "item") -> DataFrame:
    """MRR, hit@k, NDCG@k over groups that have a relevant item, and pairwise accuracy."""
    r = df.withColumn("r", F.row_number().over(W.partitionBy(group).orderBy(F.desc(score), tie)))
    rel = F.col(relevant) == 1
    per = r.groupBy(group).agg(F.min(F.when(rel, F.col("r"))).alias("first"), F.sum(F.when(rel & (F.col("r") <= k), 1 / F.log2(F.col("r") + 1.0)).otherwise(0.0)).alias("dcg"), F.count_if(rel).alias("n_rel"), F.count_if(~rel).alias("n_not"), F.sum(F.when(rel, F.col("r")).otherwise(0)).alias("rank_sum")).where("n_rel > 0")
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.col("n_rel"), F.lit(k)).cast("int")), F.lit(0.0), lambda acc, i: acc + 1 / F.log2(i + 1.0))
    won = F.col("n_rel") * F.col("n_not") - (F.col("rank_sum") - F.col("n_rel") * (F.col("n_rel") + 1) / 2)
    return per.agg(F.avg(1 / F.col("first")).alias("mrr"), F.avg((F.col("first") <= k).cast("double")).alias("hit"), F.avg(F.col("dcg") / ideal).alias("ndcg"), F.avg(F.try_divide(won, F.col("n_rel") * F.col("n_not"))).alias("pairwise"))


def entropy_floor(df: DataFrame, p: str) -> DataFrame:
    """Mean entropy of the label law: no log-loss can be lower on average."""
    return df.agg(F.avg(F.aggregate(F.col(p), F.lit(0.0), lambda acc, x: acc - F.when(x > 0, x * F.log(x)).otherwise(0.0))).alias("floor"))


def recovery(w: Vec, truth: Vec) -> dict[str, float]:
    d = ops.sub(w, truth)
    return {"max": ops.norm(d, float("inf")), "relative": ops.norm(d, 2) / max(ops.norm(truth, 2), 1e-300)}


def gap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Two logs joined by iteration: relative loss gap (a - b) / |b|."""
    return a.select("iteration", F.col("value").alias("value_a")).join(b.select("iteration", F.col("value").alias("value_b")), "iteration").withColumn("gap", (F.col("value_a") - F.col("value_b")) / F.abs("value_b"))


def improvements(log: DataFrame) -> DataFrame:
    before = F.lag("value").over(W.orderBy("iteration"))
    return log.select("iteration", "value", (F.abs(before - F.col("value")) / F.greatest(F.abs(before), F.lit(1e-6))).alias("improvement"))


class Timers:
    """Seconds by name; ``summary`` gives mean and sample deviation."""

    def __init__(self):
        self.rows: list[tuple[str, float]] = []

    @contextmanager
    def measure(self, name: str):
        t = time.perf_counter()
        yield
        self.rows.append((name, time.perf_counter() - t))

    def summary(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "name string, seconds double").groupBy("name").agg(F.count("*").alias("n"), F.avg("seconds").alias("mean"), F.stddev_samp("seconds").alias("sd"))


def size_ratio(n: float, n0: float) -> float:
    """How many times larger the cost matrix of n x n points is than that of n0 x n0."""
    return (n / n0) ** 2


def run_info(spark: SparkSession) -> dict[str, object]:
    """Caps of the session and bytes it caches."""
    sc = spark.sparkContext
    cached = sum(i.memSize() + i.diskSize() for i in sc._jsc.sc().getRDDStorageInfo())
    return {"executors": sc._jsc.sc().getExecutorMemoryStatus().size(), "cores": sc.defaultParallelism, "memory": sc.getConf().get("spark.executor.memory", sc.getConf().get("spark.driver.memory", "1g")), "cached_bytes": cached}


def plan_depth(df: DataFrame) -> int:
    """Depth of the optimised plan."""
    return max((len(line) - len(line.lstrip(" :+-")) for line in df._jdf.queryExecution().optimizedPlan().toString().splitlines()), default=0) // 3 + 1


def moved(df: DataFrame, column: str) -> int:
    """Exchanges of the plan that move ``column``; what a cached table was once made by doesn't count."""

    def each(seq) -> list:
        return [seq.apply(k) for k in range(seq.size())]

    def walk(node) -> int:
        hit = node.nodeName() in ("Exchange", "BroadcastExchange") and any(a.name() == column for a in each(node.output()))
        return hit + sum(walk(c) for c in each(node.children()))

    return walk(df._jdf.queryExecution().executedPlan())


def exchanges(df: DataFrame) -> int:
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
