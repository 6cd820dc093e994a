"""Estimators: fit on (features, labels), transform, evaluate, save, load."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin import grid, losses, metrics, optim
from gridmin.objective import Linear, Machines
from gridmin.vectors import Vec, uniform, zeros


@dataclass
class Estimator:
    """``features``: (example_id, feature_id, value); ``labels``: (example_id, label[, weight]). ``ex_parts`` is the least number
    of example parts; there are more where there are many examples."""

    length: int
    block_size: int = 1024
    ex_parts: int = 8
    minimiser: optim.Minimiser | None = None
    strategy: str | None = None
    model: Vec | None = None
    result: optim.Result | None = field(default=None, repr=False)

    stack = 1

    def loss(self) -> losses.Loss:
        raise NotImplementedError

    def _start(self, spark: SparkSession) -> Vec:
        return zeros(spark, self.length, self.block_size, stack=self.stack)

    def _objective(self, cells: DataFrame, labels: DataFrame, parts: int):
        return Linear(cells, labels, self.loss(), parts, self.strategy)

    def fit(self, features: DataFrame, labels: DataFrame) -> "Estimator":
        parts = grid.example_parts(labels, self.ex_parts)
        cells = grid.build_cells(grid.clean_features(features, self.length), parts, self.block_size).persist()
        f = self._objective(cells, labels, parts)
        self.result = (self.minimiser or optim.LimitedMemory()).run(f, self._start(features.sparkSession))
        self.model = self.result.x
        f.free()
        return self

    def _scores(self, features: DataFrame) -> DataFrame:
        none = features.select("example_id").distinct().withColumn("label", F.lit(0.0))
        parts = grid.example_parts(none, self.ex_parts)
        cells = grid.build_cells(grid.clean_features(features, self.length, on_unseen="drop"), parts, self.block_size)
        got = self._objective(cells, none, parts).scores(self.model)
        return none.select("example_id").join(got, "example_id", "left")

    def transform(self, features: DataFrame) -> DataFrame:
        return self._scores(features).select("example_id", F.coalesce(F.col("s")[0], F.lit(0.0)).alias("score"))

    def evaluate(self, features: DataFrame, labels: DataFrame) -> DataFrame:
        return metrics.regression(self.transform(features).join(labels, "example_id"))

    def _extra(self) -> dict:
        return {}

    def save(self, path: str) -> None:
        spark = self.model.df.sparkSession
        self.model.df.write.mode("overwrite").parquet(f"{path}/model")
        meta = {"length": self.length, "block_size": self.block_size, "ex_parts": self.ex_parts, "strategy": self.strategy, **self._extra()}
        spark.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "Estimator":
        out = cls(**json.loads(spark.read.text(f"{path}/meta").first()[0]))
        out.model = Vec(spark.read.parquet(f"{path}/model"), out.length, out.block_size, out.stack)
        return out


class Regressor(Estimator):
    def loss(self):
        return losses.Squared()


@dataclass
class QuantileRegressor(Estimator):
    tau: float = 0.5

    def loss(self):
        return losses.Quantile(self.tau)

    def _extra(self):
        return {"tau": self.tau}

    def evaluate(self, features, labels):
        return metrics.regression(self.transform(features).join(labels, "example_id"), tau=self.tau)


class BinaryClassifier(Estimator):
    def loss(self):
        return losses.Logistic()

    def transform(self, features):
        return super().transform(features).withColumn("p", losses.sigmoid(F.col("score")))

    def evaluate(self, features, labels):
        return metrics.classification(self.transform(features).join(labels, "example_id"))


@dataclass
class MultiClassifier(Estimator):
    k: int = 2

    def __post_init__(self):
        self.stack = self.k

    def loss(self):
        return losses.Softmax(self.k)

    def _extra(self):
        return {"k": self.k}

    def transform(self, features):
        s = F.coalesce("s", F.array_repeat(F.lit(0.0), self.k))
        best = (F.array_position(s, F.array_max(s)) - 1).cast("int")
        return self._scores(features).select("example_id", best.alias("class"), losses.softmax(s).alias("p"))

    def evaluate(self, features, labels):
        return self.transform(features).join(labels, "example_id").agg(F.avg((F.col("class") == F.col("label")).cast("double")).alias("accuracy"))


@dataclass
class FMRegressor(Estimator):
    rank: int = 4
    seed: int = 1

    def __post_init__(self):
        self.stack = self.rank

    def loss(self):
        return losses.Squared()

    def _extra(self):
        return {"rank": self.rank, "seed": self.seed}

    def _start(self, spark):
        return uniform(spark, self.length, self.seed, -0.1, 0.1, self.block_size, self.rank)  # zero is a stationary point

    def _objective(self, cells, labels, parts):
        return Machines(cells, labels, self.loss(), parts, self.strategy)

    def transform(self, features):
        return self._scores(features).select("example_id", F.coalesce("score", F.lit(0.0)).alias("score"))


class FMClassifier(FMRegressor):
    def loss(self):
        return losses.Logistic()

    def transform(self, features):
        return super().transform(features).withColumn("p", losses.sigmoid(F.col("score")))

    def evaluate(self, features, labels):
        return metrics.classification(self.transform(features).join(labels, "example_id"))


class FMRanker(FMRegressor):
    """Fitted through ranking.Pairwise; scores items by the same machine."""

    def fit_pairs(self, objective) -> "FMRanker":
        self.result = (self.minimiser or optim.AdaptiveGradient(stop=[optim.MaxIter(10)])).run(objective, self._start(objective.positives.sparkSession))
        self.model = self.result.x
        return self


@dataclass
class TransportSolver:
    eps: float = 0.1
    part_size: int = 1024
    metric: str = "sqeuclidean"
    minimiser: optim.Minimiser | None = None
    result: optim.Result | None = None

    def fit(self, x: DataFrame, y: DataFrame, key: str, coords: str) -> "TransportSolver":
        from gridmin.transport import Transport

        self.problem = Transport.of(x, y, key, coords, self.part_size, eps=self.eps, metric=self.metric)
        m = self.minimiser or optim.LimitedMemory(stop=[optim.GradNorm(5e-5), optim.MaxIter(50)])
        self.result = self.problem.solve(m)
        return self

    def plan(self, top: int = 1) -> DataFrame:
        return self.problem.plan(self.result.x, top)

    def evaluate(self) -> dict[str, float]:
        return self.problem.summary(self.result.x)
