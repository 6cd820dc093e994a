"""Structured Streaming around the methods: an event source, windowed aggregates, joins, state, scoring and training on streams.

Queries here drain their input once (``availableNow``) into a table, so their result can be held against batch SQL.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from gridmin import io, losses, optim, workloads
from gridmin.registry import register
from gridmin.session import ship
from gridmin.vectors import Vec, fill
from gridmin.vectors.vec import shared_dir

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
c = F.col


def split_files(spark: SparkSession, sf_dir: str, hours: int = 24) -> str:
    """The events table as one folder of files by time, written in time order."""
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    df = io.table(spark, sf_dir, "events").withColumn("slot", F.floor(io.micros("ts") / (3_600_000_000 * hours))).withColumn("ts", c("ts").cast("timestamp"))
    df.repartitionByRange(8, "slot").sortWithinPartitions("ts").drop("slot").write.parquet(path)
    return path


def events(spark: SparkSession, path: str, max_files: int = 4) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", max_files).parquet(path)


def drain(df: DataFrame, mode: str = "append", name: str | None = None, per_batch: Callable[[DataFrame, int], None] | None = None, checkpoint: str | None = None):
    """Run until the input is used up; the result is a Parquet table, or whatever ``per_batch`` writes. Returns (table, query)."""
    spark = df.sparkSession
    base = f"{shared_dir(spark)}/{name or 'stream'}-{uuid.uuid4().hex}"
    writer = df.writeStream.option("checkpointLocation", checkpoint or f"{base}/checkpoint").outputMode(mode).trigger(availableNow=True)
    if per_batch:
        q = writer.foreachBatch(per_batch).start()
    elif mode == "append":
        q = writer.format("parquet").option("path", f"{base}/out").start()
    else:
        out = f"{base}/out"
        q = writer.foreachBatch(lambda b, i: b.write.mode("overwrite" if mode == "complete" else "append").parquet(out if mode == "complete" else f"{out}/batch={i}")).start()
    q.awaitTermination()
    if per_batch:
        return None, q
    return spark.read.option("recursiveFileLookup", "false").parquet(f"{base}/out"), q


def _events(spark, d) -> DataFrame:
    return events(spark, split_files(spark, d))


def _latest(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Of an update-mode table, the last row of each key."""
    w = W.partitionBy(*keys).orderBy(F.desc("batch"))
    return df.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*keys, value)


@register("st_source", "select event_id, user_id, event_type, value from events")
def st_source(spark, d):
    return drain(_events(spark, d).select("event_id", "user_id", "event_type", "value"))[0]


@register("st_tumbling", "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events group by 1, 2")
def st_tumbling(spark, d):
    df = _events(spark, d).withWatermark("ts", "90 days").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drain(df.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n"), "complete")[0]


@register("st_sliding", "select epoch_us(s) // 1000000 as start, count(*) as n from (select unnest([time_bucket(interval 1 hour, ts), time_bucket(interval 1 hour, ts) - interval 1 hour]) as s from events) group by 1")
def st_sliding(spark, d):
    df = _events(spark, d).withWatermark("ts", "90 days").groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n"))
    return drain(df.select(F.unix_seconds("window.start").alias("start"), "n"), "complete")[0]


@register("st_session", "select user_id, n from (select user_id, s, count(*) as n from (select *, sum(nw) over (partition by user_id order by ts rows unbounded preceding) as s from (select *, case when lag(ts) over w is null or epoch_us(ts) - epoch_us(lag(ts) over w) >= 1800000000 then 1 else 0 end as nw from events window w as (partition by user_id order by ts))) group by 1, 2)")
def st_session(spark, d):
    df = _events(spark, d).withWatermark("ts", "90 days").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    return drain(df.select("user_id", "n"), "complete")[0]


@register("st_dedupe", "select distinct event_id from events")
def st_dedupe(spark, d):
    twice = _events(spark, d).withColumn("k", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("ts", "90 days")
    return drain(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))[0]


@register("st_interval_join", "select v.event_id as view_id, p.event_id as buy_id from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts >= v.ts and p.ts <= v.ts + interval 30 minutes")
def st_interval_join(spark, d):
    path = split_files(spark, d)
    v = events(spark, path).where("event_type = 'view'").select(c("event_id").alias("view_id"), c("user_id").alias("vu"), c("ts").alias("vt")).withWatermark("vt", "90 days")
    p = events(spark, path).where("event_type = 'purchase'").select(c("event_id").alias("buy_id"), c("user_id").alias("pu"), c("ts").alias("pt")).withWatermark("pt", "90 days")
    both = v.join(p, F.expr("vu = pu and pt >= vt and pt <= vt + interval 30 minutes")).select("view_id", "buy_id")
    return drain(both)[0]


@register("st_score", "select event_id, round(1.0::double / (1.0::double + exp(-(n_nationkey - 12) / 10.0::double)), 8) as p from events join nation on user_id % 25 = n_nationkey")
def st_score(spark, d):
    """Stream joined to a static table of weights."""
    weights = io.table(spark, d, "nation", ["n_nationkey"]).select(c("n_nationkey").alias("k"), ((c("n_nationkey") - 12) / 10.0).alias("w"))
    df = _events(spark, d).join(weights, (c("user_id") % 25) == c("k")).select("event_id", F.round(losses.sigmoid(c("w")), 8).alias("p"))
    return drain(df)[0]


@register("st_modes", "select event_type, count(*) as n from events group by 1")
def st_modes(spark, d):
    """Update mode writes changed groups each batch; the last row of each group is the total."""
    df = _events(spark, d).groupBy("event_type").agg(F.count("*").alias("n"))
    return _latest(drain(df, "update")[0], ["event_type"], "n")


@register("st_late", "select 2 as dropped, 4 as kept")
def st_late(spark, d):
    """Rows older than the watermark are dropped and counted. A batch is filtered by the watermark of the batch before the last."""
    path = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    rows = [("2024-01-01 00:00:00",), ("2024-01-01 05:00:00",), ("2024-01-01 09:00:00",)]
    for i, part in enumerate((rows, [("2024-01-01 09:30:00",)], [("2024-01-01 00:30:00",), ("2024-01-01 01:40:00",)])):
        spark.createDataFrame(part, "s string").select(c("s").cast("timestamp").alias("ts")).coalesce(1).write.parquet(f"{path}/p={i}")
    src = spark.readStream.schema("ts timestamp, p int").option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(path)
    df = src.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    table, q = drain(df.select("window.start", "n"), "update")
    return spark.createDataFrame([(late_counter(q), table.groupBy("start").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0])], "dropped int, kept int")


def late_counter(query) -> int:
    """Rows dropped behind the watermark, summed over a query's progress reports."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in json.loads(p.json)["stateOperators"])


@register("st_stateful", "select user_id, count(*) as n, round(sum(value), 4) as total from events group by 1")
def st_stateful(spark, d):
    """Per-user counters kept as state; each batch emits the users it touched."""
    df = _events(spark, d).select("user_id", "value")
    out = user_state(df)
    table = drain(out, "update")[0]
    return table.withColumn("_r", F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("n")))).where("_r = 1").select("user_id", "n", F.round("total", 4).alias("total"))


def user_state(df: DataFrame, timeout_ms: int | None = None) -> DataFrame:
    """(user_id, n, total). With ``timeout_ms`` the state of a user silent for so long goes; for endless queries only, as a query
    with timers never runs out of batches."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, total = state.get if state.exists else (0, 0.0)
        for p in parts:
            n, total = n + len(p), total + float(p["value"].sum())
        state.update((n, total))
        if timeout_ms:
            state.setTimeoutDuration(timeout_ms)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    ship(df.sparkSession)
    return df.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.ProcessingTimeTimeout if timeout_ms else GroupStateTimeout.NoTimeout)


class ModelStore:
    """Points by batch number: a replayed batch finds its result and does nothing."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def has(self, batch: int) -> bool:
        at = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/x-{batch}/_SUCCESS")
        return at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at)

    def load(self, batch: int, like: Vec) -> Vec:
        return like.with_df(self.spark.read.schema(like.df.schema).parquet(f"{self.path}/x-{batch}"))

    def save(self, batch: int, x: Vec) -> None:
        x.df.write.mode("overwrite").parquet(f"{self.path}/x-{batch}")


def train(df: DataFrame, to_objective, x0: Vec, minimiser: Callable[[], optim.Minimiser], store: ModelStore) -> list[tuple[int, float, float]]:
    """Each micro-batch is scored by the stored point first (progressive validation), then a few steps move the point.

    Returns (batch, value before, value after).
    """
    seen: list[tuple[int, float, float]] = []

    def step(batch: DataFrame, i: int) -> None:
        if batch.isEmpty() or store.has(i):
            return
        x = store.load(i - 1, x0) if store.has(i - 1) else x0
        f = to_objective(batch.persist())
        r = minimiser().run(f, x)
        store.save(i, r.x)
        seen.append((i, r.log[0][1], r.value))
        batch.unpersist()

    drain(df, per_batch=step)
    return seen


def _type_model(batch: DataFrame):
    kinds = ["click", "error", "purchase", "signup", "view"]
    feats = batch.select(c("event_id").alias("example_id"), (F.array_position(F.array(*[F.lit(k) for k in kinds]), c("event_type")) - 1).alias("feature_id"), F.lit(1.0).alias("value"))
    labels = batch.select(c("event_id").alias("example_id"), (c("value") / 100.0).alias("label"))
    return workloads.linear(feats, labels, 5, losses.Squared(), 8).objective


def _trained(spark, d) -> list[tuple[int, float, float]]:
    store = ModelStore(spark, f"{shared_dir(spark)}/model-{uuid.uuid4().hex}")
    make = lambda: optim.AdaptiveGradient(eta=0.3, stop=[optim.MaxIter(2)])
    return train(_events(spark, d), _type_model, fill(spark, 5, 0.0, 8), make, store)


@register("st_online_train", "select true as ok")
def st_online_train(spark, d):
    seen = _trained(spark, d)
    return spark.createDataFrame([(len(seen) >= 2 and all(after <= before for _, before, after in seen),)], "ok boolean")


@register("st_eval", "select true as several, true as each_falls, true as learns")
def st_eval(spark, d):
    """Progressive validation: every batch is scored before its steps, and later batches start from a point already learnt."""
    seen = _trained(spark, d)
    falls = all(after <= before for _, before, after in seen)
    return spark.createDataFrame([(len(seen) >= 2, falls, seen[-1][1] < seen[0][1])], "several boolean, each_falls boolean, learns boolean")
