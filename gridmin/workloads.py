"""Experiment workloads on the given tables, and generators that any engine can rebuild from md5 prefixes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import partial
from uuid import uuid4

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin import grid, io, losses, optim, transport, whole
from gridmin.objective import Batched, Linear, Machines, Objective
from gridmin.ranking import Pairwise, Uniform, Within
from gridmin.vectors import Vec, from_expr, uniform, zeros
from gridmin.vectors.vec import from_long, shared_dir
from gridmin.whole import SMALL


def h32(*parts) -> Column:
    """md5 prefix of the joined parts as a number below 2^32; in DuckDB ('0x' || substr(md5(s), 1, 8))::bigint."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[c.cast("string") for c in cols]).cast("binary")), 1, 8), 16, 10).cast("long")


def planted_features(ids: DataFrame, nnz: int, d: int) -> DataFrame:
    """(example_id, feature_id, value): index_j = (base + stride j) mod d, all distinct for prime d; values on a grid in [-1, 1]."""
    rows = ids.select("example_id", (h32("base", F.col("example_id")) % d).alias("b"), (h32("stride", F.col("example_id")) % (d - 1) + 1).alias("s"), F.explode(F.sequence(F.lit(0), F.lit(nnz - 1))).alias("j"))
    value = ((F.col("example_id") * 7919 + F.col("j") * 104729) % 2001 - 1000) / 1000.0
    return rows.select("example_id", ((F.col("b") + F.col("s") * F.col("j")) % d).alias("feature_id"), value.cast("double").alias("value"))


FEATURES_SQL = """
  select example_id, (b + s * j) % {d} as feature_id, (((example_id * 7919 + j * 104729) % 2001 - 1000) / 1000.0::double)::double as value
  from (select example_id, ('0x' || substr(md5('base:' || example_id), 1, 8))::bigint % {d} as b,
               ('0x' || substr(md5('stride:' || example_id), 1, 8))::bigint % ({d} - 1) + 1 as s from ids), (select unnest(range({nnz})) as j)
"""


def true_weight(idx: Column, row: Column | None = None) -> Column:
    """Planted weights on a grid in [-1, 1)."""
    return (h32("w", idx) if row is None else h32("w", row, idx)) / F.lit(2147483648.0) - 1.0


TRUE_SQL = "(('0x' || substr(md5('w:' || feature_id), 1, 8))::bigint / 2147483648.0::double - 1.0::double)"


@dataclass
class Workload:
    objective: Objective
    x0: Vec
    minimiser: optim.Minimiser
    data: dict = field(default_factory=dict)
    result: optim.Result | None = None

    def run(self) -> optim.Result:
        if self.result is None:
            self.result = self.minimiser.run(self.objective, self.x0)
        return self.result

    def trace(self) -> DataFrame:
        return self.run().log_df(self.x0.df.sparkSession)


def _parts(examples: DataFrame) -> int:
    """Example parts: half as many as shuffle partitions, more where there are many examples."""
    least = max(2, int(examples.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 2)
    return grid.example_parts(examples, least)


def quick(n: int = 10, tol: float = 1e-7, **kw) -> optim.LimitedMemory:
    return optim.LimitedMemory(stop=[optim.GradNorm(tol), optim.MaxIter(n)], **kw)


def newton(n: int = 10, tol: float = 1e-7, **kw) -> optim.TruncatedNewton:
    return optim.TruncatedNewton(stop=[optim.GradNorm(tol), optim.MaxIter(n)], **kw)


def linear(features: DataFrame, labels: DataFrame, length: int, loss: losses.Loss, block: int = 1024, minimiser=None, strategy: str | None = None) -> Workload:
    spark = features.sparkSession
    parts = _parts(labels)
    cells = grid.build_cells(features, parts, block).persist()
    f = Linear(cells, labels, loss, parts, strategy)
    return Workload(f, zeros(spark, length, block, stack=loss.k), minimiser or quick(), {"cells": cells, "features": features, "labels": labels})


def batched(features: DataFrame, labels: DataFrame, batch: Callable[[Column], Column], m: int, length: int, loss: losses.Loss, policy: str = "same", block: int = 1024, prefetch: bool = True) -> Batched:
    """Batches on disk, a folder each; one is read, laid out and cached at a time, and the next one meanwhile."""
    spark, path = features.sparkSession, f"{shared_dir(features.sparkSession)}/batches-{uuid4().hex}"
    for name, df in (("features", features), ("labels", labels)):
        io.write_batches(df.withColumn("batch_id", batch(F.col("example_id"))), f"{path}/{name}")

    def load(k: int) -> Objective:
        parts = [io.read_batch(spark, f"{path}/{name}", k).drop("batch_id") for name in ("features", "labels")]
        w = linear(*parts, length, loss, block)
        w.objective.ready(w.x0)
        return w.objective

    return Batched([partial(load, k) for k in range(m)], policy, prefetch)


def standardised(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, dict]:
    """W1r: price from quantity, discount and tax, z-scored, with a bias (feature 3)."""
    cols = ["l_quantity", "l_discount", "l_tax"]
    df = io.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", *cols])
    key = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    m = df.agg(*[F.avg(c).alias(f"m_{c}") for c in cols], *[F.stddev_pop(c).alias(f"s_{c}") for c in cols], F.avg("l_extendedprice").alias("m_y"), F.stddev_pop("l_extendedprice").alias("s_y")).first().asDict()
    z = df.select(key.alias("example_id"), *[((F.col(c) - m[f"m_{c}"]) / m[f"s_{c}"]).alias(c) for c in cols], ((F.col("l_extendedprice") - m["m_y"]) / m["s_y"]).alias("label")).persist()
    pairs = F.array(*[F.struct(F.lit(i).cast("long").alias("feature_id"), F.col(c).alias("value")) for i, c in enumerate(cols)], F.struct(F.lit(3).cast("long").alias("feature_id"), F.lit(1.0).alias("value")))
    return z.select("example_id", F.explode(pairs).alias("p")).select("example_id", "p.feature_id", "p.value"), z.select("example_id", "label"), m


def w1r(spark: SparkSession, sf_dir: str, minimiser=None) -> Workload:
    features, labels, m = standardised(spark, sf_dir)
    out = linear(features, labels, 4, losses.Squared(), 4, minimiser)
    out.data["moments"] = m
    return out


def w1(spark: SparkSession, sf_dir: str, d: int = 10_007, nnz: int = 30, batches: int = 1, policy: str = "same", only: int | None = None, minimiser=None) -> Workload:
    """Planted squared loss on orders; batch = key mod 5."""
    ids = io.table(spark, sf_dir, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("example_id"))
    feats = planted_features(ids, nnz, d).persist()
    y = feats.groupBy("example_id").agg(F.sum(F.col("value") * true_weight(F.col("feature_id"))).alias("label")).persist()
    of = F.pmod(F.col("example_id"), F.lit(5))
    if batches == 1:
        keep = of == only if only is not None else F.lit(True)
        out = linear(feats.where(keep), y.where(keep), d, losses.Squared(), 1024, minimiser)
        out.data["truth"] = from_expr(spark, d, lambda row, i: true_weight(i), 1024)
        return out
    f = batched(feats, y, lambda i: F.pmod(i, F.lit(5)).cast("int"), batches, d, losses.Squared(), policy)
    feats.unpersist()
    y.unpersist()
    return Workload(f, zeros(spark, d, 1024), minimiser or quick())


def w2(spark: SparkSession, sf_dir: str, minimiser=None) -> Workload:
    """Softmax of the ten embedding classes on their 64 coordinates."""
    e = io.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("example_id"), "embedding", F.col("label").cast("double").alias("label"))
    feats = e.select("example_id", F.posexplode("embedding").alias("feature_id", "value")).select("example_id", F.col("feature_id").cast("long").alias("feature_id"), F.col("value").cast("double").alias("value"))
    return linear(feats, e.select("example_id", "label"), 64, losses.Softmax(10), 64, minimiser)


def next_prime(n: int) -> int:
    while n < 2 or any(n % q == 0 for q in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def planted_reader(nnz: int, d: int) -> Callable:
    """For ``whole.pack``: the rows of ``planted_features``, summed by example and feature, from (example_id, times, b, s, u), with u besides."""

    def read(b) -> tuple:
        ex, base, stride = (b.column(c).to_numpy()[:, None] for c in ("example_id", "b", "s"))
        j = np.arange(nnz)
        ids, values = (base + stride * j) % d, (np.fmod(ex * 7919 + j * 104729, 2001) - 1000) / 1000.0
        values = values * b.column("times").to_numpy()[:, None]
        return ex[:, 0], np.full(len(ex), nnz), ids.reshape(-1), values.reshape(-1), b.column("u").to_numpy()

    return read


def drawn(s: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Classes by inverse distribution function of the softmax of scores (k, examples)."""
    top = s.max(0)
    p = np.exp(s - (top + np.log(np.exp(s - top).sum(0))))
    return (u >= np.cumsum(p, 0)[:-1]).sum(0)


def w2_planted(spark: SparkSession, sf_dir: str, d: int | None = None, nnz: int = 100, k: int = 10, batches: int = 5, policy: str = "same", minimiser=None) -> Workload:
    """Planted softmax on events, labels drawn from the law by inverse distribution function of a hashed uniform. As published, a
    batch has five examples for each feature, unless ``d`` says otherwise."""
    ids = io.table(spark, sf_dir, "events", ["event_id"]).select(F.col("event_id").alias("example_id"))
    n = ids.count()
    d = d or next_prime(max(2 * nnz, n // batches // 5))
    if 8 * d * k <= SMALL:
        return _w2_packed(spark, ids, n, d, nnz, k, batches, policy, minimiser)
    feats = planted_features(ids, nnz, d).persist()
    truth = spark.range(d).select(F.col("id").alias("feature_id"), *[true_weight(F.col("id"), F.lit(c)).alias(f"w{c}") for c in range(k)])  # hashed once a feature, not once a non-zero
    s = feats.join(truth, "feature_id").groupBy("example_id").agg(*[F.sum(F.col("value") * F.col(f"w{c}")).alias(f"s{c}") for c in range(k)])
    law = s.select("example_id", losses.softmax(F.array(*[f"s{c}" for c in range(k)])).alias("p")).persist()
    cdf = lambda upto: F.aggregate(F.slice("p", 1, upto), F.lit(0.0), lambda acc, x: acc + x)
    u = h32("u", F.col("example_id")) / F.lit(4294967296.0)
    label = sum(((u >= cdf(c)).cast("int") for c in range(1, k)), F.lit(0))
    labels = law.select("example_id", label.cast("double").alias("label")).persist()
    if batches == 1:
        f = linear(feats, labels, d, losses.Softmax(k), 1024).objective
    else:
        f = batched(feats, labels, lambda i: F.pmod(i, F.lit(batches)).cast("int"), batches, d, losses.Softmax(k), policy)
    feats.unpersist()
    return Workload(f, zeros(spark, d, 1024, stack=k), minimiser or quick(6), {"law": law, "labels": labels})


def _w2_packed(spark: SparkSession, ids: DataFrame, n: int, d: int, nnz: int, k: int, batches: int, policy: str, minimiser) -> Workload:
    """The same where a model fits a task: features of an example stay together from the start, and only example ids move."""
    truth = from_expr(spark, d, lambda row, i: true_weight(i, row), 1024, stack=k).cut()
    x0, path = zeros(spark, d, 1024, stack=k), f"{shared_dir(spark)}/batches-{uuid4().hex}"
    parts = grid.example_parts_of(n // batches, max(2, int(spark.conf.get("spark.sql.shuffle.partitions")) // 2))

    def packed(some: DataFrame) -> DataFrame:
        dealt = some.repartition(spark.sparkContext.defaultParallelism, "example_id").groupBy("example_id").agg(F.count("*").alias("times"))  # each part ends in a gradient of its own
        e = F.col("example_id")
        known = F.coalesce(e, F.raise_error(F.lit("null example id")).cast("long")).alias("example_id")
        rows = dealt.select(known, "times", (h32("base", e) % d).alias("b"), (h32("stride", e) % (d - 1) + 1).alias("s"), (h32("u", e) / F.lit(4294967296.0)).alias("u"))
        return whole.pack(rows, planted_reader(nnz, d), truth, drawn)

    def objective(some: DataFrame, rows: DataFrame) -> Linear:
        cells = grid.build_cells(planted_features(some, nnz, d), parts, 1024).persist()
        f = Linear(cells, whole.labels_of(rows), losses.Softmax(k), parts, packed=rows)
        f.ready(x0)
        return f

    def load(b: int) -> Objective:
        some, at = ids.where(F.pmod("example_id", F.lit(batches)) == b), f"{path}/{b}"
        if b not in written:
            packed(some).write.parquet(at)
            written.add(b)
        return objective(some, spark.read.schema(whole.ROW).parquet(at))

    written: set[int] = set()
    every = packed(ids)
    f = objective(ids, every) if batches == 1 else Batched([partial(load, b) for b in range(batches)], policy, True)
    law = whole.scores_of(every, truth).select("example_id", losses.softmax(F.col("s")).alias("p"))
    return Workload(f, x0, minimiser or quick(6), {"law": law, "labels": whole.labels_of(every)})


def w3(spark: SparkSession, sf_dir: str, eps: float = 0.1, part_size: int = 64, minimiser=None, **kw) -> Workload:
    e = io.table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    f = transport.Transport.of(e.where("vec_id % 2 = 0"), e.where("vec_id % 2 = 1"), "vec_id", "embedding", part_size=part_size, eps=eps, **kw)
    return Workload(f, f.start(), minimiser or quick(20, 5e-5))


def w3_one_dimension(spark: SparkSession, sf_dir: str, eps: float = 0.01, minimiser=None) -> Workload:
    """Supplier against customer balances, scaled to [0, 1]."""
    both = []
    for name, key, bal in (("supplier", "s_suppkey", "s_acctbal"), ("customer", "c_custkey", "c_acctbal")):
        df = io.table(spark, sf_dir, name, [key, bal])
        lo, hi = df.agg(F.min(bal), F.max(bal)).first()
        both.append(df.select(F.col(key).alias("k"), F.array((F.col(bal) - lo) / (hi - lo)).alias("c")))
    f = transport.Transport.of(*both, "k", "c", part_size=512, eps=eps)
    flat = [df.select("k", F.col("c")[0].alias("v")) for df in both]
    return Workload(f, f.start(), minimiser or quick(10, 5e-5), {"x": flat[0], "y": flat[1]})


def ball(spark: SparkSession, n: int, d: int, seed: int) -> DataFrame:
    """(pos, coords): uniform in the unit ball, a Gaussian direction times U^(1/d), from hashes of the position."""
    unit = lambda i, j, what: (h32(seed, what, i, j) + 0.5) / F.lit(4294967296.0)
    g = F.transform(F.sequence(F.lit(1), F.lit(d)), lambda j: F.sqrt(-2.0 * F.log(unit(F.col("id"), j, "r"))) * F.cos(2 * np.pi * unit(F.col("id"), j, "a")))
    rows = spark.range(n).withColumn("g", g)
    norm = F.sqrt(F.aggregate("g", F.lit(0.0), lambda acc, x: acc + x * x))
    radius = F.pow(unit(F.col("id"), F.lit(0), "len"), F.lit(1.0 / d))
    return rows.select(F.col("id").alias("pos"), F.transform("g", lambda x: x * radius / norm).alias("coords"))


def shifted_balls(spark: SparkSession, n: int, d: int, seed: int, axes: int = 20) -> DataFrame:
    """Balls of radius 1/2 at +-1/2 on ``axes`` distinct hashed axes, 2 * axes of them in equal shares."""
    order = sorted(range(d), key=lambda a: __import__("hashlib").md5(f"{seed}:axis:{a}".encode()).hexdigest())[:axes]
    pick = (h32(seed, "ball", F.col("pos")) % (2 * len(order))).cast("int")
    axis = F.element_at(F.array(*[F.lit(a) for a in order]), (F.floor(pick / 2) + 1).cast("int"))
    shift = F.when(pick % 2 == 0, 0.5).otherwise(-0.5)
    return ball(spark, n, d, seed).select("pos", F.transform("coords", lambda x, j: x * 0.5 + F.when(j == axis, shift).otherwise(0.0)).alias("coords"))


def event_features(df: DataFrame) -> DataFrame:
    """One-hot user (0-199), type or query (200-299) and item (300-...) of (example_id, user_id, query, item)."""
    q = F.lit(200) + h32("q", F.col("query")) % 97
    ids = F.array(F.col("user_id") % 200, q, F.lit(300) + F.col("item"))
    return df.select("example_id", F.explode(ids).alias("feature_id"), F.lit(1.0).alias("value"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = io.table(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "value", "props"])
    return df.select(F.col("event_id").alias("example_id"), "user_id", F.col("event_type").alias("query"), F.get_json_object("props", "$.k").cast("long").alias("item"), "value")


def w4(spark: SparkSession, sf_dir: str, k: int = 4, minimiser=None) -> Workload:
    e = events(spark, sf_dir)
    parts = _parts(e)
    cells = grid.build_cells(event_features(e), parts, 512).persist()
    f = Machines(cells, e.select("example_id", (F.col("value") / 100.0).alias("label")), losses.Squared(), parts)
    return Workload(f, uniform(spark, 512, 5, -0.1, 0.1, 512, k), minimiser or quick(5))


def w5(spark: SparkSession, sf_dir: str, k: int = 4, n_neg: int = 2, sampler: Callable | None = None, minimiser=None) -> Workload:
    pos = events(spark, sf_dir).where(F.col("query").isin("purchase", "click")).drop("value").persist()
    made = sampler(pos) if sampler else Uniform(pos.select("item"), n_neg, 3)
    f = Pairwise(pos, made, event_features, 512, _parts(pos))
    return Workload(f, uniform(spark, 512, 6, -0.1, 0.1, 512, k), minimiser or optim.AdaptiveGradient(eta=0.05, stop=[optim.MaxIter(4)]), {"positives": pos})


def orders_positives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(example_id, user_id, query, item): customer, part type and part of every line of every order."""
    o = io.table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    li = io.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"])
    p = io.table(spark, sf_dir, "part", ["p_partkey", "p_type"])
    rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    line = F.md5(F.concat_ws(":", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long")).cast("binary"))
    return rows.select(F.conv(F.substring(line, 1, 13), 16, 10).cast("long").alias("example_id"), F.col("o_custkey").alias("user_id"), F.col("p_type").alias("query"), F.col("l_partkey").alias("item"))


def order_features(df: DataFrame) -> DataFrame:
    """One-hot customer, type and part, hashed to 200, 97 and 212 of 512 features."""
    ids = F.array(F.col("user_id") % 200, F.lit(200) + h32("q", F.col("query")) % 97, F.lit(300) + F.col("item") % 212)
    return df.select("example_id", F.explode(ids).alias("feature_id"), F.lit(1.0).alias("value"))


def w5_orders(spark: SparkSession, sf_dir: str, k: int = 4, n_neg: int = 1, minimiser=None) -> Workload:
    """Ranking of the parts that customers order, against other parts of the same type."""
    pos = orders_positives(spark, sf_dir).persist()
    f = Pairwise(pos, Within(pos.select("item", F.col("query").alias("grp")), "grp", n_neg, 3), order_features, 512, _parts(pos))
    return Workload(f, uniform(spark, 512, 6, -0.1, 0.1, 512, k), minimiser or optim.AdaptiveGradient(eta=0.05, stop=[optim.MaxIter(4)]), {"positives": pos})


def w6(spark: SparkSession, sf_dir: str, label: str = "quality", bits: int = 14, minimiser=None) -> Workload:
    """Sparse logistic regression on hashed words of the labelled documents."""
    lab = io.table(spark, sf_dir, "labels")
    docs = io.table(spark, sf_dir, "documents", ["doc_id", "text"]).join(F.broadcast(lab.select("doc_id")), "doc_id", "left_semi")
    words = docs.select(F.col("doc_id").alias("example_id"), F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("w")).where("w <> ''")
    feats = words.groupBy("example_id", (h32("t", F.col("w")) % (1 << bits)).alias("feature_id")).agg(F.log1p(F.count("*").cast("double")).alias("value"))
    return linear(feats, lab.select(F.col("doc_id").alias("example_id"), F.col(label).cast("double").alias("label")), 1 << bits, losses.Logistic(), 4096, minimiser or quick(5))


def w7(spark: SparkSession, sf_dir: str, tau: float = 0.5, minimiser=None) -> Workload:
    """Quantile regression of event values on the event type."""
    kinds = ["click", "error", "purchase", "signup", "view"]
    e = io.table(spark, sf_dir, "events", ["event_id", "event_type", "value"])
    which = F.coalesce(F.array_position(F.array(*[F.lit(t) for t in kinds]), F.col("event_type")) - 1, F.lit(0))
    feats = e.select(F.col("event_id").alias("example_id"), F.greatest(which, F.lit(0)).alias("feature_id"), F.lit(1.0).alias("value"))
    labels = e.select(F.col("event_id").alias("example_id"), (F.col("value") / 100.0).alias("label"))
    return linear(feats, labels, len(kinds), losses.Quantile(tau), 8, minimiser or optim.AdaptiveGradient(eta=0.5, stop=[optim.MaxIter(25)]))


def weights_long(spark: SparkSession, rows: DataFrame, length: int, block: int) -> Vec:
    return from_long(rows, length, block)
