"""Registered queries of the methods: vectors, grid, objectives, minimisers, models, baselines, measures, with their SQL."""

from __future__ import annotations

import math
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin import baselines, grid, io, losses, metrics, optim, ranking, transport, workloads
from gridmin.objective import Accumulated, Batched, Linear, Penalised, Quadratic
from gridmin.registry import register
from gridmin.vectors import concat, fill, from_long, layout, ops, stack, uniform, zeros

B = 256


def _price(spark: SparkSession, d: str):
    p = io.table(spark, d, "part", ["p_partkey", "p_retailprice"])
    return from_long(p, p.count(), B, "p_partkey", "p_retailprice")


def _qty(spark: SparkSession, d: str):
    q = io.table(spark, d, "lineitem", ["l_partkey", "l_quantity"]).groupBy("l_partkey").agg(F.sum("l_quantity").alias("q"))
    return from_long(q, io.table(spark, d, "part", ["p_partkey"]).count(), B, "l_partkey", "q")


def _one(spark: SparkSession, **values) -> DataFrame:
    """One row of named booleans, integers, strings or doubles."""
    kind = {bool: "boolean", int: "bigint", float: "double", str: "string"}
    values = {k: bool(v) if type(v).__name__ == "bool_" else v for k, v in values.items()}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kind[type(v)]}" for k, v in values.items()))


def _ok(spark: SparkSession, *checks) -> DataFrame:
    return _one(spark, ok=all(bool(c) for c in checks))


OK = "select true as ok"


def _falls(log: list[tuple], slack: float = 1e-9) -> bool:
    return all(b[1] <= a[1] + slack for a, b in zip(log, log[1:]))


_P = "select p_partkey as idx, p_retailprice as p from part"
_PQ = "select p_partkey as idx, p_retailprice as p, coalesce(q, 0.0::double) as q from part left join (select l_partkey, sum(l_quantity) as q from lineitem group by 1) on p_partkey = l_partkey"


def _long(vec, digits: int = 6) -> DataFrame:
    return vec.to_long().withColumn("value", F.round("value", digits) + F.lit(0.0))


def _vec_query(key: str, make, sql: str, digits: int = 6) -> None:
    register(key, f"select idx, round({sql}, {digits}) + 0.0::double as value from ({_PQ})")(lambda spark, d: _long(make(spark, d), digits))


@register("vec_layout", f"select p_partkey, (p_partkey // {B})::int as block_id, (p_partkey % {B})::int as pos, p_partkey as back from part")
def vec_layout(spark, d):
    block, offset = layout.split(F.col("p_partkey"), B)
    return io.table(spark, d, "part", ["p_partkey"]).select("p_partkey", block.alias("block_id"), offset.alias("pos"), layout.join(block, offset, B).alias("back"))


_vec_query("vec_roundtrip", _price, "p")
_vec_query("vec_add", lambda s, d: ops.add(_price(s, d), _qty(s, d)), "p + q")
_vec_query("vec_sub", lambda s, d: ops.sub(_price(s, d), _qty(s, d)), "p - q")
_vec_query("vec_mul", lambda s, d: ops.mul(_price(s, d), _qty(s, d)), "p * q", 4)
_vec_query("vec_div", lambda s, d: ops.div(_qty(s, d), _price(s, d)), "q / p")
_vec_query("vec_scale", lambda s, d: ops.rdiv(2.0, ops.shift(ops.scale(_price(s, d), 0.5), 1.0)), "2.0::double / (p * 0.5::double + 1.0::double)")
_vec_query("vec_rsub", lambda s, d: ops.rsub(1000.0, _price(s, d)), "1000.0::double - p")
_vec_query("vec_keyed_zip", lambda s, d: ops.keyed_zip(_price(s, d), _qty(s, d), lambda i, x, y: F.when(i % 2 == 0, x).otherwise(y)), "case when idx % 2 = 0 then p else q end")
_vec_query("vec_lincomb", lambda s, d: ops.lincomb([1.0, -0.5, 2.0], [_price(s, d), _qty(s, d), _price(s, d)]), "3.0::double * p - 0.5::double * q", 5)
_vec_query("vec_soft_threshold", lambda s, d: ops.soft_threshold(ops.shift(_price(s, d), -1000.0), 50.0), "case when abs(p - 1000.0::double) < 50 then 0.0::double else (p - 1000.0::double) - sign(p - 1000.0::double) * 50.0::double end")
_vec_query("vec_clip_sign", lambda s, d: ops.clip(ops.sign(ops.shift(_price(s, d), -1000.0)), 0.0, 1.0), "greatest(0.0::double, least(1.0::double, sign(p - 1000.0::double)::double))")
_vec_query("vec_concat_slice", lambda s, d: concat([("u", _price(s, d)), ("v", _qty(s, d))]).segment("v"), "q")


@register("vec_dot", f"select round(sum(p * q), 2) as dot, round(sum(p * p), 2) as self_dot from ({_PQ})")
def vec_dot(spark, d):
    p, q = _price(spark, d), _qty(spark, d)
    return ops.dot_df(p, q).join(ops.dot_df(p, p).withColumnRenamed("dot", "self_dot")).select(F.round("dot", 2).alias("dot"), F.round("self_dot", 2).alias("self_dot"))


@register("vec_norm_p", "select round(sum(abs(c_acctbal)), 4) as n1, round(sqrt(sum(c_acctbal * c_acctbal)), 4) as n2, round(pow(sum(pow(abs(c_acctbal), 3)), 1.0::double / 3), 4) as n3, round(max(abs(c_acctbal)), 4) as n_inf from customer")
def vec_norm_p(spark, d):
    c = io.table(spark, d, "customer", ["c_custkey", "c_acctbal"])
    v = from_long(c, c.count(), B, "c_custkey", "c_acctbal").cut()
    return _one(spark, **{k: round(ops.norm(v, p), 4) for k, p in (("n1", 1), ("n2", 2), ("n3", 3), ("n_inf", float("inf")))})


@register("vec_gram", f"select * from (select 0 as i, 0 as j, round(sum(p * p), 2) as v from ({_PQ}) union all select 0, 1, round(sum(p * q), 2) from ({_PQ}) union all select 1, 1, round(sum(q * q), 2) from ({_PQ}))")
def vec_gram(spark, d):
    g = ops.gram([_price(spark, d), _qty(spark, d)])
    return spark.createDataFrame([(i, j, round(float(g[i, j]), 2)) for i in range(2) for j in range(i, 2)], "i int, j int, v double")


@register("vec_stacked_rows", f"select idx, round(q, 6) as value from ({_PQ})")
def vec_stacked_rows(spark, d):
    return _long(stack([_price(spark, d), _qty(spark, d)]).row(1))


@register("vec_views", f"select idx, round(p, 6) as value from ({_PQ})")
def vec_views(spark, d):
    return _long(_price(spark, d).as_stacked(2).as_dense())


@register("vec_nnz", f"select count(*) filter (q <> 0) as nnz, count(*) as n from ({_PQ})")
def vec_nnz(spark, d):
    q = _qty(spark, d)
    return _one(spark, nnz=ops.nnz(q), n=q.length)


@register("vec_tree_sum", "select l_returnflag, round(sum(l_quantity), 2) as q from lineitem group by 1")
def vec_tree_sum(spark, d):
    df = io.table(spark, d, "lineitem", ["l_returnflag", "l_quantity"]).withColumnRenamed("l_quantity", "q")
    return ops.tree_sum(df, ["l_returnflag"], "q").select("l_returnflag", F.round("q", 2).alias("q"))


@register("vec_constructors", "select idx, v, z, (('0x' || substr(md5('7:0:' || idx), 1, 8))::bigint / 4294967296.0::double) * 2.0::double - 1.0::double as u from (select unnest(range(600)) as idx, 2.5::double as v, 0.0::double as z)")
def vec_constructors(spark, d):
    f, z, u = (v.to_long().withColumnRenamed("value", n) for v, n in ((fill(spark, 600, 2.5, B), "v"), (zeros(spark, 600, B), "z"), (uniform(spark, 600, 7, -1.0, 1.0, B), "u")))
    return f.join(z, "idx").join(u, "idx")


@register("vec_float", f"select true as ok from ({_P}) limit 1")
def vec_float(spark, d):
    p = io.table(spark, d, "part", ["p_partkey", "p_retailprice"])
    f = from_long(p, p.count(), B, "p_partkey", "p_retailprice", dtype="float")
    return _ok(spark, dict(f.df.dtypes)["values"] == "array<float>", abs(ops.dot(f, f) / ops.dot(_price(spark, d), _price(spark, d)) - 1) < 1e-5)


@register("vec_cut_modes", OK)
def vec_cut_modes(spark, d):
    p = _price(spark, d)
    want = ops.dot(p, p)
    return _ok(spark, *[abs(ops.dot(p.cut(m), p) - want) < 1e-6 * want for m in ("files", "checkpoint", "table")])


# planted regression on orders ------------------------------------------------------------------------------------------

_W1 = f"with ids as (select o_orderkey as example_id from orders), feats as ({workloads.FEATURES_SQL.format(d=10007, nnz=30)}), y as (select example_id, sum(value * {workloads.TRUE_SQL}) as label from feats group by 1)"
_FIX = "((feature_id % 7 - 3) / 10.0::double)"


def _fixed(spark: SparkSession, n: int, block: int = 1024):
    """Arithmetic weights at which single evaluations are compared."""
    from gridmin.vectors import from_expr

    return from_expr(spark, n, lambda row, i: (i % 7 - 3) / F.lit(10.0), block)


@register("w1_response", f"{_W1} select example_id, round(label, 8) + 0.0::double as label from y")
def w1_response(spark, d):
    return workloads.w1(spark, d).objective.labels.select("example_id", (F.round("label", 8) + F.lit(0.0)).alias("label"))


@register("w1_score", f"{_W1} select example_id, round(sum(value * {_FIX}), 8) + 0.0::double as score from feats group by 1")
def w1_score(spark, d):
    f = workloads.w1(spark, d).objective
    return f.scores(_fixed(spark, 10_007)).select("example_id", (F.round(F.col("s")[0], 8) + F.lit(0.0)).alias("score"))


_W1E = f"{_W1}, s as (select example_id, sum(value * {_FIX}) as s from feats group by 1), e as (select example_id, s - label as r from s join y using (example_id))"


@register("w1_loss", f"{_W1E} select round(avg(r * r), 6) as loss from e")
def w1_loss(spark, d):
    return _one(spark, loss=round(workloads.w1(spark, d).objective.value(_fixed(spark, 10_007)), 6))


@register("w1_gradient", f"{_W1E} select feature_id as idx, round(sum(2 * r * value) / (select count(*) from e), 9) + 0.0::double as value from feats join e using (example_id) group by 1")
def w1_gradient(spark, d):
    f = workloads.w1(spark, d)
    g = _long(f.objective.gradient(_fixed(spark, 10_007)), 9)
    return g.join(f.data["features"].select(F.col("feature_id").alias("idx")).distinct(), "idx", "left_semi")


@register("w1_lbfgs_recovery", OK)
def w1_lbfgs_recovery(spark, d):
    w = workloads.w1(spark, d, d=503, minimiser=workloads.quick(25, 1e-6))
    r = w.run()
    from gridmin.vectors import from_expr

    truth = from_expr(spark, 503, lambda row, i: workloads.true_weight(i), 1024)
    return _ok(spark, metrics.recovery(r.x, truth)["max"] < 1e-3, r.value < 1e-6)


@register("w1a_overfit_trace", "select i::int as iteration, true as below from range(0, 5) t(i)")
def w1a_overfit_trace(spark, d):
    """One batch in the regime of few examples a weight: by iteration 4 the loss has fallen below 1/1000 of its start."""
    w = workloads.w1(spark, d, d=30_011, only=0, minimiser=workloads.quick(4, 1e-12))
    log = w.run().log
    return spark.createDataFrame([(r[0], r[1] <= log[0][1] * (1e-3 if r[0] == 4 else 1.0 + 1e-9)) for r in log[:5]], "iteration int, below boolean")


_W1B = f"with ids as (select o_orderkey as example_id from orders), feats as ({workloads.FEATURES_SQL.format(d=30011, nnz=30)}), y as (select example_id, sum(value * {workloads.TRUE_SQL}) as label from feats group by 1)"


@register("w1b_rotation_trace", f"{_W1B} select i::int as iteration, (i % 5)::int as batch_id, case when i = 0 then (select round(avg(label * label), 6) from y where example_id % 5 = 0) end as start, case when i = 5 then true end as has_fallen from range(0, 6) t(i)")
def w1b_rotation_trace(spark, d):
    """Another batch each iteration: which one, the loss at the start, and a loss well below it after a pass over the data."""
    log = workloads.w1(spark, d, d=30_011, batches=5, minimiser=workloads.quick(5)).run().log
    rows = [(r[0], r[6], round(r[1], 6) if r[0] == 0 else None, r[1] < 0.9 * log[0][1] if r[0] == 5 else None) for r in log]
    return spark.createDataFrame(rows, "iteration int, batch_id int, start double, has_fallen boolean")


# real regression on lineitem -------------------------------------------------------------------------------------------

_Z = """with m as (select avg(l_quantity) a, stddev_pop(l_quantity) sa, avg(l_discount) b, stddev_pop(l_discount) sb, avg(l_tax) c, stddev_pop(l_tax) sc, avg(l_extendedprice) y, stddev_pop(l_extendedprice) sy from lineitem),
z as (select (l_quantity - a) / sa as x0, (l_discount - b) / sb as x1, (l_tax - c) / sc as x2, (l_extendedprice - y) / sy as y from lineitem, m)"""


@register("w1r_lbfgs_trace", f"""{_Z}, a as (select *, x1 - x0 * (select regr_slope(x1, x0) from z) as u1, x2 - x0 * (select regr_slope(x2, x0) from z) as u2, y - x0 * (select regr_slope(y, x0) from z) as r0 from z),
b as (select *, u2 - u1 * (select regr_slope(u2, u1) from a) as t2, r0 - u1 * (select regr_slope(r0, u1) from a) as r1 from a),
c as (select r1 - t2 * (select regr_slope(r1, t2) from b) as r2 from b)
select 'start' as at, (select round(avg(y * y), 5) from z) as value union all select 'end', (select round(avg(r2 * r2), 5) from c)""")
def w1r_lbfgs_trace(spark, d):
    """Loss at the start and at the end, which is the residual of least squares by orthogonal steps."""
    log = workloads.w1r(spark, d).run().log
    return spark.createDataFrame([("start", round(log[0][1], 5)), ("end", round(log[-1][1], 5))], "at string, value double")


def _steps_sql(update: str, steps: int, extra: str = "") -> str:
    """Unrolled iterations: each step's gradient is an aggregate over all rows."""
    parts, prev = [_Z + ", p0 as (select 0.0::double w0, 0.0::double w1, 0.0::double w2, 0.0::double w3, 0.0::double h0, 0.0::double h1, 0.0::double h2, 0.0::double h3)"], "p0"
    for t in range(1, steps + 1):
        cols = ", ".join(f"2 * avg((w0 * x0 + w1 * x1 + w2 * x2 + w3 - y) * {f'x{i}' if i < 3 else '1.0::double'}) as g{i}" for i in range(4))
        parts.append(f"g{t} as (select {cols}, any_value(w0) w0, any_value(w1) w1, any_value(w2) w2, any_value(w3) w3, any_value(h0) h0, any_value(h1) h1, any_value(h2) h2, any_value(h3) h3 from z, {prev})")
        parts.append(f"p{t} as (select " + ", ".join(f"({update.format(w=f'w{i}', g=f'g{i}', h=f'h{i}', t=t)}) as w{i}" for i in range(4)) + ", " + ", ".join(_history(i, t, extra) for i in range(4)) + f" from g{t})")
        prev = f"p{t}"
    return ", ".join(parts) + " " + " union all ".join(f"select {i}::bigint as idx, round(w{i}, 8) + 0.0::double as value from {prev}" for i in range(4))


def _history(i: int, t: int, memory: str) -> str:
    m = int(memory) if memory else None
    return f"h{i} + g{i} * g{i} as h{i}" if m is None or t <= m else f"(1 - 1.0::double / {m}) * h{i} + g{i} * g{i} / {m} as h{i}"


def _fit_steps(key: str, make, sql: str) -> None:
    register(key, sql)(lambda spark, d: _long(workloads.w1r(spark, d, make()).run().x, 8))


_S = "sqrt({h} + {g} * {g} + 1e-2::double)"
_fit_steps("sgd_constant", lambda: optim.GradientDescent(0.1, stop=[optim.MaxIter(3)]), _steps_sql("{w} - 0.1::double * {g}", 3))
_fit_steps("sgd_power_decay", lambda: optim.GradientDescent(optim.PowerDecay(0.2, 0.5), stop=[optim.MaxIter(3)]), _steps_sql("{w} - 0.2::double * pow({t}::double, -0.5::double) * {g}", 3))
_fit_steps("adagrad_plain", lambda: optim.AdaptiveGradient(0.1, 1e-2, stop=[optim.MaxIter(3)]), _steps_sql(f"({_S} * {{w}} - 0.1::double * {{g}}) / {_S}", 3))
_fit_steps("adagrad_l2", lambda: optim.AdaptiveGradient(0.1, 1e-2, l2=0.5, stop=[optim.MaxIter(3)]), _steps_sql(f"({_S} * {{w}} - 0.1::double * {{g}}) / ({_S} + 0.05::double)", 3))
_fit_steps("adagrad_memory", lambda: optim.AdaptiveGradient(0.1, 1e-2, memory=2, stop=[optim.MaxIter(4)]), _steps_sql(f"({_S} * {{w}} - 0.1::double * {{g}}) / {_S}", 4, "2"))


def _prox(z: str, theta: str) -> str:
    return f"case when abs({z}) < {theta} then 0.0::double else {z} - {theta} * sign({z}) end"


_fit_steps("adagrad_l1", lambda: optim.AdaptiveGradient(0.1, 1e-2, l1=0.01, stop=[optim.MaxIter(3)]), _steps_sql(_prox(f"(({_S} * {{w}} - 0.1::double * {{g}}) / {_S})", f"(0.001::double / {_S})"), 3))
_fit_steps("adagrad_elastic", lambda: optim.AdaptiveGradient(0.1, 1e-2, l1=0.01, l2=0.5, stop=[optim.MaxIter(3)]), _steps_sql(_prox(f"(({_S} * {{w}} - 0.1::double * {{g}}) / ({_S} + 0.05::double))", f"(0.001::double / {_S})"), 3))
_fit_steps("adagrad_exact_prox", lambda: optim.AdaptiveGradient(0.1, 1e-2, l1=0.01, l2=0.5, prox="exact", stop=[optim.MaxIter(3)]), _steps_sql(_prox(f"(({_S} * {{w}} - 0.1::double * {{g}}) / ({_S} + 0.05::double))", f"(0.001::double / ({_S} + 0.05::double))"), 3))


@register("w1_gd3", _steps_sql("{w} - 0.1::double * {g}", 3))
def w1_gd3(spark, d):
    return _long(workloads.w1r(spark, d, optim.GradientDescent(0.1, stop=[optim.MaxIter(3)])).run().x, 8)


@register("w1r_lbfgs_normal_eq", f"{_Z} select round(regr_slope(y, x0), 4) + 0.0::double as slope, round(regr_intercept(y, x0), 4) + 0.0::double as intercept from z")
def w1r_lbfgs_normal_eq(spark, d):
    w = workloads.w1r(spark, d)
    feats = w.data["features"].where("feature_id in (0, 3)")
    r = workloads.linear(feats, w.data["labels"], 4, losses.Squared(), 4).run()
    x = {i["idx"]: i["value"] for i in r.x.to_long().collect()}
    return _one(spark, slope=round(x[0], 4) + 0.0, intercept=round(x[3], 4) + 0.0)


@register("ridge_fit", f"{_Z} select round(avg(x0 * y) / (avg(x0 * x0) + 0.05::double), 5) + 0.0::double as w from z")
def ridge_fit(spark, d):
    w = workloads.w1r(spark, d)
    r = workloads.linear(w.data["features"].where("feature_id = 0"), w.data["labels"], 1, losses.Squared(), 4, workloads.quick(10, l2=0.1)).run()
    return _one(spark, w=round(r.x.to_long().first()["value"], 5) + 0.0)


# grid -------------------------------------------------------------------------------------------------------------------


@register("grid_cells_nnz", f"with ids as (select o_orderkey as example_id from orders), feats as ({workloads.FEATURES_SQL.format(d=10007, nnz=30)}) select count(*) filter (value <> 0) as nnz, count(distinct example_id || ':' || feature_id // 1024) filter (value <> 0) as routes from feats")
def grid_cells_nnz(spark, d):
    cells = workloads.w1(spark, d).data["cells"]
    nnz = cells.agg(F.sum(F.size("vals"))).first()[0]
    return _one(spark, nnz=int(nnz), routes=grid.routes(cells).count())


STRATEGIES = ("broadcast", "gather", "replicate", "stationary")


@register("grid_strategies_agree", f"{_W1E} select strategy, round(avg(r * r), 6) as loss from e, (select unnest({list(STRATEGIES)}) as strategy) group by 1")
def grid_strategies_agree(spark, d):
    w = workloads.w1(spark, d)
    x, f = _fixed(spark, 10_007).cut(), w.objective
    rows = []
    for s in STRATEGIES:
        f.strategy = s
        rows.append((s, round(f.value(x), 6)))
    return spark.createDataFrame(rows, "strategy string, loss double")


@register("grid_strategies_gradient", f"{_W1E}, g as (select feature_id, sum(2 * r * value) / (select count(*) from e) as v from feats join e using (example_id) group by 1) select strategy, round(sum(abs(v)), 6) as l1, round(sqrt(sum(v * v)), 6) as l2 from g, (select unnest({list(STRATEGIES)}) as strategy) group by 1")
def grid_strategies_gradient(spark, d):
    """Norms of the gradient whose derivatives were sent back under each strategy."""
    w = workloads.w1(spark, d)
    x, f, rows = _fixed(spark, 10_007).cut(), w.objective, []
    for s in STRATEGIES:
        f.strategy = s
        g = f.gradient(x)
        rows.append((s, round(ops.norm(g, 1), 6), round(ops.norm(g, 2), 6)))
    return spark.createDataFrame(rows, "strategy string, l1 double, l2 double")


@register("grid_chosen", f"with ids as (select o_orderkey as example_id from orders), feats as ({workloads.FEATURES_SQL.format(d=10007, nnz=30)}) select 10007 as e, count(distinct example_id || ':' || feature_id // 1024) as routes, count(distinct feature_id // 1024) as feat_parts, true as least from feats where value <> 0")
def grid_chosen(spark, d):
    """What the choice looks at, and that the objective uses the cheapest strategy that keeps all cores busy."""
    f, x = workloads.w1(spark, d).objective, _fixed(spark, 10_007)
    s = grid.stats(f.cells, x, f.ex_parts)
    c = grid.costs(s)
    allowed = [k for k in c if k != "stationary" or s.feat_parts >= max(2, s.cores)]
    return _one(spark, e=s.e, routes=int(s.routes), feat_parts=int(s.feat_parts), least=c[f.grid.strategy_for(x)] == min(c[k] for k in allowed))


@register("grid_empty_cells", "select c_custkey::int as example_id, count(distinct (o_orderkey % 8) // 2)::int as n_cells, coalesce(sum(case o_orderkey % 8 when 2 then 0.5::double when 6 then 2.0::double else (o_orderkey % 8) / 4.0::double end), 0.0::double) as score from customer left join orders on o_custkey = c_custkey group by 1")
def grid_empty_cells(spark, d):
    """Example parts by four feature blocks: customers, whose orders (mod 8) are the features. Some miss blocks, some have no feature at all."""
    orders = io.table(spark, d, "orders", ["o_custkey", "o_orderkey"])
    feats = orders.select(F.col("o_custkey").alias("example_id"), (F.col("o_orderkey") % 8).alias("feature_id"), F.lit(1.0).alias("value"))
    labels = io.table(spark, d, "customer", ["c_custkey"]).select(F.col("c_custkey").alias("example_id"), F.lit(0.0).alias("label"))
    parts = grid.example_parts(labels, 3)
    cells = grid.build_cells(feats, parts, 2).persist()
    f = Linear(cells, labels, losses.Squared(), parts)
    x = from_long(spark.createDataFrame([(i, i / 4.0 + 0.0) for i in range(8)], "idx long, value double").withColumn("value", F.expr("case idx when 2 then 0.5D when 6 then 2.0D else value end")), 8, 2)
    n = grid.routes(cells).groupBy("example_id").agg(F.count("*").alias("n_cells"))
    rows = labels.select("example_id").join(n, "example_id", "left").join(f.scores(x), "example_id", "left")
    return rows.select(F.col("example_id").cast("int").alias("example_id"), F.coalesce("n_cells", F.lit(0)).cast("int").alias("n_cells"), F.coalesce(F.col("s")[0], F.lit(0.0)).alias("score"))


@register("grid_salted", "select l_partkey, count(*) as n, round(sum(l_quantity), 2) as q from lineitem group by 1")
def grid_salted(spark, d):
    df = grid.salt(io.table(spark, d, "lineitem", ["l_partkey", "l_quantity"]), "l_partkey", 4)
    part = df.groupBy("l_partkey", "salt").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))
    return part.groupBy("l_partkey").agg(F.sum("n").alias("n"), F.round(F.sum("q"), 2).alias("q"))


@register("planner_costs", "with s as (select (select count(*) from part)::double as e, 100 as ex_parts, (select count(*) from (select distinct l_orderkey, l_partkey // 1024 from lineitem))::double as routes, (select count(*) from (select distinct l_orderkey % 100, l_partkey from lineitem))::double as gathers), b as (select *, 2 * routes * 16 as there_and_back from s) select 'replicate' as strategy, ex_parts * e * 8 + there_and_back as bytes from b union all select 'stationary', there_and_back from b union all select 'gather', gathers * 24 + there_and_back from b")
def planner_costs(spark, d):
    """Parts as weights in 100 example parts, orders as examples, their lines as features."""
    li, e = io.table(spark, d, "lineitem", ["l_orderkey", "l_partkey"]), io.table(spark, d, "part", ["p_partkey"]).count()
    routes = li.select("l_orderkey", F.floor(F.col("l_partkey") / 1024)).distinct().count()
    gathers = li.select(F.col("l_orderkey") % 100, "l_partkey").distinct().count()
    c = grid.costs(grid.Stats(e, 1, 100, layout.n_blocks(e, 1024), routes, gathers, 400))
    return spark.createDataFrame([(k, c[k]) for k in ("replicate", "stationary", "gather")], "strategy string, bytes double")


# line searches and quasi-Newton ------------------------------------------------------------------------------------------


def _quadratic(spark):
    rows = lambda a: from_long(spark.createDataFrame([(i, float(v)) for i, v in enumerate(a)], "idx long, value double"), len(a), 2)
    return Quadratic(rows([1, 10]), rows([1, 2])), rows([0, 0])


def _priced(spark, d):
    """Quadratic over all parts with curvature 1 to 3 and slopes from their prices, and the point zero."""
    from gridmin.vectors import from_expr

    p = io.table(spark, d, "part", ["p_partkey", "p_retailprice"]).withColumn("p_retailprice", F.col("p_retailprice") / 1000.0)
    n = p.count()
    return Quadratic(from_expr(spark, n, lambda row, i: (1 + i % 3).cast("double"), B).cut(), from_long(p, n, B, "p_partkey", "p_retailprice").cut()), zeros(spark, n, B).cut()


@register("lbfgs_quadratic", "select * from (values (0::bigint, 1.0::double), (1::bigint, 0.2::double)) t(idx, value)")
def lbfgs_quadratic(spark, d):
    f, x = _quadratic(spark)
    return _long(optim.LimitedMemory(stop=[optim.GradNorm(1e-9), optim.MaxIter(15)]).run(f, x).x, 6)


@register("lbfgs_two_loop_step", OK)
def lbfgs_two_loop_step(spark, d):
    """Coefficients from dot products against the recursion on the vectors themselves: prices and quantities of all parts."""
    p, q = ops.scale(_price(spark, d), 1e-3).cut(), ops.scale(_qty(spark, d), 1e-3).cut()
    s = [p, q, ops.mul(p, q).cut()]
    y = [ops.keyed_zip(v, v, lambda i, a, b: a * (1 + (i % 3) / F.lit(10.0))).cut() for v in s]
    g = ops.keyed_zip(p, q, lambda i, a, b: F.when(i % 2 == 0, a).otherwise(-b)).cut()
    fast = ops.lincomb(optim.two_loop(ops.gram([*s, *y, g]), 3).tolist(), [*s, *y, g])
    q, al = g, []
    for i in (2, 1, 0):
        al.append(ops.dot(s[i], q) / ops.dot(s[i], y[i]))
        q = ops.lincomb([1.0, -al[-1]], [q, y[i]]).cut()
    q = ops.scale(q, ops.dot(s[2], y[2]) / ops.dot(y[2], y[2])).cut()
    for i, a in zip(range(3), al[::-1]):
        q = ops.lincomb([1.0, a - ops.dot(y[i], q) / ops.dot(s[i], y[i])], [q, s[i]]).cut()
    return _ok(spark, ops.norm(ops.add(fast, q), float("inf")) < 1e-9 * max(1.0, ops.norm(q, float("inf"))))


@register("linesearch_wolfe_holds", OK)
def linesearch_wolfe_holds(spark, d):
    f, x = _priced(spark, d)
    v, g = f.evaluate(x)
    down = ops.scale(g, -1.0).cut()
    slope, line, ls = ops.dot(g, down), f.along(x, down), optim.StrongWolfe()
    eta, _ = ls.search(line, v, slope)
    phi, s = line.at([eta])[0]
    return _ok(spark, phi <= v + ls.c1 * eta * slope, abs(s) <= ls.c2 * abs(slope))


@register("linesearch_backtracking_holds", OK)
def linesearch_backtracking_holds(spark, d):
    f, x = _priced(spark, d)
    v, g = f.evaluate(x)
    down = ops.scale(g, -1.0).cut()
    slope, line, ls = ops.dot(g, down), f.along(x, down), optim.Backtracking()
    eta, _ = ls.search(line, v, slope)
    return _ok(spark, line.at([eta])[0][0] <= v + ls.c1 * eta * slope)


@register("owlqn_soft_threshold", OK)
def owlqn_soft_threshold(spark, d):
    """Orthogonal design: the minimum of mean (x_i - c_i)^2 + l1 |x| is the soft threshold of c."""
    rows = lambda a: from_long(spark.createDataFrame([(i, float(v)) for i, v in enumerate(a)], "idx long, value double"), len(a), 2)
    f = Quadratic(rows([1, 1, 1]), rows([2.0, -0.3, -1.5]))
    r = optim.OrthantWise(l1=0.5, stop=[optim.GradNorm(1e-8), optim.MaxIter(20)]).run(f, rows([0, 0, 0]))
    x = [v["value"] for v in r.x.to_long().orderBy("idx").collect()]
    return _ok(spark, max(abs(a - b) for a, b in zip(x, [1.5, 0.0, -1.0])) < 1e-6, x[1] == 0.0)


@register("owlqn_equals_lbfgs", OK)
def owlqn_equals_lbfgs(spark, d):
    f, x = _quadratic(spark)
    kw = {"stop": [optim.MaxIter(3)]}
    a = optim.LimitedMemory(line_search=optim.Backtracking(), **kw).run(f, x)
    b = optim.OrthantWise(l1=0.0, line_search=optim.Backtracking(), **kw).run(f, x)
    return _ok(spark, a.value == b.value, a.iterations == b.iterations)


@register("stop_reasons", "select * from (values ('gradient norm'), ('improvement'), ('iterations'), ('callback')) t(reason)")
def stop_reasons(spark, d):
    f, x = _quadratic(spark)
    runs = [optim.GradientDescent(0.05, stop=[optim.GradNorm(10.0)]), optim.GradientDescent(0.05, stop=[optim.Improvement(10.0)]), optim.GradientDescent(0.05, stop=[optim.MaxIter(1)]), optim.GradientDescent(0.05, stop=[optim.MaxIter(9)], callback=lambda s: s.iteration == 1)]
    return spark.createDataFrame([(m.run(f, x).reason.value,) for m in runs], "reason string")


@register("resume_from_saved", OK)
def resume_from_saved(spark, d):
    """Gradient descent broken off after two steps and resumed equals the run without a break."""
    import uuid

    from gridmin.vectors.vec import shared_dir

    f, x = _quadratic(spark)
    path = f"{shared_dir(spark)}/resume-{uuid.uuid4().hex}"
    whole = optim.GradientDescent(0.05, stop=[optim.MaxIter(4)]).run(f, x)
    optim.GradientDescent(0.05, stop=[optim.MaxIter(2)]).run(f, x, save_to=path)
    rest = optim.GradientDescent(0.05, stop=[optim.MaxIter(4)]).run(f, x, resume_from=path)
    return _ok(spark, abs(whole.value - rest.value) < 1e-12, rest.log[0][0] == 2)


# losses ------------------------------------------------------------------------------------------------------------------

_SIG = "case when s >= 0 then 1.0::double / (1.0::double + exp(-abs(s))) else exp(-abs(s)) / (1.0::double + exp(-abs(s))) end"
_EV = "with e as (select event_id, value / 100.0::double as y, (event_id % 13 - 6) / 4.0::double as s, (event_id % 2)::double as b from events)"


def _losses(key: str, loss, label: str, value_sql: str, deriv_sql: str) -> None:
    def query(spark, d):
        e = io.table(spark, d, "events", ["event_id", "value"]).select("event_id", (F.col("value") / 100.0).alias("y"), ((F.col("event_id") % 13 - 6) / 4.0).alias("s"), (F.col("event_id") % 2).cast("double").alias("b"))
        s, y = F.col("s"), F.col(label)
        return e.agg(F.round(F.avg(loss.value(s, y)), 8).alias("loss"), F.round(F.avg(loss.derivative(s, y)), 8).alias("slope"))

    register(key, f"{_EV} select round(avg({value_sql}), 8) as loss, round(avg({deriv_sql}), 8) as slope from e")(query)


_SP = "ln(1.0::double + exp(-abs({0}))) + greatest({0}, 0.0::double)"
_losses("loss_squared", losses.Squared(), "y", "(s - y) * (s - y)", "2 * (s - y)")
_losses("loss_quantile", losses.Quantile(0.9), "y", "case when y - s >= 0 then (y - s) * 0.9::double else (y - s) * (0.9::double - 1.0::double) end", "case when y - s > 0 then -0.9::double when y - s < 0 then 1.0::double - 0.9::double else 0.0::double end")
_losses("loss_logistic", losses.Logistic(), "b", f"{_SP.format('s')} - b * s", f"({_SIG}) - b")
_losses("loss_pairwise", losses.Pairwise(), "b", _SP.format("(-s)"), f"-(1.0::double - ({_SIG}))")
_losses("user_loss", losses.huber(1.0), "y", "case when abs(s - y) <= 1 then 0.5::double * (s - y) * (s - y) else abs(s - y) - 0.5::double end", "greatest(-1.0::double, least(1.0::double, s - y))")


_CLS = "with e as (select vec_id, label, [((vec_id + c * 5) % 11 - 5) / 3.0::double for c in range(10)] as s from embeddings), z as (select *, ln(list_sum([exp(v) for v in s])) as z from e)"


def _scores10():
    return F.transform(F.sequence(F.lit(0), F.lit(9)), lambda c: ((F.col("vec_id") + c * 5) % 11 - 5) / F.lit(3.0))


@register("loss_softmax", f"{_CLS} select round(avg(z - s[label + 1]), 8) as loss, round(avg(exp(s[1] - z) - (label = 0)::int), 8) as slope0 from z")
def loss_softmax(spark, d):
    e, loss = io.table(spark, d, "embeddings", ["vec_id", "label"]).withColumn("s", _scores10()), losses.Softmax(10)
    return e.agg(F.round(F.avg(loss.value(F.col("s"), F.col("label"))), 8).alias("loss"), F.round(F.avg(loss.derivative(F.col("s"), F.col("label"))[0]), 8).alias("slope0"))


@register("loss_multilabel", "with e as (select [((doc_id + c * 5) % 11 - 5) / 3.0::double for c in range(2)] as s, quality::double as q, toxic::double * 2.0::double as t from labels), z as (select *, ln(exp(s[1]) + exp(s[2])) as z from e) select round(avg(q * (z - s[1]) + t * (z - s[2])), 8) as loss, round(avg((q + t) * exp(s[1] - z) - q), 8) as slope0 from z")
def loss_multilabel(spark, d):
    s = F.transform(F.sequence(F.lit(0), F.lit(1)), lambda c: ((F.col("doc_id") + c * 5) % 11 - 5) / F.lit(3.0))
    t = F.array(F.struct(F.lit(0).alias("class"), F.col("quality").cast("double").alias("weight")), F.struct(F.lit(1).alias("class"), (F.col("toxic") * 2.0).alias("weight")))
    e, loss = io.table(spark, d, "labels").select(s.alias("s"), t.alias("t")), losses.Softmax(2, targets=True)
    return e.agg(F.round(F.avg(loss.value(F.col("s"), F.col("t"))), 8).alias("loss"), F.round(F.avg(loss.derivative(F.col("s"), F.col("t"))[0]), 8).alias("slope0"))


def _constant_fit(spark, labels, loss, minimiser=None):
    feats = labels.select("example_id", F.lit(0).cast("long").alias("feature_id"), F.lit(1.0).alias("value"))
    return workloads.linear(feats, labels, 1, loss, 4, minimiser or workloads.quick(20)).run()


@register("logistic_prior_fit", "select round(ln(avg(quality) / (1 - avg(quality))), 4) as w from labels")
def logistic_prior_fit(spark, d):
    lab = io.table(spark, d, "labels").select(F.col("doc_id").alias("example_id"), F.col("quality").cast("double").alias("label"))
    return _one(spark, w=round(_constant_fit(spark, lab, losses.Logistic()).x.to_long().first()["value"], 4))


@register("softmax_prior_fit", "select round(-sum(p * ln(p)), 5) as loss from (select count(*) / (select count(*) from embeddings)::double as p from embeddings group by label)")
def softmax_prior_fit(spark, d):
    lab = io.table(spark, d, "embeddings", ["vec_id", "label"]).select(F.col("vec_id").alias("example_id"), F.col("label").cast("double").alias("label"))
    return _one(spark, loss=round(_constant_fit(spark, lab, losses.Softmax(10)).value, 5))


@register("quantile_fit", OK)
def quantile_fit(spark, d):
    """Objective at the fit against the objective at the exact group medians: within two per cent."""
    w = workloads.w7(spark, d, 0.5)
    r = w.run()
    e = io.table(spark, d, "events", ["event_type", "value"]).withColumn("y", F.col("value") / 100.0)
    med = e.groupBy("event_type").agg(F.expr("percentile_disc(0.5) within group (order by y)").alias("m"))
    best = e.join(F.broadcast(med), "event_type").agg(F.avg(losses.Quantile(0.5).value(F.col("m"), F.col("y")))).first()[0]
    return _ok(spark, best - 1e-9 <= r.value, r.value <= best * 1.02)


# softmax on embeddings ---------------------------------------------------------------------------------------------------

_SMX = """with x as (select vec_id, label, embedding from embeddings), s as (select vec_id, label, embedding, [list_sum([embedding[j + 1]::double * (((c * 64 + j) % 7 - 3) / 10.0::double) for j in range(64)]) for c in range(10)] as s from x),
z as (select *, ln(list_sum([exp(v) for v in s])) as z from s)"""


def _w10(spark):
    from gridmin.vectors import from_expr

    return from_expr(spark, 64, lambda row, i: ((row.cast("long") * 64 + i) % 7 - 3) / F.lit(10.0), 64, stack=10)


@register("softmax_embeddings_loss", f"{_SMX} select round(avg(z - s[label + 1]), 7) as loss from z")
def softmax_embeddings_loss(spark, d):
    return _one(spark, loss=round(workloads.w2(spark, d).objective.value(_w10(spark)), 7))


@register("softmax_embeddings_gradient", f"{_SMX} select c::int as row, j as idx, round(avg((exp(s[c + 1] - z) - (label = c)::int) * embedding[j + 1]::double), 8) + 0.0::double as value from z, (select unnest(range(10)) as c), (select unnest(range(64)) as j) group by 1, 2")
def softmax_embeddings_gradient(spark, d):
    return _long(workloads.w2(spark, d).objective.gradient(_w10(spark)), 8)


@register("softmax_embeddings_fit", OK)
def softmax_embeddings_fit(spark, d):
    r = workloads.w2(spark, d, workloads.quick(10)).run()
    return _ok(spark, abs(r.log[0][1] - math.log(10)) < 1e-9, r.value < 1.75)


# factorization machines ----------------------------------------------------------------------------------------------------

_EVF = """with e as (select event_id as example_id, user_id, event_type as query, (props->>'$.k')::bigint as item, value from events),
feats as (select example_id, user_id % 200 as feature_id from e union all select example_id, 200 + ('0x' || substr(md5('q:' || query), 1, 8))::bigint % 97 from e union all select example_id, 300 + item from e),
x as (select unnest(range(512)) as feature_id), xs as (select feature_id, [((feature_id * (k + 3)) % 11 - 5) / 10.0::double for k in range(4)] as v from x)"""


def _fm_weights(spark):
    from gridmin.vectors import from_expr

    return from_expr(spark, 512, lambda row, i: ((i * (row + 3)) % 11 - 5) / F.lit(10.0), 512, stack=4)


_FMS = f"{_EVF}, s as (select a.example_id, sum(list_dot_product(p.v, q.v)) as score from feats a join feats b on a.example_id = b.example_id and a.feature_id < b.feature_id join xs p on p.feature_id = a.feature_id join xs q on q.feature_id = b.feature_id group by 1)"


@register("fm_score", f"{_FMS} select example_id, round(score, 8) + 0.0::double as score from s")
def fm_score(spark, d):
    return workloads.w4(spark, d).objective.scores(_fm_weights(spark)).select("example_id", (F.round("score", 8) + F.lit(0.0)).alias("score"))


@register("fm_score_bruteforce", f"{_FMS} select example_id, round(score, 8) + 0.0::double as score, round(2 * score, 8) + 0.0::double as ordered from s")
def fm_score_bruteforce(spark, d):
    feats = workloads.event_features(workloads.events(spark, d)).groupBy("example_id", "feature_id").agg(F.sum("value").alias("value"))
    s = baselines.fm_bruteforce(feats, _fm_weights(spark))
    return s.select("example_id", (F.round("score", 8) + F.lit(0.0)).alias("score"), (F.round(2 * F.col("score"), 8) + F.lit(0.0)).alias("ordered"))


@register("fm_gradient", f"""{_FMS}, t as (select example_id, [sum(v[k]) for k in [1]][1] as dummy from feats join xs using (feature_id) group by 1),
tl as (select example_id, k, sum(v[k + 1]) as t from feats join xs using (feature_id), (select unnest(range(4)) as k) group by 1, 2),
r as (select s.example_id, 2 * (score - value / 100.0::double) as ds from s join e on e.example_id = s.example_id)
select k::int as row, feature_id as idx, round(sum(ds * (t - v[k + 1])) / (select count(*) from e), 8) + 0.0::double as value
from feats join xs using (feature_id) join r using (example_id) join tl using (example_id) group by 1, 2""".replace("t as (select example_id, [sum(v[k]) for k in [1]][1] as dummy from feats join xs using (feature_id) group by 1),\n", ""))
def fm_gradient(spark, d):
    w = workloads.w4(spark, d)
    g = _long(w.objective.gradient(_fm_weights(spark)), 8)
    seen = workloads.event_features(workloads.events(spark, d)).select(F.col("feature_id").alias("idx")).distinct()
    return g.join(seen, "idx", "left_semi")


_U = "((('0x' || substr(md5('{seed}:' || k || ':' || feature_id), 1, 8))::bigint / 4294967296.0::double) * (0.1::double + 0.1::double) - 0.1::double)"


@register("fm_fit_trace", f"""{_EVF.replace("((feature_id * (k + 3)) % 11 - 5) / 10.0::double", _U.format(seed=5))}, s as (select a.example_id, sum(list_dot_product(p.v, q.v)) as score from feats a join feats b on a.example_id = b.example_id and a.feature_id < b.feature_id join xs p on p.feature_id = a.feature_id join xs q on q.feature_id = b.feature_id group by 1)
select round(avg((score - value / 100.0::double) * (score - value / 100.0::double)), 6) as start, true as falls from s join e using (example_id)""")
def fm_fit_trace(spark, d):
    """The loss at the start, and that it falls to nearer the labels' variance, which a constant reaches, than to its start."""
    log = workloads.w4(spark, d).run().log
    floor = io.table(spark, d, "events", ["value"]).agg(F.var_pop(F.col("value") / 100.0)).first()[0]
    return _one(spark, start=round(log[0][1], 6), falls=_falls(log) and log[-1][1] - floor < 0.5 * (log[0][1] - floor))


_FML = f"""{_EVF}, lw as (select feature_id, ((feature_id * 5) % 7 - 3) / 10.0::double as w from x),
s as (select a.example_id, sum(list_dot_product(p.v, q.v)) as score from feats a join feats b on a.example_id = b.example_id and a.feature_id < b.feature_id join xs p on p.feature_id = a.feature_id join xs q on q.feature_id = b.feature_id group by 1),
li as (select example_id, sum(w) as score from feats join lw using (feature_id) group by 1)"""


def _fm_linear(spark, d):
    """Events with a bias feature (511, whose latent weights are zero), and weights of four latent rows and a linear one."""
    from gridmin.objective import Machines
    from gridmin.vectors import from_expr

    e = workloads.events(spark, d)
    feats = workloads.event_features(e).unionByName(e.select("example_id", F.lit(511).cast("long").alias("feature_id"), F.lit(1.0).alias("value")))
    x = from_expr(spark, 512, lambda row, i: F.when(row == 4, F.when(i == 511, F.lit(0.25)).otherwise(((i * 5) % 7 - 3) / F.lit(10.0))).otherwise(F.when(i == 511, F.lit(0.0)).otherwise(((i * (row + 3)) % 11 - 5) / F.lit(10.0))), 512, stack=5)
    f = Machines(grid.build_cells(feats, 4, 512).persist(), e.select("example_id", (F.col("value") / 100.0).alias("label")), losses.Squared(), 4, linear=True, bias=511)
    return f, x


@register("fm_linear_score", f"{_FML} select s.example_id, round(s.score + li.score + 0.25::double, 8) + 0.0::double as score from s join li on li.example_id = s.example_id")
def fm_linear_score(spark, d):
    f, x = _fm_linear(spark, d)
    return f.scores(x).select("example_id", (F.round("score", 8) + F.lit(0.0)).alias("score"))


@register("fm_linear_gradient", f"""{_FML}, r as (select s.example_id, 2 * (s.score + li.score + 0.25::double - value / 100.0::double) as ds from s join li on li.example_id = s.example_id join e on e.example_id = s.example_id),
tl as (select example_id, k, sum(v[k + 1]) as t from feats join xs using (feature_id), (select unnest(range(4)) as k) group by 1, 2), n as (select count(*)::double as n from e)
select k::int as row, feature_id as idx, round(sum(ds * (t - v[k + 1])) / any_value(n), 8) + 0.0::double as value from feats join xs using (feature_id) join r using (example_id) join tl using (example_id), n group by 1, 2
union all select 4, feature_id, round(sum(ds) / any_value(n), 8) + 0.0::double from feats join r using (example_id), n group by 2 union all select 4, 511, round(sum(ds) / any_value(n), 8) + 0.0::double from r, n
union all select k::int, 511, 0.0::double from (select unnest(range(4)) as k)""")
def fm_linear_gradient(spark, d):
    f, x = _fm_linear(spark, d)
    seen = f.cells.select("feat_part", F.explode("local_ids").alias("i")).select((F.col("feat_part").cast("long") * 512 + F.col("i")).alias("idx")).distinct()
    return _long(f.gradient(x), 8).join(seen, "idx", "left_semi")


# ranking ---------------------------------------------------------------------------------------------------------------------

_POS = """with pos as (select event_id as example_id, user_id, event_type as query, (props->>'$.k')::bigint as item from events where event_type in ('purchase', 'click')),
it as (select item, row_number() over (order by item) - 1 as rank from (select distinct item from pos)), n as (select count(*) as n from it),
dr as (select p.*, draw, ('0x' || substr(md5(example_id || ':' || draw || ':0:3'), 1, 8))::bigint as r from pos p, (select unnest(range(1, 3)) as draw))"""
_UNI = f"{_POS}, uni as (select example_id as link, draw, r % (n - 1) + (r % (n - 1) >= own.rank)::int as pick from dr join it own using (item), n), neg as (select link, draw, it.item from uni join it on it.rank = uni.pick)"


def _pos(spark, d):
    return workloads.events(spark, d).where(F.col("query").isin("purchase", "click")).drop("value")


@register("rank_sampler_uniform", f"{_UNI} select link, draw::int as draw, item from neg")
def rank_sampler_uniform(spark, d):
    return ranking.Uniform(_pos(spark, d).select("item"), 2, 3).sample(_pos(spark, d))


@register("rank_sampler_within", f"""{_POS}, g as (select item, item % 5 as grp, row_number() over (partition by item % 5 order by item) - 1 as rank, count(*) over (partition by item % 5) as size from it),
w as (select example_id as link, draw, grp, r % (size - 1) + (r % (size - 1) >= g.rank)::int as pick from dr join g using (item) where size > 1)
select link, draw::int as draw, g.item from w join g on g.grp = w.grp and g.rank = w.pick""")
def rank_sampler_within(spark, d):
    pos = _pos(spark, d)
    items = pos.select("item", (F.col("item") % 5).alias("grp"))
    return ranking.Within(items, "grp", 2, 3).sample(pos)


@register("rank_sampler_popularity", f"""{_POS}, c as (select item, n, sum(n) over (order by item) as hi, row_number() over (order by item) - 1 as rank, count(*) over () as m, sum(n) over () as total from (select item, count(*) as n from pos group by 1)),
h as (select example_id as link, draw, case when c.item = dr.item then (rank + 1) % m else rank end as pick from dr join c on r % total >= hi - n and r % total < hi)
select link, draw::int as draw, c.item from h join c on c.rank = h.pick""")
def rank_sampler_popularity(spark, d):
    return ranking.Popularity(_pos(spark, d).select("item"), 2, 3).sample(_pos(spark, d))


@register("rank_sampler_excluding", f"""{_POS}, u as (select distinct user_id from pos), f as (select user_id, it.item from u, it where not exists (select 1 from pos p where p.user_id = u.user_id and p.item = it.item)),
k as (select *, row_number() over (partition by user_id order by item) - 1 as rank, count(*) over (partition by user_id) as size from f)
select example_id as link, draw::int as draw, k.item from dr join k on k.user_id = dr.user_id and k.rank = dr.r % k.size""")
def rank_sampler_excluding(spark, d):
    return ranking.Excluding(_pos(spark, d).select("item"), 2, 3).sample(_pos(spark, d))


_RSC = f"""{_UNI}, rows as (select example_id, user_id, query, item from pos union all select -(link * 2 + draw), user_id, query, neg.item from neg join pos on pos.example_id = neg.link),
feats as (select example_id, user_id % 200 as feature_id from rows union all select example_id, 200 + ('0x' || substr(md5('q:' || query), 1, 8))::bigint % 97 from rows union all select example_id, 300 + item from rows),
xs as (select feature_id, [((feature_id * (k + 3)) % 11 - 5) / 10.0::double for k in range(4)] as v from (select unnest(range(512)) as feature_id)),
s as (select a.example_id, sum(list_dot_product(p.v, q.v)) as score from feats a join feats b on a.example_id = b.example_id and a.feature_id < b.feature_id join xs p on p.feature_id = a.feature_id join xs q on q.feature_id = b.feature_id group by 1),
dl as (select link, draw, sp.score - sn.score as s from neg join s sp on sp.example_id = link join s sn on sn.example_id = -(link * 2 + draw))"""


@register("rank_loss", f"{_RSC} select round(avg({_SP.format('(-s)')}), 8) as loss from dl")
def rank_loss(spark, d):
    return _one(spark, loss=round(workloads.w5(spark, d).objective.value(_fm_weights(spark)), 8))


@register("rank_gradient", f"""{_RSC}, dd as (select link, draw, -(1.0::double - ({_SIG})) as d from dl), ds as (select link as example_id, sum(d) as ds from dd group by 1 union all select -(link * 2 + draw), -d from dd),
tl as (select example_id, k, sum(v[k + 1]) as t from feats join xs using (feature_id), (select unnest(range(4)) as k) group by 1, 2)
select k::int as row, feature_id as idx, round(sum(ds * (t - v[k + 1])) / (select count(*) from dd), 8) + 0.0::double as value from feats join xs using (feature_id) join ds using (example_id) join tl using (example_id) group by 1, 2""")
def rank_gradient(spark, d):
    w = workloads.w5(spark, d)
    g = _long(w.objective.gradient(_fm_weights(spark)), 8)
    seen = w.objective.cells.select("feat_part", F.explode("local_ids").alias("i")).select((F.col("feat_part").cast("long") * 512 + F.col("i")).alias("idx")).distinct()
    return g.join(seen, "idx", "left_semi")


@register("rank_exact_loss", OK)
def rank_exact_loss(spark, d):
    """Sampled pairwise losses estimate the expectation over all other items."""
    pos = _pos(spark, d)
    score = lambda df: df.withColumn("score", ((F.coalesce(F.col("item") if "item" in df.columns else F.lit(0), F.lit(0)) * 7 + F.col("user_id")) % 13 - 6) / F.lit(6.0))
    exact = ranking.exact_loss(pos, pos.select("item"), score).first()[0]
    neg = ranking.Uniform(pos.select("item"), 8, 5).sample(pos)
    s = score(neg.join(pos.select(F.col("example_id").alias("link"), "user_id"), "link")).withColumnRenamed("score", "sn").join(score(pos).select(F.col("example_id").alias("link"), F.col("score").alias("sp")), "link")
    got = s.agg(F.avg(losses.softplus(F.col("sn") - F.col("sp")))).first()[0]
    return _ok(spark, abs(got - exact) < 0.02)


@register("rank_fit_trace", f"""{_RSC.replace("((feature_id * (k + 3)) % 11 - 5) / 10.0::double", _U.format(seed=6))} select round(avg({_SP.format('(-s)')}), 6) as start, true as falls from dl""")
def rank_fit_trace(spark, d):
    log = workloads.w5(spark, d).run().log
    return _one(spark, start=round(log[0][1], 6), falls=_falls(log))


_ORD = """with pos as (select ('0x' || substr(md5(concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * 100)::bigint)), 1, 13))::bigint as example_id, o_custkey as user_id, p_type as query, l_partkey as item
  from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey),
g as (select item, query as grp, row_number() over (partition by query order by item) - 1 as rank, count(*) over (partition by query) as size from (select distinct item, query from pos)),
w as (select example_id as link, grp, ('0x' || substr(md5(example_id || ':1:0:3'), 1, 8))::bigint as r, g.rank as own, size from pos join g using (item) where size > 1),
neg as (select link, g.item from w join g on g.grp = w.grp and g.rank = w.r % (w.size - 1) + (w.r % (w.size - 1) >= own)::int),
rows as (select example_id, user_id, query, item from pos union all select -(link + 1), user_id, query, neg.item from neg join pos on pos.example_id = neg.link),
fw as (select example_id, [((f * (k + 3)) % 11 - 5) / 10.0::double for k in range(4)] as v from (select example_id, unnest([user_id % 200, 200 + ('0x' || substr(md5('q:' || query), 1, 8))::bigint % 97, 300 + item % 212]) as f from rows)),
t as (select example_id, [sum(v[1]), sum(v[2]), sum(v[3]), sum(v[4])] as l, sum(list_dot_product(v, v)) as q from fw group by 1), s as (select example_id, (list_dot_product(l, l) - q) / 2 as score from t),
dl as (select sp.score - sn.score as s from neg join s sp on sp.example_id = link join s sn on sn.example_id = -(link + 1))"""


@register("rank_orders_loss", f"{_ORD} select round(avg({_SP.format('(-s)')}), 7) as loss, count(*) as pairs from dl")
def rank_orders_loss(spark, d):
    """Parts that customers order against other parts of the same type."""
    f = workloads.w5_orders(spark, d).objective
    return _one(spark, loss=round(f.value(_fm_weights(spark)), 7), pairs=f.links.count())


@register("rank_resample", OK)
def rank_resample(spark, d):
    f, x = workloads.w5(spark, d).objective, _fm_weights(spark)
    a, b = f.value(x), f.value(x)
    f.resample()
    return _ok(spark, a == b, f.value(x) != a)


# transport ----------------------------------------------------------------------------------------------------------------------

_OT = """with x as (select row_number() over (order by vec_id) - 1 as i, embedding as e from embeddings where vec_id % 2 = 0), y as (select row_number() over (order by vec_id) - 1 as j, embedding as e from embeddings where vec_id % 2 = 1),
c as (select i, j, list_sum([(a[1]::double - a[2]::double) * (a[1]::double - a[2]::double) for a in list_zip(x.e, y.e)]) as c from x, y), p as (select *, (i % 5) / 10.0::double as u, (j % 3) / 10.0::double as v from c)"""


def _potentials(spark, f):
    from gridmin.vectors import from_expr

    return concat([("u", from_expr(spark, f.n_x, lambda r, i: (i % 5) / F.lit(10.0), f.size)), ("v", from_expr(spark, f.n_y, lambda r, i: (i % 3) / F.lit(10.0), f.size))]).cut()


@register("ot_cost", f"{_OT} select round(min(c), 6) as lo, round(max(c), 6) as hi, round(avg(c), 6) as mean from c")
def ot_cost(spark, d):
    c = workloads.w3(spark, d).objective.costs()
    return c.agg(F.round(F.min("lo"), 6).alias("lo"), F.round(F.max("hi"), 6).alias("hi"), F.round(F.sum("total") / F.sum("pairs"), 6).alias("mean"))


@register("ot_value", f"{_OT} select round(-avg(u) - avg(v) + 0.5::double * avg(exp((u + v - c) / 0.5::double)), 8) as value from p")
def ot_value(spark, d):
    f = workloads.w3(spark, d, eps=0.5).objective
    return _one(spark, value=round(f.value(_potentials(spark, f)), 8))


@register("ot_gradient", f"{_OT} select 'u' as side, i as idx, round((avg(exp((u + v - c) / 0.5::double)) - 1) / (select count(*) from x), 10) + 0.0::double as value from p group by i union all select 'v', j, round((avg(exp((u + v - c) / 0.5::double)) - 1) / (select count(*) from y), 10) + 0.0::double from p group by j")
def ot_gradient(spark, d):
    f = workloads.w3(spark, d, eps=0.5).objective
    g = f.gradient(_potentials(spark, f))
    return _long(g.segment("u"), 10).withColumn("side", F.lit("u")).unionByName(_long(g.segment("v"), 10).withColumn("side", F.lit("v")))


@register("ot_line", OK)
def ot_line(spark, d):
    f = workloads.w3(spark, d, eps=0.5).objective
    x, g = _potentials(spark, f), None
    v, g = f.evaluate(x)
    down = ops.scale(g, -1.0).cut()
    line = f.along(x, down)
    (a, s), (b, _) = line.at([0.0, 3.0])
    return _ok(spark, abs(a - v) < 1e-10, abs(s - ops.dot(g, down)) < 1e-10, abs(b - f.value(ops.lincomb([1.0, 3.0], [x, down]))) < 1e-10)


@register("ot_fit_marginals", OK)
def ot_fit_marginals(spark, d):
    w = workloads.w3(spark, d, eps=0.5)
    r = w.run()
    s = w.objective.summary(r.x)
    return _ok(spark, r.reason == optim.Reason.GRADIENT, s["marginal_error"] < 5e-5, abs(s["mass"] - 1) < 0.01, abs(s["gap"]) < 0.01)


@register("ot_fit_trace", f"{_OT} select round(0.1::double * avg(exp(-c / 0.1::double)), 8) as start, true as falls, 'gradient norm' as reason, true as within_12, true as negative from p")
def ot_fit_trace(spark, d):
    """At the published regularisation 0.1: stops on the gradient norm below 0.5e-4, after how few iterations, with -L below 0.
    Quasi-Newton steps don't get there in as many where points are many, so these are Newton steps with scaling between them."""
    r = workloads.w3(spark, d, eps=0.1, minimiser=workloads.newton(13, 5e-5)).run()
    return _one(spark, start=round(r.log[0][1], 8), falls=_falls(r.log), reason=r.reason.value, within_12=r.iterations <= 12, negative=r.value < 0)


@register("ot_small_eps", OK)
def ot_small_eps(spark, d):
    """Exponents far beyond a double's range give an infinite value, no NaN, and a line search that comes back."""
    f = workloads.w3(spark, d, eps=1e-3).objective
    x = f.start().cut()
    up = concat([("u", fill(spark, f.n_x, 1.0, f.size)), ("v", fill(spark, f.n_y, 1.0, f.size))]).cut()
    (low, s), (high, t) = f.along(x, up).at([0.01, 50.0])
    return _ok(spark, math.isfinite(low), math.isfinite(s), high == float("inf"), not math.isnan(t), f.value(ops.scale(up, 50.0).cut()) > 1e250)


@register("ot_plan_cost", OK)
def ot_plan_cost(spark, d):
    w = workloads.w3(spark, d, eps=0.5)
    top = w.objective.plan(w.run().x, 2)
    return _ok(spark, top.count() == 2 * w.objective.n_x, 0 < w.objective.summary(w.run().x)["cost"] < 2.1)


@register("ot_sinkhorn_agree", OK)
def ot_sinkhorn_agree(spark, d):
    w = workloads.w3(spark, d, eps=0.5)
    return _ok(spark, abs(w.objective.value(transport.sinkhorn(w.objective, 6)) - w.run().value) < 1e-3)


_OT1 = """with sm as (select min(s_acctbal) lo, max(s_acctbal) hi from supplier), cm as (select min(c_acctbal) lo, max(c_acctbal) hi from customer),
x as (select row_number() over (order by v, k) - 1 as i, v from (select s_suppkey as k, (s_acctbal - lo) / (hi - lo) as v from supplier, sm)), y as (select row_number() over (order by v, k) - 1 as j, v from (select c_custkey as k, (c_acctbal - lo) / (hi - lo) as v from customer, cm)),
n as (select (select count(*) from x) as n, (select count(*) from y) as m), o as (select greatest(i * m, j * n) as low, least(i * m + m, j * n + n) as high, (x.v - y.v) * (x.v - y.v) as c, n * m as nm from x, y, n where i * m < j * n + n and j * n < i * m + m)"""


@register("ot_1d", f"{_OT1} select round(sum((high - low) / nm::double * c), 8) as exact, count(*) as pieces, true as falls from o")
def ot_1d(spark, d):
    """On a line the best plan pairs sorted points: its cost, and the regularised dual going down."""
    w = workloads.w3_one_dimension(spark, d, eps=0.05, minimiser=workloads.quick(3, 5e-5))
    x, y = w.data["x"], w.data["y"]
    plan = transport.sorted_coupling(x, y, "k", "v").agg(F.sum(F.col("mass") * F.col("cost")).alias("c"), F.count("*").alias("n")).first()
    return _one(spark, exact=round(plan["c"], 8), pieces=plan["n"], falls=_falls(w.run().log))


@register("ot_masses", OK)
def ot_masses(spark, d):
    """Uniform masses given explicitly agree with the built-in ones."""
    e = io.table(spark, d, "embeddings", ["vec_id", "embedding"])
    f = workloads.w3(spark, d, eps=0.5).objective
    a, b = fill(spark, f.n_x, 1.0 / f.n_x, f.size), fill(spark, f.n_y, 1.0 / f.n_y, f.size)
    g = transport.Transport.of(e.where("vec_id % 2 = 0"), e.where("vec_id % 2 = 1"), "vec_id", "embedding", part_size=64, eps=0.5, a=a, b=b)
    x = _potentials(spark, f)
    return _ok(spark, abs(f.value(x) - g.value(x)) < 1e-9)


@register("ot_sampled_baseline", OK)
def ot_sampled_baseline(spark, d):
    f = workloads.w3(spark, d, eps=1.0, part_size=16).objective
    x = f.start()
    return _ok(spark, abs(transport.sampled(f, 0.5).value(x) / f.value(x) - 1) < 0.2, metrics.size_ratio(2.5e5, 2e4) == 156.25)


@register("w3s_ball_moments", OK)
def w3s_ball_moments(spark, d):
    r = F.sqrt(F.aggregate("coords", F.lit(0.0), lambda acc, x: acc + x * x))
    m, top = workloads.ball(spark, 4000, 8, 1).agg(F.avg(r), F.max(r)).first()
    far = workloads.shifted_balls(spark, 2000, 55, 1).agg(F.max(r)).first()[0]
    return _ok(spark, abs(m - 8 / 9) < 0.01, top <= 1.0, far <= 1.0 + 1e-9)


# batches, penalties, weights -----------------------------------------------------------------------------------------------------


@register("batch_rotation_log", "select i::int as evaluation, (i % 5)::int as batch from range(0, 7) t(i)")
def batch_rotation_log(spark, d):
    f, x = _priced(spark, d)
    b = Batched([f] * 5)
    for _ in range(7):
        b.evaluate(x)
    return spark.createDataFrame([(n, k) for n, k, _ in b.log], "evaluation int, batch int")


@register("hold_policies", "select * from (values ('same', '0,0,1'), ('next', '0,1,2'), ('rotate', '0,1,2')) t(policy, batches)")
def hold_policies(spark, d):
    """Batches used by gradient, line search, gradient."""
    f, x = _priced(spark, d)
    rows = []
    for policy in ("same", "next", "rotate"):
        b = Batched([f] * 5, policy)
        _, g = b.evaluate(x)
        with b.held():
            b.along(x, g).at([0.0])
        b.evaluate(x)
        rows.append((policy, ",".join(str(k) for _, k, _ in b.log)))
    return spark.createDataFrame(rows, "policy string, batches string")


@register("accumulated_batches", OK)
def accumulated_batches(spark, d):
    w = workloads.w1r(spark, d)
    half = F.pmod(F.col("example_id"), F.lit(2))
    parts = [workloads.linear(w.data["features"].where(half == b), w.data["labels"].where(half == b), 4, losses.Squared(), 4).objective for b in (0, 1)]
    sizes = [float(w.data["labels"].where(half == b).count()) for b in (0, 1)]
    x = fill(spark, 4, 0.3, 4)
    (a, g), (b, h) = Accumulated(parts, sizes).evaluate(x), w.objective.evaluate(x)
    return _ok(spark, abs(a - b) < 1e-9, ops.norm(ops.sub(g, h)) < 1e-9)


@register("warm_start", OK)
def warm_start(spark, d):
    f, x = _quadratic(spark)
    phases = optim.chain([optim.AdaptiveGradient(0.5, stop=[optim.MaxIter(3)]), optim.LimitedMemory(stop=[optim.MaxIter(3)])], f, x)
    return _ok(spark, phases[1].value <= phases[0].value, phases[1].log[0][1] == phases[0].value)


@register("penalty_values", f"select round(0.3::double * sum(abs(p)) + 0.1::double * sum(p * p), 3) as penalty from ({_PQ})")
def penalty_values(spark, d):
    return _one(spark, penalty=round(Penalised(None, 0.3, 0.2).penalty(_price(spark, d).cut()), 3))


@register("weighted_equals_duplicated", OK)
def weighted_equals_duplicated(spark, d):
    w = workloads.w1r(spark, d)
    feats, lab = w.data["features"], w.data["labels"]
    twice = lab.withColumn("weight", F.when(F.col("example_id") % 2 == 0, 2.0).otherwise(1.0))
    again = F.col("example_id") % 2 == 0
    more_f = feats.where(again).withColumn("example_id", F.xxhash64("example_id", F.lit(1)))
    more_l = lab.where(again).withColumn("example_id", F.xxhash64("example_id", F.lit(1)))
    a = workloads.linear(feats, twice, 4, losses.Squared(), 4).objective.value(fill(spark, 4, 0.2, 4))
    b = workloads.linear(feats.unionByName(more_f), lab.unionByName(more_l), 4, losses.Squared(), 4).objective.value(fill(spark, 4, 0.2, 4))
    return _ok(spark, abs(a - b) < 1e-9)


@register("policy_gap_trace", "select i::int as iteration, case when i = 0 then round(ln(10.0::double), 8) end as start, case when i = 4 then true end as next_is_lower from range(0, 5) t(i)")
def policy_gap_trace(spark, d):
    """Planted softmax in five batches: line searches on the next batch against searches on the direction's own."""
    w = workloads.w2_planted(spark, d, policy="next")
    logs = []
    for f in (w.objective, w.objective.again("same")):
        logs.append(workloads.quick(4).run(f, w.x0).log)
        f.free()
    rows = [(a[0], round(a[1], 8) if a[0] == 0 else None, a[1] < b[1] if a[0] == 4 else None) for a, b in zip(*logs)]
    return spark.createDataFrame(rows, "iteration int, start double, next_is_lower boolean")


@register("w2_planted_trace", "select round(ln(10.0::double), 8) as start, true as has_fallen")
def w2_planted_trace(spark, d):
    """One batch of all events with 100 features each. The training loss may end below the law's entropy: the model over-fits."""
    log = workloads.w2_planted(spark, d, batches=1, minimiser=workloads.quick(4)).run().log
    return _one(spark, start=round(log[0][1], 8), has_fallen=log[-1][1] < 0.9 * log[0][1])


@register("w6_sparse_logistic_trace", "select round(ln(2.0::double), 8) as start, true as falls")
def w6_sparse_logistic_trace(spark, d):
    log = workloads.w6(spark, d).run().log
    return _one(spark, start=round(log[0][1], 8), falls=_falls(log))


@register("w9_growth", f"select share, count(distinct example_id) as examples, count(*) as nnz, count(distinct example_id || ':' || feature_id // 1024) as routes from (select unnest([1, 2, 4]) as share), (with ids as (select o_orderkey as example_id from orders) {workloads.FEATURES_SQL.format(d=10007, nnz=30)}) where value <> 0 and example_id % 4 < share group by 1")
def w9_growth(spark, d):
    """A quarter, half and all of the examples: non-zeros and routes, hence bytes moved, grow in proportion."""
    ids = io.table(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("example_id"))
    rows = []
    for share in (1, 2, 4):
        some = ids.where(F.col("example_id") % 4 < share)
        cells = grid.build_cells(workloads.planted_features(some, 30, 10_007), 4, 1024).persist()
        s = grid.stats(cells, zeros(spark, 10_007, 1024), 4)
        examples, nnz = cells.select(F.explode("ex_ids").alias("i")).distinct().count(), cells.agg(F.sum(F.size("vals"))).first()[0]
        rows.append((share, examples, nnz, s.routes))
        cells.unpersist()
    return spark.createDataFrame(rows, "share int, examples long, nnz long, routes long")


@register("w10_lineage", f"select idx, round(p / 1000.0::double / (1 + idx % 3) * (1 - pow(1 - 0.1::double * (1 + idx % 3), 30)), 8) + 0.0::double as value from ({_P}) where idx < 64")
def w10_lineage(spark, d):
    """Thirty iterations with a break after twenty: the plan stays a scan throughout, and the end is the closed form."""
    import uuid

    from gridmin.vectors import from_expr
    from gridmin.vectors.vec import shared_dir

    p = io.table(spark, d, "part", ["p_partkey", "p_retailprice"]).where("p_partkey < 64").withColumn("p_retailprice", F.col("p_retailprice") / 1000.0)
    f = Quadratic(from_expr(spark, 64, lambda row, i: (1 + i % 3).cast("double"), 64).cut(), from_long(p, 64, 64, "p_partkey", "p_retailprice").cut())
    path, depths = f"{shared_dir(spark)}/w10-{uuid.uuid4().hex}", []
    watch = lambda s: depths.append(metrics.plan_depth(s.x.df)) or False
    optim.GradientDescent(0.1, stop=[optim.MaxIter(20)], callback=watch).run(f, zeros(spark, 64, 64).cut(), save_to=path)
    r = optim.GradientDescent(0.1, stop=[optim.MaxIter(30)], callback=watch).run(f, zeros(spark, 64, 64), resume_from=path)
    if len(depths) != 32 or max(depths) > 3:
        raise AssertionError(f"plans grow: {depths}")
    return _long(r.x, 8)


@register("w6_l1_sparsity", OK)
def w6_l1_sparsity(spark, d):
    w = workloads.w6(spark, d, minimiser=optim.OrthantWise(l1=0.01, stop=[optim.MaxIter(4)]))
    r = w.run()
    return _ok(spark, ops.nnz(r.x) < r.x.length // 4, r.value < r.log[0][1])


# baselines ------------------------------------------------------------------------------------------------------------------------


@register("base_broadcast_lr", OK)
def base_broadcast_lr(spark, d):
    w = workloads.w1r(spark, d)
    ours, theirs = w.run(), baselines.broadcast_linear(w.data["features"], w.data["labels"], 4)
    x = [r["value"] for r in ours.x.to_long().orderBy("idx").collect()]
    return _ok(spark, max(abs(a - b) for a, b in zip(x, theirs)) < 1e-3)


@register("base_hashing", "select ('0x' || substr(md5('t:' || w), 1, 8))::bigint % 1024 as bucket, count(*) as n from (select unnest(string_split(lower(text), ' ')) as w from documents) where w <> '' group by 1")
def base_hashing(spark, d):
    words = io.table(spark, d, "documents", ["text"]).select(F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    return words.groupBy(baselines.hash_index(F.col("w"), 10).alias("bucket")).agg(F.count("*").alias("n"))


@register("base_minfreq", "select w, count(*) as n from (select unnest(string_split(lower(text), ' ')) as w from documents) where w <> '' group by 1 having count(*) >= 50")
def base_minfreq(spark, d):
    words = io.table(spark, d, "documents", ["text"]).select(F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    return baselines.min_count(words.withColumnRenamed("w", "feature_id"), 50).groupBy(F.col("feature_id").alias("w")).agg(F.count("*").alias("n"))


@register("base_topk_other", "with k as (select p_brand from part group by 1 order by count(*) desc, p_brand limit 5) select case when p_brand in (select p_brand from k) then p_brand else 'other' end as level, count(*) as n from part group by 1")
def base_topk_other(spark, d):
    df = baselines.topk_levels(io.table(spark, d, "part", ["p_brand"]), "p_brand", 5)
    return df.groupBy(F.col("p_brand").alias("level")).agg(F.count("*").alias("n"))


@register("base_bucketed_interactions", "select ('0x' || substr(md5(o_orderstatus || ':' || o_orderpriority), 1, 8))::bigint % 64 as bucket, count(*) as n from orders group by 1")
def base_bucketed_interactions(spark, d):
    df = baselines.bucketed_interactions(io.table(spark, d, "orders", ["o_orderstatus", "o_orderpriority"]), ["o_orderstatus", "o_orderpriority"], 64)
    return df.groupBy("bucket").agg(F.count("*").alias("n"))


@register("base_pull_push", OK)
def base_pull_push(spark, d):
    w = workloads.w1r(spark, d)
    x = fill(spark, 4, 0.25, 4)
    v, g = baselines.pull_push(w.data["features"], w.data["labels"], x, losses.Squared())
    a, b = w.objective.evaluate(x)
    return _ok(spark, abs(v - a) < 1e-9, ops.norm(ops.sub(g, b)) < 1e-9)


@register("base_nocache", OK)
def base_nocache(spark, d):
    w = workloads.w1r(spark, d)
    x = fill(spark, 4, 0.25, 4)
    return _ok(spark, abs(baselines.uncached(w).value(x) - w.objective.value(x)) < 1e-9)


@register("base_sgd_vs_lbfgs", OK)
def base_sgd_vs_lbfgs(spark, d):
    sgd, quasi = baselines.sgd_vs_lbfgs(lambda m: workloads.w1r(spark, d, m), 6)
    return _ok(spark, quasi.value <= sgd.value + 1e-9)


@register("base_hashed_online", OK)
def base_hashed_online(spark, d):
    w = workloads.w6(spark, d, bits=10)
    r = baselines.hashed_online(w.objective, w.x0, 0.5, 3)
    return _ok(spark, r.value < r.log[0][1])


@register("base_l1_subgradient", OK)
def base_l1_subgradient(spark, d):
    """Orthant steps leave exact zeros under l1; quasi-Newton on the subgradient does not need to."""
    w = workloads.w6(spark, d, bits=10)
    plain = baselines.l1_lbfgs_subgradient(w.objective, w.x0, 0.01, 3)
    orthant = optim.OrthantWise(l1=0.01, stop=[optim.MaxIter(3)]).run(w.objective, w.x0)
    return _ok(spark, ops.nnz(orthant.x) <= ops.nnz(plain.x))


@register("base_sparkml_fm", OK)
def base_sparkml_fm(spark, d):
    e = workloads.events(spark, d)
    rmse = baselines.sparkml_fm(workloads.event_features(e), e.select("example_id", (F.col("value") / 100.0).alias("label")), 512, 4, 3)
    return _ok(spark, math.isfinite(rmse))


# measures --------------------------------------------------------------------------------------------------------------------------

_PRED = "with p as (select event_id, value as label, 40.0::double + (event_id % 21) as score from events)"
_PROB = "with p as (select doc_id, quality as label, ((doc_id * 37) % 100 + 0.5::double) / 100.0::double as p from labels)"


def _prob(spark, d):
    return io.table(spark, d, "labels").select("doc_id", F.col("quality").alias("label"), (((F.col("doc_id") * 37) % 100 + 0.5) / 100.0).alias("p"))


@register("met_regression", f"{_PRED} select round(avg(r * r), 4) as mse, round(sqrt(avg(r * r)), 4) as rmse, round(avg(abs(r)), 4) as mae, round(1 - avg(r * r) / (avg(label * label) - avg(label) * avg(label)), 6) as r2, round(avg(case when r >= 0 then r * 0.5::double else r * -0.5::double end), 4) as pinball, round(avg((r <= 0)::int), 6) as coverage from (select *, label - score as r from p)")
def met_regression(spark, d):
    p = io.table(spark, d, "events", ["event_id", "value"]).select(F.col("value").alias("label"), (40.0 + F.col("event_id") % 21).alias("score"))
    m = metrics.regression(p)
    return m.select(*[F.round(c, 6 if c in ("r2", "coverage") else 4).alias(c) for c in m.columns])


@register("met_classification", f"{_PROB}, c as (select avg(case when label = 1 then -ln(p) else -ln(1 - p) end) as log_loss, count(*) filter (label = 1 and p >= 0.5) as tp, count(*) filter (label <> 1 and p >= 0.5) as fp, count(*) filter (label = 1 and p < 0.5) as fn, count(*) filter (label <> 1 and p < 0.5) as tn from p) select round(log_loss, 6) as log_loss, tp, fp, fn, tn, round((tp + tn) / (tp + fp + fn + tn), 6) as accuracy, round(tp / (tp + fp), 6) as precision, round(tp / (tp + fn), 6) as recall, round(2 * tp / (2 * tp + fp + fn), 6) as f1 from c")
def met_classification(spark, d):
    m = metrics.classification(_prob(spark, d))
    return m.select(*[F.col(c) if c in ("tp", "fp", "fn", "tn") else F.round(c, 6).alias(c) for c in m.columns])


@register("met_auc", f"{_PROB} select round(sum(case when a.p > b.p then 1.0::double when a.p = b.p then 0.5::double else 0.0::double end) / count(*), 8) as auc from p a, p b where a.label = 1 and b.label <> 1")
def met_auc(spark, d):
    return metrics.auc(_prob(spark, d), "p").select(F.round("auc", 8).alias("auc"))


@register("met_calibration", f"{_PROB} select least(floor(p * 10), 9)::int as bin, count(*) as n, round(avg(p), 6) as mean_p, round(avg(label), 6) as rate from p group by 1")
def met_calibration(spark, d):
    return metrics.calibration(_prob(spark, d)).select("bin", "n", F.round("mean_p", 6).alias("mean_p"), F.round("rate", 6).alias("rate"))


@register("met_ranking", """with e as (select user_id, event_id as item, (event_id * 37) % 1009 as score, (event_type = 'purchase')::int as rel from events), r as (select *, row_number() over (partition by user_id order by score desc, item) as r from e),
g as (select user_id, min(r) filter (rel = 1) as first, sum(case when rel = 1 and r <= 10 then 1 / log2(r + 1.0::double) else 0 end) as dcg, count(*) filter (rel = 1) as nr, count(*) filter (rel <> 1) as nn, sum(case when rel = 1 then r else 0 end) as rs from r group by 1 having count(*) filter (rel = 1) > 0),
h as (select *, list_sum([1 / log2(i + 1.0::double) for i in range(1, least(nr, 10) + 1)]) as ideal, (nr * nn - (rs - nr * (nr + 1) / 2)) / nullif(nr * nn, 0) as pw from g)
select round(avg(1.0::double / first), 8) as mrr, round(avg((first <= 10)::int), 8) as hit, round(avg(dcg / ideal), 8) as ndcg, round(avg(pw), 8) as pairwise from h""")
def met_ranking(spark, d):
    e = io.table(spark, d, "events", ["event_id", "user_id", "event_type"]).select("user_id", F.col("event_id").alias("item"), ((F.col("event_id") * 37) % 1009).alias("score"), (F.col("event_type") == "purchase").cast("int").alias("rel"))
    m = metrics.ranking(e, "user_id", "score", "rel")
    return m.select(*[F.round(c, 8).alias(c) for c in m.columns])


@register("met_entropy_floor", f"{_CLS} select round(avg(-list_sum([exp(v - z) * (v - z) for v in s])), 8) as floor from z")
def met_entropy_floor(spark, d):
    e = io.table(spark, d, "embeddings", ["vec_id"]).withColumn("s", _scores10()).withColumn("p", losses.softmax(F.col("s")))
    return metrics.entropy_floor(e, "p").select(F.round("floor", 8).alias("floor"))


@register("met_improvement", "select *, abs(lag(value) over w - value) / greatest(abs(lag(value) over w), 1e-6::double) as improvement from (select (o_orderdate::date - date '1995-01-01')::int as iteration, sum(case when o_orderstatus = 'F' then 1 else -1 end)::double as value from orders group by 1) window w as (order by iteration)")
def met_improvement(spark, d):
    """Improvements of a series that also passes through zero: finished less other orders, day by day."""
    o = io.table(spark, d, "orders", ["o_orderdate", "o_orderstatus"]).withColumn("iteration", F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")))
    return metrics.improvements(o.groupBy("iteration").agg(F.sum(F.when(F.col("o_orderstatus") == "F", 1).otherwise(-1)).cast("double").alias("value")))


@register("met_timing", "select * from (values ('load', 1::bigint, true), ('evaluate', 2::bigint, true)) t(name, n, positive)")
def met_timing(spark, d):
    t = metrics.Timers()
    with t.measure("load"):
        w = workloads.w1r(spark, d)
        w.data["cells"].count()
    for _ in range(2):
        with t.measure("evaluate"):
            w.objective.evaluate(w.x0)
    return t.summary(spark).select("name", "n", (F.col("mean") > 0).alias("positive"))


@contextmanager
def _plain_plans(spark):
    """Without run-time changes and automatic broadcasts, as for vectors that are too large for them."""
    keys = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k) for k in keys}
    for k, v in keys.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


@register("met_plan", "select what, 0 as exchanges from (select unnest(['add', 'gram', 'lincomb', 'cells broadcast', 'cells gather', 'cells replicate', 'cells stationary', 'weights stationary', 'back gather', 'back stationary', 'tiles', 'tiles line']) as what)")
def met_plan(spark, d):
    """Exchanges above vectors that were cut, above cells on both ways, above resident weights and above tiles: none."""
    rows = []
    with _plain_plans(spark):
        a, b = (v.cut() for v in (_price(spark, d), _qty(spark, d)))
        rows.append(("add", metrics.moved(ops.add(a, b).df, "values") + metrics.moved(ops.add(a, b).df, "v0")))
        for what, df in (("gram", ops.wide([a, b, a])), ("lincomb", ops.lincomb([1.0, 2.0], [a, b]).df)):
            rows.append((what, metrics.moved(df, "values") + metrics.moved(df, "v0") + metrics.moved(df, "v1")))
        f, x = workloads.w1(spark, d).objective, _fixed(spark, 10_007).cut()
        pulled = f.labels.select("example_id", F.array("label").alias("d")).persist()
        for s in STRATEGIES:
            f.strategy = s
            rows.append((f"cells {s}", metrics.moved(f.scores(x).select("example_id"), "vals")))
            if s in ("gather", "stationary"):
                rows.append((f"back {s}", metrics.moved(f.grid.back(pulled, 1, grid.transposed, x, 1), "vals")))
        rows.append(("weights stationary", metrics.moved(f.scores(x), "w")))
        t = workloads.w3(spark, d, eps=0.5).objective
        z = _potentials(spark, t)
        rows.append(("tiles", metrics.moved(t._sums(z), "xs")))
        line = t.along(z, z)
        rows.append(("tiles line", metrics.moved(line.df, "xs")))
        line.free()
    return spark.createDataFrame(rows, "what string, exchanges int")


@register("model_save_load", OK)
def model_save_load(spark, d):
    import uuid

    from gridmin.facade import MultiClassifier, Regressor
    from gridmin.vectors.vec import shared_dir

    w = workloads.w1r(spark, d)
    m = Regressor(4, 4, minimiser=workloads.quick(4)).fit(w.data["features"], w.data["labels"])
    path = f"{shared_dir(spark)}/model-{uuid.uuid4().hex}"
    m.save(path)
    again = Regressor.load(spark, path)
    worst = m.transform(w.data["features"]).join(again.transform(w.data["features"]).withColumnRenamed("score", "other"), "example_id").agg(F.max(F.abs(F.col("score") - F.col("other")))).first()[0]
    e = workloads.w2(spark, d).data
    c = MultiClassifier(64, 64, minimiser=workloads.quick(3), k=10).fit(e["features"], e["labels"])
    return _ok(spark, worst == 0.0, c.evaluate(e["features"], e["labels"]).first()[0] > 0.15)


@register("fm_classifier_fit", OK)
def fm_classifier_fit(spark, d):
    """Quality of documents from language, source and length class."""
    from gridmin.facade import FMClassifier

    docs = io.table(spark, d, "documents", ["doc_id", "lang", "source", "n_chars"]).join(io.table(spark, d, "labels"), "doc_id")
    of = lambda name, col, n, at: (workloads.h32(name, col) % n + at)
    ids = F.array(of("l", F.col("lang"), 16, 0), of("s", F.col("source"), 48, 16), F.least(F.floor(F.log2(F.col("n_chars") + 1.0)), F.lit(31)) + 64)
    feats = docs.select(F.col("doc_id").alias("example_id"), F.explode(ids).alias("feature_id"), F.lit(1.0).alias("value"))
    labels = docs.select(F.col("doc_id").alias("example_id"), F.col("quality").cast("double").alias("label"))
    m = FMClassifier(96, 96, minimiser=workloads.quick(3)).fit(feats, labels)
    return _ok(spark, m.result.value < m.result.log[0][1])


@register("met_gap", OK)
def met_gap(spark, d):
    """Training and held-out loss of the sparse logistic model; the training loss is the lower one."""
    w = workloads.w6(spark, d, bits=12)
    fold = F.pmod(F.xxhash64("example_id"), F.lit(3)) == 0
    t, h = (workloads.linear(w.data["features"].where(k), w.data["labels"].where(k), 1 << 12, losses.Logistic(), 4096, workloads.quick(5)) for k in (~fold, fold))
    x = t.run().x
    return _ok(spark, t.objective.value(x) <= h.objective.value(x))


_W1F = f"with ids as (select o_orderkey as example_id from orders), feats as ({workloads.FEATURES_SQL.format(d=10007, nnz=30)})"


@register("feat_csr", f"{_W1F} select example_id, count(*) as nnz, round(sum(value), 8) + 0.0::double as total from feats where value <> 0 group by 1")
def feat_csr(spark, d):
    """Rows of the compressed cells, put together again."""
    cells = workloads.w1(spark, d).data["cells"]
    rows = cells.select(F.explode(F.transform("ex_ids", lambda e, i: F.struct(e.alias("e"), F.slice("vals", F.col("indptr")[i] + 1, F.col("indptr")[i + 1] - F.col("indptr")[i]).alias("v")))).alias("r"))
    each = rows.select(F.col("r.e").alias("example_id"), F.explode("r.v").alias("v"))
    return each.groupBy("example_id").agg(F.count("*").alias("nnz"), (F.round(F.sum("v"), 8) + F.lit(0.0)).alias("total"))


@register("group_apply", f"{_W1F} select count(*) as cells, sum(n)::bigint as rows from (select feature_id // 1024 as b, count(distinct example_id) as n from feats where value <> 0 group by 1)")
def group_apply(spark, d):
    """Cells built one group at a time. Groups are bounded by example parts; the cells of a feature block count once."""
    ids = io.table(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("example_id"))
    cells = grid.build_cells(workloads.planted_features(ids, 30, 10_007), grid.example_parts(ids, 1), 1024)
    return cells.agg(F.countDistinct("feat_part").alias("cells"), F.sum(F.size("ex_ids")).alias("rows"))


@register("map_in_arrow", f"{_W1F} select count(*) as n, round(sum(s), 4) + 0.0::double as total from (select example_id, sum(value * {_FIX}) as s from feats group by 1)")
def map_in_arrow(spark, d):
    s = workloads.w1(spark, d).objective.scores(_fixed(spark, 10_007))
    return s.agg(F.count("*").alias("n"), (F.round(F.sum(F.col("s")[0]), 4) + F.lit(0.0)).alias("total"))


@register("feat_hashing", "select doc_id, ('0x' || substr(md5('t:' || w), 1, 8))::bigint % 4096 as idx, count(*) as n from (select doc_id, unnest(string_split(lower(text), ' ')) as w from documents) where w <> '' group by 1, 2")
def feat_hashing(spark, d):
    words = io.table(spark, d, "documents", ["doc_id", "text"]).select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    return words.groupBy("doc_id", baselines.hash_index(F.col("w"), 12).alias("idx")).agg(F.count("*").alias("n"))


@register("feat_min_count", "select o_custkey, count(*) as n from orders group by 1 having count(*) >= 8")
def feat_min_count(spark, d):
    f = io.table(spark, d, "orders", ["o_custkey"]).withColumnRenamed("o_custkey", "feature_id")
    return baselines.min_count(f, 8).groupBy(F.col("feature_id").alias("o_custkey")).agg(F.count("*").alias("n"))


@register("feat_topk_other", "with k as (select p_name from part group by 1 order by count(*) desc, p_name limit 10) select case when p_name in (select p_name from k) then p_name else 'other' end as level, count(*) as n from part group by 1")
def feat_topk_other(spark, d):
    df = baselines.topk_levels(io.table(spark, d, "part", ["p_name"]), "p_name", 10)
    return df.groupBy(F.col("p_name").alias("level")).agg(F.count("*").alias("n"))
