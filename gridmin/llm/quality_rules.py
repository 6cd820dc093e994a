"""Quality rules with risk-controlled thresholds.

Four rules each compare a statistic with a cutoff; a document is rejected if any exceeds its own. The cutoffs move together
up one ladder of levels, from lenient to strict, so a level's verdict includes those before it. Levels are tested on labelled
holdouts in that fixed order: level t of a stratum is allowed if the exact binomial test rejects "more than ``risk`` of its
good documents would go", and the first level that isn't ends the sequence, so the ladder's length costs nothing. Over the
strata the error is shared as in Holm's procedure: each of m strata starts with ``error`` / m, and a stratum whose ladder
passes whole hands its share on to the others. With probability 1 - error no stratum loses over ``risk`` of its good
documents to the rules. Of the allowed levels a stratum uses the most lenient that rejects all but ``slack`` of the labelled
poor documents that the strictest one rejects: a milder level loses no more good documents, so the bound holds for it too.

A stratum with so few good documents that not even a level without any rejection could pass (86 at 4 strata and the defaults) is
joined with all others of that kind before anything is tested: they are one stratum more, whose bound holds for their mixture. Column
``scope`` says which bound a row has: ``stratum``, ``pooled``, or ``none`` where no level passed.

Null text: no words (base rules reject it). Null stratum: a stratum of its own. Null or missing label: not in the holdout.
Repeated label rows: the largest counts. Empty table: no rows; no labels: no cutoffs. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.session import map_arrow

_BLANK, _SIGNS = b" \t\n\r\x0b\x0c", b"#*$%&|<>"
NAMES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_same_words")
STATS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("stratum", T.StringType()), *[T.StructField(n, T.LongType()) for n in NAMES]])

#: Rules: a statistic and its cutoff on each level, from lenient to strict.
RULES = {
    "symbol_share": ("n_symbols / n_words", (2.0, 1.0, 0.7, 0.5, 0.3, 0.2, 0.1, 0.05)),
    "dup_line_share": ("n_dup_lines / greatest(n_lines, 1)", (0.9, 0.7, 0.5, 0.4, 0.3, 0.2, 0.1, 0.05)),
    "repeat_share": ("n_repeat_words / n_words", (0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1, 0.05)),
    "same_word_share": ("n_same_words / n_words", (0.8, 0.5, 0.3, 0.2, 0.15, 0.1, 0.05, 0.02)),
}
LEVELS = 8
MOST_STRATA = 10_000


def statistics(raw: bytes) -> tuple[int, ...]:
    """Counts over one whole text, in the order of NAMES."""
    words = raw.split()
    n = len(words)
    chars = len(raw.decode()) - (len(raw) - len(raw.translate(None, _BLANK)))
    signs = len(raw) - len(raw.translate(None, _SIGNS))
    lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
    lines = [x for x in lines if x.split()]
    repeats, same = 0, 0
    if n:
        ids: dict[bytes, int] = {}
        a = np.array([ids.setdefault(w, len(ids)) for w in words], np.int64)
        same = int((a[1:] == a[:-1]).sum())
        if n > 3 and len(ids) < n:
            m = len(ids)
            pair = a[:-2] * m + a[1:-1]
            if m >= 1 << 20:  # keeps the triple within 63 bits
                pair = np.unique(pair, return_inverse=True)[1]
            _, back, count = np.unique(pair * m + a[2:], return_inverse=True, return_counts=True)
            hit = count[back] > 1
            cover = np.zeros(n, bool)
            for k in range(3):
                cover[k:n - 2 + k] |= hit
            repeats = int(cover.sum())
    return n, chars, signs, len(lines) - len(set(lines)), repeats, len(lines), same


def measure(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", stratum: str = "lang") -> DataFrame:
    own = common.own_columns(docs, doc_id=doc_id, text=text, stratum=stratum).withColumns({"doc_id": F.col("doc_id").cast("long"), "stratum": F.col("stratum").cast("string")})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = common.arrow_schema(STATS)
        for b in batches:
            got = list(zip(*map(statistics, common.texts_of(b, "text")), strict=True)) or [()] * len(NAMES)
            yield pa.RecordBatch.from_arrays([common.column_of(b, "doc_id"), common.column_of(b, "stratum"), *[pa.array(x, pa.int64()) for x in got]], schema=out)

    return map_arrow(own, run, STATS)


def binomial_tail(k: int, n: int, p: float) -> float:
    """P(X <= k) for X binomial (n, p), summed in logarithms."""
    if k >= n:
        return 1.0
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
    top = max(logs)
    return min(1.0, math.exp(top) * sum(math.exp(x - top) for x in logs))


def upper_bound(k: int, n: int, error: float) -> float:
    """Exact one-sided upper confidence bound of a share after k of n."""
    low, high = 0.0, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if 0 < mid < 1 and binomial_tail(k, n, mid) > error else (low, mid)
    return high


def separate(sizes: dict, risk: float, error: float) -> set:
    """The strata (name -> good documents) that are tested on their own; the others are pooled. Looks at sizes only."""
    order = sorted(sizes, key=lambda s: (-sizes[s], s is None, s or ""))
    for own in range(len(order), 0, -1):
        if sizes[order[own - 1]] * math.log1p(-risk) <= math.log(error / (own + (own < len(order)))):
            return set(order[:own])
    return set()


def levels(rejected: dict, sizes: dict, risk: float, error: float) -> dict:
    """Strictest allowed level of each tested group, 0 for none. ``rejected``: good documents that go on level 1, 2, ..."""
    done: set = set()
    while True:
        share = error / max(1, len(sizes) - len(done))
        reached = {}
        for g, n in sizes.items():
            t = 0
            while t < LEVELS and (g in done or binomial_tail(rejected[g][t], n, risk) <= share):
                t += 1
            reached[g] = t
        whole = {g for g, t in reached.items() if t == LEVELS}
        if whole == done:
            return reached
        done = whole


def _value(rule: str) -> str:
    return f"coalesce(cast({RULES[rule][0].replace('n_words', 'greatest(n_words, 1)')} as double), 0D)"


def level_of() -> Column:
    """Least level, from 1, on which a row is rejected; LEVELS + 1 if on none."""
    out = F.lit(LEVELS + 1)
    for t in range(LEVELS - 1, -1, -1):
        over = " or ".join(f"{_value(r)} > {cuts[t]}D" for r, (_, cuts) in RULES.items())
        out = F.when(F.expr(over), t + 1).otherwise(out)
    return out


def milder(level: int, poor: list[int], slack: float) -> int:
    """The least level that rejects all but ``slack`` of the poor documents that ``level`` does. ``poor``: how many go on level 1, 2, ..."""
    return next((t for t in range(1, level) if poor[t - 1] >= (1 - slack) * poor[level - 1]), level) if level else 0


def cutoffs(measured: DataFrame, labels: DataFrame, risk: float = 0.05, error: float = 0.05, slack: float = 0.01) -> DataFrame:
    """Staged, one row a stratum of the holdout: n_good, scope, level, the strictest level allowed, and the bound on the share of
    good documents lost at ``level`` (without correction: for reports). Strata beyond ``MOST_STRATA`` raise: one row each comes to the driver."""
    spark = measured.sparkSession
    known = labels.where(F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("quality").alias("_q")).where("_q is not null").select(F.col("doc_id").alias("_id"), (F.col("_q") == 1).alias("_good"))
    held = measured.join(known, F.col("doc_id") == F.col("_id")).withColumn("_level", level_of())
    goes = lambda t: F.col("_level") <= t + 1
    counts = held.groupBy("stratum").agg(F.count_if("_good").alias("n"), *[F.count_if(F.col("_good") & goes(t)).alias(f"k{t}") for t in range(LEVELS)], *[F.count_if(~F.col("_good") & goes(t)).alias(f"p{t}") for t in range(LEVELS)])
    got = counts.limit(MOST_STRATA + 1).collect()
    if len(got) > MOST_STRATA:
        raise ValueError(f"more than {MOST_STRATA} strata")
    sizes = {r["stratum"]: r["n"] for r in got}
    own = separate(sizes, risk, error)
    group = {s: (s, "stratum") if s in own else (None, "pooled") for s in sizes}
    total, lost, poor = {}, {}, {}
    for r in got:
        g = group[r["stratum"]]
        total[g] = total.get(g, 0) + r["n"]
        lost[g] = [a + r[f"k{t}"] for t, a in enumerate(lost.get(g, [0] * LEVELS))]
        poor[g] = [a + r[f"p{t}"] for t, a in enumerate(poor.get(g, [0] * LEVELS))]
    reached = levels(lost, total, risk, error)
    rows = []
    for s, g in group.items():
        t = milder(reached[g], poor[g], slack)
        rows.append((s, total[g], g[1] if t else "none", t, reached[g], upper_bound(lost[g][t - 1], total[g], error) if t else 0.0))
    return common.stage(spark.createDataFrame(rows, "stratum string, n_good long, scope string, level int, strictest int, lost_at_most double"), "cutoffs")


def judge(measured: DataFrame, cuts: DataFrame) -> DataFrame:
    """``measured`` with scope, level, base_failed, the rules' verdict and kept. ``cuts`` has MOST_STRATA rows at most. Strata
    without any label have no level."""
    side = F.broadcast(cuts.select(F.col("stratum").alias("_st"), "scope", "level"))
    joined = measured.join(side, F.col("stratum").eqNullSafe(F.col("_st")), "left").drop("_st").withColumns({"level": F.coalesce("level", F.lit(0)), "scope": F.coalesce("scope", F.lit("none"))})
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return joined.withColumn("base_failed", failed).withColumn("rule_failed", level_of() <= F.col("level")).withColumn("kept", ~F.col("base_failed") & ~F.col("rule_failed"))
