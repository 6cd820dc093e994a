"""Quality by ordinal cumulative-link regression on graded ratings.

P(grade > k) = sigmoid(f(text) - threshold_k) with one set of hashed-text weights for all grades and ordered thresholds.
f is the mean over words of the weights of a word's features: the word itself, its ending, the signs in it, and whether it
repeats the word before. The expected grade is the sum of the tail probabilities.

Grades from the labels: 0 low quality, 1 good but toxic, 2 good and clean. Training rows: as for toxicity, a bounded
sample outside the held-out fold. Null or empty text: f = 0. Null ids are scored, not learnt from. No labels: all
tails one half. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.llm.toxicity import training_rows
from gridmin.session import map_arrow

BUCKETS = 1 << 16
GRADES = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("expected_grade", T.DoubleType()), T.StructField("tail_1", T.DoubleType()), T.StructField("tail_2", T.DoubleType())])
_SIGNS = b"#*$%&|<>"


def features(word: bytes) -> list[int]:
    """Buckets of a word: itself without signs, its last three characters, and its signs."""
    low = word.lower()
    plain = low.translate(None, _SIGNS)
    out = [zlib.crc32(b"w" + plain) % BUCKETS, zlib.crc32(b"e" + plain[-3:]) % BUCKETS]
    if len(plain) != len(low):
        out.append(zlib.crc32(b"s" + bytes(sorted(set(low) & set(_SIGNS)))) % BUCKETS)
    return out


REPEAT = zlib.crc32(b"repeats") % BUCKETS


@dataclass
class Model:
    weight: np.ndarray
    thresholds: np.ndarray

    def tails(self, f: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(np.asarray(f)[:, None] - self.thresholds[None, :], -500, 500)))


def train(texts: list[bytes], grades: list[int], top: int = 2, rounds: int = 150, rate: float = 0.5, shrink: float = 1e-6) -> Model:
    """AdaGrad on the mean negative log-likelihood. Thresholds are the first one plus positive steps, so they stay in order."""
    index: dict[bytes, int] = {}
    docs = [np.array([index.setdefault(w, len(index)) for w in t.split()], np.int64) for t in texts]
    y = np.array(grades, np.int64)
    if not len(y):
        return Model(np.zeros(BUCKETS), np.zeros(top))
    bags = [np.array(features(w), np.int64) for w in index] or [np.zeros(1, np.int64)]
    size = np.array([len(b) for b in bags])
    flat, owner = np.concatenate(bags), np.repeat(np.arange(len(bags)), size)
    words = np.concatenate([*docs, np.zeros(0, np.int64)])
    of = np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    share = 1.0 / np.maximum(1, np.array([len(d) for d in docs]))
    again = np.array([(d[1:] == d[:-1]).sum() for d in docs]) * share
    w, steps = np.zeros(BUCKETS), np.concatenate([[-1.0], np.zeros(top - 1)])
    sum_w, sum_t = np.full(BUCKETS, 1e-8), np.full(top, 1e-8)
    for _ in range(rounds):
        per_word = np.bincount(owner, weights=w[flat], minlength=len(bags))
        f = np.bincount(of, weights=per_word[words], minlength=len(docs)) * share + w[REPEAT] * again
        _, d_f, g_t = likelihood(f, steps, y)
        by_word = np.bincount(words, weights=(d_f * share)[of], minlength=len(bags))
        g = np.bincount(flat, weights=by_word[owner], minlength=BUCKETS) + shrink * w
        g[REPEAT] += (d_f * again).sum()
        sum_w += g**2
        w -= rate * g / np.sqrt(sum_w)
        sum_t += g_t**2
        steps -= 0.1 * g_t / np.sqrt(sum_t)
    return Model(w, cuts(steps))


def cuts(steps: np.ndarray) -> np.ndarray:
    """Ordered thresholds: the first one, then each the exponential of its step above the one before."""
    return steps[0] + np.concatenate([[0.0], np.cumsum(np.exp(steps[1:]))])


def likelihood(f: np.ndarray, steps: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Mean negative log-likelihood of grades ``y`` at scores ``f``, and its derivatives in f and in the steps."""
    rows, none, all_ = np.arange(len(y)), np.zeros((len(y), 1)), np.ones((len(y), 1))
    s = 1.0 / (1.0 + np.exp(-np.clip(f[:, None] - cuts(steps)[None, :], -500, 500)))
    tail, slope = np.concatenate([all_, s, none], 1), np.concatenate([none, s * (1 - s), none], 1)
    p = np.maximum(tail[rows, y] - tail[rows, y + 1], 1e-12)
    d_f = -(slope[rows, y] - slope[rows, y + 1]) / p / len(y)
    d_cut = np.array([((slope[:, k + 1] / p) * ((y == k + 1).astype(float) - (y == k))).sum() / len(y) for k in range(len(steps))])
    return float(-np.log(p).mean()), d_f, np.array([d_cut.sum(), *[d_cut[k:].sum() * np.exp(steps[k]) for k in range(1, len(steps))]])


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = 3000, text: str = "text", doc_id: str = "doc_id") -> Model:
    graded = labels.select("doc_id", F.when(F.col("quality") == 0, 0).when((F.col("quality") == 1) & (F.col("toxic") == 1), 1).when(F.col("quality") == 1, 2).alias("grade"))
    texts, grades = training_rows(docs, graded, "grade", most_rows, text, doc_id, positive=2)
    return train(texts, grades)


def grade(docs: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, expected_grade, tail_1, tail_2): tail_k is P(grade >= k)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, out = shared.value, common.arrow_schema(GRADES)
        look = common.WordMemo(lambda w: float(m.weight[features(w)].sum()), 400_000).__getitem__
        for b in batches:
            f = []
            for t in common.texts_of(b, "text"):
                words = t.split()
                repeats = sum(map(bytes.__eq__, words, words[1:])) if words else 0
                f.append((sum(map(look, words)) + m.weight[REPEAT] * repeats) / len(words) if words else 0.0)
            tails = m.tails(np.array(f))
            yield pa.RecordBatch.from_arrays([common.column_of(b, "doc_id"), *[pa.array(x, pa.float64()) for x in (tails.sum(1), tails[:, 0], tails[:, 1])]], schema=out)

    return map_arrow(own, run, GRADES)
