"""Toxicity by subword bags: character n-gram vectors, averaged, under a linear softmax, trained jointly in numpy.

A word is the bag of its hashed character n-grams, so an unseen spelling shares most of its vectors with a known one. The
average is over all words of a text (``window`` None) or over every run of ``window`` words, of which the worst one is the
document's score: a few insults in a long text vanish in its mean, and at WINDOW words they do not (README: recall of
both). Training starts on the means of whole documents and then keeps to each document's worst windows under the current
model; of marked documents up to ``most_windows`` that it finds toxic. As the softmax is linear, a word enters a score
only by the sum of its n-grams' projections, so scoring is one look-up a word.

Training rows: labelled documents outside the held-out fold, at most ``most_rows`` of them, chosen by hash. Labels, language,
source and id never enter a score. Null or empty text: the score of no evidence. Null label: row unused. Repeated label
rows: the largest label counts; repeated document ids: one of the texts is learnt from. No labels: every score is
that of the untrained prior. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.session import map_arrow

WINDOW = 3
BUCKETS = 1 << 16
SCORES = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("score", T.DoubleType())])


def grams(word: bytes, buckets: int = BUCKETS) -> list[int]:
    """Buckets of the character 3- to 5-grams of a word, lower-cased, without signs at its ends, marked at both ends."""
    text = word.decode().lower().strip(".,;:!?\"'()[]{}|#*$%&<>")
    full = f"<{text}>"
    raw = full.encode()
    if len(raw) == len(full):
        parts = [raw[i:i + n] for n in (3, 4, 5) for i in range(len(raw) - n + 1)]
    else:
        parts = [full[i:i + n].encode() for n in (3, 4, 5) for i in range(len(full) - n + 1)]
    return [zlib.crc32(p) % buckets for p in parts] or [zlib.crc32(raw) % buckets]


@dataclass
class Model:
    """What scoring needs of the trained vectors: each bucket's projection on the class difference, and the bias."""

    gram: np.ndarray
    bias: float
    window: int | None = WINDOW

    def word(self, word: bytes) -> tuple[float, int]:
        g = grams(word, len(self.gram))
        return float(self.gram[g].sum()), len(g)


def windows(sums: np.ndarray, counts: np.ndarray, width: int | None) -> np.ndarray:
    """Mean projection of each run of ``width`` words (of all words, if there are fewer or no width is given)."""
    width = width or len(sums)
    s, c = np.concatenate([[0.0], np.cumsum(sums)]), np.concatenate([[0.0], np.cumsum(counts)])
    w = min(width, len(sums))
    return (s[w:] - s[:-w]) / (c[w:] - c[:-w])


def train(texts: list[bytes], labels: list[int], dim: int = 8, warm: int = 15, rounds: int = 60, rate: float = 0.5, seed: int = 3,
          decay: float = 0.02, floor: float = 0.005, marked: float = 0.35, window: int | None = WINDOW, most_windows: int = 4) -> Model:
    """Joint training of n-gram vectors and softmax by AdaGrad steps over all rows, with decaying vectors.

    The step's denominator has a floor in the largest gradient of any n-gram, so n-grams of few documents move little. Class 1
    has the share ``marked`` of the loss: below one half, clean documents are kept in doubt.
    """
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-0.5, 0.5, (BUCKETS, dim)) / dim
    out = rng.uniform(-0.5, 0.5, (dim, 2))
    bias = np.zeros(2)
    index: dict[bytes, int] = {}
    docs = [np.array([index.setdefault(w, len(index)) for w in t.split()], np.int32) for t in texts]
    y = np.array([v for v, d in zip(labels, docs) if len(d)], np.int64)
    docs = [d for d in docs if len(d)]
    if len(set(y.tolist())) < 2:
        share = (sum(labels) + 1.0) / (len(labels) + 2.0)
        return Model(np.zeros(BUCKETS), float(np.log(share / (1 - share))), window)
    flat, counted = array("i"), array("i")
    for w in index:
        g = grams(w)
        flat.extend(g)
        counted.append(len(g))
    del index
    flat, sizes = np.frombuffer(flat, np.int32), np.frombuffer(counted, np.int32).astype(np.int64)
    first = np.concatenate([[0], np.cumsum(sizes)])
    largest = 0.0
    sum_v, sum_o, sum_b = np.full(BUCKETS, 1e-8), np.full(out.shape, 1e-8), np.full(2, 1e-8)

    def summed(at: np.ndarray, values: np.ndarray, of: np.ndarray, n: int, weight: np.ndarray | float = 1.0) -> np.ndarray:
        """Row at[j] of the result adds up weight[j] * values[of[j]]; one dimension at a time, to hold little."""
        return np.stack([np.bincount(at, weights=weight * values[of, k], minlength=n) for k in range(dim)], 1)

    place = np.zeros(len(sizes), np.int64)

    def laid_out(words: np.ndarray, of: np.ndarray, times: np.ndarray, owner: np.ndarray) -> tuple:
        """Rows of means: word k stands times[k] times in row of[k]; row r belongs to document owner[r]. Vectors are summed once a
        word, then by row."""
        used = np.flatnonzero(np.bincount(words, minlength=len(sizes)))
        place[used] = np.arange(len(used))
        n = sizes[used]
        bag = flat[np.repeat((first[used] - np.cumsum(n) + n).astype(np.int32), n) + np.arange(n.sum(), dtype=np.int32)]
        weight = times / np.bincount(of, weights=times * sizes[words])[of]
        return place[words].astype(np.int32), len(used), bag, np.repeat(np.arange(len(used), dtype=np.int32), n), of, weight, owner

    def step(word: np.ndarray, used: int, bag: np.ndarray, within: np.ndarray, of: np.ndarray, weight: np.ndarray, owner: np.ndarray) -> None:
        """One step on rows as from ``laid_out``."""
        nonlocal out, bias, largest
        label = y[owner]
        share = 1.0 / np.bincount(owner, minlength=len(docs))[owner]
        balance = np.where(label == 1, marked / max(1, (y == 1).sum()), (1 - marked) / max(1, (y == 0).sum())) * share
        mean = summed(of, summed(within, vectors, bag, used), word, len(owner), weight)
        z = mean @ out + bias
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        err = (p - np.eye(2)[label]) * balance[:, None]
        touched = np.flatnonzero(np.bincount(bag, minlength=BUCKETS))
        grad = summed(bag, summed(word, err @ out.T, of, used, weight), within, BUCKETS)[touched]
        g_out, g_bias = mean.T @ err, err.sum(0)
        sum_v[touched] += (grad**2).mean(1)
        vectors[:] *= 1.0 - decay
        largest = max(largest, float((grad**2).mean(1).max()))
        vectors[touched] -= rate * grad / np.sqrt(sum_v[touched] + floor * largest)[:, None]
        np.add(sum_o, g_out**2, out=sum_o)
        out = out - rate * g_out / np.sqrt(sum_o)
        np.add(sum_b, g_bias**2, out=sum_b)
        bias = bias - rate * 0.2 * g_bias / np.sqrt(sum_b)

    counts = [np.unique(d, return_counts=True) for d in docs]
    whole = laid_out(np.concatenate([c[0] for c in counts]), np.repeat(np.arange(len(docs), dtype=np.int32), [len(c[0]) for c in counts]), np.concatenate([c[1] for c in counts]), np.arange(len(docs)))
    for _ in range(warm if window else warm + rounds):
        step(*whole)
    for _ in range(rounds if window else 0):
        projected = vectors @ (out[:, 1] - out[:, 0])
        per_word = np.add.reduceat(projected[flat], first[:-1])
        shift = bias[1] - bias[0]
        words, owner = [], []
        for k, d in enumerate(docs):
            z = windows(per_word[d], sizes[d], window)
            for n in range(most_windows if y[k] else 1):
                at = int(np.argmax(z))
                if n and z[at] + shift <= 0:
                    break
                words.append(d[at:at + window])
                owner.append(k)
                z[max(0, at - window + 1):at + window] = -np.inf
        step(*laid_out(np.concatenate(words), np.repeat(np.arange(len(words)), [len(w) for w in words]), np.ones(sum(map(len, words))), np.array(owner)))
    return Model((vectors @ (out[:, 1] - out[:, 0])), float(bias[1] - bias[0]), window)


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most_rows: int, text: str = "text", doc_id: str = "doc_id", positive: int = 1) -> tuple[list[bytes], list[int]]:
    """At most ``most_rows`` labelled texts outside the held-out fold, half of them of class ``positive`` where there are enough.

    Labels are cut to the sample before they meet the documents, so what is broadcast and collected is bounded.
    """
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~common.in_fold(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max(label).cast("int").alias("label")).withColumn("_h", F.xxhash64("doc_id"))
    half = most_rows // 2
    parts = [known.where(c).orderBy("_h").limit(half) for c in (F.col("label") == positive, F.col("label") != positive)]
    sample = parts[0].unionByName(parts[1]).select(F.col("doc_id").alias("_id"), "label")
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))
    rows = own.join(F.broadcast(sample), F.col("doc_id") == F.col("_id")).groupBy("_id").agg(F.min("text").alias("text"), F.max("label").alias("label"))
    got = sorted(rows.collect(), key=lambda r: r["_id"])
    return [(r["text"] or "").encode() for r in got], [r["label"] for r in got]


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = 3000, text: str = "text", doc_id: str = "doc_id", window: int | None = WINDOW) -> Model:
    texts, known = training_rows(docs, labels, "toxic", most_rows, text, doc_id)
    return train(texts, known, window=window)


def scores(docs: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, score) of every row; the model is of fixed size."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))
    return map_arrow(own, lambda batches: _score_batches(batches, shared), SCORES)


def below(docs: DataFrame, model: Model, cut: float, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that score under ``cut``, with their columns and no other."""
    shared, at = docs.sparkSession.sparkContext.broadcast(model), f"c{docs.columns.index(text)}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = _scorer(shared.value)
        for b in batches:
            yield b.filter(pa.array([score(t) < cut for t in common.texts_of(b, at)], pa.bool_()))

    plain = T.StructType([T.StructField(f"c{k}", f.dataType, f.nullable) for k, f in enumerate(docs.schema)])
    return map_arrow(docs.toDF(*plain.names), run, plain).toDF(*docs.columns)


def _scorer(model: Model):
    common.lean()
    memo, none = common.WordMemo(model.word, 300_000), 1.0 / (1.0 + float(np.exp(-model.bias)))
    look = memo.__getitem__

    def score(text: bytes) -> float:
        words = text.split()
        if not words:
            return none
        pair = np.array(list(map(look, words)))
        z = float(windows(pair[:, 0], pair[:, 1], model.window).max()) + model.bias
        return 1.0 / (1.0 + float(np.exp(-np.clip(z, -500, 500))))

    return score


def _score_batches(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    score, out = _scorer(shared.value), common.arrow_schema(SCORES)
    for b in batches:
        got = pa.array([score(t) for t in common.texts_of(b, "text")], pa.float64())
        yield pa.RecordBatch.from_arrays([common.column_of(b, "doc_id"), got], schema=out)
