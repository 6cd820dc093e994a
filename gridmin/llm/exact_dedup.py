"""Exact deduplication by content-defined chunk recipes.

Texts, lower-cased in A-Z only, are cut where a rolling hash of the last 32 bytes hits a pattern, so equal stretches give
equal chunks wherever they stand. A document becomes a recipe: the ordered list of its chunks' identifiers. 64-bit
identifiers are verified against SHA-256 over all chunks; should two different chunks share one, every recipe uses
the SHA-256 digests instead. Documents are equal when their recipes are; only recipes move, never texts.

Null text: empty (one group with empty texts). Null ids: lose to any id; equal ids: exactly one row stays. Repeated rows
are rows like any other. Empty table: no rows. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.session import map_arrow

RECIPES = T.StructType([
    T.StructField("uid", T.LongType()), T.StructField("doc_id", T.LongType()), T.StructField("mark", T.LongType()), T.StructField("text_sha256", T.StringType()),
    T.StructField("weak", T.ArrayType(T.LongType())), T.StructField("strong", T.ArrayType(T.BinaryType())),
])

#: Chunks are LEAST to MOST bytes long, about LEAST + 2 ** MASK_BITS on average.
LEAST, MASK_BITS, MOST = 512, 11, 16384


def _gear() -> np.ndarray:
    """256 scattered 32-bit numbers from an integer mixing rule."""
    x = (np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) & np.uint64(0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((x ^ (x >> np.uint64(27))) >> np.uint64(16)).astype(np.uint32)


GEAR = _gear()


def cuts(data: bytes) -> list[int]:
    """Chunk ends. The hash at a byte depends on the 32 bytes up to it, nothing else."""
    n = len(data)
    if n <= LEAST:
        return [n]
    h = GEAR[np.frombuffer(data, np.uint8)]
    for s in (1, 2, 4, 8, 16):
        wider = h.copy()
        wider[s:] += h[:-s] << np.uint32(s)
        h = wider
    marks = (np.flatnonzero(h >> np.uint32(32 - MASK_BITS) == 0) + 1).tolist()
    ends, last = [], 0
    for m in [*marks, n]:
        while m - last > MOST:
            last += MOST
            ends.append(last)
        if m - last >= LEAST or (m == n and m > last):
            ends.append(m)
            last = m
    return ends


def recipes(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: uid (unique), doc_id, text_sha256, and the weak and strong identifiers of its chunks, in order."""
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumns({"doc_id": F.col("doc_id").cast("long"), "mark": common.mark(F.col("text"))})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.lean()
        out, first = common.arrow_schema(RECIPES), TaskContext.get().partitionId() << 40

        def rows() -> Iterator[tuple]:
            uid = first
            for b in batches:
                for key, mark, raw in zip(common.column_of(b, "doc_id").to_pylist(), common.column_of(b, "mark").to_pylist(), common.texts_of(b, "text"), strict=True):
                    data, at, weak, strong = raw.lower(), 0, [], []
                    for end in cuts(data):
                        chunk = data[at:end]
                        weak.append(xxhash.xxh64_intdigest(chunk) - (1 << 63))
                        strong.append(hashlib.sha256(chunk).digest())
                        at = end
                    yield uid, key, mark, hashlib.sha256(data).hexdigest(), weak, strong
                    uid += 1

        yield from common.to_batches(rows(), out, 4096)

    return map_arrow(own, run, RECIPES)


def chunk_table(made: DataFrame) -> DataFrame:
    """Every different chunk once: weak identifier, least and largest digest under it, and how often it is used."""
    chunks = made.select(F.explode(F.arrays_zip("weak", "strong")).alias("c")).select("c.weak", "c.strong")
    return chunks.groupBy("weak").agg(F.min("strong").alias("strong"), F.max("strong").alias("other"), F.count("*").alias("uses"))


def deduplicate(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """uid, doc_id, mark, keep_id, group_size, kept, text_sha256: one row a document; the largest id of a group is kept."""
    made = common.stage(recipes(docs, doc_id, text), "recipes")
    clash = not chunk_table(made).where(F.col("strong") != F.col("other")).isEmpty()
    listed = made.select("uid", "doc_id", "mark", "text_sha256", F.col("strong" if clash else "weak").alias("recipe"))
    groups = listed.groupBy("recipe").agg(
        F.max(F.struct(F.coalesce("doc_id", F.lit(-(2**63))).alias("rank"), "doc_id", "uid")).alias("top"), F.count("*").alias("group_size"))
    groups = common.stage(groups.select("recipe", F.col("top.doc_id").alias("keep_id"), F.col("top.uid").alias("keep_uid"), "group_size"), "groups")
    placed = common.attach(listed, groups, "recipe", "group_size", made.count())
    return placed.select("uid", "doc_id", "mark", "keep_id", "group_size", (F.col("uid") == F.col("keep_uid")).alias("kept"), "text_sha256")


def distinct_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns."""
    judged = common.stage(deduplicate(docs, doc_id, text).select("doc_id", "mark", "kept"), "judged")
    return common.keep_rows(docs, judged.where("kept"), judged, doc_id, text)
