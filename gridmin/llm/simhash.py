"""SimHash near-duplicates by pivot distance tables.

A fingerprint is the bitwise majority of its shingles' XXH64 values. Fingerprints within ``most`` bits are linked. Equal
fingerprints become one node first. Nodes that agree on one of most + 1 blocks of bits meet in a bucket (two
fingerprints within ``most`` bits agree on at least one block). Inside a bucket each node's distances to fixed
reference fingerprints, computed once for all of its buckets, form a row of the table; by the triangle inequality a linked pair
differs by at most ``most`` in every coordinate, so a bucket is swept in order of the first coordinate, pairs with a
larger difference in any coordinate go, and only the survivors are compared. A bucket above ``most_nodes`` is split again over blocks of its remaining bits; as
nodes are distinct, a few splits leave no large bucket. Each bucket emits a spanning forest of its links, so the output
is linear in the nodes whatever the group sizes.

Null text: no words, fingerprint zero, linked like any other. Null ids: never the least of a component unless all are null.
Repeated rows: same fingerprint. Empty table: no rows. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.llm.components import components
from gridmin.session import map_arrow

FINGERPRINTS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("mark", T.LongType()), T.StructField("fp", T.LongType())])
EDGES = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])
PIVOTS = 16
MOST_NODES = 4096


def pivots(n: int = PIVOTS) -> np.ndarray:
    """Reference fingerprints: hashes of their numbers."""
    return np.array([xxhash.xxh64_intdigest(f"pivot {i}") for i in range(n)], np.uint64)


def fingerprint(text: bytes, shingle: int = 3) -> int:
    """Unsigned 64-bit fingerprint of a whole text: words, A-Z lower-cased, in space-joined shingles, repeats included."""
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= shingle:
        hashes = np.array([xxhash.xxh64_intdigest(joined, 42)], np.uint64)
        return int(hashes[0])
    digest = xxhash.xxh64_intdigest
    ends = (np.cumsum(np.fromiter(map(len, words), np.int64, len(words))) + np.arange(len(words))).tolist()
    starts = [0, *(e + 1 for e in ends[:-1])]
    n, ones = len(words) - shingle + 1, np.zeros(64, np.int64)
    for at in range(0, n, 65536):
        upto = min(n, at + 65536)
        hashes = np.fromiter([digest(joined[a:b], 42) for a, b in zip(starts[at:upto], ends[at + shingle - 1:upto + shingle - 1])], np.uint64, upto - at)
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """(doc_id, mark, fp): fp as a signed long of the same 64 bits."""
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumns({"doc_id": F.col("doc_id").cast("long"), "mark": common.mark(F.col("text"))})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.lean()
        out = common.arrow_schema(FINGERPRINTS)
        for b in batches:
            fps = np.array([fingerprint(t, shingle) for t in common.texts_of(b, "text")], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([common.column_of(b, "doc_id"), common.column_of(b, "mark"), pa.array(fps, pa.int64())], schema=out)

    return map_arrow(own, run, FINGERPRINTS)


def blocks(mask: int, parts: int) -> list[int]:
    """The bits outside ``mask``, cut into ``parts`` runs; each result is ``mask`` with one run added."""
    free = [i for i in range(64) if not mask >> i & 1]
    bounds = [len(free) * k // parts for k in range(parts + 1)]
    return [mask | sum(1 << i for i in free[a:b]) for a, b in zip(bounds, bounds[1:])]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def pivot_table(fp: Column, refs: np.ndarray) -> Column:
    """Distances of a fingerprint to the references."""
    return F.array(*[F.bit_count(fp.bitwiseXOR(F.lit(_signed(int(r))))).cast("tinyint") for r in refs])


def distances(fps: np.ndarray, refs: np.ndarray) -> np.ndarray:
    return np.bitwise_count(fps[:, None] ^ refs[None, :]).astype(np.int8)


def survivors(table: np.ndarray, most: int) -> int:
    """How many pairs of a bucket no coordinate discards (all pairs are looked at: for tests and tuning)."""
    near = np.abs(table[:, None, :].astype(np.int16) - table[None, :, :]).max(2) <= most
    return int(np.triu(near, 1).sum())


def forest(fps: np.ndarray, most: int, table: np.ndarray, rows: int = 256) -> list[tuple[int, int]]:
    """Indices of links that span every component among ``fps`` (distinct, unsigned); ``table``: their distances to the references."""
    by = np.argsort(table[:, 0], kind="stable")
    fps, table = fps[by], table[by]
    n, first = len(fps), table[:, 0]
    label, links = np.arange(n), []
    for at in range(0, n, rows):
        upto = min(n, at + rows)
        end = int(np.searchsorted(first, first[upto - 1] + most, "right"))
        near = np.ones((upto - at, end - at), bool)
        for k in range(min(4, table.shape[1])):  # the first coordinates over whole tiles, the others over what is left
            near &= np.abs(table[at:upto, None, k] - table[None, at:end, k]) <= most
        i, j = np.nonzero(near)
        i, j = i[i < j] + at, j[i < j] + at
        keep = label[i] != label[j]
        i, j = i[keep], j[keep]
        for k in range(4, table.shape[1]):
            keep = np.abs(table[i, k] - table[j, k]) <= most
            i, j = i[keep], j[keep]
        keep = np.bitwise_count(fps[i] ^ fps[j]) <= most
        i, j = i[keep], j[keep]
        if not len(i):
            continue
        _, one = np.unique(label[i] * n + label[j], return_index=True)
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while (up := root.get(x, x)) != x:
                x = up
            return x

        for a, b in zip(i[one].tolist(), j[one].tolist()):
            x, y = find(int(label[a])), find(int(label[b]))
            if x != y:
                root[max(x, y)] = min(x, y)
                links.append((int(by[a]), int(by[b])))
        old = np.array(list(root), np.int64)
        to = np.arange(n)
        to[old] = [find(int(x)) for x in old]
        label = to[label]
    return links


def links(nodes: DataFrame, most: int = 2, most_nodes: int = MOST_NODES) -> DataFrame:
    """Staged (a, b) links whose closure joins exactly the nodes (column ``fp``, distinct) within ``most`` bits, step by step."""
    spark, width, found = nodes.sparkSession, most + 1, []
    first = F.array(*[F.struct(F.lit(m).alias("m"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for m in map(_signed, blocks(0, width))])
    rows = nodes.select("fp", pivot_table(F.col("fp"), pivots()).alias("at")).select("fp", "at", F.explode(first).alias("x")).select("fp", "at", "x.m", "x.key")
    while True:
        counts = rows.groupBy("m", "key").agg(F.count("*").alias("n"))
        hot = common.stage(counts.where(F.col("n") > most_nodes).select(F.col("m").alias("hm"), F.col("key").alias("hk")), "hot")
        on = (F.col("m") == F.col("hm")) & (F.col("key") == F.col("hk"))
        masks = [r["hm"] for r in hot.select("hm").distinct().collect()]  # bit masks, at most width to the number of splits
        calm = rows.join(hot, on, "left_anti") if masks else rows
        buckets = calm.groupBy("m", "key").agg(F.collect_list(F.struct("fp", "at")).alias("each")).where(F.size("each") > 1)
        found.append(map_arrow(buckets.select("each"), _bucket_links(most), EDGES))
        if not masks:
            break
        inner = spark.createDataFrame([(m, _signed(c)) for m in masks for c in blocks(m & (1 << 64) - 1, width)], "pm long, cm long")
        split = rows.join(hot, on, "left_semi").join(F.broadcast(inner), F.col("m") == F.col("pm"))
        rows = common.stage(split.select("fp", "at", F.col("cm").alias("m"), F.col("fp").bitwiseAND(F.col("cm")).alias("key")), "split")
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return common.stage(out.distinct(), "links")


def _bucket_links(most: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = common.arrow_schema(EDGES)

        def rows() -> Iterator[tuple]:
            for b in batches:
                for each in common.column_of(b, "each"):
                    got = each.values.field("fp").to_numpy()
                    table = each.values.field("at").flatten().to_numpy().reshape(len(got), -1)
                    for i, j in forest(got.view(np.uint64), most, table):
                        yield min(got[i], got[j]), max(got[i], got[j])

        yield from common.to_batches(rows(), out)

    return run


def _rooted(made: DataFrame, most: int) -> DataFrame:
    """Staged (fp, least, top, n, root) of the distinct fingerprints of ``made``: root names the component."""
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")
    nodes = common.stage(made.groupBy("fp").agg(F.min("doc_id").alias("least"), F.min(order).alias("top"), F.count("*").alias("n")), "nodes")
    joined = components(links(nodes, most))
    rooted = nodes.join(joined, F.col("fp") == F.col("node"), "left").select("fp", "least", "top", "n", F.coalesce("root", "fp").alias("root"))
    return common.stage(rooted, "rooted")


def classes(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 3, most: int = 2) -> DataFrame:
    """(doc_id, fp, component_id): one row a document."""
    made = common.stage(fingerprints(docs, doc_id, text, shingle).select("doc_id", "mark", "fp"), "fingerprints")
    rooted = _rooted(made, most)
    tops = common.stage(rooted.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("fps")), "tops")
    each = common.stage(common.attach(rooted.select("fp", "n", "root"), tops, "root", "fps", rooted.count()).select("fp", "n", "component_id"), "each")
    return common.attach(made, each, "fp", "n", made.count()).select("doc_id", "fp", "component_id")


def distinct_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 3, most: int = 2) -> DataFrame:
    """One row of ``docs`` for each component, with all its columns: the one of least id (rows without id last)."""
    made = common.stage(fingerprints(docs, doc_id, text, shingle), "fingerprints")
    tops = _rooted(made, most).groupBy("root").agg(F.min("top").alias("top"))
    return common.keep_rows(docs, tops.select("top.doc_id", "top.mark"), made, doc_id, text)
