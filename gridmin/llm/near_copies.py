"""Near copies by whole texts: documents whose sets of 5-word shingles agree to 0.8 (Jaccard) or more are linked.

Candidates meet under keys, and every link is verified over the whole sets of its two texts, so no key links anything by
itself. There are two kinds of keys:

* components of fingerprints within ``most`` bits (the pivot method of ``simhash``);
* for what fingerprints miss, one key a shingle. In any order common to all sets, two sets at 0.8 share a shingle among
  the first n - ceil(0.8 n) + 1 of each, so every pair meets. Frequent shingles come last: passages that many unrelated
  texts hold are then rarely among the first. Which ones count as frequent changes the work, not the result.

Only components are wanted, not all links of a group, so large groups are drawn together first: in each of ``HUBS`` rounds
every node is compared with one node of each of its keys, the hub, which is linear in the rows however large the group.
After that, keys whose nodes are all in one component are done. Under the other keys every two nodes of different
components are compared, so no link that joins two components is lost. Before texts move, both steps leave out pairs whose sizes or
counts of shingles in ``BINS`` bins differ by more than those of alike sets can. The nodes of a large key are dealt into slices of ``SLICE``
and each pair of slices is a task's cell. The second step grows with the product of different components under one key:
many texts that share rare shingles and yet are not alike are the price of leaving nothing out.

A 64-bit hash stands for a shingle, and the hash of a set for texts of equal sets, which are one node. A text below five
words is one shingle; null counts as empty. Null ids come last in a component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common, simhash
from gridmin.llm.components import components
from gridmin.session import map_arrow

SHINGLE = 5
#: A shingle among the first of more texts than this, in order of hash, counts as frequent; at most so many are told apart.
FREQUENT = 8
MOST_FREQUENT = 100_000
HUBS = 1
BINS = 256
SLICE = 512
#: Partners that one task compares with a node; a node of more partners is copied to several tasks.
PARTNERS = 256
FIRST = T.StructType([T.StructField("node", T.LongType()), T.StructField("size", T.LongType()), T.StructField("first", T.ArrayType(T.LongType()))])
MADE = T.StructType([*simhash.FINGERPRINTS, T.StructField("node", T.LongType()), T.StructField("size", T.LongType()), T.StructField("bins", T.BinaryType())])


def shingles(text: bytes) -> np.ndarray:
    """Distinct hashes of the text's shingles, ascending. Words as in ``simhash.fingerprint``."""
    words = text.lower().split()
    n = len(words) - SHINGLE + 1
    if n < 1:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), 5)], np.uint64)
    each = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    out = np.zeros(n, np.uint64)
    for k in range(SHINGLE):
        out = (out ^ each[k:n + k]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return np.unique(out)


def node_of(own: np.ndarray) -> int:
    return simhash._signed(xxhash.xxh64_intdigest(own.tobytes()))


def alike(both, one, other):
    """Jaccard of at least 0.8 in whole numbers: 5 both >= 4 (one + other - both)."""
    return 9 * both >= 4 * (one + other)


def shared(one: np.ndarray, other: np.ndarray) -> int:
    """How many shingles two sets share; both ascending."""
    if len(one) > len(other):
        one, other = other, one
    at = np.minimum(np.searchsorted(other, one), len(other) - 1)
    return int((other[at] == one).sum())


def _made(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, fp, node, size, bins): one row a document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.lean()

        def rows() -> Iterator[tuple]:
            for b in batches:
                ids, marks = (common.column_of(b, k).to_pylist() for k in ("doc_id", "mark"))
                for key, mark, text in zip(ids, marks, common.texts_of(b, "text"), strict=True):
                    own = shingles(text)
                    yield key, mark, simhash._signed(simhash.fingerprint(text)), node_of(own), len(own), bins(own).tobytes()

        yield from common.to_batches(rows(), common.arrow_schema(MADE), 1024)

    return map_arrow(docs, run, MADE)


def pivot_keys(made: DataFrame, most: int) -> DataFrame:
    """(key, node): nodes whose fingerprints are in one component, where there are several."""
    rooted = simhash._rooted(made, most).select("fp", "root")
    several = rooted.groupBy("root").agg(F.count("*").alias("n")).where("n > 1").select("root")
    return made.join(rooted.join(several, "root"), "fp").select(F.xxhash64(F.lit("pivot"), "root").alias("key"), "node").distinct()


def first_shingles(own: np.ndarray, frequent: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Those of which two alike sets share one: ``own`` in order of frequency, then hash. ``frequent`` is ascending."""
    n = len(own)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, own), len(frequent) - 1)
        own = own[np.argsort(np.where(frequent[at] == own, counts[at], 0), kind="stable")]
    return own[:n - -(-4 * n // 5) + 1]


def bins(own: np.ndarray) -> np.ndarray:
    """Shingles in each bin, 255 at most. The sum of differences between two sets is never above the number of shingles that only one has."""
    return np.minimum(np.bincount((own % np.uint64(BINS)).astype(np.int64), minlength=BINS), 255).astype(np.uint8)


def may_be_alike(one: np.ndarray, size: int, others: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """For each row of ``others``: false only if it can't be alike. Alike sets differ in a ninth of their sizes' sum at most."""
    return 9 * np.abs(others.astype(np.int16) - one).sum(1, dtype=np.int64) <= size + sizes


def _first(docs: DataFrame, frequent: np.ndarray, counts: np.ndarray) -> DataFrame:
    """(node, size, first): one row a document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.lean()

        def rows() -> Iterator[tuple]:
            for b in batches:
                for own in map(shingles, common.texts_of(b, "text")):
                    yield node_of(own), len(own), first_shingles(own, frequent, counts).view(np.int64)

        yield from common.to_batches(rows(), common.arrow_schema(FIRST), 1024)

    return map_arrow(docs.select("text"), run, FIRST)


def shingle_keys(docs: DataFrame, frequent: int = FREQUENT) -> DataFrame:
    """(key, node): nodes under each of their first shingles that another text has among its first."""
    none = np.zeros(0, np.uint64)
    often = _first(docs, none, none).select(F.explode("first").alias("key")).groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > frequent)
    top = often.orderBy(F.desc("n"), "key").limit(MOST_FREQUENT).toArrow()
    keys, counts = top["key"].to_numpy().view(np.uint64), top["n"].to_numpy()
    by = np.argsort(keys)
    first = common.stage(_first(docs, keys[by], counts[by]), "first")
    rows = first.select("node", F.explode("first").alias("key"))
    held = rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    return rows.join(held, "key", "left_semi").select("key", "node").distinct()


def several(rows: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """Staged ``rows`` (key, exact, node, size) with ``top``, the component of the node, under keys that hold several components."""
    if labels is None:
        now = rows.withColumn("top", F.col("node"))
    else:
        now = rows.join(labels, "node", "left").withColumn("top", F.coalesce("root", "node")).drop("root")
    held = now.groupBy("key").agg(F.min("top").alias("lo"), F.max("top").alias("hi")).where("lo <> hi")
    return common.stage(now.join(held.select("key"), "key", "left_semi").select("key", "exact", "node", "size", "top"), "live")


def hub_pairs(live: DataFrame, turn: int) -> DataFrame:
    """(a, b): each node with the hub of each of its keys, where their components differ and their sizes may be alike."""
    order = F.struct(F.xxhash64("node", F.lit(turn)).alias("h"), "node", "size", "top")
    hubs = live.groupBy("key").agg(F.min(order).alias("hub")).select("key", F.col("hub.node").alias("a"), F.col("hub.size").alias("hub_size"), F.col("hub.top").alias("hub_top"))
    near = 5 * F.least("size", "hub_size") >= 4 * F.greatest("size", "hub_size")
    return live.join(hubs, "key").where((F.col("top") != F.col("hub_top")) & near).select("a", F.col("node").alias("b")).distinct()


def cell_pairs(live: DataFrame, nodes: DataFrame, slice_nodes: int) -> DataFrame:
    """(a, b): all pairs of different components under one key that their bins don't rule out."""
    led = live.join(live.groupBy("node").agg(F.min("key").alias("lead")), "node")
    held = led.groupBy("key").agg(F.count("*").alias("n"), F.min("lead").alias("lo"), F.max("lead").alias("hi"))
    held = held.where("lo <> hi or lo = key").select("key", F.ceil(F.col("n") / slice_nodes).cast("long").alias("g"))  # else all meet under lo
    dealt = live.join(held, "key").withColumn("own", F.pmod(F.xxhash64("node"), "g"))
    cells = dealt.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("g") - 1)))
    cells = cells.select("node", "size", "top", "key", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
    rows = cells.join(nodes.select("node", "bins"), "node").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")
    return map_arrow(rows.select("key", "i", "j", "own", "node", "size", "top", "bins"), _run_cells, simhash.EDGES).distinct()


def _run_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def pairs(cell: tuple, rows: list[tuple]) -> Iterator[tuple]:
        own, node, size, top = (np.array([r[k] for r in rows], np.int64) for k in range(4))
        each = np.array([np.frombuffer(r[4], np.uint8) for r in rows])
        for k in range(len(rows)):
            at = np.flatnonzero((top != top[k]) & (node > node[k]) & (5 * np.minimum(size, size[k]) >= 4 * np.maximum(size, size[k])) & ((own != own[k]) | (cell[1] == cell[2])))
            for m in at[may_be_alike(each[k], size[k], each[at], size[at])].tolist():
                yield int(node[k]), int(node[m])

    def rows() -> Iterator[tuple]:
        common.lean()
        cell, held = None, []
        for b in batches:
            for *name, own, node, size, top, raw in zip(*(b.column(k).to_pylist() for k in range(8))):
                if name != cell:
                    if len(held) > 1:
                        yield from pairs(cell, held)
                    cell, held = name, []
                held.append((own, node, size, top, raw))
        if len(held) > 1:
            yield from pairs(cell, held)

    yield from common.to_batches(rows(), common.arrow_schema(simhash.EDGES))


def plausible(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Staged ``pairs`` without those that the bins of their nodes rule out."""
    sketch = lambda p: nodes.select(F.col("node").alias(p), F.col("size").alias(f"{p}_size"), F.col("bins").alias(f"{p}_bins"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(common.column_of(batch, k).to_pylist()), np.uint8).reshape(-1, BINS) for k in ("a_bins", "b_bins"))
            size = common.column_of(batch, "a_size").to_numpy() + common.column_of(batch, "b_size").to_numpy()
            keep = pa.array(9 * np.abs(a.astype(np.int16) - b).sum(1, dtype=np.int64) <= size)
            yield pa.RecordBatch.from_arrays([common.column_of(batch, k).filter(keep) for k in ("a", "b")], names=["a", "b"])

    both = pairs.join(sketch("b"), "b").join(sketch("a"), "a").select("a", "b", "a_size", "b_size", "a_bins", "b_bins")
    return common.stage(map_arrow(both, run, simhash.EDGES), "plausible")


def true_links(docs: DataFrame, pairs: DataFrame, nodes: DataFrame, partners: int = PARTNERS) -> DataFrame:
    """Staged: those of ``pairs`` (a, b; staged) whose whole texts are alike. ``docs``: doc_id, text, mark."""
    held = pairs.groupBy("a").agg(F.ceil(F.count("*") / partners).cast("long").alias("g"))
    members = pairs.join(held, "a").select(F.col("b").alias("node"), "a", F.pmod(F.xxhash64("b"), "g").alias("chunk"))
    at = common.stage(members.unionByName(members.select(F.col("a").alias("node"), "a", "chunk").distinct()), "at")
    named = at.select("node").distinct().join(nodes, "node").select("node", F.col("top.doc_id").alias("_ki"), F.col("top.mark").alias("_km"))
    texts = docs.join(named, F.col("doc_id").eqNullSafe(F.col("_ki")) & (F.col("mark") == F.col("_km"))).select("node", "text")
    rows = at.join(texts, "node").select("a", "chunk", (F.col("node") != F.col("a")).alias("member"), "node", "text")
    return common.stage(map_arrow(rows.repartition("a", "chunk").sortWithinPartitions("a", "chunk", "member"), _run_links, simhash.EDGES).distinct(), "links")


def _run_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def rows() -> Iterator[tuple]:
        common.lean()
        cell, hub = None, np.zeros(0, np.uint64)
        for b in batches:
            names = zip(*(common.column_of(b, k).to_pylist() for k in ("a", "chunk", "node")))
            for (a, chunk, node), text in zip(names, common.texts_of(b, "text")):
                own = shingles(text)
                if (a, chunk) != cell:  # the first row of a chunk is the hub
                    cell, hub = (a, chunk), own
                elif node != a and alike(shared(hub, own), len(hub), len(own)):
                    yield min(a, node), max(a, node)

    yield from common.to_batches(rows(), common.arrow_schema(simhash.EDGES))


def groups(docs: DataFrame, made: DataFrame, nodes: DataFrame, most: int, hubs: int = HUBS, slice_nodes: int = SLICE) -> DataFrame:
    """(node, root) of every node that a true link joins to another."""
    keys = pivot_keys(made, most).withColumn("exact", F.lit(False)).unionByName(shingle_keys(docs).withColumn("exact", F.lit(True)))
    live, links = several(common.stage(keys.join(nodes.select("node", "size"), "node"), "keys")), None
    for turn in range(hubs):
        found = true_links(docs, plausible(hub_pairs(live, turn), nodes), nodes)
        links = found if links is None else common.stage(links.unionByName(found), "links")
        live = several(live.drop("top"), components(links))
    found = true_links(docs, common.stage(cell_pairs(live.where("exact"), nodes, slice_nodes), "pairs"), nodes)
    return components(common.stage(links.unionByName(found), "links"))


def distinct_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", most: int = 6, hubs: int = HUBS, slice_nodes: int = SLICE) -> DataFrame:
    """One row of ``docs`` for each component of true links, with all its columns: the one of least id (rows without id last)."""
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumns({"doc_id": F.col("doc_id").cast("long"), "mark": common.mark(F.col("text"))})
    made = common.stage(_made(own), "made")
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")
    nodes = common.stage(made.groupBy("node").agg(F.min(order).alias("top"), F.first("size").alias("size"), F.first("bins").alias("bins")), "nodes")
    joined = groups(own, made, nodes, most, hubs, slice_nodes)
    rooted = nodes.join(joined, "node", "left").select("top", F.coalesce("root", "node").alias("root"))
    tops = rooted.groupBy("root").agg(F.min("top").alias("top"))
    return common.keep_rows(docs, tops.select("top.doc_id", "top.mark"), made, doc_id, text)
