"""Canonical length-limited Huffman files of token ids.

Layout under a folder: ``header`` (id, code length: canonical codes follow from these alone) and ``blocks`` (file, block,
the documents of the block with their id counts, symbol count, payload bits, and the strides between the bit
offsets of every EVERY-th symbol). Blocks hold whole documents and decode alone; the offsets let one block decode as many
parallel runs. Both parts are Parquet, so any store that Spark reaches will do, and a lost task rewrites its file only.

Documents lie in ascending id order (null first; equal ids by a hash of their ids). Null or empty text: the end id
alone. Repeated rows are kept. Empty table: header and blocks without rows. Extra columns are ignored.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common, tokens
from gridmin.session import map_arrow

MAX_BITS = 16
EVERY = 128
_PART = 1 << 14

BLOCKS = T.StructType([
    T.StructField("file", T.IntegerType()), T.StructField("block", T.IntegerType()), T.StructField("first", T.LongType()),
    T.StructField("doc_ids", T.ArrayType(T.LongType())), T.StructField("doc_tokens", T.ArrayType(T.LongType())),
    T.StructField("symbols", T.LongType()), T.StructField("bits", T.LongType()), T.StructField("strides", T.ArrayType(T.IntegerType())),
    T.StructField("payload", T.BinaryType()),
])
IDS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("ids", T.BinaryType()), T.StructField("tie", T.LongType()), T.StructField("counts", T.BinaryType())])
DECODED = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("start", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("ids_crc32", T.LongType())])


def code_lengths(counts: np.ndarray, most: int = MAX_BITS) -> np.ndarray:
    """Optimal lengths of at most ``most`` bits for positive counts (coin collecting: pairs of the cheapest, level by level)."""
    n = len(counts)
    if n == 0:
        return np.zeros(0, np.int64)
    if n == 1:
        return np.ones(1, np.int64)
    most = max(most, int(n - 1).bit_length())
    order = np.argsort(counts, kind="stable")
    base = np.asarray(counts, np.int64)[order]
    levels: list[tuple[np.ndarray, np.ndarray]] = []  # at each level: sorted weights and whether an entry is a coin (else a pair)
    weights, coin = base, np.ones(n, bool)
    for _ in range(most - 1):
        levels.append((weights, coin))
        pairs = weights[: len(weights) // 2 * 2].reshape(-1, 2).sum(1)
        merged = np.concatenate([base, pairs])
        kind = np.concatenate([np.ones(n, bool), np.zeros(len(pairs), bool)])
        by = np.argsort(merged, kind="stable")
        weights, coin = merged[by], kind[by]
    levels.append((weights, coin))
    lengths, take = np.zeros(n, np.int64), 2 * n - 2
    for weights, coin in reversed(levels):
        chosen = coin[:take]
        k = int(chosen.sum())
        lengths[:k] += 1  # coins stand in ascending order, so the first k of them are taken
        take = 2 * (take - k)
    out = np.empty(n, np.int64)
    out[order] = lengths
    return out


class Codec:
    """Canonical codes of (symbol, length) pairs: shorter first, then by symbol."""

    def __init__(self, symbols: np.ndarray, lengths: np.ndarray):
        by = np.lexsort((symbols, lengths))
        self.symbols, self.lengths = np.asarray(symbols, np.int64)[by], np.asarray(lengths, np.int64)[by]
        self.most = int(self.lengths.max(initial=1))
        steps = np.left_shift(1, self.most - self.lengths) if len(by) else np.zeros(0, np.int64)
        aligned = np.concatenate([[0], np.cumsum(steps)])[: len(by)]
        size = int(self.symbols.max(initial=0)) + 1
        self.code = np.zeros(size, np.uint32)  # code and, in the low 5 bits, its length: one look-up a symbol
        self.code[self.symbols] = ((aligned >> (self.most - self.lengths)) << 5 | self.lengths).astype(np.uint32)
        self.table = np.zeros(1 << self.most, np.uint32)  # symbol and, in the low 5 bits, its code's length
        self.table[:int(steps.sum())] = np.repeat((self.symbols << 5 | self.lengths).astype(np.uint32), steps)

    def encode(self, ids: np.ndarray, every: int = EVERY) -> tuple[bytes, int, np.ndarray]:
        """(payload, bits, bit offset of each ``every``-th symbol). Codes never overlap, so adding them per 32-bit word packs them."""
        out, marks, start, bits = [], [], 0, 0
        carry = np.uint64(0)  # the word at which a part ends is finished by the next one
        for k in range(0, len(ids), _PART):  # parts that stay in the processor's cache
            both = self.code[ids[k:k + _PART]]
            n = (both & np.uint32(31)).astype(np.int64)
            ends = np.cumsum(n)
            at = ends - n + start
            marks.append(at[-k % every::every] + (bits - start))
            word = at >> 5
            first = np.flatnonzero(np.diff(word, prepend=-1))
            window = (both >> np.uint32(5)).astype(np.uint64) << (64 - n - (at & 31)).astype(np.uint64)
            packed = np.zeros(int(word[-1]) + 2, np.uint64)
            packed[word[first]] = np.add.reduceat(window >> np.uint64(32), first)
            packed[word[first] + 1] += np.add.reduceat(window & np.uint64(0xFFFFFFFF), first)
            packed[0] += carry
            bits += int(ends[-1])
            full, start = divmod(start + int(ends[-1]), 32)
            out.append(packed[:full].astype(">u4").tobytes())
            carry = packed[full] if full < len(packed) else np.uint64(0)
        out.append(np.array([carry]).astype(">u4").tobytes())
        return b"".join(out)[: (bits + 7) >> 3], bits, np.concatenate([*marks, np.zeros(0, np.int64)])

    def decode(self, payload: bytes, symbols: int, checkpoints: np.ndarray, every: int = EVERY) -> np.ndarray:
        """All runs between checkpoints advance together, one table look-up a symbol."""
        raw = np.frombuffer(payload + bytes(12 - len(payload) % 4), ">u4").astype(np.uint64)
        pairs = raw[:-1] << np.uint64(32) | raw[1:]  # 64 bits from each 32-bit word on
        out = np.empty((every, len(checkpoints)), np.uint32)
        at, drop, mask = np.array(checkpoints, np.int64), 64 - self.most, np.uint64((1 << self.most) - 1)
        live = len(checkpoints)
        last = symbols - (live - 1) * every if live else 0
        for k in range(every if live > 1 else last):
            if k == last:
                live -= 1  # the final run is shorter
                at = at[:live]
            key = pairs[at >> 5] >> (drop - (at & 31)).astype(np.uint64) & mask
            got = self.table[key]
            out[k, :live] = got
            at = at + (got & np.uint32(31))
        return (out >> np.uint32(5)).T.reshape(-1)[:symbols]


def encode_ids(docs: DataFrame, doc_id: str, text: str, tokenizer: str | None, end_id: int = tokens.END_ID) -> DataFrame:
    """doc_id, ids (unsigned 16-bit where the vocabulary allows, else 32-bit) and a hash to order equal ids. Each task adds a row
    with nothing but its counts of all ids, as signed 64-bit numbers: a column of its own, so reading it leaves the ids alone."""
    shared = tokens.tokenizer_json(docs.sparkSession, tokenizer)
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, out = tokens.ChunkEncoder.of(shared), common.arrow_schema(IDS)
        end, width = end_id.to_bytes(encoder.bytes, "little"), encoder.width
        counts = np.zeros(encoder.size, np.int64)

        def rows() -> Iterator[tuple]:
            for b in batches:
                for k, ids in zip(common.column_of(b, "doc_id").to_pylist(), encoder.encode_column(common.column_of(b, "text")), strict=True):
                    yield k, ids + end, zlib.crc32(ids), None

        for made in common.to_batches(rows(), out, 1024):
            counts += np.bincount(np.frombuffer(made.column(1).buffers()[2], width), minlength=len(counts))
            yield made
        yield from common.to_batches([(None, None, None, counts.tobytes())], out)

    return map_arrow(own, run, IDS)


def _counts(staged: DataFrame) -> np.ndarray:
    """Global counts by id: the tasks' count rows are added up in rounds of salted sums, never all in one place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(0, np.int64)
        for b in batches:
            for raw in common.column_of(b, "counts").to_pylist():
                c = np.frombuffer(raw, np.int64)
                total = c + total if len(total) else c
        if len(total):
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], names=["counts"])

    rows = map_arrow(staged.select("counts").where(F.col("counts").isNotNull()), run, "counts binary")
    some = max(1, int(int(staged.sparkSession.conf.get("spark.sql.shuffle.partitions")) ** 0.5))
    fewer = map_arrow(rows.repartition(some), run, "counts binary").coalesce(1)
    got = map_arrow(fewer, run, "counts binary").collect()  # one row of a number for each id of the vocabulary
    return np.frombuffer(got[0]["counts"], np.int64) if got else np.zeros(0, np.int64)


def write_files(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text", tokenizer: str | None = None,
                block_symbols: int = 1 << 18, max_bits: int = MAX_BITS) -> None:
    """Tokenize all of ``docs`` and write ``header`` and ``blocks`` below ``path``.

    Global counts have a row for each id of the vocabulary at most; they alone come to the driver, to fix the code lengths.
    """
    spark = docs.sparkSession
    staged = common.stage(encode_ids(docs, doc_id, text, tokenizer), "ids")
    counts = _counts(staged)
    width = "<u2" if len(counts) <= 1 << 16 else "<u4"
    symbols = np.flatnonzero(counts)
    lengths = code_lengths(counts[symbols], max_bits)
    header = spark.createDataFrame([(int(s), int(n)) for s, n in zip(symbols, lengths)], "symbol long, bits int")
    header.coalesce(1).write.parquet(f"{path}/header")
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ordered = staged.where(F.col("ids").isNotNull()).select("doc_id", "ids", "tie").repartitionByRange(parts, F.col("doc_id").asc_nulls_first(), "tie").sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "tie")
    code = spark.sparkContext.broadcast((symbols, lengths))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, out, file = Codec(*code.value), common.arrow_schema(BLOCKS), TaskContext.get().partitionId()

        def blocks() -> Iterator[tuple]:
            keys, parts, size, block, first = [], [], 0, 0, 0
            for b in batches:
                for key, raw in zip(common.column_of(b, "doc_id").to_pylist(), common.column_of(b, "ids").to_pylist(), strict=True):
                    ids = np.frombuffer(raw, width)
                    keys.append(key)
                    parts.append(ids)
                    size += len(ids)
                    if size >= block_symbols:
                        yield one(keys, parts, size, block, first)
                        block, first = block + 1, first + size
                        keys, parts, size = [], [], 0
            if keys:
                yield one(keys, parts, size, block, first)

        def one(keys: list, parts: list, size: int, block: int, first: int) -> tuple:
            payload, bits, marks = codec.encode(np.concatenate(parts))
            return file, block, first, keys, [len(p) for p in parts], size, bits, np.diff(marks, prepend=0).tolist(), payload

        yield from common.to_batches(blocks(), out, 16)

    map_arrow(ordered.select("doc_id", "ids"), run, BLOCKS).write.option("compression", "none").parquet(f"{path}/blocks")
    common.drop_staged(spark, staged)


def read_files(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, start (ids before it in the whole order), n_tokens, ids_crc32, and ``ids`` as 32-bit bytes if asked for."""
    header = spark.read.schema("symbol long, bits int").parquet(f"{path}/header").toPandas()  # a row for each id of the vocabulary at most
    code = spark.sparkContext.broadcast((header["symbol"].to_numpy(np.int64), header["bits"].to_numpy(np.int64)))
    blocks = spark.read.schema(BLOCKS).parquet(f"{path}/blocks")
    sizes = blocks.groupBy("file").agg(F.sum("symbols").alias("n"))  # a row for each file: as many as write tasks
    before = sizes.select("file", (F.sum("n").over(W.orderBy("file")) - F.col("n")).alias("before"))
    placed = blocks.join(F.broadcast(before), "file").select((F.col("before") + F.col("first")).alias("first"), "doc_ids", "doc_tokens", "symbols", "strides", "payload")
    schema = T.StructType([*DECODED.fields, *([T.StructField("ids", T.BinaryType())] if with_ids else [])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, out = Codec(*code.value), common.arrow_schema(schema)

        def rows() -> Iterator[tuple]:
            for b in batches:
                for r in b.to_pylist():
                    raw = codec.decode(r["payload"], r["symbols"], np.cumsum(np.array(r["strides"], np.int64))).astype("<u4").tobytes()
                    at = 0
                    for key, n in zip(r["doc_ids"], r["doc_tokens"], strict=True):
                        ids = raw[at * 4:(at + n) * 4]
                        yield (key, r["first"] + at, n, zlib.crc32(ids), *([ids] if with_ids else []))
                        at += n

        yield from common.to_batches(rows(), out, 1024 if with_ids else 8192)

    return map_arrow(placed, run, schema)


def round_trip(docs: DataFrame, **options) -> DataFrame:
    """Write to a new folder in the shared directory and read back."""
    path = f"{common.shared_dir(docs.sparkSession)}/huffman-{uuid.uuid4().hex}"
    write_files(docs, path, **options)
    return read_files(docs.sparkSession, path)
