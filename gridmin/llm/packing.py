"""Harmonic packing of token sequences.

A piece whose length lies in (C/(j+1), C/j] belongs to class j; a bin of class j takes exactly j pieces. Each worker packs
the rows of its partition alone, in one pass: no exchange, and memory for a fixed number of bins. Every piece of classes 1 to
K - 1 goes to a bin of its class. Full bins leave gaps; the short pieces of class K and beyond are cut to fill them
exactly. Where short pieces are too few for that, gaps are settled: each time ``GAPS`` bins wait, and at the end of the partition, the
emptiest are taken apart and their pieces fill the others. What is left at the end, less than C and the unfinished bins, is
cut at powers of two. ``filler`` marks the pieces that fill gaps; all others lie in the bin of their class.

Null or empty text: a document of the end id alone. Null ids, ties and repeated rows: each row is packed as its own
document under the id it has. Empty table: no rows. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common, tokens
from gridmin.session import map_arrow

SCHEMA = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("start", T.LongType()), T.StructField("length", T.LongType()),
    T.StructField("ids_crc32", T.LongType()), T.StructField("doc_tokens", T.LongType()), T.StructField("sequence_id", T.LongType()),
    T.StructField("offset", T.LongType()), T.StructField("sequence_tokens", T.LongType()), T.StructField("class", T.IntegerType()), T.StructField("filler", T.BooleanType()),
])
#: Bins with a gap that a worker holds at most; at C = 4096 they take 16 MB.
GAPS = 1024


class Packer:
    """Streaming packer of one partition. ``put`` and ``finish`` yield finished pieces.

    A piece is (doc_id, start, ids bytes, doc_tokens, filler); a finished one adds (sequence, offset, sequence total, class).
    """

    def __init__(self, first: int, capacity: int = 4096, classes: int = 8, gaps: int = GAPS):
        self.capacity, self.classes, self.most_gaps = capacity, classes, gaps
        self.next = first
        self.open: dict[int, list[tuple]] = {}
        self.gaps: deque[tuple[int, list[tuple], int]] = deque()  # class, pieces, tokens used

    def put(self, doc_id, ids: bytes) -> Iterator[tuple]:
        c, total = self.capacity, len(ids) // 4
        at = 0
        while total - at >= c:
            yield from self._close(1, [(doc_id, at, ids[at * 4:(at + c) * 4], total, False)])
            at += c
        if at == total:
            return
        rest = (doc_id, at, ids[at * 4:], total, False)
        j = c // (total - at)
        if j >= self.classes:
            yield from self._pour(rest)
            return
        held = self.open.setdefault(j, [])
        held.append(rest)
        if len(held) == j:
            del self.open[j]
            used = sum(len(p[2]) for p in held) // 4
            if used == c:
                yield from self._close(j, held)
            else:
                self.gaps.append((j, held, used))
                if len(self.gaps) >= self.most_gaps:
                    yield from self._settle(self.most_gaps // 2)

    def _pour(self, piece: tuple) -> Iterator[tuple]:
        doc_id, start, ids, total, _ = piece
        while ids:
            if not self.gaps:
                self.gaps.append((self.classes, [], 0))
            j, held, used = self.gaps.popleft()
            n = min(self.capacity - used, len(ids) // 4)
            held.append((doc_id, start, ids[:n * 4], total, True))
            start, ids, used = start + n, ids[n * 4:], used + n
            if used == self.capacity:
                yield from self._close(j, held)
            else:
                self.gaps.appendleft((j, held, used))

    def _settle(self, upto: int) -> Iterator[tuple]:
        """Takes the emptiest bins apart until ``upto`` are left; their pieces fill the fullest first."""
        self.gaps = deque(sorted(self.gaps, key=lambda g: -g[2]))
        while len(self.gaps) > upto:
            for piece in self.gaps.pop()[1]:
                yield from self._pour(piece)

    def _close(self, j: int, pieces: list[tuple]) -> Iterator[tuple]:
        total, at = sum(len(p[2]) for p in pieces) // 4, 0
        for doc_id, start, ids, doc, filler in pieces:
            yield doc_id, start, ids, doc, filler, self.next, at, total, j
            at += len(ids) // 4
        self.next += 1

    def finish(self) -> Iterator[tuple]:
        yield from self._settle(1)
        for _, pieces in sorted(self.open.items()):
            for piece in pieces:
                yield from self._pour(piece)
        held = [p for _, pieces, _ in self.gaps for p in pieces]
        self.gaps.clear()
        self.open.clear()
        left, now, size = sum(len(p[2]) for p in held) // 4, [], 0
        want = self._next_size(left)
        for doc_id, start, ids, doc, _ in held:
            while ids:
                n = min(want - size, len(ids) // 4)
                now.append((doc_id, start, ids[:n * 4], doc, True))
                start, ids, size = start + n, ids[n * 4:], size + n
                if size == want:
                    yield from self._close(0, now)
                    left -= size
                    now, size = [], 0
                    want = self._next_size(left)

    def _next_size(self, left: int) -> int:
        return self.capacity if left >= self.capacity else 1 << max(0, left.bit_length() - 1)


def pack(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", tokenizer: str | None = None, end_id: int = tokens.END_ID,
         capacity: int = 4096, classes: int = 8, with_ids: bool = False) -> DataFrame:
    """One row a piece (SCHEMA, and ``ids`` as unsigned 32-bit little-endian bytes if asked for).

    Sequences hold ``capacity`` ids or a power of two of them, so none needs padding. Sequence numbers are unique over
    the table; class 0 marks the rest of a partition.
    """
    shared = tokens.tokenizer_json(docs.sparkSession, tokenizer)
    schema = T.StructType([*SCHEMA.fields, *([T.StructField("ids", T.BinaryType())] if with_ids else [])])
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, out = tokens.ChunkEncoder.of(shared), common.arrow_schema(schema)
        packer = Packer(TaskContext.get().partitionId() << 40, capacity, classes)

        def rows() -> Iterator[tuple]:
            for b in batches:
                for key, ids in zip(common.column_of(b, "doc_id").to_pylist(), encoder.encode_column(common.column_of(b, "text")), strict=True):
                    yield from packer.put(key, encoder.wide(ids) + end)
            yield from packer.finish()

        pieces = ((d, s, len(i) // 4, zlib.crc32(i), n, q, o, t, j, f, *([i] if with_ids else [])) for d, s, i, n, f, q, o, t, j in rows())
        yield from common.to_batches(pieces, out, 1024 if with_ids else 8192)

    return map_arrow(own, run, schema)
