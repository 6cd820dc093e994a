"""Greedy word-piece lengths by a longest-match automaton.

The vocabulary is a trie with two roots: one for pieces that begin a word, one for pieces that continue it. Every
node has a failure link, the node where matching goes on after the longest pieces before it are popped, and the
number of pieces popped on the way. Counting then reads each character once and follows links, so a word costs time
in its length and no piece is ever built. A word that can't be cut into pieces counts as one unknown.

Null or empty text: no words, no tokens. Null ids and repeated rows: a row each. Empty table: no rows. Extra columns are
ignored. Words of any length are counted whole. The mark ## of a continuing piece is notation: a word that begins with these
characters is cut by them like any other.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmin.llm import common
from gridmin.session import map_arrow

COUNTS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("n_unknown", T.LongType())])


def vocabulary(path: str | None = None) -> list[str]:
    """Word pieces from a public sentencepiece file: its word-start mark becomes none, all other pieces continue a word (##)."""
    import sentencepiece

    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    out = []
    for i in range(model.get_piece_size()):
        if model.is_control(i) or model.is_unknown(i) or model.is_byte(i):
            continue
        piece = model.id_to_piece(i)
        text = piece.lstrip("▁")
        if text and "▁" not in text:
            out.append(text if piece != text else f"##{text}")
    return sorted(set(out))


class Automaton:
    START, CONTINUE, NONE = 0, 1, -1

    def __init__(self, pieces: Iterable[str]):
        self.go: dict[tuple[int, str], int] = {}
        self.fail: list[int] = [self.NONE, self.NONE]
        self.pops: list[int] = [0, 0]
        ends, children = set(), [[], []]
        for piece in pieces:
            more = piece.startswith("##") and len(piece) > 2
            at = self.CONTINUE if more else self.START
            for c in piece[2:] if more else piece:
                to = self.go.get((at, c))
                if to is None:
                    to = self.go[at, c] = len(self.fail)
                    self.fail.append(self.NONE)
                    self.pops.append(0)
                    children.append([])
                    children[at].append((c, to))
                at = to
            ends.add(at)
        queue = deque([self.START, self.CONTINUE])
        while queue:
            parent = queue.popleft()
            for c, node in children[parent]:
                if node in ends:
                    self.fail[node], self.pops[node] = self.CONTINUE, 1
                else:
                    at, popped = self.fail[parent], self.pops[parent]
                    while at != self.NONE and (at, c) not in self.go:
                        popped, at = popped + self.pops[at], self.fail[at]
                    if at != self.NONE:
                        self.fail[node], self.pops[node] = self.go[at, c], popped
                queue.append(node)

    def count(self, word: str) -> int:
        """Pieces of the greedy longest-match cut; 0 if there is none."""
        go, fail, pops = self.go, self.fail, self.pops
        at, n = self.START, 0
        for c in word:
            while (to := go.get((at, c))) is None:
                if fail[at] == self.NONE:
                    return 0
                n += pops[at]
                at = fail[at]
            at = to
        while at != self.CONTINUE:
            if fail[at] == self.NONE:
                return 0
            n += pops[at]
            at = fail[at]
        return n


_BUILT: dict[int, Automaton] = {}


def token_counts(docs: DataFrame, pieces: list[str] | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_words, n_tokens, n_unknown): unknown words count as one token each. The vocabulary is sent out; its size is fixed."""
    spark: SparkSession = docs.sparkSession
    shared = spark.sparkContext.broadcast(pieces if pieces is not None else vocabulary())
    own = common.own_columns(docs, doc_id=doc_id, text=text).withColumn("doc_id", F.col("doc_id").cast("long"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key = hash(tuple(shared.value))
        if key not in _BUILT:
            _BUILT[key] = Automaton(shared.value)
        count, out = _BUILT[key].count, common.arrow_schema(COUNTS)
        look = common.WordMemo(lambda w: count(w.decode()), 1_000_000).__getitem__
        for b in batches:
            rows = []
            for t in common.texts_of(b, "text"):
                found = list(map(look, t.split()))
                unknown = found.count(0)
                rows.append((len(found), sum(found) + unknown, unknown))
            n, tokens, unknown = zip(*rows, strict=True) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([common.column_of(b, "doc_id"), *[pa.array(x, pa.int64()) for x in (n, tokens, unknown)]], schema=out)

    return map_arrow(own, run, COUNTS)
