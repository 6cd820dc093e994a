"""Ids of whole texts from a public tokenizer file, with a cache of the texts' white-space-separated chunks.

The tokenizer used here drops white space, and its normaliser, splitter and merges never look across an ASCII blank, so
the ids of a text are the ids of its chunks in a row. Chunks unknown so far go through the tokenizers library
together; everything else is a dictionary look-up. ``tests/llm`` compares this with encoding whole texts.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
from collections.abc import Iterable, Iterator
from itertools import compress, islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import SparkSession

from gridmin.llm import common

END_ID = 2
#: Bytes of text that are split at once.
RUN = 16 << 20
_TAIL = ".,;:!?*#$%&|"
_BLANK = re.compile(rb"[ \t\n\x0b\x0c\r]")
_ENCODERS: dict[str, "ChunkEncoder"] = {}


def tokenizer_json(spark: SparkSession, path: str | None = None) -> Broadcast:
    """The tokenizer file, read on the driver and sent out (its size is that of a vocabulary, not of the data)."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, encoding="utf-8") as f:
        return spark.sparkContext.broadcast(f.read())


def listed(column: pa.Array) -> list[bytes]:
    """The texts of a column without nulls as bytes."""
    return column.cast(pa.large_binary()).to_numpy(zero_copy_only=False).tolist()


def runs(text: bytes, size: int) -> Iterator[bytes]:
    """The text in runs of at least ``size`` bytes (but the last) that end before an ASCII blank."""
    at = 0
    while at < len(text):
        end = _BLANK.search(text, at + size)
        upto = end.start() if end else len(text)
        yield text[at:upto]
        at = upto


class ChunkEncoder:
    """bytes of a text -> its ids as bytes of numpy type ``width``: unsigned 16-bit where the vocabulary allows, else 32-bit."""

    def __init__(self, json_text: str, limit: int = 600_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(json_text)
        self.limit = limit
        self.words = self._word_tokenizer(json_text)
        self.known: dict[bytes, bytes] = {}
        self.tails = _Tails(self)
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.size = max(vocab.values()) + 1
        self.width, self.bytes = ("<u2", 2) if self.size <= 1 << 16 else ("<u4", 4)
        self.ends = np.zeros(self.size, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True

    @classmethod
    def of(cls, shared: Broadcast) -> "ChunkEncoder":
        """One encoder a worker process, kept between tasks."""
        text = shared.value
        key = f"{len(text)}:{hash(text)}"
        if key not in _ENCODERS:
            _ENCODERS[key] = cls(text)
        return _ENCODERS[key]

    def encode(self, texts: Iterable[bytes], step: int = 2048) -> Iterable[bytes]:
        """Ids of each text, in order; ``step`` texts are taken at a time."""
        texts = iter(texts)
        while part := list(islice(texts, step)):
            yield from self.encode_column(pa.array(part, pa.large_binary()).cast(pa.large_string()))

    def encode_column(self, column: pa.Array, rows: int = 8192, size: int = RUN) -> Iterator[bytes]:
        """Ids of each text of a column; null counts as empty. Up to ``rows`` texts or ``size`` bytes are split, and their different
        chunks looked up, together. A longer text goes in runs of about ``size`` bytes that end at a blank."""
        column = pc.fill_null(column.cast(pa.large_string()), "")
        ends = np.cumsum(pc.binary_length(column).to_numpy())
        at = 0
        while at < len(column):
            before = int(ends[at - 1]) if at else 0
            upto = min(at + rows, int(np.searchsorted(ends, before + size, "right")))
            if upto > at:
                yield from self._encode_part(column.slice(at, upto - at))
                at = upto
            else:
                yield b"".join(ids for run in runs(column[at].as_buffer().to_pybytes(), size) for ids in self._encode_part(pa.array([run], pa.large_binary()).cast(pa.large_string())))
                at += 1

    def _encode_part(self, texts: pa.Array) -> Iterator[bytes]:
        chunks = pc.ascii_split_whitespace(texts)
        coded = chunks.flatten().dictionary_encode()
        names = listed(coded.dictionary)
        if len(self.known) > self.limit:
            self.known = {}
        ids = list(map(self.known.get, names))
        if None in ids:
            at = [k for k, i in enumerate(ids) if i is None]
            self._learn([names[k] for k in at], coded.dictionary.take(pa.array(at, pa.int64())))
            ids = list(map(self.known.__getitem__, names))
        size = np.fromiter(map(len, ids), np.int64, len(ids)) // self.bytes
        first, flat = np.cumsum(size) - size, np.frombuffer(b"".join(ids), self.width)
        codes = coded.indices.to_numpy()
        n = size[codes]
        ends = np.concatenate([[0], np.cumsum(n)])
        words = chunks.offsets.to_numpy()
        stop = ends[words - words[0]]
        for low in range(0, len(texts), 256):  # texts whose ids are gathered at once
            w0, w1 = words[low] - words[0], words[min(low + 256, len(texts))] - words[0]
            m = n[w0:w1]
            take = np.repeat(first[codes[w0:w1]] - (ends[w0:w1] - ends[w0]), m) + np.arange(m.sum())
            raw, base = flat[take].tobytes(), ends[w0]
            for k in range(low, min(low + 256, len(texts))):
                yield raw[(stop[k] - base) * self.bytes:(stop[k + 1] - base) * self.bytes]

    def wide(self, ids: bytes) -> bytes:
        """The same ids, little-endian unsigned 32-bit."""
        return np.frombuffer(ids, self.width).astype("<u4").tobytes()

    def _word_tokenizer(self, json_text: str):
        """The same model behind a splitter that only cuts lines, for words known to be letters in normal form and lower case.
        None if it doesn't agree with the full tokenizer on the vocabulary's own words."""
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        spec = json.loads(json_text)
        if spec["model"].get("end_of_word_suffix") != "</w>":
            return None
        short = Tokenizer.from_str(json_text)
        short.normalizer = normalizers.Sequence([])
        short.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.CharDelimiterSplit("\n"), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        probe = [w for w in (t.removesuffix("</w>") for t in spec["model"]["vocab"]) if w.isascii() and w.isalpha() and w.islower()][::8]
        probe += ["\u00fcber", "\u00e9t\u00e9", "ni\u00f1o", "\u4e2d\u6587", "\u043c\u0438\u0440"]
        both = [t.encode_batch_fast(["\n".join(probe)], add_special_tokens=False)[0].ids for t in (short, self.tokenizer)]
        return short if both[0] == both[1] else None

    def _learn(self, new: list[bytes], texts: pa.Array) -> None:
        """Chunks of letters and a tail of plain signs are put together from both; all others are encoded alone."""
        known, tails = self.known, self.tails
        heads = pc.utf8_rtrim(texts, characters=_TAIL)
        letters = pc.utf8_is_alpha(heads).to_numpy(zero_copy_only=False)
        stems = heads.filter(pa.array(letters)).dictionary_encode()
        names, chunks = listed(stems.dictionary), list(compress(new, letters))
        ids = list(map(known.get, names))
        fresh = [k for k, i in enumerate(ids) if i is None]
        for at in range(0, len(fresh), 2048):
            part = fresh[at:at + 2048]
            for k, i in zip(part, self._joined([names[k] for k in part])):
                ids[k] = i
        known.update(zip(names, ids))
        size = pc.binary_length(heads).to_numpy()[letters]
        whole = list(map(ids.__getitem__, stems.indices.to_pylist()))
        signs = [c[n:] for c, n in zip(chunks, size.tolist())]
        known.update(zip(chunks, map(bytes.__add__, whole, map(tails.__getitem__, signs))))
        odd = list(compress(new, ~letters))
        known.update(zip(odd, self._alone([c.decode() for c in odd])))

    def _joined(self, words: list[bytes]) -> list[bytes]:
        """Words of letters, a line each. They end as often as there are lines; if not, each is encoded alone. Texts not in
        normal form, or whose lower case depends on context or length, go through the full tokenizer."""
        text = b"\n".join(words).decode()
        lower = text.lower()
        plain = self.words is not None and unicodedata.is_normalized("NFC", text) and len(lower) == len(text) and "\u03a3" not in text and "\u0130" not in text
        ids = np.array((self.words if plain else self.tokenizer).encode_batch_fast([lower if plain else text], add_special_tokens=False)[0].ids, self.width)
        ends = np.flatnonzero(self.ends[ids]) + 1
        if len(ends) != len(words):
            return self._alone([w.decode() for w in words])
        raw, cuts = ids.tobytes(), [0, *(ends * self.bytes).tolist()]
        return [raw[a:b] for a, b in zip(cuts, cuts[1:])]

    def _alone(self, texts: list[str]) -> list[bytes]:
        if not texts:
            return []
        return [np.array(e.ids, self.width).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]


def _forget() -> None:
    for encoder in _ENCODERS.values():
        encoder.known = {}


common._CACHES.append(_forget)


class _Tails(dict):
    """Ids of runs of plain signs."""

    def __init__(self, encoder: ChunkEncoder):
        super().__init__()
        self.encoder = encoder
        self[b""] = b""

    def __missing__(self, tail: bytes) -> bytes:
        if len(self) > 100_000:
            self.clear()
            self[b""] = b""
        ids = self[tail] = self.encoder._alone([tail.decode()])[0]
        return ids
