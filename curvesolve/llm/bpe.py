"""Byte-pair encoding and decoding with a public vocabulary file.

Merging uses a segment tree over the ranks of adjacent pairs: each leaf holds the pair that begins at
its position, each inner node the smaller of its children, so the root is the leftmost pair of
lowest rank. A merge changes three leaves, each updated along one path, until the root is empty.

Defined results: a null text is encoded as an empty one; strings of the special tokens in a text
become their ids, as in the library; nothing is truncated; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import os
import unicodedata
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NONE = 1 << 62
#: Children of a node of the segment tree.
FAN = 32
#: Chunks kept in a worker's memory, and characters of the longest one kept; beyond that the memory is emptied and filled anew.
CACHE, KEPT = 600_000, 64


def byte_chars() -> list[str]:
    """The printable stand-in of each byte, as byte-level vocabularies write it."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    shift = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in set(plain))}
    return [chr(shift.get(b, b)) for b in range(256)]


def merge(ids: list[int], pairs: dict[int, tuple[int, int]]) -> list[int]:
    """Apply merges in order of rank, leftmost first, until no adjacent pair is mergeable.

    ``pairs``: {first id << 20 | second id: (rank, id of the merged symbol)}. Each node of the tree
    has up to FAN children, so that most words need the root alone.
    """
    n = len(ids)
    if n < 2:
        return ids
    get, made = pairs.get, [0] * n
    leaves = [NONE] * (n - 1)
    for i in range(n - 1):
        if (r := get(ids[i] << 20 | ids[i + 1])) is not None:
            leaves[i], made[i] = r[0] << 32 | i, r[1]
    levels = [leaves]
    while len(levels[-1]) > FAN:
        low = levels[-1]
        levels.append([min(low[i:i + FAN]) for i in range(0, len(low), FAN)])
    top, deep = levels[-1], len(levels) > 1
    out = list(ids)
    after, before = [*range(1, n + 1)], [*range(-1, n - 1)]
    while (best := min(top)) != NONE:
        i = best & 0xFFFFFFFF
        j = after[i]
        k, h = after[j], before[i]
        out[i], out[j], after[i] = made[i], -1, k
        if j < n - 1:
            leaves[j] = NONE
        leaves[i] = NONE
        if k < n:
            before[k] = i
            if (r := get(out[i] << 20 | out[k])) is not None:
                made[i], leaves[i] = r[1], r[0] << 32 | i
        if h >= 0:
            if (r := get(out[h] << 20 | out[i])) is None:
                leaves[h] = NONE
            else:
                made[h], leaves[h] = r[1], r[0] << 32 | h
        if deep:
            for at in {x // FAN for x in (h, i, j) if 0 <= x < n - 1}:
                for low, high in zip(levels, levels[1:]):
                    high[at] = min(low[at * FAN:at * FAN + FAN])
                    at //= FAN
    return [s for s in out if s >= 0]


class Codec:
    """Encodes and decodes as the library does with the same file."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        model = spec["model"]
        self.ids: dict[str, int] = dict(model["vocab"])
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in {**self.ids, **self.special}.items()}
        merges = [p if isinstance(p, list) else p.split(" ") for p in model["merges"]]
        self.pairs = {self.ids[a] << 20 | self.ids[b]: (r, self.ids[a + b]) for r, (a, b) in reversed([*enumerate(merges)])}
        self.end = model["end_of_word_suffix"] or ""
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words = regex.compile(split["pattern"]["Regex"].replace(r"\s", r"\p{White_Space}")).findall
        self.stops = regex.compile("|".join(map(regex.escape, self.special)) or "(?!)")
        #: What every special token begins with; texts without it hold none.
        self.mark = os.path.commonprefix([*self.special])
        steps = [n["type"] for n in (spec["normalizer"] or {"normalizers": []})["normalizers"]]
        if steps not in (["NFC", "Replace", "Lowercase"], ["NFC", "Lowercase"]):
            raise ValueError(f"a vocabulary with the normal form {steps} is not supported")
        self.odd = regex.compile("[\x1c-\x1f]").search
        self.chars = byte_chars()
        self.cache: dict[str, bytes] = {}

    def word(self, word: str) -> bytes:
        """A word's ids as little-endian 32-bit integers."""
        symbols = [self.chars[b] for b in word.encode()]
        symbols[-1] += self.end
        return array("I", merge([self.ids[s] for s in symbols], self.pairs)).tobytes()

    def chunk(self, chunk: str) -> bytes:
        """The same for a stretch without white space, kept in memory while there is room."""
        got = b"".join([self.word(w) for w in self.words(chunk)])
        if len(chunk) <= KEPT:
            if len(self.cache) >= CACHE:
                self.cache.clear()
            self.cache[chunk] = got
        return got

    @staticmethod
    def normal(text: str) -> str:
        """NFC, then lower case code point by code point; white space is dropped later by the split."""
        text = unicodedata.normalize("NFC", text)
        return text.lower() if "Σ" not in text else "".join(c.lower() for c in text)

    def encode(self, text: str | None) -> bytes:
        """The ids as little-endian 32-bit integers."""
        text, at, parts = text or "", 0, []
        get, chunk = self.cache.get, self.chunk
        for m in [*self.stops.finditer(text), None] if self.special and self.mark in text else [None]:
            piece = text[at:m.start()] if m else text[at:]
            # No word crosses white space; control characters that only Python counts as such need the full pattern.
            piece = self.normal(piece)
            parts += [get(w) or chunk(w) for w in (piece.split() if not self.odd(piece) else self.words(piece))]
            if m:
                parts.append(self.special[m[0]].to_bytes(4, "little"))
                at = m.end()
        return b"".join(parts)

    def decode(self, ids: Iterable[int]) -> str:
        """Tokens of known ids, joined by blanks, as a tokenizer without decoder does; special ones stay."""
        known = map(self.tokens.get, ids)
        return " ".join([t for t in known if t is not None])


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    """One codec per worker process and file."""
    return Codec(path)


def encode_documents(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids array<int>) of every document. ``path`` must exist on every executor."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path)
        for b in batches:
            ids = [memoryview(enc.encode(t.as_py())).cast("I").tolist() for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])
    return _source(docs).mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of rows (doc_id, ids)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path)
        for b in batches:
            text = [enc.decode(x.as_py() or []) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(text, pa.string())], names=["doc_id", "text"])
    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def digest_documents(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): an encoding and its decoding in one pass."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path)
        for b in batches:
            rows = []
            for t in b.column(1):
                ids = enc.encode(t.as_py())
                text = enc.decode(memoryview(ids).cast("I")).encode("utf-8", "surrogatepass")
                rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(text).hexdigest()))
            n, i, d = zip(*rows) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(i, pa.string()), pa.array(d, pa.string())],
                                             names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
    return _source(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
