"""Vectorised byte kernels over Arrow text columns: words, shingles, hashes.

Words are runs of bytes other than the ASCII blanks 0x20 and 0x09-0x0D.  All
kernels work on pieces of a few megabytes of whole documents, so memory follows
the piece and not the partition.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
GOLD = U64(0x9E3779B97F4A7C15)
PIECE_BYTES = 2 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser, element by element."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def stream(n: int, seed: int) -> np.ndarray:
    """n pseudo-random words from a seed, by rule."""
    with np.errstate(over="ignore"):
        return mix(np.arange(1, n + 1, dtype=U64) * GOLD + U64(seed))


BYTE_CODE = stream(256, 11)
BASE = U64(int(stream(1, 23)[0]) | 1)
BLANK = np.zeros(256, bool)
BLANK[[0x20, *range(0x09, 0x0E)]] = True


def powers(base: U64, n: int) -> np.ndarray:
    p = np.full(max(n, 1), base, dtype=U64)
    p[0] = U64(1)
    return np.multiply.accumulate(p)


def text_bytes(texts: pa.Array, lower: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a string array; nulls are empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if lower:
        texts = pc.utf8_lower(texts)
    _, off, data = texts.buffers()
    n = len(texts)
    offsets = np.frombuffer(off, dtype=np.int64, count=n + 1 + texts.offset)[texts.offset :]
    if n == 0 or data is None:
        return np.zeros(n + 1, np.int64), np.zeros(0, np.uint8)
    raw = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]]
    return offsets - offsets[0], raw


def pieces(texts: pa.Array, limit: int = PIECE_BYTES):
    """Yield (first row, rows) slices of about `limit` bytes of whole documents."""
    sizes = pc.fill_null(pc.binary_length(texts.cast(pa.large_string())), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    start, held = 0, 0
    for i, s in enumerate(sizes):
        if held and held + s > limit:
            yield start, i
            start, held = i, 0
        held += int(s)
    if start < len(sizes):
        yield start, len(sizes)


class Words:
    """Words of a piece: byte start, byte end, document and 64-bit hash of each."""

    __slots__ = ("doc", "end", "first", "hash", "n_docs", "start")

    def __init__(self, offsets: np.ndarray, data: np.ndarray, hashes: bool = True):
        n = self.n_docs = len(offsets) - 1
        word = ~BLANK[data]
        edge = np.zeros(len(data) + 1, bool)
        edge[offsets] = True
        before = np.empty(len(data), bool)
        if len(data):
            before[0] = False
            before[1:] = word[:-1]
            begins = word & (~before | edge[:-1])
            after = np.zeros(len(data), bool)
            after[:-1] = word[1:]
            ends = word & (~after | edge[1:])
            self.start, self.end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
        else:
            self.start = self.end = np.zeros(0, np.int64)
        self.doc = np.searchsorted(offsets, self.start, side="right") - 1
        # documents of no bytes share an offset; the last of them owns the bytes that follow
        self.first = np.searchsorted(self.doc, np.arange(n + 1))
        self.hash = self._hashes(data, word) if hashes else None

    def _hashes(self, data: np.ndarray, word: np.ndarray) -> np.ndarray:
        if not len(self.start):
            return np.zeros(0, U64)
        size = self.end - self.start
        at = np.flatnonzero(word)
        lead = np.cumsum(size) - size
        inside = np.arange(len(at)) - np.repeat(lead, size)
        with np.errstate(over="ignore"):
            terms = BYTE_CODE[data[at]] * powers(BASE, int(size.max()))[inside]
            return mix(np.add.reduceat(terms, lead) + size.astype(U64) * GOLD)


def shingles(words: Words, width: int = 5, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of each run of `width` words; a shorter text gives one shingle of all its words."""
    h, doc = words.hash, words.doc
    n = len(h)
    if n == 0:
        return np.zeros(0, U64), np.zeros(0, np.int64)
    base = powers(U64(int(stream(1, 31 + seed)[0]) | 1), width)
    count = np.diff(words.first)
    left = words.first[1:][doc] - np.arange(n)
    with np.errstate(over="ignore"):
        total = np.zeros(n, U64)
        for t in range(width):
            term = np.zeros(n, U64)
            term[: n - t] = h[t:] * base[t]
            total += np.where(left > t, term, U64(0))
        keep = (left >= width) | ((count[doc] < width) & (np.arange(n) == words.first[:-1][doc]))
        return mix(total[keep] + U64(seed)), doc[keep]


def sequence_keys(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit keys of each document's sequence of words."""
    n = len(words.hash)
    keys = []
    inside = np.arange(n) - words.first[:-1][words.doc] if n else np.zeros(0, np.int64)
    count = np.diff(words.first)
    top = int(count.max()) if len(count) else 0
    for seed in (41, 43):
        out = np.zeros(words.n_docs, U64)
        if n:
            with np.errstate(over="ignore"):
                terms = mix(words.hash + U64(seed)) * powers(U64(int(stream(1, seed)[0]) | 1), top)[inside]
                full = np.flatnonzero(count)
                out[full] = np.add.reduceat(terms, words.first[:-1][full])
        with np.errstate(over="ignore"):
            keys.append(mix(out + count.astype(U64) * GOLD))
    return keys[0], keys[1]
