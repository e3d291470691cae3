"""Vectorised words and hashes over Arrow columns of UTF-8 text.

A batch of documents is one flat byte buffer with offsets.  Word borders, word hashes and n-gram hashes are array
operations over that buffer, so no Python loop runs per word.  Words are runs of bytes that are not separators;
all separators used here are ASCII, so bytes of multi-byte characters never split a word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Text bytes handled at once; a longer single document is handled alone.
SLICE_BYTES = 1 << 20

BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
BASE_INVERSE = np.uint64(pow(int(BASE), -1, 1 << 64))

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Separators of `[^\x20\x09-\x0D]+` words.
SPACES = np.zeros(256, dtype=bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True

#: Separators of `[^\x00-\x2F\x3A-\x60\x7B-\x7F]+` words (after lower-casing).
NOT_ALNUM = np.zeros(256, dtype=bool)
NOT_ALNUM[[*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]] = True

_powers = np.ones(1, dtype=np.uint64)
_inverses = np.ones(1, dtype=np.uint64)


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of BASE and of its inverse modulo 2**64, at least n of each."""
    global _powers, _inverses
    if len(_powers) < n:
        size = max(n, 1 << 16)
        with np.errstate(over="ignore"):
            _powers = np.cumprod(np.r_[np.uint64(1), np.full(size - 1, BASE, dtype=np.uint64)], dtype=np.uint64)
            _inverses = np.cumprod(np.r_[np.uint64(1), np.full(size - 1, BASE_INVERSE, dtype=np.uint64)], dtype=np.uint64)
    return _powers, _inverses


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over all 64 output bits."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(33)
        x *= np.uint64(0xFF51AFD7ED558CCD)
        x ^= x >> np.uint64(33)
        x *= np.uint64(0xC4CEB9FE1A85EC53)
        x ^= x >> np.uint64(33)
    return x


class SpanHasher:
    """Hash of any span of one buffer in constant time (polynomial prefix hash)."""

    def __init__(self, data: np.ndarray):
        powers, self._inverse = _power_tables(len(data) + 1)
        with np.errstate(over="ignore"):
            self._prefix = np.empty(len(data) + 1, dtype=np.uint64)
            self._prefix[0] = 0
            np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers[: len(data)], dtype=np.uint64, out=self._prefix[1:])

    def spans(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix64((self._prefix[ends] - self._prefix[starts]) * self._inverse[starts])


def text_column(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Flat bytes and the n + 1 offsets of a text or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    kind = np.int64 if wide else np.int32
    at = np.frombuffer(offsets, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    flat = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    return flat[at[0] : at[-1]], at - at[0]


def slices(batches, column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut so that each holds about `limit` text bytes at most (or one longer document)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        _, at = text_column(batch.column(batch.schema.get_field_index(column)))
        first = 0
        while first < batch.num_rows:
            last = max(int(np.searchsorted(at, at[first] + limit, side="right")) - 1, first + 1)
            yield batch.slice(first, last - first)
            first = last


class Words:
    """Words of a batch: lower-cased bytes, word spans, and each document's range of words."""

    def __init__(self, column: pa.Array, separators: np.ndarray):
        data, self.offsets = text_column(column)
        self.data = LOWER[data]
        self.n_docs = len(self.offsets) - 1
        inside = ~separators[self.data]
        n = len(inside)
        cut = np.zeros(n + 1, dtype=bool)
        cut[self.offsets] = True
        before = np.empty(n, dtype=bool)
        before[:1] = False
        before[1:] = inside[:-1]
        after = np.empty(n, dtype=bool)
        after[-1:] = False
        after[:-1] = inside[1:]
        self.starts = np.flatnonzero(inside & (~before | cut[:-1]))
        self.ends = np.flatnonzero(inside & (~after | cut[1:])) + 1
        #: Document i has the words first[i] .. first[i + 1] - 1.
        self.first = np.searchsorted(self.starts, self.offsets)
        self.counts = np.diff(self.first)

    def hashes(self) -> np.ndarray:
        return SpanHasher(self.data).spans(self.starts, self.ends)

    def doc_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(self.n_docs), self.counts)


def pair_hash(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Order-sensitive hash of two hash arrays."""
    with np.errstate(over="ignore"):
        return mix64(left * np.uint64(0xD6E8FEB86659FD93) + (right ^ np.uint64(0xA5A5A5A5A5A5A5A5)))


def gram_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of k consecutive word hashes (len - k + 1 of them)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = words[:n]
    for j in range(1, k):
        out = pair_hash(out, words[j : j + n])
    return out
