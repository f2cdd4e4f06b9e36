"""Vectorised text features: code points, words and rolling hashes as numpy arrays.

Texts are handled in blocks of about a quarter of a million characters, so memory is bounded by the
block or by the longest single text, never by the size of an Arrow batch.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

BLOCK_CHARS = 1 << 18
#: Rows of an Arrow batch that are turned into Python objects at a time.
BATCH_ROWS = 512
_BASE = 0x9E3779B97F4A7C15 | 1
_powers: dict[str, np.ndarray] = {}


def blocks(texts: list[str], limit: int = BLOCK_CHARS) -> Iterator[tuple[int, int]]:
    """Ranges of texts whose lengths add up to about ``limit``; a longer text stands alone."""
    at, total = 0, 0
    for i, t in enumerate(texts):
        if i > at and total + len(t) > limit:
            yield at, i
            at, total = i, 0
        total += len(t) + 1
    if at < len(texts):
        yield at, len(texts)


def pieces(batches: Iterator[pa.RecordBatch], rows: int = BATCH_ROWS) -> Iterator[pa.RecordBatch]:
    """The batches in slices without copies, so that only a slice is ever held as Python objects."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
    release()


def release() -> None:
    """Give freed memory back to the system at the end of a task: idle workers stay alive beside others."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # no such function in this C library


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2^64."""
    if "p" not in _powers or len(_powers["p"]) < n:
        size = max(n, 2 * BLOCK_CHARS)
        for name, base in (("p", _BASE), ("q", pow(_BASE, -1, 1 << 64))):
            row = np.full(size, base, np.uint64)
            row[0] = 1
            _powers[name] = np.cumprod(row, dtype=np.uint64)
    return _powers["p"][:n], _powers["q"][:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (splitmix64)."""
    x = x + np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Block:
    """Several texts end to end, each followed by one blank; words are runs of non-blanks."""

    def __init__(self, texts: list[str], word_chars: np.ndarray | None = None):
        joined = " ".join(texts) + " "
        # surrogates cannot come out of Arrow strings; "surrogatepass" only keeps tests simple
        self.codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        ends = np.cumsum([len(t) + 1 for t in texts])
        self.starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
        self.ends = ends.astype(np.int64)
        self.n = len(texts)
        if word_chars is None:
            c = self.codes
            self.blank = (c == 32) | ((c >= 9) & (c <= 13))
        else:
            self.blank = ~word_chars[self.codes]
            self.blank[self.ends - 1] = True
        edge = np.diff(np.concatenate([[True], self.blank]).astype(np.int8))
        self.w_start = np.flatnonzero(edge == -1)
        self.w_end = np.flatnonzero(edge == 1)
        if len(self.w_end) < len(self.w_start):
            self.w_end = np.append(self.w_end, len(self.codes))
        self.w_doc = np.searchsorted(self.ends, self.w_start, side="right")

    def prefix_sums(self) -> np.ndarray:
        p, _ = powers(len(self.codes))
        out = np.zeros(len(self.codes) + 1, np.uint64)
        np.cumsum((self.codes.astype(np.uint64) + np.uint64(1)) * p, out=out[1:])
        return out

    def spans_hash(self, sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of the characters in [start, end), whatever their place."""
        _, q = powers(len(self.codes) + 1)
        return mix((sums[end] - sums[start]) * q[start])

    def word_hashes(self) -> np.ndarray:
        return self.spans_hash(self.prefix_sums(), self.w_start, self.w_end)


def segment_sums(values: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """Sums of values by owner, in double precision."""
    return np.bincount(owner, weights=values, minlength=n)
