"""Vectorised byte kernels shared by the text operators: Arrow buffers in, NumPy arrays out, whole texts always.

A `Block` is a run of documents whose bytes lie next to each other in one Arrow buffer.  Words and lines are found
by table look-ups over the bytes and hashed with a polynomial over prefix sums modulo 2**64, finished by an avalanche
mix, so no Python object is made per word.  Hash equality stands for equality of bytes only where the caller says so.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Texts are worked on in blocks of about so many bytes; one longer text is one block.
BLOCK_BYTES = 1 << 19
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_INV = pow(_BASE, -1, 1 << 64)
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]

SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True
NOT_SPACE = ~SPACE
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes of words after lower-casing A-Z: digits, a-z and everything above ASCII.
ALNUM = np.zeros(256, bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[128:] = True


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, grown on demand and kept by the worker."""
    have = len(_powers[0])
    if have < n:
        size = 1 << max(16, (n - 1).bit_length())
        for k, base in enumerate((_BASE, _INV)):
            steps = np.full(size, base & _MASK, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit avalanche (in a new array)."""
    h = h ^ (h >> np.uint64(30))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


class Block:
    """Documents `first .. first + n` of a record batch: `buf` holds their bytes, `off` the n + 1 offsets in it."""

    def __init__(self, buf: np.ndarray, off: np.ndarray, first: int):
        self.buf, self.off, self.first, self.n = buf, off, first, len(off) - 1

    def prefix(self, data: np.ndarray) -> np.ndarray:
        p, _ = powers(len(data) + 1)
        s = np.empty(len(data) + 1, np.uint64)
        s[0] = 0
        np.cumsum(data.astype(np.uint64) * p[: len(data)] + p[: len(data)], out=s[1:])
        return s

    @staticmethod
    def hashes(s: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Hash of each byte range a..b of the data whose prefix sums are s; the length takes part."""
        _, inv = powers(len(s))
        return mix((s[b] - s[a]) * inv[a] + (b - a).astype(np.uint64))

    def words(self, member: np.ndarray, data: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and documents of the maximal runs of member bytes, never across documents."""
        data = self.buf if data is None else data
        if not len(data):
            e = np.zeros(0, np.int64)
            return e, e, e
        inside = member[data]
        edge = np.empty(len(data) + 1, bool)
        edge[0], edge[-1] = inside[0], inside[-1]
        np.not_equal(inside[1:], inside[:-1], out=edge[1:-1])
        inner = self.off[1:-1]
        inner = inner[(inner > 0) & (inner < len(data))]
        joint = np.unique(inner[inside[inner] & inside[inner - 1]]) if len(inner) else inner
        at = np.flatnonzero(edge)
        starts, ends = at[0::2], at[1::2]
        if len(joint):
            starts, ends = np.sort(np.concatenate([starts, joint])), np.sort(np.concatenate([ends, joint]))
        return starts, ends, self.docs_of(starts)

    def docs_of(self, at: np.ndarray) -> np.ndarray:
        """Document of each byte position (positions ascend)."""
        cuts = np.searchsorted(at, self.off[1:], "left")
        return np.repeat(np.arange(self.n), np.diff(np.concatenate([[0], cuts])))

    def lines(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and documents of the lines between newlines; an empty text is one empty line."""
        nl = np.flatnonzero(self.buf == 10)
        own = self.docs_of(nl)
        starts = np.concatenate([self.off[:-1], nl + 1])
        ends = np.concatenate([nl, self.off[1:]])
        docs, docs_e = np.concatenate([np.arange(self.n), own]), np.concatenate([own, np.arange(self.n)])
        return starts[np.lexsort((starts, docs))], ends[np.lexsort((ends, docs_e))], np.sort(docs)

    def text(self, i: int) -> bytes:
        return self.buf[self.off[i] : self.off[i + 1]].tobytes()


def grams(h: np.ndarray, docs: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word windows that lie in one document, and the index of their first words."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    g = h[:n].copy()
    for j in range(1, k):
        g *= np.uint64(_BASE)
        g += h[j : j + n]
    at = np.flatnonzero(docs[:n] == docs[k - 1 :])
    return mix(g[at]), at


def blocks(column: pa.Array, limit: int = BLOCK_BYTES) -> Iterator[Block]:
    """Blocks of a string column of one record batch; null texts are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if len(column) == 0:
        return
    column = column.fill_null("") if column.null_count else column
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    buf = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, "right")) - 1)
        j = min(j, len(column))
        yield Block(buf[off[i] : off[j]], off[i : j + 1] - off[i], i)
        i = j


def per_doc(docs: np.ndarray, n: int, weights: np.ndarray | None = None) -> np.ndarray:
    return np.bincount(docs, weights, minlength=n)


def cover(starts: np.ndarray, length: int, n: int) -> np.ndarray:
    """Which of n items lie in a window of `length` that begins at one of `starts`."""
    d = np.zeros(n + 1, np.int64)
    np.add.at(d, starts, 1)
    np.add.at(d, np.minimum(starts + length, n), -1)
    return np.cumsum(d[:n]) > 0
