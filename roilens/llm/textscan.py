"""Whole-batch text scanning over Arrow buffers with numpy: words, lines, hashes and counts.

A slice of documents becomes one byte array in which every text is followed by a line feed, so no
word or line crosses two documents.  Words are maximal runs of bytes other than space and 0x09-0x0D;
UTF-8 never uses those bytes inside a character, so the byte view and the character view agree.
Hashes are 64-bit polynomials taken from one prefix sum, which makes the hash of any byte range two
lookups; all of it is vectorised, nothing runs per word or per character in Python.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 1 << 20
_ENDED = pa.scalar("\n", pa.large_string()), pa.scalar("", pa.large_string())
_RNG = np.random.default_rng(20240101)
_TABLE = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the hash base and of its inverse, modulo 2**64."""
    if len(_powers[0]) < n:
        size = max(n + n // 4, 1 << 20)
        for k, b in enumerate((_BASE, _INVERSE)):
            p = np.full(size, b, np.uint64)
            p[0] = 1
            _powers[k] = np.multiply.accumulate(p)
    return _powers[0][:n], _powers[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A finaliser that spreads all input bits over all output bits."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def tidy(rows: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``rows`` for ``mapInArrow``, after whose last batch the worker gives freed memory back to the system.

    Workers serve later stages too, so what their allocators keep would add up on an executor.
    """

    def all_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from rows(batches)
        finally:
            _powers[:] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]  # made again in some milliseconds
            gc.collect()
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
            if trim:
                trim(0)

    return all_rows


def slices(texts: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes each; a longer text stands alone."""
    lengths = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    start = size = 0
    for i, n in enumerate(lengths.tolist()):
        if size and size + n > limit:
            yield start, i
            start, size = i, 0
        size += n
    if start < len(lengths):
        yield start, len(lengths)


class Scan:
    """Bytes, words and lines of some documents; null texts count as empty."""

    def __init__(self, texts: pa.Array):
        ended = pc.binary_join_element_wise(pc.fill_null(texts.cast(pa.large_string()), ""), *_ENDED)
        offsets = np.frombuffer(ended.buffers()[1], np.int64, len(ended) + 1, ended.offset * 8)
        data = np.frombuffer(ended.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
        self.n = len(ended)
        self.offsets = offsets - offsets[0]
        self.data = data
        space = SPACE[data]
        edge = np.flatnonzero(space[1:] != space[:-1]) + 1
        if len(data) and not space[0]:
            edge = np.concatenate(([0], edge))
        self.starts, self.ends = edge[0::2], edge[1::2]
        self.word_doc = np.searchsorted(self.offsets, self.starts, "right") - 1
        self._prefix: dict[str, np.ndarray] = {}

    def per_doc(self, where: np.ndarray, weights: np.ndarray | None = None) -> np.ndarray:
        """Counts (or sums of weights) by document of byte positions."""
        return np.bincount(np.searchsorted(self.offsets, where, "right") - 1, weights, self.n)

    def byte_counts(self, classes: np.ndarray, n_classes: int) -> np.ndarray:
        """documents x classes: how many bytes of each class a text has, its end mark left out."""
        out = np.empty((self.n, n_classes), np.int64)
        of = classes[self.data]
        for k in range(n_classes):
            seen = np.concatenate(([0], np.cumsum(of == k)))
            out[:, k] = seen[self.offsets[1:] - 1] - seen[self.offsets[:-1]]
        return out

    def hashes(self, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
        """64-bit hashes of byte ranges; equal bytes give equal hashes wherever they stand."""
        key = "lower" if lower else "raw"
        power, inverse = powers(len(self.data) + 1)
        if key not in self._prefix:
            values = _TABLE[LOWER] if lower else _TABLE
            p = np.zeros(len(self.data) + 1, np.uint64)
            np.cumsum(values[self.data] * power[:-1], out=p[1:])
            self._prefix[key] = p
        p = self._prefix[key]
        return mix((p[ends] - p[starts]) * inverse[starts] + (ends - starts).astype(np.uint64))

    def word_hashes(self, lower: bool = False) -> np.ndarray:
        return self.hashes(self.starts, self.ends, lower)

    def words_per_doc(self) -> np.ndarray:
        return np.bincount(self.word_doc, minlength=self.n)

    def windows(self, word_hash: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """First word's index and hash of every run of k words inside one document."""
        n = len(word_hash) - k + 1
        if n <= 0:
            return np.empty(0, np.int64), np.empty(0, np.uint64)
        at = np.flatnonzero(self.word_doc[:n] == self.word_doc[k - 1 :])
        h = np.zeros(len(at), np.uint64)
        for j in range(k):
            h = h * _BASE + word_hash[at + j]
        return at, mix(h)

    def lines(self) -> tuple[np.ndarray, np.ndarray]:
        """Byte ranges of lines that hold a word (split at line feeds only)."""
        ends = np.flatnonzero(self.data == 10)
        starts = np.concatenate(([0], ends[:-1] + 1))
        has = np.searchsorted(self.starts, ends, "left") > np.searchsorted(self.starts, starts, "left")
        return starts[has], ends[has]


def repeated(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For every key: whether an equal one stands earlier, and whether it has any equal at all."""
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    later, any_ = np.zeros(len(keys), bool), np.zeros(len(keys), bool)
    later[order[1:]] = same
    any_[order[1:]] |= same
    any_[order[:-1]] |= same
    return later, any_


def keyed(hashes: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """Hashes that differ between documents."""
    return mix(hashes ^ mix(docs.astype(np.uint64) + np.uint64(0x632BE59BD9B4E019)))
