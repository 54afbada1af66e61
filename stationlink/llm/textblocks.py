"""Whole Arrow batches of texts as arrays of words and hashes.

Texts of a batch are handled in blocks of about ``max_bytes``, so that memory stays bounded however many rows a batch
has; one longer text is a block of its own. All hashes are fixed functions of the words, the same in every process.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_STEP = U(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finisher (the public MurmurHash3 one)."""
    x = x.astype(U, copy=True)
    x ^= x >> U(33)
    x *= U(0xFF51AFD7ED558CCD)
    x ^= x >> U(33)
    x *= U(0xC4CEB9FE1A85EC53)
    x ^= x >> U(33)
    return x


_BYTE = mix(np.arange(256, dtype=U) + U(0xA24BAED4963EE407))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32

#: Bytes of words: all but space and \t..\r; all but ASCII punctuation, capitals and control codes (after lower-casing).
SPACED = np.ones(256, bool)
SPACED[[32, *range(9, 14)]] = False
ALNUM = np.ones(256, bool)
ALNUM[:128] = [chr(c).isdigit() or chr(c).isalpha() for c in range(128)]


@lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    def of(base: int) -> np.ndarray:
        out = np.full(n, base, U)
        out[0] = 1
        return np.multiply.accumulate(out)

    return of(_BASE), of(_INVERSE)


@dataclass
class Words:
    """Words of a block: first[d]..first[d+1] are those of its text d; byte places count from the block's start."""

    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    hash: np.ndarray
    data: np.ndarray
    offset: np.ndarray
    total: np.ndarray
    inverse: np.ndarray

    def beginnings(self, which: np.ndarray, n: int) -> np.ndarray:
        """Hashes of the first n bytes of the words ``which``, each longer than that."""
        at = self.start[which]
        return mix(((self.total[at + n] - self.total[at]) * self.inverse[at]) ^ U(n))

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def raw(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, n + 1 offsets) of a string array; null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    offset = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2], np.uint8) if texts.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data, offset


@lru_cache(maxsize=1)
def _lean() -> None:
    """Let this process give freed memory back: large arrays are mapped by themselves, Arrow takes its memory from the system."""
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        ctypes.CDLL(None).mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD of glibc
    except (OSError, AttributeError):
        pass  # another C library: it keeps its own ways


def blocks(texts: pa.Array, max_bytes: int = 1 << 18) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from row, to row, bytes, offsets within them)."""
    _lean()
    if not len(texts):
        return
    data, offset = raw(texts)
    lo = 0
    while lo < len(offset) - 1:
        hi = max(lo + 1, int(np.searchsorted(offset, offset[lo] + max_bytes, "right")) - 1)
        hi = min(hi, lo + 4096, len(offset) - 1)
        yield lo, hi, data[offset[lo] : offset[hi]], offset[lo : hi + 1] - offset[lo]
        lo = hi


def words(data: np.ndarray, offset: np.ndarray, kind: np.ndarray = SPACED, lower: bool = True) -> Words:
    """Words are runs of bytes of ``kind`` inside one text; A-Z count as a-z if ``lower``."""
    n = len(data)
    small = _LOWER[data] if lower else data
    inside = np.zeros(n + 2, bool)
    inside[1:-1] = kind[small]
    edge = np.zeros(n + 1, bool)
    edge[offset] = True
    at = inside[1:] & (~inside[:-1] | edge)
    to = inside[:-1] & (~inside[1:] | edge)
    start, end = np.flatnonzero(at), np.flatnonzero(to)
    size = 1 << max(18, (n + 1).bit_length())
    power, inverse = _powers(size)
    total = np.zeros(n + 1, U)
    np.cumsum(_BYTE[small] * power[:n], out=total[1:])
    value = mix((total[end] - total[start]) * inverse[start])
    return Words(start, end, np.searchsorted(start, offset), value, small, offset, total, inverse)


def ngrams(value: np.ndarray, k: int) -> np.ndarray:
    """Hash of each k consecutive words, at its first word; runs that leave the text are for the caller to mask."""
    n = len(value) - k + 1
    if n <= 0:
        return np.zeros(0, U)
    out = value[:n].copy()
    for j in range(1, k):
        out = out * _STEP + value[j : n + j]
    return mix(out + U(k))


def ngram_counts(first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(places of the k-grams that lie in one text, number of them in each text)."""
    count = np.maximum(np.diff(first) - k + 1, 0)
    place = np.repeat(first[:-1] - np.r_[0, np.cumsum(count)[:-1]], count) + np.arange(count.sum())
    return place, count


def word_hash(word: str, lower: bool = True) -> int:
    """The hash ``words`` gives to one word."""
    got = np.frombuffer(word.encode(), np.uint8)
    return int(words(got, np.array([0, len(got)]), np.ones(256, bool), lower).hash[0])
