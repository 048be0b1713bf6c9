"""Vectorised word splitting and hashing on the UTF-8 buffers of Arrow text columns.

Texts are never turned into Python strings: words, lines and n-grams are byte ranges of a
buffer, hashed with prefix sums modulo 2**64 and mixed. A chunk holds whole documents of
about ``CHUNK`` bytes (one document at least), so memory does not depend on the batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK = 1 << 20
U = np.uint64
_BASE, _WORD = U(0x9E3779B97F4A7C15), U(0xD6E8FEB86659FD93)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n (at least); kept for the next call."""
    have = _powers.get(int(base))
    if have is None or len(have[0]) < n:
        size = n if n > 8 * CHUNK else max(1 << 16, 1 << (n - 1).bit_length())  # grows in powers of two, so small chunks need small tables
        inverse = U(pow(int(base), -1, 1 << 64))
        have = tuple(np.concatenate(([U(1)], np.cumprod(np.full(size - 1, b, U)))) for b in (base, inverse))
        if n <= 8 * CHUNK:
            _powers[int(base)] = have
    return have


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h = h * U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


def ngram_hash(tokens: np.ndarray, n: int, base: np.uint64 = _WORD) -> np.ndarray:
    """Hash of each run of n tokens; entry i is the run that starts at i."""
    if len(tokens) < n:
        return np.empty(0, U)
    up, down = powers(base, len(tokens) + 1)
    total = np.concatenate(([U(0)], np.cumsum(tokens * up[: len(tokens)])))
    return mix((total[n:] - total[:-n]) * down[: len(tokens) - n + 1] + U(n))


def repeated(keys: np.ndarray) -> np.ndarray:
    """Mask of the entries whose value occurs twice or more."""
    if len(keys) < 2:
        return np.zeros(len(keys), bool)
    ordered = np.sort(keys)
    twice = ordered[1:][ordered[1:] == ordered[:-1]]
    if not len(twice):
        return np.zeros(len(keys), bool)
    twice = np.unique(twice)
    at = np.searchsorted(twice, keys)
    at[at == len(twice)] = 0
    return twice[at] == keys


def covered(starts: np.ndarray, length: int | np.ndarray, size: int) -> np.ndarray:
    """Mask over size places of those inside [s, s + length) for some start s."""
    edge = np.zeros(size + 1, np.int64)
    np.add.at(edge, starts, 1) if len(starts) < 64 else edge.__iadd__(np.bincount(starts, minlength=size + 1)[: size + 1])
    ends = starts + length
    np.subtract.at(edge, ends, 1) if len(starts) < 64 else edge.__isub__(np.bincount(ends, minlength=size + 1)[: size + 1])
    return np.cumsum(edge[:-1]) > 0


class Chunk:
    """Some whole documents: their bytes and each one's offsets."""

    def __init__(self, first: int, data: np.ndarray, offsets: np.ndarray, lower: bool = False):
        self.first, self.offsets = first, offsets
        self.data = LOWER[data] if lower else data
        self.docs = len(offsets) - 1
        self._prefix: np.ndarray | None = None

    def words(self, in_word: np.ndarray | None = None) -> None:
        """Find words: runs of bytes that are not white space (or that in_word, a table of 256, marks)."""
        keep = ~SPACE[self.data] if in_word is None else in_word[self.data]
        n = len(keep)
        edge = np.empty(n + 1, bool)
        edge[0], edge[n] = n > 0 and keep[0], n > 0 and keep[n - 1]
        np.not_equal(keep[1:], keep[:-1], out=edge[1:n])
        places = np.flatnonzero(edge)
        starts, ends = places[0::2], places[1::2]
        inner = self.offsets[1:-1]
        inner = np.unique(inner[(inner > 0) & (inner < n)])
        cut = inner[keep[inner] & keep[inner - 1]] if len(inner) else inner  # words that touch across documents
        if len(cut):
            starts, ends = np.sort(np.concatenate((starts, cut))), np.sort(np.concatenate((ends, cut)))
        self.keep, self.starts, self.ends = keep, starts, ends
        self.at = np.searchsorted(starts, self.offsets)  # the first word of each document

    def prefix(self) -> np.ndarray:
        if self._prefix is None:
            up, _ = powers(_BASE, len(self.data) + 1)
            total = np.empty(len(self.data) + 1, U)
            total[0] = 0
            np.cumsum((self.data.astype(U) + U(1)) * up[: len(self.data)], out=total[1:])
            self._prefix = total
        return self._prefix

    def range_hash(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hash of the bytes of each range."""
        total = self.prefix()
        _, down = powers(_BASE, len(self.data) + 1)
        return mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(U))

    def word_hash(self) -> np.ndarray:
        return self.range_hash(self.starts, self.ends)

    def doc_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(self.docs), np.diff(self.at))

    def per_doc(self, flags: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Sum of flags between consecutive places of at."""
        total = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))
        return np.diff(total[at])

    def window_ok(self, n: int) -> np.ndarray:
        """For each start of n words in the chunk: do they lie in one document?"""
        total = len(self.starts)
        if total < n:
            return np.zeros(0, bool)
        ok = np.ones(total - n + 1, bool)
        for end in self.at[1:-1] if self.docs < 200 else np.unique(self.at[1:-1]):
            ok[max(0, end - n + 1) : end] = False
        return ok


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if len(column) == 0:
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(column: pa.Array, lower: bool = False, limit: int = CHUNK) -> Iterator[Chunk]:
    data, offsets = buffers(column)
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield Chunk(i, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], lower)
        i = j
