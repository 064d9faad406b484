"""Vectorised word arithmetic over the byte buffer of a batch of texts.

A word is a maximal run of bytes other than space, tab, newline, vertical tab,
form feed and carriage return.  Those separators are single bytes in UTF-8, so
words are found on the raw buffer.  Every function treats a whole Arrow batch at
once; no loop runs per word or per character.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

MASK = np.uint64(0xFFFFFFFFFFFFFFFF)
_BASE = 0x9E3779B97F4A7C15 | 1  # odd, hence invertible modulo 2**64
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def mix64(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """Bijective avalanche of uint64 values."""
    z = x + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def _powers(n: int, base: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    out = np.full(n, np.uint64(base), dtype=np.uint64)
    if n:
        out[0] = 1
        np.multiply.accumulate(out, out=out)
    return out


_CACHE: dict[int, np.ndarray] = {}


def powers(n: int, base: int) -> np.ndarray:
    have = _CACHE.get(base)
    if have is None or len(have) < n:
        have = _CACHE[base] = _powers(max(n, 1 << 16), base)
    return have[:n]


def forget() -> None:
    """Empty the table of powers, so that it isn't shipped with a function."""
    _CACHE.clear()


_BYTE_A = mix64(np.arange(256, dtype=np.uint64), 11)
_BYTE_B = mix64(np.arange(256, dtype=np.uint64), 12)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the n + 1 offsets; null reads as empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    texts = texts.cast(pa.large_string())
    n = len(texts)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = texts.buffers()
    offsets = np.frombuffer(off, dtype=np.int64)[texts.offset : texts.offset + n + 1]
    if data is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]]
    return raw, offsets - offsets[0]


#: Everything but ASCII letters and the bytes of other scripts.
NOT_LETTER = np.ones(256, dtype=bool)
NOT_LETTER[65:91] = NOT_LETTER[97:123] = NOT_LETTER[128:] = False


class Words:
    """start, end: byte bounds of each word; first: index of each text's first word (n + 1)."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, lower: bool = False, gap: np.ndarray = _SPACE):
        self.raw = _LOWER[raw] if lower else raw
        self.offsets = offsets
        word = ~gap[raw]
        edge = np.empty(len(raw) + 1, dtype=bool)
        if len(raw):
            np.not_equal(word[1:], word[:-1], out=edge[1:-1])
            edge[0], edge[-1] = word[0], word[-1]
            # a text that ends in a word and is followed by one that begins with a word
            inner = offsets[1:-1]
            inner = inner[(inner > 0) & (inner < len(raw))]
            joined = np.unique(inner[word[inner] & word[inner - 1]])
        else:
            edge[:] = False
            joined = np.zeros(0, np.int64)
        marks = np.flatnonzero(edge)
        self.start, self.end = marks[0::2], marks[1::2]
        if len(joined):
            self.start = np.sort(np.concatenate([self.start, joined]))
            self.end = np.sort(np.concatenate([self.end, joined]))
        self.first = np.searchsorted(self.start, offsets)
        self.first[-1] = len(self.start)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def owner(self) -> np.ndarray:
        """Index of the text of each word."""
        return np.repeat(np.arange(len(self.first) - 1), self.counts())

    def hashes(self, second: bool = False) -> np.ndarray:
        """A 64-bit hash of each word that depends on its bytes alone."""
        return spans_hash(self.raw, self.start, self.end, second)


def spans_hash(raw: np.ndarray, start: np.ndarray, end: np.ndarray, second: bool = False) -> np.ndarray:
    """Hash of raw[start:end] for many spans at once by prefix sums modulo 2**64."""
    out = np.empty(len(start), dtype=np.uint64)
    base = (_BASE * 5) & 0xFFFFFFFFFFFFFFFF if second else _BASE
    table = _BYTE_B if second else _BYTE_A
    inverse = pow(base, -1, 1 << 64)
    step = 1 << 20
    at = 0
    while at < len(start):  # by blocks, so that the working set stays small
        lo = int(start[at])
        upto = max(int(np.searchsorted(start, lo + step)), at + 1)
        hi = int(end[upto - 1])
        value = table[raw[lo:hi]]
        value *= powers(hi - lo, base)
        total = np.empty(hi - lo + 1, dtype=np.uint64)
        total[0] = 0
        np.cumsum(value, out=total[1:])
        s, e = start[at:upto] - lo, end[at:upto] - lo
        span = (total[e] - total[s]) * powers(hi - lo + 1, inverse)[s]
        out[at:upto] = mix64(span + (e - s).astype(np.uint64))
        at = upto
    return out


def windows(word: np.ndarray, first: np.ndarray, k: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Rolling polynomial (Rabin-Karp) hash of k consecutive words of one text.

    Returns the hash of the window that starts at each word, and whether that
    window lies inside its text.
    """
    n = len(word)
    inside = np.zeros(n, dtype=bool)
    if n == 0:
        return np.zeros(0, np.uint64), inside
    total = np.zeros(n, dtype=np.uint64)
    base = mix64(np.array([seed + 101], dtype=np.uint64))[0] | np.uint64(1)
    m = n - k + 1
    if m > 0:
        for i in range(k):  # k fused multiply-adds over the whole batch
            total[:m] *= base
            total[:m] += word[i : i + m]
    last = np.repeat(first[1:], np.diff(first))
    inside = np.arange(n) + k <= last
    return mix64(total, seed), inside
