"""Vectorised word arithmetic over Arrow text columns.

One pass over the UTF-8 bytes of a slice of a batch yields word boundaries and 64-bit word hashes; hashes of any run of
words then come from prefix sums in O(1).  All separators used by the operators are ASCII, so byte-level splitting equals
code-point-level splitting.  Hashes are plain arithmetic with fixed constants: every executor and every retry gets the same
values.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

_U = np.uint64
_BYTE_BASE = 0x9E3779B97F4A7C15
_RUN_BASES = (0xD6E8FEB86659FD93, 0xA0761D6478BD642F)
CHUNK_BYTES = 1 << 18

#: Word separators \x20 and \x09-\x0D.
BLANKS = np.zeros(256, bool)
BLANKS[[0x20, *range(0x09, 0x0E)]] = True
#: Complement of the class [^\x00-\x2F\x3A-\x60\x7B-\x7F]: what separates lower-cased alphanumeric words.
NON_ALNUM = np.zeros(256, bool)
NON_ALNUM[[*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply rounds)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class _Powers:
    """Powers of an odd base and of its inverse modulo 2^64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inv = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, _U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up))
            up, down = np.full(size, self.base, _U), np.full(size, self.inv, _U)
            up[0] = down[0] = 1
            self.up, self.down = np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U)
        return self.up, self.down


_BYTE = _Powers(_BYTE_BASE)
_RUN = tuple(_Powers(b) for b in _RUN_BASES)


def _prefix(values: np.ndarray, powers: _Powers) -> np.ndarray:
    out = np.zeros(len(values) + 1, _U)
    np.cumsum(values * powers.get(len(values) + 1)[0][: len(values)], dtype=_U, out=out[1:])
    return out


def _between(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, powers: _Powers) -> np.ndarray:
    raw = (prefix[end] - prefix[start]) * powers.get(len(prefix))[1][start]
    return mix(raw ^ ((end - start).astype(_U) * _U(0xFF51AFD7ED558CCD)))


@dataclass
class Words:
    """Words of consecutive rows. ``ptr[i]:ptr[i+1]`` are the words of row i; start/end are byte offsets into ``data``."""

    data: np.ndarray
    row_ptr: np.ndarray
    start: np.ndarray
    end: np.ndarray
    ptr: np.ndarray
    hash: np.ndarray

    def __post_init__(self):
        self._prefixes: dict[int, np.ndarray] = {}

    @property
    def rows(self) -> int:
        return len(self.ptr) - 1

    def counts(self) -> np.ndarray:
        return np.diff(self.ptr)

    def run_hash(self, start: np.ndarray, end: np.ndarray, which: int = 0) -> np.ndarray:
        """Hash of the word sequence start:end (word indexes); ``which`` picks one of two independent hashes."""
        if which not in self._prefixes:
            values = self.hash if not which else mix(self.hash + _U(0x632BE59BD9B4E019))
            self._prefixes[which] = _prefix(values, _RUN[which])
        return _between(self._prefixes[which], start, end, _RUN[which])

    def windows(self, k: int) -> np.ndarray:
        """Word indexes at which k consecutive words of one row start."""
        room = np.repeat(self.ptr[1:], self.counts())
        at = np.arange(len(self.start))
        return at[at + k <= room]

    def row_of(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.ptr, at, side="right") - 1

    def text(self, at: int) -> bytes:
        return self.data[self.start[at] : self.end[at]].tobytes()


def split_words(data: np.ndarray, row_ptr: np.ndarray, blanks: np.ndarray = BLANKS, hashes: bool = True) -> Words:
    """Words of the rows data[row_ptr[i]:row_ptr[i+1]]."""
    n = len(data)
    solid = ~blanks[data]
    first = np.zeros(n + 1, bool)
    first[row_ptr] = True
    begins, ends = solid.copy(), solid.copy()
    if n:
        begins[1:] &= ~solid[:-1] | first[1:n]
        ends[:-1] &= ~solid[1:] | first[1:n]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    ptr = np.searchsorted(start, row_ptr)
    hashed = _between(_prefix(data.astype(_U) + _U(1), _BYTE), start, end, _BYTE) if hashes else np.zeros(0, _U)
    return Words(data, row_ptr, start, end, ptr, hashed)


def slices(texts: pa.Array, size: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Row ranges lo, hi of about ``size`` bytes with their bytes and row pointers; null rows are empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    if not len(texts):
        return
    wide = pa.types.is_large_string(texts.type) or pa.types.is_large_binary(texts.type)
    _, offsets, data = texts.buffers()
    ptr = np.frombuffer(offsets, np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    lo = 0
    while lo < len(texts):
        hi = max(lo + 1, int(np.searchsorted(ptr, ptr[lo] + size, side="right")) - 1)
        yield lo, hi, raw[ptr[lo] : ptr[hi]], ptr[lo : hi + 1] - ptr[lo]
        lo = hi


def words_of(texts: pa.Array, blanks: np.ndarray = BLANKS, lower: bool = False, size: int = CHUNK_BYTES) -> Iterator[tuple[int, int, Words]]:
    """Row ranges of a text column with their words, a bounded number of bytes at a time (a longer row comes alone)."""
    for lo, hi, data, ptr in slices(texts, size):
        yield lo, hi, split_words(LOWER[data] if lower else data, ptr, blanks)


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
