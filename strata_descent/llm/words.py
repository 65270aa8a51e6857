"""Vectorised word and n-gram kernels over Arrow string buffers.

Everything works on the UTF-8 bytes of a whole batch at once, so no Python loop runs per word.
A word is a maximal run of bytes other than space and the controls 9 to 13; a word never spans
two rows.  Null texts count as empty.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
#: Bytes that one vectorised step handles; a longer text is a step of its own.
STEP_BYTES = 1 << 20

_IS_WORD = np.ones(256, dtype=bool)
_IS_WORD[[0x20, *range(0x09, 0x0E)]] = False
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_rng = np.random.default_rng(20_240_229)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.int64).astype(U64) * U64(2) + U64(1)
_GRAM = _rng.integers(1, 2**63, 64, dtype=np.int64).astype(U64) * U64(2) + U64(1)
_BASE = U64(0x9E3779B97F4A7C15)
_BASE_INVERSE = U64(pow(int(_BASE), -1, 2**64))
_powers: dict[str, np.ndarray] = {}


def _power(name: str, base: np.uint64, n: int) -> np.ndarray:
    have = _powers.get(name)
    if have is None or len(have) < n:
        size = 1 << max(16, (n - 1).bit_length())
        with np.errstate(over="ignore"):
            have = np.cumprod(np.full(size, base, dtype=U64))
        _powers[name] = have
    return have[:n]


def mix(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    h = h.astype(U64, copy=True)
    with np.errstate(over="ignore"):
        h += U64(salt)
        h ^= h >> U64(33)
        h *= U64(0xFF51AFD7ED558CCD)
        h ^= h >> U64(33)
        h *= U64(0xC4CEB9FE1A85EC53)
        h ^= h >> U64(33)
    return h


@dataclass
class Words:
    """Words of the rows of one step: byte bounds, and for each row the range of its words."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    row_words: np.ndarray  # len rows + 1
    row_bytes: np.ndarray  # len rows + 1

    @property
    def rows(self) -> int:
        return len(self.row_words) - 1

    def counts(self) -> np.ndarray:
        return np.diff(self.row_words)

    def row_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(self.rows), self.counts())

    def hashes(self, lower: bool = False) -> np.ndarray:
        data = _LOWER[self.data] if lower else self.data
        n = len(data)
        if not n or not len(self.starts):
            return np.zeros(len(self.starts), dtype=U64)
        with np.errstate(over="ignore"):
            sums = np.zeros(n + 1, dtype=U64)
            np.cumsum(_BYTE[data] * _power("up", _BASE, n), out=sums[1:])
            h = (sums[self.ends] - sums[self.starts]) * _power("down", _BASE_INVERSE, n)[self.starts]
        return mix(h + (self.ends - self.starts).astype(U64))

    def grams(self, n: int, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all n-word windows that stay inside a row, and each window's first word."""
        total = len(hashes)
        if total < n:
            return np.zeros(0, dtype=U64), np.zeros(0, dtype=np.int64)
        with np.errstate(over="ignore"):
            g = np.zeros(total - n + 1, dtype=U64)
            for j in range(n):
                g += hashes[j : total - n + 1 + j] * _GRAM[j]
        left = np.repeat(self.row_words[1:], self.counts())[: total - n + 1] - np.arange(total - n + 1)
        first = np.flatnonzero(left >= n)
        return mix(g[first]), first


def _bytes_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1] if offsets else np.zeros(len(column) + 1, dtype=np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def split(data: np.ndarray, at: np.ndarray) -> Words:
    word = _IS_WORD[data]
    inner = at[:-1][at[:-1] < at[1:]]
    before = np.empty_like(word)
    after = np.empty_like(word)
    if len(word):
        before[0] = False
        before[1:] = word[:-1]
        before[inner] = False
        after[-1] = False
        after[:-1] = word[1:]
        after[inner[inner > 0] - 1] = False
    starts = np.flatnonzero(word & ~before)
    ends = np.flatnonzero(word & ~after) + 1
    return Words(data, starts, ends, np.searchsorted(starts, at), at)


def steps(batch: pa.RecordBatch, column: str = "text") -> Iterator[tuple[int, int, Words]]:
    """(first row, row after the last, words) for runs of rows of about STEP_BYTES together."""
    data, at = _bytes_of(batch.column(batch.schema.get_field_index(column)))
    first, rows = 0, len(at) - 1
    while first < rows:
        last = int(np.searchsorted(at, at[first] + STEP_BYTES, side="right")) - 1
        last = min(max(last, first + 1), rows)
        yield first, last, split(data[at[first] : at[last]], at[first : last + 1] - at[first])
        first = last


def row_sets(row: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, value) pairs, by row and then by value as an unsigned number."""
    order = np.lexsort((value, row))
    row, value = row[order], value[order]
    keep = np.ones(len(row), dtype=bool)
    keep[1:] = (row[1:] != row[:-1]) | (value[1:] != value[:-1])
    return row[keep], value[keep]
