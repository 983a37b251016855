"""Whole Arrow batches as flat byte arrays: words, lines and rolling hashes in numpy.

A batch of texts is one buffer with document bounds; every function here works on all
documents of a slice at once, so no Python loop runs per word or character.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute

U64 = np.uint64
BASE = U64(0x9E3779B97F4A7C15)
BASE_INVERSE = U64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_rng = np.random.Generator(np.random.PCG64(20240229))
BYTE_VALUES = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U64(2) + U64(1)
MULTIPLIERS = _rng.integers(1, 2**63, 512, dtype=np.uint64) * U64(2) + U64(1)
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers = [np.ones(1, U64), np.ones(1, U64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``n`` powers of the base and of its inverse modulo 2**64."""
    if len(_powers[0]) < n:
        for k, base in enumerate((BASE, BASE_INVERSE)):
            p = np.full(max(n, 1 << 16), base, U64)
            p[0] = 1
            _powers[k] = np.cumprod(p)
    return _powers[0][:n], _powers[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h ^= h >> U64(27)
    h *= U64(0x94D049BB133111EB)
    h ^= h >> U64(31)
    return h


class Slice:
    """Texts of some rows: ``buf`` holds their UTF-8 bytes, document i is buf[at[i]:at[i+1]]."""

    def __init__(self, column: pa.Array, lower: bool = False):
        column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
        if column.null_count:
            column = column.fill_null(b"")
        _, offsets, data = column.buffers()
        at = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8)
        raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
        self.buf = raw[at[0] : at[-1]]
        if lower:
            self.buf = LOWER[self.buf]
        self.at = at - at[0]
        self.docs = len(column)

    def prefix(self) -> np.ndarray:
        """Prefix sums of byte values times powers, so any substring hashes in O(1)."""
        p, _ = powers(len(self.buf) + 1)
        out = np.zeros(len(self.buf) + 1, U64)
        np.cumsum(BYTE_VALUES[self.buf] * p[:-1], out=out[1:])
        return out

    def hashes(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        _, inverse = powers(len(self.buf) + 1)
        return mix((prefix[end] - prefix[start]) * inverse[start] + (end - start).astype(U64) * MULTIPLIERS[0])

    def spans(self, separator: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Maximal runs of bytes that are no separators: starts, ends, and per document bounds."""
        inside = ~separator[self.buf]
        before = np.empty_like(inside)
        before[1:] = inside[:-1]
        after = np.empty_like(inside)
        after[:-1] = inside[1:]
        if len(inside):
            before[0] = after[-1] = False
            full = self.at[:-1][self.at[1:] > self.at[:-1]]
            before[full] = False
            after[full[full > 0] - 1] = False
        start = np.flatnonzero(inside & ~before)
        end = np.flatnonzero(inside & ~after) + 1
        return start, end, np.searchsorted(start, self.at)

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.spans(IS_SPACE)


def shingles(word_hash: np.ndarray, bounds: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the n-word window that starts at each word, and whether it stays in its document."""
    out = np.zeros(len(word_hash), U64)
    for k in range(n):
        out[: len(out) - k] += word_hash[k:] * MULTIPLIERS[1 + k]
    last = np.repeat(bounds[1:], np.diff(bounds))
    return mix(out), np.arange(len(word_hash)) + n <= last


def slices(batch: pa.RecordBatch, text: str, most_bytes: int = 2_000_000, most_rows: int = 4000) -> Iterator[pa.RecordBatch]:
    """Row slices of bounded text size (one longer text makes a slice of its own)."""
    column = batch.column(batch.schema.get_field_index(text))
    lengths = np.asarray(pa.compute.binary_length(column).fill_null(0)).astype(np.int64)
    total = np.concatenate([[0], np.cumsum(lengths)])
    i = 0
    while i < batch.num_rows:
        j = int(np.searchsorted(total, total[i] + most_bytes, "right")) - 1
        j = min(max(j, i + 1), i + most_rows, batch.num_rows)
        yield batch.slice(i, j - i)
        i = j
