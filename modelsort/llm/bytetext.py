"""Vectorised views of Arrow text columns: bytes, words and word hashes in numpy.

Everything works on the UTF-8 bytes of whole texts. A column is cut into blocks
of bounded bytes (one longer text forms a block of its own) so that temporaries
stay small whatever the batch size.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 2 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15)
_rng = np.random.default_rng(20240229)
_BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Word bytes: digits, ASCII letters and every byte of a non-ASCII character.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[65:91] = ALNUM[97:123] = ALNUM[128:] = True
#: Everything but ASCII white space (space and \t \n \v \f \r).
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[32, 9, 10, 11, 12, 13]] = False


def utf8_view(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a text column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    if not (wide or pa.types.is_string(column.type) or pa.types.is_binary(column.type)):
        column, wide = column.cast(pa.large_string()), True
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def blocks(offsets: np.ndarray, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``size`` bytes each, or of one row."""
    row, n = 0, len(offsets) - 1
    while row < n:
        stop = max(row + 1, int(np.searchsorted(offsets, offsets[row] + size, side="right")) - 1)
        yield row, min(stop, n)
        row = min(stop, n)


def word_bounds(data: np.ndarray, offsets: np.ndarray, table: np.ndarray = ALNUM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of each word, and the offsets of rows in the word list."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = table[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    edges = offsets[(offsets > 0) & (offsets < len(data))]
    first[edges] |= inside[edges]
    last[edges - 1] |= inside[edges - 1]
    starts = np.flatnonzero(first)
    ends = np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        with np.errstate(over="ignore"):
            _POWERS = np.cumprod(np.full(max(n, 2 * len(_POWERS)), _BASE, np.uint64)) * np.uint64(pow(int(_BASE), -1, 2**64))
    return _POWERS[:n]


_POWERS = np.ones(1, np.uint64)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, prefixes: tuple[int, ...] = ()) -> np.ndarray:
    """64-bit hash of each word: a polynomial over random byte codes, then mixed.

    With ``prefixes`` a column follows for each length, the hash of the word's
    first bytes, or 0 where the word is not longer or a character would be cut.
    """
    if not len(starts):
        return np.zeros((0, 1 + len(prefixes)) if prefixes else 0, np.uint64)
    with np.errstate(over="ignore"):
        # Powers run from a word's start, so equal words hash alike anywhere.
        lengths = (ends - starts).astype(np.int32)
        at = np.cumsum(lengths) - lengths
        place = np.arange(lengths.sum(), dtype=np.int32) - np.repeat(at.astype(np.int32), lengths)
        where = place + np.repeat(starts.astype(np.int32), lengths)
        terms = _BYTE_CODE[data[where]] * _powers(int(lengths.max()))[place]
        whole = mix(np.add.reduceat(terms, at) + lengths.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        if not prefixes:
            return whole
        out = np.zeros((len(starts), 1 + len(prefixes)), np.uint64)
        out[:, 0] = whole
        sums = np.append(np.uint64(0), np.cumsum(terms))
        for k, size in enumerate(prefixes, 1):
            longer = np.flatnonzero(lengths > size)
            longer = longer[data[starts[longer] + size] & 0xC0 != 0x80]
            out[longer, k] = mix(sums[at[longer] + size] - sums[at[longer]] + np.uint64(size + (1 << 20)) * np.uint64(0xD6E8FEB86659FD93))
        return out


def mix(x: np.ndarray) -> np.ndarray:
    """Finalising mixer, so that any bits of a hash can serve as an index."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        return x ^ (x >> np.uint64(32))


class HashIndex:
    """Position of 64-bit keys in a fixed distinct list, by open addressing in numpy."""

    def __init__(self, keys: np.ndarray):
        self.keys = np.asarray(keys, np.uint64)
        bits = max(4, int(len(self.keys) * 4).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.table = np.full(1 << bits, -1, np.int32)
        left, step = np.arange(len(self.keys)), 0
        while len(left):
            slot = (self._slot(self.keys[left]) + step) & self.mask
            free = self.table[slot] < 0
            self.table[slot[free]] = left[free]
            left = left[self.table[slot] != left]
            step += 1
        self.steps = step

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Index of each key, -1 where absent."""
        if not len(self.keys):
            return np.full(len(keys), -1, np.int32)
        slot = self._slot(keys)
        found = self.table[slot]
        bad = np.flatnonzero((found >= 0) & (self.keys[found] != keys))
        step = 1
        while len(bad):
            at = self.table[(slot[bad] + step) & self.mask]
            found[bad] = at
            bad = bad[(at >= 0) & (self.keys[at] != keys[bad])]
            step += 1
        return found


def row_sums(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sum of ``values`` over each row's range; empty rows give 0."""
    out = np.zeros((len(bounds) - 1, *values.shape[1:]), values.dtype if values.dtype != bool else np.int64)
    full = bounds[1:] > bounds[:-1]
    if full.any():
        out[full] = np.add.reduceat(values, bounds[:-1][full], axis=0, dtype=out.dtype)
    return out
