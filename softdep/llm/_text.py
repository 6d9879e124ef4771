"""Words and shingles of Arrow text columns as NumPy arrays, without a Python object per word."""

from __future__ import annotations

import sys
from collections.abc import Iterator
from types import ModuleType

import numpy as np
import pyarrow as pa

BLANK_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
#: Text is taken in pieces of whole rows of about so many bytes, which bounds the arrays built from it.
PIECE_BYTES = 1 << 18
_BASE = 0x9E3779B97F4A7C15 | 1


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def pieces(column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) of consecutive runs of rows; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, off, data = column.buffers()
    n = len(column)
    if not n:
        return
    offs = np.frombuffer(off, kind, n + 1, column.offset * np.dtype(kind).itemsize).astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    row = 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(offs, offs[row] + PIECE_BYTES, "right")) - 1)
        yield row, raw[offs[row] : offs[end]], offs[row : end + 1] - offs[row]
        row = end


def lowered(data: np.ndarray) -> np.ndarray:
    """ASCII letters A-Z in lower case, on UTF-8 bytes."""
    return np.where((data >= 65) & (data <= 90), data + 32, data).astype(np.uint8)


def lowered_latin(data: np.ndarray) -> np.ndarray:
    """As lowered, and the accented capitals of Latin-1 too (two bytes, the first C3)."""
    out = lowered(data)
    after = np.flatnonzero(data[:-1] == 0xC3) + 1
    second = data[after]
    capital = after[(second >= 0x80) & (second <= 0x9E) & (second != 0x97)]
    out[capital] += 0x20
    return out


def spans(data: np.ndarray, offs: np.ndarray, apart: tuple[int, ...] = BLANK_BYTES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, start, end) of each word, a run of bytes that are not in apart."""
    if not len(data):
        return (np.zeros(0, np.int64),) * 3
    blank = np.zeros(256, bool)
    blank[list(apart)] = True
    word = ~blank[data]
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1]
    last[:-1] &= ~word[1:]
    full = offs[:-1] < offs[1:]
    a, b = offs[:-1][full], offs[1:][full] - 1
    first[a] |= word[a]
    last[b] |= word[b]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return np.searchsorted(offs, start, "right") - 1, start, end


def _powers(pieces_long: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, for whole pieces. Kept once by each process, under a name of its own, since
    functions reach workers by value and their globals come anew with each task."""
    kept = sys.modules.setdefault("_softdep_kept", ModuleType("_softdep_kept"))
    held = getattr(kept, "powers", None)
    if held is None or len(held[0]) < pieces_long * PIECE_BYTES:
        base = np.full(pieces_long * PIECE_BYTES, _BASE, np.uint64)
        base[0] = 1
        power = np.cumprod(base)
        base[1:] = pow(_BASE, -1, 1 << 64)
        held = kept.powers = power, np.cumprod(base)
    return held


class Hashes:
    """64-bit hashes of spans of data, by prefix sums of a polynomial of the bytes."""

    def __init__(self, data: np.ndarray):
        power, self.inverse = _powers(-(-(len(data) + 1) // PIECE_BYTES))
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[: len(data)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mixed((self.sums[end] - self.sums[start]) * self.inverse[start] + (end - start).astype(np.uint64) * np.uint64(0xD1B54A32D192ED03))


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return Hashes(data).of(start, end)


def shingles(row: np.ndarray, hashes: np.ndarray, n_rows: int, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of each run of size words of a row; of a shorter row with words, the whole sequence as one."""
    odd = [np.uint64((0xA0761D6478BD642F * (2 * k + 1)) % (1 << 64) | 1) for k in range(size)]
    parts, rows = [], []
    if len(row) >= size:
        inside = row[: len(row) - size + 1] == row[size - 1 :]
        h = np.zeros(int(inside.sum()), np.uint64)
        for k in range(size):
            h = mixed(h + hashes[k : len(row) - size + 1 + k][inside] * odd[k])
        parts.append(h)
        rows.append(row[: len(row) - size + 1][inside])
    counts = np.bincount(row, minlength=n_rows)
    short = np.flatnonzero((counts > 0) & (counts < size))
    if len(short):
        first = np.searchsorted(row, short)
        h = np.full(len(short), 0x2545F4914F6CDD1D, np.uint64) * counts[short].astype(np.uint64)
        for k in range(size - 1):
            more = counts[short] > k
            h[more] = mixed(h[more] + hashes[first[more] + k] * odd[k])
        parts.append(h)
        rows.append(short)
    if not parts:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    r, h = np.concatenate(rows), np.concatenate(parts)
    order = np.argsort(r, kind="stable")
    return r[order], h[order]
