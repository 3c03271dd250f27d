"""Vectorised tokenising of Arrow string columns.

A word is a maximal run of bytes other than space and the control bytes 9 to 13;
ASCII capitals are lowered. All work is done on the column's own byte buffer, in
slices of bounded size, so that memory follows the slice and not the table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 19
_TABLE = 1 << 20
_NEAR, _FAR = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_POW, _INV = _powers(_NEAR, _TABLE), _powers(pow(_NEAR, -1, 1 << 64), _TABLE)
_FAR_POW, _FAR_INV = _powers(_FAR, 1 << 12), _powers(pow(_FAR, -1, 1 << 64), 1 << 12)


def _weight(at: np.ndarray, near: np.ndarray, far: np.ndarray) -> np.ndarray:
    """Powers for byte places of a text that is longer than the table."""
    return near[at & (_TABLE - 1)] * far[at >> 20]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


@dataclass
class Words:
    """Words of a slice of texts: ``doc`` is the row within the slice."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    hash: np.ndarray
    first: np.ndarray  # of each row, the index of its first word; one more at the end
    base: int  # the slice's first row in its batch
    rows: int


def _plain(column) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets and bytes of a string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if pa.types.is_string_view(column.type) or pa.types.is_null(column.type):
        column = column.cast(pa.large_string())
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, kind)
    return at.astype(np.int64), np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)


_SPOKEN = np.ones(256, bool)  # bytes that make up words once punctuation is gone
_SPOKEN[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = False


def plain(at: np.ndarray, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Without ASCII punctuation, and with the capitals of Latin-1 letters lowered too."""
    keep = _SPOKEN[raw]
    kept = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(keep, out=kept[1:])
    raw = raw[keep]
    if len(raw) > 1:
        high = (raw[:-1] == 0xC3) & (raw[1:] >= 0x80) & (raw[1:] <= 0x9E) & (raw[1:] != 0x97)
        raw[1:][high] += 0x20
    return kept[at], raw


def slices(column, most: int = SLICE_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, byte offsets from 0, bytes) of runs of whole texts of about ``most`` bytes."""
    at, data = _plain(column)
    row, rows = 0, len(at) - 1
    while row < rows:
        to = max(row + 1, int(np.searchsorted(at, at[row] + most, "right")) - 1)
        yield row, at[row : to + 1] - at[row], data[at[row] : at[to]]
        row = to


def words(column, most: int = SLICE_BYTES, spoken: bool = False) -> Iterator[Words]:
    """``spoken``: words without punctuation (see ``plain``)."""
    with np.errstate(over="ignore"):
        for row, at, raw in slices(column, most):
            if spoken:
                at, raw = plain(at, raw)
            low, blank, n = _LOWER[raw], _BLANK[raw], len(raw)
            begins = ~blank
            begins[1:] &= blank[:-1]
            cut = at[:-1][at[:-1] < n]
            begins[cut] = ~blank[cut]
            start = np.flatnonzero(begins)
            ends = ~blank
            ends[:-1] &= blank[1:]
            cut = at[1:][at[1:] > 0] - 1
            ends[cut] = ~blank[cut]
            end = np.flatnonzero(ends) + 1
            if n <= _TABLE:
                h = np.cumsum((low.astype(np.uint64) + np.uint64(1)) * _POW[:n])
                back = _INV[start]
            else:
                place = np.arange(n)
                h = np.cumsum((low.astype(np.uint64) + np.uint64(1)) * _weight(place, _POW, _FAR_POW))
                back = _weight(start, _INV, _FAR_INV)
            # A difference of the running sum, shifted back to the word's own start.
            h = h[end - 1] - np.where(start > 0, h[start - 1], np.uint64(0)) if n else np.zeros(0, np.uint64)
            h = mix(h * back ^ ((end - start).astype(np.uint64) << np.uint64(48)))
            doc = np.searchsorted(at, start, "right") - 1
            first = np.searchsorted(doc, np.arange(len(at)), "left")
            yield Words(low, start, end, doc, h, first, row, len(at) - 1)
