"""Vectorised word splitting and hashing over the bytes of an Arrow string column.

Works on the concatenated UTF-8 buffer: one lookup table says which bytes belong to words (a byte of a multi-byte
character is decided as a whole, since the tables treat all bytes from 0x80 alike), another folds A-Z. A word's 64-bit
value is a polynomial hash taken from wrapped prefix sums, then mixed; nothing runs per word in Python.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_BASE = np.uint64(0x9E3779B97F4A7C15)
_UNBASE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))

FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32

#: Words are runs of bytes other than ASCII white space.
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
#: Words are runs of ASCII digits, letters and non-ASCII bytes.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[0x30:0x3A] = ALNUM[0x41:0x5B] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finalizer."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(16, (n - 1).bit_length())
    if size not in _POWERS:
        _POWERS.clear()
        up, down = np.full(size, _BASE), np.full(size, _UNBASE)
        up[0] = down[0] = 1
        _POWERS[size] = np.cumprod(up), np.cumprod(down)
    return _POWERS[size]


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes and the n+1 offsets of a string column; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_string(column.type) or pa.types.is_binary(column.type):
        kind = np.int32
    else:
        column, kind = column.cast(pa.large_string()), np.int64
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, at, data = column.buffers()
    offsets = np.frombuffer(at, dtype=kind, count=len(column) + 1, offset=column.offset * np.dtype(kind).itemsize).astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, most: int = 4 << 20):
    """Row ranges whose bytes add up to about ``most``; a longer row stands alone."""
    row, rows = 0, len(offsets) - 1
    while row < rows:
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + most, side="right")) - 1)
        yield row, end
        row = end


def _pieces(raw: np.ndarray, table: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Cut a long buffer in front of bytes outside words, so that scratch arrays stay small."""
    cuts = [0]
    while len(raw) - cuts[-1] > most:
        at = cuts[-1] + most
        while at < len(raw) and table[raw[at]]:
            outside = np.flatnonzero(~table[raw[at : at + most]])
            at += int(outside[0]) if len(outside) else most
        cuts.append(min(at, len(raw)))
    return list(zip(cuts, [*cuts[1:], len(raw)], strict=True))


def words(raw: np.ndarray, offsets: np.ndarray, table: np.ndarray, most: int = 8 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word (A-Z folded), and the n+1 offsets of each row's words."""
    values, at, _ = words_and_sizes(raw, offsets, table, most)
    return values, at


def words_and_sizes(raw: np.ndarray, offsets: np.ndarray, table: np.ndarray, most: int = 8 << 20) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As ``words``, and each word's bytes."""
    values, places, sizes = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for low, high in _pieces(raw, table, most):
        if low < high:
            cut = offsets[(offsets > low) & (offsets < high)] - low
            value, start, size = _words(raw[low:high], np.unique(cut), table)
            values.append(value)
            places.append(start + low)
            sizes.append(size)
    return np.concatenate(values), np.searchsorted(np.concatenate(places), offsets), np.concatenate(sizes)


def _words(raw: np.ndarray, cut: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    inside = table[raw]
    before, after = np.empty_like(inside), np.empty_like(inside)
    before[0], before[1:] = False, inside[:-1]
    after[-1], after[:-1] = False, inside[1:]
    starts_mask, ends_mask = inside & ~before, inside & ~after
    starts_mask[cut] = inside[cut]
    ends_mask[cut - 1] = inside[cut - 1]
    starts, ends = np.flatnonzero(starts_mask), np.flatnonzero(ends_mask) + 1
    up, down = _powers(len(raw) + 1)
    total = np.empty(len(raw) + 1, np.uint64)
    total[0] = 0
    np.cumsum((FOLD[raw].astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=total[1:])
    value = (total[ends] - total[starts]) * down[starts]
    return mix(value + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), starts, ends - starts


def shingles(hashes: np.ndarray, at: np.ndarray, size: int, sizes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles, sorted inside each row, and their n+1 offsets. A shorter row that has words is one shingle.

    With word sizes, a shingle's value leads with its length in six bits, long ones first: long shingles are rare ones,
    so the order of values is an order of rarity that needs no table.
    """
    counts = np.diff(at)
    rows = len(counts)
    out = np.zeros(len(hashes), np.uint64)
    for k in range(size):
        n = len(hashes) - k
        if n <= 0:
            break
        factor = np.uint64((0xA24BAED4963EE407 * (2 * k + 1) + 2 * k) % (1 << 64) | 1)
        out[:n] += mix(hashes[k:] ^ np.uint64(k * 0x632BE5AB) if k else hashes) * factor if k else hashes * factor
    row = np.repeat(np.arange(rows), counts)
    place = np.arange(len(hashes)) - np.repeat(at[:-1], counts)
    keep = place <= np.repeat(counts - size, counts)
    if (short := (counts > 0) & (counts < size)).any():
        for r in np.flatnonzero(short):  # at most size - 1 words each
            value = np.uint64(counts[r])
            for h in hashes[at[r] : at[r + 1]]:
                value = mix(np.array([value ^ h]))[0]
            out[at[r]], keep[at[r]] = value, True
    values = mix(out[keep])
    if sizes is not None:
        long = np.concatenate([[0], np.cumsum(sizes)])
        place = np.flatnonzero(keep)
        length = np.minimum(long[np.minimum(place + size, at[1:][row[keep]])] - long[place], 63)
        values = ((63 - length).astype(np.uint64) << np.uint64(58)) | (values >> np.uint64(6))
    row = row[keep]
    bounds = np.searchsorted(row, np.arange(rows + 1))
    return distinct_sorted(values, bounds)


def distinct_sorted(values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    parts, sizes = [], np.zeros(len(bounds), np.int64)
    for r in range(len(bounds) - 1):
        part = np.unique(values[bounds[r] : bounds[r + 1]])
        parts.append(part)
        sizes[r + 1] = len(part)
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint64)), np.cumsum(sizes)
