"""Whole-column text kernels in numpy: words, their hashes, shingle sets and similarity sketches of many texts at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
#: Bytes of text that a kernel takes at a time; a longer single text is a slice of its own.
SLICE = 1 << 20

_rng = np.random.Generator(np.random.PCG64(7))
_BYTE = _rng.integers(0, 2**64, 256, dtype=np.uint64)
_BYTE_LOWER = _BYTE.copy()
_BYTE_LOWER[65:91] = _BYTE[97:123]
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True
_BASE = 0x9E3779B97F4A7C15 | 1
_BACK = pow(_BASE, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64 bits."""
    x = x ^ (x >> U(30))
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


_powers: list[np.ndarray] = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the base and of its inverse, modulo 2**64."""
    if len(_powers[0]) < n:
        for k, base in enumerate((_BASE, _BACK)):
            row = np.full(n, base, dtype=np.uint64)
            row[0] = 1
            _powers[k] = np.multiply.accumulate(row)
    out = _powers[0][:n], _powers[1][:n]
    if n > 4 * SLICE:  # don't keep what one very long text has needed
        _powers[0], _powers[1] = (x[: SLICE].copy() for x in out)
    return out


def slices(column: pa.Array, limit: int = SLICE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets in them) of a string column; null counts as empty."""
    column = column.cast(pa.large_string()).fill_null("") if column.null_count else column.cast(pa.large_string())
    n = len(column)
    if not n:
        return
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + limit, side="right")) - 1)
        yield i, j, raw[at[i] : at[j]], at[i : j + 1] - at[i]
        i = j


def word_bounds(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each text (and the end) the number of its first word."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(at), np.int64)
    inside = ~_BLANK[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    edges = at[:-1][at[:-1] < n]
    first[edges] = inside[edges]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[edges[edges > 0] - 1] = inside[edges[edges > 0] - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, at)


def word_hashes(data: np.ndarray, at: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """The hash of each word, and for each text the number of its first word."""
    starts, ends, first = word_bounds(data, at)
    if not len(starts):
        return np.zeros(0, np.uint64), first
    up, down = powers(len(data))
    sums = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((_BYTE_LOWER if lower else _BYTE)[data] * up, out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts]), first


def shingles(hashes: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of all texts and for each text the number of its first; a text of fewer words has its whole sequence as one."""
    count = np.diff(first)
    n = len(hashes)
    out = np.zeros(max(0, n - size + 1), dtype=np.uint64)
    for k in range(size):
        out = mix(out + hashes[k : k + len(out)] + U(k + 1))
    each = np.maximum(count - size + 1, (count > 0).astype(np.int64))
    begin = np.concatenate([[0], np.cumsum(each)])
    keep = np.zeros(begin[-1], dtype=np.uint64)
    full = count >= size
    # positions of the shingles of texts with enough words
    source = np.repeat(first[:-1] - begin[:-1], each) + np.arange(begin[-1])
    is_full = np.repeat(full, each)
    keep[is_full] = out[source[is_full]]
    for i in np.flatnonzero(~full & (count > 0)):
        h = np.zeros(1, dtype=np.uint64)
        for k in range(count[i]):
            h = mix(h + hashes[first[i] + k] + U(k + 1))
        keep[begin[i]] = mix(h + U(count[i]) * U(0x51ED270B))[0]
    return keep, begin


def distinct(values: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's values sorted and without repeats."""
    parts = [np.unique(values[a:b]) for a, b in zip(begin[:-1], begin[1:])]
    sizes = np.fromiter(map(len, parts), dtype=np.int64, count=len(parts))
    return np.concatenate(parts) if parts else values, np.concatenate([[0], np.cumsum(sizes)])


def text_sets(column: pa.Array, size: int, lower: bool = True) -> list[np.ndarray]:
    """The set of shingle hashes of each text, sorted."""
    out: list[np.ndarray] = []
    for _, _, data, at in slices(column):
        hashes, first = word_hashes(data, at, lower)
        values, begin = distinct(*shingles(hashes, first, size))
        out += [values[a:b] for a, b in zip(begin[:-1], begin[1:])]
    return out


def fast_sketch(values: np.ndarray, begin: np.ndarray, width: int) -> np.ndarray:
    """[text, coordinate]: sketches by fast similarity sketching; all ones for an empty set.

    In round r < width every value is hashed to a coordinate and a rank; a coordinate that no earlier round has
    filled keeps the least rank.  In round width + c every value goes to coordinate c, so that after 2 * width rounds
    every coordinate is full.  Sets that are full leave; most do after the first rounds."""
    count = np.diff(begin)
    out = np.full((len(count), width), 2**64 - 1, dtype=np.uint64)
    live = np.flatnonzero(count > 0)
    owner = np.repeat(np.arange(len(count)), count)
    todo = values
    for r in range(2 * width):
        if not len(live):
            break
        rank = mix(todo ^ U((0xD1B54A32D192ED03 * (r + 1)) % 2**64))
        if r < width:
            cell = owner * width + (rank % U(width)).astype(np.int64)
        else:
            cell = owner * width + (r - width)
        flat = out.reshape(-1)
        free = flat[cell] == U(2**64 - 1)
        np.minimum.at(flat, cell[free], rank[free] >> U(1))
        still = (out[live] == U(2**64 - 1)).any(axis=1)
        if not still.all():
            live = live[still]
            mask = np.zeros(len(count), dtype=bool)
            mask[live] = True
            keep = mask[owner]
            owner, todo = owner[keep], todo[keep]
    return out


def bands(sketch: np.ndarray, rows: int) -> np.ndarray:
    """[text, band]: one hash for each band of `rows` coordinates, different for each band."""
    n, width = sketch.shape
    parts = sketch.reshape(n, width // rows, rows)
    out = np.broadcast_to(mix(np.arange(1, width // rows + 1, dtype=np.uint64)), parts.shape[:2]).copy()
    for k in range(rows):
        out = mix(out + parts[:, :, k] * U(0x9FB21C651E98DF25))
    return out
