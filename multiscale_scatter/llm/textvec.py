"""Vectorised word work on Arrow text columns.

A batch's strings lie end to end in one byte buffer.  Word bounds and 64-bit word hashes are computed
over that buffer with numpy, for pieces of bounded size, without making a Python object for any word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text worked on at once; a longer text is a piece of its own.
PIECE = 1 << 18

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True

_BASE = 0x9E3779B97F4A7C15 | 1
_INV = pow(_BASE, -1, 1 << 64)
_POWERS: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64, at least n of each."""
    while len(_POWERS[0]) < n:
        m = len(_POWERS[0])
        for k, b in ((0, _BASE), (1, _INV)):
            _POWERS[k] = np.concatenate([_POWERS[k], _POWERS[k] * np.uint64(pow(b, m, 1 << 64))])
    return _POWERS[0], _POWERS[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


def string_parts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def pieces(column: pa.Array, limit: int = PIECE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of consecutive rows with at most limit bytes, one row at least."""
    raw, at = string_parts(column)
    n, row = len(at) - 1, 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(at, at[row] + limit, side="right")) - 1)
        end = min(end, n)
        yield row, end, raw[at[row] : at[end]], at[row : end + 1] - at[row]
        row = end


#: Bytes that separate words where punctuation doesn't belong to them: ASCII but for letters and digits.
BREAKS = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def word_bounds(raw: np.ndarray, at: np.ndarray, breaks: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, words per row)."""
    if not len(raw):
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(at) - 1, np.int64)
    inside = ~breaks[raw]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    cut = at[1:-1]
    cut = cut[(cut > 0) & (cut < len(raw))]
    first[cut] = inside[cut]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[cut - 1] = inside[cut - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    k = np.searchsorted(starts, at)
    return starts, ends, np.diff(k)


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of raw[starts:ends], from one running sum of the buffer."""
    up, down = _powers(len(raw) + 1)
    total = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts] ^ (ends - starts).astype(np.uint64))


def laid_hashes(raw: np.ndarray, sizes: np.ndarray, limit: int = PIECE) -> np.ndarray:
    """span_hashes of strings that lie end to end, with working memory for limit bytes at once."""
    ends = np.cumsum(sizes)
    out = np.empty(len(sizes), np.uint64)
    a = 0
    while a < len(sizes):
        base = ends[a] - sizes[a]
        b = max(a + 1, int(np.searchsorted(ends, base + limit, side="right")))
        out[a:b] = span_hashes(raw[base : ends[b - 1]], ends[a:b] - sizes[a:b] - base, ends[a:b] - base)
        a = b
    return out


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def lower_ascii(raw: np.ndarray) -> np.ndarray:
    """A-Z lower-cased; other bytes stay."""
    return _LOWER[raw]


def shingle_hashes(words: np.ndarray, counts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, per row) of the runs of width words; a row with fewer words, but some, has one run of all of them."""
    ends = np.cumsum(counts)
    begins = ends - counts
    n = np.where(counts >= width, counts - width + 1, (counts > 0).astype(np.int64))
    out_end = np.cumsum(n)
    row = np.repeat(np.arange(len(counts)), n)
    begin = begins[row] + (np.arange(int(out_end[-1]) if len(n) else 0) - (out_end - n)[row])
    size = np.minimum(counts, width)[row]
    h = size.astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D)
    for j in range(width):
        use = size > j
        if use.all():
            h = (h * np.uint64(0xD6E8FEB86659FD93)) ^ words[begin + j]
        else:
            h[use] = (h[use] * np.uint64(0xD6E8FEB86659FD93)) ^ words[begin[use] + j]
    return mix(h), n
