"""Vectorised hashing of words and word windows over Arrow text buffers.

The words of a whole batch are found and hashed with a fixed number of numpy
passes over the bytes, without making a Python object per word.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SLICE = 1 << 20
_P = 0x9E3779B97F4A7C55 | 1
_MASK = (1 << 64) - 1


class _Tables(dict):
    """A cache that travels empty when code is sent to workers."""

    def __reduce__(self) -> tuple:
        return (_Tables, ())


_POWERS = _Tables()


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n."""
    got = _POWERS.get(base)
    if got is None or len(got[0]) < n:
        size = max(n, _SLICE + 64)
        out = []
        for b in (base, pow(base, -1, 1 << 64)):
            a = np.full(size, b, dtype=np.uint64)
            a[0] = 1
            out.append(np.multiply.accumulate(a))
        got = _POWERS[base] = (out[0], out[1])
        if size > 4 * _SLICE:  # an outsized word; don't keep its table
            del _POWERS[base]
    return got


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (in place)."""
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts, and where each begins (one more offset at the end). A null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    return raw[at[0]:at[-1]], at - at[0]


def text_slices(column: pa.Array, limit: int = 2 << 20) -> list[tuple[int, int]]:
    """Row ranges (begin, length) of at most `limit` bytes of text each, or of one text, so that work arrays stay small."""
    _, at = text_buffer(column)
    out, i = [], 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(at, at[i] + limit, side="right")) - 1)
        out.append((i, j - i))
        i = j
    return out


def word_spans(raw: np.ndarray, at: np.ndarray, blank: np.ndarray = _BLANK) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of every word; none runs over the border of a text."""
    solid = ~blank[raw]
    if not len(raw):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    begin = solid.copy()
    begin[1:] &= ~solid[:-1]
    end = solid.copy()
    end[:-1] &= ~solid[1:]
    inner = at[1:-1]
    inner = inner[(inner > 0) & (inner < len(raw))]
    begin[inner] = solid[inner]
    end[inner - 1] = solid[inner - 1]
    return np.flatnonzero(begin), np.flatnonzero(end) + 1


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
    """64-bit hash of each word's bytes."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + _SLICE, side="right")))
        lo, hi = int(starts[i]), int(ends[j - 1])
        up, down = powers(_P, hi - lo + 1)
        part = raw[lo:hi]
        vals = (_LOWER[part] if lower else part).astype(np.uint64)
        vals += np.uint64(0x5BD1E995A7)
        vals *= up[: hi - lo]
        total = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum(vals, out=total[1:])
        s, e = starts[i:j] - lo, ends[i:j] - lo
        h = (total[e] - total[s]) * down[s]
        h += (e - s).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        out[i:j] = mix(h)
        i = j
    return out


def window_hashes(words: np.ndarray, width: int, base: int = 0xC2B2AE3D27D4EB4F) -> np.ndarray:
    """Hash of every run of `width` words; two bases give two independent hashes."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.empty(n, np.uint64)
    step = 1 << 18
    up, down = powers(base | 1, step + width + 1)
    for i in range(0, n, step):
        k = min(step, n - i)
        total = np.zeros(k + width, np.uint64)
        np.cumsum(words[i:i + k + width - 1] * up[: k + width - 1], out=total[1:])
        out[i:i + k] = (total[width:width + k] - total[:k]) * down[:k]
    return mix(out)


def owners(at: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Index of the text that holds each word."""
    return np.searchsorted(at, starts, side="right") - 1
