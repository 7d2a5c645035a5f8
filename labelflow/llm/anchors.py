"""Content-determined triggers of byte strings: where a rolling hash is least among its neighbours.

Every string of ``span`` bytes contains one gram of ``gram`` bytes whose hash is least (the last of equals). It
depends on those bytes alone, so equal strings have it at the same offset. Consecutive strings that share it make
one segment.
"""

from __future__ import annotations

import numpy as np

from .words import mix

_M = np.uint64(0x9E3779B97F4A7C15)
_R = np.random.default_rng(977).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_R2 = np.random.default_rng(978).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def rolling(data: np.ndarray, width: int, values: np.ndarray = _R) -> np.ndarray:
    """A hash of each run of ``width`` bytes, by doubling."""
    whole = None
    piece, size = values[data], 1
    base = int(_M)  # as a Python number: powers wrap without a warning
    left = width
    offset = 0
    while left:
        if left & 1:
            part = piece[offset:]
            whole = part if whole is None else whole[: len(part)] * np.uint64(base) + part
            offset += size
        left >>= 1
        if left:
            piece = piece[:-size] * np.uint64(base) + piece[size:] if len(piece) > size else piece[:0]
            base = base * base % (1 << 64)
            size *= 2
    n = max(0, len(data) - width + 1)
    return mix(whole[:n])


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each run of ``width`` values."""
    out, size = values, 1
    while size * 2 <= width:
        out = np.minimum(out[:-size], out[size:])
        size *= 2
    rest = width - size
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def segments(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray, span: int, gram: int):
    """For texts at ``starts`` of ``data``: (text, first string, strings, anchor's hash, segment's hash) of each segment."""
    n = len(data) - span + 1
    if n <= 0:
        empty = np.empty(0, np.int64)
        return empty, empty, empty, np.empty(0, np.uint64), np.empty(0, np.uint64)
    grams = rolling(data, gram)
    low = np.uint64((1 << 23) - 1)
    ranked = (grams & ~low) | (low - np.arange(len(grams), dtype=np.uint64))
    anchor = (low - (sliding_min(ranked, span - gram + 1) & low)).astype(np.int64)
    # a string must lie in one text
    text = np.full(n, -1)
    for i, (a, size) in enumerate(zip(starts.tolist(), sizes.tolist())):
        if size >= span:
            text[a : a + size - span + 1] = i
    inside = text >= 0
    edge = np.append(True, (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1]))
    first = np.flatnonzero(edge & inside)
    ends = np.flatnonzero(np.append(edge, True))
    last = ends[np.searchsorted(ends, first, "right")]
    power = np.cumprod(np.full(len(data) + 1, _M, np.uint64))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_R2[data] * power[:-1], dtype=np.uint64)])
    stop = last - 1 + span
    inverse = np.uint64(pow(int(_M), -1, 1 << 64))
    back = np.cumprod(np.full(len(data) + 1, inverse, np.uint64))
    content = (sums[stop] - sums[first]) * back[first]
    return text[first], first, last - first, grams[anchor[first]], mix(content ^ (stop - first).astype(np.uint64))
