"""Words of many texts as 64-bit keys, and a lookup from keys to rows, over arrays."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Bytes whose words are keyed at once; arrays of so many stay in cache.
SLICE = 1 << 18
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_VALUE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: ASCII white space, and ASCII bytes that are neither letters nor digits.
SPACE = np.isin(np.arange(256), list(b" \t\n\r\x0b\x0c"))
NOT_ALNUM = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

Part = tuple[int, int, int]


def mix(keys: np.ndarray) -> np.ndarray:
    keys = (keys ^ (keys >> np.uint64(32))) * _B
    return keys ^ (keys >> np.uint64(29))


def parts_of(texts: list[bytes], size: int = SLICE) -> Iterator[list[Part]]:
    """Parts of texts, (text, from, to), in groups of about ``size`` bytes; longer texts are cut at white space."""
    group, held = [], 0
    for i, text in enumerate(texts):
        at = 0
        while True:
            end = len(text)
            if end - at > size:
                end = next((p for p in range(at + size, len(text)) if text[p] in b" \t\n\r\x0b\x0c"), len(text))
            group.append((i, at, end))
            held += end - at + 1
            if held >= size:
                yield group
                group, held = [], 0
            if end == len(text):
                break
            at = end
    if group:
        yield group


def word_keys(texts: list[bytes], parts: list[Part], blank: np.ndarray = SPACE, prefix: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """A key for each word of these parts (A-Z lower-cased), and the number of words of each part.

    With ``prefix``, the key is that of the word's first bytes, and differs from the key of any whole word.
    """
    data = LOWER[np.frombuffer(b" ".join(texts[i][a:b] for i, a, b in parts) + b" ", np.uint8)]
    gap = blank[data]
    start = np.flatnonzero(~gap & np.append(True, gap[:-1]))
    ends = np.cumsum([b - a + 1 for _, a, b in parts])
    counts = np.diff(np.searchsorted(start, ends), prepend=0)
    if not len(start):
        return np.empty(0, np.uint64), counts
    length = np.flatnonzero(gap & np.append(False, ~gap[:-1])) - start
    inside = np.arange(len(data))
    inside[start[0] :] -= np.repeat(start, np.diff(np.append(start, len(data))))
    powers = np.cumprod(np.full(int(length.max()) + 1, _B, np.uint64))
    term = _VALUE[data] * powers[np.minimum(inside, len(powers) - 1)]
    term[gap] = 0
    if prefix:
        term[inside >= prefix] = 0
        length = np.minimum(length, prefix) + (prefix << 32)
    return mix(np.add.reduceat(term, start) + length.astype(np.uint64) * _A), counts


def keys_by_text(texts: list[bytes], blank: np.ndarray = SPACE) -> list[np.ndarray]:
    """The word keys of each text."""
    out: list[list[np.ndarray]] = [[] for _ in texts]
    for parts in parts_of(texts):
        keys, counts = word_keys(texts, parts, blank)
        for (i, _, _), piece in zip(parts, np.split(keys, np.cumsum(counts)[:-1])):
            out[i].append(piece)
    return [np.concatenate(x) if len(x) != 1 else x[0] for x in out]


def gram_keys(words: np.ndarray, q: int) -> np.ndarray:
    """A key for each run of q words."""
    n = max(0, len(words) - q + 1)
    key = mix(words[:n] + np.uint64(q))
    for j in range(1, q):
        key = mix(key * np.uint64(3) ^ words[j : j + n])
    return key


class KeyTable:
    """Open addressing from distinct 64-bit keys to their row numbers."""

    def __init__(self, keys: np.ndarray):
        bits = max(4, int(len(keys)).bit_length() + 1)
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys = np.zeros(1 << bits, np.uint64)
        self.rows = np.full(1 << bits, -1, np.int32)
        left, at = np.arange(len(keys)), self._slot(keys)
        while len(left):
            free = self.rows[at] < 0
            self.rows[at[free]] = left[free]
            mine = self.rows[at] == left
            self.keys[at[mine]] = keys[left[mine]]
            left, at = left[~mine], (at[~mine] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * _A) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Row numbers, -1 where absent."""
        at = self._slot(keys)
        out = self.rows[at]
        todo = np.flatnonzero((out >= 0) & (self.keys[at] != keys))
        at = at[todo]
        while len(todo):
            at = (at + 1) & self.mask
            out[todo] = self.rows[at]
            again = (self.rows[at] >= 0) & (self.keys[at] != keys[todo])
            todo, at = todo[again], at[again]
        return out
