"""Prefix-free parsing: the order of all suffixes of repetitive texts from a dictionary and a parse.

A phrase ends at a trigger, a window of ``width`` bytes whose rolling hash is 0 modulo ``modulus``, and the next
begins with that window, so phrases overlap by ``width``. Texts are closed by a sentinel window. No suffix of a
phrase that is longer than the overlap is a proper prefix of another. Hence a suffix of a text is ordered by its
rest of the phrase (ranked once for each distinct phrase) and then by the parse that follows (ranked over the parse).
"""

from __future__ import annotations

import numpy as np

from .anchors import rolling

SENTINEL = 256


def _ranks(symbols: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The rank of each position among the runs from there to its end, equal for equal runs; by prefix doubling."""
    rank = np.unique(symbols, return_inverse=True)[1].astype(np.int64)
    place, step = np.arange(len(symbols)), 1
    longest = int((ends - place).max(initial=0))
    while step < longest:
        beyond = place + step
        follow = np.where(beyond < ends, rank[np.minimum(beyond, len(rank) - 1)] + 1, 0)
        rank = np.unique(rank * (len(rank) + 2) + follow, return_inverse=True)[1].astype(np.int64)
        step *= 2
    return rank


class PrefixFreeParse:
    """Dictionary and parse of some texts, and the order of their suffixes."""

    def __init__(self, texts: list[bytes], width: int = 6, modulus: int = 16):
        self.width = width
        sizes = np.array([len(t) for t in texts], np.int64)
        closed = sizes + width
        self.starts = np.cumsum(closed) - closed
        symbols = np.full(int(closed.sum()), SENTINEL, np.int16)
        body = np.frombuffer(b"".join(texts), np.uint8)
        at = np.arange(len(body)) + np.repeat(np.arange(len(texts)) * width, sizes)
        symbols[at] = body
        # a phrase starts at each text's start and at each trigger inside a text
        padded = (symbols & 255).astype(np.uint8)
        trigger = np.zeros(len(symbols), bool)
        if len(symbols) >= width:
            hashes = rolling(padded, width)
            trigger[: len(hashes)] = hashes % np.uint64(modulus) == 0
        first_sentinel = self.starts + sizes
        clean = np.ones(len(symbols), bool)
        for back in range(width):
            clean[np.maximum(first_sentinel - 1 - back + width - 1, 0)] = False  # windows that touch a sentinel
            clean[np.maximum(first_sentinel - back, 0)] = False
        trigger &= clean
        trigger[self.starts] = True
        begin = np.flatnonzero(trigger)
        owner = np.searchsorted(self.starts, begin, "right") - 1
        limit = self.starts[owner] + closed[owner]
        follow = np.append(begin[1:], len(symbols))
        stop = np.where(follow < limit, follow + width, limit)
        # distinct phrases
        names: dict[bytes, int] = {}
        raw = symbols.tobytes()
        ids = np.fromiter((names.setdefault(raw[2 * a : 2 * b], len(names)) for a, b in zip(begin.tolist(), stop.tolist())), np.int64, len(begin))
        joined = np.frombuffer(b"".join(names), np.int16)
        lengths = np.array([len(k) // 2 for k in names], np.int64)
        heads = np.cumsum(lengths) - lengths
        self.dictionary = list(names)
        suffix_rank = _ranks(joined, np.repeat(heads + lengths, lengths))
        # the parse in the order of phrases, a text at a time
        self.parse = np.unique(suffix_rank[heads], return_inverse=True)[1][ids] if len(ids) else ids
        last_of = np.searchsorted(owner, owner, "right")
        parse_rank = _ranks(self.parse, last_of) if len(ids) else ids
        after = np.arange(len(begin)) + 1
        next_rank = np.where(after < last_of, parse_rank[np.minimum(after, len(begin) - 1)] + 1, 0) if len(ids) else ids
        # each position belongs to the last phrase that starts at or before it
        phrase = np.cumsum(trigger) - 1
        offset = np.arange(len(symbols)) - begin[phrase]
        self.key = (suffix_rank[heads[ids[phrase]] + offset], next_rank[phrase])
        self.symbols = symbols

    def order(self, positions: np.ndarray) -> np.ndarray:
        """These positions in the order of their suffixes."""
        first, second = self.key
        return positions[np.lexsort((second[positions], first[positions]))]

    def equal_runs(self, positions: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
        """Positions in suffix order, and the number of the class of each: equal for equal ``span`` bytes."""
        ordered = self.order(positions)
        same = np.zeros(max(0, len(ordered) - 1), bool)
        view = np.lib.stride_tricks.sliding_window_view(self.symbols, span) if len(self.symbols) >= span else np.empty((0, span))
        for i in range(0, len(same), 20_000):
            a, b = ordered[i : i + 20_000], ordered[i + 1 : i + 20_001]
            a = a[: len(b)]
            same[i : i + len(b)] = (view[a] == view[b]).all(axis=1)
        return ordered, np.concatenate([np.zeros(1, np.int64), np.cumsum(~same)])[: len(ordered)]
