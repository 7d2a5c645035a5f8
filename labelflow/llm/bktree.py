"""Burkhard-Keller trees over 64-bit fingerprints, many trees at a time as flat arrays.

A node's children are keyed by their Hamming distance to it; a search with radius r at distance d follows only
the edges whose key lies in [d - r, d + r]. Both building and searching go level by level over all trees of a
shard at once.
"""

from __future__ import annotations

import numpy as np

#: Pairs of query and node that one step of a search starts from at most; it may follow several edges from each.
FRONTIER = 1 << 18


class Forest:
    """BK-trees of the distinct fingerprints of each bucket. ``bucket`` numbers the tree of each key.

    Of equal keys of a bucket the first is the node, and a search that meets it finds all of them.
    """

    def __init__(self, keys: np.ndarray, bucket: np.ndarray):
        self.keys = np.asarray(keys, np.uint64)
        _, first, inverse = np.unique(bucket, return_index=True, return_inverse=True)
        at = self.root = first[inverse].astype(np.int64)
        self.equal = np.lexsort((self.keys, inverse))
        head = np.ones(len(at), bool)
        head[1:] = (np.diff(self.keys[self.equal]) != 0) | (np.diff(inverse[self.equal]) != 0)
        begin = np.flatnonzero(head)
        self.begin, self.copies = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        self.begin[self.equal[begin]], self.copies[self.equal[begin]] = begin, np.diff(np.append(begin, len(at)))
        todo = np.flatnonzero((at != np.arange(len(at))) & (self.copies > 0))
        at = at[todo]
        codes, children = [], []
        while len(todo):
            code = at * 65 + np.bitwise_count(self.keys[todo] ^ self.keys[at])
            edge, pick, inverse = np.unique(code, return_index=True, return_inverse=True)
            child = todo[pick]
            codes.append(edge)
            children.append(child)
            at = child[inverse]
            rest = at != todo
            todo, at = todo[rest], at[rest]
        self.codes = np.concatenate(codes) if codes else np.empty(0, np.int64)
        self.children = np.concatenate(children) if children else np.empty(0, np.int64)
        order = np.argsort(self.codes, kind="stable")
        self.codes, self.children = self.codes[order], self.children[order]

    def search(self, radius: int, queries: np.ndarray | None = None):
        """Yield arrays (query, node) of keys of one tree at most ``radius`` bits apart, each query in its own tree."""
        queries = np.arange(len(self.keys)) if queries is None else queries
        stack = [(queries, self.root[queries])]
        while stack:
            q, node = stack.pop()
            if len(q) > FRONTIER:
                stack += [(q[: len(q) // 2], node[: len(q) // 2]), (q[len(q) // 2 :], node[len(q) // 2 :])]
                continue
            d = np.bitwise_count(self.keys[q] ^ self.keys[node]).astype(np.int64)
            hit = (d <= radius) & ((q != node) | (self.copies[node] > 1))
            if hit.any():
                yield from self._members(q[hit], node[hit])
            low = np.searchsorted(self.codes, node * 65 + np.maximum(d - radius, 1), "left")
            high = np.searchsorted(self.codes, node * 65 + np.minimum(d + radius, 64), "right")
            n = high - low
            total = int(n.sum())
            if total:
                to = np.repeat(low - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(total)
                stack.append((np.repeat(q, n), self.children[to]))

    def _members(self, q: np.ndarray, node: np.ndarray):
        """Yield (query, key) for all keys equal to each node, but for the query itself."""
        ends = np.cumsum(self.copies[node])
        at = 0
        while at < len(q):
            done = int(ends[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(ends, done + FRONTIER, "right")))
            n = self.copies[node[at:to]]
            member = self.equal[np.repeat(self.begin[node[at:to]] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]
            who = np.repeat(q[at:to], n)
            other = who != member
            if other.any():
                yield who[other], member[other]
            at = to


class Union:
    """Union-find over 0..n-1 that keeps the smallest member as the root."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def roots(self) -> np.ndarray:
        while True:
            up = self.parent[self.parent]
            if (up == self.parent).all():
                return self.parent
            self.parent = up

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        while True:
            root = self.roots()
            x, y = root[a], root[b]
            apart = x != y
            if not apart.any():
                return
            a, b = np.minimum(x[apart], y[apart]), np.maximum(x[apart], y[apart])
            np.minimum.at(self.parent, b, a)
