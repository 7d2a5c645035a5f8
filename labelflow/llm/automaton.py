"""Byte automata: a small regular-expression parser, subset construction, minimisation, and scanning in lanes.

Syntax: literals, ``\\xHH`` and escaped characters, ``[...]`` with ranges and ``^``, ``(...)``, ``(?i:...)`` for ASCII
letters in either case, ``|``, ``?``, ``*``, ``+`` and ``{m}``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Lanes are about so long; each starts where the state is known whatever came before.
LANE = 256


class _Parser:
    """Patterns to trees: ('set', frozenset), ('cat', [...]), ('alt', [...]), ('star', t), ('opt', t)."""

    def __init__(self, pattern: str):
        self.text, self.at, self.fold = pattern, 0, False

    def peek(self) -> str:
        return self.text[self.at : self.at + 1]

    def take(self) -> str:
        self.at += 1
        return self.text[self.at - 1]

    def alternatives(self):
        parts = [self.sequence()]
        while self.peek() == "|":
            self.take()
            parts.append(self.sequence())
        return parts[0] if len(parts) == 1 else ("alt", parts)

    def sequence(self):
        parts = []
        while self.peek() not in ("", "|", ")"):
            item = self.atom()
            while self.peek() and self.peek() in "?*+{":
                sign = self.take()
                if sign == "{":
                    end = self.text.index("}", self.at)
                    n, self.at = int(self.text[self.at : end]), end + 1
                    item = ("cat", [item] * n)
                else:
                    item = {"?": ("opt", item), "*": ("star", item), "+": ("cat", [item, ("star", item)])}[sign]
            parts.append(item)
        return ("cat", parts)

    def atom(self):
        c = self.take()
        if c == "(":
            before = self.fold
            if self.text.startswith("?i:", self.at):
                self.at, self.fold = self.at + 3, True
            inner = self.alternatives()
            self.take()
            self.fold = before
            return inner
        if c == "[":
            return self.members()
        return self.folded({self.byte(c)})

    def byte(self, c: str) -> int:
        if c == "\\":
            c = self.take()
            if c == "x":
                self.at += 2
                return int(self.text[self.at - 2 : self.at], 16)
        return ord(c)

    def members(self):
        negated, found = self.peek() == "^", set()
        if negated:
            self.take()
        while self.peek() != "]":
            low = high = self.byte(self.take())
            if self.peek() == "-" and self.text[self.at + 1] != "]":
                self.take()
                high = self.byte(self.take())
            found |= set(range(low, high + 1))
        self.take()
        return ("set", frozenset(set(range(256)) - found)) if negated else self.folded(found)

    def folded(self, found: set):
        if self.fold:
            found = found | {b ^ 32 for b in found if chr(b).isalpha() and b < 128}
        return ("set", frozenset(found))


def parse(pattern: str):
    return _Parser(pattern).alternatives()


def mirrored(tree):
    kind, inner = tree
    if kind == "set":
        return tree
    if kind == "cat":
        return (kind, [mirrored(t) for t in reversed(inner)])
    return (kind, [mirrored(t) for t in inner]) if kind == "alt" else (kind, mirrored(inner))


class _Graph:
    """States with empty moves and moves on byte sets."""

    def __init__(self):
        self.empty: list[list[int]] = []
        self.moves: list[list[tuple[frozenset, int]]] = []

    def state(self) -> int:
        self.empty.append([])
        self.moves.append([])
        return len(self.empty) - 1

    def add(self, tree, start: int) -> int:
        """Add ``tree`` from ``start``; its end."""
        kind, inner = tree
        if kind == "cat":
            for t in inner:
                start = self.add(t, start)
            return start
        end = self.state()
        if kind == "set":
            self.moves[start].append((inner, end))
        elif kind == "alt":
            for t in inner:
                self.empty[self.add(t, start)].append(end)
        else:
            first = self.state()
            self.empty[start].append(first)
            last = self.add(inner, first)
            self.empty[last] += [end] + [first] * (kind == "star")
            self.empty[start].append(end)
        return end

    def closure(self, states) -> frozenset:
        found, todo = set(states), list(states)
        while todo:
            for t in self.empty[todo.pop()]:
                if t not in found:
                    found.add(t)
                    todo.append(t)
        return frozenset(found)


@dataclass
class Automaton:
    """table[state * n_classes + class_of[byte]] is the next state; accepts[state] has bit k if pattern k ends there."""

    table: np.ndarray
    class_of: np.ndarray
    accepts: np.ndarray
    n_classes: int
    dead: int  # a state that never accepts again, or -1

    def step(self, state: int, byte: int) -> int:
        return int(self.table[state * self.n_classes + int(self.class_of[byte])])


def compile_automaton(trees: list, anchored: bool) -> Automaton:
    """One minimal automaton of all patterns; unless anchored, a match may begin at any byte."""
    graph = _Graph()
    start = graph.state()
    ends: dict[int, int] = {}
    for k, tree in enumerate(trees):
        first = graph.state()
        graph.empty[start].append(first)
        ends[graph.add(tree, first)] = 1 << k
    sets = list({s for moves in graph.moves for s, _ in moves})
    marks = np.array([[b in s for s in sets] for b in range(256)], np.uint8).reshape(256, len(sets))
    _, sample, class_of = np.unique(marks, axis=0, return_index=True, return_inverse=True)
    class_of = class_of.reshape(-1)
    begin = graph.closure([start])
    number, todo, rows = {begin: 0}, [begin], []
    while todo:
        now, row = todo.pop(0), []
        for b in sample:
            to = {t for s in now for members, t in graph.moves[s] if int(b) in members}
            goal = graph.closure(to) if anchored else graph.closure(to) | begin
            if goal not in number:
                number[goal] = len(number)
                todo.append(goal)
            row.append(number[goal])
        rows.append(row)
    table = np.array(rows, np.int64)
    bits = np.array([sum({ends[s] for s in now if s in ends}) for now in number], np.int64)
    # states that no input tells apart become one
    group = np.unique(bits, return_inverse=True)[1]
    while True:
        _, finer = np.unique(np.column_stack([group, group[table]]), axis=0, return_inverse=True)
        finer = finer.reshape(-1)
        if finer.max() == group.max():
            break
        group = finer
    order = np.full(group.max() + 1, -1)
    order[group[::-1]] = np.arange(len(group))[::-1]  # a state of each group
    rename = np.argsort(np.argsort(order))  # the start stays 0
    small = rename[group[table[order[np.argsort(order)]]]]
    small_bits = bits[np.sort(order)]
    loops = (small == np.arange(len(small))[:, None]).all(axis=1) & (small_bits == 0)
    return Automaton(small.astype(np.int32).reshape(-1), class_of.astype(np.uint8), small_bits.astype(np.uint32), table.shape[1], int(np.flatnonzero(loops)[0]) if loops.any() else -1)


class LaneScanner:
    """Runs an automaton over many texts at once, a byte of each lane at a time.

    Texts are cut after byte pairs that lead every state to the same one, so each lane begins in a known state and
    the trace is that of one pass over each text.
    """

    def __init__(self, automaton: Automaton):
        self.a = a = automaton
        table = a.table.reshape(-1, a.n_classes)
        after = table[table]  # [state, first class, second class]
        known = (after == after[0]).all(axis=0)
        self.known, self.state_after = known.reshape(-1), after[0].reshape(-1)

    def trace(self, data: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """The state after each byte of ``data``, which holds texts that begin at ``starts``."""
        a, n = self.a, len(data)
        cls = a.class_of[data]
        pair = cls[:-1].astype(np.int32) * a.n_classes + cls[1:]
        cuts = np.flatnonzero(self.known[pair]) + 2
        if len(cuts):
            near = np.searchsorted(cuts, np.arange(LANE, n, LANE))
            cuts = np.unique(cuts[near[near < len(cuts)]])
            # a pair must lie within one text
            owner = np.searchsorted(starts, cuts - 1, "right") == np.searchsorted(starts, cuts - 2, "right")
            cuts = cuts[owner & (cuts < n)]
        begin = np.concatenate([starts, cuts])
        state = np.concatenate([np.zeros(len(starts), np.int32), self.state_after[pair[cuts - 2]].astype(np.int32) if len(cuts) else np.empty(0, np.int32)])
        begin, first = np.unique(begin, return_index=True)
        state = state[first]
        length = np.diff(np.append(begin, n))
        order = np.argsort(-length, kind="stable")
        begin, state, length = begin[order], state[order], length[order]
        out = np.empty(n, np.uint16)
        live = np.searchsorted(-length, -np.arange(1, (length[0] if len(length) else 0) + 1), "right")
        for t, k in enumerate(live.tolist()):
            at = begin[:k] + t
            state = a.table[state[:k] * a.n_classes + cls[at]]
            out[at] = state
        return out
