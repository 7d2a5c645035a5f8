"""Secret scan by one deterministic automaton for all rules.

Rule expressions are compiled together by subset construction and minimised into a transition array; each text is
one pass over its bytes, many texts at a time. A rule's match ends where the array says that it accepts; its start
comes from the rule's mirrored automaton, run back from the end. Conditions on lengths are applied to matches, so a
failing match still uses up its text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .automaton import LaneScanner, compile_automaton, mirrored, parse
from .common import id_of, lean, text_of

_SLICE_BYTES = 8 << 20


@dataclass(frozen=True)
class Rule:
    """A match is head then tail; it counts if the tail, or the whole, has enough characters.

    ``tail`` is a repeated byte class, or empty for rules of fixed form.
    """

    kind: str
    head: str
    tail: str
    least_tail: int = 0
    least_whole: int = 0


#: The three base kinds in their stated order, then those that this scanner adds.
BASE = ("assign", "access", "hex")
RULES = (
    Rule("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?""", "[A-Za-z0-9+/_.=\\-]+", least_tail=6),
    Rule("access", "AKIA", "[A-Z0-9]+", least_whole=20),
    Rule("hex", "", "[0-9a-f]+", least_whole=24),
    Rule("forge", "gh[opsur]_", "[A-Za-z0-9]+", least_tail=36),
    Rule("chat", "xox[abprs]-", "[A-Za-z0-9\\-]+", least_tail=10),
    Rule("cloud", "AIza", "[A-Za-z0-9_\\-]+", least_tail=35),
    Rule("webtoken", "eyJ", "[A-Za-z0-9_.\\-]+", least_whole=30),
    Rule("keyblock", "-----BEGIN (RSA |DSA |EC |OPENSSH |PGP )?PRIVATE KEY( BLOCK)?-----", ""),
)


class Scanner:
    """Compiled rules."""

    def __init__(self, rules: tuple[Rule, ...] = RULES):
        self.rules = rules
        trees = [parse(r.head + r.tail) for r in rules]
        self.lanes = LaneScanner(compile_automaton(trees, anchored=False))
        self.back = [compile_automaton([mirrored(t)], anchored=True) for t in trees]
        self.heads = [compile_automaton([parse(r.head)], anchored=True) for r in rules]
        # each accepted byte of a tail is one character of it, so shorter runs can't pass
        fixed = [len(r.head) if r.head.isalnum() else 0 for r in rules]
        self.least_run = [max(1, r.least_tail, r.least_whole - f if f or not r.head else 1) if r.tail else 1 for r, f in zip(rules, fixed)]

    def spans(self, texts: list[bytes]) -> list[list[tuple[int, int, int]]]:
        """(start, rule number, end) in bytes for each text, sorted."""
        out: list[list[tuple[int, int, int]]] = [[] for _ in texts]
        lengths = np.array([len(t) for t in texts], np.int64)
        ends = np.cumsum(lengths)
        data = np.frombuffer(b"".join(texts), np.uint8)
        if not len(data):
            return out
        starts = (ends - lengths)[lengths > 0]
        full = np.flatnonzero(lengths > 0)
        bits = self.lanes.a.accepts[self.lanes.trace(data, starts)]
        for k in range(len(self.rules)):
            at = np.flatnonzero(bits & (1 << k))
            if not len(at):
                continue
            text = full[np.searchsorted(starts, at, "right") - 1]
            new = np.append(True, (np.diff(at) != 1) | (np.diff(text) != 0))
            first = np.flatnonzero(new)
            last = np.append(first[1:], len(at)) - 1
            origin = (ends - lengths)[text[first]]
            stops, owner = at[last] - origin + 1, text[first]
            ready = -1  # runs up to here are decided
            for i in np.flatnonzero(last - first + 1 >= self.least_run[k]).tolist():
                # a failing match before may use up part of this one, and so on back
                j = i
                while j - 1 > ready and owner[j - 1] == owner[i] and self.start(k, texts[owner[j]], int(stops[j]), 0) < stops[j - 1]:
                    j -= 1
                floor = used if ready >= 0 and owner[ready] == owner[i] else 0
                for r in range(j, i + 1):
                    floor = self.match(k, texts[owner[r]], int(stops[r]), floor, out[owner[r]])
                ready, used = i, floor
        for found in out:
            found.sort()
        return out

    def start(self, k: int, text: bytes, end: int, floor: int) -> int:
        """The leftmost start, from ``floor`` on, of a match of rule k that ends at ``end``; ``end`` if none."""
        back, state, start = self.back[k], 0, end
        for i in range(end - 1, floor - 1, -1):
            state = back.step(state, text[i])
            if state == back.dead:
                break
            if back.accepts[state]:
                start = i
        return start

    def match(self, k: int, text: bytes, end: int, floor: int, found: list[tuple[int, int, int]]) -> int:
        """Append the match of rule k that ends at ``end``, if it fulfils the rule; where the next may start."""
        start = self.start(k, text, end, floor)
        if start == end:
            return floor
        head, state, tail_at = self.heads[k], 0, start
        for i in range(start, end):
            state = head.step(state, text[i])
            if state == head.dead:
                break
            if head.accepts[state]:
                tail_at = i + 1
        rule = self.rules[k]
        if end - tail_at >= rule.least_tail and end - start >= rule.least_whole:
            found.append((start, k, end))
        return end


def scan_texts(texts: list[str], scanner: Scanner) -> list[list[tuple[str, int, int]]]:
    """(kind, start, end) in code points for each text, by start, then by the order of rules."""
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    out, i = [], 0
    while i < len(raw):
        j, size = i, 0
        while j < len(raw) and (j == i or size + len(raw[j]) <= _SLICE_BYTES):
            size += len(raw[j])
            j += 1
        for text, data, found in zip(texts[i:j], raw[i:j], scanner.spans(raw[i:j])):
            point = (lambda b: b) if len(text) == len(data) else (lambda b, data=data: len(data[:b].decode("utf-8", "surrogatepass")))
            out.append([(scanner.rules[k].kind, point(a), point(b)) for a, k, b in found])
        i = j
    return out


def find_secrets(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_spans for each row.

    Matches of a kind are the leftmost ones that don't overlap; kinds may overlap each other. Null texts count as
    empty: zero counts, the digest of the empty string, no spans. Repeated rows repeat; an empty table gives an
    empty result; other columns are ignored. Letters beyond ASCII never match.
    """

    scanner = Scanner(rules)  # compiled once; its arrays travel with the task

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = scan_texts(batch.column(1).to_pylist(), scanner)
            written = [[f"{k}:{a}:{b}" for k, a, b in x] for x in found]
            base = [",".join(w for w, (k, _, _) in zip(ws, x) if k in BASE) for ws, x in zip(written, found)]
            counts = [pa.array([sum(k == kind for k, _, _ in x) for x in found], pa.int64()) for kind in BASE]
            digests = pa.array([hashlib.sha256(b.encode()).hexdigest() for b in base], pa.string())
            spans = pa.array([",".join(ws) for ws in written], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, digests, spans, pa.array([len(x) for x in found], pa.int64())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_spans"])

    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_spans long"
    return docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(lean(run), schema)


def redact(docs: DataFrame, *, text_col: str = "text", mask: str = "[SECRET]", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """``docs`` with each found span (overlapping ones joined) replaced by ``mask``; null texts stay null."""
    from pyspark.sql import functions as F

    scanner = Scanner(rules)

    @F.pandas_udf("string")
    def masked(column):
        texts = [t or "" for t in column]
        out = []
        for text, spans in zip(texts, scan_texts(texts, scanner)):
            parts, at = [], 0
            for _, a, b in spans:
                if b > at:
                    parts += [text[at : max(a, at)], mask] if a >= at else []
                    at = b
            out.append("".join(parts) + text[at:])
        return type(column)(out)

    done = F.when(F.col(f"`{text_col}`").isNotNull(), masked(F.col(f"`{text_col}`")))
    return docs.withColumn(text_col, done)
