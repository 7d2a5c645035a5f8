"""Benchmark decontamination: near copies of benchmark items by edit distance over words.

The CGK random walk turns edit distance into Hamming distance: a pointer runs over a sequence, writes the word it
points at for each of 3n steps, and moves on when a random bit of (step, word) says so; two sequences under the same
bits fall into step again soon after an edit. Repeated bit sampling of the written words is then a locality
sensitive hash. Item-sized windows of a document look their keys up in the items' tables, and each hit is verified
by the exact edit distance. The number of tables is chosen by simulating edits of the items at the threshold until
the target recall is met.

Windows are embedded where the document has runs of q words of an item, at the offset that lines them up. That
loses nothing: with d edits among n words, n - q + 1 - q d runs of q words stay on diagonals at most 2 d apart, so
a window needs as many, and q is taken so that this is positive at the threshold. All documents and all words are read; the items are the only thing sent to workers.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import ROW, id_of, lean, slices, text_of, with_row_key, without_ids
from .words import NOT_ALNUM, KeyTable, gram_keys, keys_by_text, mix

#: Most words of benchmark items that are sent to workers at once; larger sets go in several blocks of items.
BLOCK_WORDS = 2_000_000
_PAD = np.uint64(0x5851F42D4C957F2D)


def allowed_edits(n: int, similarity: float) -> int:
    return math.floor((1 - similarity) * n + 1e-9)


def run_length(n: int, edits: int, most: int = 3) -> int:
    """The longest run q <= most of which one is sure to survive the edits."""
    return next((q for q in range(min(most, n), 0, -1) if n - q + 1 - q * edits > 0), 1)


def text_words(texts: list[str]) -> list[np.ndarray]:
    """Word keys of each text: runs of letters and digits, lower-cased."""
    return keys_by_text([t.lower().encode("utf-8", "surrogatepass") for t in texts], NOT_ALNUM)


def cgk(words: np.ndarray, starts: np.ndarray, lengths: np.ndarray, walk: int) -> np.ndarray:
    """The embeddings (rows: sequences of ``words``; columns: 3 x the longest steps), all under the same bits."""
    steps = 3 * int(lengths.max(initial=0))
    out = np.full((len(starts), steps), _PAD, np.uint64)
    at = np.zeros(len(starts), np.int64)
    salt = mix(np.arange(1, steps + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(walk * 7919 + 1))
    last = len(words) - 1
    for j in range(steps):
        live = (at < lengths) & (j < 3 * lengths)
        word = np.where(live, words[np.minimum(starts + at, last)], _PAD)
        out[:, j] = word
        at += live & ((mix(word ^ salt[j]) >> np.uint64(40)) & np.uint64(1)).astype(bool)
    return out


def sample_keys(embedded: np.ndarray, lengths: np.ndarray, walk: int, table: int, bits: int) -> np.ndarray:
    """A table's key of each embedding: some of its positions (the same for all of a length), and the length."""
    draw = np.random.default_rng((walk, table)).random(bits)
    at = (draw[None, :] * (3 * lengths[:, None])).astype(np.int64)
    picked = np.take_along_axis(embedded, at, axis=1)
    key = mix(lengths.astype(np.uint64) + np.uint64(1 + 64 * walk + table))
    for k in range(bits):
        key = mix(key ^ picked[:, k])
    return key


def substring_distance(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """The least edit distance of ``item`` to a part of ``text``, and that part: (distance, from, to)."""
    n = len(text)
    cost, begin = np.zeros(n + 1, np.int64), np.arange(n + 1)
    ramp = np.arange(n + 1)
    for i, word in enumerate(item, 1):
        best = cost + 1
        came = begin.copy()
        diagonal = cost[:-1] + (text != word)
        better = diagonal <= best[1:]
        best[1:][better] = diagonal[better]
        came[1:][better] = begin[:-1][better]
        # insertions: the least of what lies to the left plus the way from there
        slope = best - ramp
        low = np.minimum.accumulate(slope)
        source = np.maximum.accumulate(np.where(slope == low, ramp, 0))
        cost, begin = low + ramp, came[source]
    end = int(cost.argmin())
    return int(cost[end]), int(begin[end]), end


@dataclass
class Benchmark:
    """Items as word keys, their runs, and their LSH tables."""

    ids: list[int]
    words: list[np.ndarray]
    similarity: float = 0.8
    recall: float = 0.99
    bits: int = 3
    walks: int = 4
    tables: int = field(init=False)

    def __post_init__(self):
        keep = [i for i, w in enumerate(self.words) if len(w)]
        self.ids, self.words = [self.ids[i] for i in keep], [self.words[i] for i in keep]
        self.edits = [allowed_edits(len(w), self.similarity) for w in self.words]
        runs = [run_length(len(w), d) for w, d in zip(self.words, self.edits)]
        self.sizes = sorted(set(runs))
        self.runs = {}
        for q in self.sizes:
            keys, item, offset = [], [], []
            for i, (w, r) in enumerate(zip(self.words, runs)):
                if r == q:
                    k = gram_keys(w, q)
                    keys.append(k)
                    item += [i] * len(k)
                    offset += range(len(k))
            keys = np.concatenate(keys)
            order = np.argsort(keys, kind="stable")
            found, first = np.unique(keys[order], return_index=True)
            self.runs[q] = (KeyTable(found), np.append(first, len(keys)), np.array(item)[order], np.array(offset)[order], _filter(found))
        self.flat = np.concatenate(self.words) if self.words else np.empty(0, np.uint64)
        self.lengths = np.array([len(w) for w in self.words], np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.tables = self._needed() if self.words else 1
        self.lsh = []
        for walk in range(self.walks):
            embedded = cgk(self.flat, self.starts, self.lengths, walk)
            for t in range(self.tables):
                keys = sample_keys(embedded, self.lengths, walk, t, self.bits)
                order = np.argsort(keys, kind="stable")
                self.lsh.append((walk, t, keys[order], order))

    def _needed(self) -> int:
        """Tables for each walk: enough that edited items, simulated at the threshold, reach the target recall."""
        rng = np.random.default_rng(5)
        pairs = []
        for i in rng.integers(0, len(self.words), 400):
            w = list(self.words[i])
            for _ in range(self.edits[i]):
                at, kind = int(rng.integers(0, len(w) + 1)), int(rng.integers(0, 3))
                new = np.uint64(rng.integers(1, 1 << 62))
                w[at : at + (kind != 0)] = [] if kind == 2 else [new]
            w = (w + [np.uint64(rng.integers(1, 1 << 62)) for _ in range(len(self.words[i]))])[: len(self.words[i])]
            pairs.append((self.words[i], np.array(w, np.uint64)))
        flat = np.concatenate([x for p in pairs for x in p])
        lengths = np.array([len(x) for p in pairs for x in p], np.int64)
        starts = np.cumsum(lengths) - lengths
        same = [(lambda e: e[::2] == e[1::2])(cgk(flat, starts, lengths, w)) for w in range(self.walks)]
        hit, own = np.zeros(len(pairs), bool), lengths[::2]
        for t in range(4096):
            for walk in range(self.walks):
                at = (np.random.default_rng((walk, t)).random(self.bits)[None, :] * (3 * own[:, None])).astype(np.int64)
                hit |= np.take_along_axis(same[walk], at, axis=1).all(axis=1)
            if hit.mean() >= self.recall:
                return t + 1
        raise ValueError(f"{self.recall} of the simulated edits aren't met by 4096 tables a walk: take fewer bits, more walks or a higher similarity")

    def find(self, texts: list[str]) -> list[tuple[int, int, int, int, int]]:
        """(text, item, distance, from, to) in words, the best place of each item in each text that reaches the threshold."""
        out = []
        if not self.words:
            return out
        docs = text_words(texts)
        sizes = np.array([len(d) for d in docs], np.int64)
        ends = np.cumsum(sizes)
        flat = np.concatenate(docs) if docs else np.empty(0, np.uint64)
        lanes = []
        for q in self.sizes:
            if len(flat) < q:
                continue
            grams = gram_keys(flat, q)
            table, first, item, offset, quick = self.runs[q]
            near = np.flatnonzero(quick[(grams >> np.uint64(44)).astype(np.int64)])
            row = table.find(grams[near])
            near, row = near[row >= 0], row[row >= 0]
            doc = np.searchsorted(ends, near, "right")
            inside = near + q <= ends[doc]
            near, row, doc = near[inside], row[inside], doc[inside]
            n = first[row + 1] - first[row]
            each = np.repeat(first[row], n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            lanes.append(self._dense(np.repeat(doc, n), np.repeat(near, n) - offset[each], item[each], q))
        if not lanes:
            return out
        lanes = np.unique(np.concatenate(lanes), axis=0)
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        for i in range(0, len(lanes), 20_000):
            self._look_up(lanes[i : i + 20_000], flat, docs, ends - sizes, sizes, best)
        return [(d, i, *v) for (d, i), v in sorted(best.items())]

    def _dense(self, doc: np.ndarray, at: np.ndarray, item: np.ndarray, q: int) -> np.ndarray:
        """(text, window start, words) where an item has as many runs on near diagonals as are sure to survive."""
        order = np.lexsort((at, item, doc))
        doc, at, item = doc[order], at[order], item[order]
        slack = np.array(self.edits, np.int64)[item]
        need = self.lengths[item] - q + 1 - q * slack
        new = np.append(True, (np.diff(doc) != 0) | (np.diff(item) != 0)) if len(doc) else np.empty(0, bool)
        reach = int(at.max(initial=0)) + 4 * int(self.lengths.max()) + 2
        place = np.cumsum(new) * reach + at + int(self.lengths.max())
        upto = np.searchsorted(place, place + 2 * slack, "right")
        enough = np.flatnonzero(upto - np.arange(len(at)) >= need)
        edge = np.bincount(enough, minlength=len(at) + 1) - np.bincount(upto[enough], minlength=len(at) + 1)
        keep = np.cumsum(edge)[: len(at)] > 0
        return np.column_stack([doc[keep], at[keep], self.lengths[item[keep]]])

    def _look_up(self, lanes, flat, docs, begins, sizes, best) -> None:
        doc, at, length = lanes.T
        # a window that would begin before its text begins there
        at = np.maximum(at, begins[doc])
        pairs = set()
        for walk in range(self.walks):
            inside = np.minimum(length, begins[doc] + sizes[doc] - at)
            embedded = cgk(flat, at, inside, walk)
            full = np.full((len(at), 3 * int(length.max(initial=0))), _PAD, np.uint64)
            full[:, : embedded.shape[1]] = embedded
            for w, t, keys, order in self.lsh:
                if w == walk:
                    mine = sample_keys(full, length, w, t, self.bits)
                    low, high = np.searchsorted(keys, mine, "left"), np.searchsorted(keys, mine, "right")
                    for lane in np.flatnonzero(high > low).tolist():
                        pairs.update((lane, int(i)) for i in order[low[lane] : high[lane]])
        ranges: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for lane, i in sorted(pairs):
            d, slack, n = int(doc[lane]), self.edits[i], len(self.words[i])
            start = int(at[lane] - begins[d])
            if n == length[lane] and best.get((d, i), (1,))[0]:
                if start + n <= len(docs[d]) and (docs[d][start : start + n] == self.words[i]).all():
                    best[d, i] = (0, start, start + n)
                else:
                    ranges.setdefault((d, i), []).append((max(0, start - slack), min(len(docs[d]), start + n + slack)))
        for (d, i), spans in ranges.items():
            if best.get((d, i), (1,))[0] == 0:
                continue
            joined: list[list[int]] = []
            for low, high in sorted(spans):
                if joined and low <= joined[-1][1]:
                    joined[-1][1] = max(high, joined[-1][1])
                else:
                    joined.append([low, high])
            for low, high in joined:
                cost, a, b = substring_distance(self.words[i], docs[d][low:high])
                if cost <= self.edits[i]:
                    best[d, i] = min(best.get((d, i), (1 << 30,)), (cost, low + a, low + b))


def _filter(keys: np.ndarray) -> np.ndarray:
    """One bit for each value of the upper 20 bits."""
    out = np.zeros(1 << 20, bool)
    out[(keys >> np.uint64(44)).astype(np.int64)] = True
    return out


def find_leaks(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", similarity: float = 0.8, recall: float = 0.99, block_words: int = BLOCK_WORDS) -> DataFrame:
    """doc_id, item_id, distance, similarity, start_word, end_word: one row for each document row and item it holds.

    An item is held if its words can be turned into a part of the document by at most (1 - similarity) x its words
    edits. Words are runs of letters and digits, lower-cased, so case, punctuation and spacing don't matter. The
    best place counts, then the first. Items and documents without words (null, empty) hold nothing; repeated rows
    and items give rows of their own; empty tables give an empty result.
    """
    rows = docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text"))
    items = benchmark.select(id_of(item_col).alias("item_id"), text_of(item_text_col).alias("text"))
    out = None
    for block in _blocks(items, block_words):
        ids, texts = block
        bench = Benchmark(list(range(len(ids))), text_words(texts), similarity, recall)

        def run(batches: Iterator[pa.RecordBatch], bench=bench, ids=ids) -> Iterator[pa.RecordBatch]:
            for batch in (part for whole in batches for part in slices(whole, 1, 2 << 20)):
                of, found = batch.column(0).to_pylist(), bench.find(batch.column(1).to_pylist())
                n = [len(bench.words[k]) for _, k, *_ in found]
                columns = [
                    pa.array([of[d] for d, *_ in found], pa.int64()), pa.array([ids[bench.ids[k]] for _, k, *_ in found], pa.int64()),
                    pa.array([x[2] for x in found], pa.int64()), pa.array([1 - x[2] / m for x, m in zip(found, n)], pa.float64()),
                    pa.array([x[3] for x in found], pa.int64()), pa.array([x[4] for x in found], pa.int64()),
                ]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "item_id", "distance", "similarity", "start_word", "end_word"])

        part = rows.mapInArrow(lean(run), "doc_id long, item_id long, distance long, similarity double, start_word long, end_word long")
        out = part if out is None else out.unionByName(part)
    return out


def _blocks(items: DataFrame, block_words: int) -> Iterator[tuple[list, list[str]]]:
    """The items in blocks of a bounded number of words, read a partition at a time; one empty block if none."""
    ids, texts, held, any_yet = [], [], 0, False
    for row in items.toLocalIterator():
        ids.append(row["item_id"])
        texts.append(row["text"])
        held += row["text"].count(" ") + 1
        if held >= block_words:
            yield ids, texts
            ids, texts, held, any_yet = [], [], 0, True
    if ids or not any_yet:
        yield ids, texts


def drop_leaks(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that hold no item, with all their columns; rows of one id are judged on their own."""
    rows = with_row_key(docs, id_col, text_col)
    leaks = find_leaks(rows, benchmark, id_col=ROW, text_col=text_col, **options)
    return without_ids(rows, leaks.select("doc_id"), ROW).drop(ROW)
