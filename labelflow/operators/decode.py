"""From sketches back to labels, without estimating every pair of node and label where that can be helped.

An estimate is the least of a label's cells. A label reaches a threshold only if its cell in each row does, so the top
labels of a node are found with a rising threshold: a label whose cell in some row is no larger than the r-th best
estimate so far is dropped there. Nodes are decoded in Arrow batches of their arrays; only what is asked for leaves
a batch. The cells of a range of labels are computed in place, so nothing that grows with the labels is sent.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.sketch import SketchSpec, cells_of
from .blocks import array_states

#: Labels of a set with gaps that may be sent to workers.
LABELS_SENT = 4_000_000
#: Labels and nodes of which estimates are made at once.
_LABELS, _NODES = 4096, 256


def label_index(labels: DataFrame, spec: SketchSpec) -> DataFrame:
    """cell, label for each label and row."""
    return labels.select("label", F.explode(cells_of(F.col("label"), spec)).alias("cell"))


def label_chunks(labels: DataFrame):
    """A function that yields the labels as ascending arrays. A range without gaps is sent as its ends."""
    low, high, n = labels.agg(F.min("label"), F.max("label"), F.countDistinct("label")).first()
    if not n:
        return lambda: iter(())
    if high - low + 1 == n:
        return lambda: (np.arange(a, min(a + _LABELS, high + 1)) for a in range(low, high + 1, _LABELS))
    if n > LABELS_SENT:
        raise ValueError(f"{n} labels with gaps between them: number them densely first")
    held = np.unique(labels.select("label").toArrow()["label"].to_numpy())
    return lambda: (held[a : a + _LABELS] for a in range(0, len(held), _LABELS))


def cells_at(labels: np.ndarray, spec: SketchSpec) -> np.ndarray:
    """The cells (rows of the sketch x labels)."""
    a, b = (np.array(x, np.int64)[:, None] for x in (spec.a, spec.b))
    return (labels[None, :] * a + b) % spec.prime % spec.width + np.arange(spec.depth)[:, None] * spec.width


def estimates(state: np.ndarray, cells: np.ndarray) -> np.ndarray:
    """nodes x labels from arrays of nodes."""
    out = state[:, cells[0]]
    for row in cells[1:]:
        np.minimum(out, state[:, row], out=out)
    return out


def arrays_of(sketch: DataFrame, spec: SketchSpec) -> DataFrame:
    """node, s of a sketch in cells or array form."""
    return sketch.select("node", "s") if "s" in sketch.columns else array_states(sketch.select("node", "cell", "val"), "cell", "val", spec.cells)


def _batches(batches: Iterator[pa.RecordBatch], size: int, column: int = 1) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
    """Slices of few nodes with their arrays as a matrix."""
    for whole in batches:
        for i in range(0, whole.num_rows, _NODES):
            part = whole.slice(i, _NODES)
            yield part, part.column(column).flatten().to_numpy().reshape(-1, size)


def _best(state: np.ndarray, chunks, spec: SketchSpec, r: int, theta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, label, estimate) of the r largest estimates of each row of at least ``theta``, ties to the smaller label."""
    floor = np.full(len(state), np.nextafter(theta, 0) if theta else 0.0)
    row, label, value = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    for labels in chunks():
        cells = cells_at(labels, spec)
        at, of = np.nonzero(state[:, cells[0]] > floor[:, None])
        least = state[at, cells[0][of]]
        for more in cells[1:]:
            least = np.minimum(least, state[at, more[of]])
            keep = least > floor[at]
            at, of, least = at[keep], of[keep], least[keep]
        row, label, value = np.concatenate([row, at]), np.concatenate([label, labels[of]]), np.concatenate([value, least])
        order = np.lexsort((label, -value, row))
        row, label, value = row[order], label[order], value[order]
        rank = np.arange(len(row)) - np.searchsorted(row, row)
        keep = rank < r
        row, label, value, rank = row[keep], label[keep], value[keep], rank[keep]
        full = rank == r - 1
        floor[row[full]] = np.maximum(floor[row[full]], value[full])
    return row, label, value


def decode_topk(sketch: DataFrame, labels: DataFrame, spec: SketchSpec, r: int, nodes: DataFrame | None = None) -> DataFrame:
    """node, label, estimate, rank: the r labels with the largest positive estimates, ties by label."""
    if nodes is not None:
        sketch = sketch.join(nodes.select("node").distinct(), "node", "left_semi")
    chunks = label_chunks(labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, state in _batches(batches, spec.cells):
            row, label, value = _best(state, chunks, spec, r, 0.0)
            rank = np.arange(len(row)) - np.searchsorted(row, row) + 1
            yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row)), pa.array(label), pa.array(value), pa.array(rank.astype(np.int32))], names=["node", "label", "estimate", "rank"])

    return arrays_of(sketch, spec).mapInArrow(run, "node long, label long, estimate double, rank int")


def decode_threshold(sketch: DataFrame, labels: DataFrame, spec: SketchSpec, theta: float) -> DataFrame:
    """node, label, estimate for all estimates of at least theta > 0."""
    if theta <= 0:
        raise ValueError("theta must be positive: absent cells are 0")
    chunks = label_chunks(labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, state in _batches(batches, spec.cells):
            for labels in chunks():
                row, label, value = _best(state, lambda x=labels: iter((x,)), spec, len(labels), theta)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row)), pa.array(label), pa.array(value)], names=["node", "label", "estimate"])

    return arrays_of(sketch, spec).mapInArrow(run, "node long, label long, estimate double")


def decode_all(sketch: DataFrame, labels: DataFrame, spec: SketchSpec) -> DataFrame:
    """node, label, score: every positive estimate (nodes x labels at most)."""
    return decode_threshold(sketch, labels, spec, 5e-324).withColumnRenamed("estimate", "score")


def rank_gold(sketch: DataFrame, gold: DataFrame, labels: DataFrame, spec: SketchSpec, digits: int | None = None) -> DataFrame:
    """node, label, above, level for gold pairs with a positive estimate: how many labels of the node have larger
    estimates, and how many are at least as large. ``digits`` rounds estimates first. One row leaves for each pair."""
    chunks = label_chunks(labels)
    asked = gold.groupBy(F.col("node").alias("n_")).agg(F.collect_list("label").alias("gold"))
    both = arrays_of(sketch.join(gold.select("node").distinct(), "node", "left_semi"), spec).join(asked, F.col("node") == F.col("n_")).select("node", "s", "gold")

    def rounded(x: np.ndarray) -> np.ndarray:
        return x if digits is None else np.round(x, digits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, state in _batches(batches, spec.cells):
            lists = part.column(2).to_pylist()
            row = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
            label = np.array([x for found in lists for x in found], np.int64)
            cells = cells_at(label, spec)
            own = rounded(state[row, cells].min(axis=0)) if len(row) else np.empty(0)
            above, level = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
            for labels in chunks():
                found = rounded(estimates(state, cells_at(labels, spec)))
                for i in range(0, len(row), _NODES):
                    mine = found[row[i : i + _NODES]]
                    above[i : i + _NODES] += (mine > own[i : i + _NODES, None]).sum(axis=1)
                    level[i : i + _NODES] += (mine >= own[i : i + _NODES, None]).sum(axis=1)
            keep = own > 0
            yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row[keep])), *(pa.array(x[keep]) for x in (label, above, level))], names=["node", "label", "above", "level"])

    return both.mapInArrow(run, "node long, label long, above long, level long")


def pair_errors(sketch: DataFrame, exact: DataFrame, labels: DataFrame, spec: SketchSpec, eps: float, sizes: DataFrame | None = None) -> DataFrame:
    """max_over, min_over, violations over every pair of a node with an entry and a label: estimate less exact score.

    ``exact`` is (node, label, score). Nodes without an entry have no error. A row leaves for each batch of nodes. Where
    nodes stand for classes, ``sizes`` (node, size) tells how often their violations count.
    """
    chunks = label_chunks(labels)
    scores = exact.groupBy(F.col("node").alias("n_")).agg(F.collect_list(F.struct("label", "score")).alias("scores"))
    both = arrays_of(sketch, spec).join(scores, F.col("node") == F.col("n_"), "full")
    zero = F.array_repeat(F.lit(0.0), spec.cells)
    both = both.select(F.coalesce("node", "n_").alias("node"), F.coalesce("s", zero).alias("s"), "scores")
    times = F.lit(1).cast("long")
    if sizes is not None:
        both = both.join(sizes.select(F.col("node").alias("c_"), "size"), F.col("node") == F.col("c_"), "left")
        times = F.coalesce("size", times)
    both = both.select("node", "s", "scores", times.alias("size"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, state in _batches(batches, spec.cells):
            known = part.column(2)
            size, often = np.array([len(x) if x.is_valid else 0 for x in known]), part.column(3).to_numpy()
            row, flat = np.repeat(np.arange(len(size)), size), known.flatten()
            label, score = flat.field("label").to_numpy(), flat.field("score").to_numpy()
            high, low, over = -np.inf, np.inf, 0
            for labels in chunks():
                gap = estimates(state, cells_at(labels, spec))
                inside = np.flatnonzero((label >= labels[0]) & (label <= labels[-1]))
                gap[row[inside], np.searchsorted(labels, label[inside])] -= score[inside]
                high, low, over = max(high, gap.max()), min(low, gap.min()), over + int((gap > eps).sum(axis=1) @ often)
            yield pa.RecordBatch.from_arrays([pa.array([high]), pa.array([low]), pa.array([over])], names=["high", "low", "over"])

    found = both.mapInArrow(run, "high double, low double, over long")
    return found.agg(F.max("high").alias("max_over"), F.min("low").alias("min_over"), F.coalesce(F.sum("over"), F.lit(0)).alias("violations"))
