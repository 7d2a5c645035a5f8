"""Propagation by slices of the label axis.

No step mixes labels or cells, so a slice of them iterates by itself. Where a graph's edges fit in a worker, a task
gets all edges (packed) and one slice of the state, runs every step there, and nothing is exchanged between steps.
The edges and the bytes of a slice are checked before; larger graphs take the steps of ``blocks`` or ``propagate``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut

#: Directed edges of a graph that one task may hold, and bytes of one array of a slice's state.
SLICE_EDGES, SLICE_BYTES = 6_000_000, 96 << 20
#: Products of edges and columns that a step makes at once.
_AT_ONCE = 1 << 21


@dataclass
class Sliced:
    """Rows (slice, node, s) of the last state and (slice, iter, entries, delta) of each step."""

    rows: DataFrame
    width: int
    size: int

    def cells(self) -> DataFrame:
        """node, key, val of all entries that aren't 0."""
        flat = self.rows.filter("node is not null").select("node", "slice", F.posexplode("s").alias("at", "val"))
        return flat.filter("val != 0").select("node", (F.col("slice").cast("long") * self.width + F.col("at")).alias("key"), "val")

    def blocks(self) -> DataFrame:
        """node, s: the whole array of each node that has an entry."""
        n = -(-self.size // self.width)
        held = self.rows.filter("node is not null").groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct("slice", "s"))).alias("m"))
        part = lambda i: F.coalesce(F.try_element_at("m", F.lit(i)), F.array_repeat(F.lit(0.0), self.width))
        return held.select("node", F.slice(F.concat(*[part(i) for i in range(n)]), 1, self.size).alias("s"))

    def trace(self) -> list[dict]:
        """iter, state_entries, state_bytes (of the arrays), max_delta."""
        found = self.rows.filter("node is null").groupBy("iter").agg(F.sum("entries").alias("entries"), F.max("delta").alias("delta"), F.sum("bytes").alias("bytes")).orderBy("iter").collect()
        return [{"iter": r["iter"], "state_entries": r["entries"], "state_bytes": r["bytes"], "max_delta": r["delta"]} for r in found]


def fits(edges: int, nodes: int) -> bool:
    """Whether a graph of so many directed edges and nodes can run in slices."""
    return edges <= SLICE_EDGES and 8 * nodes <= SLICE_BYTES


def _packed(edges: DataFrame) -> DataFrame:
    """The edges as binary blobs: sources, destinations, coefficients."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(b.column(i).to_numpy().tobytes() for i in range(3))], pa.binary())], names=["blob"])

    return edges.select("src", "dst", "coef").mapInArrow(run, "blob binary")


def _unpacked(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    parts = [(np.frombuffer(b, np.int64, len(b) // 24), np.frombuffer(b, np.int64, len(b) // 24, len(b) // 3), np.frombuffer(b, np.float64, len(b) // 24, len(b) // 3 * 2)) for b in blobs]
    if not parts:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    return tuple(np.concatenate(x) for x in zip(*parts))


def _step(state: np.ndarray, fixed: np.ndarray, src: np.ndarray, coef: np.ndarray, heads: np.ndarray, goals: np.ndarray) -> np.ndarray:
    """fixed plus, for each goal, the sum of its edges' coefficients times their sources."""
    after, ends = fixed.copy(), np.append(heads[1:], len(src))
    at = 0
    while at < len(goals):
        first = heads[at]
        to = max(at + 1, int(np.searchsorted(ends, first + _AT_ONCE // state.shape[1], "right")))
        pulled = state[src[first : ends[to - 1]]]
        pulled *= coef[first : ends[to - 1], None]
        after[goals[at:to]] += np.add.reduceat(pulled, heads[at:to] - first, axis=0)
        at = to
    return after


def _kernel(width: int, steps: int):
    def run(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        number = (left["slice"] if left.num_rows else right["of"])[0].as_py()
        blobs, counted = left["blob"].to_pylist(), left["counted"].to_pylist()
        src, dst, coef = _unpacked([b for b, c in zip(blobs, counted) if not c])
        sized, _, times = _unpacked([b for b, c in zip(blobs, counted) if c])
        node, place, val = right["node"].to_numpy(), right["key"].to_numpy() - number * width, right["val"].to_numpy()
        names = np.unique(np.concatenate([src, dst, node]))
        order = np.argsort(dst, kind="stable")
        src, dst, coef = np.searchsorted(names, src[order]), dst[order], coef[order]
        heads = np.flatnonzero(np.append(True, dst[1:] != dst[:-1])) if len(dst) else np.empty(0, np.int64)
        goals = np.searchsorted(names, dst[heads])
        state, fixed = np.zeros((len(names), width)), np.zeros((len(names), width))
        row, own = np.searchsorted(names, node), right["fixed"].to_numpy(zero_copy_only=False)
        for into, mine in ((state, ~own), (fixed, own)):
            np.add.at(into, (row[mine], place[mine]), val[mine])
        weight = np.ones(len(names), np.int64)
        known = np.isin(sized, names)
        weight[np.searchsorted(names, sized[known])] = times[known]
        filled = lambda x: int(np.count_nonzero(x, axis=1) @ weight)
        trace = [(0, filled(state), None)]
        for t in range(1, steps + 1):
            after = _step(state, fixed, src, coef, heads, goals)
            trace.append((t, filled(after), float(np.abs(after - state, out=state).max(initial=0))))
            state = after
        kept = np.flatnonzero(state.any(axis=1))
        n, m = len(kept), len(trace)
        flat = pa.array(state[kept].reshape(-1))
        return pa.table({
            "slice": pa.array(np.full(n + m, number), pa.int32()), "node": pa.concat_arrays([pa.array(names[kept], pa.int64()), pa.nulls(m, pa.int64())]),
            "iter": pa.array([None] * n + [t for t, _, _ in trace], pa.int32()), "entries": pa.array([None] * n + [e for _, e, _ in trace], pa.int64()),
            "delta": pa.array([None] * n + [d for _, _, d in trace], pa.float64()), "bytes": pa.array([None] * n + [state.nbytes] * m, pa.int64()),
            "s": pa.concat_arrays([pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * width), flat), pa.nulls(m, pa.list_(pa.float64()))]),
        })

    return run


def run_slices(edges: DataFrame, start: DataFrame, fixed: DataFrame, key: str, val: str, size: int, nodes: int, max_iter: int, sizes: DataFrame | None = None) -> Sliced:
    """All steps of the update from ``start`` with constants ``fixed`` (node, key, val), for keys 0..size-1. Where nodes
    stand for classes, ``sizes`` (node, size) tells how often the trace counts their entries."""
    spark = edges.sparkSession
    tasks = max(4, spark.sparkContext.defaultParallelism)
    width = max(1, min(SLICE_BYTES // (8 * max(nodes, 1)), -(-size // (2 * tasks))))
    n = -(-size // width)
    left = _packed(edges).withColumn("counted", F.lit(False))
    if sizes is not None:
        times = sizes.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.col("size").cast("double").alias("coef"))
        left = left.unionByName(_packed(times).withColumn("counted", F.lit(True)))
    left = left.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    entry = lambda df, flag: df.select("node", F.col(key).cast("long").alias("key"), F.col(val).alias("val"), F.lit(flag).alias("fixed"))
    rows = entry(start, False).unionByName(entry(fixed, True)).withColumn("of", F.floor(F.col("key") / width).cast("int"))
    schema = "slice int, node long, iter int, entries long, delta double, bytes long, s array<double>"
    parts = 4 * n  # so that few slices share a task
    found = left.repartition(parts, "slice").groupBy("slice").cogroup(rows.repartition(parts, "of").groupBy("of")).applyInArrow(_kernel(width, max_iter), schema)
    return Sliced(cut(found, "slices"), width, size)
