"""Propagation on array states: one array of doubles for each node, of all labels (dense) or of sketch cells.

``sliced`` runs slices of the arrays through all steps without exchanges, where the edges fit in a worker (see
``slices``); it is taken wherever it fits, else ``fused``. ``summarizer`` sums weighted vectors by the JVM aggregate of the machine-learning library: one exchange a step, with
partial sums. ``fused`` is an Arrow kernel for the dense regime: a task holds a block of nodes with their out-edges,
adds what arrived, and emits for each destination one partial sum, tagged with the destination's block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sketch as cms
from ..functions.sketch import SketchSpec
from ..plans.affine import AffinePlan
from ..session import cut, discard
from .propagate import PropagationResult, constants
from .slices import fits, run_slices


def array_states(rows: DataFrame, key: str, val: str, size: int) -> DataFrame:
    """node, s (an array of ``size``) from (node, key, val) with keys 0..size-1; arrays are filled over Arrow batches."""

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, step):
                batch = whole.slice(i, step)
                entries = batch.column(1)
                flat = entries.flatten()
                out = np.zeros((batch.num_rows, size))
                owner = np.repeat(np.arange(batch.num_rows), pc.list_value_length(entries).to_numpy(zero_copy_only=False))
                out[owner, flat.field("k").to_numpy()] = flat.field("v").to_numpy()
                yield pa.RecordBatch.from_arrays([batch.column(0), _lists(out)], names=["node", "s"])

    step = max(1, (8 << 20) // (8 * size))
    grouped = rows.groupBy("node").agg(F.collect_list(F.struct(F.col(key).cast("int").alias("k"), F.col(val).alias("v"))).alias("e"))
    return grouped.mapInArrow(fill, "node long, s array<double>")


def _lists(values: np.ndarray) -> pa.ListArray:
    n, size = values.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * size), pa.array(values.reshape(-1)))


def block_step(edges: DataFrame, fixed: DataFrame, state: DataFrame) -> DataFrame:
    """One update by the JVM aggregate."""
    from pyspark.ml.functions import array_to_vector, vector_to_array
    from pyspark.ml.stat import Summarizer

    side = state.select(F.col("node").alias("u_"), "s")
    pulled = edges.filter("coef > 0").join(side, F.col("src") == F.col("u_")).select(F.col("dst").alias("node"), "coef", "s")
    rows = pulled.unionByName(fixed.select("node", F.lit(1.0).alias("coef"), "s"))
    return rows.groupBy("node").agg(vector_to_array(Summarizer.sum(array_to_vector(F.col("s")), F.col("coef"))).alias("s"))


def _matrix(column: pa.ChunkedArray | pa.Array, size: int) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy().reshape(-1, size) if len(flat) else np.zeros((0, size))


def fused_step(edges: DataFrame, parts: DataFrame, size: int, n_blocks: int) -> DataFrame:
    """One step on partials (blk, node, s): the sums of each node's partials, pushed along its out-edges (blk, src, dst,
    coef), as partials of the destinations. Edges keep their block, so only partials are exchanged."""

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        node = left.column("node").to_numpy()
        values = _matrix(left.column("s"), size)
        names, where = np.unique(node, return_inverse=True)
        total = np.zeros((len(names), size))
        np.add.at(total, where, values)
        src, dst, coef = (right.column(c).to_numpy() for c in ("src", "dst", "coef"))
        at = np.searchsorted(names, src).clip(0, max(len(names) - 1, 0))
        have = (names[at] == src) if len(names) else np.zeros(len(src), bool)
        order = np.flatnonzero(have)[np.argsort(dst[have], kind="stable")]
        goal, first = np.unique(dst[order], return_index=True)
        out = np.zeros((len(goal), size))
        bounds = np.append(first, len(order))
        for i in range(len(goal)):
            e = order[bounds[i] : bounds[i + 1]]
            out[i] = coef[e] @ total[at[e]]
        blk = (goal % n_blocks).astype(np.int64)
        return pa.table({"blk": blk, "node": goal, "s": _lists(out)})

    return parts.groupBy("blk").cogroup(edges.groupBy("blk")).applyInArrow(kernel, "blk long, node long, s array<double>")


#: Bytes of arrays that one block of the fused kernel may hold.
BLOCK_BYTES = 128 << 20


def propagate_blocks(
    plan: AffinePlan, seeds: DataFrame, priors: DataFrame | None = None, *, spec: SketchSpec | None = None, labels: int | None = None, max_iter: int = 10, kernel: str = "auto",
    n_blocks: int | None = None, init: str = "seeds", trace: bool = False, sizes: DataFrame | None = None,
) -> PropagationResult:
    """As :func:`propagate.propagate`, with an array for each node; the result is in long or cells form, its ``blocks``
    in array form. ``sizes`` (node, size) of classes (see ``lump``) make a trace count the entries of all members.

    ``labels`` is the number of labels of a dense run. ``kernel`` is sliced, fused, summarizer or auto: sliced if the
    edges fit in a worker, else fused. A trace needs the sliced kernel.
    """
    key, val = ("label", "score") if spec is None else ("cell", "val")
    if spec is not None:
        seeds = cms.encode(seeds, "label", "score", ["node"], spec)
        priors = cms.encode(priors, "label", "score", ["node"], spec) if priors is not None else None
    size = spec.cells if spec is not None else labels or (seeds.agg(F.max("label")).first()[0] or 0) + 1
    fixed = cut(constants(plan, seeds, priors, key, val), "constants")
    edges = cut(plan.edges.filter("coef > 0"), "edges")
    start = seeds.select("node", key, val) if init == "seeds" else fixed.limit(0).select("node", key, val)
    found, store = [], "exact_dense" if spec is None else "sketch_block"
    nodes = edges.select("src").distinct().count() if kernel in ("auto", "fused") else 0
    if kernel == "auto":
        kernel = "sliced" if fits(edges.count(), nodes) else "fused"
    if kernel == "sliced":
        nodes = nodes or edges.select("src").distinct().count()
        run = run_slices(edges, start, fixed, key, val, size, nodes, max_iter, sizes)
        cells = run.cells().select("node", F.col("key").cast("long" if spec is None else "int").alias(key), F.col("val").alias(val))
        return PropagationResult(cells, store, spec, run.trace() if trace else [], run.blocks())
    if trace:
        raise ValueError("a trace of array states needs the sliced kernel")
    fixed, state = cut(array_states(fixed, key, val, size), "constants"), array_states(start, key, val, size)
    if kernel == "fused":
        n = n_blocks or max(4, int(fixed.sparkSession.conf.get("spark.sql.shuffle.partitions")), 8 * size * nodes // BLOCK_BYTES + 1)
        dealt = cut(edges.withColumn("blk", F.pmod(F.col("src"), F.lit(n)).cast("long")).repartition(n, "blk"), "edges")
        part = lambda df: df.select(F.pmod(F.col("node"), F.lit(n)).cast("long").alias("blk"), "node", "s")
        flow = part(state)
        for _ in range(max_iter):
            found.append(flow)
            flow = cut(fused_step(dealt, flow, size, n).unionByName(part(fixed)), "partials")
            discard(found[-1])
        state = block_step(edges.limit(0), flow, state.limit(0))
    else:
        for t in range(1, max_iter + 1):
            state = block_step(edges, fixed, state)
            if t % 2 == 0 and t < max_iter:
                found.append(state := cut(state, "state"))
    state = cut(state, "state")
    for old in found:
        discard(old)
    cells = cms.to_cells(state, ["node"])
    if spec is None:
        cells = cells.select("node", F.col("cell").cast("long").alias("label"), F.col("val").alias("score"))
    return PropagationResult(cells, store, spec, [], state)
