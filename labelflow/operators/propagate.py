"""Propagation of label scores or sketch cells over an affine plan.

One step is a join of the static edges with the state, scaled, united with constants that were folded before the
loop, and one sum by (node, key). ``key`` is a label for exact propagation and a cell for sketched propagation: the
code is the same, since encoding commutes with the update. Edges rest in buckets by source, those of hubs dealt over
several by a salt, so a step moves the state and the partial sums only. States are cut to the shared folder every few
steps and the ones before deleted, so plans stay short and a lost executor costs no more than those steps.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sketch as cms
from ..functions.sizing import choose_store, expected_entries
from ..functions.sketch import SketchSpec
from ..plans.affine import AffinePlan
from ..session import cut, discard, rest


class StateBudgetExceeded(RuntimeError):
    """The state outgrew its budget, or is sure to in the next step: the controlled stand-in for running out of memory.
    ``entries`` is the size found, or a lower bound."""

    def __init__(self, iteration: int, entries: int, budget: int, trace: list[dict] | None = None):
        super().__init__(f"iteration {iteration}: {entries} entries, budget {budget}")
        self.iteration, self.entries, self.budget, self.trace = iteration, entries, budget, trace or []


@dataclass
class PropagationResult:
    """``scores`` are (node, label, score); a sketch is (node, cell, val). ``trace`` has a row for each iteration, ``blocks``
    (node, s) where the run held arrays."""

    state: DataFrame
    store: str
    spec: SketchSpec | None = None
    trace: list[dict] = field(default_factory=list)
    blocks: DataFrame | None = None

    @property
    def scores(self) -> DataFrame:
        if self.spec is not None:
            raise ValueError("a sketch has estimates, not scores: use estimate or decode")
        return self.state

    @property
    def sketch(self) -> DataFrame:
        if self.spec is None:
            raise ValueError("an exact result has no sketch")
        return self.state

    def estimate(self, pairs: DataFrame) -> DataFrame:
        """node, label, estimate for requested pairs."""
        if self.blocks is not None and self.spec is not None:
            return cms.estimate_arrays(self.blocks, pairs, "label", ["node"], self.spec)
        return cms.estimate(self.sketch, pairs, "label", ["node"], self.spec)


def validate_scores(scores: DataFrame) -> DataFrame:
    """Scores that must not be negative or NaN, or estimates could be too low; raises when the plan runs."""
    ok = (F.col("score") >= 0) & (F.col("score") < F.lit(float("inf")))
    return scores.withColumn("score", F.when(ok, F.col("score")).otherwise(F.raise_error(F.lit("scores must be finite and not negative")).cast("double")))


def constants(plan: AffinePlan, seeds: DataFrame, priors: DataFrame | None, key: str, val: str) -> DataFrame:
    """inject Q + prior R as (node, key, val), summed."""
    parts = plan.inject.join(seeds.select("node", key, val), "node").select("node", key, (F.col("coef") * F.col(val)).alias(val))
    if priors is not None:
        parts = parts.unionByName(plan.prior.join(priors.select("node", key, val), "node").select("node", key, (F.col("coef") * F.col(val)).alias(val)))
    return parts.groupBy("node", key).agg(F.sum(val).alias(val)).filter(F.col(val) != 0)


def met(edges: DataFrame, side: DataFrame, hubs: DataFrame | None = None) -> DataFrame:
    """Edges with the rows (u_, ...) of their sources; with ``hubs`` (src, salts) of :func:`place`, those of hubs go to each
    bucket of their edges."""
    at = F.col("src") == F.col("u_")
    if hubs is not None:
        side = side.join(F.broadcast(hubs.select(F.col("src").alias("h_"), "salts")), F.col("u_") == F.col("h_"), "left")
        side = side.withColumn("s_", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)))
        at &= F.col("salt") == F.col("s_")
    return edges.join(side, at)


def step(edges: DataFrame, fixed: DataFrame, state: DataFrame, key: str = "label", val: str = "score", one_exchange: bool = False, hint: str | None = None, hubs: DataFrame | None = None) -> DataFrame:
    """One update of all nodes. Sums are combined in each task before they move, so a node that is reached by many is
    no hot key; with ``hubs`` (src, salts) of :func:`place`, nor is one that reaches many. ``one_exchange`` places rows
    by node before the sum, so the next join needs no other exchange (and partial sums are given up): better where few
    rows of a task share node and key."""
    side = state.select(F.col("node").alias("u_"), F.col(key).alias("k_"), F.col(val).alias("v_"))
    pulled = met(edges.hint(hint) if hint else edges, side, hubs).select(F.col("dst").alias("node"), F.col("k_").alias(key), (F.col("coef") * F.col("v_")).alias(val))
    rows = pulled.unionByName(fixed.select("node", key, val))
    if one_exchange:
        rows = rows.repartition("node")
    return rows.groupBy("node", key).agg(F.sum(val).alias(val)).filter(F.col(val) != 0)


def least_entries(edges: DataFrame, state: DataFrame) -> int:
    """A lower bound of the next state's entries, without making it: a node gets all labels of each neighbour."""
    return least_after(edges, state.groupBy("node").agg(F.count(F.lit(1)).alias("n")))


def least_after(edges: DataFrame, counts: DataFrame) -> int:
    """As :func:`least_entries`, from the entries of each node (node, n)."""
    own = counts.select(F.col("node").alias("u_"), "n")
    return edges.filter("coef > 0").join(own, F.col("src") == F.col("u_")).groupBy("dst").agg(F.max("n").alias("n")).agg(F.sum("n")).first()[0] or 0


#: A node is a hub if it has over 1 / HUB_SHARE of the edges (there are fewer than HUB_SHARE), and so many at least.
HUB_SHARE, HUB_EDGES = 256, 100_000


def place(plan: AffinePlan, name: str = "edges", hub_edges: int = HUB_EDGES) -> AffinePlan:
    """The plan with its edges at rest in buckets by source, as the static side of all steps; the edges of hubs are
    dealt by (source, salt), with about as many salts as a hub has times the edges that make one."""
    edges = cut(plan.edges.select("src", "dst", "coef"), name)
    limit = max(hub_edges, edges.count() // HUB_SHARE)
    hubs = edges.groupBy("src").count().filter(F.col("count") > limit).select("src", F.ceil(F.col("count") / limit).cast("int").alias("salts"))
    hubs = cut(hubs, "hubs")
    if hubs.limit(1).count():
        found = edges.join(F.broadcast(hubs), "src", "left")
        resting = rest(found.select("src", F.pmod(F.xxhash64("dst"), F.coalesce("salts", F.lit(1))).cast("int").alias("salt"), "dst", "coef"), name, "src", "salt")
    else:
        hubs, resting = None, rest(edges, name, "src")
    discard(edges)
    return AffinePlan(plan.inject, resting, plan.prior, plan.method, True, hubs)


def delta(before: DataFrame, after: DataFrame, key: str = "label", val: str = "score") -> DataFrame:
    """node, key, delta: the change of each entry, absent ones counted as 0."""
    a = before.select("node", key, F.col(val).alias("x"))
    b = after.select("node", key, F.col(val).alias("y"))
    return a.join(b, ["node", key], "full").select("node", key, (F.coalesce("y", F.lit(0.0)) - F.coalesce("x", F.lit(0.0))).alias("delta"))


def propagate(
    plan: AffinePlan, seeds: DataFrame, priors: DataFrame | None = None, *, store: str = "exact_long", spec: SketchSpec | None = None, max_iter: int = 10,
    tol: float | None = None, init: str | DataFrame = "seeds", budget: int | None = None, trace: bool | str = False, cut_every: int = 2, shard_rows: bool = False, labels: int | None = None,
) -> PropagationResult:
    """Iterate ``plan`` from seeds (or zero, or a given state).

    ``store`` is exact_long, exact_dense, sketch (cells, or arrays where a node is expected to fill over a third of
    them), sketch_cells or sketch_block; 'auto' chooses by bytes for each node from the number of ``labels``, the size of
    ``spec`` and the entries that the graph's degrees let expect. ``tol`` ends the loop when no entry moves more; ``budget``
    is the most entries a state may have. A ``trace`` of 'entries' leaves out how far entries moved. ``shard_rows`` runs each
    sketch row by itself, with 1/depth of the state at once.
    """
    seeds = validate_scores(seeds.select("node", "label", "score"))
    plain = tol is None and budget is None and not trace and not shard_rows and isinstance(init, str)
    if store == "auto" or store == "sketch" and plain and spec is not None:
        plan = replace(plan, edges=cut(plan.edges, "edges"))
        size = plan.edges.agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("src").alias("nodes")).first()
        mass = seeds.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("label").alias("labels")).first()
        m = labels or mass["labels"]
        each = expected_entries(size["nodes"], size["edges"], mass["n"], m, max_iter)
        if store == "auto":
            store = choose_store(m, spec.cells if spec else 1 << 40, each)
        if store == "sketch" and plain:
            store = "sketch_block" if 3 * min(spec.cells, spec.depth * each) > spec.cells else "sketch_cells"
    store = "sketch" if store == "sketch_cells" else store
    if store in ("exact_dense", "sketch_block"):
        from .blocks import propagate_blocks

        return propagate_blocks(plan, seeds, priors, spec=spec if store == "sketch_block" else None, labels=labels, max_iter=max_iter, init=init, trace=trace)
    if store == "exact_long":
        return _loop(plan, seeds, priors, "label", "score", None, store, max_iter, tol, init, budget, trace, cut_every)
    if spec is None:
        raise ValueError("a sketched run needs a spec")
    if not shard_rows:
        code = lambda df: cms.encode(df, "label", "score", ["node"], spec)
        return _loop(plan, code(seeds), code(priors) if priors is not None else None, "cell", "val", spec, store, max_iter, tol, init, budget, trace, cut_every)
    placed, rows = place(plan), []
    for j in range(spec.depth):
        one = spec.row(j)
        code = lambda df, one=one: cms.encode(df, "label", "score", ["node"], one)
        found = _loop(placed, code(seeds), code(priors) if priors is not None else None, "cell", "val", one, store, max_iter, tol, init, budget, False, cut_every)
        rows.append(found.state.select("node", (F.col("cell") + j * spec.width).cast("int").alias("cell"), "val"))
    state = rows[0]
    for r in rows[1:]:
        state = state.unionByName(r)
    return PropagationResult(state, store, spec)


def _loop(plan, seeds, priors, key, val, spec, store, max_iter, tol, init, budget, trace, cut_every) -> PropagationResult:
    fixed = cut(constants(plan, seeds, priors, key, val), "constants")
    placed = plan if plan.at_rest or max_iter < 2 else place(plan)
    if isinstance(init, DataFrame):
        state = init.select("node", key, val)
    else:
        state = seeds.select("node", key, val) if init == "seeds" else fixed.limit(0).select("node", key, val)
    rows, size, written = [], 16, None
    watch = trace or budget is not None or tol is not None
    if watch:
        state = written = cut(state, "state")
        entries = state.count()
        rows.append({"iter": 0, "state_entries": entries, "state_bytes": entries * size, "seconds": 0.0, "max_delta": None})
    try:
        for t in range(1, max_iter + 1):
            began = time.time()
            if budget is not None and (least := least_entries(placed.edges, state)) > budget:
                raise StateBudgetExceeded(t, least, budget, rows)
            after = step(placed.edges, fixed, state, key, val, hubs=placed.hubs)
            if watch or t % cut_every == 0 or t == max_iter > 1:
                after = cut(after, "state")
            if watch:
                entries = after.count()
                moved = delta(state, after, key, val).agg(F.max(F.abs("delta"))).first()[0] or 0.0 if trace is True or tol is not None else None
                rows.append({"iter": t, "state_entries": entries, "state_bytes": entries * size, "seconds": time.time() - began, "max_delta": moved})
                if budget is not None and entries > budget:
                    raise StateBudgetExceeded(t, entries, budget, rows)
            if watch or t % cut_every == 0 or t == max_iter > 1:
                discard(written)
                written = after
            state = after
            if tol is not None and rows[-1]["max_delta"] <= tol:
                break
    finally:
        if placed is not plan:
            discard(placed.edges)
    return PropagationResult(state, store, spec, rows)


def residual_update(plan: AffinePlan, state: DataFrame, new_seeds: DataFrame, max_iter: int = 10, key: str = "label", val: str = "score") -> DataFrame:
    """The state after seeds were added: the update is affine, so the new seeds' contribution propagates alone from
    zero and is added. The plan must be that of the new seed set's nodes (their inject coefficients)."""
    extra = _loop(plan, new_seeds.select("node", key, val), None, key, val, None, "exact_long", max_iter, None, "zero", None, False, 2)
    both = state.select("node", key, val).unionByName(extra.state.select("node", key, val))
    return both.groupBy("node", key).agg(F.sum(val).alias(val))
