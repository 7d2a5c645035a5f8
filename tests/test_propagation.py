"""Propagation on small graphs against closed forms and invariants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from labelflow.functions import sketch as cms
from labelflow.operators import decode, graph, measures
from labelflow.operators.blocks import propagate_blocks
from labelflow.operators.propagate import StateBudgetExceeded, constants, place, propagate, residual_update, step
from labelflow.plans import affine

MU = (0.98, 0.01, 0.01)
SPEC = cms.SketchSpec.create(5, 3, 9)
EDGES = [(0, 1, 1.0), (1, 2, 2.0), (2, 3, 1.0), (3, 4, 1.0), (4, 5, 1.0), (3, 5, 1.0)]
SEEDS = [(0, 0, 1.0), (0, 1, 1.0), (4, 2, 1.0)]
N, M = 7, 3  # node 6 is isolated


@pytest.fixture(scope="module")
def toy(spark):
    edges = spark.createDataFrame(EDGES, "src long, dst long, w double")
    seeds = spark.createDataFrame(SEEDS, "node long, label long, score double")
    return spark.range(N).withColumnRenamed("id", "node"), edges, seeds


def dense(df, key="label", val="score", width=M):
    out = np.zeros((N, width))
    for r in df.collect():
        out[r["node"], r[key]] = r[val]
    return out


def adjacency():
    w = np.zeros((N, N))
    for a, b, x in EDGES:
        w[a, b] += x
        w[b, a] += x
    return w


def matrices():
    a, q, s = adjacency(), np.zeros((N, M)), np.zeros(N)
    for n, l, x in SEEDS:
        q[n, l], s[n] = x, 1
    m = MU[0] * s + MU[1] * a.sum(axis=1) + MU[2]
    return a, q, s, m


def test_one_step_and_limit(toy):
    nodes, edges, seeds = toy
    a, q, s, m = matrices()
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    one = (MU[0] * s[:, None] * q + MU[1] * a @ q) / m[:, None]
    assert np.allclose(dense(propagate(plan, seeds, max_iter=1).scores), one)
    limit = np.linalg.solve(np.diag(m) - MU[1] * a, MU[0] * s[:, None] * q)
    found = propagate(plan, seeds, max_iter=60, tol=1e-9)
    assert np.allclose(dense(found.scores), limit, atol=1e-6)
    assert found.trace[-1]["max_delta"] <= 1e-9


def test_isolated_nodes_keep_prior(toy, spark):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    prior = spark.createDataFrame([(6, 1, 0.5)], "node long, label long, score double")
    assert dense(propagate(plan, seeds, prior, max_iter=2).scores)[6].tolist() == [0, 0.5, 0]
    m = {r["node"]: r["m_vv"] for r in affine.normaliser(graph.symmetrise(edges), seeds, MU, nodes).collect()}
    assert m[6] == pytest.approx(MU[2])


@pytest.mark.parametrize("store,kwargs", [("sketch", {}), ("sketch", {"shard_rows": True}), ("sketch_block", {})])
def test_sketch_commutes_with_every_rule(toy, store, kwargs):
    nodes, edges, seeds = toy
    plans = [affine.modified_adsorption(edges, seeds, MU, nodes)]
    if store == "sketch" and not kwargs:
        plans += [affine.harmonic(edges, seeds), affine.adsorption(edges, seeds, "entropy", nodes), affine.absorbing_walk(edges, seeds, 0.5), affine.restart_walk(edges, seeds, 0.8)]
    for plan in plans:
        exact = propagate(plan, seeds, max_iter=3).scores
        want = dense(cms.encode(exact, "label", "score", ["node"], SPEC), "cell", "val", SPEC.cells)
        got = dense(propagate(plan, seeds, store=store, spec=SPEC, max_iter=3, **kwargs).sketch, "cell", "val", SPEC.cells)
        assert np.allclose(want, got), plan.method


def test_dense_fused_and_salted_agree(toy, spark):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    want = dense(propagate(plan, seeds, max_iter=3).scores)
    assert np.allclose(dense(propagate(plan, seeds, store="exact_dense", labels=M, max_iter=3).scores), want)
    for kernel in ("sliced", "fused", "summarizer"):
        run = propagate_blocks(plan, seeds, labels=M, max_iter=3, kernel=kernel)
        assert np.allclose(dense(run.scores), want), kernel
        arrays = {r["node"]: r["s"] for r in run.blocks.collect()}
        assert all(np.allclose(arrays.get(n, [0] * M), want[n]) for n in range(N))
    fixed = constants(plan, seeds, None, "label", "score")
    placed = place(plan, hub_edges=1)
    assert {r["src"] for r in placed.hubs.collect()} == {1, 2, 3, 4, 5} and placed.hubs.agg(F.max("salts")).first()[0] == 3
    assert np.allclose(dense(step(placed.edges, fixed, seeds, hubs=placed.hubs)), dense(step(plan.edges, fixed, seeds)))
    assert np.allclose(dense(step(plan.edges, fixed, seeds, one_exchange=True)), dense(step(plan.edges, fixed, seeds)))


def test_edges_at_rest_do_not_move(toy, spark):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    fixed, held = constants(plan, seeds, None, "label", "score"), spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for hub_edges in (10**6, 1):
            placed = place(plan, hub_edges=hub_edges)
            twice = step(placed.edges, fixed, step(placed.edges, fixed, seeds, hubs=placed.hubs), hubs=placed.hubs)
            text = twice._jdf.queryExecution().executedPlan().toString().split("\n")
            scans = [i for i, line in enumerate(text) if "lf_edges_" in line]
            assert len(scans) == 2 and all("Bucketed: true" in text[i] for i in scans)
            for i in scans:  # what stands above a scan, up to the join
                above = []
                for line in reversed(text[:i]):
                    above.append(line)
                    if "Join" in line:
                        break
                assert not any("Exchange" in line for line in above), above
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)


def test_old_states_and_edges_are_deleted(toy, spark):
    import os

    from labelflow.session import state_dir

    nodes, edges, seeds = toy
    folder = state_dir(spark).removeprefix("file:")
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    before = set(os.listdir(folder))
    found = propagate(plan, seeds, max_iter=8, cut_every=2).scores
    new = sorted(x.split("-")[0].split("_")[0] for x in set(os.listdir(folder)) - before)
    assert new.count("state") == 1 and "lf" not in new and found.count()


def test_stores_are_chosen_by_expected_entries(spark):
    ring = spark.range(400).select(F.col("id").alias("src"), ((F.col("id") + 1) % 400).alias("dst"), F.lit(1.0).alias("w"))
    own = spark.range(400).select(F.col("id").alias("node"), F.col("id").alias("label"), F.lit(1.0).alias("score"))
    plan = affine.modified_adsorption(ring, own, MU)
    assert propagate(plan, own, store="auto", labels=400, max_iter=2).store == "exact_long"
    few = own.filter("node < 40").withColumn("label", F.col("label") % 2)
    assert propagate(plan, few, store="auto", labels=2, max_iter=9).store == "exact_dense"
    assert propagate(plan, own, store="auto", labels=400, max_iter=9, spec=SPEC).store == "sketch_block"
    assert propagate(plan, own, store="sketch", max_iter=9, spec=SPEC).store == "sketch_block"
    with pytest.raises(Exception, match="keys of a sketch"):
        cms.encode(own.withColumn("label", F.col("label") - 1), "label", "score", ["node"], SPEC).collect()


def test_traces_of_slices(toy):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    a = propagate(plan, seeds, store="sketch", spec=SPEC, max_iter=3, trace=True).trace
    b = propagate(plan, seeds, store="sketch_block", spec=SPEC, max_iter=3, trace=True).trace
    assert [r["state_entries"] for r in a] == [r["state_entries"] for r in b]
    assert np.allclose([r["max_delta"] for r in a[1:]], [r["max_delta"] for r in b[1:]])


def test_controls(toy, spark):
    nodes, edges, seeds = toy
    gold = spark.createDataFrame([(1, 0), (1, 1), (2, 2)], "node long, label long")
    assert measures.random_mrr(gold, 3).first()["mrr"] == pytest.approx(((2 * 1 + 1 * 0.5) / 3 + (1 + 1 / 2 + 1 / 3) / 3) / 2)
    assert measures.random_mrr(gold, 214).first()["mrr"] > 0
    votes = {(r["node"], r["label"]): r["score"] for r in measures.one_hop_votes(edges, seeds).collect()}
    assert votes[1, 0] == 1.0 and votes[2, 0] == 2.0 and votes[3, 2] == 1.0 + 1.0


def test_absorption_by_node(toy, spark):
    nodes, edges, seeds = toy
    lam = spark.createDataFrame([(0, 2.0), (4, 0.5), (2, 1.0)], "node long, lam double")
    y = dense(propagate(affine.absorbing_walk(edges, seeds, lam), seeds, max_iter=1).scores)
    a, q, s, _ = matrices()
    rate = np.array([2.0, 0, 1.0, 0, 0.5, 0, 0])
    total = (rate + a.sum(axis=1))[:, None]
    assert np.allclose(y, np.divide(rate[:, None] * s[:, None] * q + a @ q, total, out=np.zeros((N, M)), where=total > 0))


def test_harmonic_clamps_seeds(toy):
    nodes, edges, seeds = toy
    y = dense(propagate(affine.harmonic(edges, seeds), seeds, max_iter=50).scores)
    assert y[0].tolist() == [1, 1, 0] and y[4].tolist() == [0, 0, 1]
    a = adjacency()
    for v in (1, 2, 3, 5):
        assert np.allclose(y[v], a[v] @ y / a[v].sum(), atol=1e-4)


def test_entropy_probabilities_sum_to_one(toy):
    nodes, edges, seeds = toy
    for r in affine.walk_probabilities(edges, seeds, "entropy", nodes).collect():
        assert r["p_inject"] + r["p_continue"] + r["p_abandon"] == pytest.approx(1)
        assert min(r["p_inject"], r["p_continue"], r["p_abandon"]) >= -1e-12


def test_objective_never_rises_and_rows_stay_bounded(toy):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    totals = []
    for t in range(4):
        y = propagate(plan, seeds, max_iter=t).scores if t else seeds
        totals.append(measures.objective(y, edges, seeds, MU).first()["total"])
        assert measures.row_norm(y).first()["max_norm"] <= 2 + 1e-12
    assert all(b <= a + 1e-12 for a, b in zip(totals, totals[1:]))


def test_decode_equals_full_estimates(toy, spark):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    found = propagate(plan, seeds, store="sketch", spec=SPEC, max_iter=3)
    labels = spark.range(M).select(F.col("id").alias("label"))
    pairs = measures.all_pairs(nodes, M)
    full = {(r["node"], r["label"]): r["estimate"] for r in found.estimate(pairs).collect()}
    high = decode.decode_threshold(found.sketch, labels, SPEC, 1e-4)
    assert {(r["node"], r["label"]): r["estimate"] for r in high.collect()} == {k: v for k, v in full.items() if v >= 1e-4}
    top = decode.decode_topk(found.sketch, labels, SPEC, 1, nodes).collect()
    for r in top:
        assert r["estimate"] == max(v for (n, _), v in full.items() if n == r["node"])
    exact = propagate(plan, seeds, max_iter=3).scores
    want = dense(exact)
    gaps = [v - want[n, l] for (n, l), v in full.items()]
    for chunk in (4096, 2):
        decode._LABELS = chunk
        err = measures.approximation_error(found.sketch, exact, labels, SPEC, 0.01, N).first()
        decode._LABELS = 4096
        assert err["min_over"] == pytest.approx(min(gaps)) and err["max_over"] == pytest.approx(max(gaps))
        assert (err["violations"], err["pairs"]) == (sum(g > 0.01 for g in gaps), N * M)
    gold = spark.createDataFrame([(0, 1), (3, 2), (5, 0)], "node long, label long")
    for ties in ("min", "max", "mean"):
        plain = measures.mrr(spark.createDataFrame([(n, l, v) for (n, l), v in full.items()], "node long, label long, score double"), gold, ties).first()
        assert measures.mrr_sketch(found.sketch, gold, labels, SPEC, ties).first() == plain
    gaps_between = spark.createDataFrame([(0,), (2,)], "label long")
    assert {r["label"] for r in decode.decode_topk(found.sketch, gaps_between, SPEC, 2).collect()} <= {0, 2}
    assert decode.decode_topk(found.sketch, labels.limit(0), SPEC, 2).count() == 0


def test_budget_stops_growth(toy):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    with pytest.raises(StateBudgetExceeded) as e:
        propagate(plan, seeds, max_iter=5, budget=8)
    assert e.value.iteration >= 1
    trace = propagate(plan, seeds, max_iter=3, trace=True).trace
    assert [r["iter"] for r in trace] == [0, 1, 2, 3] and trace[-1]["state_entries"] >= trace[0]["state_entries"]


def test_new_seeds_propagate_alone(toy, spark):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    first, second = seeds.filter("label < 2"), seeds.filter("label = 2")
    a = propagate(plan, first, max_iter=4, init="zero").scores
    both = residual_update(plan, a, second, 4)
    assert np.allclose(dense(both), dense(propagate(plan, seeds, max_iter=4, init="zero").scores))


def test_refusals(toy, spark):
    nodes, edges, seeds = toy
    bad = spark.createDataFrame([(0, 0, -1.0)], "node long, label long, score double")
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    with pytest.raises(Exception, match="not negative"):
        propagate(plan, bad, max_iter=1).scores.collect()
    with pytest.warns(UserWarning):
        affine.modified_adsorption(edges, seeds, (1.0, 1.0, 1.0), nodes)
    with pytest.raises(NotImplementedError):
        affine.squared_loss_only("max-margin propagation")
    with pytest.raises(ValueError):
        affine.assert_substochastic(affine.AffinePlan(spark.createDataFrame([(0, 0.9)], "node long, coef double"), spark.createDataFrame([(1, 0, 0.5)], "src long, dst long, coef double"), spark.createDataFrame([(0, 0.0)], "node long, coef double")))
    affine.assert_substochastic(affine.custom_plan(plan.inject, plan.edges, plan.prior))
    ok = affine.check_assumptions(seeds, MU, edges)
    assert all(ok.values())
    with pytest.raises(ValueError):
        propagate(plan, seeds, store="sketch")
    with pytest.raises(ValueError):
        propagate(plan, seeds, max_iter=1).sketch


def test_no_row_at_a_time_python(toy):
    nodes, edges, seeds = toy
    plan = affine.modified_adsorption(edges, seeds, MU, nodes)
    found = propagate(plan, seeds, store="sketch", spec=SPEC, max_iter=1).sketch
    text = found._jdf.queryExecution().executedPlan().toString()
    assert "BatchEvalPython" not in text and "Python" not in text
