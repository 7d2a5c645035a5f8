"""Classes of nodes: runs on them are runs on all nodes."""

import pytest
from pyspark.sql import functions as F

from labelflow.functions.sketch import SketchSpec
from labelflow.operators import measures as ms
from labelflow.operators.blocks import propagate_blocks
from labelflow.operators.lump import lump
from labelflow.operators.propagate import propagate
from labelflow.plans.affine import modified_adsorption

MU = (0.98, 0.01, 0.01)
SPEC = SketchSpec.create(5, 3, 42)


@pytest.fixture(scope="module")
def graph(spark):
    """40 items of 6 kinds by three attributes, one edge of another weight, two items seeded twice."""
    rows = [(i, 100 + i % 2, 1.0) for i in range(40)] + [(i, 110 + i % 3, 1.0) for i in range(40)] + [(7, 120, 2.0), (13, 120, 0.5)]
    edges = spark.createDataFrame(rows, "src long, dst long, w double")
    seeds = spark.createDataFrame([(0, 0, 1.0), (0, 3, 1.0), (1, 1, 1.0), (8, 2, 1.0)], "node long, label long, score double")
    return edges, seeds


def rounded(df, *keys):
    return {tuple(r[k] for k in keys[:-1]): round(r[keys[-1]], 12) for r in df.collect()}


def test_classes_lose_nothing(spark, graph):
    edges, seeds = graph
    plan = modified_adsorption(edges, seeds, MU)
    c = lump(plan, seeds)
    assert c.members.count() == 46 and c.members.select("of").distinct().count() == 17
    for steps in (1, 2, 4):
        whole = propagate(plan, seeds, max_iter=steps).scores
        assert rounded(c.spread(propagate_blocks(c.plan, seeds, labels=4, max_iter=steps).scores), "node", "label", "score") == rounded(whole, "node", "label", "score")
        cells = propagate(plan, seeds, store="sketch_cells", spec=SPEC, max_iter=steps).sketch
        assert rounded(c.spread(propagate_blocks(c.plan, seeds, spec=SPEC, max_iter=steps).sketch), "node", "cell", "val") == rounded(cells, "node", "cell", "val")


def test_traces_and_measures_of_classes_count_all_members(spark, graph):
    edges, seeds = graph
    plan = modified_adsorption(edges, seeds, MU)
    c = lump(plan, seeds)
    run = propagate_blocks(c.plan, seeds, labels=4, max_iter=3, trace=True, sizes=c.sizes)
    whole = propagate(plan, seeds, max_iter=3, trace=True)
    assert [r["state_entries"] for r in run.trace] == [r["state_entries"] for r in whole.trace]
    a = ms.objective(run.scores, c.edges(edges), seeds, MU, sizes=c.sizes).first()
    b = ms.objective(whole.scores, edges, seeds, MU).first()
    assert all(a[k] == pytest.approx(b[k], abs=1e-12) for k in ("fit", "smooth", "prior", "total"))
    labels = spark.range(4).select(F.col("id").alias("label"))
    narrow = SketchSpec.create(2, 1, 42)
    rough = propagate(plan, seeds, store="sketch_block", spec=narrow, max_iter=3)
    few = propagate_blocks(c.plan, seeds, spec=narrow, max_iter=3)
    x = ms.approximation_error(few.blocks, run.scores, labels, narrow, 1e-6, 46, c.sizes).first()
    y = ms.approximation_error(rough.blocks, whole.scores, labels, narrow, 1e-6, 46).first()
    assert x["violations"] == y["violations"] > 20 and x["max_over"] == pytest.approx(y["max_over"])
    gold = spark.range(2, 40).select(F.col("id").alias("node"), (F.col("id") % 4).alias("label"))
    scores = lambda df: df.withColumn("score", F.round("score", 10))
    assert ms.mrr(scores(run.scores), gold, "max", c.members).first() == ms.mrr(scores(whole.scores), gold, "max").first()


def test_entries_are_counted_without_a_state(spark):
    edges = spark.createDataFrame([(i, 100 + i % 3, 1.0) for i in range(20)] + [(i, 110 + i % 4, 1.0) for i in range(15)] + [(4, 120, 1.0)], "src long, dst long, w double")
    seeds = spark.range(22).select(F.col("id").alias("node"), F.col("id").alias("label"), F.lit(1.0).alias("score"))
    plan = modified_adsorption(edges, seeds, MU)
    degree = plan.edges.groupBy("src").count()
    for steps in (0, 1, 2):
        y = seeds if not steps else propagate(plan, seeds, max_iter=steps).scores
        want = ms.work_units(plan.edges, y, 1).first()["exact_ops"]
        got = ms.injected_entries(edges, seeds, steps).agg(F.sum(F.expr("times * entries")).alias("n"), F.sum(F.expr("times * degree * entries")).alias("ops"), F.sum(F.expr("times * degree")).alias("edges")).first()
        assert (got["n"], got["ops"], got["edges"]) == (y.count(), want, degree.agg(F.sum("count")).first()[0])
    with pytest.raises(ValueError):
        ms.injected_entries(edges, seeds.withColumn("label", F.lit(1)), 2)


def test_nearest_vectors_with_copies_and_ties():
    import numpy as np

    from labelflow.sources.graphs import _in_order, _nearest

    draw = np.random.default_rng(3)
    v = draw.integers(-2, 3, (700, 8)).astype(np.float32)
    v[100:160] = v[5]
    v[300] = 0
    ids = draw.permutation(5000)[:700].astype(np.int64)
    src, dst, cos = _nearest(ids, v, ids, v, 5)
    x = v.astype(np.float64)
    norm = np.sqrt(_in_order(x, x))
    with np.errstate(invalid="ignore"):
        for i in (0, 5, 120, 300, 699):
            c = _in_order(np.repeat(x[i : i + 1], 700, axis=0), x) / (norm[i] * norm)
            order = [j for j in np.lexsort((ids, -np.where(np.isnan(c), np.inf, c))) if j != i][:5]
            mine = src == ids[i]
            assert list(dst[mine]) == list(ids[order]) and np.array_equal(cos[mine], c[order], equal_nan=True)


def test_queries_of_seeds_read_the_parts_when_the_task_is_held(spark):
    from conftest import SF
    from labelflow.queries import fixtures as fx
    from labelflow.queries import methods, relational

    fx.parts_kb(spark, SF)
    names = ("block_sketch_roundtrip", "distinct_labels_per_node", "seed_intersection", "seed_sample", "seed_sparsity", "seeds_per_node_list", "sizing_table")
    for name in names:
        df = (relational.Q | methods.Q)[name](spark, SF)
        assert any(f.endswith("/part.parquet") for f in df.inputFiles()), name


def test_pairs_of_near_values_meet_once(spark, duck):
    from conftest import SF
    from labelflow.queries import relational

    df = relational.Q["value_band_edges"](spark, SF)
    assert "Aggregate" not in df._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, df.collect())) == sorted(duck.sql(relational.SQL["value_band_edges"]).fetchall())
