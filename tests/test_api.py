"""The one-object interface, parity of the Python functions, deletion and size of written states."""

import pytest
from pyspark.sql import functions as F

from labelflow.api import LabelFlow
from labelflow.functions import sql as lf_sql
from labelflow.functions.sketch import SketchSpec, encode, to_block
from labelflow.operators.propagate import StateBudgetExceeded, propagate
from labelflow.plans import affine
from labelflow.queries import methods
from labelflow.session import cut, discard, written_bytes
from labelflow.sources import graphs

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def ring(spark):
    edges = spark.range(60).select(F.col("id").alias("src"), ((F.col("id") + 1) % 60).alias("dst"), F.lit(1.0).alias("w"))
    seeds = spark.createDataFrame([(0, 0, 1.0), (20, 1, 1.0), (40, 2, 1.0)], "node long, label long, score double")
    return edges, seeds


def rows(df):
    return sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r)) for r in df.collect())


def test_flow_equals_its_parts(ring):
    edges, seeds = ring
    flow = LabelFlow(edges.sparkSession).graph(edges).seed(seeds)
    want = propagate(affine.modified_adsorption(edges, seeds), seeds, max_iter=3).scores
    assert rows(flow.plan().run("exact_long", max_iter=3).scores) == rows(want)
    assert rows(flow.run("auto", max_iter=3).scores) == rows(want)
    run = flow.run("sketch", "sparse", max_iter=3)
    assert (run.spec.width, run.spec.depth) == (55, 4)
    exact = {(n, l): s for n, l, s in rows(want)}
    for r in run.estimate(want).collect():
        assert r["estimate"] >= exact[r["node"], r["label"]] - 1e-9
    assert flow.plan("harmonic").run("sketch_cells", (7, 2), max_iter=2).spec.width == 7
    assert flow.spec("zipf", z=2.0).width < flow.spec("sparse").width
    with pytest.raises(NotImplementedError):
        flow.plan("max_margin")
    with pytest.raises(ValueError):
        LabelFlow(edges.sparkSession).plan()
    with pytest.raises(ValueError):
        flow.spec("tail")


def test_budget_stops_before_a_step_that_is_sure_to_exceed_it(spark):
    g = graphs.synthetic_photo(spark, 300, 5)
    own = g.nodes.filter("kind = 'item'").select("node", F.col("node").alias("label"), F.lit(1.0).alias("score"))
    with pytest.raises(StateBudgetExceeded) as e:
        propagate(affine.modified_adsorption(g.edges, own, nodes=g.nodes), own, max_iter=9, budget=20_000)
    assert 1 < e.value.iteration <= 3 and len(e.value.trace) >= e.value.iteration


def test_curves_of_many_labels(spark):
    for r in (methods.Q["few_labels_curve"], methods.Q["many_labels_curve"]):
        found = r(spark, SF).collect()
        exact, sketched = ([x for x in found if x["method"] == m] for m in ("exact", "sketch"))
        assert exact[0]["bytes"] < sketched[0]["bytes"] and exact[-1]["outcome"] == "over budget" and exact[-1]["iter"] <= 5
        assert len({x["bytes"] for x in sketched}) == 1 and sketched[-1]["iter"] in (10, 20)


def test_python_functions_agree(spark):
    spec = SketchSpec.create(5, 3, 2)
    lf_sql.register(spark, spec)
    keys = spark.createDataFrame([(3, 1.5), (9, 2.0)], "key long, val double")
    keys.createOrReplaceTempView("lf_keys")
    spark.udtf.register("py_cells", lf_sql.cells_udtf(spec))
    plain = spark.sql("SELECT key, c.cell, c.val FROM lf_keys, LATERAL lf_cells(key, lf_keys.val) c")
    assert rows(plain) == rows(spark.sql("SELECT key, c.cell, c.val FROM lf_keys, LATERAL py_cells(key, lf_keys.val) c"))
    blocks = to_block(encode(keys.select((F.col("key") % 2).alias("node"), F.col("key").alias("label"), F.col("val").alias("score")), "label", "score", ["node"], spec), ["node"], spec).withColumn("w", F.lit(0.5))
    a, b = lf_sql.vector_sum(blocks, ["node"], "s", F.col("w")), lf_sql.vector_sum_arrow(blocks, "node", "s", "w")
    assert sorted(tuple(r["s"]) for r in a.collect()) == sorted(tuple(r["s"]) for r in b.collect())


def test_written_frames(spark):
    df = cut(spark.range(1000), "bytes")
    assert written_bytes(df) > 1000
    discard(df)
    with pytest.raises(Exception):
        df.count()


def test_bucketed_neighbours_reach_the_recall(spark):
    from labelflow.queries import relational

    assert relational.Q["knn_recall"](spark, SF).first()["recall"] >= 0.9
