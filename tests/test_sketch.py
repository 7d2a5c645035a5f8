"""Count-min sketches, sizing rules, SQL functions."""

import math

import pytest
from pyspark.sql import functions as F

from labelflow.functions import sizing
from labelflow.functions import sketch as cms
from labelflow.functions.sql import register, vector_sum

SPEC = cms.SketchSpec.create(7, 3, 5)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def vector(spark):
    return spark.createDataFrame([(n, k, float((n + 1) * (k % 5))) for n in range(3) for k in range(20)], "node long, label long, score double")


def test_cells_match_plain_arithmetic(spark, vector):
    want = {}
    for n, k, v in vector.collect():
        for j in range(SPEC.depth):
            c = SPEC.cell_index(k, j)
            want[n, c] = want.get((n, c), 0) + v
    got = {(r["node"], r["cell"]): r["val"] for r in cms.encode(vector, "label", "score", ["node"], SPEC).collect()}
    assert got == {k: v for k, v in want.items() if v}


def test_estimates_never_below_and_exact_without_collisions(spark, vector):
    s = cms.encode(vector, "label", "score", ["node"], SPEC)
    for r in cms.estimate(s, vector, "label", ["node"], SPEC).join(vector, ["node", "label"]).collect():
        assert r["estimate"] >= r["score"] - 1e-12
    wide = cms.SketchSpec(1000, 2, 0, cms.PRIME, (1, 1), (0, 3))
    s = cms.encode(vector, "label", "score", ["node"], wide)
    assert all(r["estimate"] == r["score"] for r in cms.estimate(s, vector, "label", ["node"], wide).join(vector, ["node", "label"]).collect())


def test_one_cell_holds_all_mass(spark, vector):
    one = cms.SketchSpec.create(1, 2, 1)
    s = cms.encode(vector, "label", "score", ["node"], one)
    total = {r["node"]: r["s"] for r in vector.groupBy("node").agg(F.sum("score").alias("s")).collect()}
    assert all(r["estimate"] == total[r["node"]] for r in cms.estimate(s, vector, "label", ["node"], one).collect())
    assert all(r["mass"] == total[r["node"]] for r in cms.row_mass(s, ["node"], one).collect())


def test_linear_and_layouts_agree(spark, vector):
    s = cms.encode(vector, "label", "score", ["node"], SPEC)
    double = cms.encode(vector.withColumn("score", F.col("score") * 2.5), "label", "score", ["node"], SPEC)
    assert rows(cms.combine([(2.0, s), (0.5, s)], ["node"]).select("node", "cell", F.round("val", 9))) == rows(double.select("node", "cell", F.round("val", 9)))
    block = cms.to_block(s, ["node"], SPEC)
    assert rows(cms.to_cells(block, ["node"]).select("node", "cell", "val")) == rows(s.select("node", "cell", "val"))
    mixed = block.select("node", cms.combine_blocks(F.col("s"), F.col("s"), 2.0, 0.5).alias("s"))
    assert rows(cms.to_cells(mixed, ["node"]).select("node", "cell", F.round("val", 9))) == rows(double.select("node", "cell", F.round("val", 9)))
    est = block.crossJoin(spark.range(20).withColumnRenamed("id", "label")).select("node", "label", cms.estimate_block(F.col("s"), F.col("label"), SPEC).alias("estimate"))
    assert rows(est) == rows(cms.estimate(s, vector, "label", ["node"], SPEC).select("node", "label", "estimate"))
    weighted = cms.weighted_sum(s.withColumn("w", F.lit(2.5)), ["node"], "w")
    assert rows(weighted.select("node", "cell", F.round("val", 9))) == rows(double.select("node", "cell", F.round("val", 9)))


def test_specs_guard_and_empty(spark):
    with pytest.raises(ValueError):
        SPEC.assert_same(cms.SketchSpec.create(7, 3, 6))
    assert cms.SketchSpec.from_dict(SPEC.as_dict()) == SPEC
    assert cms.empty_sketch(spark, SPEC).count() == 0
    assert cms.empty_sketch(spark, SPEC, layout="block").first()["s"] == [0.0] * SPEC.cells
    with pytest.raises(ValueError):
        cms.SketchSpec.create(0, 1)


def test_prescribed_sizes():
    assert [(s.width, s.depth) for s in (sizing.size_sparse(2, 192, 0.05, 0.1), sizing.size_sparse(1, 10_000, 0.05, 0.1), sizing.size_sparse(1, 1_000_000, 0.05, 0.1))] == [(109, 8), (55, 12), (55, 17)]
    assert sizing.size_zipf_printed(0.05, 1.5, 192, 0.1).width == math.ceil(math.e / math.sqrt(0.05))
    assert sizing.size_tail(2, 0.1, 0.1, printed=True).flag and not sizing.size_tail(2, 0.1, 0.1).flag
    assert sizing.size_sparse(1, 10, 0.1, 0.1, simultaneous_nodes=1000).depth > sizing.size_sparse(1, 10, 0.1, 0.1).depth
    assert sizing.size_community(2, 0.01, 0.05, 10, 0.1).width == 7
    assert sizing.recommend(2, 192, 0.05, 0.1, z=1.0).rule == "sparse" and sizing.recommend(2, 192, 0.05, 0.1, z=2.0).rule == "zipf"


def test_store_choice_prefers_the_sketch_only_when_it_is_smaller():
    assert sizing.choose_store(192, 872, 192) == "exact_dense"
    assert sizing.choose_store(1_000_000, 935, 500_000) == "sketch"
    assert sizing.choose_store(1_000_000, 935, 3) == "exact_long"


def test_sql_functions(spark, vector):
    register(spark, SPEC)
    vector.createOrReplaceTempView("lf_vector")
    got = spark.sql("SELECT node, c.cell, sum(c.val) AS val FROM lf_vector, LATERAL lf_cells(label, score) c GROUP BY 1, 2 HAVING sum(c.val) != 0")
    want = cms.encode(vector, "label", "score", ["node"], SPEC)
    assert rows(got) == rows(want.select("node", "cell", "val"))
    assert spark.sql(f"SELECT lf_hash(5L, {SPEC.a[0]}L, {SPEC.b[0]}L, 7L)").first()[0] == SPEC.cell_index(5, 0)
    cms.to_block(want, ["node"], SPEC).createOrReplaceTempView("lf_block")
    assert rows(spark.sql("SELECT node, e.cell, e.val FROM lf_block, LATERAL lf_explode(s) e")) == rows(want.select("node", "cell", "val"))
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan


def test_vector_sum(spark):
    df = spark.createDataFrame([(1, [1.0, 0.0], 2.0), (1, [3.0, 1.0], 0.5)], "k int, s array<double>, w double")
    assert vector_sum(df, ["k"], "s", F.col("w")).first()["s"] == [3.5, 0.5]


def test_builtin_sketch_counts(spark):
    assert cms.builtin_counts(spark.range(10).select(F.col("id")), "id", 0.1, 0.9, 1).first()[0]


def test_share_of_seeds_that_break_the_bound_is_small():
    size = sizing.size_sparse(1, 40, 0.1, 0.1)
    broken = 0
    for seed in range(40):
        spec = cms.SketchSpec.create(size.width, size.depth, seed)
        value = [1 / 40] * 40
        cell = [0.0] * spec.cells
        for k, v in enumerate(value):
            for j in range(spec.depth):
                cell[spec.cell_index(k, j)] += v
        broken += any(min(cell[spec.cell_index(k, j)] for j in range(spec.depth)) - v > 0.1 for k, v in enumerate(value))
    assert broken <= 4
