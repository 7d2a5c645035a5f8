"""Graph tools, builders, seeds, measures of structure, sources."""

import pytest
from pyspark.sql import functions as F

from labelflow.operators import graph, measures
from labelflow.schema import require
from labelflow.sources import graphs, seeds, tables
from labelflow.functions.sketch import SketchSpec, encode

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_clean_contracts_loops_and_parallels(spark):
    e = spark.createDataFrame([(0, 0, 1.0), (0, 1, 1.0), (1, 0, 2.0), (2, 1, 0.0)], "src long, dst long, w double")
    assert rows(graph.clean(e)) == [(0, 1, 3.0)]
    assert rows(graph.symmetrise(graph.clean(e))) == [(0, 1, 3.0), (1, 0, 3.0)]
    bad = spark.createDataFrame([(0, 1, float("nan"))], "src long, dst long, w double")
    with pytest.raises(Exception, match="finite"):
        graph.clean(bad).collect()
    with pytest.raises(ValueError):
        require(e.drop("w"), "edges")
    assert require(e.select("w", "dst", "src"), "edges").columns == ["src", "dst", "w"]


def test_two_triangles(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (0, 2, 1.0), (3, 4, 1.0), (4, 5, 1.0), (3, 5, 1.0), (2, 3, 1.0)], "src long, dst long, w double")
    c = spark.createDataFrame([(n, "a" if n < 3 else "b") for n in range(6)], "node long, community string")
    for r in measures.conductance(e, c).collect():
        assert (r["vol"], r["boundary"]) == (7.0, 1.0) and r["psi"] == pytest.approx(1 / 3) and r["phi"] == pytest.approx(1 / 7)
        assert r["psi"] >= r["phi"]
    found = measures.escape_mass(e, c, 1).collect()
    assert all(r["mass"] <= r["psi"] + 1e-12 and r["bound"] == pytest.approx(r["psi"]) for r in found)
    mass = {r["node"]: r["mass"] for r in found}
    assert mass[2] == pytest.approx(1 / 3) and mass[0] == 0
    assert {r["node"]: r["deg"] for r in graph.degree(e).collect()}[2] == 3
    assert rows(graph.reachable(e, spark.createDataFrame([(0,)], "node long"), 2)) == [(0, 0), (1, 1), (2, 1), (3, 2)]
    assert graph.prune_degree(e, least=3).count() == 1
    assert graph.restricted_transition(e, c.filter("community = 'a'")).agg(F.sum("p")).first()[0] == pytest.approx(2 + 2 / 3)
    y = spark.createDataFrame([(0, 0, 1.0)], "node long, label long, score double")
    assert graph.laplacian_quadratic(e, y).first()["value"] == 2.0


def test_planted_blocks_have_the_stated_conductance(spark):
    g, c = graphs.planted_blocks(spark, 4, 6, 0.2)
    for r in measures.conductance(g.edges, c).collect():
        assert r["psi"] == pytest.approx(0.2) and r["phi"] <= r["psi"] + 1e-12


def test_dense_ids(spark):
    df = spark.createDataFrame([(x,) for x in ["b", "a", "c", "a", None]], "k string")
    assert rows(graph.encode_ids(df, ["k"]).filter("k is not null")) == [("a", 1), ("b", 2), ("c", 3)]
    ids = [r["id"] for r in graph.encode_ids(spark.range(1000).select((F.col("id") * 7 % 1000).alias("k")), ["k"]).collect()]
    assert sorted(ids) == list(range(1000))


def test_mrr_by_hand(spark):
    y = spark.createDataFrame([(1, 0, 3.0), (1, 1, 2.0), (1, 2, 2.0), (2, 0, 1.0)], "node long, label long, score double")
    g = spark.createDataFrame([(1, 1), (2, 5), (3, 0)], "node long, label long")
    assert measures.mrr(y, g, "min").first()["mrr"] == pytest.approx((1 / 2) / 3)
    assert measures.mrr(y, g, "max").first()["mrr"] == pytest.approx((1 / 3) / 3)
    assert measures.mrr(y, g, "mean").first()["mrr"] == pytest.approx((1 / 2.5) / 3)


def test_zipf_fit(spark):
    y = spark.createDataFrame([(0, k, 1.0 / (k + 1) ** 1.3) for k in range(50)], "node long, label long, score double")
    assert measures.zipf_exponent(measures.skew_profile(y, 1)).first()["z"] == pytest.approx(1.3, abs=1e-6)


def test_builders_hold_their_contracts(spark):
    for g in (graphs.parts_kb(spark, SF), graphs.parts_kb(spark, SF, noise=True), graphs.event_tags(spark, SF), graphs.geo_hierarchy(spark, SF), graphs.page_links(spark, SF), graphs.order_items(spark, SF), graphs.customer_part(spark, SF), graphs.synthetic_photo(spark, 200, 20)):
        require(g.nodes, "nodes"), require(g.edges, "edges")
        ids = g.nodes.select("node")
        assert ids.count() == ids.distinct().count()
        assert not g.edges.select(F.explode(F.array("src", "dst")).alias("node")).join(ids, "node", "left_anti").count()
    assert graphs.parts_kb(spark, SF).edges.count() == 800


def test_seeds(spark):
    gold = spark.createDataFrame([(n, n % 3) for n in range(30)], "node long, label long")
    s = seeds.seeds_per_class(gold, 2)
    assert rows(s.groupBy("label").count()) == [(0, 2), (1, 2), (2, 2)] and seeds.is_binary(s)
    assert seeds.holdout(gold, s).count() == 24
    assert seeds.seed_sparsity(s).first()["k"] == 1.0 and not seeds.overlap_report(s).count()
    assert rows(seeds.self_injection(spark.createDataFrame([(9,), (4,)], "node long"))) == [(4, 0, 1.0), (9, 1, 1.0)]


def test_files_and_epochs(spark, tmp_path):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 0.5)], "src long, dst long, w double")
    for fmt in ("parquet", "orc", "json"):
        tables.write(e, f"{tmp_path}/{fmt}", fmt)
        good, bad = tables.read_edges(spark, f"{tmp_path}/{fmt}", fmt)
        assert rows(good) == rows(e) and bad.count() == 0
    (tmp_path / "x.csv").write_text("src,dst,w\n0,1,1.0\noops,2,3\n")
    good, bad = tables.read_edges(spark, str(tmp_path / "x.csv"), "csv")
    assert rows(good) == [(0, 1, 1.0)] and bad.count() == 1 and good.count() == 1
    spec = SketchSpec.create(5, 2)
    s = encode(spark.createDataFrame([(0, 3, 1.0)], "node long, label long, score double"), "label", "score", ["node"], spec)
    tables.save_sketch(s, spec, f"{tmp_path}/sketch")
    back, found = tables.load_sketch(spark, f"{tmp_path}/sketch", spec)
    assert rows(back) == rows(s) and found == spec
    with pytest.raises(ValueError):
        tables.load_sketch(spark, f"{tmp_path}/sketch", SketchSpec.create(5, 2, 1))
    store = tables.EpochStore(spark, f"{tmp_path}/epochs")
    assert store.latest() is None
    for i in range(4):
        store.put(i, e)
    assert store.epochs() == [2, 3] and rows(store.latest()[1]) == rows(e)


def test_bucketed_join_needs_no_exchange(spark, tmp_path):
    a = tables.bucketed(spark.range(100).select(F.col("id").alias("k"), F.col("id").alias("x")), "lf_bucket_a", "k", 4)
    b = tables.bucketed(spark.range(100).select(F.col("id").alias("k"), F.col("id").alias("y")), "lf_bucket_b", "k", 4)
    plan = a.hint("merge").join(b, "k")
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in text
    spark.sql("DROP TABLE lf_bucket_a")
    spark.sql("DROP TABLE lf_bucket_b")


def test_filters_reach_the_scan(spark):
    from labelflow.queries.relational import edges_filtered_by_date

    text = edges_filtered_by_date(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual(l_shipdate" in text
    assert "l_comment" not in text and "l_quantity" not in text
