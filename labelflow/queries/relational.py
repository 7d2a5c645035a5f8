"""Relational queries: each engine operation on the given tables, with independent SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sketch as cms
from ..operators import graph as ops
from ..operators.propagate import delta, step
from ..plans.affine import modified_adsorption
from ..sources import graphs, seeds
from ..sources.tables import table
from . import fixtures as fx
from .sql import GEO, KB, iterate, ma, cells_sql, with_

Q, SQL = {}, {}


def query(sql: str | None = None):
    def put(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


ATTRS = """SELECT p_partkey AS src, kind, key FROM (
  SELECT p_partkey, 'brand' AS kind, p_brand AS key FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part
  UNION ALL SELECT p_partkey, 'word1', split_part(p_name, ' ', 1) FROM part UNION ALL SELECT p_partkey, 'word2', split_part(p_name, ' ', 2) FROM part)"""


@query(ATTRS)
def edges_part_attrs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.part_attributes(spark, sf_dir)


@query("SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_shipdate >= DATE '1996-01-01' AND l_shipdate < DATE '1997-01-01'")
def edges_filtered_by_date(spark, sf_dir):
    day = lambda s: F.lit(s).cast("date").cast("timestamp_ntz")
    rows = table(spark, sf_dir, "lineitem").filter((F.col("l_shipdate") >= day("1996-01-01")) & (F.col("l_shipdate") < day("1997-01-01")))
    return rows.select("l_orderkey", "l_partkey").distinct()


@query("SELECT l_partkey AS src, l_suppkey AS dst, round(sum(CAST(l_extendedprice AS DECIMAL(18,4)) * (1 - CAST(l_discount AS DECIMAL(18,4))))::DOUBLE, 6) AS w FROM lineitem GROUP BY 1, 2")
def weighted_trade_edges(spark, sf_dir):
    d = lambda c: F.col(c).cast("decimal(18,4)")
    rows = table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))
    return rows.agg(F.round(F.sum(d("l_extendedprice") * (F.lit(1).cast("decimal(18,4)") - d("l_discount"))).cast("double"), 6).alias("w"))


@query("SELECT o_custkey AS c_custkey, l_partkey, count(*)::DOUBLE AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def customer_part_edges(spark, sf_dir):
    return graphs.customer_part_links(spark, sf_dir)


PULL = with_(KB, ma(), ["pulled AS (SELECT c.dst AS node, s.label, sum(c.coef * s.score) AS score FROM coef c JOIN seeds s ON s.node = c.src GROUP BY 1, 2)"]) + " SELECT node, label, round(score, 6) AS score FROM pulled"


def _pull(spark, sf_dir, hint):
    t = fx.parts_kb(spark, sf_dir)
    plan = modified_adsorption(t.edges, t.seeds, fx.MU, t.nodes)
    out = step(plan.edges, t.seeds.limit(0), t.seeds, hint=hint)
    return out.select("node", "label", F.round("score", 6).alias("score"))


@query(PULL)
def pull_step_smj(spark, sf_dir):
    return _pull(spark, sf_dir, "merge")


@query(PULL)
def pull_step_shj(spark, sf_dir):
    return _pull(spark, sf_dir, "shuffle_hash")


@query("""SELECT 'nation' AS kind1, n_nationkey::VARCHAR AS key1, 'region' AS kind2, n_regionkey::VARCHAR AS key2, 1.0::DOUBLE AS w FROM nation JOIN region ON n_regionkey = r_regionkey
UNION ALL SELECT 'customer', c_custkey::VARCHAR, 'nation', c_nationkey::VARCHAR, 1.0 FROM customer JOIN nation ON c_nationkey = n_nationkey
UNION ALL SELECT 'supplier', s_suppkey::VARCHAR, 'nation', s_nationkey::VARCHAR, 1.0 FROM supplier JOIN nation ON s_nationkey = n_nationkey""")
def geo_hierarchy_edges(spark, sf_dir):
    return graphs.geo_links(spark, sf_dir)


@query(with_(KB) + " SELECT p_partkey, p_name FROM part WHERE p_partkey NOT IN (SELECT node FROM seeds)")
def unseeded_parts(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    return table(spark, sf_dir, "part").join(t.seeds, F.col("p_partkey") == F.col("node"), "left_anti").select("p_partkey", "p_name")


@query(with_(KB) + " SELECT p_partkey, p_name FROM part WHERE p_partkey IN (SELECT node FROM seeds)")
def seeded_parts(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    return table(spark, sf_dir, "part").join(t.seeds, F.col("p_partkey") == F.col("node"), "left_semi").select("p_partkey", "p_name")


@query("SELECT a.s_suppkey AS src, b.s_suppkey AS dst FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > b.s_acctbal")
def price_dominance_edges(spark, sf_dir):
    a = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("src"), "s_nationkey", F.col("s_acctbal").alias("x"))
    b = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("dst"), "s_nationkey", F.col("s_acctbal").alias("y"))
    return a.join(b, "s_nationkey").filter("x > y").select("src", "dst")


@query("SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.event_id < b.event_id AND abs(a.value - b.value) <= 0.01::DOUBLE")
def value_band_edges(spark, sf_dir):
    return graphs.value_band(spark, sf_dir, 0.01)


@query("""WITH e AS (SELECT event_id, ts, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events)
SELECT a.event_id AS src, b.event_id AS dst FROM e a JOIN e b ON a.k = b.k AND a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000""")
def co_activity_edges(spark, sf_dir):
    return graphs.co_activity(spark, sf_dir, 60)


@query("""SELECT event_id, user_id, coalesce(last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS)
OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS last_signup FROM events""")
def label_as_of_event(spark, sf_dir):
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    signup = F.when(F.col("event_type") == "signup", F.col("event_id"))
    return table(spark, sf_dir, "events").select("event_id", "user_id", F.coalesce(F.last(signup, ignorenulls=True).over(before), F.lit(-1)).cast("long").alias("last_signup"))


@query(with_(KB, ma(), iterate(2)) + " SELECT coalesce(a.node, b.node) AS node, coalesce(a.label, b.label) AS label, round(coalesce(b.score, 0) - coalesce(a.score, 0), 6) + 0.0 AS delta FROM y1 a FULL JOIN y2 b ON a.node = b.node AND a.label = b.label")
def score_delta(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    from ..operators.propagate import constants

    plan = modified_adsorption(t.edges, t.seeds, fx.MU, t.nodes)
    fixed = constants(plan, t.seeds, None, "label", "score")
    y1 = step(plan.edges, fixed, t.seeds)
    y2 = step(plan.edges, fixed, y1)
    return delta(y1, y2).select("node", "label", (F.round("delta", 6) + 0.0).alias("delta"))


@query(with_(KB) + " SELECT node, sum(w) AS deg FROM (SELECT src AS node, w FROM edges UNION ALL SELECT dst, w FROM edges) GROUP BY 1")
def node_degree(spark, sf_dir):
    return ops.degree(fx.parts_kb(spark, sf_dir).edges)


@query(with_(KB) + " SELECT kind, sum(w) AS volume FROM (SELECT src AS node, w FROM edges UNION ALL SELECT dst, w FROM edges) d JOIN nodes USING (node) GROUP BY 1")
def volume_by_community(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    return ops.degree(t.edges).join(t.nodes, "node").groupBy("kind").agg(F.sum("deg").alias("volume"))


@query(with_(KB) + " SELECT node, array_to_string(list_sort(list(label)), ',') AS labels, max(name) AS last_name FROM seeds JOIN dict USING (label) GROUP BY node")
def seeds_per_node_list(spark, sf_dir):
    drawn, labels = fx.part_seeds(spark, sf_dir)
    return drawn.join(labels, "label").groupBy("node").agg(F.array_join(F.sort_array(F.collect_list("label")), ",").alias("labels"), F.max("name").alias("last_name"))


@query(with_(KB) + " SELECT node, count(DISTINCT label) AS labels FROM seeds GROUP BY node")
def distinct_labels_per_node(spark, sf_dir):
    return fx.part_seeds(spark, sf_dir)[0].groupBy("node").agg(F.countDistinct("label").alias("labels"))


def _coverage(kind: str) -> str:
    return with_(KB) + f""" SELECT p_brand, p_type, grouping(p_brand, p_type)::BIGINT AS level, count(*) AS parts, sum(CASE WHEN p_partkey IN (SELECT node FROM seeds) THEN 1 ELSE 0 END)::BIGINT AS seeded
    FROM part GROUP BY {kind}"""


def _marked(spark, sf_dir):
    s = fx.parts_kb(spark, sf_dir).seeds.select("node").distinct().withColumn("s", F.lit(1))
    return table(spark, sf_dir, "part").join(s, F.col("p_partkey") == F.col("node"), "left")


def _counted(grouped):
    return grouped.agg(F.grouping_id().cast("long").alias("level"), F.count(F.lit(1)).alias("parts"), F.sum(F.coalesce("s", F.lit(0))).alias("seeded"))


@query(_coverage("CUBE (p_brand, p_type)"))
def seed_coverage_cube(spark, sf_dir):
    return _counted(_marked(spark, sf_dir).cube("p_brand", "p_type"))


@query(_coverage("ROLLUP (p_brand, p_type)"))
def seed_coverage_rollup(spark, sf_dir):
    return _counted(_marked(spark, sf_dir).rollup("p_brand", "p_type"))


@query(_coverage("GROUPING SETS ((p_brand), (p_type))"))
def seed_coverage_sets(spark, sf_dir):
    return _counted(_marked(spark, sf_dir).groupingSets([["p_brand"], ["p_type"]], "p_brand", "p_type"))


Y2 = with_(KB, ma(), iterate(2))


def _y2(spark, sf_dir):
    from .methods import exact

    return exact(spark, sf_dir, 2)


@query(Y2 + """ SELECT * FROM (SELECT node, label, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM (SELECT node, label, round(score, 6) AS score FROM y2) r
WINDOW w AS (PARTITION BY node ORDER BY score DESC, label), v AS (PARTITION BY node ORDER BY score DESC)) WHERE rn <= 3""")
def top_labels_per_node(spark, sf_dir):
    y = _y2(spark, sf_dir).withColumn("score", F.round("score", 6))
    w, v = Window.partitionBy("node").orderBy(F.desc("score"), "label"), Window.partitionBy("node").orderBy(F.desc("score"))
    out = y.select("node", "label", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"))
    return out.filter("rn <= 3")


@query(Y2 + """ SELECT node, label, gap FROM (SELECT node, label, row_number() OVER w AS rn, round(score - lead(score, 1, 0.0) OVER w, 6) + 0.0 AS gap FROM (SELECT node, label, round(score, 6) AS score FROM y2) r
WINDOW w AS (PARTITION BY node ORDER BY score DESC, label)) WHERE rn = 1""")
def score_gap_to_runner_up(spark, sf_dir):
    w = Window.partitionBy("node").orderBy(F.desc("score"), "label")
    y = _y2(spark, sf_dir).withColumn("score", F.round("score", 6))
    out = y.withColumn("rn", F.row_number().over(w)).withColumn("gap", F.round(F.col("score") - F.lead("score", 1, 0.0).over(w), 6) + 0.0)
    return out.filter("rn = 1").select("node", "label", "gap")


@query(Y2 + """ SELECT node, label, round(sum(score) OVER (PARTITION BY node ORDER BY score DESC, label ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 9) AS tail FROM (SELECT node, label, round(score, 8) AS score FROM y2) r""")
def tail_mass_profile(spark, sf_dir):
    w = Window.partitionBy("node").orderBy(F.desc("score"), "label").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    return _y2(spark, sf_dir).withColumn("score", F.round("score", 8)).select("node", "label", F.round(F.sum("score").over(w), 9).alias("tail"))


DEG = "deg AS (SELECT node, sum(w) AS deg FROM (SELECT src AS node, w FROM edges UNION ALL SELECT dst, w FROM edges) GROUP BY 1)"


@query(with_(KB, [DEG]) + " SELECT node, deg FROM deg ORDER BY deg DESC, node LIMIT 20")
def heaviest_hubs(spark, sf_dir):
    return ops.degree(fx.parts_kb(spark, sf_dir).edges).orderBy(F.desc("deg"), "node").limit(20)


@query(with_(KB) + " SELECT node FROM (SELECT src AS node FROM edges UNION SELECT dst FROM edges UNION SELECT node FROM seeds)")
def nodes_union(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    return t.edges.select(F.col("src").alias("node")).unionByName(t.edges.select(F.col("dst").alias("node"))).unionByName(t.seeds.select("node")).distinct()


@query(with_(KB) + " SELECT s.node FROM seeds s JOIN dict USING (label) WHERE name LIKE 'bt|%' INTERSECT SELECT s.node FROM seeds s JOIN dict USING (label) WHERE name LIKE 'nm|%'")
def seed_intersection(spark, sf_dir):
    drawn, labels = fx.part_seeds(spark, sf_dir)
    named = drawn.join(labels, "label")
    return named.filter(F.col("name").startswith("bt|")).select("node").intersect(named.filter(F.col("name").startswith("nm|")).select("node"))


@query(with_(KB, ma(), iterate(1)) + " SELECT node FROM nodes EXCEPT SELECT node FROM y1")
def nodes_without_scores(spark, sf_dir):
    from .methods import exact

    return fx.parts_kb(spark, sf_dir).nodes.select("node").subtract(exact(spark, sf_dir, 1).select("node"))


TOKENS = f"""pairs AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '{graphs.WORD}'))) AS token FROM documents),
df AS (SELECT token FROM pairs GROUP BY token HAVING count(*) BETWEEN 2 AND (SELECT greatest(2, floor(0.05::DOUBLE * count(*) + 1e-9)) FROM documents))"""


@query(f"WITH {TOKENS} SELECT doc_id AS id, token FROM pairs JOIN df USING (token)")
def doc_token_edges(spark, sf_dir):
    return graphs.token_links(table(spark, sf_dir, "documents"), "doc_id", "text")


@query("SELECT page_id AS src, 'host' AS kind, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS key FROM pages WHERE regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) <> ''")
def page_host_edges(spark, sf_dir):
    return graphs.page_pairs(spark, sf_dir).filter("kind = 'host'")


@query("""SELECT src, 'link' AS kind, key FROM (SELECT page_id AS src, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS key FROM pages) WHERE key <> ''""")
def page_link_edges(spark, sf_dir):
    return graphs.page_pairs(spark, sf_dir).filter("kind = 'link'")


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, user_id, count(*) AS n FROM events GROUP BY 1, 2")
def event_day_edges(spark, sf_dir):
    day = F.date_format(F.date_trunc("day", F.col("ts")), "yyyy-MM-dd")
    return table(spark, sf_dir, "events").groupBy(day.alias("day"), "user_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS orders, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::BIGINT AS last_day FROM orders GROUP BY 1")
def monthly_orders(spark, sf_dir):
    month = F.date_format(F.date_trunc("month", F.col("o_orderdate")), "yyyy-MM")
    gap = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("long")
    return table(spark, sf_dir, "orders").groupBy(month.alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.max(gap).alias("last_day"))


S20 = fx.spec(20, 3)


@query(with_(KB) + f" SELECT node, {cells_sql('label', S20)} AS cell, 1.0 AS val FROM seeds".replace("SELECT node, unnest", "SELECT node, cell, sum(val)::DOUBLE AS val FROM (SELECT node, unnest") + ") GROUP BY 1, 2")
def block_sketch_roundtrip(spark, sf_dir):
    drawn, _ = fx.part_seeds(spark, sf_dir)
    return cms.to_cells(cms.encode(drawn, "label", "score", ["node"], S20, "block"), ["node"]).withColumn("cell", F.col("cell").cast("long"))


@query(with_(KB) + " SELECT node, label, score AS score FROM seeds")
def label_score_map(spark, sf_dir):
    maps = fx.parts_kb(spark, sf_dir).seeds.groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct("label", "score"))).alias("m"))
    return maps.select("node", F.explode("m").alias("label", "score"))


@query("SELECT event_id AS src, 'k' || json_extract_string(props, '$.k') AS key FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
def event_props_edges(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf_dir, "events").filter(k.isNotNull()).select(F.col("event_id").alias("src"), F.concat(F.lit("k"), k.cast("string")).alias("key"))


KNN = """v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings),
cosines AS (SELECT a.id AS src, b.id AS dst, list_dot_product(a.v, b.v) / (sqrt(list_dot_product(a.v, a.v)) * sqrt(list_dot_product(b.v, b.v))) AS c FROM v a JOIN v b ON a.id <> b.id),
knn AS (SELECT src, dst, greatest(c, 0.0) AS w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY c DESC, dst) AS r FROM cosines) WHERE r <= 5)"""


@query(f"WITH {KNN} SELECT src, dst, round(w, 6) AS w FROM knn")
def knn_edges(spark, sf_dir):
    return graphs.knn_pairs(spark, sf_dir).select("src", "dst", F.round("w", 6).alias("w"))


@query(with_(KB, [DEG]) + " SELECT n.kind, d.node, d.deg FROM deg d JOIN nodes n USING (node) WHERE d.deg > (SELECT avg(deg) FROM deg) AND d.deg >= (SELECT avg(e.deg) FROM deg e JOIN nodes o USING (node) WHERE o.kind = n.kind)")
def above_average_hubs(spark, sf_dir):
    t = fx.parts_kb(spark, sf_dir)
    ops.degree(t.edges).join(t.nodes, "node").createOrReplaceTempView("lf_degree")
    return spark.sql("""
        WITH kinds AS (SELECT kind AS k, avg(deg) AS mean FROM lf_degree GROUP BY kind)
        SELECT d.kind, d.node, d.deg FROM lf_degree d JOIN kinds ON d.kind = k
        WHERE d.deg > (SELECT avg(deg) FROM lf_degree) AND d.deg >= mean""")


@query("SELECT p_type, sum(CASE WHEN p_size <= 10 THEN 1 ELSE 0 END)::BIGINT AS small, sum(CASE WHEN p_size BETWEEN 11 AND 30 THEN 1 ELSE 0 END)::BIGINT AS middle, sum(CASE WHEN p_size > 30 THEN 1 ELSE 0 END)::BIGINT AS large FROM part GROUP BY 1")
def score_matrix_pivot(spark, sf_dir):
    size = F.when(F.col("p_size") <= 10, "small").when(F.col("p_size") <= 30, "middle").otherwise("large")
    wide = table(spark, sf_dir, "part").withColumn("b", size).groupBy("p_type").pivot("b", ["small", "middle", "large"]).count()
    return wide.na.fill(0, ["small", "middle", "large"])


@query(with_(KB) + " SELECT node, label FROM seeds")
def seed_sample(spark, sf_dir):
    return fx.part_seeds(spark, sf_dir)[0].select("node", "label")


@query()
def knn_recall(spark, sf_dir):
    """vectors, recall: the share of the exact five nearest that the bucketed search finds."""
    exact = graphs.knn_pairs(spark, sf_dir).select("src", "dst")
    found = graphs.lsh_neighbours(spark, sf_dir).select(F.col("src").alias("s_"), F.col("dst").alias("d_"))
    both = exact.join(found, (F.col("src") == F.col("s_")) & (F.col("dst") == F.col("d_")), "left")
    return both.agg(F.countDistinct("src").alias("vectors"), F.round(F.avg(F.when(F.col("s_").isNotNull(), 1.0).otherwise(0.0)), 4).alias("recall"))
