"""Graph tools over edge tables (src, dst, w): each unordered pair once, until :func:`symmetrise`."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut


@dataclass
class Graph:
    nodes: DataFrame  # node, kind, key
    edges: DataFrame  # src, dst, w


def strip_self_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("src != dst")


def drop_zero(edges: DataFrame) -> DataFrame:
    return edges.filter("w != 0")


def merge_parallel(edges: DataFrame, how: str = "sum") -> DataFrame:
    """One row for each unordered pair; ``how`` is sum, max or min."""
    agg = {"sum": F.sum, "max": F.max, "min": F.min}[how]
    return edges.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(agg("w").alias("w"))


def clean(edges: DataFrame) -> DataFrame:
    """Checked, without loops, parallels and zero weights. Negative or non-finite weights raise when the plan runs."""
    ok = (F.col("w") >= 0) & (F.col("w") < F.lit(float("inf")))
    checked = edges.withColumn("w", F.when(ok, F.col("w")).otherwise(F.raise_error(F.lit("edge weights must be finite and not negative")).cast("double")))
    return drop_zero(merge_parallel(strip_self_loops(checked)))


def symmetrise(edges: DataFrame, parts: int | None = None) -> DataFrame:
    """A = W' + W'^T as directed rows (src, dst, w), placed by dst in so many ``parts`` if given."""
    both = edges.select("src", "dst", "w").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    both = both.repartition(parts, "dst") if parts else both
    return both.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def degree(edges: DataFrame) -> DataFrame:
    """node, deg of undirected edges."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node"), "w")
    return ends.groupBy("node").agg(F.sum("w").alias("deg"))


def laplacian_quadratic(edges: DataFrame, scores: DataFrame) -> DataFrame:
    """label, y^T (D - W) y: the sum over edges of w (y_u - y_v)^2."""
    both = edges.select(F.col("src").alias("node"), "src", "dst", "w", F.lit(1.0).alias("side")).unionByName(edges.select(F.col("dst").alias("node"), "src", "dst", "w", F.lit(-1.0).alias("side")))
    gaps = both.join(scores, "node").groupBy("src", "dst", "w", "label").agg(F.sum(F.col("side") * F.col("score")).alias("gap"))
    return gaps.groupBy("label").agg(F.sum(F.col("w") * F.col("gap") ** 2).alias("value"))


def row_normalise(directed: DataFrame) -> DataFrame:
    """src, dst, coef with the coefficients that reach a node summing to 1."""
    total = directed.groupBy("dst").agg(F.sum("w").alias("t")).withColumnRenamed("dst", "d_")
    return directed.join(total, F.col("dst") == F.col("d_")).select("src", "dst", (F.col("w") / F.col("t")).alias("coef"))


def sym_normalise(directed: DataFrame) -> DataFrame:
    """src, dst, coef = w / sqrt(d_src d_dst)."""
    total = directed.groupBy("dst").agg(F.sum("w").alias("t"))
    out = directed.join(total.select(F.col("dst").alias("d1"), F.col("t").alias("t1")), F.col("dst") == F.col("d1"))
    out = out.join(total.select(F.col("dst").alias("d2"), F.col("t").alias("t2")), F.col("src") == F.col("d2"))
    return out.select("src", "dst", (F.col("w") / F.sqrt(F.col("t1") * F.col("t2"))).alias("coef"))


def transition(edges: DataFrame) -> DataFrame:
    """src, dst, p: a step of the random walk from src."""
    directed = symmetrise(edges)
    total = directed.groupBy("src").agg(F.sum("w").alias("t")).withColumnRenamed("src", "s_")
    return directed.join(total, F.col("src") == F.col("s_")).select("src", "dst", (F.col("w") / F.col("t")).alias("p"))


def restricted_transition(edges: DataFrame, members: DataFrame) -> DataFrame:
    """The steps that stay among ``members`` (node)."""
    inside = members.select("node").distinct()
    steps = transition(edges)
    return steps.join(inside.withColumnRenamed("node", "src"), "src", "left_semi").join(inside.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst", "p")


def prune_degree(edges: DataFrame, least: float = 0, most: float = float("inf")) -> DataFrame:
    """Edges whose both ends have a degree in the range."""
    keep = degree(edges).filter((F.col("deg") >= least) & (F.col("deg") <= most)).select("node")
    return induced_subgraph(edges, keep)


def induced_subgraph(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    ids = nodes.select("node")
    return edges.join(ids.withColumnRenamed("node", "src"), "src", "left_semi").join(ids.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst", "w")


def reachable(edges: DataFrame, seeds: DataFrame, hops: int) -> DataFrame:
    """node, hop: the least number of steps from a seed, up to ``hops``."""
    both = symmetrise(edges).select("src", "dst")
    found = seeds.select("node").distinct().withColumn("hop", F.lit(0))
    frontier = found
    for h in range(1, hops + 1):
        new = frontier.join(both, F.col("node") == F.col("src")).select(F.col("dst").alias("node")).distinct()
        frontier = cut(new.join(found, "node", "left_anti").withColumn("hop", F.lit(h)), "frontier")
        found = found.unionByName(frontier)
    return found


def encode_ids(df: DataFrame, keys: list[str], name: str = "id", first: int = 0, unique: bool = False) -> DataFrame:
    """Distinct keys with dense numbers in their order; ``unique`` keys are so already.

    A range sort numbers the rows within each partition; the sizes of the partitions before, from a table with one
    row for each partition, are added. No window runs over all rows.
    """
    order = [F.col(k).asc_nulls_first() for k in keys]
    dealt = (df.select(*keys) if unique else df.select(*keys).distinct()).repartitionByRange(*order).sortWithinPartitions(*order)
    nth = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    rows = cut(dealt.select("*", F.spark_partition_id().alias("part_"), nth.alias("nth_")), "ids")
    sizes = rows.groupBy("part_").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select(F.col("part_").alias("p_"), (F.sum("n").over(Window.orderBy("part_")) - F.col("n")).alias("before_"))
    return rows.join(F.broadcast(before), F.col("part_") == F.col("p_")).select(*keys, (F.col("before_") + F.col("nth_") + F.lit(first)).alias(name))


def same(a: Column, b: Column) -> Column:
    return a.eqNullSafe(b)
