"""Connected components of a link table, on DataFrames, by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import discard
from .common import materialise


def _lowest(edges: DataFrame) -> DataFrame:
    """(u, v) with ``low``, the smallest of u and its neighbours. Sums are combined before the shuffle; the join
    back is an ordinary equi-join, which adaptive execution splits where one node has most of the links."""
    low = edges.groupBy("u").agg(F.min("v").alias("low")).select(F.col("u").alias("k"), F.least("k", "low").alias("low"))
    return edges.join(low, F.col("u") == F.col("k")).select("u", "v", "low")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _lowest(both).filter("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).filter("u != v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    found = _lowest(down)
    rest = found.filter("v != low").select(F.col("v").alias("u"), F.col("low").alias("v"))
    return found.select("u", F.col("low").alias("v")).unionByName(rest).distinct()


def connected_components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for each node of a link between different nodes; component is its smallest node.

    Each round is written to the shared folder, which cuts the lineage, and the one before deleted; the number of rounds grows with the
    logarithm of the largest component.
    """
    u, v = F.col(a).cast("long"), F.col(b).cast("long")
    edges = materialise(links.filter(u != v).select(F.greatest(u, v).alias("u"), F.least(u, v).alias("v")).distinct(), "links")

    def mark(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    last = mark(edges)
    while last[0]:
        before, edges = edges, materialise(_small_star(_large_star(edges)), "stars")
        now = mark(edges)
        discard(before)
        if now == last:
            break
        last = now
    nodes = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
