"""Classes of nodes that no step can tell apart.

Nodes without seeds or priors whose in-edges are the same (sources and coefficients) have the same scores, and the same
sketch, after every step. The smallest node of a class stands for it: its in-edges stay, and the out-edges of the class
are summed. The run on classes is that on all nodes, so nothing is lost; what is asked of nodes is found for their
classes and spread to the members at the end. A graph without such nodes keeps its size.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.affine import AffinePlan
from ..session import cut, discard

#: In-edges of the nodes that are compared; a node with more is a class of its own.
LISTED = 64


@dataclass
class Lumped:
    """``plan`` over the classes, ``members`` (node, of) of all nodes that can get a score, ``sizes`` (node, size)."""

    plan: AffinePlan
    members: DataFrame
    sizes: DataFrame

    def spread(self, rows: DataFrame) -> DataFrame:
        """Rows (node, ...) of classes as rows of all their members."""
        held = rows.withColumnRenamed("node", "class_").join(self.members, F.col("class_") == F.col("of"))
        return held.select("node", *[c for c in rows.columns if c != "node"])

    def edges(self, edges: DataFrame) -> DataFrame:
        """Undirected edges (src, dst, w) between classes, with the weight of all their members' edges."""
        side = lambda at: self.members.select(F.col("node").alias(at), F.col("of").alias(f"{at}_of"))
        ends = edges.join(side("src"), "src").join(side("dst"), "dst").select(F.col("src_of").alias("src"), F.col("dst_of").alias("dst"), "w")
        return ends.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def lump(plan: AffinePlan, seeds: DataFrame, priors: DataFrame | None = None) -> Lumped:
    """The classes of ``plan`` for runs from ``seeds`` (and ``priors``), whose nodes are classes of their own."""
    edges = cut(plan.edges.filter("coef > 0").select("src", "dst", "coef"), "edges")
    own = seeds.select("node") if priors is None else seeds.select("node").unionByName(priors.select("node"))
    own = own.distinct()
    few = edges.groupBy(F.col("dst").alias("d_")).agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") <= LISTED).join(own, F.col("d_") == F.col("node"), "left_anti")
    lists = edges.join(few.select("d_"), F.col("dst") == F.col("d_"), "left_semi").groupBy("dst").agg(F.sort_array(F.collect_list(F.struct("src", "coef"))).alias("in"))
    lists = cut(lists, "in-edges")
    first = lists.groupBy(F.col("in").alias("in_")).agg(F.min("dst").alias("of"))
    alike = cut(lists.join(first, F.col("in") == F.col("in_")).select(F.col("dst").alias("node"), "of"), "alike")
    every = edges.select(F.col("dst").alias("node")).unionByName(own).distinct()
    alone = every.join(alike.select("node"), "node", "left_anti").select("node", F.col("node").alias("of"))
    members = cut(alike.unionByName(alone), "members")
    kept = members.filter("node = of").select(F.col("node").alias("d_"))
    into = edges.join(kept, F.col("dst") == F.col("d_"), "left_semi")
    classes = into.join(members, F.col("src") == F.col("node")).groupBy(F.col("of").alias("src"), "dst").agg(F.sum("coef").alias("coef"))
    classes = cut(classes, "classes")
    for old in (edges, lists, alike):
        discard(old)
    sizes = cut(members.groupBy(F.col("of").alias("node")).agg(F.count(F.lit(1)).alias("size")), "sizes")
    return Lumped(AffinePlan(plan.inject, classes, plan.prior, plan.method), members, sizes)
