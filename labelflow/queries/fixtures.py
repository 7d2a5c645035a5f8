"""Graphs, seeds and gold labels of the workloads, written once for each session and scale."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sketch import SketchSpec
from ..operators.graph import Graph
from ..session import cut
from ..sources import graphs, seeds
from ..sources.tables import table

MU = (0.98, 0.01, 0.01)
SIZES = ((109, 8), (109, 3), (20, 8), (20, 3))
_HELD: dict[tuple, object] = {}


@dataclass
class Task:
    nodes: DataFrame
    edges: DataFrame
    seeds: DataFrame
    gold: DataFrame
    labels: DataFrame
    m: int


def spec(width: int, depth: int) -> SketchSpec:
    return SketchSpec.create(width, depth, 42)


def held(spark: SparkSession, sf_dir: str, name: str, make):
    """``make()``, once for each session and scale."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _HELD:
        _HELD[key] = make()
    return _HELD[key]


def forget_runs() -> None:
    """Drop all that is held but graphs, seeds and gold, so that the next query makes its own states."""
    for key in [k for k, v in _HELD.items() if not isinstance(v, Task)]:
        del _HELD[key]


def per_class(parts: int) -> int:
    """Seeds a class: the experiment's 10, but 1 on the smoke scale, where 10 would leave nothing to hold out."""
    return 1 if parts < 1000 else 10


def task(graph: Graph, members: DataFrame, n_seeds: int, name: str) -> Task:
    """A classification task from memberships (node, name)."""
    labels = cut(seeds.label_dictionary(members), f"{name}-labels")
    gold = cut(seeds.labelled(members, labels), f"{name}-gold")
    return Task(cut(graph.nodes, f"{name}-nodes"), cut(graph.edges, f"{name}-edges"), cut(seeds.seeds_per_class(gold, n_seeds), f"{name}-seeds"), gold, labels, labels.count())


def parts_kb(spark: SparkSession, sf_dir: str, noise: bool = False) -> Task:
    def make():
        n = table(spark, sf_dir, "part").count()
        return task(graphs.parts_kb(spark, sf_dir, noise), graphs.part_classes(spark, sf_dir), per_class(n), "kb")

    return held(spark, sf_dir, f"kb{noise}", make)


def part_seeds(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Seeds (node, label, score) and labels (label, name) of :func:`parts_kb`, drawn from the table in the plan itself: what
    asks for seeds alone reads the parts, whether or not the task is held."""
    members = graphs.part_classes(spark, sf_dir)
    labels = cut(seeds.label_dictionary(members), "kb-labels")
    n = table(spark, sf_dir, "part").count()
    return seeds.seeds_per_class(seeds.labelled(members, labels), per_class(n)), labels


def geo(spark: SparkSession, sf_dir: str) -> Task:
    """Customers and suppliers classed by nation, 10 seeds for each."""

    def make():
        g = graphs.geo_hierarchy(spark, sf_dir)
        b = graphs.GEO_BASE
        name = lambda t, key, nation, kind: table(spark, sf_dir, t).select((F.col(key) + b[kind]).alias("node"), F.lpad(F.col(nation).cast("string"), 2, "0").alias("name"))
        members = name("customer", "c_custkey", "c_nationkey", "customer").unionByName(name("supplier", "s_suppkey", "s_nationkey", "supplier"))
        return task(g, members, 10, "geo")

    return held(spark, sf_dir, "geo", make)


def _injected(graph: Graph, kind: str, name: str) -> Task:
    """Each node of a kind seeded with a label of its own."""
    nodes = cut(graph.nodes, f"{name}-nodes")
    own = nodes.filter(F.col("kind") == kind)
    q = cut(seeds.self_injection(own.select("node")), f"{name}-seeds")
    return Task(nodes, cut(graph.edges, f"{name}-edges"), q, q.select("node", "label"), q.select("label", F.col("node").cast("string").alias("name")), q.count())


#: Events of the smaller self-injection graph, a subset of the larger one's.
FEW_EVENTS = 10_000


def events(spark: SparkSession, sf_dir: str) -> Task:
    """Every event seeded with a label of its own."""
    return held(spark, sf_dir, "events", lambda: _injected(graphs.event_tags(spark, sf_dir), "event", "ev"))


def few_events(spark: SparkSession, sf_dir: str) -> Task:
    """The first events, each with a label of its own."""
    return held(spark, sf_dir, "few-events", lambda: _injected(graphs.event_tags(spark, sf_dir, FEW_EVENTS), "event", "few"))


def order_items(spark: SparkSession, sf_dir: str) -> Task:
    """Every order seeded with a label of its own, among customers, parts and suppliers."""
    return held(spark, sf_dir, "orders", lambda: _injected(graphs.order_items(spark, sf_dir), "order", "orders"))


def docs(spark: SparkSession, sf_dir: str, by: str = "lang") -> Task:
    """Documents classed by language (or source) through shared tokens, 5 seeds for each."""

    def make():
        members = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("node"), F.col(by).alias("name"))
        return task(graphs.doc_tokens(spark, sf_dir), members, 5, "docs")

    return held(spark, sf_dir, f"docs-{by}", make)
