"""One object from graph to result: ``LabelFlow(spark).graph(...).seed(...).plan(...).run(...)``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import sizing
from .functions.sketch import SketchSpec
from .operators.graph import Graph, clean
from .operators.propagate import PropagationResult, propagate
from .plans import affine
from .plans.affine import AffinePlan
from .schema import require
from .session import cut
from .sources.seeds import seed_sparsity

METHODS = ("modified_adsorption", "harmonic", "adsorption", "absorbing_walk", "restart_walk")


class LabelFlow:
    """A propagation task, built step by step; each step returns the object."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.nodes: DataFrame | None = None
        self.edges: DataFrame | None = None
        self.seeds: DataFrame | None = None
        self.priors: DataFrame | None = None
        self.labels: int | None = None
        self._plan: AffinePlan | None = None

    def graph(self, edges: DataFrame | Graph, nodes: DataFrame | None = None) -> "LabelFlow":
        """The graph: edges (src, dst, w), checked and with loops and parallels merged; nodes (node) add isolated ones."""
        if isinstance(edges, Graph):
            edges, nodes = edges.edges, edges.nodes
        self.edges = cut(clean(require(edges, "edges")), "graph")
        self.nodes = nodes.select("node") if nodes is not None else None
        return self

    def seed(self, seeds: DataFrame, priors: DataFrame | None = None, labels: int | None = None) -> "LabelFlow":
        """Seeds and priors (node, label, score); ``labels`` is their number if not all are seeded."""
        self.seeds = cut(require(seeds, "scores"), "seeds")
        self.priors = require(priors, "scores") if priors is not None else None
        self.labels = labels or (self.seeds.agg(F.max("label")).first()[0] or 0) + 1
        return self

    def plan(self, method: str | AffinePlan = "modified_adsorption", **params) -> "LabelFlow":
        """The update: a name of METHODS with its parameters, or an affine plan of one's own."""
        if self.edges is None or self.seeds is None:
            raise ValueError("a plan needs a graph and seeds")
        if isinstance(method, AffinePlan):
            self._plan = method
        elif method not in METHODS:
            affine.squared_loss_only(method)
        else:
            if method in ("modified_adsorption", "adsorption"):
                params = {"nodes": self.nodes} | params
            self._plan = getattr(affine, method)(self.edges, self.seeds, **params)
        return self

    def spec(self, rule: str | tuple[int, int] | SketchSpec = "sparse", eps: float = 0.05, delta: float = 0.1, z: float | None = None, seed: int = 42) -> SketchSpec:
        """A sketch by a sizing rule ('sparse', or 'zipf' with the exponent z), or of a given width and depth."""
        if isinstance(rule, SketchSpec):
            return rule
        if isinstance(rule, tuple):
            return SketchSpec.create(*rule, seed)
        if rule == "sparse":
            k = seed_sparsity(self.seeds).first()["k"] or 1.0
            return sizing.size_sparse(k, self.labels, eps, delta).spec(seed)
        if rule == "zipf" and z:
            return sizing.size_zipf(eps, z, delta).spec(seed)
        raise ValueError("a sketch is sized by 'sparse', by 'zipf' with z, or by (width, depth)")

    def run(self, store: str = "auto", spec: str | tuple[int, int] | SketchSpec | None = None, **options) -> PropagationResult:
        """Iterate; see :func:`operators.propagate.propagate` for stores and options (max_iter, tol, budget, trace, init)."""
        if self._plan is None:
            self.plan()
        made = self.spec(spec) if spec is not None else self.spec() if store.startswith("sketch") else None
        return propagate(self._plan, self.seeds, self.priors, store=store, spec=made, labels=self.labels, **options)
