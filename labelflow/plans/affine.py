"""The affine intermediate form: Y_v <- inject_v Q_v + sum over u of coef_uv Y_u + prior_v R_v.

All propagation methods compile to it before any iteration; constants are divided and folded once. A method that
mixes labels, or whose update isn't linear, has no such form and can't run on sketches.
"""

from __future__ import annotations

import warnings
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import row_normalise, strip_self_loops, sym_normalise, symmetrise
from ..session import cut, rest


@dataclass
class AffinePlan:
    inject: DataFrame  # node, coef
    edges: DataFrame  # src, dst, coef
    prior: DataFrame  # node, coef
    method: str = "custom"
    at_rest: bool = False  # whether the edges lie in buckets by source (see operators.propagate.place)
    hubs: DataFrame | None = None  # src, salts: sources of edges at rest that are dealt over several buckets
    pairs: DataFrame | None = None  # src, dst, w of the edges, at rest in buckets by dst: each pair once in each direction

    def row_weight(self) -> DataFrame:
        """node, weight: the total of each node's coefficients from neighbours; with inject and prior at most 1."""
        parts = [self.edges.select(F.col("dst").alias("node"), "coef"), self.inject, self.prior]
        return reduce(DataFrame.unionByName, parts).groupBy("node").agg(F.sum("coef").alias("weight"))


def _isolated(nodes: DataFrame | None, *known: DataFrame) -> DataFrame:
    every = [k.select("node") for k in known] + ([nodes.select("node")] if nodes is not None else [])
    return reduce(DataFrame.unionByName, every).distinct()


def normaliser(edges: DataFrame, seeds: DataFrame, mu: tuple[float, float, float], nodes: DataFrame | None = None, indicator: DataFrame | None = None) -> DataFrame:
    """node, m_vv = mu1 S_vv + mu2 sum of A_uv + mu3, for all nodes. ``edges`` are symmetrised (src, dst, w);
    ``indicator`` (node, s) replaces the 0/1 of seeds."""
    pulled = strip_self_loops(edges).groupBy(F.col("dst").alias("node")).agg(F.sum("w").alias("a"))
    s = indicator if indicator is not None else seeds.select("node").distinct().withColumn("s", F.lit(1.0))
    every = _isolated(nodes, pulled, s)
    joined = every.join(pulled, "node", "left").join(s, "node", "left")
    m = mu[0] * F.coalesce("s", F.lit(0.0)) + mu[1] * F.coalesce("a", F.lit(0.0)) + F.lit(float(mu[2]))
    return joined.select("node", F.coalesce("s", F.lit(0.0)).alias("s"), m.alias("m_vv"))


def modified_adsorption(edges: DataFrame, seeds: DataFrame, mu: tuple[float, float, float] = (0.98, 0.01, 0.01), nodes: DataFrame | None = None, probs: str | float = "indicator", loops: str = "strip", at_rest: bool = False) -> AffinePlan:
    """The default method. ``edges`` hold each pair once. ``probs``: 'indicator' (S is 0/1 and W' = W), 'entropy', or
    a number p (inject p on seeds, continue otherwise). ``loops='keep'`` counts self-loops in M as well. ``at_rest`` writes the pairs in
    buckets by node, and M, once for all that reads the plan."""
    if sum(mu) > 1 + 1e-12:
        warnings.warn("the mu's sum to over 1; updates are weighted means all the same, but the stated bound assumes at most 1", stacklevel=2)
    if probs == "indicator":
        directed, indicator = symmetrise(edges, int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")) if at_rest else None), None
    else:
        p = walk_probabilities(edges, seeds, probs, nodes)
        sym = symmetrise(edges)
        out = sym.join(p.select(F.col("node").alias("dst"), "p_continue"), "dst").select("src", "dst", (F.col("w") * F.col("p_continue")).alias("w"))
        # W'_uv + W'_vu, each pair now in both directions with its own factor
        back = out.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
        directed = out.unionByName(back).groupBy("src", "dst").agg(F.sum("w").alias("w"))
        indicator = p.select("node", F.col("p_inject").alias("s"))
    if loops == "strip":
        directed = strip_self_loops(directed)
    if at_rest:
        directed = rest(directed, "pairs", "dst")
    m = normaliser(directed, seeds, mu, nodes, indicator)
    if at_rest:
        m = cut(m, "normaliser")
    if loops == "keep":
        own = directed.filter("src = dst").select(F.col("src").alias("node"), F.col("w").alias("loop"))
        m = m.join(own, "node", "left").select("node", "s", (F.col("m_vv") + mu[1] * F.coalesce("loop", F.lit(0.0))).alias("m_vv"))
    coef = directed.join(m.select(F.col("node").alias("dst"), "m_vv"), "dst").select("src", "dst", (mu[1] * F.col("w") / F.col("m_vv")).alias("coef"))
    inject = m.filter("s > 0").select("node", (mu[0] * F.col("s") / F.col("m_vv")).alias("coef"))
    return AffinePlan(inject, coef, m.select("node", (F.lit(float(mu[2])) / F.col("m_vv")).alias("coef")), "modified_adsorption", pairs=directed if at_rest else None)


def walk_probabilities(edges: DataFrame, seeds: DataFrame, mode: str | float = "entropy", nodes: DataFrame | None = None, beta: float = 2.0) -> DataFrame:
    """node, p_inject, p_continue, p_abandon. 'entropy' weighs by the entropy H of a node's neighbours:
    c = ln beta / ln(beta + e^H), d = (1 - c) sqrt(H) on seeds, both divided by max(c + d, 1)."""
    sym = strip_self_loops(symmetrise(edges))
    total = sym.groupBy("dst").agg(F.sum("w").alias("t")).withColumnRenamed("dst", "d_")
    share = F.col("w") / F.col("t")
    entropy = sym.join(total, F.col("dst") == F.col("d_")).groupBy(F.col("dst").alias("node")).agg(F.sum(-share * F.ln(share)).alias("h"))
    s = seeds.select("node").distinct().withColumn("seed", F.lit(1))
    every = _isolated(nodes, entropy, s).join(entropy, "node", "left").join(s, "node", "left")
    h, seeded = F.coalesce("h", F.lit(0.0)), F.col("seed").isNotNull()
    if mode == "indicator":
        return every.select("node", F.when(seeded, 1.0).otherwise(0.0).alias("p_inject"), F.lit(1.0).alias("p_continue"), F.lit(0.0).alias("p_abandon"))
    if mode == "entropy":
        c = F.ln(F.lit(beta)) / F.ln(F.lit(beta) + F.exp(h))
        d = F.when(seeded, (1 - c) * F.sqrt(h)).otherwise(0.0)
        z = F.greatest(c + d, F.lit(1.0))
        return every.select("node", (d / z).alias("p_inject"), (c / z).alias("p_continue"), (1 - d / z - c / z).alias("p_abandon"))
    p = float(mode)
    return every.select("node", F.when(seeded, p).otherwise(0.0).alias("p_inject"), F.when(seeded, 1 - p).otherwise(1.0).alias("p_continue"), F.lit(0.0).alias("p_abandon"))


def dummy_prior(probabilities: DataFrame, label: int) -> DataFrame:
    """Prior rows that give each node's abandon probability to the label 'none of these'."""
    return probabilities.filter("p_abandon > 0").select("node", F.lit(label).cast("long").alias("label"), F.col("p_abandon").alias("score"))


def _no_prior(frame: DataFrame) -> DataFrame:
    return frame.select("node", F.lit(0.0).alias("coef")).limit(0)


def harmonic(edges: DataFrame, seeds: DataFrame) -> AffinePlan:
    """Seeds keep their scores; every other node is the weighted mean of its neighbours."""
    coef = row_normalise(strip_self_loops(symmetrise(edges)))
    seeded = seeds.select("node").distinct()
    free = coef.join(seeded.withColumnRenamed("node", "dst"), "dst", "left_anti").select("src", "dst", "coef")
    inject = seeded.select("node", F.lit(1.0).alias("coef"))
    return AffinePlan(inject, free, _no_prior(inject), "harmonic")


def adsorption(edges: DataFrame, seeds: DataFrame, probs: str | float = "entropy", nodes: DataFrame | None = None) -> AffinePlan:
    """The predecessor: a three-way mean by the probabilities to inject, continue and abandon."""
    p = walk_probabilities(edges, seeds, probs, nodes)
    coef = row_normalise(strip_self_loops(symmetrise(edges)))
    coef = coef.join(p.select(F.col("node").alias("dst"), "p_continue"), "dst").select("src", "dst", (F.col("coef") * F.col("p_continue")).alias("coef"))
    return AffinePlan(p.filter("p_inject > 0").select("node", F.col("p_inject").alias("coef")), coef, p.filter("p_abandon > 0").select("node", F.col("p_abandon").alias("coef")), "adsorption")


def absorbing_walk(edges: DataFrame, seeds: DataFrame, lam: float | DataFrame = 1.0) -> AffinePlan:
    """A walk that is absorbed at a node with rate lam against its degree; ``lam`` is one rate, or (node, lam) with a
    rate for each node (0 where absent)."""
    sym = strip_self_loops(symmetrise(edges))
    deg = sym.groupBy(F.col("dst").alias("node")).agg(F.sum("w").alias("deg"))
    every = _isolated(None, deg, seeds).join(deg, "node", "left").withColumn("deg", F.coalesce("deg", F.lit(0.0)))
    if isinstance(lam, DataFrame):
        every = every.join(lam.select("node", "lam"), "node", "left").withColumn("lam", F.coalesce("lam", F.lit(0.0)))
    else:
        every = every.withColumn("lam", F.lit(float(lam)))
    coef = sym.join(every.withColumnRenamed("node", "dst"), "dst").select("src", "dst", (F.col("w") / (F.col("lam") + F.col("deg"))).alias("coef"))
    inject = seeds.select("node").distinct().join(every, "node").filter("lam > 0").select("node", (F.col("lam") / (F.col("lam") + F.col("deg"))).alias("coef"))
    return AffinePlan(inject, coef, _no_prior(inject), "absorbing_walk")


def restart_walk(edges: DataFrame, seeds: DataFrame, alpha: float = 0.85, norm: str = "row") -> AffinePlan:
    """Local and global consistency: alpha of the neighbours, 1 - alpha of the seeds. ``norm='sym'`` may exceed the
    L1 contraction; :func:`assert_substochastic` tells."""
    sym = strip_self_loops(symmetrise(edges))
    coef = (row_normalise if norm == "row" else sym_normalise)(sym)
    inject = seeds.select("node").distinct().select("node", F.lit(1.0 - alpha).alias("coef"))
    return AffinePlan(inject, coef.select("src", "dst", (alpha * F.col("coef")).alias("coef")), _no_prior(inject), "restart_walk")


def custom_plan(inject: DataFrame, edges: DataFrame, prior: DataFrame | None = None, check: bool = True) -> AffinePlan:
    plan = AffinePlan(inject.select("node", "coef"), edges.select("src", "dst", "coef"), prior.select("node", "coef") if prior is not None else _no_prior(inject))
    if check:
        assert_substochastic(plan)
    return plan


def assert_substochastic(plan: AffinePlan, slack: float = 1e-9) -> None:
    """Raise if some node's coefficients sum to over 1, or one is negative: then bounds on scores don't hold."""
    if plan.edges.filter("coef < 0").limit(1).count() or plan.row_weight().filter(F.col("weight") > 1 + slack).limit(1).count():
        raise ValueError("the plan isn't a weighted mean: its coefficients are negative or sum to over 1")


def squared_loss_only(method: str) -> None:
    """Refuse methods without a linear update."""
    raise NotImplementedError(f"{method}: its update isn't linear in the scores, so it can't run on sketches")


def check_assumptions(seeds: DataFrame, mu: tuple[float, float, float], edges: DataFrame | None = None, priors: DataFrame | None = None) -> dict[str, bool]:
    """Which conditions of the sparse bound hold: sums of mu, binary and sparse seeds, light priors, no loops."""
    mass = seeds.groupBy("node").agg(F.sum("score").alias("s")).agg(F.max("s")).first()[0] or 0.0
    out = {"mu_sum": sum(mu) <= 1 + 1e-12, "binary": not seeds.filter("score not in (0.0, 1.0)").limit(1).count(), "non_negative": not seeds.filter("score < 0").limit(1).count()}
    if priors is not None:
        heaviest = priors.groupBy("node").agg(F.sum("score").alias("s")).agg(F.max("s")).first()[0] or 0.0
        out["prior_mass"] = heaviest <= mass + 1e-12
    if edges is not None:
        out["no_loops"] = not edges.filter("src = dst").limit(1).count()
    return out
