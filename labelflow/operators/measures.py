"""Measures of accuracy, memory, skew and structure."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import sketch as cms
from ..functions.sketch import SketchSpec
from ..plans.affine import AffinePlan
from ..session import cut
from .decode import pair_errors, rank_gold
from .graph import symmetrise, transition
from .propagate import delta, step


def gold_ranks(scores: DataFrame, gold: DataFrame, ties: str = "max") -> DataFrame:
    """node, label, rank of each gold label among the node's scores; null where the score is absent or 0.

    The rank counts larger scores (ties 'min'), or those at least as large ('max'), or the mean of both.
    """
    own = gold.select("node", "label").join(scores.filter("score > 0"), ["node", "label"], "left")
    rivals = scores.filter("score > 0").select("node", F.col("score").alias("other"))
    met = own.filter("score is not null").join(rivals, "node").groupBy("node", "label").agg(
        F.sum(F.when(F.col("other") > F.col("score"), 1).otherwise(0)).alias("above"), F.sum(F.when(F.col("other") >= F.col("score"), 1).otherwise(0)).alias("level"),
    )
    rank = {"min": F.col("above") + 1, "max": F.col("level"), "mean": (F.col("above") + 1 + F.col("level")) / 2}[ties]
    return gold.select("node", "label").join(met.select("node", "label", rank.cast("double").alias("rank")), ["node", "label"], "left")


def _mean_reciprocal(ranks: DataFrame) -> DataFrame:
    best = ranks.groupBy("node").agg(F.coalesce(1 / F.min("rank"), F.lit(0.0)).alias("reciprocal"))
    return best.agg(F.count(F.lit(1)).alias("nodes"), F.coalesce(F.avg("reciprocal"), F.lit(0.0)).alias("mrr"))


def class_values(gold: DataFrame, members: DataFrame, asked, value: str = "rank") -> DataFrame:
    """node, label, value of ``gold`` where ``members`` (node, of) have a class for each node (see ``lump``): ``asked`` is
    called with each pair of a class and a label once. Null for nodes without a class."""
    held = gold.select("node", "label").join(members, "node", "left")
    pairs = held.filter("of is not null").select(F.col("of").alias("node"), "label").distinct()
    found = asked(pairs).select(F.col("node").alias("c_"), F.col("label").alias("l_"), value)
    return held.join(found, (F.col("of") == F.col("c_")) & (F.col("label") == F.col("l_")), "left").select("node", "label", value)


def mrr(scores: DataFrame, gold: DataFrame, ties: str = "max", members: DataFrame | None = None) -> DataFrame:
    """nodes, mrr: the mean over gold nodes of 1 / rank of the best-ranked gold label; absent labels give 0. With
    ``members``, scores are those of classes."""
    if members is not None:
        return _mean_reciprocal(class_values(gold, members, lambda pairs: gold_ranks(scores, pairs, ties)))
    return _mean_reciprocal(gold_ranks(scores, gold, ties))


def mrr_sketch(sketch: DataFrame, gold: DataFrame, labels: DataFrame, spec: SketchSpec, ties: str = "max", digits: int | None = None, members: DataFrame | None = None) -> DataFrame:
    """As :func:`mrr`, by estimates; ranks are taken within batches of nodes, so only gold pairs leave them."""
    if members is not None:
        return _mean_reciprocal(class_values(gold, members, lambda pairs: _estimated_ranks(sketch, pairs, labels, spec, ties, digits)))
    return _mean_reciprocal(_estimated_ranks(sketch, gold, labels, spec, ties, digits))


def _estimated_ranks(sketch: DataFrame, gold: DataFrame, labels: DataFrame, spec: SketchSpec, ties: str, digits: int | None) -> DataFrame:
    met = rank_gold(sketch, gold, labels, spec, digits)
    rank = {"min": F.col("above") + 1, "max": F.col("level"), "mean": (F.col("above") + 1 + F.col("level")) / 2}[ties]
    return gold.select("node", "label").join(met.select("node", "label", rank.cast("double").alias("rank")), ["node", "label"], "left")


def random_mrr(gold: DataFrame, labels: int) -> DataFrame:
    """nodes, mrr of a random ranking, in expectation: with g gold labels of m, the sum over r of 1/r times the
    probability that the best gold label has rank r, which is C(m - r, g - 1) / C(m, g)."""
    r = F.explode(F.sequence(F.lit(1), F.lit(labels))).alias("r")
    ways = gold.groupBy("node").agg(F.countDistinct("label").alias("g")).groupBy("g").agg(F.count(F.lit(1)).alias("n"))
    choose = lambda n, k: F.exp(_log_factorial(n) - _log_factorial(k) - _log_factorial(n - k))
    share = ways.select("g", "n", r).filter(F.col("r") <= labels - F.col("g") + 1).select("g", "n", (choose(F.lit(labels) - F.col("r"), F.col("g") - 1) / choose(F.lit(labels), F.col("g")) / F.col("r")).alias("p"))
    each = share.groupBy("g", "n").agg(F.sum("p").alias("p"))
    return each.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("nodes"), F.coalesce(F.sum(F.col("n") * F.col("p")) / F.sum("n"), F.lit(0.0)).alias("mrr"))


def _log_factorial(n):
    """ln n! of a column of whole numbers (Stirling's series, exact to rounding from 10 on; smaller ones from the list)."""
    n = n.cast("double")
    large = (n + 0.5) * F.ln(n) - n + 0.5 * F.ln(F.lit(2 * 3.141592653589793)) + 1 / (12 * n) - 1 / (360 * n * n * n) + 1 / (1260 * F.pow(n, F.lit(5.0)))
    return F.when(n < 10, F.ln(F.factorial(n.cast("int")).cast("double"))).otherwise(large)


def one_hop_votes(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """node, label, score: the weight of seeded neighbours, the control that looks one or two steps far in a graph of
    items and attributes (attributes count the seeds, items their attributes)."""
    sym = symmetrise(edges)
    one = sym.join(seeds.select(F.col("node").alias("src"), "label", "score"), "src").groupBy(F.col("dst").alias("src"), "label").agg(F.sum(F.col("w") * F.col("score")).alias("score"))
    two = sym.join(one, "src").groupBy(F.col("dst").alias("node"), "label").agg(F.sum(F.col("w") * F.col("score")).alias("score"))
    return one.select(F.col("src").alias("node"), "label", "score").unionByName(two).groupBy("node", "label").agg(F.sum("score").alias("score"))


def errors(sketch: DataFrame, exact: DataFrame, pairs: DataFrame, spec: SketchSpec) -> DataFrame:
    """node, label, error = estimate - exact for pairs (node, label), zeros included."""
    est = cms.estimate(sketch, pairs, "label", ["node"], spec)
    return est.join(exact, ["node", "label"], "left").select("node", "label", (F.col("estimate") - F.coalesce("score", F.lit(0.0))).alias("error"))


def all_pairs(nodes: DataFrame, labels: int) -> DataFrame:
    """Each node with each of a small number of labels."""
    return nodes.select("node", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(labels - 1).cast("long"))).alias("label"))


def approximation_error(sketch: DataFrame, exact: DataFrame, labels: DataFrame, spec: SketchSpec, eps: float, nodes: int | None = None, sizes: DataFrame | None = None) -> DataFrame:
    """max_over, min_over, violations (errors above eps) over all pairs of a node and one of ``labels``, absent scores
    as 0; and pairs, if the number of ``nodes`` is given. ``sizes`` are those of classes (see ``lump``)."""
    out = pair_errors(sketch, exact, labels, spec, eps, sizes)
    if nodes is not None:
        out = out.withColumn("pairs", F.lit(nodes * labels.count()).cast("long"))
    return out


def state_size(scores: DataFrame, store: str, width: int = 0) -> DataFrame:
    """entries and bytes: 16 an entry in long form, 8 for each of ``width`` array cells of a node."""
    if store in ("exact_long", "sketch"):
        return scores.agg(F.count(F.lit(1)).alias("entries")).select("entries", (F.col("entries") * 16).alias("bytes"))
    return scores.agg(F.countDistinct("node").alias("nodes")).select((F.col("nodes") * width).alias("entries"), (F.col("nodes") * width * 8).alias("bytes"))


def work_units(edges: DataFrame, scores: DataFrame, cells: int) -> DataFrame:
    """exact_ops (edges times the entries at their source) and sketch_ops (edges times cells)."""
    entries = scores.groupBy(F.col("node").alias("src")).agg(F.count(F.lit(1)).alias("nnz"))
    return edges.join(entries, "src", "left").agg(F.sum(F.coalesce("nnz", F.lit(0))).alias("exact_ops"), (F.count(F.lit(1)) * cells).alias("sketch_ops"))


#: Neighbours of a seeded node whose subsets are counted.
ENDS = 12


def injected_entries(edges: DataFrame, seeds: DataFrame, steps: int) -> DataFrame:
    """times, degree, entries: how many nodes of that degree hold so many entries after 0, 1 or 2 steps from seeds of one
    label each, where every edge joins a node with a seed and one without.

    No state is made. After two steps a seeded node holds the labels of all that share a neighbour with it; these are
    counted by inclusion and exclusion over the subsets of its neighbours, of which nodes with the same ones share the
    count. Nodes without a seed hold the labels of their neighbours.
    """
    if steps not in (0, 1, 2):
        raise ValueError("entries are counted for 0, 1 or 2 steps")
    size = seeds.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("node").alias("nodes"), F.countDistinct("label").alias("labels")).first()
    if not size["n"] == size["nodes"] == size["labels"]:
        raise ValueError("each seed must have a node and a label of its own")
    own = lambda at: seeds.select(F.col("node").alias(at), F.lit(True).alias(f"{at}_own"))
    marked = edges.filter("w > 0 and src != dst").join(own("src"), "src", "left").join(own("dst"), "dst", "left")
    a, b = F.col("src_own").isNotNull(), F.col("dst_own").isNotNull()
    one = F.when(a != b, F.when(a, F.col("src")).otherwise(F.col("dst"))).otherwise(F.raise_error(F.lit("an edge joins two nodes with seeds, or two without")).cast("long"))
    pairs = cut(marked.select(one.alias("node"), F.when(a, F.col("dst")).otherwise(F.col("src")).alias("end")), "ends")
    sets = pairs.groupBy(F.col("node").alias("n_")).agg(F.sort_array(F.collect_set("end")).alias("ends"))
    held = seeds.select("node").join(sets, F.col("node") == F.col("n_"), "left").select(F.coalesce("ends", F.array().cast("array<long>")).alias("ends"))
    held = cut(held.groupBy("ends").agg(F.count(F.lit(1)).alias("times")), "end-sets")
    rest = pairs.distinct().groupBy("end").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("times"))
    rest = rest.select("times", "degree", F.col("degree").alias("entries") if steps else F.lit(0).cast("long").alias("entries"))
    degree = F.size("ends").cast("long").alias("degree")
    if steps < 2:
        return held.select("times", degree, F.lit(1).cast("long").alias("entries")).unionByName(rest)
    n = F.when(F.size("ends") <= ENDS, F.size("ends")).otherwise(F.raise_error(F.lit(f"a seeded node has over {ENDS} neighbours")).cast("int"))
    parts = held.filter(F.size("ends") > 0).select("ends", "times", F.explode(F.sequence(F.lit(1), F.pow(F.lit(2), n).cast("int") - 1)).alias("i"))
    parts = parts.select("ends", "times", F.when(F.bit_count("i") % 2 == 1, 1).otherwise(-1).alias("sign"), F.expr("filter(ends, (x, j) -> (shiftright(i, j) & 1) = 1)").alias("part"))
    shared = parts.groupBy(F.col("part").alias("p_")).agg(F.sum("times").alias("c"))
    met = parts.join(shared, F.col("part") == F.col("p_")).groupBy("ends").agg(F.first("times").alias("times"), F.sum(F.col("sign") * F.col("c")).alias("entries"))
    alone = held.filter(F.size("ends") == 0).select("times", degree, F.lit(1).cast("long").alias("entries"))
    return met.select("times", degree, "entries").unionByName(alone).unionByName(rest)


def skew_profile(scores: DataFrame, nodes: int, most: int = 256) -> DataFrame:
    """rank, mean_score over all nodes (absent ones 0), reference = first mean / rank."""
    ranked = scores.withColumn("rank", F.row_number().over(Window.partitionBy("node").orderBy(F.desc("score"), "label"))).filter(F.col("rank") <= most)
    means = cut(ranked.groupBy("rank").agg((F.sum("score") / F.lit(float(nodes))).alias("mean_score")), "profile")
    top = means.filter("rank = 1").select(F.col("mean_score").alias("top"))
    return means.join(F.broadcast(top)).select("rank", "mean_score", (F.col("top") / F.col("rank")).alias("reference"))


def zipf_exponent(profile: DataFrame, low: int = 1, high: int = 256) -> DataFrame:
    """z, the negated slope of ln mean score on ln rank."""
    return profile.filter(F.col("rank").between(low, high) & (F.col("mean_score") > 0)).agg((-F.regr_slope(F.ln("mean_score"), F.ln(F.col("rank").cast("double")))).alias("z"))


def tail_mass(values: DataFrame, by: str, val: str, k: int) -> DataFrame:
    """by, t_k: what lies outside the k largest values."""
    ranked = values.withColumn("r", F.row_number().over(Window.partitionBy(by).orderBy(F.desc(val))))
    return ranked.groupBy(by).agg(F.sum(F.when(F.col("r") > k, F.col(val)).otherwise(0.0)).alias("t_k"))


def row_norm(scores: DataFrame) -> DataFrame:
    """max_norm: the largest L1 norm of a row."""
    return scores.groupBy("node").agg(F.sum("score").alias("s")).agg(F.max("s").alias("max_norm"))


def boundary(edges: DataFrame, communities: DataFrame) -> DataFrame:
    """node, community, vol (its degree), out (the weight that leaves the community) for members."""
    sym = symmetrise(edges)
    c = communities.select(F.col("node").alias("n1"), "community")
    other = communities.select(F.col("node").alias("n2"), F.col("community").alias("c2"))
    met = sym.join(c, F.col("src") == F.col("n1")).join(other, F.col("dst") == F.col("n2"), "left")
    inside = F.col("community").eqNullSafe(F.col("c2"))
    return met.groupBy(F.col("src").alias("node"), "community").agg(F.sum("w").alias("vol"), F.sum(F.when(inside, 0.0).otherwise(F.col("w"))).alias("out"))


def conductance(edges: DataFrame, communities: DataFrame) -> DataFrame:
    """community, vol, boundary, psi (the largest share that a member sends outside), phi (boundary over the smaller
    volume); psi >= phi where the community has at most half of the volume."""
    total = edges.agg((2 * F.sum("w")).alias("total"))
    out = boundary(edges, communities).groupBy("community").agg(F.sum("vol").alias("vol"), F.sum("out").alias("boundary"), F.max(F.col("out") / F.col("vol")).alias("psi"))
    return out.join(F.broadcast(total)).select("community", "vol", "boundary", "psi", (F.col("boundary") / F.least(F.col("vol"), F.col("total") - F.col("vol"))).alias("phi"))


def escape_mass(edges: DataFrame, communities: DataFrame, steps: int) -> DataFrame:
    """node, mass, psi, bound: the probability that a walk from a member leaves its community within so many steps, the
    community's max-conductance (which bounds one step, and a walk that is absorbed when it first stops), and
    1 - (1 - psi) ** steps, which bounds them all."""
    shares = boundary(edges, communities)
    psi = shares.groupBy(F.col("community").alias("c_")).agg(F.max(F.col("out") / F.col("vol")).alias("psi"))
    walk = transition(edges)
    c = communities.select("node", "community")
    inside = walk.join(c.select(F.col("node").alias("src"), F.col("community").alias("a")), "src").join(c.select(F.col("node").alias("dst"), F.col("community").alias("b")), "dst").filter("a = b").select("src", "dst", "p")
    inside = cut(inside, "inside")
    stay = c.select("node", F.lit(1.0).alias("stay"))
    for t in range(steps):
        moved = inside.join(stay.withColumnRenamed("node", "dst"), "dst").groupBy(F.col("src").alias("node")).agg(F.sum(F.col("p") * F.col("stay")).alias("stay"))
        stay = c.select("node").join(moved, "node", "left").select("node", F.coalesce("stay", F.lit(0.0)).alias("stay"))
    mass = stay.join(c.withColumnRenamed("node", "n_"), F.col("node") == F.col("n_")).join(psi, F.col("community") == F.col("c_"))
    return mass.select("node", (1 - F.col("stay")).alias("mass"), "psi", (1 - F.pow(1 - F.col("psi"), F.lit(steps))).alias("bound"))


def reach_mass(plan: AffinePlan, seeds: DataFrame, steps: int) -> DataFrame:
    """node, label, mass: the weight of walks from a node that end at the label's seeds, the bound of its score
    where seeds are binary."""
    fixed = cut(plan.inject.join(seeds, "node").select("node", "label", (F.col("coef") * F.when(F.col("score") > 0, 1.0).otherwise(0.0)).alias("score")), "reach")
    state = seeds.select("node", "label", F.when(F.col("score") > 0, 1.0).otherwise(0.0).alias("score"))
    for _ in range(steps):
        state = step(plan.edges, fixed, state)
    return state.select("node", "label", F.col("score").alias("mass"))


def retrieval(scores: DataFrame, gold: DataFrame, cuts: tuple[int, ...] = (1, 10)) -> DataFrame:
    """item, gold, recall_at_k for each cut, reciprocal: of the ranking of each item's documents by score (ties to the
    smaller document) against its gold documents. ``scores`` has item, doc, score; ``gold`` item, doc."""
    ranked = scores.withColumn("rank", F.row_number().over(Window.partitionBy("item").orderBy(F.desc("score"), "doc"))).select(F.col("item").alias("i_"), F.col("doc").alias("d_"), "rank")
    met = gold.join(ranked, (F.col("item") == F.col("i_")) & (F.col("doc") == F.col("d_")), "left")
    recall = [F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(f"recall_at_{k}") for k in cuts]
    return met.groupBy("item").agg(F.count(F.lit(1)).alias("gold"), *recall, F.coalesce(1 / F.min("rank"), F.lit(0.0)).alias("reciprocal"))


def objective(scores: DataFrame, edges: DataFrame, seeds: DataFrame, mu: tuple[float, float, float], priors: DataFrame | None = None, sizes: DataFrame | None = None) -> DataFrame:
    """fit, smooth, prior, total: what the modified adsorption update lowers, summed over labels. With ``sizes`` (node,
    size), scores and edges are those of classes without seeds and priors, or of one node (see ``lump``).

    fit sums (Q - Y)^2 over seeded nodes, smooth is the quadratic form of the Laplacian of W' + W'^T, prior sums
    (Y - R)^2; each is weighted by its mu.
    """
    seeded = seeds.select("node").distinct()
    gap = scores.join(seeded, "node", "left_semi").select("node", "label", F.col("score").alias("y"))
    fit = gap.join(seeds.select("node", "label", F.col("score").alias("q")), ["node", "label"], "full").agg(F.coalesce(F.sum((F.coalesce("q", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))) ** 2), F.lit(0.0)).alias("fit"))
    sym = symmetrise(edges).filter("src < dst")
    from .graph import laplacian_quadratic

    smooth = laplacian_quadratic(sym, scores).agg(F.coalesce(F.sum("value"), F.lit(0.0)).alias("smooth"))
    base = scores.select("node", "label", F.col("score").alias("y"))
    if priors is not None:
        base = base.join(priors.select("node", "label", F.col("score").alias("r")), ["node", "label"], "full")
    else:
        base = base.withColumn("r", F.lit(0.0))
    times = F.lit(1)
    if sizes is not None:
        base, times = base.join(sizes.select("node", "size"), "node", "left"), F.coalesce("size", times)
    prior = base.agg(F.coalesce(F.sum(times * (F.coalesce("y", F.lit(0.0)) - F.coalesce("r", F.lit(0.0))) ** 2), F.lit(0.0)).alias("prior"))
    one = fit.join(F.broadcast(smooth)).join(F.broadcast(prior))
    return one.select((mu[0] * F.col("fit")).alias("fit"), (mu[1] * F.col("smooth")).alias("smooth"), (mu[2] * F.col("prior")).alias("prior")).withColumn("total", F.expr("fit + smooth + prior"))


def max_delta(before: DataFrame, after: DataFrame) -> DataFrame:
    return delta(before, after).agg(F.max(F.abs("delta")).alias("max_delta"))
