"""Widths and depths that keep the error of estimates within a bound."""

from __future__ import annotations

import math
from dataclasses import dataclass

from .sketch import SketchSpec


@dataclass(frozen=True)
class Size:
    width: int
    depth: int
    rule: str
    flag: str = ""

    def spec(self, seed: int = 42) -> SketchSpec:
        return SketchSpec.create(self.width, self.depth, seed)


def _up(x: float) -> int:
    return max(1, math.ceil(x - 1e-12))


def size_basic(eta: float, delta: float) -> Size:
    """Error at most eta times the vector's L1 norm, for one estimate, with probability 1 - delta."""
    return Size(_up(math.e / eta), _up(math.log(1 / delta)), "basic")


def size_sparse(k: float, m: int, eps: float, delta: float, simultaneous_nodes: int = 1) -> Size:
    """Error below eps for all m labels (of one node, or of so many) when rows of seeds have mass k at most."""
    return Size(_up(math.e * k / eps), _up(math.log(simultaneous_nodes * m / delta)), "sparse")


def size_tail(k: int, eta: float, delta: float, printed: bool = False) -> Size:
    """Error at most eta times the mass outside the k largest components.

    The published text states a width of 1/(3k) and multiplies the depth by ln(3/2); its argument needs more than 3k
    bins, and a failure of 2/3 for each row needs the division. ``printed`` gives the stated formula.
    """
    if printed:
        return Size(max(_up(1 / (3 * k)), _up(math.e / eta)), _up(math.log(1.5) * math.log(1 / delta)), "tail-printed", "width and depth as stated don't support the argument")
    return Size(max(3 * k + 1, _up(3 / eta)), _up(math.log(1 / delta) / math.log(1.5)), "tail")


def size_zipf(eta: float, z: float, delta: float) -> Size:
    """For values that fall as rank to the power -z."""
    return Size(_up(math.e * eta ** -min(1.0, 1 / z)), _up(math.log(1 / delta)), "zipf")


def size_zipf_printed(eps: float, z: float, m: int, delta: float) -> Size:
    """The corollary as stated for z > 1; it disagrees with :func:`size_zipf` and is never a default."""
    if z <= 1:
        raise ValueError("stated for z > 1 only")
    return Size(_up(math.e / eps ** (z - 1)), _up(math.log(m / delta)), "zipf-printed", "inconsistent with the theorem it follows")


def size_community(k: int, psi: float, eps: float, m: int, delta: float) -> Size:
    """For communities whose max-conductance is at most psi, k labels inside."""
    return Size(max(3 * k + 1, _up(math.e * psi / eps)), _up(math.log(m / delta)), "community")


def recommend(k: float, m: int, eps: float, delta: float, z: float | None = None) -> Size:
    """The sparse rule, unless a skew fitted above 1 gives a narrower sketch."""
    sparse = size_sparse(k, m, eps, delta)
    if z is None or z <= 1:
        return sparse
    zipf = size_zipf(eps, z, delta)
    return Size(zipf.width, sparse.depth, "zipf") if zipf.width < sparse.width else sparse


def expected_entries(nodes: int, edges: int, seeds: int, m: int, steps: int) -> float:
    """Entries of a node that ``steps`` steps over ``edges`` directed edges let expect: its share of the seeds, times the
    mean degree for each step, and at most all m labels."""
    mean = edges / max(nodes, 1)
    return min(float(m), seeds / max(nodes, 1) * (1 + mean) ** min(steps, 64))


def choose_store(m: int, cells: int, nnz_per_node: float) -> str:
    """The layout with the fewest bytes for each node: 16 an entry (long), 8 a label (dense), 8 a cell (sketch)."""
    cost = {"exact_long": 16 * nnz_per_node, "exact_dense": 8.0 * m, "sketch": 8.0 * cells}
    return min(cost, key=lambda s: (cost[s], s))
