"""Exact links of texts within loose components: every pair is compared on its full sets of word shingles.

A loose component is dealt to units of bounded rows and shingles. All units of a component also get its first text,
so most large groups join there; only texts that did not join it are then compared with the component's other
units. A unit returns the stars of its local components, never its pairs, so the rows made are linear in a group
that hangs together; they grow with the square only of the number of units that stay apart within a component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bktree import Union
from .common import lean, materialise, slices
from .components import connected_components
from .words import gram_keys, keys_by_text

#: Texts whose words and shingles are held at once.
SLICE_ROWS = 500


def node_of(words: np.ndarray) -> int:
    """A signed 64-bit number of a text's words."""
    return xxhash.xxh64_intdigest(words.tobytes()) - (1 << 63)


def shingles(words: np.ndarray, shingle: int) -> np.ndarray:
    """The distinct keys of the text's shingles; a shorter text is one shingle, one without words has none."""
    return np.unique(gram_keys(words, min(shingle, len(words)))) if len(words) else words


def alike(sets: list[np.ndarray], similarity: float, known: np.ndarray | None = None) -> np.ndarray:
    """The smallest row of each row's component by pairs of at least this Jaccard similarity.

    Rows of equal ``known`` count as one component from the start; pairs within a component are not compared.
    """
    n = len(sets)
    union = Union(n)
    if known is not None:
        _, first, inverse = np.unique(known, return_index=True, return_inverse=True)
        union.add(np.arange(n), first[inverse])
    size = np.array([len(s) for s in sets], np.int64)
    flat = np.concatenate(sets)
    _, number = np.unique(flat, return_inverse=True)
    holders = np.repeat(np.arange(n), size)[np.argsort(number, kind="stable")]
    count = np.bincount(number, minlength=1)
    start = np.cumsum(count) - count
    ends = np.cumsum(size)
    for i in range(n - 1):
        root = union.roots()
        apart = root[i + 1 :] != root[i]
        if not apart.any():
            continue
        mine = number[ends[i] - size[i] : ends[i]]
        k = count[mine]
        at = np.repeat(start[mine] - (np.cumsum(k) - k), k) + np.arange(int(k.sum()))
        common = np.bincount(holders[at], minlength=n)[i + 1 :]
        hit = np.flatnonzero(apart & (common > 0) & (common >= similarity * (size[i] + size[i + 1 :] - common) - 1e-9)) + i + 1
        if len(hit):
            union.add(np.full(len(hit), i), hit)
    return union.roots()


def _solve(units: DataFrame, similarity: float, weight: int, unit_shingles: int) -> DataFrame:
    """(a, b) stars of the components in each unit; ``units`` has unit, node, known, shingles."""
    parts = max(int(units.sparkSession.conf.get("spark.sql.shuffle.partitions")), weight // unit_shingles + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(found) if (found := list(batches)) else None
        if table is None or not table.num_rows:
            return
        unit, node, known = (table.column(c).to_numpy() for c in ("unit", "node", "known"))
        held = table.column("shingles")
        order = np.lexsort((node, unit))
        for rows in np.split(order, np.flatnonzero(np.diff(unit[order])) + 1):
            sets = [np.frombuffer(held[int(i)].as_py(), np.uint64) for i in rows]
            root = alike(sets, similarity, known[rows])
            moved = np.flatnonzero(root != np.arange(len(root)))
            if len(moved):
                yield pa.RecordBatch.from_arrays([pa.array(node[rows[moved]]), pa.array(node[rows[root[moved]]])], names=["a", "b"])

    return units.select("unit", "node", "known", "shingles").repartition(parts, "unit").mapInArrow(lean(run), "a long, b long")


def exact_links(texts: DataFrame, loose: DataFrame, *, shingle: int, similarity: float, unit_rows: int = 1024, unit_shingles: int = 1 << 21, broadcast_rows: int = 1_000_000) -> DataFrame:
    """(a, b) links of nodes whose components are those of all pairs of one loose component with at least ``similarity``.

    ``texts`` has text and key, ``loose`` has node, key (of one text of the node) and component, the smallest node
    of its loose component.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in slices(whole, 2, rows=SLICE_ROWS)):
            words = keys_by_text([t.encode("utf-8", "surrogatepass") for t in batch.column(2).to_pylist()])
            keep = np.array([node_of(w) for w in words], np.int64) == batch.column(0).to_numpy()
            sets = [shingles(w, shingle) for w, k in zip(words, keep) if k]
            arrays = [batch.column(j).filter(pa.array(keep)) for j in (0, 1)] + [pa.array([len(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["node", "component", "size", "shingles"])

    side = loose.select("node", "component", F.col("key").alias("k"))
    side = F.broadcast(side) if side.count() <= broadcast_rows else side
    held = texts.join(side, F.col("key") == F.col("k")).groupBy("node", "component").agg(F.min("text").alias("text"))
    sets = materialise(held.mapInArrow(lean(run), "node long, component long, size long, shingles binary"), "near-sets")

    def parts(n: str, weight: str):
        return F.greatest(F.ceil(F.col(n) / unit_rows), F.ceil(F.col(weight) / unit_shingles), F.lit(1)).cast("int")

    def dealt(count: str):
        return F.pmod(F.xxhash64("node", F.lit(11)), F.col(count)).cast("int")

    totals = sets.groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("weight"))
    totals = materialise(totals.filter("n > 1").select(F.col("component").alias("c"), parts("n", "weight").alias("parts"), "weight"), "near-totals")
    whole = totals.agg(F.sum("weight").alias("weight"), F.max("parts").alias("parts")).first()
    rows = sets.join(totals.drop("weight"), F.col("component") == F.col("c"))
    to = F.when(F.col("node") == F.col("component"), F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array(dealt("parts")))
    first = rows.withColumn("part", F.explode(to)).withColumn("unit", F.xxhash64("component", "part")).withColumn("known", F.col("node"))
    links = materialise(_solve(first, similarity, whole["weight"] or 0, unit_shingles), "near-first")
    if (whole["parts"] or 1) == 1:
        return links
    found = connected_components(links).select(F.col("node").alias("m"), F.col("component").alias("known"))
    rows = rows.filter("parts > 1").join(found, F.col("node") == F.col("m"), "left").withColumn("known", F.coalesce("known", "node"))
    rows = materialise(rows.select("node", "component", "size", "shingles", "parts", "known", (F.coalesce("known", "node") != F.col("component")).alias("left")), "near-left")
    rest = rows.filter("left").groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("weight"))
    rest = materialise(rest.select(F.col("component").alias("c"), parts("n", "weight").alias("rest_parts")), "near-rest")
    both = rows.join(rest, F.col("component") == F.col("c"))
    to_joined, to_rest = F.sequence(F.lit(0), F.col("parts") - 1), F.sequence(F.lit(0), F.col("rest_parts") - 1)
    joined = both.filter("not left").withColumn("x", F.explode(to_rest)).withColumn("y", dealt("parts")).withColumn("kind", F.lit(0))
    left = both.filter("left").withColumn("own", dealt("rest_parts"))
    cross = left.withColumn("y", F.explode(to_joined)).withColumn("x", F.col("own")).withColumn("kind", F.lit(0))
    among = left.withColumn("other", F.explode(to_rest)).withColumn("x", F.least("own", "other")).withColumn("y", F.greatest("own", "other")).withColumn("kind", F.lit(1))
    units = None
    for part in (joined, cross, among):
        part = part.select(F.xxhash64("component", "kind", "x", "y").alias("unit"), "node", "known", "size", "shingles")
        units = part if units is None else units.unionByName(part)
    weight = units.agg(F.sum("size")).first()[0] or 0
    return links.unionByName(_solve(units, similarity, weight, unit_shingles))
