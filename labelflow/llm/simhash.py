"""SimHash near-duplicates: 64-bit fingerprints of word shingles, linked within a Hamming radius by BK-trees.

Fingerprints that differ in at most r bits agree on at least two of r + 2 blocks of their bits, so each choice of
two blocks is one table of buckets and no link is lost; the number of tables is the same at every size. A bucket's fingerprints are one shard tree: children are
keyed by their Hamming distance to the parent and a search follows only the edges within the radius. The trees are
not broadcast, as their total grows with the corpus; each is built in the task to which its bucket was dealt and
is searched there by the bucket's own members. A bucket of more than ``tree_size`` fingerprints becomes several
trees, and each pair of them is a unit of work of its own. A unit returns the stars of its local components, never
its pairs; connected components then join the units. Equal fingerprints meet before, by aggregation.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bktree import Forest, Union
from .common import ROW, id_of, lean, materialise, slices, text_of, with_row_key, without_ids
from .components import connected_components
from .verify import SLICE_ROWS, exact_links, node_of, shingles
from .words import gram_keys, keys_by_text, mix

SHINGLE_SEED = 42
_CHUNK = 1 << 16


def fingerprint(text: str, shingle: int = 3) -> int:
    """The 64-bit SimHash: bit j is set if it is set in over half of the shingles' hashes."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    body = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = ends - np.array([len(w) + 1 for w in words])
    k = min(shingle, len(words))
    spans = zip(starts[: len(words) - k + 1].tolist(), (ends[k - 1 :] - 1).tolist())
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(body[a:b], SHINGLE_SEED) for a, b in spans), np.uint64, len(words) - k + 1)
    ones = np.zeros(64, np.int64)
    for i in range(0, len(hashes), _CHUNK):
        bits = np.unpackbits(hashes[i : i + _CHUNK].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed long) for each row; null texts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = np.array([fingerprint(x.as_py(), shingle) for x in batch.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp, pa.int64())], names=["doc_id", "fp"])

    return docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(lean(run), "doc_id long, fp long")


def _bucket_keys(fp: Column, blocks: int, radius: int, first: int) -> Column:
    edges = [64 * i // blocks for i in range(blocks + 1)]
    tables = []
    for t, chosen in enumerate(combinations(range(blocks), blocks - radius)):
        mask = sum(((1 << edges[i + 1]) - (1 << edges[i])) for i in chosen)
        signed = mask - (1 << 64) if mask >> 63 else mask
        tables.append(F.struct(F.lit(first + t).alias("t"), fp.bitwiseAND(F.lit(signed)).alias("bits")))
    return F.array(*tables)


def hamming_links(nodes: DataFrame, *, radius: int = 3, tree_size: int = 1024, unit_rows: int = 200_000) -> DataFrame:
    """(a, b) links of ``node`` longs whose components are those of all pairs of ``fp`` within ``radius`` bits."""
    n, blocks = nodes.count(), radius + 2
    tables = nodes.select("node", "fp", F.explode(_bucket_keys(F.col("fp"), blocks, radius, 0)).alias("key"))
    counts = tables.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("key").alias("k"), "n")
    held = tables.join(counts, F.col("key") == F.col("k")).withColumn("trees", F.ceil(F.col("n") / tree_size).cast("int"))
    units = (
        held.withColumn("own", F.pmod(F.xxhash64("node", F.lit(7)), F.col("trees")).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("trees") - 1)))
        .select("node", "fp", F.xxhash64("key.t", "key.bits", F.least("own", "other"), F.greatest("own", "other")).alias("unit"))
    )
    parts = max(int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions")), n * math.comb(blocks, radius) // unit_rows + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(found) if (found := list(batches)) else None
        if table is None or not table.num_rows:
            return
        node = table.column("node").to_numpy()
        forest, union = Forest(table.column("fp").to_numpy().view(np.uint64), table.column("unit").to_numpy()), Union(len(node))
        for a, b in forest.search(radius):
            union.add(a, b)
        root = union.roots()
        moved = np.flatnonzero(root != np.arange(len(root)))
        yield pa.RecordBatch.from_arrays([pa.array(node[moved]), pa.array(node[root[moved]])], names=["a", "b"])

    return units.repartition(parts, "unit").mapInArrow(lean(run), "a long, b long")


def star_links(keyed: DataFrame) -> DataFrame:
    """(a, b) links of each ``node`` to the smallest one of the same ``key``."""
    lows = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("b")).filter("n > 1").select(F.col("key").alias("k"), "b")
    return keyed.join(lows, F.col("key") == F.col("k")).filter("node != b").select(F.col("node").alias("a"), "b")


def pair_prints(words: np.ndarray) -> tuple[int, int]:
    """Two fingerprints of the word pairs under independent hashes."""
    pairs = gram_keys(words, min(2, len(words))) if len(words) else words
    out = []
    for salt in (0x1B873593, 0x85EBCA6B):
        ones = np.zeros(64, np.int64)
        for i in range(0, len(pairs), _CHUNK):
            hashes = mix(pairs[i : i + _CHUNK] * np.uint64(2 * salt + 1))
            ones += np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out.append(int(np.packbits(ones * 2 > len(pairs), bitorder="little").view("<i8")[0]))
    return out[0], out[1]


def simhash_components(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3, tree_size: int = 1024) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable by links) for each row.

    Words are runs of non-space after lower-casing A-Z; a text of fewer words than ``shingle`` is one shingle, one
    without words has fingerprint zero and links like any other. Repeated rows share their component; null ids take
    part in links but are never the smallest (component_id is null where all ids are). An empty table gives an
    empty result; other columns are ignored.
    """
    fps = materialise(fingerprints(docs, id_col=id_col, text_col=text_col, shingle=shingle), "simhash-fps")
    distinct = materialise(fps.groupBy("fp").agg(F.min("doc_id").alias("low")), "simhash-distinct")
    links = hamming_links(distinct.withColumn("node", F.col("fp")), radius=radius, tree_size=tree_size)
    nodes = materialise(connected_components(links), "simhash-nodes")
    label = distinct.join(nodes.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", F.coalesce("component", "fp").alias("label"))
    lows = label.groupBy("label").agg(F.min("low").alias("component_id"))
    members = label.join(lows, "label").select(F.col("fp").alias("f"), "component_id")
    return fps.join(members, F.col("fp") == F.col("f")).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def band_keys(keys: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """A key for each band of ``rows`` least hashes of a set of shingle keys; two sets share one with probability J ** rows."""
    if not len(keys):
        return np.empty(0, np.uint64)
    odd = np.random.default_rng(20240301).integers(0, 1 << 63, bands * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    low = np.full(bands * rows, np.iinfo(np.uint64).max, np.uint64)
    step = max(1, (1 << 16) // (bands * rows))
    for i in range(0, len(keys), step):
        low = np.minimum(low, mix(keys[i : i + step, None] * odd).min(axis=0))
    out = np.arange(bands, dtype=np.uint64)
    for column in low.reshape(bands, rows).T:
        out = mix(out * np.uint64(3) ^ column)
    return out


def near_components(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, similarity: float = 0.8, radius: int = 3, bands: int = 24, band_rows: int = 5, tree_size: int = 1024, unit_rows: int = 1024) -> DataFrame:
    """doc_id, component_id (smallest doc_id reachable) for each row, by resemblance of word shingles.

    Loose components join texts within ``radius`` bits in either of two fingerprints of word pairs, and texts that
    share one of ``bands`` keys of ``band_rows`` least hashes of their shingles. The latter alone meet a pair of
    Jaccard similarity J with probability 1 - (1 - J ** band_rows) ** bands whatever the edit: 0.99993 at 0.8.
    Within a loose component all pairs are compared on their full sets of shingles and linked if the similarity is
    at least ``similarity``. Texts shorter than a shingle are one shingle; texts without
    words resemble each other only. Nulls, repeated rows and other columns are as in :func:`simhash_components`.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in slices(whole, 2, rows=SLICE_ROWS)):
            words = keys_by_text([t.encode("utf-8", "surrogatepass") for t in batch.column(2).to_pylist()])
            prints = [pair_prints(w) for w in words]
            arrays = [batch.column(0), batch.column(1), pa.array([node_of(w) for w in words], pa.int64()), *(pa.array([x[j] for x in prints], pa.int64()) for j in (0, 1))]
            arrays.append(pa.array([band_keys(shingles(w, shingle), bands, band_rows).view(np.int64) for w in words], pa.list_(pa.int64())))
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "key", "node", "fp", "fp2", "bands"])

    texts = docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text"))
    keyed = texts.select("doc_id", F.xxhash64("text").alias("key"), "text")
    rows = materialise(keyed.mapInArrow(lean(run), "doc_id long, key long, node long, fp long, fp2 long, bands array<long>"), "near-rows")
    nodes = materialise(rows.groupBy("node", "fp", "fp2", "bands").agg(F.min("doc_id").alias("low"), F.min("key").alias("key")), "near-nodes")
    loose = star_links(nodes.select("node", F.explode("bands").alias("key")))
    for c in ("fp", "fp2"):
        prints = materialise(nodes.groupBy(F.col(c).alias("fp")).agg(F.min("node").alias("node")), "near-prints")
        for part in (star_links(nodes.select("node", F.col(c).alias("key"))), hamming_links(prints, radius=radius, tree_size=tree_size)):
            loose = loose.unionByName(part)
    held = materialise(connected_components(loose), "near-loose").join(nodes.select(F.col("node").alias("m"), "key"), F.col("node") == F.col("m")).select("node", "key", "component")
    links = exact_links(keyed.select("key", "text"), held, shingle=shingle, similarity=similarity, unit_rows=unit_rows)
    found = materialise(connected_components(links), "near-components")
    label = nodes.select("node", "low").join(found, "node", "left").select("node", "low", F.coalesce("component", "node").alias("label"))
    lows = label.groupBy("label").agg(F.min("low").alias("component_id"))
    members = label.join(lows, "label").select(F.col("node").alias("n_"), "component_id")
    return rows.select("doc_id", "node").join(members, F.col("node") == F.col("n_")).select("doc_id", "component_id")


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row of each component by :func:`near_components`, that of the smallest id, with all columns.

    Null ids come last; rows of one id and text stay or go together, those of one id and different texts do not.
    """
    rows = with_row_key(docs, id_col, text_col)
    found = near_components(rows, id_col=ROW, text_col=text_col, **options).withColumnRenamed("doc_id", "row")
    ids = rows.select(F.col(ROW).alias("r"), id_of(id_col).alias("id")).distinct()
    found = materialise(found.distinct().join(ids, F.col("row") == F.col("r")).select("row", "component_id", F.struct(F.col("id").isNull(), "id", "row").alias("rank")), "near-ranks")
    kept = found.groupBy("component_id").agg(F.min("rank").alias("least"))
    kept = kept.select(F.col("component_id").alias("c"), F.col("least.row").alias("stays"))
    gone = found.join(kept, F.col("component_id") == F.col("c")).filter("row != stays").select("row")
    return without_ids(rows, gone, ROW).drop(ROW)
