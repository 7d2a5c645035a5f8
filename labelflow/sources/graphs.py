"""Graph builders over the given tables. Node ids are natural keys where these are dense, else dense numbers."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.graph import Graph, encode_ids
from ..session import cut
from .tables import table

WORD = "[a-zà-öø-ÿ]+"


def _attributes(links: DataFrame, first: int) -> tuple[DataFrame, DataFrame]:
    """(node, kind, key) of the attribute side of links (src, kind, key), and the edges."""
    links = cut(links, "links")
    ids = encode_ids(links, ["kind", "key"], "node", first)
    edges = links.join(ids.select(F.col("kind").alias("k_"), F.col("key").alias("y_"), F.col("node").alias("dst")), (F.col("kind") == F.col("k_")) & (F.col("key") == F.col("y_")))
    return ids.select("node", "kind", "key"), edges.select("src", "dst", F.lit(1.0).alias("w"))


def part_attributes(spark: SparkSession, sf_dir: str, noise: bool = False) -> DataFrame:
    """src, kind, key: brand, type and the two words of the name of each part (and its size, as noise)."""
    words = F.split("p_name", " ")
    pairs = [("brand", F.col("p_brand")), ("type", F.col("p_type")), ("word1", words[0]), ("word2", words[1])]
    pairs += [("size", F.col("p_size").cast("string"))] if noise else []
    cells = F.array(*[F.struct(F.lit(k).alias("kind"), v.alias("key")) for k, v in pairs])
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("src"), F.inline(cells))


def parts_kb(spark: SparkSession, sf_dir: str, noise: bool = False) -> Graph:
    """Parts linked to their attributes."""
    part = table(spark, sf_dir, "part")
    top = part.agg(F.max("p_partkey")).first()[0] or 0
    nodes, edges = _attributes(part_attributes(spark, sf_dir, noise), top + 1)
    own = part.select(F.col("p_partkey").alias("node"), F.lit("part").alias("kind"), F.col("p_partkey").cast("string").alias("key"))
    return Graph(own.unionByName(nodes), edges)


def part_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """node, name: the two classes of each part, brand with type and its name."""
    both = F.array(F.concat_ws("|", F.lit("bt"), "p_brand", "p_type"), F.concat_ws("|", F.lit("nm"), "p_name"))
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), F.explode(both).alias("name"))


def event_tags(spark: SparkSession, sf_dir: str, max_event_id: int | None = None) -> Graph:
    """Events linked to their user and to the value k of their properties."""
    events = table(spark, sf_dir, "events")
    if max_event_id is not None:
        events = events.filter(F.col("event_id") < max_event_id)
    k = F.from_json("props", "k int")["k"].cast("string")
    cells = F.array(F.struct(F.lit("k").alias("kind"), k.alias("key")), F.struct(F.lit("user").alias("kind"), F.col("user_id").cast("string").alias("key")))
    top = events.agg(F.max("event_id")).first()[0] or 0
    nodes, edges = _attributes(events.select(F.col("event_id").alias("src"), F.inline(cells)).filter("key is not null"), top + 1)
    own = events.select(F.col("event_id").alias("node"), F.lit("event").alias("kind"), F.col("event_id").cast("string").alias("key"))
    return Graph(own.unionByName(nodes), edges)


def _numbered(links: DataFrame) -> Graph:
    """A graph from links (kind1, key1, kind2, key2, w), all ends numbered."""
    links = cut(links, "links")
    ends = links.select(F.col("kind1").alias("kind"), F.col("key1").alias("key")).unionByName(links.select(F.col("kind2").alias("kind"), F.col("key2").alias("key")))
    ids = cut(encode_ids(ends, ["kind", "key"], "node"), "nodes").select("node", "kind", "key")
    a = ids.select(F.col("node").alias("src"), F.col("kind").alias("kind1"), F.col("key").alias("key1"))
    b = ids.select(F.col("node").alias("dst"), F.col("kind").alias("kind2"), F.col("key").alias("key2"))
    return Graph(ids, links.join(a, ["kind1", "key1"]).join(b, ["kind2", "key2"]).select("src", "dst", "w"))


def _numbered_keys(links: list[tuple[str, str, DataFrame, bool]]) -> Graph:
    """As :func:`_numbered`, from links (a, b) of whole numbers for each two kinds, which may have to be made distinct. Numbers, not
    text, meet and move; the ids follow the order of the text all the same."""
    keys, ends = {}, None
    for kind1, kind2, df, _ in links:
        for kind, key in ((kind1, "a"), (kind2, "b")):
            one = df.select(F.col(key).alias("key"))
            keys[kind] = keys[kind].unionByName(one) if kind in keys else one
    for kind, of_kind in keys.items():
        one = of_kind.distinct().select(F.lit(kind).alias("kind"), F.col("key").cast("string").alias("key"))
        ends = one if ends is None else ends.unionByName(one)
    ids = cut(encode_ids(ends, ["kind", "key"], "node", unique=True), "nodes").select("node", "kind", "key")
    of = lambda kind, key, node: ids.filter(F.col("kind") == kind).select(F.col("key").cast("long").alias(key), F.col("node").alias(node))
    edges = None
    for kind1, kind2, df, repeated in links:
        met = (df.distinct() if repeated else df).join(of(kind1, "a", "src"), "a").join(of(kind2, "b", "dst"), "b").select("src", "dst", F.lit(1.0).alias("w"))
        edges = met if edges is None else edges.unionByName(met)
    return Graph(ids, edges)


def _link(kind1: str, key1: Column, kind2: str, key2: Column, w: Column | None = None) -> list[Column]:
    return [F.lit(kind1).alias("kind1"), key1.cast("string").alias("key1"), F.lit(kind2).alias("kind2"), key2.cast("string").alias("key2"), (F.lit(1.0) if w is None else w.cast("double")).alias("w")]


def order_items(spark: SparkSession, sf_dir: str) -> Graph:
    """Orders with customers and parts, parts with suppliers; pairs once."""
    orders, items = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    a, b = lambda c: F.col(c).alias("a"), lambda c: F.col(c).alias("b")
    bought = items.select(a("l_orderkey"), b("l_partkey"))
    return _numbered_keys([
        ("order", "customer", orders.select(a("o_orderkey"), b("o_custkey")), False),
        ("order", "part", bought, True),
        ("part", "supplier", items.select(a("l_partkey"), b("l_suppkey")), True),
    ])


def customer_part_links(spark: SparkSession, sf_dir: str, weight: str = "count") -> DataFrame:
    """c_custkey, l_partkey, w: purchases counted, or their revenue."""
    value = F.count(F.lit(1)).cast("double") if weight == "count" else F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount")))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice", "l_discount")
    return items.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("c_custkey"), "l_partkey").agg(value.alias("w"))


def customer_part(spark: SparkSession, sf_dir: str, weight: str = "count") -> Graph:
    return _numbered(customer_part_links(spark, sf_dir, weight).select(*_link("customer", F.col("c_custkey"), "part", F.col("l_partkey"), F.col("w"))))


def geo_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """kind1, key1, kind2, key2, w: nations in regions, customers and suppliers in nations."""
    # nation and region have 25 and 5 rows by definition
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    region = F.broadcast(table(spark, sf_dir, "region").select("r_regionkey"))
    known = F.broadcast(nation.select("n_nationkey"))
    customers = table(spark, sf_dir, "customer").join(known, F.col("c_nationkey") == F.col("n_nationkey"))
    suppliers = table(spark, sf_dir, "supplier").join(known, F.col("s_nationkey") == F.col("n_nationkey"))
    return (
        nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select(*_link("nation", F.col("n_nationkey"), "region", F.col("n_regionkey")))
        .unionByName(customers.select(*_link("customer", F.col("c_custkey"), "nation", F.col("c_nationkey"))))
        .unionByName(suppliers.select(*_link("supplier", F.col("s_suppkey"), "nation", F.col("s_nationkey"))))
    )


#: The id ranges of the geography graph.
GEO_BASE = {"region": 0, "nation": 100, "customer": 1_000_000_000, "supplier": 1_500_000_000}


def geo_hierarchy(spark: SparkSession, sf_dir: str) -> Graph:
    """The geography graph; ids are keys plus a base for each kind."""
    links = geo_links(spark, sf_dir)

    def node(kind: str, key: str) -> Column:
        base = F.create_map(*[F.lit(x) for pair in GEO_BASE.items() for x in pair])
        return (base[F.col(kind)].cast("long") + F.col(key).cast("long"))

    edges = links.select(node("kind1", "key1").alias("src"), node("kind2", "key2").alias("dst"), "w")
    ends = links.select(F.col("kind1").alias("kind"), F.col("key1").alias("key")).unionByName(links.select(F.col("kind2").alias("kind"), F.col("key2").alias("key"))).distinct()
    return Graph(ends.select(node("kind", "key").alias("node"), "kind", "key"), edges)


def tokens(text: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(f"({WORD})")))


#: Tokens in more than this share of the rows tell little and are left out.
TOKEN_SHARE = 0.05


def token_links(rows: DataFrame, id_col: str, text_col: str, min_df: int = 2, share: float = TOKEN_SHARE) -> DataFrame:
    """id, token: distinct tokens of each row that occur in min_df rows or more and in at most this share of all."""
    pairs = rows.select(F.col(id_col).alias("id"), F.explode(tokens(F.col(text_col))).alias("token"))
    max_df = max(min_df, math.floor(share * rows.count() + 1e-9))
    held = pairs.groupBy("token").agg(F.count(F.lit(1)).alias("df")).filter(F.col("df").between(min_df, max_df)).select("token")
    return pairs.join(held, "token").select("id", "token")


def _token_graph(rows: DataFrame, kind: str, min_df: int, share: float) -> Graph:
    top = rows.agg(F.max("id")).first()[0] or 0
    links = token_links(rows, "id", "text", min_df, share).select(F.col("id").alias("src"), F.lit("token").alias("kind"), F.col("token").alias("key"))
    nodes, edges = _attributes(links, top + 1)
    own = rows.select(F.col("id").alias("node"), F.lit(kind).alias("kind"), F.col("id").cast("string").alias("key"))
    return Graph(own.unionByName(nodes), edges)


def doc_tokens(spark: SparkSession, sf_dir: str, min_df: int = 2, share: float = TOKEN_SHARE) -> Graph:
    """Documents and the tokens that several of them share."""
    return _token_graph(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), "document", min_df, share)


def conversation_tokens(spark: SparkSession, sf_dir: str, min_df: int = 2, share: float = TOKEN_SHARE) -> Graph:
    """Turns of conversations and their tokens; a turn's id is conv_id * 1000 + turn."""
    rows = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    return _token_graph(rows, "turn", min_df, share)


def word_grams(text: Column, n: int) -> Column:
    """The distinct runs of n words (lower-cased, split at white space) as strings."""
    words = F.split(F.trim(F.regexp_replace(F.lower(text), r"[\x20\x09-\x0D]+", " ")), " ")

    def runs(held: Column) -> Column:
        each = F.transform(F.sequence(F.lit(1), F.size(held) - n + 1), lambda i: F.array_join(F.slice(held, i, n), " "))
        return F.when(F.size(held) >= n, F.array_distinct(each)).otherwise(F.array().cast("array<string>"))

    # a variable of an outer function holds the words, which would be split anew for each run else
    return F.element_at(F.transform(F.array(words), runs), 1)


def passage_pairs(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """item_id, doc_id, shared: documents that share runs of n words with a benchmark item. Runs meet as hashes."""
    grams = lambda t, i: table(spark, sf_dir, t).select(i, F.explode(F.transform(word_grams(F.col("text"), n), lambda g: F.xxhash64(g))).alias("g"))
    docs = grams("documents", "doc_id").join(grams("benchmark", "item_id").select("g").distinct(), "g", "left_semi")
    return grams("benchmark", "item_id").join(docs, "g").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("shared"))


def passage_links(spark: SparkSession, sf_dir: str, n: int = 8) -> Graph:
    """Benchmark items and documents; item i is node i, documents follow."""
    pairs = cut(passage_pairs(spark, sf_dir, n), "passages")
    base = (table(spark, sf_dir, "benchmark").agg(F.max("item_id")).first()[0] or 0) + 1
    edges = pairs.select(F.col("item_id").alias("src"), (F.col("doc_id") + base).alias("dst"), F.col("shared").cast("double").alias("w"))
    items = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("node"), F.lit("item").alias("kind"), F.col("item_id").cast("string").alias("key"))
    docs = table(spark, sf_dir, "documents").select((F.col("doc_id") + base).alias("node"), F.lit("document").alias("kind"), F.col("doc_id").cast("string").alias("key"))
    return Graph(items.unionByName(docs), edges)


def page_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src (page_id), kind (host, link), key."""
    pages = table(spark, sf_dir, "pages")
    hosts = pages.select(F.col("page_id").alias("src"), F.lit("host").alias("kind"), F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1).alias("key"))
    links = pages.select(F.col("page_id").alias("src"), F.lit("link").alias("kind"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"')))).alias("key"))
    return hosts.unionByName(links).filter("key != ''")


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages with their host and the targets of their links."""
    pages = table(spark, sf_dir, "pages")
    top = pages.agg(F.max("page_id")).first()[0] or 0
    nodes, edges = _attributes(page_pairs(spark, sf_dir), top + 1)
    return Graph(pages.select(F.col("page_id").alias("node"), F.lit("page").alias("kind"), F.col("page_id").cast("string").alias("key")).unionByName(nodes), edges)


#: Vectors of a block that are compared with those of another in one unit of work.
KNN_BLOCK = 8192


def _in_order(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The dot products of rows, summed from the first place to the last."""
    out = np.zeros(len(x))
    for i in range(x.shape[1]):
        out += x[:, i] * y[:, i]
    return out


def _nearest(src: np.ndarray, x: np.ndarray, dst: np.ndarray, y: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(src, dst, cos) of the k nearest of ``dst`` for each of ``src`` by exact cosine, ties to the smaller id.

    Copies of a vector are compared once. Products in single precision leave out what is below the k + 1 best by more
    than their error; the rest is summed in double precision, in order. The cosine of a zero vector is NaN, the largest.
    """
    def distinct(ids: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, ...]:
        v = np.ascontiguousarray(v + np.float32(0))  # -0 is 0
        _, first, of = np.unique(v.view(np.dtype((np.void, v.dtype.itemsize * v.shape[1]))).ravel(), return_index=True, return_inverse=True)
        v = v[first].astype(np.float64)
        norm = np.sqrt(_in_order(v, v))
        return v, norm, (v / np.where(norm > 0, norm, 1)[:, None]).astype(np.float32), of.ravel()

    order = np.argsort(dst, kind="stable")
    dst, y = dst[order], y[order]
    a, na, ua, of_a = distinct(src, x)
    b, nb, ub, of_b = distinct(dst, y)
    held = np.argsort(of_b, kind="stable")  # ids ascend within a copied vector, of which k + 1 are enough
    start = np.searchsorted(of_b[held], np.arange(len(b)))
    copies = np.minimum(np.diff(np.append(start, len(dst))), k + 1)
    groups = min(16, max(1, len(b) // (4 * (k + 1))))
    wide = -(-len(b) // groups)
    best_id, best = np.full((len(a), k + 1), -1, np.int64), np.zeros((len(a), k + 1))
    for i in range(0, len(a), 512):
        c = np.full((min(512, len(a) - i), groups * wide), -np.inf, np.float32)
        c[:, : len(b)] = ua[i : i + 512] @ ub.T
        c[na[i : i + 512] == 0, : len(b)] = np.inf
        c[:, np.flatnonzero(nb == 0)] = np.inf
        peaks = c.reshape(len(c), groups, wide).max(axis=1)
        m = min(k + 1, wide)
        least = np.partition(peaks, wide - m, axis=1)[:, wide - m] if m == k + 1 else np.full(len(c), -2, np.float32)
        at, to = np.nonzero(c >= (least - np.float32(2e-5))[:, None])
        inside = to < len(b)
        at, to = at[inside], to[inside]
        with np.errstate(invalid="ignore", divide="ignore"):
            cos = np.concatenate([_in_order(a[i + at[j : j + 65536]], b[to[j : j + 65536]]) for j in range(0, len(at), 65536)]) / (na[i + at] * nb[to])
        times = copies[to]
        at, cos = np.repeat(at, times), np.repeat(cos, times)
        ids = dst[held[np.repeat(start[to], times) + np.arange(len(at)) - np.repeat(np.cumsum(times) - times, times)]]
        order = np.lexsort((ids, -np.where(np.isnan(cos), np.inf, cos), at))
        at, cos, ids = at[order], cos[order], ids[order]
        rank = np.arange(len(at)) - np.searchsorted(at, at)
        keep = rank <= k
        best_id[i + at[keep], rank[keep]], best[i + at[keep], rank[keep]] = ids[keep], cos[keep]
    found, cos = best_id[of_a], best[of_a]
    other = (found >= 0) & (found != src[:, None])
    other &= np.cumsum(other, axis=1) <= k
    return np.repeat(src, other.sum(axis=1)), found[other], cos[other]


def knn_pairs(spark: SparkSession, sf_dir: str, k: int = 5, block: int = KNN_BLOCK) -> DataFrame:
    """src, dst, w: the k nearest by cosine, exactly. Vectors meet in pairs of blocks, each a unit of work of an Arrow
    kernel that returns the k nearest there, and no side is broadcast."""
    v = cut(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), "vectors")
    n = max(1, -(-v.count() // block))
    every, own = F.sequence(F.lit(0), F.lit(n - 1)), F.pmod(F.hash("id"), F.lit(n))
    left = v.select("id", "v", own.alias("i"), F.explode(every).alias("j"))
    right = v.select("id", "v", F.explode(every).alias("i"), own.alias("j"))

    def nearest(a: pa.Table, b: pa.Table) -> pa.Table:
        src, dst, cos = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
        if a.num_rows and b.num_rows:
            x, y = (t["v"].combine_chunks().flatten().to_numpy().reshape(t.num_rows, -1) for t in (a, b))
            src, dst, cos = _nearest(a["id"].to_numpy(), x, b["id"].to_numpy(), y, k)
        return pa.table({"src": src, "dst": dst, "cos": cos})

    pairs = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(nearest, "src long, dst long, cos double")
    ranked = pairs.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst")))
    return ranked.filter(F.col("r") <= k).select("src", "dst", F.greatest("cos", F.lit(0.0)).alias("w"))


def lsh_neighbours(spark: SparkSession, sf_dir: str, k: int = 5, tables: int = 64, bits: int = 6, seed: int = 7) -> DataFrame:
    """As :func:`knn_pairs` among vectors that share a bucket of sign bits in some table (approximate, for scale); the
    sums are taken by an Arrow kernel for each bucket, which returns a vector's k nearest there and no other pairs."""
    v = cut(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v")), "vectors")
    width = len(v.first()["v"])
    planes = np.random.default_rng(seed).normal(size=(width, tables * bits))

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            signs = (b.column(1).flatten().to_numpy().reshape(-1, width) @ planes > 0).reshape(-1, tables, bits)
            keys = signs @ (1 << np.arange(bits)) + np.arange(tables) * (1 << bits)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(list(keys), pa.list_(pa.int64()))], names=["id", "v", "keys"])

    def nearest(t: pa.Table) -> pa.Table:
        ids = t["id"].to_numpy()
        x = t["v"].combine_chunks().flatten().to_numpy().reshape(-1, width)
        x = x / np.maximum(np.sqrt((x * x).sum(axis=1)), 1e-300)[:, None]
        src, dst, cos = [], [], []
        for i in range(0, len(ids), 512):
            c = x[i : i + 512] @ x.T
            c[np.arange(len(c)), np.arange(i, i + len(c))] = -np.inf
            m = min(k, len(ids) - 1)
            if m > 0:
                top = np.argpartition(-c, m - 1, axis=1)[:, :m]
                src.append(np.repeat(ids[i : i + len(c)], m))
                dst.append(ids[top].reshape(-1))
                cos.append(np.take_along_axis(c, top, axis=1).reshape(-1))
        join = lambda parts, kind: pa.array(np.concatenate(parts) if parts else [], kind)
        return pa.table({"src": join(src, pa.int64()), "dst": join(dst, pa.int64()), "cos": join(cos, pa.float64())})

    rows = v.mapInArrow(keyed, "id long, v array<double>, keys array<long>").select("id", "v", F.explode("keys").alias("key"))
    pairs = rows.groupBy("key").applyInArrow(nearest, "src long, dst long, cos double").groupBy("src", "dst").agg(F.max("cos").alias("cos"))
    ranked = pairs.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst")))
    return ranked.filter(F.col("r") <= k).select("src", "dst", F.greatest("cos", F.lit(0.0)).alias("w"))


def value_band(spark: SparkSession, sf_dir: str, delta: float) -> DataFrame:
    """src < dst of events whose values differ by at most delta: a range join by buckets a little wider than that. One side
    lies in its own bucket only, so a pair meets once and no pair is exchanged."""
    e = table(spark, sf_dir, "events").select("event_id", "value").filter("value is not null")
    cell = F.floor(F.col("value") / F.lit(delta * (1 + 1e-6))).cast("long")
    a = e.select(F.col("event_id").alias("src"), F.col("value").alias("x"), F.explode(F.array(cell - 1, cell, cell + 1)).alias("cell"))
    b = e.select(F.col("event_id").alias("dst"), F.col("value").alias("y"), cell.alias("cell"))
    near = a.join(b, "cell").filter((F.col("src") < F.col("dst")) & (F.abs(F.col("x") - F.col("y")) <= F.lit(delta)))
    return near.select("src", "dst")


def co_activity(spark: SparkSession, sf_dir: str, minutes: int = 60) -> DataFrame:
    """src < dst of events with the same k at most so many minutes apart."""
    e = table(spark, sf_dir, "events").select("event_id", "ts", F.get_json_object("props", "$.k").cast("int").alias("k"))
    step = minutes * 60
    sec = F.unix_timestamp(F.col("ts").cast("timestamp"))
    cell = F.floor(sec / step).cast("long")
    a = e.select(F.col("event_id").alias("src"), F.col("ts").alias("t1"), "k", F.explode(F.array(cell - 1, cell, cell + 1)).alias("cell"))
    b = e.select(F.col("event_id").alias("dst"), F.col("ts").alias("t2"), "k", cell.alias("cell"))
    apart = F.abs(F.unix_micros(F.col("t1").cast("timestamp")) - F.unix_micros(F.col("t2").cast("timestamp")))
    return a.join(b, ["k", "cell"]).filter((F.col("src") < F.col("dst")) & (apart <= step * 1_000_000)).select("src", "dst")


def synthetic_photo(spark: SparkSession, n: int, tags: int, per_item: int = 6) -> Graph:
    """Items 0..n-1 with tags n..n+tags-1, heavy at the head: for label counts beyond the given tables."""
    u = (F.pmod(F.xxhash64("id", "j"), F.lit(1 << 30)) / F.lit(float(1 << 30)))
    tag = F.least(F.floor(F.pow(F.lit(float(tags)), u)) - 1, F.lit(tags - 1)).cast("long")
    items = spark.range(n).select("id", F.explode(F.sequence(F.lit(1), F.lit(per_item))).alias("j"))
    edges = items.select(F.col("id").alias("src"), (tag + n).alias("dst")).distinct().withColumn("w", F.lit(1.0))
    nodes = spark.range(n + tags).select(F.col("id").alias("node"), F.when(F.col("id") < n, "item").otherwise("tag").alias("kind"), F.col("id").cast("string").alias("key"))
    return Graph(nodes, edges)


def planted_blocks(spark: SparkSession, blocks: int, size: int, psi: float) -> tuple[Graph, DataFrame]:
    """Cliques joined in a ring of matched members, the cross weight chosen so that each node sends a share psi of its
    weight outside; and the communities."""
    cross = psi * (size - 1) / (1 - psi) / (1 if blocks == 2 else 2)
    ids = spark.range(blocks * size).select(F.col("id").alias("src"))
    block, place = F.floor(F.col("src") / size), F.col("src") % size
    inside = ids.select("src", F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("j"), block.alias("b")).select("src", (F.col("b") * size + F.col("j")).alias("dst"), F.lit(1.0).alias("w")).filter("src < dst")
    ring = ids.select("src", (((block + 1) % blocks) * size + place).cast("long").alias("dst"), F.lit(float(cross)).alias("w"))
    ring = ring.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "w").distinct().filter("src != dst and w > 0")
    nodes = ids.select(F.col("src").alias("node"), F.lit("member").alias("kind"), F.col("src").cast("string").alias("key"))
    return Graph(nodes, inside.unionByName(ring)), ids.select(F.col("src").alias("node"), block.cast("string").alias("community"))
