"""Exact dedup, sharding and line dedup against plain Python, with nulls, ties, empty tables and clashing columns."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from labelflow.llm import exact_dedup, line_dedup, sharding

SCHEMA = "doc_id long, text string, source string"
ROWS = [(5, "a  b", "s"), (3, "a\tb", "s"), (9, None, "t"), (8, "", None), (1, "c" * 5000, "s"), (2, "a b ", "t"), (None, "a b", "s"), (5, "a  b", "s")]
NO_PYTHON = ("Python", "Pandas", "Arrow")


def squeezed(t):
    return re.sub(r"[ \t-\r]+", " ", t or "")


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("salts,copies", [(4, 1), (3, 40)])
def test_exact_dedup(spark, salts, copies):
    rows = ROWS + [(100 + i, "hot text", "s") for i in range(copies)]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("digest", F.lit(1)).withColumn("salt", F.lit(2)).withColumn("keep_id", F.lit(3))
    out = exact_dedup.exact_dedup(df, salts=salts)
    groups = defaultdict(list)
    for i, t, _ in rows:
        groups[squeezed(t)].append(i)
    want = Counter()
    for i, t, _ in rows:
        ids = groups[squeezed(t)]
        low = min((x for x in ids if x is not None), default=None)
        want[i, low, len(ids), i == low, hashlib.sha256(squeezed(t).encode()).hexdigest()] += 1
    assert Counter(tuple(r) for r in out.collect()) == want
    assert not any(p in plan(out) for p in NO_PYTHON)
    assert exact_dedup.exact_dedup(df.limit(0)).count() == 0
    kept = {r["doc_id"] for r in exact_dedup.keep_first(df).collect()}
    assert kept == {r[0] for r, n in ((k, v) for k, v in want.items()) if r[3]}


@pytest.mark.parametrize("n_shards", [8, 3])
def test_shards_interleave_sources(spark, n_shards):
    rows = ROWS + [(1000 + i, f"text {i}", "big" if i % 3 else f"small{i % 7}") for i in range(400)]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("part", F.lit(0)).withColumn("slot", F.lit(0)).repartition(5)
    out = sharding.stratified_shards(df, n_shards).collect()
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in out) == Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _ in rows)
    shards = defaultdict(list)
    for r in out:
        assert r["law"] == "rows" and r["grown_shard"] is None
        shards[r["shard"]].append(r)
    assert sorted(shards) == list(range(n_shards))
    sizes = [len(v) for v in shards.values()]
    assert max(sizes) - min(sizes) <= 1
    totals = Counter(s for _, _, s in rows)
    for source, n in totals.items():
        # a cut takes n / shards of a source up to a row; the largest makes up for what the others lack
        off = [abs(sum(r["source"] == source for r in v) - n / n_shards) for v in shards.values()]
        assert max(off) <= (len(totals) if source == "big" else 2)
    for v in shards.values():
        assert sorted(r["slot"] for r in v) == list(range(len(v)))
    again = {(r["doc_id"], r["text_crc32"]): r["shard"] for r in sharding.stratified_shards(df.repartition(2), n_shards).filter("doc_id >= 1000").collect()}
    assert again == {(r["doc_id"], r["text_crc32"]): r["shard"] for r in out if (r["doc_id"] or 0) >= 1000}
    assert sharding.stratified_shards(df.limit(0)).count() == 0


@pytest.mark.parametrize("limit", [10**6, 0])
def test_line_dedup(spark, limit):
    rows = [(i, f"menu\nbody {i}\n\nmenu" if i % 2 else f"body {i}\nrare", "a") for i in range(30)] + [(i, "menu\nx" if i < 54 else f"own {i}", "few") for i in range(50, 56)] + [(i, "copied\ntext", "two") for i in (60, 61)]
    rows += [(90, None, "a"), (91, "", "a"), (92, "menu", "a"), (93, "menu\nz", None)]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("host", F.lit("clash")).withColumn("lines", F.lit(1))
    pages = Counter(s for _, _, s in rows)
    seen = Counter((s, x) for _, t, s in rows for x in set((t or "").split("\n")))
    bad = {k for k, n in seen.items() if n >= 3 and n > pages[k[0]] * 0.1 and k[1].strip(" \t\n\r\x0b\x0c")}
    assert ("a", "menu") in bad and ("a", "rare") in bad and ("few", "menu") in bad and ("two", "copied") not in bad
    want = {i: None if t is None else "\n".join(x for x in t.split("\n") if (s, x) not in bad) for i, t, s in rows}
    out = line_dedup.drop_boilerplate(df, broadcast_lines=limit)
    assert out.columns == df.columns and {r["doc_id"]: r["text"] for r in out.collect()} == want
    assert not any(p in plan(out) for p in NO_PYTHON)
    report = {r["doc_id"]: r for r in line_dedup.line_dedup_report(df, broadcast_lines=limit).collect()}
    for i, t, s in rows:
        lines = (t or "").split("\n")
        assert report[i]["n_lines"] == len(lines) and report[i]["n_dropped"] == sum((s, x) in bad for x in lines)
        assert report[i]["kept_md5"] == hashlib.md5((want[i] or "").encode()).hexdigest()
    assert line_dedup.drop_boilerplate(df.limit(0)).count() == 0
