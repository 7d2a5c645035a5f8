"""SimHash, near duplicates, passages, quality and the pipeline against plain Python."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from conftest import SF
from labelflow.llm import decontam, passages, pfp, quality, simhash
from labelflow.llm.bktree import Forest
from labelflow.llm.components import connected_components

SCHEMA = "doc_id long, text string"


def components(ids, links):
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


def test_trees_find_all_neighbours():
    rnd = np.random.default_rng(1)
    base = rnd.integers(0, 1 << 63, 40, dtype=np.uint64)
    keys = np.unique(np.concatenate([base, base ^ np.uint64(1), base ^ np.uint64(6), base ^ np.uint64(0xF0)]))
    bucket = (np.arange(len(keys)) % 3).astype(np.int64)
    got = {(int(a), int(b)) for x, y in Forest(keys, bucket).search(3) for a, b in zip(x, y)}
    want = {(i, j) for i in range(len(keys)) for j in range(len(keys)) if i != j and bucket[i] == bucket[j] and int(keys[i] ^ keys[j]).bit_count() <= 3}
    assert got == want


def test_trees_find_equal_keys():
    keys = np.array([5, 5, 9, 5, 1 << 40, 9, 1 << 40, 5], np.uint64)
    bucket = np.array([0, 0, 0, 1, 1, 0, 1, 1], np.int64)
    got = [(int(a), int(b)) for x, y in Forest(keys, bucket).search(2) for a, b in zip(x, y)]
    want = {(i, j) for i in range(len(keys)) for j in range(len(keys)) if i != j and bucket[i] == bucket[j] and int(keys[i] ^ keys[j]).bit_count() <= 2}
    assert set(got) == want and len(got) == len(want)


def test_components(spark):
    rnd = random.Random(2)
    links = [(rnd.randrange(200), rnd.randrange(200)) for _ in range(120)] + [(i, i + 1) for i in range(300, 340)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    ids = {x for a, b in links if a != b for x in (a, b)}
    assert got == components(ids, [(a, b) for a, b in links if a != b])


def plain_fingerprint(text):
    import xxhash

    w = (text or "").encode().lower().split()
    if not w:
        return 0
    s = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << j for j in range(64) if sum(x >> j & 1 for x in h) * 2 > len(h))


@pytest.mark.parametrize("tree_size", [1024, 3])
def test_simhash_components(spark, tree_size):
    rnd = random.Random(4)
    rows = []
    for i in range(60):
        w = [f"w{rnd.randrange(500)}" for _ in range(rnd.choice([0, 1, 2, 40, 200]))]
        rows += [(3 * i, " ".join(w)), (3 * i + 1, "\n".join(w).upper()), (3 * i + 2, " ".join([*w, "tail"]))]
    rows += [(1000, None), (1001, ""), (1001, ""), (None, "")]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("fp", F.lit(1)).withColumn("component", F.lit(1)).repartition(3)
    prints = [(i, plain_fingerprint(t)) for i, t in rows]
    known = [i for i, _ in prints if i is not None]
    links = [(a, b) for a, x in prints for b, y in prints if a is not None and b is not None and a < b and (x ^ y).bit_count() <= 3]
    want = components(set(known), links)
    for r in simhash.simhash_components(df, tree_size=tree_size).collect():
        if r["doc_id"] is not None:
            assert (r["fingerprint"], r["component_id"]) == (f"{dict(prints)[r['doc_id']]:016x}", want[r["doc_id"]])
    assert simhash.simhash_components(df.limit(0)).count() == 0


def test_near_copies_meet_and_others_stay(spark):
    rnd = random.Random(6)
    rows, group = [], {}
    for i in range(40):
        w = [f"w{rnd.randrange(3000)}" for _ in range(150)]
        for c in range(4):
            x = list(w)
            if c:
                x[rnd.randrange(150)] = "changed"
            rows.append((10 * i + c, " ".join(x)))
            group[10 * i + c] = 10 * i
    rows += [(900, None), (901, "")]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("sketch", F.lit(0))
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_components(df).collect()}
    assert sum(got[i] == g for i, g in group.items()) >= 0.97 * len(group)
    assert all(got[i] // 10 == i // 10 for i in group)
    assert {r["doc_id"] for r in simhash.keep_one(df).collect()} == set(got.values())


def plain_shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def plain_near(rows, similarity=0.8):
    sets = {i: plain_shingles(t) for i, t in rows}
    links = [(a, b) for a in sets for b in sets if a < b and (sets[a] == sets[b] or len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b]))]
    return components(set(sets), links)


@pytest.mark.parametrize("unit_rows", [1024, 5])
def test_near_links_are_exact(spark, unit_rows):
    rnd = random.Random(8)
    rows = []
    for i in range(25):
        w = [f"w{rnd.randrange(5000)}" for _ in range(300)]
        for c in range(12):
            x = list(w)
            for at in rnd.sample(range(300), rnd.randrange(4, 9)):
                x[at] = f"new{rnd.randrange(10**6)}"
            rows.append((100 * i + c, " ".join(x)))
    rows += [(5000 + i, t) for i, t in enumerate([None, "", "a b", "A  b", "a c"])]
    found = simhash.near_components(spark.createDataFrame(rows, SCHEMA).repartition(3), unit_rows=unit_rows).collect()
    assert {r["doc_id"]: r["component_id"] for r in found} == plain_near(rows)


def test_near_copies_by_block_edits(spark):
    rnd = random.Random(9)
    new = lambda n: [f"w{rnd.randrange(10**6)}" for _ in range(n)]
    rows = []
    for n in (12, 60, 200, 1000):
        for _ in range(40):
            w, k = new(n), max(1, n // 12)
            for x in (w, w[: n - k], w[: n // 2] + new(k) + w[n // 2 :], w[: n - k // 2 - 1] + new(k // 2 + 1)):
                rows.append((len(rows), " ".join(x)))
    line = new(11)
    rows += [(len(rows) + i, " ".join(line * 60 + new(6))) for i in range(20)]
    tail = new(120)
    rows += [(10_000 + i, " ".join(line * 60 + tail[: 118 + i % 3] + new(i % 4))) for i in range(20)]
    found = simhash.near_components(spark.createDataFrame(rows, SCHEMA)).collect()
    assert {r["doc_id"]: r["component_id"] for r in found} == plain_near(rows)


def test_rows_of_one_id_are_judged_on_their_own(spark):
    rnd = random.Random(10)
    texts = [" ".join(f"w{rnd.randrange(10**6)}" for _ in range(40)) for _ in range(4)]
    rows = [(5, texts[0]), (None, texts[0] + " tail"), (None, texts[1]), (7, texts[2]), (7, texts[3]), (7, texts[3])]
    df = spark.createDataFrame(rows, SCHEMA).withColumns({"source": F.lit("s"), "lang": F.lit("l")})
    key = lambda r: (r["doc_id"] or -1, r["text"])
    kept = sorted(map(key, simhash.keep_one(df).collect()))
    assert kept == sorted((i or -1, t) for i, t in rows if t != rows[1][1])
    bench = spark.createDataFrame([(1, texts[2])], "item_id long, text string")
    assert sorted(map(key, decontam.drop_leaks(df, bench).collect())) == sorted((i or -1, t) for i, t in rows if t != texts[2])


def plain_passages(rows, span):
    seen, out = set(), {}
    for d, t in sorted(rows):
        raw, cover = (t or "").encode(), bytearray(len((t or "").encode()))
        for i in range(len(raw) - span + 1):
            w = raw[i : i + span]
            if w in seen:
                cover[i : i + span] = b"\1" * span
            seen.add(w)
        runs = sum(c and not p for c, p in zip(cover, b"\0" + bytes(cover)))
        out[d] = (len(raw), sum(cover), runs, hashlib.sha256(bytes(b for b, c in zip(raw, cover) if not c)).hexdigest())
    return out


@pytest.mark.parametrize("options", [{}, {"span": 30, "gram": 10}, {"hot_rows": 3, "broadcast_rows": 0}])
def test_passages(spark, options):
    rnd = random.Random(7)
    base = ["".join(rnd.choice("abcé ") for _ in range(rnd.randint(5, 120))) for _ in range(8)] + ["x" * 150]
    rows = [(i, None if i == 5 else "" if i == 6 else "".join(rnd.choice(base) for _ in range(rnd.randint(0, 6)))) for i in range(80)]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("doc", F.lit(0)).withColumn("pos", F.lit(0)).repartition(3)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in passages.repeat_report(df, **options).collect()}
    assert got == plain_passages(rows, options.get("span", 100))
    assert passages.repeat_report(df.limit(0)).count() == 0


def test_prefix_free_parse_orders_suffixes():
    rnd = random.Random(4)
    for _ in range(60):
        base = [bytes(rnd.choice(b"ab") for _ in range(rnd.randint(0, 60))) for _ in range(3)]
        texts = [b"".join(rnd.choice(base) for _ in range(rnd.randint(0, 4))) for _ in range(rnd.randint(1, 6))]
        width = rnd.choice([1, 2, 3, 6])
        parse = pfp.PrefixFreeParse(texts, width, rnd.choice([2, 3, 5]))
        at = np.array([s + i for s, t in zip(parse.starts.tolist(), texts) for i in range(len(t))], dtype=int)
        suffix = {int(s + i): [*t[i:]] + [256] * width for s, t in zip(parse.starts.tolist(), texts) for i in range(len(t))}
        found = [suffix[int(p)] for p in parse.order(at)]
        assert found == sorted(found)


def test_quality_on_held_out_rows(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    held = labels.filter(F.pmod(F.xxhash64("doc_id"), F.lit(4)) == 0)
    out = quality.classify(docs, labels.join(held, "doc_id", "left_anti")).join(held, "doc_id").collect()
    right = sum(r["keep"] == (r["quality"] == 1 and r["toxic"] == 0) for r in out)
    assert right >= 0.9 * len(out)


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, None, None, "x"), (2, "", "h", None), (2, "", "h", None)], "doc_id long, text string, source string, lang string").withColumn("low", F.lit(1))
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r["keep"] for r in quality.classify(docs, none).collect()] == [True] * 3
    some = spark.createDataFrame([(1, 0, None), (None, 1, 1), (7, 1, 1)], "doc_id long, quality int, toxic int")
    assert quality.classify(docs, some).count() == 3 and quality.classify(docs.limit(0), some).count() == 0


def test_sparse_sites_shrink_to_the_global_rate(spark):
    rows = [(i, "big", "a", 3.0 if i % 2 else -3.0, -5.0) for i in range(400)] + [(900, "tiny", "a", 3.0, -5.0)] + [(1000 + i, "bad", "b", 3.0, -5.0) for i in range(300)]
    sites = {r["host"]: r for r in quality.posteriors(spark.createDataFrame(rows, "doc_id long, host string, path string, z_low double, z_toxic double")).collect()}
    assert sites["bad"]["path_low"] > sites["tiny"]["path_low"] > 0.5 > 0.05 < sites["big"]["path_low"]
    assert sites["tiny"]["path_low"] < 0.95


def test_pipeline_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, rows = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.columns == columns
        now = docs.count()
        assert now <= rows and now > 0.5 * rows, name
        rows = now
    out = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert out.count() == rows and not out.filter("not round_trip").count()
