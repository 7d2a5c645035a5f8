"""BPE, secrets, PPM and decontamination against plain Python."""

import base64
import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from labelflow.llm import bpe, decontam, ppm, secrets
from labelflow.llm.queries import tokenizer_files

SCHEMA = "doc_id long, text string"
ODD = ["don't  stop\n\n", "é́ \U0001f600x", " 　 a", "x" * 5000, "", None, "\x85\xa0\x1c ab12²", "'s 'S"]


@pytest.fixture(scope="module")
def codec():
    return bpe.codec(*tokenizer_files())


@pytest.fixture(scope="module")
def tiktoken_codec():
    import tiktoken

    path, pattern = tokenizer_files()
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


@settings(max_examples=300, deadline=None)
@given(text=st.text(max_size=60))
def test_bpe_equals_tiktoken(codec, tiktoken_codec, text):
    text = text.encode("utf-8", "ignore").decode()
    ids = codec.ids(text)
    assert ids.tolist() == tiktoken_codec.encode_ordinary(text)
    assert codec.decode(ids) == text.encode()


def test_bpe_rows_and_offsets(spark, codec, tiktoken_codec):
    df = spark.createDataFrame(list(enumerate(ODD)), SCHEMA).withColumn("ids", F.lit(0))
    out = {r["doc_id"]: r for r in bpe.encode_decode(df, *tokenizer_files(), with_ids=True, with_offsets=True).collect()}
    for i, t in enumerate(ODD):
        ids = tiktoken_codec.encode_ordinary(t or "")
        r = out[i]
        assert (r["ids"], r["n_tokens"]) == (ids, len(ids)) and r["round_trip"]
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
        for a, b, x in zip(r["char_starts"], r["char_ends"], ids):
            assert codec.strings[x] in (t or "")[a:b].encode()
    back = bpe.decode_ids(bpe.encode_ids(df, *tokenizer_files()), *tokenizer_files())
    assert {r["doc_id"]: r["text"] for r in back.collect()} == {i: t or "" for i, t in enumerate(ODD)}
    assert bpe.encode_decode(df.limit(0), *tokenizer_files()).count() == 0


PATTERNS = [r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", r"AKIA[A-Z0-9]+", r"[0-9a-f]+"]
KINDS = ("assign", "access", "hex")


def plain_secrets(t):
    out = [(m.start(), 0, m.end()) for m in re.finditer(PATTERNS[0], t, re.I | re.A) if len(m[2]) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer(PATTERNS[1], t) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer(PATTERNS[2], t) if m.end() - m.start() >= 24]
    return [(KINDS[k], a, b) for a, k, b in sorted(out)]


def test_secrets(spark):
    rnd = random.Random(3)
    pool = ["token", "TOKEN", "api_key", "apikey", "secret", "passwd", "AKIA", "AK", "=", ":", " ", '"', "'", "a", "f", "9", "Z", "é", "abcdef", "0123456789abcdef", "ABCDEFGHIJKLMNOP", "\n", "=="]
    texts = ["".join(rnd.choice(pool) for _ in range(rnd.randint(0, 60))) for _ in range(1500)] + [None, "", "é token=abcdefg", "ghp_" + "a1" * 18]
    df = spark.createDataFrame(list(enumerate(texts)), SCHEMA).withColumn("spans", F.lit(1))
    for r in secrets.find_secrets(df).collect():
        want = plain_secrets(texts[r["doc_id"]] or "")
        assert [r["n_assign"], r["n_access"], r["n_hex"]] == [sum(k == x for k, _, _ in want) for x in KINDS]
        written = ",".join(f"{k}:{a}:{b}" for k, a, b in want)
        assert r["base_sha256"] == hashlib.sha256(written.encode()).hexdigest()
        assert [s for s in r["spans"].split(",") if s.split(":")[0] in KINDS] == [s for s in written.split(",") if s]
    assert [r["text"] for r in secrets.redact(df.filter("doc_id = 1502")).collect()] == ["é [SECRET]"]
    assert secrets.find_secrets(df.limit(0)).count() == 0


@pytest.mark.parametrize("head", [10**6, 30, 0])
def test_ppm_equals_the_plain_trie(spark, head):
    rnd = random.Random(1)
    texts = ["".join(rnd.choice("abc dé\n") for _ in range(rnd.randint(0, 60))) for _ in range(40)] + [None, "", "zq~", "AAAA aaaa", "AAAA aaaa"]
    rows = list(enumerate(texts))
    trie, words = ppm.ByteTrie(3), Counter()
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i, _ in rows}
    for i, t in rows:
        if not held[i]:
            trie.learn((t or "").encode())
            words.update((t or "").encode().lower().split())
            words["end"] += 1
    n, v = sum(words.values()), len(words)
    df = spark.createDataFrame(rows, SCHEMA).withColumn("score", F.lit(0)).repartition(3)
    for r in ppm.ppm_scores(df, order=3, head_grams=head, head_words=head).collect():
        t = (texts[r["doc_id"]] or "").encode()
        tokens = [*t.lower().split(), "end"]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[r["doc_id"]], len(tokens), sum(words[x] > 0 for x in tokens), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((words[x] + 1) / (n + v + 1)) for x in tokens), abs=1e-6)
        assert r["score"] == pytest.approx(trie.code(t), abs=1e-6)
    assert ppm.ppm_scores(df.limit(0)).count() == 0


def test_ppm_learns_while_coding():
    trie = ppm.ByteTrie(3)
    first, second = trie.code(b"abcabcabc", learn=True), trie.code(b"abcabcabc", learn=True)
    assert second > first
    cost = sum(10 ** trie.code(bytes([a])) for a in range(256)) + 10 ** trie.code(b"")
    assert cost < 1


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        old, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            old, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, old + (x != y))
    return row[-1]


def test_substring_distance():
    rnd = random.Random(5)
    for _ in range(200):
        a, b = [rnd.randint(0, 3) for _ in range(rnd.randint(1, 6))], [rnd.randint(0, 3) for _ in range(rnd.randint(0, 9))]
        d, i, j = decontam.substring_distance(np.array(a), np.array(b, dtype=int))
        assert d == min(edit_distance(a, b[x:y]) for x in range(len(b) + 1) for y in range(x, len(b) + 1))
        assert edit_distance(a, b[i:j]) == d


def test_decontamination(spark):
    rnd = random.Random(2)
    vocabulary = [f"w{i}" for i in range(300)]
    items = [(i, " ".join(rnd.choices(vocabulary, k=k))) for i, k in enumerate((12, 25, 40, 60, 5, 3))] + [(6, ""), (7, None)]
    docs, want = [(0, None), (1, ""), (2, " ".join(rnd.choices(vocabulary, k=800)))], set()
    for n in range(120):
        i = rnd.randrange(6)
        w = items[i][1].upper().split()
        for _ in range(rnd.randint(0, decontam.allowed_edits(len(w), 0.8))):
            at, kind = rnd.randrange(len(w)), rnd.randrange(3)
            w[at : at + (kind != 0)] = [] if kind == 2 else [f"new{rnd.random()}"]
        docs.append((10 + n, " ".join(rnd.choices(vocabulary, k=rnd.randrange(60))) + ", " + " ".join(w) + ". " + " ".join(rnd.choices(vocabulary, k=rnd.randrange(60)))))
    words = lambda t: re.findall(r"[a-z0-9]+", (t or "").lower())
    for d, t in docs:
        for i, x in items:
            a, b = words(x), words(t)
            if a:
                cost = decontam.substring_distance(np.array([hash(z) for z in a]), np.array([hash(z) for z in b], dtype=int))[0]
                if cost <= decontam.allowed_edits(len(a), 0.8):
                    want.add((d, i, cost))
    df, bench = spark.createDataFrame(docs, SCHEMA).withColumn("item_id", F.lit(0)), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"], r["distance"]) for r in decontam.find_leaks(df, bench).collect()}
    assert {x[:2] for x in got} <= {x[:2] for x in want}
    assert len({x[:2] for x in got}) >= 0.95 * len(want)
    left = {r["doc_id"] for r in decontam.drop_leaks(df, bench).collect()}
    assert left == {d for d, _ in docs} - {d for d, _, _ in got}
    assert {r["doc_id"] for r in decontam.find_leaks(df, bench, block_words=20).collect()} == {d for d, _, _ in got}
    assert decontam.find_leaks(df.limit(0), bench).count() == 0 and decontam.find_leaks(df, bench.limit(0)).count() == 0
