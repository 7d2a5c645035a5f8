"""Language-model scores by prediction by partial matching over bytes, and a unigram base score.

The model is a byte-context trie: for each context of up to ``order`` symbols, the counts of the symbols that
followed it. A symbol is coded in the longest known context; where it was never seen there, an escape with the
estimate q / (T + q) (q distinct symbols, T in total) leads to the context shorter by one, in which the symbols of
the longer one are excluded; at last, all symbols that are still possible are equal. Each text is coded to its end
mark, so scores are log-probabilities of texts.

A pretrained trie makes the code length of a symbol a function of its gram (context and symbol), so a corpus is
trained by counting grams and scored by looking grams up. The most frequent grams and words, a fixed number whatever
the corpus, are sent to the workers with their costs and price nearly all of a text where it is read. What a text has
of the others is written as rows (text, gram, times), which are joined with the rest of the model; grams that were
never learnt are priced by escapes, order by order, in joins over the counts. A gram or word outside the head is
rare, so no key of these joins is hot. That is one path at every size. ``ByteTrie`` is the plain form, which also
learns while it codes (adaptive code length).
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_of, lean, materialise, slices, text_of
from .words import KeyTable, Part, parts_of

SYMBOLS = 257
MARK = 256
_BITS = 9
#: The token at the end of a text; no word is empty.
_END = b""
#: Grams and words that are sent to all workers at most: about 16 bytes each gram, 40 each word.
HEAD_GRAMS, HEAD_WORDS = 1 << 20, 1 << 18
#: Distinct grams or words that a task counts before it passes them on.
_HELD = 2_000_000


class ByteTrie:
    """Counts of symbols by context, coded with escapes and exclusion; ``code(text, learn=True)`` is adaptive."""

    def __init__(self, order: int = 4):
        self.order = order
        self.counts: dict[tuple, Counter] = defaultdict(Counter)

    def _symbols(self, text: bytes) -> list[int]:
        return [MARK] * self.order + list(text) + [MARK]

    def learn(self, text: bytes) -> None:
        s = self._symbols(text)
        for i in range(self.order, len(s)):
            self._count(s, i)

    def _count(self, s: list[int], i: int) -> None:
        for k in range(self.order + 1):
            self.counts[tuple(s[i - k : i])][s[i]] += 1

    def _cost(self, s: list[int], i: int) -> float:
        excluded: set[int] = set()
        total = 0.0
        for k in range(self.order, -1, -1):
            seen = self.counts.get(tuple(s[i - k : i]))
            if not seen:
                continue
            left = {x: n for x, n in seen.items() if x not in excluded}
            if left:
                whole = sum(left.values()) + len(left)
                if s[i] in left:
                    return total + math.log10(left[s[i]] / whole)
                total += math.log10(len(left) / whole)
            excluded |= set(seen)
        return total - math.log10(SYMBOLS - len(excluded))

    def code(self, text: bytes, learn: bool = False) -> float:
        """log10 of the text's probability."""
        s, total = self._symbols(text), 0.0
        for i in range(self.order, len(s)):
            total += self._cost(s, i)
            if learn:
                self._count(s, i)
        return total


def grams_of(texts: list[bytes], part: list[Part], order: int) -> tuple[np.ndarray, np.ndarray]:
    """The gram at each symbol of these parts, and where each part begins among them."""
    blocks, marks, starts, size, n = [], [], [], 0, 0
    for i, a, b in part:
        before = texts[i][max(0, a - order) : a]
        pad = order - len(before)
        marks += range(size, size + pad)
        block = b"\0" * pad + before + texts[i][a:b]
        if b == len(texts[i]):
            marks.append(size + len(block))
            block += b"\0"
        blocks.append(block)
        starts.append(n)
        size += len(block)
        n += len(block) - order
    symbols = np.frombuffer(b"".join(blocks), np.uint8).astype(np.uint64)
    symbols[marks] = MARK
    gram = symbols.copy()
    for j in range(1, order + 1):
        gram[j:] |= symbols[:-j] << np.uint64(_BITS * j)
    lengths = np.array([len(b) for b in blocks])
    valid = np.ones(size, bool)
    heads = np.cumsum(lengths) - lengths
    for j in range(order):
        valid[heads + j] = False
    return gram[valid], np.array(starts)


def held_out(id_column: Column) -> Column:
    """True for the fold that is not learnt from; null ids count as the empty text."""
    return F.pmod(F.crc32(F.coalesce(id_column.cast("string"), F.lit("")).cast("binary")), F.lit(7)) == 2


def _words(text: bytes) -> Iterator[list[bytes]]:
    """The words of a text, a slice at a time."""
    for part in parts_of([text]):
        for _, a, b in part:
            yield text[a:b].lower().split()


def count_table(texts: DataFrame, order: int) -> DataFrame:
    """gram or word (the other is null) and n over the column ``text``, summed in each task first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams: list[tuple[np.ndarray, np.ndarray]] = []
        words: Counter = Counter()

        def merged() -> tuple[np.ndarray, np.ndarray]:
            keys, where = np.unique(np.concatenate([k for k, _ in grams]), return_inverse=True)
            return keys, np.bincount(where, np.concatenate([n for _, n in grams]), len(keys)).astype(np.int64)

        def told_grams() -> Iterator[pa.RecordBatch]:
            keys, n = merged()
            grams.clear()
            for i in range(0, len(keys), 1 << 17):
                part = keys[i : i + (1 << 17)].view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.nulls(len(part), pa.binary()), pa.array(n[i : i + (1 << 17)])], names=["gram", "word", "n"])

        def told_words() -> Iterator[pa.RecordBatch]:
            while words:
                part = [words.popitem() for _ in range(min(len(words), 1 << 16))]
                yield pa.RecordBatch.from_arrays([pa.nulls(len(part), pa.int64()), pa.array([w for w, _ in part], pa.binary()), pa.array([n for _, n in part], pa.int64())], names=["gram", "word", "n"])

        for batch in (part for whole in batches for part in slices(whole, 0)):
            found = [x.encode("utf-8", "surrogatepass") for x in batch.column(0).to_pylist()]
            for part in parts_of(found):
                grams.append(np.unique(grams_of(found, part, order)[0], return_counts=True))
                if len(grams) > 32:
                    grams[:] = [merged()]
                    if len(grams[0][0]) > _HELD:
                        yield from told_grams()
            for t in found:
                for part in _words(t):
                    words.update(part)
                if len(words) > _HELD:
                    yield from told_words()
            words[_END] += len(found)
        if grams:
            yield from told_grams()
        yield from told_words()

    counted = texts.select("text").mapInArrow(lean(run), "gram long, word binary, n long")
    return counted.groupBy("gram", "word").agg(F.sum("n").alias("n"))


def _head(table: DataFrame, most: int) -> Column:
    """A condition on ``n`` that at most ``most`` rows meet, the most frequent: by quarters of powers of two."""
    quarter = F.floor(F.log2("n") * 4)
    sizes = sorted(((r["q"], r["count"]) for r in table.groupBy(quarter.alias("q")).count().collect()), reverse=True)  # at most 256 rows
    least, held = 1 << 20, 0
    for q, rows in sizes:
        if held + rows > most:
            break
        least, held = q, held + rows
    return quarter >= least


def _cut(k: int, of: str = "gram") -> Column:
    return F.col(of).bitwiseAND(F.lit((1 << _BITS * (k + 1)) - 1))


def seen_costs(grams: DataFrame) -> DataFrame:
    """gram, n, cost (log10 probability of its last symbol) for the learnt grams (gram, n)."""
    contexts = grams.groupBy(F.shiftrightunsigned("gram", _BITS).alias("x")).agg((F.sum("n") + F.count(F.lit(1))).alias("whole"))
    return grams.join(contexts, F.shiftrightunsigned("gram", _BITS) == F.col("x")).select("gram", "n", F.log10(F.col("n") / F.col("whole")).alias("cost"))


def escaped_costs(asked: DataFrame, grams: DataFrame, order: int) -> DataFrame:
    """gram, cost for distinct grams that were never learnt; ``grams`` has the learnt ones (gram, n).

    Orders 0 and 1 and the contexts up to order 2 are broadcast: they have at most 257 ** 2 rows whatever the corpus.
    In the other joins a key has at most 257 ** 3 rows on either side.
    """
    levels = {order: grams.select(F.col("gram").alias("g"), F.col("n").alias("c"))}
    for k in range(order - 1, -1, -1):
        levels[k] = materialise(levels[k + 1].groupBy(_cut(k, "g").alias("g")).agg(F.sum("c").alias("c")), "ppm-level")

    def small(df: DataFrame, rows: int) -> DataFrame:
        return F.broadcast(df) if rows <= SYMBOLS**2 else df

    todo = asked.select("gram", F.lit(0.0).alias("cost"), F.lit(0).cast("long").alias("mass"), F.lit(0).cast("long").alias("kinds"))
    priced = None
    for k in range(order, -1, -1):
        own = levels[k].withColumn("x", F.shiftrightunsigned("g", _BITS))
        if k:  # what the symbols of a context weigh one order below
            below = small(levels[k - 1].select(F.col("g").alias("h"), F.col("c").alias("b")), SYMBOLS**k)
            whole = own.join(below, _cut(k - 1, "g") == F.col("h"))
        else:
            whole = own.withColumn("b", F.lit(0).cast("long"))
        contexts = whole.groupBy(F.col("x").alias("y")).agg(F.sum("c").alias("T"), F.count(F.lit(1)).alias("q"), F.sum("b").alias("E"))
        counts = small(levels[k].withColumnRenamed("g", "g_"), SYMBOLS ** (k + 1))
        met = todo.withColumn("at", _cut(k)).join(counts, F.col("at") == F.col("g_"), "left").withColumn("x", F.shiftrightunsigned("at", _BITS))
        met = met.join(small(contexts, SYMBOLS**k), F.col("x") == F.col("y"), "left")
        kinds = F.col("q") - F.col("kinds")
        total = F.col("T") - F.col("mass") + kinds
        found = F.col("c").isNotNull()
        price = F.when(found, F.log10(F.col("c") / total)).when(kinds > 0, F.log10(kinds / total)).otherwise(0.0)
        met = met.select("gram", (F.col("cost") + price).alias("cost"), F.coalesce("E", F.lit(0)).cast("long").alias("mass"), F.coalesce("q", F.lit(0)).cast("long").alias("kinds"), found.alias("done"))
        met = materialise(met, "ppm-escapes")
        ended = met.filter("done").select("gram", "cost")
        priced = ended if priced is None else priced.unionByName(ended)
        todo = met.filter("not done")
    never = todo.select("gram", (F.col("cost") - F.log10(F.greatest(F.lit(SYMBOLS) - F.col("kinds"), F.lit(1)).cast("double"))).alias("cost"))
    return priced.unionByName(never)


_PART = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("log", pa.float64()), ("score", pa.float64()), ("gram", pa.int64()), ("word", pa.binary()), ("times", pa.int64())])


def _part(rows: int, **columns) -> pa.RecordBatch:
    """A batch of partial results: the columns given, the others null."""
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(rows, f.type) for f in _PART], schema=_PART)


def _priced_by_head(order: int, sent):
    """Rows of texts with what the head prices, and rows (row, gram or word, times) for what it doesn't."""
    model: dict = {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not model:
            grams, costs, words, counts = sent.value
            model.update(grams=KeyTable(grams), costs=np.append(costs, 0.0), words=dict(zip(words, counts)))
        find, costs, known = model["grams"].find, model["costs"], model["words"]
        row = TaskContext.get().partitionId() << 33
        for batch in (part for whole in batches for part in slices(whole, 1)):
            texts = [x.encode("utf-8", "surrogatepass") for x in batch.column(1).to_pylist()]
            score, log, tokens, met = np.zeros(len(texts)), np.zeros(len(texts)), np.zeros(len(texts), np.int64), np.zeros(len(texts), np.int64)
            for pieces in parts_of(texts):
                keys, starts = grams_of(texts, pieces, order)
                at = find(keys)
                owner = np.array([i for i, _, _ in pieces])
                size = np.diff(np.append(starts, len(keys)))
                np.add.at(score, owner, np.where(size > 0, np.add.reduceat(np.append(costs[at], 0), starts), 0))
                rare = np.flatnonzero(at < 0)
                if len(rare):
                    of, rare = owner[np.searchsorted(starts, rare, "right") - 1], keys[rare]
                    order_ = np.lexsort((rare, of))
                    of, rare = of[order_], rare[order_]
                    new = np.flatnonzero(np.append(True, (np.diff(of) != 0) | (rare[1:] != rare[:-1])))
                    yield _part(len(new), row=row + of[new], gram=rare[new].view(np.int64), times=np.diff(np.append(new, len(of))))
            others: list[tuple[int, bytes, int]] = []
            for i, t in enumerate(texts):
                left: Counter = Counter()
                for found in (*_words(t), [_END]):
                    c = np.array([known.get(w, -1) for w in found], np.int64)
                    tokens[i] += len(c)
                    met[i] += (c > 0).sum()
                    log[i] += np.log10(np.maximum(c, 0) + 1).sum()
                    left.update(found[k] for k in np.flatnonzero(c < 0).tolist())
                others += [(row + i, w, n) for w, n in left.items()]
            if others:
                yield _part(len(others), row=[r for r, _, _ in others], word=[w for _, w, _ in others], times=[n for _, _, n in others])
            yield _part(len(texts), row=np.arange(row, row + len(texts)), doc_id=batch.column(0), held_out=batch.column(2), n_tokens=tokens, n_known=met, log=log, score=score)
            row += len(texts)

    return run


def ppm_scores(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", order: int = 4, head_grams: int = HEAD_GRAMS, head_words: int = HEAD_WORDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for each row.

    The trie and the word counts are learnt from all rows that :func:`held_out` doesn't name, and score all rows.
    Null texts count as empty: one token, the end, and the code length of the end mark. Null ids count as the empty
    string in the fold; repeated rows repeat (and count in training as often). With nothing to learn from, base scores
    are 0 and symbols equally likely. Other columns are ignored; an empty table gives an empty result. The sizes of the
    heads change what is shuffled, not the result.
    """
    rows = docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).withColumn("held_out", held_out(F.col("doc_id")))
    table = materialise(count_table(rows.filter(~F.col("held_out")), order), "ppm-counts")
    grams, words = table.filter("gram is not null").select("gram", "n"), table.filter("word is not null").select("word", "n")
    seen = materialise(seen_costs(grams), "ppm-seen")
    whole = words.agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).first()
    train, base = whole["n"] or 0, math.log10((whole["n"] or 0) + whole["v"] + 1)
    common, often = seen.filter(_head(seen, head_grams)).toArrow(), words.filter(_head(words, head_words)).toArrow()  # of fixed size at most
    sent = docs.sparkSession.sparkContext.broadcast((common["gram"].to_numpy().view(np.uint64), common["cost"].to_numpy(), often["word"].to_pylist(), often["n"].to_pylist()))
    schema = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, log double, score double, gram long, word binary, times long"
    parts = materialise(rows.select("doc_id", "text", "held_out").mapInArrow(lean(_priced_by_head(order, sent)), schema), "ppm-parts")
    rare = parts.filter("gram is not null").select("row", "gram", "times")
    asked = materialise(rare.select("gram").distinct().join(seen.select(F.col("gram").alias("k_"), "cost"), F.col("gram") == F.col("k_"), "left").select("gram", "cost"), "ppm-asked")
    costs = asked.filter("cost is not null").unionByName(escaped_costs(asked.filter("cost is null"), grams, order))
    costs = costs.select(F.col("gram").alias("k_"), "cost")
    by_gram = rare.join(costs, F.col("gram") == F.col("k_")).groupBy(F.col("row").alias("r1")).agg(F.sum(F.col("times") * F.col("cost")).alias("more"))
    counts = words.select(F.col("word").alias("k_"), "n")
    by_word = parts.filter("word is not null").select("row", "word", "times").join(counts, F.col("word") == F.col("k_"))
    by_word = by_word.groupBy(F.col("row").alias("r2")).agg(F.sum("times").alias("met"), F.sum(F.col("times") * F.log10(F.col("n") + 1.0)).alias("more_log"))
    texts = parts.filter("n_tokens is not null").select("row", "doc_id", "held_out", "n_tokens", "n_known", "log", "score")
    joined = texts.join(by_gram, F.col("row") == F.col("r1"), "left").join(by_word, F.col("row") == F.col("r2"), "left")
    none = F.lit(0)
    return joined.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("met", none)).alias("n_known"), F.lit(train).cast("long").alias("train_tokens"),
        (F.col("log") + F.coalesce("more_log", none) - F.col("n_tokens") * F.lit(base)).alias("base_score"), (F.col("score") + F.coalesce("more", none)).alias("score"),
    )
