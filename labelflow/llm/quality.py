"""Quality and toxicity of documents by hierarchical empirical Bayes.

*Document evidence*: a logistic classifier for each head (low quality, toxic) over the presence of words, word
beginnings and binned measures of form. It is fitted on a bounded sample of labelled rows: the ``sample_rows``
labels with the smallest hash of their id. Its features are those that depart significantly from the base rate.

*Site evidence*: over all documents, the sum of the classifier's probabilities is aggregated by path and host. A
host's rate is shrunk toward the global rate, and a path's toward its host's, each with the strength (pseudo-count)
that the spread between groups supports, so sparse sites stay near their parent. The posterior log-odds of a
document are the classifier's plus the path's log-odds minus the global ones.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ROW, id_of, lean, materialise, slices, text_of, with_row_key, without_ids
from .words import NOT_ALNUM, KeyTable, mix, parts_of, word_keys

HEADS = ("low", "toxic")
PREFIXES = (0, 4, 5, 6)
_FORMS = 7
#: Bytes of text whose features a worker holds at once, and pairs of row and feature that a step of the fit takes at once.
_HELD, _PAIRS = 1 << 19, 1 << 18
_CLASSES = np.stack([
    np.isin(np.arange(256), np.arange(65, 91)),
    np.isin(np.arange(256), np.arange(97, 123)),
    np.isin(np.arange(256), np.arange(48, 58)),
    np.isin(np.arange(256), [*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]),
    np.arange(256) == 10,
    np.arange(256) == 32,
    np.arange(256) >= 128,
]).T.astype(np.uint8)


def _features(texts: list[bytes], table: KeyTable | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(text, feature key) over whole texts, or (text, row of ``table``) for the keys it has; pairs may repeat."""
    owners, keys, words = [], [], np.zeros(len(texts))
    forms, sizes = np.zeros((len(texts), _FORMS)), np.array([len(t) for t in texts], np.float64)

    def add(owner: np.ndarray, key: np.ndarray) -> None:
        if table is not None:
            key = table.find(key)
            owner, key = owner[key >= 0], key[key >= 0]
        owners.append(owner)
        keys.append(key)

    for parts in parts_of(texts):
        of = np.array([i for i, _, _ in parts])
        data = np.frombuffer(b"".join(texts[i][a:b] for i, a, b in parts), np.uint8)
        sizes_here = np.array([b - a for _, a, b in parts])
        edges = np.cumsum(sizes_here)
        for j in range(_FORMS):
            total = np.append(0, np.cumsum(_CLASSES[:, j][data], dtype=np.int32))
            np.add.at(forms[:, j], of, total[edges] - total[edges - sizes_here])
        for prefix in PREFIXES:
            k, n = word_keys(texts, parts, NOT_ALNUM, prefix)
            if not prefix:
                np.add.at(words, of, n)
            add(np.repeat(of, n), k)
    upper, lower, digit, mark, line, space, high = forms.T
    letters = np.maximum(upper + lower + high, 1)
    size, count = np.maximum(sizes, 1), np.maximum(words, 1)
    packed = np.array([len(zlib.compress(t, 1)) for t in texts], np.float64)
    measures = np.stack([upper / letters, digit / size, mark / size, mark / count, line / count * 10, space / size, letters / count / 10, packed / size, np.log2(count + 1) / 20, high / size])
    for m, values in enumerate(measures):
        # bins of a twentieth, the last open
        add(np.arange(len(texts)), (np.minimum((values * 20).astype(np.int64), 40) + 64 * m + 1).astype(np.uint64))
    return np.concatenate(owners), np.concatenate(keys)


def _groups(texts: list[bytes], size: int = _HELD) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about so many bytes, whose features are made at once."""
    start = held = 0
    for i, t in enumerate(texts):
        held += len(t)
        if held >= size:
            yield start, i + 1
            start, held = i + 1, 0
    if start < len(texts):
        yield start, len(texts)


def _once(owner: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each pair once."""
    _, first = np.unique(key ^ mix(owner.astype(np.uint64) + np.uint64(1)), return_index=True)
    return owner[first], key[first]


@dataclass
class Classifier:
    """keys of features, weights (features x heads), bias by head."""

    keys: np.ndarray
    weights: np.ndarray
    bias: np.ndarray

    def logits(self, texts: list[bytes]) -> np.ndarray:
        parts = [self._logits(texts[a:b]) for a, b in _groups(texts)]
        return np.concatenate(parts) if parts else np.zeros((0, len(HEADS)))

    def _logits(self, texts: list[bytes]) -> np.ndarray:
        table = self.__dict__.setdefault("_table", KeyTable(self.keys))
        owner, row = _features(texts, table)
        pair = np.unique(owner * max(1, len(self.keys)) + row)
        owner, row = pair // max(1, len(self.keys)), pair % max(1, len(self.keys))
        return np.stack([self.bias[h] + np.bincount(owner, self.weights[row, h], len(texts)) for h in range(len(HEADS))], axis=1)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_table"}


def _fit_logistic(ends: np.ndarray, row: np.ndarray, n_features: int, target: np.ndarray, ridge: float = 0.5, rounds: int = 400, tolerance: float = 1e-4) -> tuple[np.ndarray, float]:
    """Ridge logistic regression on binary features by limited-memory quasi-Newton steps, until no weight moves more than
    ``tolerance`` or ``rounds`` are done. ``row`` lists the features of each text, ``ends`` where each text's end."""
    n = len(target)
    rate = (target.sum() + 0.5) / (n + 1)
    size = np.diff(ends, prepend=0)
    cuts, at = [], 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _PAIRS, "right")))
        cuts.append((at, to, int(ends[at - 1]) if at else 0, int(ends[to - 1])))
        at = to

    def loss(x: np.ndarray) -> tuple[float, np.ndarray]:
        w, b = x[:-1], x[-1]
        value, slope = ridge / 2 * float(w @ w), np.append(ridge * w, 0.0)
        for a, z, first, last in cuts:
            found = row[first:last]
            sums = np.append(0.0, np.cumsum(w[found]))
            score = b + sums[ends[a:z] - first] - sums[ends[a:z] - size[a:z] - first]
            value += float((np.logaddexp(0, score) - target[a:z] * score).sum())
            gap = 1 / (1 + np.exp(-np.clip(score, -30, 30))) - target[a:z]
            slope[:-1] += np.bincount(found, np.repeat(gap, size[a:z]), n_features)
            slope[-1] += gap.sum()
        return value, slope

    pace = max(1.0, np.percentile(size, 90) if n else 1)
    scale = 2 / pace / np.append(np.maximum(np.bincount(row, minlength=n_features), 1) + ridge, max(n, 1) / 2)
    x = np.append(np.zeros(n_features), np.log(rate / (1 - rate)))
    value, slope = loss(x)
    past: list[tuple[np.ndarray, np.ndarray, float]] = []
    for _ in range(rounds):
        q, shares = slope.copy(), []
        for s, y, r in reversed(past):
            shares.append(r * float(s @ q))
            q -= shares[-1] * y
        q *= scale * (float(past[-1][0] @ past[-1][1]) / float(past[-1][1] @ (scale * past[-1][1])) if past else 1.0)
        for (s, y, r), share in zip(past, reversed(shares)):
            q += (share - r * float(y @ q)) * s
        fall, length = float(slope @ q), 1.0
        while True:
            step = -length * q
            after, new = loss(x + step)
            if after <= value - 1e-4 * length * fall or length < 1e-6:
                break
            length /= 2
        if after > value:  # as low as rounding lets it be
            break
        bend = float(step @ (new - slope))
        if bend > 0:
            past = [*past[-9:], (step, new - slope, 1 / bend)]
        x, value, slope = x + step, after, new
        if np.abs(step).max(initial=0) < tolerance:
            break
    return x[:-1], float(x[-1])


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", sample_rows: int = 20_000, max_features: int = 20_000, least_rows: int = 4, least_z: float = 5.0) -> Classifier:
    """The classifier of a bounded sample of the labelled rows (quality 0 is low; null labels count as neither)."""
    order = F.xxhash64(F.col("doc_id"))
    picked = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), (F.coalesce("quality", F.lit(1)) == 0).cast("int").alias("low"), (F.coalesce("toxic", F.lit(0)) == 1).cast("int").alias("toxic"))
        .filter("doc_id is not null").groupBy("doc_id").agg(F.max("low").alias("low"), F.max("toxic").alias("toxic"))
        .orderBy(order, "doc_id").limit(sample_rows)
    )
    picked = materialise(picked.coalesce(1), "quality-sample").select(F.col("doc_id").alias("__id"), "low", "toxic")
    rows = docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(picked), F.col("doc_id") == F.col("__id")).select("text", "low", "toxic")
    rows = materialise(rows, "quality-rows")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, sums = np.empty(0, np.uint64), np.empty((0, 3), np.int64)
        for batch in (part for whole in batches for part in slices(whole, 0, 1 << 20)):
            texts = [x.encode("utf-8", "surrogatepass") for x in batch.column(0).to_pylist()]
            marks = np.stack([np.ones(len(texts)), batch.column(1).to_numpy(), batch.column(2).to_numpy()], axis=1).astype(np.int64)
            for a, b in _groups(texts):
                owner, key = _once(*_features(texts[a:b]))
                found, where = np.unique(np.concatenate([keys, key]), return_inverse=True)
                values = np.concatenate([sums, marks[a + owner]])
                sums = np.stack([np.bincount(where, values[:, j], len(found)) for j in range(3)], axis=1).astype(np.int64)
                keys = found
        if len(keys):
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), *(pa.array(sums[:, j]) for j in range(3))], names=["key", "n", "low", "toxic"])

    whole = rows.agg(F.count(F.lit(1)).alias("n"), F.sum("low").alias("low"), F.sum("toxic").alias("toxic")).first()
    n = whole["n"]
    if not n:  # nothing is labelled
        return Classifier(np.empty(0, np.uint64), np.zeros((0, 2)), np.full(2, -30.0))
    z = []
    for head in HEADS:
        rate = F.lit(((whole[head] or 0) + 0.5) / (n + 1))
        z.append(F.abs(F.col(head) - F.col("n") * rate) / F.sqrt(F.col("n") * rate * (1 - rate) + 0.5))
    tested = (
        rows.mapInArrow(lean(count), "key long, n long, low long, toxic long").groupBy("key").agg(*[F.sum(c).alias(c) for c in ("n", *HEADS)])
        .filter(F.col("n") >= least_rows).withColumn("z", F.greatest(*z)).filter(F.col("z") >= least_z)
        .orderBy(F.desc("z"), "key").limit(max_features).select("key").toArrow()
    )
    keys = tested.column("key").to_numpy().view(np.uint64)
    table = KeyTable(keys)

    def design(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in slices(whole, 0, _HELD)):
            texts = [x.encode("utf-8", "surrogatepass") for x in batch.column(0).to_pylist()]
            lists: list[np.ndarray] = []
            for a, b in _groups(texts):
                owner, row = _features(texts[a:b], table)
                pair = np.unique(owner * max(1, len(keys)) + row)
                ends = np.searchsorted(pair, np.arange(1, b - a) * max(1, len(keys)))
                lists += np.split((pair % max(1, len(keys))).astype(np.int32), ends)
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array(lists, pa.list_(pa.int32()))], names=["low", "toxic", "rows"])

    held = rows.mapInArrow(lean(design), "low int, toxic int, rows array<int>").toArrow()  # at most sample_rows rows
    lists = held.column("rows").combine_chunks()
    ends, row = lists.offsets.to_numpy()[1:].astype(np.int64), lists.values.to_numpy().astype(np.intp)
    fitted = [_fit_logistic(ends, row, len(keys), held.column(h).to_numpy().astype(float)) for h in HEADS]
    return Classifier(keys, np.stack([w for w, _ in fitted], axis=1), np.array([b if whole[h] else -30.0 for (_, b), h in zip(fitted, HEADS)]))


def evidence(docs: DataFrame, model: Classifier, *, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang") -> DataFrame:
    """doc_id, host, path and the classifier's log-odds of each head for each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in slices(whole, 3, _HELD)):
            logits = model.logits([x.encode("utf-8", "surrogatepass") for x in batch.column(3).to_pylist()]) if batch.num_rows else np.zeros((0, 2))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(logits[:, 0]), pa.array(logits[:, 1])], names=["doc_id", "host", "path", "z_low", "z_toxic"])

    rows = docs.select(id_of(id_col).alias("doc_id"), F.col(f"`{host_col}`").cast("string").alias("host"), F.col(f"`{path_col}`").cast("string").alias("path"), text_of(text_col).alias("text"))
    return rows.mapInArrow(lean(run), "doc_id long, host string, path string, z_low double, z_toxic double")


def _logit(p: Column) -> Column:
    return F.ln(p / (1 - p))


def _strength(groups: DataFrame, total: str, parent: Column, most: float = 1e6) -> float:
    """Pseudo-count by moments: the spread of group rates around the parent's beyond what their sizes explain."""
    rate = F.col(total) / F.col("n")
    spread = F.sum(F.col("n") * (rate - parent) ** 2)
    noise = F.sum(parent * (1 - parent))
    row = groups.agg(spread.alias("spread"), noise.alias("noise"), F.sum("n").alias("n"), F.count(F.lit(1)).alias("k")).first()
    if not row["k"] or row["noise"] is None:
        return most
    # E spread = noise * (1 - rho) + rho * sum(n p (1 - p)); rho is the share of variance between groups
    within = row["noise"] / row["k"]
    rho = (row["spread"] / row["k"] - within) / max(within * (row["n"] / row["k"] - 1), 1e-12)
    return min(most, max(1.0, 1 / rho - 1)) if rho > 1 / most else most


def posteriors(scored: DataFrame) -> DataFrame:
    """host, path, n and the shrunk rates of both heads (and the shift of log-odds) for each path."""
    chance = {h: 1 / (1 + F.exp(-F.col(f"z_{h}"))) for h in HEADS}
    paths = materialise(scored.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), *[F.sum(chance[h]).alias(h) for h in HEADS]), "quality-paths")
    hosts = paths.groupBy("host").agg(*[F.sum(c).alias(c) for c in ("n", *HEADS)])
    whole = paths.agg(*[F.sum(c).alias(c) for c in ("n", *HEADS)]).first()
    n = whole["n"] or 0
    rate = {h: ((whole[h] or 0.0) + 0.5) / (n + 1.0) for h in HEADS}
    for h in HEADS:
        k = _strength(hosts, h, F.lit(rate[h]))
        hosts = hosts.withColumn(f"host_{h}", (F.col(h) + k * rate[h]) / (F.col("n") + k))
    hosts = hosts.select(F.col("host").alias("h_"), *[f"host_{h}" for h in HEADS])
    joined = materialise(paths.join(hosts, F.col("host").eqNullSafe(F.col("h_"))).drop("h_"), "quality-sites")
    for h in HEADS:
        k = _strength(joined, h, F.col(f"host_{h}"))
        joined = joined.withColumn(f"path_{h}", (F.col(h) + k * F.col(f"host_{h}")) / (F.col("n") + k))
        joined = joined.withColumn(f"shift_{h}", _logit(F.col(f"path_{h}")) - F.lit(float(np.log(rate[h] / (1 - rate[h])))))
    return joined.select("host", "path", "n", *[c for h in HEADS for c in (f"host_{h}", f"path_{h}", f"shift_{h}")])


def classify(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang", threshold: float = 0.5, model: Classifier | None = None, **fitting) -> DataFrame:
    """doc_id, p_low, p_toxic, site_low, site_toxic, keep for each row.

    A row is kept unless the posterior of a head reaches ``threshold``. Null texts count as empty; null hosts and
    paths are groups of their own; without labels the classifier is sure of nothing and all rows are kept. Repeated
    rows repeat; an empty table gives an empty result; other columns are ignored.
    """
    model = model or fit(docs, labels, id_col=id_col, text_col=text_col, **fitting)
    scored = materialise(evidence(docs, model, id_col=id_col, text_col=text_col, host_col=host_col, path_col=path_col), "quality-scored")
    sites = posteriors(scored).select(F.col("host").alias("h_"), F.col("path").alias("p_"), *[F.col(f"path_{h}").alias(f"site_{h}") for h in HEADS], *[f"shift_{h}" for h in HEADS])
    joined = scored.join(sites, F.col("host").eqNullSafe(F.col("h_")) & F.col("path").eqNullSafe(F.col("p_")))
    p = {h: 1 / (1 + F.exp(-(F.col(f"z_{h}") + F.col(f"shift_{h}")))) for h in HEADS}
    return joined.select(
        "doc_id", *[p[h].alias(f"p_{h}") for h in HEADS], *[f"site_{h}" for h in HEADS],
        ((p["low"] < threshold) & (p["toxic"] < threshold)).alias("keep"),
    )


def keep_good(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang", model: Classifier | None = None, threshold: float = 0.5, **fitting) -> DataFrame:
    """The rows of ``docs`` that :func:`classify` keeps, with all their columns; rows of one id are judged on their own."""
    model = model or fit(docs, labels, id_col=id_col, text_col=text_col, **fitting)
    rows = with_row_key(docs, id_col, text_col, host_col, path_col)
    judged = classify(rows, labels, id_col=ROW, text_col=text_col, host_col=host_col, path_col=path_col, threshold=threshold, model=model)
    return without_ids(rows, judged.filter(~F.col("keep")).select("doc_id"), ROW).drop(ROW)
