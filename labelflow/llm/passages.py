"""Removal of repeated passages: each byte covered by a string of ``span`` bytes that also starts earlier.

1. *Parse*. Texts are cut by rolling-hash triggers (see ``anchors``): every string of ``span`` bytes belongs to one
   segment, namely that of its trigger, and equal strings have equal triggers. A task keeps the first place of each
   (trigger, segment content); its later copies are known to be repeats. At most one row for each trigger and task is
   shuffled, so a passage that a third of all documents share is no hot key.
2. *Triggers that meet*. Of equal segments the first place stays. Where a trigger has one content, that settles all
   strings of it; this is so for all but the borders of repeats. Where it has several, the first segment of each
   content is contested.
3. *Order*. Only contested segments are fetched as text and dealt by trigger. Each task puts its strings in corpus
   order by prefix-free parsing (``pfp``: dictionary and parse suffix ranks) and equal neighbours, compared byte by
   byte, form a class whose first place stays. A trigger with very many contested segments is dealt over several
   tasks, whose class heads are merged by a 128-bit key.
4. *Removal*. The ranges found are grouped by document and taken out.

The order of the whole corpus is never held in one place: parse and dictionary are those of a task's segments.
Places compare by (doc_id, crc32 of the text, byte); segments compare by two 64-bit hashes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anchors import _R2, rolling, segments
from .common import id_of, lean, materialise, text_of
from .pfp import PrefixFreeParse
from .words import mix

_LAST = (1 << 63) - 1
_SCHEMA = "kind int, h long, s long, doc long, uid long, pos long, n long"
_NAMES = ["kind", "h", "s", "doc", "uid", "pos", "n"]
CANDIDATE, MARKER, CONTESTED, REPEAT, HEAD = range(5)
_ORDER_BYTES = 1 << 20
#: Strings whose starts are hashed at once.
_PARSE = 1 << 20


def _rows(kind: int, **columns: np.ndarray) -> Iterator[pa.RecordBatch]:
    size = len(columns["doc"])
    for i in range(0, size, 1 << 17):
        m = min(size - i, 1 << 17)
        get = lambda name: pa.array(columns[name][i : i + m].view(np.int64)) if name in columns else pa.array(np.zeros(m, np.int64))  # noqa: E731, B023
        yield pa.RecordBatch.from_arrays([pa.array(np.full(m, kind, np.int32)), *(get(c) for c in _NAMES[1:])], names=_NAMES)


def _joined(doc: np.ndarray, uid: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, ...]:
    """Byte ranges with those of a document that touch or overlap made one."""
    order = np.lexsort((begin, uid, doc))
    doc, uid, begin, end = doc[order], uid[order], begin[order], end[order]
    if not len(doc):
        return doc, uid, begin, end
    new_doc = np.append(True, (np.diff(doc) != 0) | (np.diff(uid) != 0))
    lift = np.cumsum(new_doc) * (int(end.max()) + 2)  # the documents one after another
    reach = np.maximum.accumulate(end + lift)
    new = np.append(True, (begin + lift)[1:] > reach[:-1])
    first = np.flatnonzero(new)
    return doc[first], uid[first], begin[first], (reach - lift)[np.append(first[1:], len(new)) - 1]


def _first_places(h, s, doc, uid, pos):
    """Order by (h, s, place), where a new h and a new (h, s) begin, and whether the place is that of the first."""
    order = np.lexsort((pos, uid, doc, s, h))
    h, s, doc, uid, pos = h[order], s[order], doc[order], uid[order], pos[order]
    new_h = np.append(True, h[1:] != h[:-1])[: len(h)]
    new = new_h | np.append(True, s[1:] != s[:-1])[: len(h)]
    head = np.flatnonzero(new)[np.cumsum(new) - 1] if len(h) else np.empty(0, np.int64)
    same = (doc == doc[head]) & (uid == uid[head]) & (pos == pos[head])
    return order, new_h, new, same


def _parse_task(span: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        for batch in batches:
            texts = [t.encode("utf-8", "surrogatepass") for t in batch.column(2).to_pylist()]
            docs, uids = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            # strings start in [a, b) of text i
            pieces = [(i, a, min(a + _PARSE, len(t) - span + 1)) for i, t in enumerate(texts) for a in range(0, len(t) - span + 1, _PARSE)]
            at = 0
            while at < len(pieces):
                group, size = [], 0
                while at < len(pieces) and (not group or size + pieces[at][2] - pieces[at][1] + span <= _PARSE):
                    group.append(pieces[at])
                    size += pieces[at][2] - pieces[at][1] + span
                    at += 1
                sizes = np.array([b - a + span - 1 for _, a, b in group])
                starts = np.cumsum(sizes) - sizes
                data = np.frombuffer(b"".join(texts[i][a : b + span - 1] for i, a, b in group), np.uint8)
                piece, first, n, h, s = segments(data, starts, sizes, span, gram)
                of = np.array([i for i, _, _ in group])[piece]
                held.append((h.view(np.int64), s.view(np.int64), docs[of], uids[of], first - starts[piece] + np.array([a for _, a, _ in group])[piece], n))
        if not held:
            return
        h, s, doc, uid, pos, n = (np.concatenate(x) for x in zip(*held))
        held.clear()
        order, new_h, new, same = _first_places(h, s, doc, uid, pos)
        h, s, doc, uid, pos, n = (x[order] for x in (h, s, doc, uid, pos, n))
        late = ~same
        d, u, b, e = _joined(doc[late], uid[late], pos[late], pos[late] + n[late] - 1 + span)
        yield from _rows(REPEAT, h=mix(d.view(np.uint64) * np.uint64(31) + b.view(np.uint64)), doc=d, uid=u, pos=b, n=e - b)
        group = np.cumsum(new_h) - 1
        several = np.bincount(group, new)[group] > 1
        pick = new & ~several
        yield from _rows(CANDIDATE, h=h[pick], s=s[pick], doc=doc[pick], uid=uid[pick], pos=pos[pick], n=n[pick])
        pick = new & several
        # dealt by place: these need no meeting
        yield from _rows(CONTESTED, h=mix(doc[pick].view(np.uint64) * np.uint64(31) + pos[pick].view(np.uint64)), s=h[pick], doc=doc[pick], uid=uid[pick], pos=pos[pick], n=n[pick])
        pick = new_h & several
        yield from _rows(MARKER, h=h[pick], doc=doc[pick])

    return run


def _meet_task(span: int):
    """Candidates of a trigger meet: REPEAT rows are byte ranges, CONTESTED rows have their trigger in ``s``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = []
        for batch in batches:
            table = pa.Table.from_batches([batch])
            passing = table.filter(pa.compute.is_in(table["kind"], pa.array([CONTESTED, REPEAT], pa.int32())))
            yield from passing.to_batches()
            rest = table.filter(pa.compute.is_in(table["kind"], pa.array([CANDIDATE, MARKER], pa.int32())))
            held.append([rest[c].to_numpy() for c in _NAMES])
        if not held:
            return
        kind, h, s, doc, uid, pos, n = (np.concatenate(x) for x in zip(*held))
        held.clear()
        marked = np.unique(h[kind == MARKER])
        row = kind == CANDIDATE
        h, s, doc, uid, pos, n = (x[row] for x in (h, s, doc, uid, pos, n))
        order, new_h, new, same = _first_places(h, s, doc, uid, pos)
        h, s, doc, uid, pos, n = (x[order] for x in (h, s, doc, uid, pos, n))
        late = ~same
        d, u, b, e = _joined(doc[late], uid[late], pos[late], pos[late] + n[late] - 1 + span)
        yield from _rows(REPEAT, h=np.zeros(len(d), np.int64), doc=d, uid=u, pos=b, n=e - b)
        group = np.cumsum(new_h) - 1
        contested = new & ((np.bincount(group, new)[group] > 1) | np.isin(h, marked))
        yield from _rows(CONTESTED, s=h[contested], doc=doc[contested], uid=uid[contested], pos=pos[contested], n=n[contested])

    return run


def _fetch_task(span: int):
    """Contested segments with their bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, uid, h, pos, n, body = [], [], [], [], [], []
            for d, u, text, found in zip(*(c.to_pylist() for c in batch.columns)):
                raw = text.encode("utf-8", "surrogatepass")
                for x in found:
                    doc.append(d)
                    uid.append(u)
                    h.append(x["s"])
                    pos.append(x["pos"])
                    n.append(x["n"])
                    body.append(raw[x["pos"] : x["pos"] + x["n"] - 1 + span])
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in (h, doc, uid, pos, n)), pa.array(body, pa.binary())], names=["h", "doc", "uid", "pos", "n", "body"])

    return run


def _order_task(span: int):
    """Strings of contested segments in suffix order: later places of a class are repeats; heads of salted triggers go on."""

    def resolve(table: pa.Table) -> Iterator[pa.RecordBatch]:
        texts = table["body"].to_pylist()
        doc, uid, pos, n, salt = (table[c].to_numpy() for c in ("doc", "uid", "pos", "n", "salt"))
        parse = PrefixFreeParse(texts)
        segment = np.repeat(np.arange(len(texts)), n)
        offset = np.arange(len(segment)) - np.repeat(np.cumsum(n) - n, n)
        where = parse.starts[segment] + offset
        back = np.zeros(len(parse.symbols), np.int64)
        back[where] = np.arange(len(where))
        ordered, group = parse.equal_runs(where, span)
        string = back[ordered]
        d, u, p = doc[segment[string]], uid[segment[string]], pos[segment[string]] + offset[string]
        rank = np.lexsort((p, u, d, group))
        string, group, d, u, p = string[rank], group[rank], d[rank], u[rank], p[rank]
        head = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
        of = head[np.cumsum(np.append(True, group[1:] != group[:-1])) - 1]
        late = (d != d[of]) | (u != u[of]) | (p != p[of])
        a, b, begin, end = _joined(d[late], u[late], p[late], p[late] + span)
        yield from _rows(REPEAT, doc=a, uid=b, pos=begin, n=end - begin)
        dealt = head[salt[segment[string[head]]] >= 0]
        if len(dealt):
            data = (parse.symbols & 255).astype(np.uint8)
            at = parse.starts[segment[string[dealt]]] + offset[string[dealt]]
            yield from _rows(HEAD, h=rolling(data, span)[at], s=rolling(data, span, _R2)[at], doc=d[dealt], uid=u[dealt], pos=p[dealt])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        if not table.num_rows:
            return
        table = table.sort_by([("h", "ascending"), ("salt", "ascending")]).combine_chunks()
        h, salt = table["h"].to_numpy(), table["salt"].to_numpy()
        ends = np.append(np.flatnonzero((h[1:] != h[:-1]) | (salt[1:] != salt[:-1])) + 1, len(h))
        size = np.cumsum(table["n"].to_numpy() + span)
        at = 0
        while at < len(h):
            base = size[at - 1] if at else 0
            fit = ends[np.searchsorted(size[ends - 1], base + _ORDER_BYTES, "right") - 1] if size[ends[0] - 1] <= base + _ORDER_BYTES else at
            stop = int(fit) if fit > at else int(ends[np.searchsorted(ends, at, "right")])
            yield from resolve(table.slice(at, stop - at))
            at = stop

    def guarded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = list(batches)
        if found:
            yield from run(found)

    return guarded


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = text_of(text_col)
    return docs.select(F.coalesce(id_of(id_col), F.lit(_LAST)).alias("doc"), F.crc32(text.cast("binary")).alias("uid"), text.alias("text"))


def _by_document(docs: DataFrame, found: DataFrame, how: str, columns: list[str], broadcast_rows: int) -> DataFrame:
    """``docs`` with the list ``found`` of its rows there; the table is sent to all if its rows are few enough."""
    grouped = found.groupBy("doc", "uid").agg(F.collect_list(F.struct(*columns)).alias("found"))
    few = found.count() <= broadcast_rows
    return docs.join(F.broadcast(grouped) if few else grouped, ["doc", "uid"], how)


def repeated_ranges(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", span: int = 100, gram: int = 32, hot_rows: int = 5_000, task_bytes: int = 15_000_000, broadcast_rows: int = 0) -> DataFrame:
    """doc, uid, pos, n: byte ranges (they may overlap) of repeated strings. ``doc`` is the id, nulls last."""
    keyed = _keyed(docs, id_col, text_col)
    size = keyed.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), size // task_bytes)
    parsed = keyed.mapInArrow(lean(_parse_task(span, gram)), _SCHEMA)
    met = materialise(parsed.repartition(parts, "h").mapInArrow(lean(_meet_task(span)), _SCHEMA), "passages-met")
    contested = met.filter(F.col("kind") == CONTESTED).select("s", "doc", "uid", "pos", "n")
    hot = materialise(contested.groupBy("s").count().filter(F.col("count") > hot_rows).select(F.col("s").alias("hot"), F.ceil(F.col("count") / hot_rows).alias("salts")), "passages-hot")
    with_text = _by_document(keyed, contested, "inner", ["s", "pos", "n"], broadcast_rows).select("doc", "uid", "text", "found")
    fetched = with_text.mapInArrow(lean(_fetch_task(span)), "h long, doc long, uid long, pos long, n long, body binary")
    salted = fetched.join(F.broadcast(hot), F.col("h") == F.col("hot"), "left").select(
        "h", "doc", "uid", "pos", "n", "body", F.coalesce(F.pmod(F.xxhash64("doc", "uid", "pos"), F.col("salts")), F.lit(-1)).alias("salt")
    )
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), contested.count() * 2 * span // task_bytes)
    ordered = materialise(salted.repartition(parts, "h", "salt").mapInArrow(lean(_order_task(span)), _SCHEMA), "passages-ordered")
    heads = ordered.filter(F.col("kind") == HEAD).select("h", "s", "doc", "uid", "pos")
    lowest = heads.groupBy("h", "s").agg(F.min(F.struct("doc", "uid", "pos")).alias("low"))
    late = heads.join(lowest, ["h", "s"]).filter(F.struct("doc", "uid", "pos") != F.col("low")).select("doc", "uid", "pos", F.lit(span).cast("long").alias("n"))
    settled = met.unionByName(ordered).filter(F.col("kind") == REPEAT).select("doc", "uid", "pos", "n")
    return settled.unionByName(late) if heads.limit(1).count() else settled


def _merge(found: list[dict] | None) -> list[tuple[int, int]]:
    spans: list[tuple[int, int]] = []
    for a, b in sorted((x["pos"], x["pos"] + x["n"]) for x in found or ()):
        if spans and a <= spans[-1][1]:
            spans[-1] = (spans[-1][0], max(b, spans[-1][1]))
        else:
            spans.append((a, b))
    return spans


def _kept(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    parts, at = [], 0
    for a, b in spans:
        parts.append(raw[at:a])
        at = b
    return b"".join(parts) + raw[at:]


def repeat_report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 0, with_text: bool = False, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept, the bytes) for each row.

    Strings are judged on the input, not on what is left; none crosses documents. Null texts count as empty. Null ids
    come after all others; rows that share id and text are one document (neither removes from the other, and each
    row gets its result); rows that share only the id are ordered by the checksum of their text. An empty table gives
    an empty result; other columns are ignored.
    """
    found = repeated_ranges(docs, id_col=id_col, text_col=text_col, broadcast_rows=broadcast_rows, **options)
    found = materialise(found, "passages-ranges")
    keyed = docs.select(id_of(id_col).alias("doc_id"), text_of(text_col).alias("text")).withColumns({"doc": F.coalesce("doc_id", F.lit(_LAST)), "uid": F.crc32(F.col("text").cast("binary"))})
    joined = _by_document(keyed, found, "left", ["pos", "n"], broadcast_rows).select("doc_id", "text", "found")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = [t.encode("utf-8", "surrogatepass") for t in batch.column(1).to_pylist()]
            spans = [_merge(f) for f in batch.column(2).to_pylist()]
            left = [_kept(t, s) for t, s in zip(raw, spans)]
            columns = [
                batch.column(0), pa.array([len(t) for t in raw], pa.int64()), pa.array([sum(b - a for a, b in s) for s in spans], pa.int64()),
                pa.array([len(s) for s in spans], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in left], pa.string()),
            ]
            yield pa.RecordBatch.from_arrays([*columns, *([pa.array(left, pa.binary())] * with_text)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *["kept"] * with_text])

    return joined.mapInArrow(lean(run), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_text)
