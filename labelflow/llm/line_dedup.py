"""Line deduplication by site-relative frequency, with DataFrame functions only.

A line is boilerplate of a site when the share of the site's pages that contain it exceeds ``ratio``. A site can
have at most (mean distinct lines a page) / ratio such lines, so they fit in one array for each site; a page's
text is then filtered in place, and lines are shuffled as 12-byte hashes only, combined before the shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, text_of

#: Above this number of boilerplate lines over all sites, they are joined by site and salt instead of broadcast.
BROADCAST_LINES = 200_000
SALTS = 32


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _key(line: Column) -> Column:
    return F.struct(F.xxhash64(line).alias("a"), F.hash(line).alias("b"))


def boilerplate(docs: DataFrame, *, host_col: str = "source", text_col: str = "text", ratio: float = 0.1, least: int = 3, min_pages: int = 1) -> DataFrame:
    """One row per site that has boilerplate: host, pages, lines (array of line keys)."""
    pages = docs.select(F.col(f"`{host_col}`").cast("string").alias("host"), text_of(text_col).alias("body"))
    totals = pages.groupBy("host").agg(F.count(F.lit(1)).alias("pages")).filter(F.col("pages") >= min_pages)
    said = F.filter(_lines(F.col("body")), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    seen = pages.select("host", F.explode(F.array_distinct(F.transform(said, _key))).alias("line"))
    counts = seen.groupBy("host", "line").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= least)
    t = totals.select(F.col("host").alias("h"), "pages")
    common = counts.join(t, F.col("host").eqNullSafe(F.col("h"))).filter(F.col("n") > F.col("pages") * F.lit(ratio))
    return common.groupBy("host", "pages").agg(F.collect_list("line").alias("lines"))


def _filtered(docs: DataFrame, host_col: str, text_col: str, ratio: float, least: int, min_pages: int, broadcast_lines: int) -> DataFrame:
    """``docs`` with ``__kept``: the lines that stay, null where nothing of the site is boilerplate."""
    found = materialise(boilerplate(docs, host_col=host_col, text_col=text_col, ratio=ratio, least=least, min_pages=min_pages), "line-boilerplate")
    size = found.agg(F.sum(F.size("lines"))).first()[0] or 0
    host = F.col(f"`{host_col}`").cast("string")
    side = found.select(F.col("host").alias("__host"), F.col("lines").alias("__lines"))
    if size <= broadcast_lines:
        joined = docs.join(F.broadcast(side), host.eqNullSafe(F.col("__host")), "left")
    else:
        side = side.withColumn("__part", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salted = docs.withColumn("__salt", F.pmod(F.xxhash64(F.col(f"`{text_col}`")), F.lit(SALTS)).cast("int"))
        joined = salted.join(side, host.eqNullSafe(F.col("__host")) & (F.col("__salt") == F.col("__part")), "left")
    kept = F.filter(_lines(F.col(f"`{text_col}`")), lambda x: ~F.array_contains(F.col("__lines"), _key(x)))
    return joined.withColumn("__kept", F.when(F.col("__lines").isNotNull(), kept))


def drop_boilerplate(docs: DataFrame, *, host_col: str = "source", text_col: str = "text", ratio: float = 0.1, least: int = 3, min_pages: int = 1, broadcast_lines: int = BROADCAST_LINES) -> DataFrame:
    """``docs`` with boilerplate lines taken out of its text; all columns and rows stay.

    A line goes when more than ``ratio`` of the pages of its site contain it (repeats within a page count once), and at
    least ``least`` pages, so that a page and its copy on a small site keep their text. Sites of any size count, unless
    ``min_pages`` is raised. Lines of white
    space only are never boilerplate. Null sites form one site; null texts stay null and count as pages without
    lines; a page whose lines all go has the empty text. Repeated rows count as pages of their own. Other
    columns pass through (names that start with two underscores are reserved).
    """
    text = F.coalesce(F.array_join("__kept", "\n"), F.col(f"`{text_col}`"))
    columns = [text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns]
    return _filtered(docs, host_col, text_col, ratio, least, min_pages, broadcast_lines).select(*columns)


def line_dedup_report(docs: DataFrame, *, id_col: str = "doc_id", host_col: str = "source", text_col: str = "text", ratio: float = 0.1, least: int = 3, min_pages: int = 1, broadcast_lines: int = BROADCAST_LINES) -> DataFrame:
    """doc_id, host, n_lines, n_dropped, kept_md5 for each row; null texts as empty (one line, nothing dropped)."""
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{host_col}`").cast("string").alias("host"), text_of(text_col).alias("text"))
    out = _filtered(rows, "host", "text", ratio, least, min_pages, broadcast_lines)
    n = F.size(_lines(F.col("text"))).cast("long")
    return out.select(
        "doc_id", "host", n.alias("n_lines"),
        F.coalesce(n - F.size("__kept"), F.lit(0)).cast("long").alias("n_dropped"),
        F.md5(F.coalesce(F.array_join("__kept", "\n"), F.col("text"))).alias("kept_md5"),
    )
