"""Exact deduplication by skew-safe combining, with DataFrame functions only.

1. *Locally*: the partial aggregation keyed by (digest, salt, whole text) merges equal texts of a task before
   anything is shuffled.
2. *Salted merge*: the same aggregation finishes by (digest, salt, whole text). The salt is 0 for ordinary
   digests, so for these the group is complete. A digest that holds more than 1/1024 of all rows is dealt over
   ``salts`` parts by the document's id.
3. *Global merge*: the few salt winners of hot digests are combined by (digest, whole text).

Texts are grouping keys at each stage, so the whole content is compared; the digest only places rows. Before it also
names the text of a row in the last join, the merged table is searched for a digest with two texts (an error).
At most 1024 digests can be hot, hence the broadcast of their list has a fixed bound, and the texts of the
corpus cross the network once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACES, id_of, materialise, text_of

#: A digest is hot when it has over 1/HOT_PARTS of the rows: there are fewer than HOT_PARTS such digests.
HOT_PARTS = 1024


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, collapse_spaces: bool = True, salts: int = 64) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Null texts count as empty and equal the empty text. ``keep_id`` is the smallest non-null id among equal
    texts (null if all ids are null) and ``kept`` is true where the row's id is that id, so rows repeated with the
    same id and text are all kept and counted in ``group_size``. An empty table gives an empty result. Other
    columns are ignored, whatever their names.
    """
    body = text_of(text_col)
    if collapse_spaces:
        body = F.regexp_replace(body, SPACES, " ")
    rows = docs.select(id_of(id_col).alias("doc_id"), body.alias("body")).withColumn("digest", F.unhex(F.sha2("body", 256)))
    keys = materialise(rows.select("doc_id", "digest"), "exact-keys")
    limit = max(16, keys.count() // HOT_PARTS)
    hot = materialise(keys.groupBy("digest").count().filter(F.col("count") > limit).select("digest", F.lit(True).alias("hot")), "exact-hot")

    def salted(df: DataFrame) -> DataFrame:
        part = F.when(F.col("hot"), F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int")).otherwise(F.lit(-1))
        return df.join(F.broadcast(hot), "digest", "left").withColumn("salt", part).drop("hot")

    merged = salted(rows).groupBy("digest", "salt", "body").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    merged = materialise(merged.withColumn("body", F.when(F.col("salt") >= 0, F.col("body"))), "exact-merged")
    # texts were compared whole; a digest stands for one text from here on
    if merged.groupBy("digest", "salt").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").limit(1).count():
        raise ValueError("different texts share a SHA-256 digest")
    parts = merged.filter("salt >= 0")
    whole = parts.groupBy("digest", "body").agg(F.min("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    winners = (
        merged.filter("salt < 0").drop("body")
        .unionByName(parts.select("digest", "salt", "body").join(whole, ["digest", "body"]).drop("body"))
    )
    return (
        salted(keys).join(winners, ["digest", "salt"])
        .select(
            "doc_id", "keep_id", "group_size",
            F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
            F.lower(F.hex("digest")).alias("text_sha256"),
        )
    )


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that :func:`exact_dedup` keeps, with all their columns."""
    kept = exact_dedup(docs, id_col, text_col, **options).filter("kept").select(F.col("doc_id").alias("__keep_id")).distinct()
    return docs.join(kept, docs[id_col].eqNullSafe(kept["__keep_id"]), "left_semi")
