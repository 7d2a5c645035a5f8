"""Corpus pipeline: classify, clean lines, drop near copies, drop benchmark leaks, tokenise.

Each stage takes (spark, docs, sf_dir) and works on all rows that the stage before kept. All but the last return the
columns of documents. ORACLE_SQL is None: classifier, fingerprints, edit distances and tokens have no SQL form; the
stages are tested against brute force.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from labelflow.llm import bpe, decontam, line_dedup, quality, simhash
from labelflow.llm.common import materialise, read
from labelflow.llm.queries import tokenizer_files

ORACLE_SQL = None


def drop_bad(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Quality classifier: rows judged low or toxic go."""
    return quality.keep_good(docs, read(spark, sf_dir, "labels"))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Line dedup: boilerplate lines of each source go; n_chars follows the text."""
    from pyspark.sql import functions as F

    return line_dedup.drop_boilerplate(docs).withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars")))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """SimHash near-dedup: the document with the smallest id of each group stays."""
    return simhash.keep_one(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Benchmark decontamination: documents that hold an item go."""
    return decontam.drop_leaks(docs, read(spark, sf_dir, "benchmark"))


def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Byte-level BPE: token counts, digests of ids and of the decoded bytes, and the ids themselves."""
    return bpe.encode_decode(docs, *tokenizer_files(), with_ids=True)


STAGES = [
    ("quality classifier", drop_bad),
    ("line dedup", drop_lines),
    ("simhash near-dedup", drop_copies),
    ("benchmark decontamination", drop_leaks),
    ("byte-level bpe", tokenise),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to documents; what each keeps is written before the next reads it."""
    docs = read(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialise(docs, "pipeline")
    return docs
