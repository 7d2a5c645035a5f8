"""The queries of the corpus operators, over whole tables with production parameters, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, decontam, exact_dedup, line_dedup, passages, ppm, quality, secrets, sharding, simhash
from .common import read


def tokenizer_files() -> tuple[str, str]:
    """Path of the rank file and the pattern of the public tokenizer."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(read(spark, sf_dir, "documents"), *tokenizer_files())


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_dedup_report(read(spark, sf_dir, "documents"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find_secrets(read(spark, sf_dir, "documents"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_components(read(spark, sf_dir, "documents"))


def op6_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages.repeat_report(read(spark, sf_dir, "documents"))


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.stratified_shards(read(spark, sf_dir, "documents"))


def op8_ppm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.ppm_scores(read(spark, sf_dir, "documents"))


def op9_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.find_leaks(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(read(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_byte_bpe, op2_line_dedup, op3_quality, op4_secrets, op5_simhash, op6_passages, op7_sharding, op8_ppm, op9_decontam, op10_exact_dedup)}

ORACLE_SQL = {
    "op2_line_dedup": r"""
        WITH pages AS (SELECT doc_id, source AS host, coalesce(text, '') AS body FROM documents),
        totals AS (SELECT host, count(*) AS pages FROM pages GROUP BY host),
        seen AS (
            SELECT host, line, count(*) AS n
            FROM (SELECT host, unnest(list_distinct(string_split(body, chr(10)))) AS line FROM pages)
            WHERE regexp_matches(line, '[^\x20\x09-\x0D]')
            GROUP BY host, line
        ),
        bad AS (
            SELECT s.host, s.line FROM seen s JOIN totals t ON s.host IS NOT DISTINCT FROM t.host
            WHERE s.n >= 3 AND s.n > t.pages * 0.1::DOUBLE
        ),
        sets AS (SELECT host, list(line) AS lines FROM bad GROUP BY host),
        kept AS (
            SELECT p.doc_id, p.host, string_split(p.body, chr(10)) AS old,
                   list_filter(string_split(p.body, chr(10)), lambda x: NOT coalesce(list_contains(b.lines, x), false)) AS new
            FROM pages p LEFT JOIN sets b ON p.host IS NOT DISTINCT FROM b.host
        )
        SELECT doc_id, host, len(old)::BIGINT AS n_lines, (len(old) - len(new))::BIGINT AS n_dropped,
               md5(coalesce(array_to_string(new, chr(10)), '')) AS kept_md5
        FROM kept
    """,
    "op7_sharding": rf"""
        WITH steps AS (
            SELECT list(c ORDER BY i) AS crc
            FROM (SELECT i, list_reduce(range(8), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, i) AS c FROM range(256) t(i))
        ),
        sized AS (
            SELECT doc_id, source, strlen(coalesce(text, ''))::BIGINT + 1 AS size,
                   list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda h: ('0x' || h)::BIGINT) AS octets
            FROM documents
        ),
        summed AS (
            SELECT doc_id, source, size, xor(list_reduce(octets, lambda c, o: xor(c >> 8, crc[(xor(c, o) & 255) + 1]), 4294967295::BIGINT), 4294967295) AS text_crc32
            FROM sized, steps
        ),
        once AS (SELECT *, ((doc_id % {sharding.DRAW_P} + 42) * {sharding.DRAW_A}) % {sharding.DRAW_P} AS x FROM summed),
        twice AS (SELECT *, ((xor(x, x >> 15) + 42) * {sharding.DRAW_B}) % {sharding.DRAW_P} AS y FROM once),
        ranked AS (
            SELECT *, (row_number() OVER (PARTITION BY source ORDER BY xor(y, y >> 15), doc_id) - 1 + 0.5::DOUBLE) / count(*) OVER (PARTITION BY source) AS fraction
            FROM twice
        ),
        placed AS (
            SELECT *, row_number() OVER (ORDER BY fraction, source, xor(y, y >> 15), doc_id) - 1 AS place, count(*) OVER () AS total FROM ranked
        )
        SELECT doc_id, size, text_crc32, 'rows' AS law, (place * 8 // total)::INT AS shard,
               place - ((place * 8 // total) * total + 7) // 8 AS slot, NULL::INT AS grown_shard, source
        FROM placed
    """,
    "op10_exact_dedup": r"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents),
        g AS (SELECT body, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY body)
        SELECT n.doc_id, g.keep_id, g.group_size::BIGINT AS group_size, n.doc_id IS NOT DISTINCT FROM g.keep_id AS kept,
               sha256(n.body) AS text_sha256
        FROM n JOIN g ON n.body = g.body
    """,
}
