"""Proportional stratified interleaving: shards that all show the mixture of sources, with DataFrame functions only.

Rows of each source are ranked in a seeded shuffle order; a row's fractional rank is (rank + 1/2) / rows of its
source. In the order of fractional ranks, any contiguous cut of 1/n of the rows holds 1/n of each source up to a
row. Both rankings are global sorts without a global window: rows are dealt by range, sorted within their
partition and numbered there, and the numbers of the partitions before them are added from a table with one row
for each partition.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import id_of, materialise, text_of

_IN_PARTITION = (1 << 33) - 1
#: The prime and the factors of the seeded order.
DRAW_P, DRAW_A, DRAW_B = 2_147_483_647, 1_103_515_245, 1_664_525


def _draw(id_column: Column, seed: int) -> Column:
    """A seeded number below 2^31 for each id: two products modulo a prime, the upper bits folded in after each."""
    x = F.pmod(F.coalesce(id_column, F.lit(0)), F.lit(DRAW_P))
    for factor in (DRAW_A, DRAW_B):
        x = F.pmod((x + F.lit(seed)) * F.lit(factor), F.lit(DRAW_P))
        x = x.bitwiseXOR(F.shiftright(x, 15))
    return x


def _numbered(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """``df`` sorted over all partitions, with ``part`` and the row's ``nth`` there. Written once, so numbers hold."""
    dealt = df.repartitionByRange(*[F.col(c) for c in order]).sortWithinPartitions(*order)
    nth = F.monotonically_increasing_id().bitwiseAND(F.lit(_IN_PARTITION))
    return materialise(dealt.select("*", F.spark_partition_id().alias("part"), nth.alias("nth")), name)


def stratified_shards(docs: DataFrame, n_shards: int = 8, *, seed: int = 42, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "source") -> DataFrame:
    """One row per input row: doc_id, size, text_crc32, law ('rows'), shard, slot, grown_shard (null), source.

    Sizes of shards differ by one row at most and slots are gapless from 0 in each. Null sources form a stratum
    of their own; null texts count as empty (size 1, checksum 0). Repeated rows are ranked one after another.
    An empty table gives an empty result; other columns are ignored.
    """
    body = text_of(text_col)
    rows = docs.select(
        id_of(id_col).alias("doc_id"),
        F.col(f"`{stratum_col}`").cast("string").alias("source"),
        (F.octet_length(body).cast("long") + 1).alias("size"),
        F.crc32(body.cast("binary")).alias("text_crc32"),
    ).withColumn("draw", _draw(F.col("doc_id"), seed))
    first = _numbered(rows, ["source", "draw", "doc_id", "text_crc32", "size"], "shard-ranked")
    counts = first.groupBy("part", "source").agg(F.min("nth").alias("start"), F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(
        F.col("part").alias("p"), F.col("source").alias("s"), "start",
        F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"),
        F.sum("n").over(Window.partitionBy("source")).alias("total"),
    )
    rank = F.col("before") + F.col("nth") - F.col("start")
    ranked = (
        first.join(counts, (F.col("part") == F.col("p")) & F.col("source").eqNullSafe(F.col("s")))
        .withColumn("fraction", (rank + F.lit(0.5)) / F.col("total"))
        .select("doc_id", "source", "size", "text_crc32", "draw", "fraction")
    )
    second = _numbered(ranked, ["fraction", "source", "draw", "doc_id", "text_crc32", "size"], "shard-mixed")
    sizes = second.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    # one row for each partition of the sort
    sizes = sizes.select(
        F.col("part").alias("p"),
        (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"),
        F.sum("n").over(Window.partitionBy(F.lit(1))).alias("total"),
    )
    exact = F.expr(f"cast((before + nth) * {int(n_shards)} div total as int)")
    return (
        second.join(F.broadcast(sizes), F.col("part") == F.col("p"))
        .withColumn("shard", exact)
        .withColumn("slot", F.expr(f"before + nth - (shard * total + {int(n_shards) - 1}) div {int(n_shards)}"))
        .select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")
    )
