"""Seeds, label dictionaries and evaluation sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.graph import encode_ids
from .tables import table

#: The linear order by which seeds are drawn.
DRAW_A, DRAW_B, DRAW_P = 1_103_515_245, 12_345, 2_147_483_647


def label_dictionary(members: DataFrame, name: str = "name") -> DataFrame:
    """label, name: dense numbers in the order of names."""
    return encode_ids(members, [name], "label").select("label", F.col(name).alias("name"))


def labelled(members: DataFrame, dictionary: DataFrame) -> DataFrame:
    """node, label from node, name."""
    return members.join(dictionary.withColumnRenamed("name", "n_"), F.col("name") == F.col("n_")).select("node", "label")


def seeds_per_class(gold: DataFrame, per_class: int) -> DataFrame:
    """node, label, score: of each label the members that come first in a fixed pseudo-random order."""
    draw = (F.col("node") * DRAW_A + DRAW_B) % DRAW_P
    ranked = gold.withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy(draw, "node")))
    return ranked.filter(F.col("r") <= per_class).select("node", "label", F.lit(1.0).alias("score"))


def self_injection(nodes: DataFrame) -> DataFrame:
    """Each node seeded with a label of its own, numbered densely."""
    ids = encode_ids(nodes, ["node"], "label")
    return ids.select("node", "label", F.lit(1.0).alias("score"))


def overlap_report(seeds: DataFrame) -> DataFrame:
    """node, labels of nodes with several."""
    return seeds.groupBy("node").agg(F.countDistinct("label").alias("labels")).filter("labels > 1")


def seed_sparsity(seeds: DataFrame) -> DataFrame:
    """k (the largest mass of a seed row), dual_nodes."""
    rows = seeds.groupBy("node").agg(F.sum("score").alias("mass"), F.count(F.lit(1)).alias("n"))
    return rows.agg(F.max("mass").alias("k"), F.sum(F.when(F.col("n") > 1, 1).otherwise(0)).alias("dual_nodes"))


def is_binary(seeds: DataFrame) -> bool:
    return not seeds.filter("score != 0 and score != 1").limit(1).count()


def holdout(gold: DataFrame, seeds: DataFrame) -> DataFrame:
    """The gold rows of nodes that aren't seeded."""
    return gold.join(seeds.select("node").distinct(), "node", "left_anti")


def from_labels_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """node (doc_id), name: quality and toxic as two overlapping labels."""
    flags = F.array(F.when(F.col("quality") == 1, F.lit("quality")), F.when(F.col("toxic") == 1, F.lit("toxic")))
    return table(spark, sf_dir, "labels").select(F.col("doc_id").alias("node"), F.explode(F.filter(flags, lambda x: x.isNotNull())).alias("name"))


def from_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), F.col("label").cast("long").alias("label"))
