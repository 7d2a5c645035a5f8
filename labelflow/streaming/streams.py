"""Sketches of event streams with Structured Streaming, and propagation that follows a stream of seeds.

A sketch is a sum, so windows of a stream are ordinary streaming aggregates by (window, cell); state is bounded by the
active windows' cells and closed by the watermark.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sketch import SketchSpec, cells_of
from ..operators.propagate import residual_update
from ..plans.affine import AffinePlan
from ..session import cut, state_dir
from ..sources.tables import SCHEMAS


def _spread(events: DataFrame, key: str, val: str, spec: SketchSpec) -> DataFrame:
    return events.select("ts", F.explode(cells_of(F.col(key), spec)).alias("cell"), F.col(val).cast("double").alias("val"))


def tumbling_sketch(events: DataFrame, spec: SketchSpec, width: str = "1 day", lateness: str = "1 hour", slide: str | None = None, key: str = "user_id", val: str = "value") -> DataFrame:
    """window_start, cell, val: a sketch of each window (sliding if ``slide`` is given)."""
    rows = _spread(events.withWatermark("ts", lateness), key, val, spec)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.groupBy(window.alias("w"), "cell").agg(F.sum("val").alias("val")).select(F.col("w.start").alias("window_start"), "cell", "val")


def session_totals(events: DataFrame, gap: str = "30 minutes", lateness: str = "1 hour") -> DataFrame:
    """user_id, session_start, n, total of each session."""
    s = F.session_window("ts", gap)
    out = events.withWatermark("ts", lateness).groupBy(s.alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return out.select("user_id", F.col("s.start").alias("session_start"), "n", "total")


def deduplicated(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Each event id once within the watermark."""
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def seed_state(events: DataFrame, spec: SketchSpec) -> DataFrame:
    """node, cell, val: the running sketch of each user's events (update mode)."""
    rows = events.select(F.col("user_id").alias("node"), F.explode(cells_of(F.col("event_id"), spec)).alias("cell"), F.col("value").alias("val"))
    return rows.groupBy("node", "cell").agg(F.sum("val").alias("val"))


def with_nodes(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """A stream of events joined with a static node dictionary (key, node)."""
    return events.join(dictionary, events["user_id"].cast("string") == dictionary["key"]).select("ts", "event_id", "node", "value")


def interval_edges(left: DataFrame, right: DataFrame, minutes: int = 60) -> DataFrame:
    """Edges between events of two streams by the same user at most so many minutes later."""
    a = left.withWatermark("ts", "1 hour").select(F.col("event_id").alias("src"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = right.withWatermark("ts", "1 hour").select(F.col("event_id").alias("dst"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    near = (F.col("ua") == F.col("ub")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"INTERVAL {minutes} MINUTES")) & (F.col("src") != F.col("dst"))
    return a.join(b, near).select("src", "dst")


def follow_seeds(stream: DataFrame, plan: AffinePlan, start: DataFrame, store, max_iter: int = 3):
    """A foreachBatch function: each batch of new seeds (node, label, score) propagates alone and is added to the
    state, which goes into ``store`` (an EpochStore) as the next epoch. A batch that is replayed isn't added twice."""
    store.put(0, start)

    def apply(batch: DataFrame, number: int) -> None:
        latest, state = store.latest()
        if number + 1 <= latest:
            return
        store.put(number + 1, residual_update(plan, state, cut(batch, "seeds"), max_iter))

    return stream.writeStream.trigger(availableNow=True).foreachBatch(apply)


#: The user of the row that ends a finite stream.
CLOSING_USER = -1


def split_by_day(spark: SparkSession, sf_dir: str, files: int = 6, copies: int = 1, closing: bool = False) -> str:
    """The events in the shared folder as files that follow each other in time, for a file stream (which orders by
    the time of writing). ``closing`` adds a row of CLOSING_USER ten days later, which lets the watermark pass all."""
    path = f"{state_dir(spark)}/events-{uuid.uuid4().hex}"
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select(*[c.split()[0] for c in SCHEMAS["events"].split(", ")])
    low, high = e.agg(F.min(F.unix_micros(F.col("ts").cast("timestamp"))), F.max(F.unix_micros(F.col("ts").cast("timestamp")))).first()
    step = ((high or 0) - (low or 0)) // files + 1
    part = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(low or 0)) / step)
    for i in range(files):
        rows = e.filter(part == i).withColumn("n_", F.explode(F.sequence(F.lit(1), F.lit(copies)))).drop("n_")
        rows.coalesce(1).write.mode("append").parquet(path)
    if closing:
        last = e.agg(F.max("ts").alias("ts")).withColumns({"ts": F.col("ts") + F.expr("INTERVAL 10 DAYS"), "event_id": F.lit(-1), "user_id": F.lit(CLOSING_USER), "value": F.lit(0.0)})
        last = last.select(*[F.col(c).cast(t) if c in last.columns else F.lit(None).cast(t).alias(c) for c, t in (x.split() for x in SCHEMAS["events"].split(", "))])
        last.coalesce(1).write.mode("append").parquet(path)
    return path


def collected(stream: DataFrame, keys: tuple[str, ...] = (), progress: list | None = None) -> DataFrame:
    """All rows of a finite stream, through Parquet files: appended rows, or with ``keys`` the last update of each key.

    ``progress`` gets the stream's progress reports.
    """
    spark = stream.sparkSession
    root = f"{state_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{root}/state").trigger(availableNow=True)
    if keys:
        def put(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{root}/out/batch={number}")

        q = writer.outputMode("update").foreachBatch(put).start()
    else:
        q = writer.outputMode("append").format("parquet").option("path", f"{root}/out").start()
    q.awaitTermination()
    if progress is not None:
        progress += q.recentProgress
    if not keys:
        return spark.read.schema(stream.schema).parquet(f"{root}/out")
    rest = [c for c in stream.columns if c not in keys]
    rows = spark.read.schema(stream.schema.add("batch", "long")).parquet(f"{root}/out")
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last"))
    return last.select(*keys, *[F.col(f"last.{c}").alias(c) for c in rest])
