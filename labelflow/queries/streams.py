"""Streaming queries: finite streams of the events, run to their end and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import encode_ids
from ..session import cut, state_dir
from ..sources.tables import EpochStore, event_stream, table
from ..streaming import streams as st
from . import fixtures as fx
from .methods import ma_plan, r6
from .sql import KB, cells_sql, iterate, ma, with_

Q, SQL = {}, {}
SPEC = fx.spec(64, 4)


def query(sql: str | None = None):
    def put(f):
        Q[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


def _stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_stream(spark, st.split_by_day(spark, sf_dir))


_START = "strftime({}, '%Y-%m-%d %H:%M:%S')"


def _named(df: DataFrame) -> DataFrame:
    return df.select(F.date_format("window_start", "yyyy-MM-dd HH:mm:ss").alias("window_start"), F.col("cell").cast("long").alias("cell"), r6("val").alias("val"))


@query(f"SELECT {_START.format('w')} AS window_start, cell, round(sum(value), 6) AS val FROM (SELECT date_trunc('day', ts) AS w, value, {cells_sql('user_id', SPEC)} AS cell FROM events) GROUP BY 1, 2")
def stream_window_cells(spark, sf_dir):
    """Windows of a day, by the last update of each cell, so that the last windows are there too."""
    return _named(st.collected(st.tumbling_sketch(_stream(spark, sf_dir), SPEC), ("window_start", "cell")))


@query(f"""SELECT {_START.format('w')} AS window_start, cell, round(sum(value), 6) AS val FROM (
SELECT time_bucket(INTERVAL '15 minutes', ts) - k * INTERVAL '15 minutes' AS w, value, {cells_sql('user_id', SPEC)} AS cell FROM events, (SELECT unnest([0, 1, 2, 3]) AS k)) GROUP BY 1, 2""")
def stream_sliding_cells(spark, sf_dir):
    return _named(st.collected(st.tumbling_sketch(_stream(spark, sf_dir), SPEC, "1 hour", slide="15 minutes"), ("window_start", "cell")))


@query("""WITH g AS (SELECT user_id, ts, value, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS session_start, count(*) AS n, round(sum(value), 6) AS total FROM s GROUP BY user_id, s.n""")
def stream_session_totals(spark, sf_dir):
    """Sessions are written once the watermark has passed them; a closing row lets it pass all."""
    stream = event_stream(spark, st.split_by_day(spark, sf_dir, closing=True))
    out = st.collected(st.session_totals(stream)).filter(F.col("user_id") != st.CLOSING_USER)
    return out.select("user_id", F.date_format("session_start", "yyyy-MM-dd HH:mm:ss").alias("session_start"), "n", r6("total").alias("total"))


@query("""WITH last AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events), late AS (SELECT date_trunc('day', ts) AS w FROM events ORDER BY ts, event_id LIMIT 20)
SELECT strftime(w, '%Y-%m-%d') AS day, count(*) AS n, (SELECT count(DISTINCT w) FROM late) AS late_groups FROM (SELECT date_trunc('day', ts) AS w FROM events), last WHERE w + INTERVAL 1 DAY <= mark GROUP BY w""")
def stream_late_drop(spark, sf_dir):
    """Rows by day that a watermark of an hour lets through when the 20 earliest events come again at the end, and how
    many groups of late rows were dropped (the engine counts them after summing each batch)."""
    path = st.split_by_day(spark, sf_dir)
    late = spark.read.parquet(path).orderBy("ts", "event_id").limit(20)
    cut(late, "late").coalesce(1).write.mode("append").parquet(path)
    counted = event_stream(spark, path).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    reports: list = []
    out = st.collected(counted.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"), progress=reports)
    dropped = sum(s["numRowsDroppedByWatermark"] for r in reports for s in r["stateOperators"])
    return out.select("day", "n", F.lit(dropped).cast("long").alias("late_groups"))


@query("""SELECT e.event_id, d.node, round(e.value, 6) AS value FROM events e JOIN (SELECT key, row_number() OVER (ORDER BY key) - 1 AS node FROM (SELECT DISTINCT user_id::VARCHAR AS key FROM events)) d ON d.key = e.user_id::VARCHAR""")
def stream_named_events(spark, sf_dir):
    """The stream joined with a static dictionary of nodes."""
    users = table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("key")).distinct()
    named = st.with_nodes(_stream(spark, sf_dir), cut(encode_ids(users, ["key"], "node"), "users").select("key", "node"))
    return st.collected(named).select("event_id", "node", r6("value").alias("value"))


@query("""SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE AND a.event_id <> b.event_id""")
def stream_interval_edges(spark, sf_dir):
    """Two streams of the events joined within an hour for each user: edges between events that follow each other."""
    path = st.split_by_day(spark, sf_dir)
    return st.collected(st.interval_edges(event_stream(spark, path), event_stream(spark, path)))


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, sf_dir):
    """Every file twice within the watermark: each event comes out once."""
    doubled = event_stream(spark, st.split_by_day(spark, sf_dir, copies=2))
    return st.collected(st.deduplicated(doubled).select("event_id", "user_id"))


@query(f"SELECT node, cell, round(sum(value), 6) AS val FROM (SELECT user_id AS node, value, {cells_sql('event_id', SPEC)} AS cell FROM events) GROUP BY 1, 2")
def stream_seed_state(spark, sf_dir):
    out = st.collected(st.seed_state(_stream(spark, sf_dir), SPEC), ("node", "cell"))
    return out.select("node", F.col("cell").cast("long").alias("cell"), r6("val").alias("val"))


@query(with_(KB, ma(), iterate(4, start="seeds WHERE false")) + " SELECT node, label, round(score, 5) AS score FROM y4 WHERE round(score, 5) > 0")
def stream_warm_start(spark, sf_dir):
    """The seeds arrive in two batches; each propagates alone from zero and the contributions add up."""
    t = fx.parts_kb(spark, sf_dir)
    plan = ma_plan(t)
    path = f"{state_dir(spark)}/seeds-{abs(hash((sf_dir, id(t), spark.sparkContext.applicationId)))}"
    t.seeds.repartition(2, "label").write.mode("overwrite").parquet(path)
    stream = spark.readStream.schema("node long, label long, score double").option("maxFilesPerTrigger", 1).parquet(path)
    store = EpochStore(spark, f"{path}-epochs-{id(stream)}")
    q = st.follow_seeds(stream, plan, t.seeds.limit(0).select("node", "label", "score"), store, 4).option("checkpointLocation", f"{path}-check-{id(stream)}").start()
    q.awaitTermination()
    return store.latest()[1].select("node", "label", F.round("score", 5).alias("score")).filter("score > 0")
