"""Helpers shared by the corpus operators: shared state folder, materialised tables, column guards."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The reserved name of a row's key.
ROW = "__labelflow_row"
#: Rows of an Arrow batch of documents at most.
BATCH_ROWS = 2_000
#: ASCII white space, as the contracts state it.
SPACES = r"[\x20\x09-\x0D]+"


def state_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    It is read from ``spark.checkpoint.dir``; a temporary one is made only where that is unset on a single
    machine, as in tests.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if not known:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="labelflow-"))
        known = spark.sparkContext.getCheckpointDir()
    return known.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: later stages don't repeat its work,
    and the loss of an executor costs nothing that was written."""
    spark = df.sparkSession
    path = f"{state_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path  # for session.discard
    return out


def slices(batch: pa.RecordBatch, text: int, size: int = 1 << 20, rows: int = 2_000) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of at most ``rows`` rows and about ``size`` bytes in its column ``text``, at least a row each."""
    ends = np.cumsum(pc.binary_length(batch.column(text)).fill_null(0).to_numpy(zero_copy_only=False), dtype=np.int64)
    at = 0
    while at < batch.num_rows:
        done = int(ends[at - 1]) if at else 0
        to = min(max(at + 1, int(np.searchsorted(ends, done + size, "right"))), at + rows)
        yield batch.slice(at, to - at)
        at = to


def lean(run: Callable) -> Callable:
    """A function of Arrow batches whose worker gives its memory back to the system: Arrow buffers at once, the rest at
    the end of the task. Workers are used again by later stages, which would pay for what they keep. Rows are whole
    documents here, so the session's Arrow batches are set to BATCH_ROWS rows where they are larger."""
    spark, name = SparkSession.getActiveSession(), "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark is not None and not 0 < int(spark.conf.get(name, "10000")) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim:
                trim(0)

    return wrapped


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def text_of(name: str) -> Column:
    """The text column with null as empty."""
    return F.coalesce(F.col(f"`{name}`").cast("string"), F.lit(""))


def id_of(name: str) -> Column:
    return F.col(f"`{name}`").cast("long")


def with_row_key(docs: DataFrame, *columns: str) -> DataFrame:
    """``docs`` with ROW, a long of these columns: rows that differ in one, null or not, are told apart."""
    parts = [x for c in columns for x in (F.col(f"`{c}`").isNull(), F.col(f"`{c}`"))]
    return docs.withColumn(ROW, F.xxhash64(*parts))


def without_ids(docs: DataFrame, ids: DataFrame, id_col: str, *, broadcast_rows: int = 1_000_000) -> DataFrame:
    """``docs`` but for rows whose id (null included) is in the one column of ``ids``, with all their columns.

    The ids are written first; they are sent to all executors if they are at most ``broadcast_rows``, else both
    sides are dealt by id. Column names that start with ``__labelflow`` are reserved.
    """
    found = materialise(ids.select(F.col(ids.columns[0]).alias("__labelflow_id")).distinct(), "ids")
    side = F.broadcast(found) if found.count() <= broadcast_rows else found
    return docs.join(side, F.col(f"`{id_col}`").eqNullSafe(F.col("__labelflow_id")), "left_anti")
