"""Session settings for local use, and the shared state folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int = 8, memory: str = "8g", partitions: int | None = None) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName("labelflow")
        .config("spark.sql.shuffle.partitions", partitions or cores)
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def state_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or on a single machine a temporary one where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="labelflow-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: ends the lineage and survives lost executors."""
    path = f"{state_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def written_bytes(df: DataFrame) -> int:
    """The bytes that a frame of :func:`cut` takes on disk."""
    spark = df.sparkSession
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df.written_at)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()


def discard(df: DataFrame | None) -> None:
    """Delete what :func:`cut` or :func:`rest` wrote for ``df``, once nothing reads it any more."""
    path = df.__dict__.get("written_at") if df is not None else None
    if path is None:
        return
    spark = df.sparkSession
    if "written_as" in df.__dict__:
        spark.sql(f"DROP TABLE IF EXISTS {df.written_as}")
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def rest(df: DataFrame, name: str, *keys: str) -> DataFrame:
    """``df`` written bucketed and sorted by ``keys``, in as many buckets as a shuffle has partitions: joins by these
    keys read it where it lies, and only the other side moves."""
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    called = f"lf_{name}_{uuid.uuid4().hex}"
    path = f"{state_dir(spark)}/{called}"
    df.repartition(n, *keys).write.bucketBy(n, *keys).sortBy(*keys).option("path", path).saveAsTable(called)
    out = spark.table(called)
    out.written_at, out.written_as = path, called
    return out
