"""Table scans with explicit schemas, file readers and writers, sketches on disk, epochs, event streams."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sketch import SketchSpec
from ..session import cut

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table. The schema comes from the file; columns are those of SCHEMAS, so scans prune to what is used."""
    names = [c.split()[0] for c in SCHEMAS[name].replace("array<float>", "array").split(", ")]
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*names)


def _read(spark: SparkSession, path: str, fmt: str, schema: str) -> tuple[DataFrame, DataFrame]:
    """Rows that fit the schema, and those that don't with their text in _corrupt_record (csv, tsv and json only). Text
    is parsed once and written; both results read what was written."""
    if fmt in ("parquet", "orc"):
        df = spark.read.schema(schema).format(fmt).load(path)
        return df, df.limit(0).select(F.lit("").alias("_corrupt_record"))
    reader = spark.read.schema(schema + ", _corrupt_record string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
    reader = reader.format("json") if fmt == "json" else reader.format("csv").option("header", fmt == "csv").option("sep", "," if fmt == "csv" else "\t")
    df = cut(reader.load(path), "read")
    bad = F.col("_corrupt_record").isNotNull()
    return df.filter(~bad).drop("_corrupt_record"), df.filter(bad)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> tuple[DataFrame, DataFrame]:
    return _read(spark, path, fmt, "src bigint, dst bigint, w double")


def read_seeds(spark: SparkSession, path: str, fmt: str = "parquet") -> tuple[DataFrame, DataFrame]:
    return _read(spark, path, fmt, "node bigint, label bigint, score double")


def read_labels(spark: SparkSession, path: str, fmt: str = "parquet") -> tuple[DataFrame, DataFrame]:
    return _read(spark, path, fmt, "label bigint, name string")


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> str:
    """Write a result to a new directory."""
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
    return path


def bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by ``key``: later joins by it need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def save_sketch(sketch: DataFrame, spec: SketchSpec, path: str) -> None:
    """The sketch and, beside it, its spec and fingerprint in one row."""
    sketch.write.parquet(f"{path}/cells")
    row = [(json.dumps(spec.as_dict()), spec.fingerprint())]
    sketch.sparkSession.createDataFrame(row, "spec string, fingerprint string").coalesce(1).write.parquet(f"{path}/spec")


def load_sketch(spark: SparkSession, path: str, expect: SketchSpec | None = None) -> tuple[DataFrame, SketchSpec]:
    row = spark.read.parquet(f"{path}/spec").first()
    spec = SketchSpec.from_dict(json.loads(row["spec"]))
    if spec.fingerprint() != row["fingerprint"]:
        raise ValueError("the stored spec doesn't match its fingerprint")
    if expect is not None:
        expect.assert_same(spec)
    return spark.read.parquet(f"{path}/cells"), spec


class EpochStore:
    """Numbered states of an iteration in one folder; ``latest`` finds where to go on. Keeps the last two."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def put(self, epoch: int, df: DataFrame) -> DataFrame:
        df.write.mode("overwrite").parquet(f"{self.path}/epoch={epoch}")
        for old in [e for e in self.epochs() if e < epoch - 1]:
            self._fs.delete(self._path(f"{self.path}/epoch={old}"), True)
        return self.get(epoch)

    def get(self, epoch: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/epoch={epoch}")

    def epochs(self) -> list[int]:
        """Epochs written to their end."""
        root = self._path(self.path)
        if not self._fs.exists(root):
            return []
        found = [s.getPath() for s in self._fs.listStatus(root)]
        done = [p for p in found if self._fs.exists(self._path(p, "_SUCCESS"))]
        return sorted(int(p.getName().split("=")[1]) for p in done)

    def latest(self) -> tuple[int, DataFrame] | None:
        found = self.epochs()
        return (found[-1], self.get(found[-1])) if found else None


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events of a folder of Parquet files as a stream, in the order of files; ts is a timestamp for watermarks."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def sink(stream: DataFrame, kind: str, target, checkpoint: str | None = None, mode: str = "append"):
    """Start a stream into memory (a view's name), parquet (a path) or foreach (a function of batch and number)."""
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True)
    writer = writer.option("checkpointLocation", checkpoint) if checkpoint else writer
    if kind == "memory":
        return writer.format("memory").queryName(target).start()
    if kind == "parquet":
        return writer.format("parquet").option("path", target).start()
    if kind == "foreach":
        return writer.foreachBatch(target).start()
    raise ValueError(f"no sink of kind {kind}")
