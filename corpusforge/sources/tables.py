"""Declared schemas, scans with a schema check, and sinks."""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "benchmark": "item_id bigint, text string",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def check(df: DataFrame, name: str) -> DataFrame:
    """df if it has the declared columns with their kinds (any integer counts as any other)."""
    from pyspark.sql.types import StructType

    want = StructType.fromDDL(SCHEMAS[name])
    whole = {"int": "n", "bigint": "n", "smallint": "n"}
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    wrong = [f.name for f in want if whole.get(have.get(f.name), have.get(f.name)) != whole.get(f.dataType.simpleString(), f.dataType.simpleString())]
    if wrong:
        raise ValueError(f"{name}: columns missing or of another kind: {wrong}")
    return df


def write_partitioned(df: DataFrame, path: str, by: list[str], rows_per_file: int = 2_000_000) -> None:
    """Parquet by partition; each task writes sorted runs, so files stay few and prunable."""
    df.sortWithinPartitions(*by).write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).partitionBy(*by).parquet(path)


def write_jsonl(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def manifest(df: DataFrame, key: str) -> DataFrame:
    """Row count and an order-free digest of a data set."""
    return df.agg(F.count(F.lit(1)).alias("n_rows"), F.sum(F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 8), 16, 10).cast("bigint")).alias("digest"))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only in local mode."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir is not set: driver and executors need a shared folder")
    import tempfile

    return tempfile.mkdtemp(prefix="corpusforge-")


_WRITTEN: list[str] = []


def cut_lineage(df: DataFrame) -> DataFrame:
    """df written to the shared folder as Parquet and read back: loops stay restartable, plans short, and a lost
    executor costs no more than what is being worked on. The table goes when the driver ends."""
    spark = df.sparkSession
    if not _WRITTEN:
        atexit.register(_forget, spark)
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _forget(spark: SparkSession) -> None:
    for path in _WRITTEN:
        try:
            where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # noqa: BLE001
            return


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int = 32) -> DataFrame:
    """df as a table bucketed and sorted by a key: later joins and aggregations on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


def read_files(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """A declared schema over csv (with header), json, text, orc or parquet files; malformed rows fail the job."""
    reader = spark.read.schema(schema)
    if kind in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    if kind == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(kind).load(path)


def write_files(df: DataFrame, path: str, kind: str) -> None:
    writer = df.write.mode("overwrite")
    if kind == "csv":
        writer = writer.option("header", True).option("escape", '"')
    writer.format(kind).save(path)
