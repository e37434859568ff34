"""What several operators of this subpackage need: shared folders, sizes, words, hashes."""

from __future__ import annotations

import atexit
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: the six white-space characters that separate words.
SPACE = " \t\n\x0b\f\r"
SPACES_RE = r"[\x20\x09-\x0D]+"


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where none is set, a fresh local one in local mode only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir is not set: driver and executors need a shared folder")
    import tempfile

    folder = spark.conf.get("corpusforge.scratch", None)
    if not folder:
        folder = tempfile.mkdtemp(prefix="corpusforge-")
        spark.conf.set("corpusforge.scratch", folder)
    return folder


_LANDED: list[str] = []


def landed(df: DataFrame, what: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it again: cuts lineage, survives lost executors.

    The table goes when the driver ends, or before with `remove_landed`, once nothing reads it.
    """
    spark = df.sparkSession
    if not _LANDED:
        atexit.register(remove_landed, spark)
    path = f"{shared_folder(spark)}/{what}-{uuid.uuid4().hex}"
    _LANDED.append(path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def landed_so_far() -> int:
    return len(_LANDED)


def remove_landed(spark: SparkSession, since: int = 0, keep: int = 0) -> None:
    """Delete the tables landed from number `since` on, but for the last `keep`; a session that has ended deletes nothing."""
    for path in _LANDED[since : len(_LANDED) - keep]:
        try:
            where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # noqa: BLE001
            return


def block_count(docs: DataFrame, text: str = "text", target: int = 4 << 20, least: int = 256) -> int:
    """How many hashed blocks hold about `target` bytes of text each; one narrow aggregation."""
    size = docs.agg(F.sum(F.octet_length(F.col(text)))).first()[0] or 0
    return max(least, -(-size // target))


def native_words(text: Column) -> Column:
    """Words of a text as an array, by built-in functions only; null and blank texts have none."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACE))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, SPACES_RE, -1))


def text_words(text: str | None) -> list[bytes]:
    """The same words as UTF-8; bytes.split() knows exactly the six separators."""
    return text.encode("utf-8", "surrogatepass").split() if text else []


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


_ODD = np.array([(0x9E3779B97F4A7C15 * (2 * i + 3) ** 5 + 2 * i) % 2**64 | 1 for i in range(16)], np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


def gram_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k consecutive words, from the words' hashes."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = h[:n] * _ODD[0]
    for i in range(1, k):
        out = out + h[i : i + n] * _ODD[i]
    return mixed(out)


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every w neighbours, by doubling."""
    if len(x) < w:
        return np.empty(0, x.dtype)
    have = 1
    while 2 * have <= w:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    rest = w - have
    return np.minimum(x[:-rest], x[rest:]) if rest else x


def record_batch(schema: pa.Schema, **columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in schema], schema=schema)
