"""Relational surface: as-of join, interval join, salted aggregation, sketches."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, days: int = 30) -> DataFrame:
    """Each left row with the latest right value at or before its time, without an inequality join.

    Rows meet in windows of one key and some days, so a busy key is many tasks. What a window inherits is
    carried from the last one of its key that holds a right row: a frame of one row a key and window.
    """
    slot = F.floor(F.datediff(F.col(at).cast("date"), F.lit("1970-01-01").cast("date")) / days)
    kind = right.schema[value].dataType
    a = left.select(*left.columns, F.lit(None).cast(kind).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(*[F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(0).alias("_side"))
    both = a.unionByName(b).withColumn("_slot", slot)
    ends = both.groupBy(key, "_slot").agg(F.max_by("_v", F.when((F.col("_side") == 0) & F.col("_v").isNotNull(), F.col(at))).alias("_last"))
    earlier = Window.partitionBy(key).orderBy("_slot").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select(F.col(key).alias("_k"), F.col("_slot").alias("_ks"), F.last("_last", ignorenulls=True).over(earlier).alias("_before"))
    inside = Window.partitionBy(key, "_slot").orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    here = both.withColumn("_here", F.last("_v", ignorenulls=True).over(inside)).where("_side = 1")
    out = here.join(carried, here[key].eqNullSafe(F.col("_k")) & here["_slot"].eqNullSafe(F.col("_ks")), "left")
    return out.withColumn(value, F.coalesce("_here", "_before")).drop("_v", "_side", "_slot", "_last", "_before", "_here", "_k", "_ks")


def interval_join(events: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs of events of one key at most so many seconds apart, by time buckets: an equi-join."""
    t = F.unix_seconds(F.col(at).cast("timestamp"))
    x = events.withColumn("_t", t).withColumn("_b", F.floor(F.col("_t") / seconds))
    a = x.select(key, F.col("event_id").alias("a"), F.col("_t").alias("ta"), F.explode(F.array(F.col("_b"), F.col("_b") + 1)).alias("b"))
    b = x.select(F.col(key).alias("_k"), F.col("event_id").alias("b_id"), F.col("_t").alias("tb"), F.col("_b"))
    return a.join(b, (F.col(key) == F.col("_k")) & (F.col("b") == F.col("_b"))).where((F.col("tb") >= F.col("ta")) & (F.col("tb") - F.col("ta") <= seconds) & (F.col("a") != F.col("b_id"))).select(key, "a", F.col("b_id").alias("b"))


def salted_count(df: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Two-level count: a hot key is split over salts first."""
    part = df.withColumn("_s", F.pmod(F.xxhash64(*df.columns[:1]), F.lit(salts))).groupBy(key, "_s").agg(F.count(F.lit(1)).alias("n"))
    return part.groupBy(key).agg(F.sum("n").alias("n"))


def count_min(df: DataFrame, key: str, epsilon: float = 0.001, confidence: float = 0.99, seed: int = 1) -> DataFrame:
    """A mergeable count-min sketch of a column, one row of bytes."""
    return df.agg(F.count_min_sketch(key, F.lit(epsilon), F.lit(confidence), F.lit(seed)).alias("sketch"))


def reservoir(df: DataFrame, k: int, by: list[str], key: str, seed: int = 0) -> DataFrame:
    """A uniform sample of k rows a group: those with the smallest seeded hashes, cut in every task before the shuffle."""
    from ..functions import text as T

    w = Window.partitionBy(*by).orderBy("_u", key)
    return df.withColumn("_u", T.uniform(F.col(key), F.lit(seed))).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_u", "_r")


def stratified(df: DataFrame, column: str, fractions: dict[str, float], key: str, seed: int = 0) -> DataFrame:
    """A share of each value's rows, by a hash of the key: the same under any partitioning; values not named go."""
    from ..functions import text as T

    share = F.lit(0.0)
    for k, v in fractions.items():
        share = F.when(F.col(column) == k, F.lit(v)).otherwise(share)
    return df.where(T.uniform(F.col(key), F.lit(seed)) < share)


@udtf(returnType="pos: bigint, part: string", useArrow=False)
class UrlParts:
    """The parts of a URL after its scheme, numbered from 1; a null URL has none."""

    def eval(self, url: str):
        if url is not None:
            for i, part in enumerate(re.sub(r"^[a-z]+://", "", url).split("/"), 1):
                yield i, part
