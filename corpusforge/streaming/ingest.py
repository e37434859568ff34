"""Streams: the row-local ladder, dedup within a watermark, windows, and a running token budget.

In tests streams read a folder of Parquet files with an availableNow trigger and land in memory tables
or Parquet; on a cluster the checkpoint location belongs in a shared store.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import web
from ..sources.tables import SCHEMAS


def document_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(SCHEMAS["documents"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(SCHEMAS["events"]).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def ladder_stream(docs: DataFrame) -> DataFrame:
    """The stateless part of the ladder; batch and stream share the code."""
    t = F.col("text")
    return web.paragraph_rules(web.min_chars(docs).where(~web.has_braces(t) & ~web.has_phrase(t) & ~web.has_word(t)))


def dedup_stream(docs: DataFrame, at: str, delay: str = "1 hour") -> DataFrame:
    """First arrival of each text within the watermark; state is bounded by the delay."""
    return docs.withColumn("text_hash", F.md5("text")).withWatermark(at, delay).dropDuplicatesWithinWatermark(["text_hash"])


def tumbling(events: DataFrame, width: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type")
    return w.agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    s = events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return s.agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def token_budget(docs: DataFrame, budgets: dict[str, int]) -> DataFrame:
    """Running words per language against a budget, over the whole stream."""
    x = docs.select("lang", F.size(T.words(F.col("text"))).cast("bigint").alias("n")).groupBy("lang").agg(F.sum("n").alias("tokens"))
    cap = F.lit(None).cast("bigint")
    for k, v in budgets.items():
        cap = F.when(F.col("lang") == k, F.lit(v)).otherwise(cap)
    return x.withColumns({"budget": cap, "full": F.col("tokens") >= cap})


def with_static(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream rows with the columns of a static table; rows without a partner stay."""
    return stream.join(static, key, "left")


def matched_streams(asked: DataFrame, answered: DataFrame, key: str, at: str, within: str, delay: str = "10 minutes") -> DataFrame:
    """Pairs of two streams' rows of one key, the second at most `within` after the first; watermarks bound the state."""
    a = asked.withWatermark(at, delay).select(F.col(key), F.col(at).alias("_a"))
    b = answered.withWatermark(at, delay).select(F.col(key).alias("_k"), F.col(at).alias("_b"))
    on = (F.col(key) == F.col("_k")) & (F.col("_b") >= F.col("_a")) & (F.col("_b") <= F.col("_a") + F.expr(f"interval {within}"))
    return a.join(b, on).select(key, (F.unix_seconds("_b") - F.unix_seconds("_a")).alias("waited"))


def token_ledger(docs: DataFrame, budgets: dict[str, int]) -> DataFrame:
    """(lang, tokens, taken, full): custom state by language: documents are taken until the budget is reached.

    Only numbers leave a batch, one row a language; the state is two of them.
    """
    import pandas as pd

    def step(key, batches, state):
        tokens, taken = state.get if state.exists else (0, 0)
        cap = budgets.get(key[0])
        for b in batches:
            for n in b["n"]:
                if cap is None or tokens < cap:
                    tokens, taken = tokens + int(n), taken + 1
        state.update((tokens, taken))
        yield pd.DataFrame({"lang": [key[0]], "tokens": [tokens], "taken": [taken], "full": [cap is not None and tokens >= cap]})

    counted = docs.select("lang", F.size(T.words(F.col("text"))).cast("bigint").alias("n"))
    return counted.groupBy("lang").applyInPandasWithState(step, "lang string, tokens bigint, taken bigint, full boolean", "tokens bigint, taken bigint", "update", "NoTimeout")
