"""Accounting: parameters, steps, schedules, phases."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Hyper-parameters of the reference model.
REFERENCE = {"vocab": 128_000, "width": 4096, "ffn": 12_288, "layers": 42, "heads": 32, "kv_heads": 8, "tied": False}
#: Sequences and tokens of a step, tokens of each phase, peak rate, tuning rate.
SEQUENCES, LENGTH = 2800, 4096
PHASE_TOKENS = (3_600_000_000_000, 400_000_000_000, 40_000_000_000)
PEAK, TUNING_RATE, EPOCHS = 3e-4, 7e-6, 3


def embedding_params(vocab: int, width: int, tied: bool = False) -> int:
    return vocab * width * (1 if tied else 2)


def param_account(cfg: DataFrame) -> DataFrame:
    """Parameters by part for rows of hyper-parameters."""
    d, kv = F.col("width"), F.col("width") / F.col("heads") * F.col("kv_heads")
    attention = (2 * d * d + 2 * d * kv).cast("bigint")
    out = cfg.withColumns({"embedding": (F.col("vocab") * d).cast("bigint"), "head": F.when(F.col("tied"), F.lit(0)).otherwise(F.col("vocab") * d).cast("bigint"), "attention_layer": attention, "ffn_layer": (3 * d * F.col("ffn")).cast("bigint"), "kv_share": F.col("kv_heads") / F.col("heads")})
    out = out.withColumn("body", (F.col("layers") * (F.col("attention_layer") + F.col("ffn_layer") + 2 * d) + d).cast("bigint"))
    return out.withColumn("total", F.col("embedding") + F.col("head") + F.col("body"))


def config_frame(spark: SparkSession) -> DataFrame:
    c = REFERENCE
    rows = [("reference", c["vocab"], c["width"], c["ffn"], c["layers"], c["heads"], c["kv_heads"], c["tied"]), ("double vocabulary", 2 * c["vocab"], c["width"], c["ffn"], c["layers"], c["heads"], c["kv_heads"], False)]
    return spark.createDataFrame(rows, "model string, vocab bigint, width bigint, ffn bigint, layers bigint, heads bigint, kv_heads bigint, tied boolean")


def phase_steps(spark: SparkSession, tokens=PHASE_TOKENS, sequences: int = SEQUENCES, length: int = LENGTH) -> DataFrame:
    rows = spark.createDataFrame([(i + 1, t) for i, t in enumerate(tokens)], "phase int, tokens bigint")
    return rows.withColumn("steps", F.ceil(F.col("tokens") / (sequences * length)))


@dataclass(frozen=True)
class Schedule:
    """Steps of phases 1+2 and of the last; warm-up and decay as shares of the former."""

    main: int = math.ceil(sum(PHASE_TOKENS[:2]) / (SEQUENCES * LENGTH))
    last: int = math.ceil(PHASE_TOKENS[2] / (SEQUENCES * LENGTH))
    peak: float = PEAK
    warm: float = 0.1
    flat: float = 0.9
    floor: float = 0.1

    def rate(self, step: Column, kind: str = "trapezoid") -> Column:
        n, w, p = float(self.main), self.warm * self.main, self.flat * self.main
        s = step.cast("double")
        warm = self.peak * s / w
        if kind == "constant":
            return F.when(s < w, warm).otherwise(F.lit(self.peak))
        if kind == "cosine":
            return F.when(s < w, warm).when(s < n, self.peak * (self.floor + (1 - self.floor) * 0.5 * (1 + F.cos(math.pi * (s - w) / (n - w))))).otherwise(F.lit(self.peak * self.floor))
        decay = F.when(s < w, warm).when(s < p, F.lit(self.peak)).when(s < n, self.peak * (1 - (1 - self.floor) * (s - p) / (n - p)))
        if kind == "two_phase" or not self.last:
            return decay.otherwise(F.lit(self.peak * self.floor))
        return decay.otherwise(self.peak * self.floor * (1 - F.least((s - n) / self.last, F.lit(1.0))))


def lr_schedule(spark: SparkSession, schedule: Schedule = Schedule(), stride: int = 100, kind: str = "trapezoid") -> DataFrame:
    steps = spark.range(0, schedule.main + schedule.last + 1, stride).withColumnRenamed("id", "step")
    n, s = schedule.main, F.col("step")
    return steps.select("step", F.when(s < round(0.9 * n), 1).when(s < n, 2).otherwise(3).alias("phase"), F.round(schedule.rate(s, kind), 12).alias("lr"))


def laid_over(df: DataFrame, tokens: str, schedule: Schedule = Schedule(), kind: str = "trapezoid", key: str = "doc_id") -> DataFrame:
    """key, step, phase, lr: the step at which each document begins when df is read once over the whole calendar."""
    total = df.agg(F.sum(tokens).cast("bigint").alias("_total"))
    x = assign_phase(df.select(key, tokens), tokens, [], key).crossJoin(F.broadcast(total))
    s = F.col("step")
    x = x.withColumn("step", F.expr(f"(running - {tokens}) * {schedule.main + schedule.last} div nullif(_total, 0)"))
    return x.select(key, "step", F.when(s < round(0.9 * schedule.main), 1).when(s < schedule.main, 2).otherwise(3).alias("phase"), F.round(schedule.rate(s, kind), 12).alias("lr"))


def phase_steps_of(df: DataFrame, tokens: str, shares=PHASE_TOKENS, sequences: int = SEQUENCES, length: int = LENGTH, key: str = "doc_id") -> DataFrame:
    """phase, tokens, steps of df, cut at the shares that the published phases have of all tokens."""
    total = df.agg(F.sum(tokens).cast("bigint").alias("_total"))
    x = assign_phase(df.select(key, tokens), tokens, [], key).crossJoin(F.broadcast(total))
    unit = math.gcd(*shares)
    parts, phase = [t // unit for t in shares], F.lit(len(shares))
    for i in range(len(shares) - 1, 0, -1):
        phase = F.when(F.col("running") * sum(parts) <= F.col("_total") * sum(parts[:i]), F.lit(i)).otherwise(phase)
    by = x.groupBy(phase.alias("phase")).agg(F.sum(tokens).cast("bigint").alias("tokens"))
    return by.withColumn("steps", F.ceil(F.col("tokens") / (sequences * length)))


def vocabulary_configs(words: DataFrame) -> DataFrame:
    """Hyper-parameters of the reference with every word of a language in its vocabulary, for rows (lang, word)."""
    c = REFERENCE
    rest = [F.lit(c[k]).cast("bigint").alias(k) for k in ("width", "ffn", "layers", "heads", "kv_heads")]
    return words.select("lang", "word").distinct().groupBy("lang").agg(F.count(F.lit(1)).alias("vocab")).select(F.col("lang").alias("model"), "vocab", *rest, F.lit(c["tied"]).alias("tied"))


#: Rows that one task of a running sum takes.
RUNNING_ROWS = 1_000_000


def assign_phase(df: DataFrame, tokens: str, bounds: list[int], key: str = "doc_id") -> DataFrame:
    """Running token count in shuffled order to phase. Two-level prefix sum: no window over all rows.

    The order is a hash of the key, cut into slices; slice totals (a small frame) give each slice's offset,
    and sums run inside slices.
    """
    from pyspark.sql import Window

    from ..functions import text as T

    slices = max(8, -(-df.count() // RUNNING_ROWS))
    sliced = df.withColumn("_u", T.uniform(F.col(key))).withColumn("_s", F.floor(F.col("_u") * slices).cast("int"))
    totals = sliced.groupBy("_s").agg(F.sum(tokens).alias("_n"))
    ahead = totals.select("_s", (F.sum("_n").over(Window.partitionBy(F.lit(0)).orderBy("_s")) - F.col("_n")).alias("_ahead"))
    at = F.sum(tokens).over(Window.partitionBy("_s").orderBy("_u", key)) + F.col("_ahead")
    out = sliced.join(ahead, "_s").withColumn("running", at)
    phase = F.lit(len(bounds) + 1)
    for i in range(len(bounds), 0, -1):
        phase = F.when(F.col("running") <= bounds[i - 1], F.lit(i)).otherwise(phase)
    return out.withColumn("phase", phase).drop("_u", "_s", "_ahead")


def sft_steps(rows: int, batch: int, epochs: int = EPOCHS) -> int:
    return epochs * math.ceil(rows / batch)
