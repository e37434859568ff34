"""Synthetic answers: candidates, a stand-in judge, judge filter, best of N, multiple choice, baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import text as T

PASS = 9


def make_candidates(conv: DataFrame) -> DataFrame:
    """Each user turn with the assistant turns of its conversation as candidate answers."""
    u = conv.where("role = 'user'").select("conv_id", F.col("turn").alias("u_turn"), F.col("text").alias("prompt"))
    a = conv.where("role = 'assistant'").select("conv_id", "turn", F.col("text").alias("answer"))
    x = u.join(a, "conv_id")
    order = Window.partitionBy("conv_id", "u_turn").orderBy("turn")
    return x.withColumn("cand_no", F.row_number().over(order).cast("bigint")).select((F.col("conv_id") * 1000 + F.col("u_turn")).alias("prompt_id"), "cand_no", F.concat(F.lit("gen"), (F.col("turn") % 3).cast("string")).alias("generator"), "prompt", "answer")


def judge(cands: DataFrame) -> DataFrame:
    """Stand-in judge, 1 to 10: length of the answer and words shared with the prompt."""
    w = T.words(F.lower("answer"))
    shared = F.size(F.array_intersect(w, T.words(F.lower("prompt"))))
    s = 1 + F.least(F.lit(5), F.floor(F.size(w) / 12)) + F.least(F.lit(4), shared)
    return cands.withColumn("judge_proxy", s.cast("bigint"))


def judge_filter(df: DataFrame, least: int = PASS) -> DataFrame:
    return df.where(F.col("judge_proxy") >= least)


def best_of_n(df: DataFrame, seed: int = 0) -> DataFrame:
    """Top score of each prompt; ties by a seeded hash. An aggregate, so no group is sorted."""
    best = F.max_by(F.struct("cand_no", "judge_proxy"), F.struct("judge_proxy", T.uniform(F.col("prompt_id"), F.col("cand_no"), F.lit(seed)), "cand_no"))
    return df.groupBy("prompt_id").agg(best.alias("b"), F.count(F.lit(1)).alias("candidates")).select("prompt_id", "b.*", "candidates")


def select_baseline(df: DataFrame, kind: str, seed: int = 0) -> DataFrame:
    """first, random, longest, or one generator."""
    if kind == "one_generator":
        df = df.where("generator = 'gen0'")
    order = {"first": -F.col("cand_no"), "random": T.uniform(F.col("prompt_id"), F.col("cand_no"), F.lit(seed)), "longest": F.struct(F.length("answer"), -F.col("cand_no")), "one_generator": -F.col("cand_no")}[kind]
    return df.groupBy("prompt_id").agg(F.max_by("cand_no", order).alias("cand_no"), F.max_by("judge_proxy", order).alias("judge_proxy"))


def synthetic_report(df: DataFrame) -> DataFrame:
    return df.rollup("generator").agg(F.count(F.lit(1)).alias("rows"), F.round(F.avg("judge_proxy"), 6).alias("mean_judge")).withColumn("generator", F.coalesce("generator", F.lit("(all)")))


#: Items of a bucket in which distractors are sought, and the least number of buckets.
BUCKET_ITEMS, LEAST_BUCKETS = 100_000, 16


def make_mcq(df: DataFrame, k: int = 3, buckets: int | None = None, seed: int = 0) -> DataFrame:
    """Items with k distractors from the next answers of the same hashed bucket, and a seeded position.

    Buckets follow the number of items, so that each is a window one task can hold.
    """
    if buckets is None:
        buckets = max(LEAST_BUCKETS, -(-df.count() // BUCKET_ITEMS))
    b = F.pmod(F.conv(F.substring(F.md5(F.col("prompt_id").cast("string")), 1, 8), 16, 10).cast("bigint"), F.lit(buckets))
    order = Window.partitionBy("_b").orderBy("prompt_id")
    x = df.withColumn("_b", b).withColumns({f"d{i}": F.lead("answer", i).over(order) for i in range(1, k + 1)})
    x = x.where(F.col(f"d{k}").isNotNull()).withColumn("gold", F.floor(T.uniform(F.col("prompt_id"), F.lit(seed)) * (k + 1)).cast("bigint"))
    others = F.array(*[F.col(f"d{i}") for i in range(1, k + 1)])
    options = F.concat(F.slice(others, F.lit(1), F.col("gold").cast("int")), F.array("answer"), F.slice(others, (F.col("gold") + 1).cast("int"), F.lit(k)))
    return x.select("prompt_id", "gold", options.alias("options"))


#: Kinds of sources, their category, the phase from which they enter, and their languages.
KINDS = (
    ("filtered web text", "web", 1, "all"),
    ("sentence pairs", "parallel", 1, "all"),
    ("document pairs", "parallel", 2, "all"),
    ("code and maths text", "code_math", 1, "all"),
    ("educational code and maths training sets", "code_math", 2, "all"),
    ("judged synthetic answers", "code_math", 3, "all"),
    ("encyclopaedia", "higher_quality", 1, "all"),
    ("papers and books", "higher_quality", 1, "en"),
    ("synthetic textbooks", "higher_quality", 2, "en"),
    ("translated synthetic textbooks", "higher_quality", 3, "de es fr it nl pt ru zh"),
)


def source_kinds(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(k, c, p, langs.split()) for k, c, p, langs in KINDS], "kind string, category string, from_phase int, languages array<string>")


def sources_for_phase(kinds: DataFrame, phase: int) -> DataFrame:
    """Kinds of sources that a phase reads: what has entered stays."""
    return kinds.where(F.col("from_phase") <= phase)


def translate_documents(docs: DataFrame, targets: tuple[str, ...], corpus: DataFrame) -> DataFrame:
    """doc_id, lang, text: English documents rendered in each target language (stand-in for translation)."""
    from . import language

    english, out = docs.where("lang = 'en'"), None
    for lang in targets:
        part = language.translate(english, language.rank_lexicon(corpus, "en", lang)).withColumn("lang", F.lit(lang))
        out = part if out is None else out.unionByName(part)
    return out.select("doc_id", "lang", "text")


def mix_generators(frames: dict[str, DataFrame]) -> DataFrame:
    """Originals and several generators' answers in one frame, by name."""
    out = None
    for name, df in frames.items():
        part = df.withColumn("generator", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def rewrite_questions(df: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Stand-in for rewriting: a polite frame around the question with its words replaced through a lexicon; ids stay."""
    from . import language

    said = language.translate(df, lexicon, "prompt_id", "prompt")
    return df.drop("prompt").join(said, "prompt_id").withColumn("prompt", F.concat(F.lit("Please answer: "), "prompt"))


def translate_items(items: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Multiple-choice items with every option rendered through a lexicon; ids and right answers stay."""
    from . import language

    options = items.select("prompt_id", F.posexplode("options").alias("o", "text")).select(F.struct("prompt_id", "o").alias("key"), "text")
    said = options.select("key").join(language.translate(options, lexicon, "key"), "key", "left")
    by = said.groupBy(F.col("key.prompt_id").alias("prompt_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct(F.col("key.o").alias("o"), F.coalesce("text", F.lit("")).alias("t")))), lambda x: x["t"]).alias("options"))
    return items.select("prompt_id", "gold").join(by, "prompt_id")
