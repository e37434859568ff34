"""The corpus pipeline: quality rules, near-dedup, substring dedup, personal data, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each stage's rows into
the shared folder and reads them again, so a lost executor costs one stage at most. All stages but
the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from corpusforge.llm import near_dedup, packing, pii, quality_rules, substring_dedup
from corpusforge.llm.queries import tokenizer_file
from corpusforge.llm.shared import landed, landed_so_far, remove_landed


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 7: documents that fail a rule go."""
    return quality_rules.keep_quality(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 5: of each group of near copies the document with the smallest id stays."""
    return near_dedup.drop_near_duplicates(docs)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 1: passages that stand in an earlier document are cut out."""
    return substring_dedup.cut_repeats(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 3: spans of personal data are replaced by their kind."""
    return pii.mask_personal(docs, pii.fit_spans(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 8: every piece of every document gets its place in a training sequence."""
    return packing.pack_documents(docs, tokenizer_file("byte_bpe_50k.json").decode())


STAGES = [("quality", quality), ("near_copies", near_copies), ("repeats", repeats), ("personal_data", personal_data), ("pack", pack)]
#: Learned span scores, registers and bin packing have no SQL form; a test holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before = landed_so_far()
        docs = landed(stage(spark, docs, sf_dir), f"stage-{name}")
        # What the stage landed on its way, and its input, are read no more.
        remove_landed(spark, max(0, before - (name != STAGES[0][0])), keep=1)
    return docs
