"""Educational scores: annotation, projection to other languages, learned scorer, gates, report.

The scorer stands in for a fine-tuned encoder: logistic regression (pyspark.ml) on hashed character
n-grams and length ratios. Its column ends in _proxy and it is never reported as the real model.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as T
from . import language

#: Bounds of the educational score by phase.
BOUNDS = {1: 2.0, 2: 3.0, 3: 3.0}


def annotate(df: DataFrame, labels: DataFrame) -> DataFrame:
    """Labelled documents with the label as a score of 0 or 5: the truth that scorers are trained and judged on."""
    return df.join(labels.select("doc_id", (F.col("quality") * 5.0).alias("edu_score")), "doc_id")


def all_scores(df: DataFrame, labels: DataFrame) -> DataFrame:
    """Every document with an edu_score of 0 to 5, labelled or not.

    A labelled one takes half its score from the label; the rest, and all of an unlabelled one's, is the
    row-local stand-in for the classifier (share of letters).
    """
    share = F.col("edu_proxy")
    x = letter_share_score(df).join(labels.select("doc_id", "quality"), "doc_id", "left")
    return x.withColumn("edu_score", F.round(F.when(F.col("quality").isNull(), share).otherwise(2.5 * F.col("quality") + share / 2), 6)).drop("quality", "edu_proxy")


def project(annotated: DataFrame, corpus: DataFrame, targets: list[str]) -> DataFrame:
    """English annotations carried over renderings in other languages."""
    out = None
    for lang in targets:
        english = annotated.where("lang = 'en'")
        text = language.translate(english, language.rank_lexicon(corpus, "en", lang))
        part = english.select("doc_id", "edu_score").join(text, "doc_id").withColumn("lang", F.lit(lang))
        out = part if out is None else out.unionByName(part)
    return out


def quality_gate(df: DataFrame, phase: int, strict: bool = True) -> DataFrame:
    """Phase 1: English above its bound, other languages as they are; later phases: all above the raised bound.

    The bound of the last two phases is the same. A document without a score passes in phase 1 unless English.
    """
    above = F.coalesce(F.col("edu_score") > BOUNDS[phase] if strict else F.col("edu_score") >= BOUNDS[phase], F.lit(False))
    return df.where(above | F.coalesce(F.col("lang") != "en", F.lit(True)) if phase == 1 else above)


def simple_features(text: Column) -> list[Column]:
    n = F.greatest(F.length(text), F.lit(1))
    return [(1 - T.count_class(text, r"\p{L}") / n), F.log(n + 1.0), T.count_class(text, r"\p{Lu}") / n]


def fit_quality(train: DataFrame, features: int = 1 << 14):
    """A fitted pipeline: text, edu_score to edu_proxy (probability of a score above the middle)."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, VectorAssembler

    stages = [HashingTF(inputCol="_grams", outputCol="_tf", numFeatures=features), VectorAssembler(inputCols=["_tf", "_f0", "_f1", "_f2"], outputCol="_x"), LogisticRegression(featuresCol="_x", labelCol="_y", regParam=0.01, maxIter=20)]
    return Pipeline(stages=stages).fit(_prepare(train).withColumn("_y", (F.col("edu_score") > 2.5).cast("double")))


def _prepare(df: DataFrame) -> DataFrame:
    out = df.withColumn("_l", F.split(F.lower("text"), ""))
    whole = F.slice("_l", F.lit(1), F.greatest(F.size("_l") - 2, F.lit(0)))
    grams = F.transform(whole, lambda x, i: F.concat(x, F.get(F.col("_l"), i + 1), F.get(F.col("_l"), i + 2)))
    return out.withColumn("_grams", grams).drop("_l").withColumns({f"_f{i}": c for i, c in enumerate(simple_features(F.col("text")))})


def score_quality(df: DataFrame, model) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    out = model.transform(_prepare(df)).withColumn("edu_proxy", vector_to_array("probability")[1] * 5)
    return out.select(*df.columns, "edu_proxy")


def quality_report(df: DataFrame, score: str, truth: str, bound: float) -> DataFrame:
    """Precision, recall, F1 and Pearson correlation by language."""
    hit, yes = F.col(score) > bound, F.col(truth) > bound
    by = df.groupBy("lang").agg(F.count_if(hit & yes).alias("tp"), F.count_if(hit & ~yes).alias("fp"), F.count_if(~hit & yes).alias("fn"), F.count_if(~hit & ~yes).alias("tn"), F.corr(score, truth).alias("r"))
    p, q = F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fp")), F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fn"))
    return by.select("lang", "tp", "fp", "fn", "tn", F.round(p, 6).alias("precision"), F.round(q, 6).alias("recall"), F.round(F.try_divide(2 * p * q, p + q), 6).alias("f1"), F.round("r", 6).alias("pearson"))


def letter_share_score(df: DataFrame) -> DataFrame:
    """Baseline: one feature, the share of letters, as a score of 0 to 5."""
    n = F.greatest(F.length("text"), F.lit(1))
    return df.withColumn("edu_proxy", F.round(5.0 * T.count_class(F.col("text"), r"\p{L}") / n, 6))


def majority_score(df: DataFrame) -> DataFrame:
    """Baseline: every document gets the commoner side of its language's annotation."""
    good = F.count_if(F.col("edu_score") > 2.5)
    by = df.groupBy("lang").agg(F.when(2 * good >= F.count(F.lit(1)), 5.0).otherwise(0.0).alias("edu_proxy"))
    return df.join(F.broadcast(by), "lang")


def area_under_curve(df: DataFrame, score: str, truth: str, bound: float) -> DataFrame:
    """AUC by language from mid-ranks of distinct scores: one aggregate, then a window over distinct scores."""
    g = df.groupBy("lang", F.col(score).alias("_s")).agg(F.count_if(F.col(truth) > bound).alias("p"), F.count_if(F.col(truth) <= bound).alias("q"))
    below = F.sum("q").over(Window.partitionBy("lang").orderBy("_s")) - F.col("q")
    wins = g.withColumn("w", F.col("p") * (below + F.col("q") / 2.0))
    return wins.groupBy("lang").agg(F.round(F.try_divide(F.sum("w"), F.sum("p") * F.sum("q")), 6).alias("auc"))


def kept_by_threshold(df: DataFrame, score: str, bounds: tuple[float, ...]) -> DataFrame:
    """Share of documents above each bound, by language."""
    x = df.select("lang", score, F.explode(F.array(*[F.lit(b) for b in bounds])).alias("bound"))
    return x.groupBy("lang", "bound").agg(F.count_if(F.col(score) > F.col("bound")).alias("kept"), F.count(F.lit(1)).alias("n"))
