"""Quality rules: a threshold table compiled into one Spark projection, with no user functions.

`quality_features` computes row-local features (words, symbols, stop words, lines, repeats) with
built-in functions; `compile_rules` turns a table of (rule, feature, low, high, from_words) into
one array of failed rule names. Nothing is shuffled.

Edge cases: a null text counts as empty and fails the base rule (no words); blank texts likewise;
repeated rows and ties are judged row by row; empty tables give empty results; texts of any length
are judged whole, one row at a time; further columns of the input, whatever their names, pass through
`apply_rules` unless they are called like a column that it adds, which replaces them.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import SPACES_RE, native_words

#: Frequent function words of English, French, German and Spanish.
STOP_WORDS = (
    "the of and to in is a that it for on be with as was are by this "
    "la le de les et des en un une que il ou "
    "der die und das den ist ein eine ver "
    "el los y con por las del una"
).split()
#: The languages of the stop words. Texts of others, or of no stated language, are not judged by them.
STOP_LANGUAGES = ("en", "fr", "de", "es")
SYMBOLS = r"[#*$%&|<>]"
#: Letters of scripts written without spaces between words: there, a run between spaces is no word.
UNSPACED = r"[^\p{IsHan}\p{IsHiragana}\p{IsKatakana}\p{IsBopomofo}\p{IsYi}\p{IsThai}\p{IsLao}\p{IsKhmer}\p{IsMyanmar}\p{IsTibetan}\p{IsJavanese}\p{IsBalinese}\p{IsTai_Le}\p{IsNew_Tai_Lue}\p{IsTai_Tham}]"


@dataclass(frozen=True)
class Rule:
    """A document that the rule covers fails if its feature is outside [low, high] and it has at least from_words words."""

    name: str
    feature: str
    low: float | None = None
    high: float | None = None
    from_words: int = 0
    #: "": every text; "spaced": texts of scripts with spaces; "stop_words": texts of STOP_LANGUAGES.
    covers: str = ""


#: The production table. Each rule judges only texts that its measure means something for; none has a cap on size.
DEFAULT_RULES = (
    Rule("symbols", "symbol_ratio", high=0.25),
    Rule("word_length", "mean_word_chars", low=2.0, high=20.0, covers="spaced"),
    Rule("stop_words", "stop_ratio", low=0.005, from_words=300, covers="stop_words"),
    Rule("duplicate_lines", "dup_line_ratio", high=0.6),
)


def _covered(pairs: Column) -> Column:
    """Window starts that have a twin, from (hash, position) pairs in order. `pairs` must be a column, not an expression: it is read inside lambdas."""
    twin = lambda p, j: (p["h"] == F.get(pairs, j - 1)["h"]) | (p["h"] == F.get(pairs, j + 1)["h"])
    return F.array_sort(F.transform(F.filter(pairs, lambda p, j: F.coalesce(twin(p, j), F.lit(False))), lambda p: p["i"]))


def _span(starts: Column) -> Column:
    """Words in 5-word windows at these ascending starts: five each, less what the window before covers."""
    step = F.aggregate(starts, F.struct(F.lit(-5).alias("last"), F.lit(0).alias("n")), lambda a, i: F.struct(i.alias("last"), (a["n"] + F.least(F.lit(5), i - a["last"])).alias("n")))
    return F.coalesce(step["n"], F.lit(0))


#: The columns that `quality_features` adds.
FEATURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "stop_ratio", "symbol_ratio", "mean_word_chars", "dup_line_ratio")


def _boxed(df: DataFrame) -> Column:
    """All columns as one, so that no name of theirs can meet a name used here."""
    return F.struct(*[F.col(f"`{c}`") for c in df.columns])


def _unboxed(row: str, columns: list[str]) -> list[Column]:
    return [F.col(f"{row}.`{c}`").alias(c) for c in columns]


def quality_features(df: DataFrame, text: str = "text") -> DataFrame:
    """df with the features of each text. The expensive arrays are dropped again."""
    columns = df.columns
    df = df.select(_boxed(df).alias("_row"), F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")).alias("_t"))
    df = df.withColumn("_w", native_words(F.col("_t")))
    df = df.withColumns(
        {
            "_wh": F.transform("_w", lambda w: F.xxhash64(w)),
            "_lines": F.filter(F.split("_t", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")),
            "n_words": F.size("_w").cast("long"),
            "word_chars": F.length(F.array_join("_w", "")).cast("long"),
            "n_symbols": (F.length("_t") - F.length(F.regexp_replace("_t", SYMBOLS, ""))).cast("long"),
        }
    )
    # Equal windows give equal hashes wherever they stand.
    grams = F.transform(F.slice("_wh", F.lit(1), F.greatest(F.size("_wh") - 4, F.lit(0))), lambda h, i: F.xxhash64(h, *[F.get(F.col("_wh"), i + k) for k in range(1, 5)]))
    df = df.withColumns({"_g": grams, "_stops": F.size(F.filter("_w", lambda w: F.lower(w).isin(STOP_WORDS)))})
    # Most texts repeat nothing: only the others are sorted.
    pairs = F.sort_array(F.transform("_g", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("_p", F.when(F.size(F.array_distinct("_g")) < F.size("_g"), pairs))
    df = df.withColumn("_p", _covered(F.col("_p")))
    df = df.withColumns(
        {
            "n_lines": F.size("_lines").cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "n_repeat_words": _span(F.col("_p")).cast("long"),
            "stop_ratio": F.coalesce(F.try_divide(F.col("_stops").cast("double"), F.col("n_words")), F.lit(0.0)),
        }
    )
    ratio = lambda a, b: F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))
    df = df.withColumns({"symbol_ratio": ratio("n_symbols", "n_words"), "mean_word_chars": ratio("word_chars", "n_words"), "dup_line_ratio": ratio("n_dup_lines", "n_lines")})
    return df.select(*_unboxed("_row", [c for c in columns if c not in FEATURES]), *FEATURES)


def _covers(text: Column, lang: Column) -> dict[str, Column]:
    """What a rule may cover. Below a tenth of unspaced letters, words without them are long on their own when the mean is."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    unspaced = F.length(F.regexp_replace(text, UNSPACED, ""))
    return {
        "": F.lit(True),
        "spaced": 10 * unspaced < F.greatest(F.col("word_chars"), F.lit(1)),
        "stop_words": F.coalesce(F.regexp_extract(F.lower(lang), "^[a-z]+", 0).isin(*STOP_LANGUAGES), F.lit(False)),
    }


def compile_rules(rules: tuple[Rule, ...] = DEFAULT_RULES, text: str = "text", lang: Column | None = None) -> Column:
    """The names of the rules that a row of features fails."""
    found, covers = [], _covers(F.col(text), F.lit(None).cast("string") if lang is None else lang)
    for r in rules:
        x = F.col(r.feature).cast("double")
        out = F.lit(False)
        if r.low is not None:
            out = out | (x < F.lit(float(r.low)))
        if r.high is not None:
            out = out | (x > F.lit(float(r.high)))
        # What a rule covers comes last: it is worked out for texts outside the bounds only.
        found.append(F.when(out & (F.col("n_words") >= r.from_words), F.when(covers[r.covers], F.lit(r.name))))
    return F.array_compact(F.array(*found))


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def apply_rules(df: DataFrame, text: str = "text", rules: tuple[Rule, ...] = DEFAULT_RULES, lang: str = "lang") -> DataFrame:
    """df with features, base_failed, failed_rules and kept. Without a column of languages, no text is judged by stop words."""
    known = F.col(lang).cast("string") if lang in df.columns else None
    out = quality_features(df, text).withColumns({"base_failed": base_failed(), "failed_rules": compile_rules(rules, text, known)})
    return out.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))


def keep_quality(docs: DataFrame, rules: tuple[Rule, ...] = DEFAULT_RULES) -> DataFrame:
    """The rows that pass, with the columns they came with."""
    boxed = docs.select(_boxed(docs).alias("_row"), F.col("text"), *[F.col(c) for c in docs.columns if c == "lang"])
    # Spark would push the filter below the features and copy their expressions into it, each many times
    # over; it does not push through a projection that numbers rows.
    judged = apply_rules(boxed, rules=rules).select("_row", "kept", F.monotonically_increasing_id().alias("_no"))
    return judged.where("kept and _no >= 0").select(*_unboxed("_row", docs.columns))


__all__ = ["DEFAULT_RULES", "SPACES_RE", "Rule", "apply_rules", "compile_rules", "keep_quality", "quality_features"]
