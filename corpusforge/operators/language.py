"""Language models over word and character n-grams: identification, perplexity, rank lexicons.

Models are fitted once and landed; what is scored is scored once per distinct word or n-gram, with the
scores of all languages in one row, and joined to the documents' words. Where the table of distinct
words is small (counted, MOST_BROADCAST rows) it is broadcast and no word is shuffled; beyond that
(document, word) counts meet it in a shuffle, whose frequent words adaptive execution splits.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StringType, StructField, StructType

from ..functions import text as T
from ..sources.tables import cut_lineage
from . import kneser


def doc_words(df: DataFrame) -> DataFrame:
    """(doc_id, lang, word, cnt) of lower-cased letter words; documents without any have no rows."""
    return df.select("doc_id", "lang", F.explode(T.letter_words(F.col("text"))).alias("word")).groupBy("doc_id", "lang", "word").agg(F.count(F.lit(1)).alias("cnt"))


def word_counts(df: DataFrame, lang_col: str | None = "lang") -> DataFrame:
    keys = [lang_col] if lang_col else []
    return df.select(*keys, F.explode(T.words(F.col("text"))).alias("word")).groupBy(*keys, "word").agg(F.count(F.lit(1)).alias("cnt"))


def gram_rows(words: DataFrame, sizes: tuple[int, ...]) -> DataFrame:
    """words (with a column word) with one row for each of its character n-grams, begin and end marked."""
    x = words.withColumn("_p", F.concat(F.lit("^"), F.col("word"), F.lit("$")))
    x = x.withColumn("_i", F.explode(F.sequence(F.lit(1), F.length("_p")))).withColumn("_n", F.explode(F.array(*[F.lit(n) for n in sizes])))
    return x.where(F.col("_i") + F.col("_n") - 1 <= F.length("_p")).withColumn("gram", F.substring(F.col("_p"), F.col("_i"), F.col("_n"))).drop("_p", "_i", "_n")


#: Distinct words up to which their scores are sent to every executor (about 100 bytes each).
MOST_BROADCAST = 1_000_000


def fit_langid(df: DataFrame, sizes: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """(lang, gram, c): counts of character n-grams of words, by language; landed."""
    w = df.select("lang", F.explode(T.letter_words(F.col("text"))).alias("word")).groupBy("lang", "word").agg(F.count(F.lit(1)).alias("cnt"))
    return cut_lineage(gram_rows(w, sizes).groupBy("lang", "gram").agg(F.sum("cnt").alias("c")))


def word_scores(words: DataFrame, model: DataFrame, sizes: tuple[int, ...] = (1, 2, 3)) -> tuple[DataFrame, list[str]]:
    """(word, n, s): n-grams of each word and its log-probability in each language (in the order of the names)."""
    rows = model.groupBy("lang").agg(F.sum("c").alias("total")).orderBy("lang").collect()  # as many rows as languages
    langs = [r["lang"] for r in rows]
    kinds = model.agg(F.countDistinct("gram")).first()[0]
    unseen = [math.log(1.0 / (r["total"] + kinds)) for r in rows]
    gain = [F.sum(F.when(F.col("lang") == x, F.log(F.col("c") + 1.0))).alias(f"_{i}") for i, x in enumerate(langs)]
    gains = model.groupBy("gram").agg(*gain)
    grams = gram_rows(words.select("word"), sizes)
    by = grams.join(gains, "gram", "left").groupBy("word").agg(F.count(F.lit(1)).alias("n"), *[F.coalesce(F.sum(f"_{i}"), F.lit(0.0)).alias(f"_{i}") for i in range(len(langs))])
    return by.select("word", "n", F.array(*[F.col(f"_{i}") + F.col("n") * F.lit(u) for i, u in enumerate(unseen)]).alias("s")), langs


def predict_langid(df: DataFrame, model: DataFrame, sizes: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """doc_id, lang, predicted, margin per n-gram, by naive Bayes with add-one smoothing.

    Every document has a row; one without letters has no prediction.
    """
    said = df.select("doc_id", "lang", F.explode_outer(T.letter_words(F.col("text"))).alias("word"))
    scores, langs = word_scores(said.select("word").where("word is not null").distinct(), model, sizes)
    scores = cut_lineage(scores)
    if scores.count() <= MOST_BROADCAST:
        said, scores, cnt = said, F.broadcast(scores), F.lit(1)
    else:
        said, cnt = said.groupBy("doc_id", "lang", "word").agg(F.count(F.lit(1)).alias("cnt")), F.col("cnt")
    x = said.join(scores, "word", "left")
    total = x.groupBy("doc_id", "lang").agg(F.sum(cnt * F.col("n")).alias("n"), *[F.sum(cnt * F.get("s", F.lit(i))).alias(f"_{i}") for i in range(len(langs))])
    best = F.sort_array(F.array(*[F.struct((-F.col(f"_{i}")).alias("s"), F.lit(x).alias("guess")) for i, x in enumerate(langs)]))
    first, second = F.get("best", F.lit(0)), F.get("best", F.lit(1))
    margin = (F.coalesce(second["s"], first["s"]) - first["s"]) / F.col("n")
    return total.withColumn("best", best).select("doc_id", "lang", F.when(F.col("n").isNotNull(), first["guess"]).alias("predicted"), F.round(margin, 6).alias("margin"))


def vote_langid(df: DataFrame, train: DataFrame, top: int = 50) -> DataFrame:
    """Baseline: the language whose frequent words cover most of the text.

    A document without any of them has no prediction and no votes. Frequent words are few (top by
    language); their window is cut in every task before the shuffle.
    """
    order = Window.partitionBy("lang").orderBy(F.desc("cnt"), "word")
    counts = doc_words(train).groupBy("lang", "word").agg(F.sum("cnt").alias("cnt"))
    frequent = counts.withColumn("r", F.row_number().over(order)).where(F.col("r") <= top).groupBy("word").agg(F.collect_list("lang").alias("guesses"))
    said = df.select("doc_id", "lang", F.explode_outer(T.letter_words(F.col("text"))).alias("word"))
    votes = said.join(F.broadcast(frequent), "word", "left").select("doc_id", "lang", F.explode_outer("guesses").alias("guess"))
    votes = votes.groupBy("doc_id", "lang", "guess").agg(F.count("guess").alias("votes"))
    best = F.min_by("guess", F.struct(-F.col("votes"), "guess"))
    return votes.groupBy("doc_id", "lang").agg(best.alias("predicted"), F.max("votes").alias("votes"))


def filter_lang(df: DataFrame, predicted: DataFrame, tau: float = 0.0) -> DataFrame:
    good = predicted.where((F.col("lang") == F.col("predicted")) & (F.col("margin") >= tau)).select("doc_id")
    return df.join(good, "doc_id", "left_semi")


def fit_unigram(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Counts (lang, word, c) and sizes (lang, total, kinds) of trusted text."""
    c = doc_words(df).groupBy("lang", "word").agg(F.sum("cnt").alias("c"))
    return c, c.groupBy("lang").agg(F.sum("c").alias("total"), F.count(F.lit(1)).alias("kinds"))


def all_sizes(df: DataFrame, sizes: DataFrame) -> DataFrame:
    """Sizes for every language of df: one without text is smoothed over the words of all languages with text."""
    langs = df.select("lang").distinct()
    words = sizes.agg(F.coalesce(F.sum("kinds"), F.lit(0)).alias("_all"))
    out = langs.join(sizes, "lang", "left").crossJoin(F.broadcast(words))
    return out.select("lang", F.coalesce("total", F.lit(0)).alias("total"), F.coalesce("kinds", "_all").alias("kinds"))


def perplexity_unigram(df: DataFrame, lm: tuple[DataFrame, DataFrame]) -> DataFrame:
    """exp of the mean negative log-probability of a document's words, add-one smoothed.

    Every document has a row: one without words has no perplexity, one of a language without trusted
    text is smoothed over the words of all languages.
    """
    counts, sizes = lm
    sizes = all_sizes(df, sizes)
    said = df.select("doc_id", "lang", F.explode_outer(T.letter_words(F.col("text"))).alias("word")).groupBy("doc_id", "lang", "word").agg(F.count("word").alias("cnt"))
    x = said.join(counts, ["lang", "word"], "left").join(F.broadcast(sizes), "lang", "left")
    p = (F.coalesce("c", F.lit(0)) + 1.0) / (F.col("total") + F.col("kinds") + 1)
    return x.groupBy("doc_id", "lang").agg(F.round(F.exp(-F.try_divide(F.sum(F.col("cnt") * F.log(p)), F.sum("cnt"))), 6).alias("perplexity"))


def perplexity_paragraphs(df: DataFrame, lm: tuple[DataFrame, DataFrame]) -> DataFrame:
    """doc_id, pos, lang, perplexity of every paragraph: the document form on lines."""
    lines = df.select("doc_id", "lang", F.posexplode(T.paragraphs(F.col("text"))).alias("pos", "text"))
    scored = perplexity_unigram(lines.select(F.struct("doc_id", "pos").alias("doc_id"), "lang", "text"), lm)
    return scored.select("doc_id.doc_id", "doc_id.pos", "lang", "perplexity")


def said_bigrams(df: DataFrame) -> DataFrame:
    """(doc_id, lang, u, w): every word bigram, with a start mark and an end mark."""
    x = df.select("doc_id", "lang", F.concat(F.array(F.lit("<s>")), T.letter_words(F.col("text")), F.array(F.lit("</s>"))).alias("ws"))
    pairs = F.transform(F.slice("ws", F.lit(2), F.size("ws") - 1), lambda w, i: F.struct(F.get(F.col("ws"), i).alias("u"), w.alias("w")))
    return x.select("doc_id", "lang", F.explode(pairs).alias("p")).select("doc_id", "lang", "p.u", "p.w")


def bigram_counts(df: DataFrame) -> DataFrame:
    """(lang, u, w, c) of a training text, landed: the parts of a model are all taken from it."""
    return cut_lineage(said_bigrams(df).groupBy("lang", "u", "w").agg(F.count(F.lit(1)).alias("c")))


def mean_log(said: DataFrame, keys: list[str], model: DataFrame, probability) -> DataFrame:
    """doc_id, lang, perplexity of what documents say.

    probability(rows, near) adds the column p to rows that have the keys; `near` marks the model's tables, which
    are hashed by partition, so that what documents say is never sorted. A model of up to MOST_BROADCAST
    rows meets every word; a larger one meets each distinct key once, and the documents then meet the scores.
    """
    by_hash = lambda t: t.hint("shuffle_hash")
    if model.count() <= MOST_BROADCAST:
        return probability(said, by_hash).groupBy("doc_id", "lang").agg(F.exp(-F.avg(F.log("p"))).alias("perplexity"))
    scores = cut_lineage(probability(said.select(*keys).distinct(), by_hash).select(*keys, F.log("p").alias("p")))
    return said.join(by_hash(scores), keys).groupBy("doc_id", "lang").agg(F.exp(-F.avg("p")).alias("perplexity"))


def perplexity_bigram(df: DataFrame, trusted: DataFrame) -> DataFrame:
    """Interpolated Kneser-Ney of order 2: absolute discount n1/(n1+2 n2), continuation counts below.

    A language without trusted text is smoothed over the words of all languages.
    """
    c = bigram_counts(trusted)
    ctx = c.groupBy("lang", "u").agg(F.sum("c").alias("cu"), F.count(F.lit(1)).alias("nu"))
    cont = c.groupBy("lang", "w").agg(F.count(F.lit(1)).alias("nw"))
    size = c.groupBy("lang").agg((F.count_if(F.col("c") == 1) / (F.count_if(F.col("c") == 1) + 2.0 * F.count_if(F.col("c") == 2))).alias("d"), F.count(F.lit(1)).alias("total"), F.countDistinct("w").alias("kinds"))
    size = all_sizes(df, size.select("lang", "total", "kinds")).join(size.select("lang", "d"), "lang", "left")

    def probability(rows: DataFrame, near) -> DataFrame:
        x = rows.join(near(c), ["lang", "u", "w"], "left").join(near(ctx), ["lang", "u"], "left").join(near(cont), ["lang", "w"], "left").join(F.broadcast(size), "lang")
        lower = (F.coalesce("nw", F.lit(0)) + 1.0) / (F.col("total") + F.col("kinds") + 1)
        return x.withColumn("p", F.when(F.col("cu").isNull(), lower).otherwise((F.greatest(F.coalesce("c", F.lit(0)) - F.col("d"), F.lit(0.0)) + F.col("d") * F.col("nu") * lower) / F.col("cu")))

    return mean_log(said_bigrams(df), ["lang", "u", "w"], c, probability).withColumn("perplexity", F.round("perplexity", 6))


def said_ngrams(df: DataFrame, order: int) -> DataFrame:
    """(doc_id, lang, g): word n-grams joined by spaces, with order - 1 start marks and an end mark."""
    x = df.select("doc_id", "lang", F.concat(F.array(*[F.lit("<s>")] * (order - 1)), T.letter_words(F.col("text")), F.array(F.lit("</s>"))).alias("ws"))
    runs = F.transform(F.sequence(F.lit(1), F.size("ws") - order + 1), lambda i: F.array_join(F.slice("ws", i, F.lit(order)), " "))
    return x.select("doc_id", "lang", F.explode(runs).alias("g"))


def perplexity_kneser_ney(df: DataFrame, trusted: DataFrame, order: int) -> DataFrame:
    """Interpolated Kneser-Ney of any order from 2: counts at the top, distinct left neighbours below.

    Each level's discount is n1/(n1+2 n2), 0.5 where nothing was met once; the lowest level is smoothed
    by one. Texts without words hold the end mark only; a language without trusted text is smoothed over
    the words of all languages. Words travel as numbers (kneser); beyond the vocabulary that fits there,
    n-grams meet the model by joins.
    """
    if order < 2:
        raise ValueError("order must be 2 or more")
    words = kneser.trusted_words(trusted)
    fits, total = kneser.fits(words)
    return kneser.perplexities(df, trusted, order, words, total) if fits else joined_kneser_ney(df, trusted, order)


def joined_kneser_ney(df: DataFrame, trusted: DataFrame, order: int) -> DataFrame:
    """perplexity_kneser_ney by equi-joins, level by level, on the n-gram's end and on its context: once per
    distinct n-gram, then joined back to the documents."""
    top = cut_lineage(said_ngrams(trusted, order).groupBy("lang", "g").agg(F.count(F.lit(1)).alias("c")))
    levels = {order: top}
    for k in range(order - 1, 0, -1):
        levels[k] = levels[k + 1].groupBy("lang", F.substring_index("g", " ", -k).alias("g")).agg(F.count(F.lit(1)).alias("c"))
    lowest = all_sizes(df, levels[1].groupBy("lang").agg(F.sum("c").alias("total"), F.count(F.lit(1)).alias("kinds")))

    def probability(rows: DataFrame, near) -> DataFrame:
        x = rows.withColumn("end", F.substring_index("g", " ", -1))
        x = x.join(near(levels[1].withColumnRenamed("g", "end")), ["lang", "end"], "left").join(F.broadcast(lowest), "lang")
        p = x.withColumn("p", (F.coalesce("c", F.lit(0)) + 1.0) / (F.col("total") + F.col("kinds") + 1)).drop("end", "c", "total", "kinds")
        for k in range(2, order + 1):
            c = levels[k]
            once, twice = F.count_if(F.col("c") == 1), F.count_if(F.col("c") == 2)
            discount = c.groupBy("lang").agg(F.when(once > 0, once / (once + 2.0 * twice)).otherwise(0.5).alias("d"))
            contexts = c.groupBy("lang", F.substring_index("g", " ", k - 1).alias("before")).agg(F.sum("c").alias("cu"), F.count(F.lit(1)).alias("nu"))
            end = F.substring_index("g", " ", -k)
            x = p.withColumns({"end": end, "before": F.substring_index(end, " ", k - 1)})
            x = x.join(near(c.withColumnRenamed("g", "end")), ["lang", "end"], "left").join(near(contexts), ["lang", "before"], "left").join(F.broadcast(discount), "lang", "left")
            mixed = (F.greatest(F.coalesce("c", F.lit(0)) - F.col("d"), F.lit(0.0)) + F.col("d") * F.col("nu") * F.col("p")) / F.col("cu")
            p = x.withColumn("p", F.when(F.col("cu").isNull(), F.col("p")).otherwise(mixed)).drop("end", "before", "c", "cu", "nu", "d")
        return p

    return mean_log(said_ngrams(df, order), ["lang", "g"], top, probability)


def perplexity_tail(scored: DataFrame, keep: float = 2 / 3, exact: bool = True) -> DataFrame:
    """Rows at or under the language's percentile; the sketch form is for scale."""
    cut = F.percentile("perplexity", F.lit(keep)) if exact else F.percentile_approx("perplexity", F.lit(keep), F.lit(10_000))
    bound = scored.groupBy("lang").agg(cut.alias("bound"))
    return scored.join(F.broadcast(bound), "lang").where(F.col("perplexity") <= F.col("bound")).drop("bound")


def frequency_ranks(counts: DataFrame, prefix: int = 3) -> DataFrame:
    """(lang, word, cnt) with each word's rank in its language: by count, then by word.

    Two levels: words of one count and one beginning are ranked among themselves; how many come before
    them is a running sum over (count, beginning), whose number follows the alphabet, not the corpus.
    """
    keyed = counts.withColumn("_p", F.left("word", F.lit(prefix)))
    steps = keyed.groupBy("lang", "cnt", "_p").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("lang").orderBy(F.desc("cnt"), "_p")) - F.col("_n")
    inside = F.row_number().over(Window.partitionBy("lang", "cnt", "_p").orderBy("word"))
    return keyed.withColumn("_i", inside).join(steps.select("lang", "cnt", "_p", before.alias("_b")), ["lang", "cnt", "_p"]).select("lang", "word", "cnt", (F.col("_b") + F.col("_i")).cast("bigint").alias("rank"))


def ranked_words(df: DataFrame, langs: tuple[str, ...]) -> DataFrame:
    """frequency_ranks of the letter words of these languages."""
    said = df.where(F.col("lang").isin(*langs)).select("lang", F.explode(T.letter_words(F.col("text"))).alias("word"))
    return frequency_ranks(said.groupBy("lang", "word").agg(F.count(F.lit(1)).alias("cnt")))


def rank_lexicon(df: DataFrame, src: str, tgt: str) -> DataFrame:
    """Stand-in for translation: words of equal frequency rank correspond."""
    return lexicon_of(ranked_words(df, (src, tgt)), src, tgt)


def lexicon_of(ranked: DataFrame, src: str, tgt: str) -> DataFrame:
    """(rank, src_word, tgt_word) of two of the ranked languages."""
    r = ranked.where(F.col("lang").isin(src, tgt))
    sides = [F.max(F.when(F.col("lang") == x, F.col("word"))) for x in (src, tgt)]
    both = r.groupBy("rank").agg(sides[0].alias("src_word"), sides[1].alias("tgt_word"))
    return both.where("src_word is not null and tgt_word is not null")


def translate(df: DataFrame, lexicon: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Words replaced through a lexicon, others copied; order is rebuilt by position."""
    w = df.select(key, F.posexplode(T.words(F.col(text))).alias("pos", "w"))
    out = w.join(lexicon.select(F.col("src_word").alias("_s"), "tgt_word"), F.lower("w") == F.col("_s"), "left")
    return out.groupBy(key).agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", F.coalesce("tgt_word", "w").alias("w")))), lambda x: x["w"]), " ").alias(text))


def carried(lexicon: DataFrame) -> pa.Table | None:
    """(src_word, tgt_word) on the driver, to travel with the tasks; None above MOST_BROADCAST words."""
    words = lexicon.select("src_word", "tgt_word").limit(MOST_BROADCAST + 1).toArrow()
    return words if words.num_rows <= MOST_BROADCAST else None


#: What T.words() says, where texts are read in Python.
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def rendered(low: str | None, own: str | None, known: dict[str, str]) -> str | None:
    """The words of a text, found by their lower-cased form or else as they are, joined by spaces; none without words."""
    if own is None:
        return None
    words = WORD.findall(own)
    return " ".join(map(known.get, words if low == own else WORD.findall(low), words)) if words else None


def render(df: DataFrame, lexicon: DataFrame, columns: dict[str, str], key: str) -> DataFrame:
    """df with another column for each of these: what translate() makes of it, null where it has no words.

    A lexicon of up to MOST_BROADCAST words travels with the tasks, and nothing of df is shuffled; a larger one
    meets df's words in a shuffle by the key.
    """
    words = carried(lexicon)
    if words is None:
        for c, new in columns.items():
            df = df.join(translate(df.select(key, c), lexicon, key, c).withColumnRenamed(c, new), key, "left")
        return df
    shared, kept = df.sparkSession.sparkContext.broadcast(words), df.columns
    both = [x for i, c in enumerate(columns) for x in (F.lower(c).alias(f"_l{i}"), F.col(c).alias(f"_w{i}"))]

    def run(batches):
        known = dict(zip(*[c.to_pylist() for c in shared.value.columns]))
        for b in batches:
            texts = [c.to_pylist() for c in b.columns[len(kept) :]]
            new = [pa.array([rendered(x, y, known) for x, y in zip(*texts[i : i + 2])], pa.string()) for i in range(0, len(texts), 2)]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(kept)], *new], [*kept, *columns.values()])

    schema = StructType([*df.schema.fields, *[StructField(new, StringType()) for new in columns.values()]])
    return df.select(*kept, *both).mapInArrow(run, schema)


def packed_grams(points: np.ndarray, sizes: tuple[int, ...]) -> np.ndarray:
    """Numbers of the n-grams (up to three characters) of words written as ^word$ after each other; they order as the n-grams do."""
    bits, shift, end = points.astype(np.int64), 21, ord("$")
    out = []
    for n in sizes:
        if len(bits) < n:
            continue
        inside = np.ones(len(bits) - n + 1, bool)
        code = np.zeros(len(inside), np.int64)
        for i in range(n):
            part = bits[i : i + len(inside)]
            code |= part << (shift * (2 - i))
            if i < n - 1:
                inside &= part != end  # only the last character may end a word
        out.append(code[inside])
    return np.concatenate(out) if out else np.zeros(0, np.int64)


def first_grams(codes: np.ndarray, top: int) -> np.ndarray:
    """The `top` most frequent of them, ties to the smaller, best first."""
    kinds, counts = np.unique(codes, return_counts=True)
    return kinds[np.lexsort((kinds, -counts))[:top]]


def distance_langid(df: DataFrame, train: DataFrame, top: int = 300, sizes: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """Variant: ranked n-gram profiles; a gram's cost is its change of rank, `top` where the language lacks it.

    Every document has a row; one without letters has neither a prediction nor a distance. Languages' profiles (top n-grams
    a language) travel with the tasks; a document's own is worked out where its text is read, so nothing of it is shuffled.
    """
    if max(sizes) > 3:
        raise ValueError("n-grams have up to three characters")
    counts = fit_langid(train, sizes)
    r = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("c"), "gram"))
    ranked = counts.withColumn("r", r).where(F.col("r") <= top).orderBy("lang", "r").collect()  # bounded by the languages
    known: dict = {}
    for row in ranked:
        padded = [ord(c) for c in row["gram"]] + [0, 0]
        known.setdefault(row["lang"], {})[padded[0] << 42 | padded[1] << 21 | padded[2]] = row["r"]
    profiles = [(lang, np.array(sorted(of), np.int64), np.array([of[k] for k in sorted(of)], np.int64)) for lang, of in sorted(known.items(), key=lambda x: (x[0] is None, x[0] or ""))]

    def judged(text: str | None) -> tuple:
        if not text:
            return None, None
        mine = first_grams(packed_grams(np.frombuffer(text.encode("utf-32-le"), np.uint32), sizes), top)
        rank, best, guess = np.arange(1, len(mine) + 1), 0, None
        for lang, grams, ranks in profiles:
            i = np.minimum(np.searchsorted(grams, mine), len(grams) - 1)
            gain = int((top - np.abs(rank - ranks[i]))[grams[i] == mine].sum())
            if gain > best:
                best, guess = gain, lang
        return guess, len(mine) * top - best

    def run(batches):
        for b in batches:
            found = [judged(t.as_py()) for t in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([g for g, _ in found], pa.string()), pa.array([x for _, x in found], pa.int64())], ["doc_id", "lang", "predicted", "distance"])

    words = T.letter_words(F.col("text"))
    marked = F.when(F.size(words) > 0, F.concat(F.lit("^"), F.array_join(words, "$^"), F.lit("$")))
    return df.select("doc_id", "lang", marked.alias("marked")).mapInArrow(run, f"doc_id {df.schema['doc_id'].dataType.simpleString()}, lang string, predicted string, distance bigint")


def perplexity_backoff(df: DataFrame, trusted: DataFrame, factor: float = 0.4) -> DataFrame:
    """Stupid back-off of order 2: the bigram's share of its context, else a factor times the word's share.

    A language without trusted text counts every word as one of all languages' words.
    """
    c = bigram_counts(trusted)
    ctx = c.groupBy("lang", "u").agg(F.sum("c").alias("cu"))
    uni = c.groupBy("lang", "w").agg(F.sum("c").alias("cw"))
    size = all_sizes(df, c.groupBy("lang").agg(F.sum("c").alias("total"), F.countDistinct("w").alias("kinds")))

    def probability(rows: DataFrame, near) -> DataFrame:
        x = rows.join(near(c), ["lang", "u", "w"], "left").join(near(ctx), ["lang", "u"], "left").join(near(uni), ["lang", "w"], "left").join(F.broadcast(size), "lang")
        total = F.when(F.col("total") > 0, F.col("total")).otherwise(F.greatest("kinds", F.lit(1)))
        return x.withColumn("p", F.when(F.col("c").isNotNull(), F.col("c") / F.col("cu")).otherwise(factor * F.coalesce("cw", F.lit(1)) / total))

    return mean_log(said_bigrams(df), ["lang", "u", "w"], c, probability).withColumn("perplexity", F.round("perplexity", 3))


def perplexity_bands(scored: DataFrame, cuts: tuple[float, float] = (1 / 3, 2 / 3), exact: bool = True) -> DataFrame:
    """head, middle or tail by the language's percentiles."""
    cut = lambda q: F.percentile("perplexity", F.lit(q)) if exact else F.percentile_approx("perplexity", F.lit(q), F.lit(10_000))
    bound = scored.groupBy("lang").agg(cut(cuts[0]).alias("lo"), cut(cuts[1]).alias("hi"))
    band = F.when(F.col("perplexity") <= F.col("lo"), "head").when(F.col("perplexity") <= F.col("hi"), "middle").otherwise("tail")
    return scored.join(F.broadcast(bound), "lang").withColumn("band", band).drop("lo", "hi")


def perplexity_below(scored: DataFrame, bounds: dict[str, float], default: float) -> DataFrame:
    """Variant: an absolute bound by language."""
    b = F.lit(default)
    for lang, v in bounds.items():
        b = F.when(F.col("lang") == lang, F.lit(v)).otherwise(b)
    return scored.where(F.col("perplexity") <= b)
