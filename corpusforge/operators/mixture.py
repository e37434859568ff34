"""Mixing: available tokens, weights of strata and cells by phase, joint weights, budgets, samplers, trials.

A stratum is a language, or "code_math" for all documents of that category whatever their language; a
cell is a category inside a stratum. Documents of a source that the registry doesn't know count as web
text, documents without a language as "und": every document belongs to one cell.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage

#: Shares of English and of code and maths by phase, and the candidates of the trials.
PHASE_SHARES = {1: (0.50, 0.05), 2: (0.325, 0.07), 3: (0.325, 0.23)}
TRIALS = {"p2": ((0.48, 0.07), (0.40, 0.15), (0.325, 0.07)), "p3": ((0.30, 0.095), (0.325, 0.23), (0.325, 0.23))}
#: Category shares that the candidates hold besides.
PARALLEL_THIRD, HIGH_SHARE = 0.02, 0.34
TRIAL_CATEGORIES = {"p2": ({"higher_quality": HIGH_SHARE},) * 3, "p3": ({}, {}, {"parallel": PARALLEL_THIRD})}
#: A trial's share of the tokens that its phase has: here, of all that is available.
TRIAL_FRACTION = 0.2
#: The category of each source of the tables.
CATEGORIES = tuple((f"src{i}", "web" if i < 12 else "parallel" if i < 15 else "code_math" if i < 18 else "higher_quality") for i in range(20))
CODE, OTHER = "code_math", "web"


def category_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(CATEGORIES), "source string, category string")


def with_cell(df: DataFrame) -> DataFrame:
    """df with category and stratum; the registry is a literal of a few rows."""
    out = df.join(F.broadcast(category_frame(df.sparkSession)), "source", "left").withColumn("category", F.coalesce("category", F.lit(OTHER)))
    return out.withColumn("stratum", F.when(F.col("category") == CODE, CODE).otherwise(F.coalesce("lang", F.lit("und"))))


def available_tokens(df: DataFrame) -> DataFrame:
    """Tokens (words) by language and category; one row a cell leaves each task."""
    rows = with_cell(df.select("lang", "source", F.size(T.words(F.col("text"))).cast("bigint").alias("n")))
    return rows.groupBy(F.coalesce("lang", F.lit("und")).alias("lang"), "category").agg(F.sum("n").alias("tokens"), F.count(F.lit(1)).alias("docs"))


def by_stratum(avail: DataFrame) -> DataFrame:
    """(lang, available): tokens of each stratum, code and maths under their own name."""
    return avail.groupBy(F.when(F.col("category") == CODE, CODE).otherwise(F.col("lang")).alias("lang")).agg(F.sum("tokens").alias("available"))


def language_weights(avail: DataFrame, share_en: float, share_code: float) -> DataFrame:
    """English and code/maths fixed; the rest in proportion to the other strata's tokens."""
    other = by_stratum(avail).where(~F.col("lang").isin("en", CODE))
    total = F.sum("available").over(Window.partitionBy(F.lit(1)))
    rest = other.select("lang", (F.lit(1 - share_en - share_code) * F.col("available") / total).alias("weight"))
    fixed = avail.sparkSession.createDataFrame([("en", share_en), (CODE, share_code)], "lang string, weight double")
    return fixed.union(rest).select("lang", F.round("weight", 6).alias("weight"))


def cell_weights(avail: DataFrame, share_en: float, share_code: float, fixed: dict[str, float] | None = None) -> DataFrame:
    """(lang, category, weight): strata as in `language_weights`; inside each, some categories hold a share of
    the whole mix and the others are raised or cut in proportion to what is available.

    A stratum without documents of a category that holds a share gives that part to its other categories.
    """
    fixed = fixed or {}
    cells = avail.withColumn("lang", F.when(F.col("category") == CODE, CODE).otherwise(F.col("lang"))).groupBy("lang", "category").agg(F.sum("tokens").cast("double").alias("n"))
    named = F.lit(None).cast("double")
    for k, v in fixed.items():
        named = F.when(F.col("category") == k, F.lit(v / (1 - share_code))).otherwise(named)
    inside = Window.partitionBy("lang")
    free = F.sum(F.when(named.isNull(), F.col("n"))).over(inside)
    raw = F.when(F.col("lang") == CODE, F.lit(1.0)).otherwise(F.coalesce(named, F.lit(1 - sum(fixed.values()) / (1 - share_code)) * F.col("n") / free))
    x = cells.withColumn("raw", raw).withColumn("part", F.col("raw") / F.sum("raw").over(inside))
    return x.join(F.broadcast(language_weights(avail, share_en, share_code)), "lang").select("lang", "category", F.round(F.col("weight") * F.col("part"), 9).alias("weight"))


def weights_kind(avail: DataFrame, kind: str, alpha: float = 0.3) -> DataFrame:
    """Baselines: natural proportions, uniform, temperature alpha."""
    by = avail.groupBy("lang").agg(F.sum("tokens").alias("tokens"))
    x = {"natural": F.col("tokens").cast("double"), "uniform": F.lit(1.0), "temperature": F.pow(F.col("tokens").cast("double"), F.lit(alpha))}[kind]
    return by.withColumn("x", x).select("lang", F.round(F.col("x") / F.sum("x").over(Window.partitionBy(F.lit(1))), 6).alias("weight"))


def fit_joint(avail: list[tuple[str, str, float]], by_lang: dict[str, float], by_cat: dict[str, float], rounds: int = 500) -> dict[tuple[str, str], float]:
    """Joint weights that meet both margins, by proportional fitting. The table has languages x categories cells."""
    x = {(a, c): float(n) for a, c, n in avail if n > 0}
    for _ in range(rounds):
        for axis, want in ((0, by_lang), (1, by_cat)):
            have: dict[str, float] = {}
            for k, v in x.items():
                have[k[axis]] = have.get(k[axis], 0.0) + v
            for k in x:
                x[k] *= want[k[axis]] / have[k[axis]]
    for axis, want in ((0, by_lang), (1, by_cat)):
        for name, w in want.items():
            if abs(sum(v for k, v in x.items() if k[axis] == name) - w) > 1e-9:
                raise ValueError(f"margins cannot be met: {name}")
    return x


def budget(weights: DataFrame, avail: DataFrame, tokens: int, bound: float = 4.0) -> DataFrame:
    """Target tokens and repetition of each stratum; flagged beyond a bound. A stratum with a weight and no tokens has no repetition."""
    out = weights.join(by_stratum(avail), "lang", "left").withColumn("available", F.coalesce("available", F.lit(0).cast("bigint")))
    out = out.withColumn("target", F.round(F.col("weight") * tokens).cast("bigint"))
    out = out.withColumn("repetition", F.round(F.try_divide(F.col("target").cast("double"), F.col("available")), 6))
    return out.withColumn("over", F.col("repetition") > bound)


def cell_rates(weights: DataFrame, avail: DataFrame, tokens: int) -> DataFrame:
    """(lang, category, rate): how often each cell's documents are taken for a budget."""
    cells = avail.withColumn("lang", F.when(F.col("category") == CODE, CODE).otherwise(F.col("lang"))).groupBy("lang", "category").agg(F.sum("tokens").alias("n"))
    return weights.join(cells, ["lang", "category"]).select("lang", "category", F.round(F.try_divide(F.round(F.col("weight") * tokens), F.col("n")), 6).alias("rate"))


def trial_tokens(avail: DataFrame, fraction: float = TRIAL_FRACTION) -> int:
    """The budget of a trial: it grows with the input. One number goes to the driver."""
    return round(fraction * (avail.agg(F.sum("tokens").alias("n")).first()["n"] or 0))


def copies(rate: Column, *key: Column) -> Column:
    """floor(rate), and one more with the fractional probability, from a hash of the key."""
    whole = F.floor(rate)
    return (whole + F.when(T.uniform(*key) < rate - whole, 1).otherwise(0)).cast("int")


def sample_to_budget(df: DataFrame, rates: DataFrame, phase: int = 1, seed: int = 0) -> DataFrame:
    """df with each document as often as its stratum's rate asks for: no shuffle, the same after retries."""
    n = copies(F.col("rate"), F.col("doc_id"), F.lit(phase), F.lit(seed))
    out = with_cell(df).join(F.broadcast(rates.select(F.col("lang").alias("stratum"), "rate")), "stratum").withColumn("_n", n)
    return out.where("_n > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("_n")))).drop("_n", "rate", "category")


#: Documents of one language that one task takes in the exact sampler.
EXACT_ROWS = 100_000


def sample_exact(df: DataFrame, targets: DataFrame, tokens: str, seed: int = 0) -> DataFrame:
    """In hash order, documents until the language's target is reached (the last may pass it).

    The order is cut into slices of the hash; slice totals (a small frame) say what comes before each, and
    sums run inside slices.
    """
    rows = df.count()
    slices = max(8, -(-rows // EXACT_ROWS))
    x = df.join(F.broadcast(targets.select("lang", "target")), "lang").withColumn("_u", T.uniform(F.col("doc_id"), F.lit(seed)))
    x = x.withColumn("_s", F.floor(F.col("_u") * slices).cast("int"))
    totals = x.groupBy("lang", "_s").agg(F.sum(tokens).alias("_t"))
    ahead = totals.select("lang", "_s", (F.sum("_t").over(Window.partitionBy("lang").orderBy("_s")) - F.col("_t")).alias("_a"))
    run = F.sum(tokens).over(Window.partitionBy("lang", "_s").orderBy("_u", "doc_id")) + F.col("_a")
    out = x.join(ahead, ["lang", "_s"]).where(F.col("_a") < F.col("target")).withColumn("_run", run)
    return out.where(F.col("_run") - F.col(tokens) < F.col("target")).drop("_run", "_u", "_s", "_a", "target")


def mix_report(sample: DataFrame, weights: DataFrame, tokens: str) -> DataFrame:
    """Achieved and target share of each stratum."""
    got = sample.groupBy(F.col("stratum").alias("lang")).agg(F.sum(tokens).alias("n"))
    got = got.withColumn("achieved", F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(1))))
    return weights.join(got, "lang", "left").select("lang", "weight", F.round(F.coalesce("achieved", F.lit(0.0)), 6).alias("achieved"), F.round(F.abs(F.col("weight") - F.coalesce("achieved", F.lit(0.0))), 6).alias("deviation"))


def held_out_scores(train: DataFrame, takes: list[Column], held: DataFrame) -> DataFrame:
    """(variant, task, score, tokens): mean log-likelihood of held-out documents by language, and words trained on.

    takes: for each variant, how often a document is taken. All variants share one scan of the training text
    and one table of word counts (a column each). A language without a sampled word is smoothed over the
    words of all languages; documents without words have no likelihood.
    """
    names = [f"c{i}" for i in range(len(takes))]
    said = train.select("lang", *[t.cast("bigint").alias(n) for t, n in zip(takes, names)], F.explode(T.letter_words(F.col("text"))).alias("word"))
    counts = cut_lineage(said.where(" + ".join(names) + " > 0").groupBy("lang", "word").agg(*[F.sum(n).alias(n) for n in names]))
    sizes = counts.groupBy("lang").agg(*[F.sum(n).alias(f"t_{n}") for n in names], *[F.count_if(F.col(n) > 0).alias(f"k_{n}") for n in names])
    every = sizes.agg(*[F.coalesce(F.sum(f"k_{n}"), F.lit(0)).alias(f"e_{n}") for n in names], *[F.coalesce(F.sum(f"t_{n}"), F.lit(0)).alias(f"n_{n}") for n in names])
    x = held.select("doc_id", "lang", F.explode(T.letter_words(F.col("text"))).alias("word")).join(counts, ["lang", "word"], "left")
    x = x.join(F.broadcast(sizes), "lang", "left").crossJoin(F.broadcast(every))
    p = lambda n: (F.coalesce(n, F.lit(0)) + 1.0) / (F.coalesce(f"t_{n}", F.lit(0)) + F.when(F.coalesce(F.col(f"t_{n}"), F.lit(0)) > 0, F.col(f"k_{n}")).otherwise(F.col(f"e_{n}")) + 1)
    docs = x.groupBy("doc_id", "lang").agg(*[F.avg(F.log(p(n))).alias(n) for n in names], *[F.first(f"n_{n}").alias(f"n_{n}") for n in names])
    by = docs.groupBy(F.col("lang").alias("task")).agg(*[F.avg(n).alias(n) for n in names], *[F.first(f"n_{n}").alias(f"n_{n}") for n in names])
    rows = F.array(*[F.struct(F.lit(i + 1).alias("variant"), F.round(F.col(n), 6).alias("score"), F.col(f"n_{n}").alias("tokens")) for i, n in enumerate(names)])
    return by.select("task", F.explode(rows).alias("r")).select("r.variant", "task", "r.score", "r.tokens")


def mixture_trial(df: DataFrame, held: Column, phase: int, fraction: float = TRIAL_FRACTION, seed: int = 0) -> DataFrame:
    """(variant, task, score) of the candidates of a phase, each on a share of the available tokens."""
    avail = cut_lineage(available_tokens(df))
    tokens = trial_tokens(avail, fraction)
    train, takes = with_cell(df).where(~held), []
    for i, (shares, fixed) in enumerate(zip(TRIALS[f"p{phase}"], TRIAL_CATEGORIES[f"p{phase}"])):
        rates = cell_rates(cell_weights(avail, *shares, fixed), avail, tokens)
        train = train.join(F.broadcast(rates.select(F.col("lang").alias("stratum"), "category", F.col("rate").alias(f"_r{i}"))), ["stratum", "category"], "left")
        takes.append(copies(F.coalesce(f"_r{i}", F.lit(0.0)), F.col("doc_id"), F.lit(phase), F.lit(seed)))
    return held_out_scores(train, takes, df.where(held)).drop("tokens")


#: Checkpoints as shares of the documents, and the phase each belongs to.
CHECKPOINTS = ((1, 0.3), (1, 0.6), (1, 0.9), (2, 0.93), (2, 0.96), (2, 0.99), (3, 0.993), (3, 0.996), (3, 1.0))


def progress_points(df: DataFrame, held: Column, seed: int = 0) -> DataFrame:
    """(phase, tokens in millions, metric): held-out log-likelihood after each checkpoint, all languages alike."""
    u = T.uniform(F.col("doc_id"), F.lit("progress"), F.lit(seed))
    scores = held_out_scores(df.where(~held), [(u < share).cast("int") for _, share in CHECKPOINTS], df.where(held))
    phase = F.element_at(F.array(*[F.lit(p) for p, _ in CHECKPOINTS]), F.col("variant"))
    return scores.groupBy("variant").agg(F.avg("score").alias("metric"), F.first("tokens").alias("tokens")).select(phase.alias("phase"), (F.col("tokens") / 1e6).alias("tokens"), F.round("metric", 6).alias("metric"))


def phase_delta(weights: DataFrame) -> DataFrame:
    """Weights over phases with the change from the phase before."""
    w = Window.partitionBy("lang").orderBy("phase")
    return weights.withColumn("delta", F.round(F.col("weight") - F.lag("weight").over(w), 6))


def choose_mix(scores: DataFrame) -> DataFrame:
    """Mean rank of each variant over tasks (higher score better) and tasks where it isn't first."""
    w = Window.partitionBy("task").orderBy(F.desc("score"))
    return scores.withColumn("r", F.rank().over(w)).groupBy("variant").agg(F.round(F.avg("r"), 6).alias("mean_rank"), F.count_if(F.col("r") > 1).alias("losses"))


def shuffle_key(df: DataFrame, seed: int = 0) -> DataFrame:
    return df.withColumn("shuffle_key", T.uniform(F.col("doc_id"), F.lit(seed)))


def category_shares(avail: DataFrame, fixed: dict[str, float]) -> DataFrame:
    """Share of each category: some set, the rest raised or cut in proportion to what is available."""
    by = avail.groupBy("category").agg(F.sum("tokens").cast("double").alias("tokens"))
    named = F.lit(None).cast("double")
    for k, v in fixed.items():
        named = F.when(F.col("category") == k, F.lit(v)).otherwise(named)
    free = F.when(named.isNull(), F.col("tokens"))
    rest = F.lit(1 - sum(fixed.values())) * free / F.sum(free).over(Window.partitionBy(F.lit(1)))
    return by.select("category", F.round(F.coalesce(named, rest), 6).alias("share"))


def mix_distance(report: DataFrame) -> DataFrame:
    """L1 distance of achieved and target shares, and the entropy of what was achieved."""
    a = F.col("achieved")
    return report.agg(F.round(F.sum("deviation"), 5).alias("l1"), F.round(-F.sum(F.when(a > 0, a * F.log(a))), 5).alias("entropy"))


def balanced_sample(df: DataFrame, seed: int = 0) -> DataFrame:
    """Documents for tokenizer training: every language thinned towards the smallest one's words."""
    by = df.groupBy("lang").agg(F.sum(F.size(T.words(F.col("text"))).cast("bigint")).alias("n"))
    rate = by.select("lang", F.round(F.min("n").over(Window.partitionBy(F.lit(1))) / F.col("n"), 6).alias("rate"))
    return df.join(F.broadcast(rate), "lang").where(T.uniform(F.col("doc_id"), F.lit("tokenizer"), F.lit(seed)) < F.col("rate")).drop("rate")
