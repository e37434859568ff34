"""Instruction corpus: scores, gates, curves, decontamination, masks, packing, epochs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage

#: Prompt and reward bounds, sequence length, epochs. RHO is ours.
PROMPT, REWARD, LENGTH, EPOCHS, RHO = 4.0, 0.08, 4096, 3, 0.25
STRICT = (0, 1)


def prompt_scores(conv: DataFrame) -> DataFrame:
    """Stand-in scores of user turns: complexity, readability (0 to 5) and the answer's reward (0 to 1)."""
    w = T.words(F.col("text"))
    n, kinds = F.size(w), F.size(F.array_distinct(w))
    x = conv.where("role = 'user'").select("conv_id", "turn", (F.col("conv_id") % 5).alias("corpus"), F.least(F.lit(5.0), n / 4.0).alias("complexity"), F.round(5.0 * F.coalesce(F.try_divide(kinds.cast("double"), n), F.lit(0.0)), 6).alias("readability"))
    a = conv.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.round(F.least(F.lit(1.0), F.size(T.words(F.col("text"))) / 100.0), 6).alias("reward"))
    return x.join(a, ["conv_id", "turn"], "left")


def strict_gate(df: DataFrame, least: float = PROMPT) -> DataFrame:
    return df.where(~((F.col("complexity") < least) | (F.col("readability") < least)))


def soft_downsample(df: DataFrame, least: float = PROMPT, rho: float = RHO, seed: int = 0) -> DataFrame:
    low = (F.col("complexity") < least) | (F.col("readability") < least)
    return df.where(~low | (T.uniform(F.col("conv_id"), F.col("turn"), F.lit(seed)) < rho))


def gate(df: DataFrame, **options) -> DataFrame:
    """Strict rule for strict corpora, soft rule for the others, in one plan."""
    low = (F.col("complexity") < PROMPT) | (F.col("readability") < PROMPT)
    lucky = T.uniform(F.col("conv_id"), F.col("turn"), F.lit(options.get("seed", 0))) < options.get("rho", RHO)
    return df.where(~low | (~F.col("corpus").isin(*STRICT) & lucky))


def reward_gate(df: DataFrame, least: float = REWARD, read_min: float = PROMPT) -> DataFrame:
    """Low rewards go, unless the prompt itself is hard to read; rows without a reward stay."""
    return df.where((F.coalesce("reward", F.lit(1.0)) >= least) | (F.col("readability") < read_min))


def retention_curve(df: DataFrame, bounds: list[float]) -> DataFrame:
    """Rows kept and their mean reward for each bound: one pass, one row a bound."""
    x = df.select(F.col("reward"), F.explode(F.array(*[F.lit(float(b)) for b in bounds])).alias("bound"))
    keep = F.col("reward") >= F.col("bound")
    return x.groupBy("bound").agg(F.count_if(keep).alias("kept"), F.round(F.avg(F.when(keep, F.col("reward"))), 6).alias("mean_reward"))


#: Distinct benchmark runs up to which they are sent to every executor (16 bytes each).
MOST_RUNS = 2_000_000


def decontaminate(df: DataFrame, bench: DataFrame, key: str = "doc_id", k: int = 8) -> DataFrame:
    """Rows that share no run of k words with any benchmark item.

    Runs are compared by two 64-bit hashes over the words' hashes. The benchmark's are counted: while they
    are few they are broadcast, and no run of the corpus is shuffled.
    """
    def runs(df: DataFrame, *keep: str) -> DataFrame:
        # Words and their hashes are columns of their own: a lambda would work them out again for every position.
        x = df.select(*keep, T.words(F.lower("text")).alias("w")).where(F.size("w") >= k)
        x = x.select(*keep, F.transform("w", lambda a: F.xxhash64(a)).alias("h"))
        at = lambda i, n: F.get(F.col("h"), i + n)
        grams = F.transform(F.sequence(F.lit(0), F.size("h") - k), lambda i: F.struct(F.xxhash64(*[at(i, n) for n in range(k)]).alias("a"), F.xxhash64(F.lit(1), *[at(i, n) for n in reversed(range(k))]).alias("b")))
        return x.select(*keep, F.explode(grams).alias("g")).select(*keep, "g.a", "g.b")

    known = cut_lineage(runs(bench).distinct())
    hit = runs(df, key).join(F.broadcast(known) if known.count() <= MOST_RUNS else known, ["a", "b"], "left_semi").select(key).distinct()
    return df.join(hit, key, "left_anti")


def instruction_report(df: DataFrame) -> DataFrame:
    low = (F.col("complexity") < PROMPT) | (F.col("readability") < PROMPT)
    kept = ~low | ~F.col("corpus").isin(*STRICT)
    x = df.select("corpus", F.when(kept, "kept").otherwise("low prompt").alias("reason"))
    return x.rollup("corpus", "reason").agg(F.count(F.lit(1)).alias("rows")).select(F.coalesce(F.col("corpus").cast("string"), F.lit("(all)")).alias("corpus"), F.coalesce("reason", F.lit("(all)")).alias("reason"), "rows")


def curate(conv: DataFrame, licensed: tuple[str, ...], seed: int = 0) -> DataFrame:
    """Every collected prompt with the reason that decides on it: each stage judges what the last one left.

    Order: licence of the generator, prompt scores (strict corpora lose low prompts, others keep a share),
    reward (unless the prompt is hard to read), repeated prompts (the smallest id stays), kept.
    """
    pairs = human_pairs(conv).join(prompt_scores(conv), ["conv_id", "turn"])
    low = (F.col("complexity") < PROMPT) | (F.col("readability") < PROMPT)
    lucky = ~F.col("corpus").isin(*STRICT) & (T.uniform(F.col("conv_id"), F.col("turn"), F.lit(seed)) < RHO)
    poor = (F.coalesce("reward", F.lit(1.0)) < REWARD) & (F.col("readability") >= PROMPT)
    named = pairs.withColumn("generator", F.concat(F.lit("gen"), ((F.col("conv_id") + F.col("turn")) % 3).cast("string")))
    reason = F.when(~F.col("generator").isin(*licensed), "licence").when(low & ~lucky, "low prompt").when(poor, "low reward")
    x = named.withColumn("reason", reason).withColumn("_k", F.md5(T.normalized(F.col("prompt"))))
    first = x.where("reason is null").groupBy("_k").agg(F.min(F.struct("conv_id", "turn")).alias("_f"))
    x = x.join(first, "_k", "left").withColumn("reason", F.coalesce("reason", F.when(F.struct("conv_id", "turn") == F.col("_f"), "kept").otherwise("repeated")))
    return x.drop("_k", "_f")


def curation_ledger(curated: DataFrame) -> DataFrame:
    """Rows by corpus and reason, with totals."""
    x = curated.rollup("corpus", "reason").agg(F.count(F.lit(1)).alias("rows"))
    return x.select(F.coalesce(F.col("corpus").cast("string"), F.lit("(all)")).alias("corpus"), F.coalesce("reason", F.lit("(all)")).alias("reason"), "rows")


def translate_pairs(pairs: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Prompts and answers rendered through a lexicon (stand-in for translation); ids stay."""
    from . import language

    keyed = pairs.withColumn("_k", F.struct("conv_id", "turn"))
    said = language.translate(keyed, lexicon, "_k", "prompt")
    answered = language.translate(keyed, lexicon, "_k", "answer")
    out = keyed.select("_k").join(said, "_k", "left").join(answered, "_k", "left")
    return out.select("_k.conv_id", "_k.turn", F.coalesce("prompt", F.lit("")).alias("prompt"), F.coalesce("answer", F.lit("")).alias("answer"))


def balanced_instructions(docs: DataFrame, langs: tuple[str, ...], templates: dict[str, str], seed: int = 0) -> DataFrame:
    """Instructions thinned so that languages with little data get as many as those with much: every target
    language keeps the share (least documents of any of them / its own)."""
    n = docs.where(F.col("lang").isin(*langs)).groupBy(F.col("lang").alias("tgt_lang")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    # The language with least text keeps all of its instructions.
    rate = n.select("tgt_lang", F.round(F.min("n").over(Window.partitionBy(F.lit(1))) / F.col("n"), 6).alias("rate"))
    made = make_instructions(docs, langs, templates).join(F.broadcast(rate), "tgt_lang")
    return made.where(T.uniform(F.col("doc_id"), F.col("tgt_lang"), F.col("category"), F.lit(seed)) < F.col("rate")).drop("rate")


def loss_mask(conv: DataFrame) -> DataFrame:
    """Words of a conversation in turn order, and which of them are targets (the assistant's)."""
    t = conv.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    x = t.select("conv_id", F.flatten(F.transform("turns", lambda r: F.transform(T.words(r["text"]), lambda w: F.struct(w.alias("w"), (r["role"] == "assistant").alias("m"))))).alias("x"))
    return x.select("conv_id", F.transform("x", lambda r: r["w"]).alias("ids"), F.transform("x", lambda r: r["m"]).alias("mask"), F.size("x").cast("bigint").alias("n_tokens"), F.size(F.filter("x", lambda r: r["m"])).cast("bigint").alias("n_target"))


#: Tokens of a packing shard, and the least number of shards.
SHARD_TOKENS, LEAST_SHARDS = 50_000_000, 4


def pack_chunks(items: DataFrame, length: int = LENGTH, shards: int | None = None) -> DataFrame:
    """Concatenate and cut: rows of `length` tokens inside each shard, in hash order; items may straddle.

    Shards follow the tokens, so that each is a window one task can hold; only a shard's last row is loose.
    """
    if shards is None:
        shards = max(LEAST_SHARDS, -(-(items.agg(F.sum("n_tokens")).first()[0] or 0) // SHARD_TOKENS))
    h = F.conv(F.substring(F.md5(F.col("conv_id").cast("string")), 1, 8), 16, 10).cast("bigint")
    w = Window.partitionBy("shard").orderBy("h", "conv_id")
    x = items.withColumns({"h": h, "shard": F.pmod(h, F.lit(shards))}).withColumn("until", F.sum("n_tokens").over(w))
    first, last = F.floor((F.col("until") - F.col("n_tokens")) / length), F.floor((F.col("until") - 1) / length)
    return x.where("n_tokens > 0").select("conv_id", "shard", first.alias("first_row"), last.alias("last_row"), "n_tokens")


def pack_report(items: DataFrame, length: int = LENGTH, shards: int | None = None) -> DataFrame:
    """Rows of each mode, fill, and rows saved against one row an item."""
    packed = pack_chunks(items, length, shards).groupBy("shard").agg((F.max("last_row") + 1).alias("rows"), F.sum("n_tokens").alias("tokens"), F.count(F.lit(1)).alias("items"))
    return packed.select("shard", "rows", "tokens", "items", F.round(F.col("tokens") / (F.col("rows") * length), 6).alias("fill"), (F.col("items") - F.col("rows")).alias("saved"))


def epochs(items: DataFrame, n: int = EPOCHS) -> DataFrame:
    """Every item once an epoch, each epoch in an order of its own."""
    return items.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).withColumn("key", T.uniform(F.col("conv_id"), F.col("epoch")))


def masked_loss(masked: DataFrame) -> DataFrame:
    """Mean negative log-probability of target words and of all words, under the corpus's own unigrams."""
    x = masked.select("conv_id", F.explode(F.arrays_zip("ids", "mask")).alias("z")).select("conv_id", F.col("z.ids").alias("w"), F.col("z.mask").alias("m"))
    c = x.groupBy("w").agg(F.count(F.lit(1)).alias("c"))
    total = x.agg(F.count(F.lit(1)).alias("n"))
    y = x.join(c, "w").crossJoin(F.broadcast(total)).withColumn("l", -F.log(F.col("c") / F.col("n")))
    return y.groupBy("conv_id").agg(F.round(F.avg(F.when(F.col("m"), F.col("l"))), 6).alias("masked"), F.round(F.avg("l"), 6).alias("unmasked"))


def make_instructions(docs: DataFrame, langs: tuple[str, ...], templates: dict[str, str]) -> DataFrame:
    """(document, target language, category) to a template instruction. Few languages and categories: exploded literals."""
    cats = F.array(*[F.struct(F.lit(k).alias("category"), F.lit(v).alias("template")) for k, v in sorted(templates.items())])
    x = docs.select("doc_id", "lang", F.explode(F.array(*[F.lit(x) for x in langs])).alias("tgt_lang")).withColumn("t", F.explode(cats))
    return x.select("doc_id", "tgt_lang", F.col("t.category").alias("category"), F.concat(F.col("t.template"), F.lit(" ["), F.col("tgt_lang"), F.lit("] #"), F.col("doc_id").cast("string")).alias("instruction"))


def human_pairs(conv: DataFrame) -> DataFrame:
    """(conv_id, turn, prompt, answer): user turns with the assistant turn that follows."""
    u = conv.where("role = 'user'").select("conv_id", "turn", F.col("text").alias("prompt"))
    return u.join(conv.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("answer")), ["conv_id", "turn"])


def collect_instructions(frames: dict[str, DataFrame]) -> DataFrame:
    """Union of instruction sets by name, each row with its origin."""
    out = None
    for origin, df in frames.items():
        part = df.withColumn("origin", F.lit(origin))
        out = part if out is None else out.unionByName(part, allowMissingColumns=True)
    return out


def license_gate(df: DataFrame, allowed: tuple[str, ...], column: str = "generator") -> DataFrame:
    """Rows of permitted generators; a row without a generator is human and stays."""
    return df.where(F.col(column).isNull() | F.col(column).isin(*allowed))


def dedup_instructions(conv: DataFrame) -> DataFrame:
    """Conversations whose first user turn is new: the smallest id of each normal form."""
    first = conv.where("role = 'user'").groupBy("conv_id").agg(F.min_by("text", "turn").alias("text"))
    return first.groupBy(F.md5(T.normalized(F.col("text"))).alias("_k")).agg(F.min("conv_id").alias("conv_id")).select("conv_id")


def reward_robustness(original: DataFrame, rendered: DataFrame) -> DataFrame:
    """Pearson correlation of each score between prompts and their renderings in another language."""
    keys, scores = ["conv_id", "turn"], ("complexity", "readability", "reward")
    x = original.select(*keys, *scores).join(rendered.select(*keys, *[F.col(c).alias(f"r_{c}") for c in scores]), keys)
    return x.agg(*[F.round(F.corr(c, f"r_{c}"), 6).alias(c) for c in scores])


def answer_from_doc(docs: DataFrame, k: int = 2) -> DataFrame:
    """Grounded answer: the k lines that share most words with the document's first line, in their order."""
    x = docs.select("doc_id", T.paragraphs(F.col("text")).alias("ps")).where(F.size("ps") > 1)
    x = x.select("doc_id", F.get("ps", F.lit(0)).alias("instruction"), F.slice("ps", F.lit(2), F.size("ps")).alias("ps"))
    x = x.withColumn("q", T.words(F.lower("instruction")))
    scored = F.transform("ps", lambda p, i: F.struct(-F.size(F.array_intersect(T.words(F.lower(p)), F.col("q"))).alias("s"), i.alias("i"), p.alias("p")))
    best = F.slice(F.sort_array(scored), 1, k)
    ordered = F.sort_array(F.transform(best, lambda b: F.struct(b["i"].alias("i"), b["p"].alias("p"))))
    return x.select("doc_id", "instruction", F.array_join(F.transform(ordered, lambda b: b["p"]), "\n").alias("answer"))


def mt_items(pairs: DataFrame, last_train: int = 2022) -> DataFrame:
    """Pairs of editions that may train, without any whose source text an evaluation edition holds too."""
    held = pairs.where(F.col("edition") > last_train).select(F.md5("src_text").alias("_k")).distinct()
    return pairs.where(F.col("edition") <= last_train).withColumn("_k", F.md5("src_text")).join(held, "_k", "left_anti").drop("_k")


def pack_bins(items: DataFrame, mode: str = "first_fit_decreasing", length: int = LENGTH, per_shard: int = 50_000) -> DataFrame:
    """(conv_id, part, shard, bin, n_tokens): items never split unless longer than a row; shards follow the item count.

    Modes: none (a row an item), next_fit, first_fit_decreasing. A shard holds about `per_shard` items whatever the size of the input.
    """
    import pandas as pd

    shards = max(1, -(-items.count() // per_shard))
    cuts = F.transform(F.sequence(F.lit(0), ((F.col("n_tokens") - 1) / length).cast("int")), lambda p: F.struct(p.alias("part"), F.least(F.lit(length), F.col("n_tokens") - p * length).cast("bigint").alias("n_tokens")))
    x = items.where("n_tokens > 0").select("conv_id", F.explode(cuts).alias("c")).select("conv_id", "c.part", "c.n_tokens").withColumn("shard", F.pmod(F.crc32(F.col("conv_id").cast("string")), F.lit(shards)).cast("int"))

    def place(b: pd.DataFrame) -> pd.DataFrame:
        order = ["n_tokens", "conv_id", "part"] if mode == "first_fit_decreasing" else ["conv_id", "part"]
        b = b.sort_values(order, ascending=[c != "n_tokens" for c in order]).reset_index(drop=True)
        room: list[int] = []
        tree_size = 1
        while tree_size < len(b):
            tree_size *= 2
        # A tournament tree over open rows finds the first one with room in log time.
        tree = [length] * (2 * tree_size) if mode == "first_fit_decreasing" else []
        bins = []
        for n in b["n_tokens"]:
            if mode == "none" or (mode == "next_fit" and (not room or room[-1] < n)):
                room.append(length)
            if mode != "first_fit_decreasing":
                room[-1] -= n
                bins.append(len(room) - 1)
                continue
            i = 1
            while i < tree_size:
                i = 2 * i if tree[2 * i] >= n else 2 * i + 1
            bins.append(i - tree_size)
            tree[i] -= n
            while i > 1:
                i //= 2
                tree[i] = max(tree[2 * i], tree[2 * i + 1])
        return b.assign(bin=bins)[["conv_id", "part", "shard", "bin", "n_tokens"]]

    return x.groupBy("shard").applyInPandas(lambda b: place(b), "conv_id bigint, part int, shard int, bin bigint, n_tokens bigint")


def bin_report(packed: DataFrame, length: int = LENGTH) -> DataFrame:
    """Rows, tokens and fill of a packing."""
    x = packed.groupBy("shard", "bin").agg(F.sum("n_tokens").alias("n"))
    return x.agg(F.count(F.lit(1)).alias("rows"), F.sum("n").alias("tokens"), F.max("n").alias("fullest")).withColumn("fill", F.round(F.col("tokens") / (F.col("rows") * length), 6))
