"""Personal data by weak supervision, in DataFrame functions only.

Four strict patterns (email, ip, card, phone) give the base spans. Wider patterns propose further
candidates (written-out emails, national phone numbers, access tokens). Four labelers vote on each
candidate (+1, -1, 0): its shape, a gazetteer, the words before it, and its composition. Every
labeler can vote both ways on every kind (but the gazetteer of secrets: for or not at all), so that
agreement between them tells how reliable each is.
Expectation-maximisation over the table of vote patterns estimates those reliabilities; its
posteriors train a logistic span classifier over votes, kind and length, which decides.

Only the vote-pattern table reaches the driver: at most kinds x 3^labelers x length classes rows
(3 x 81 x 5), whatever the size of the corpus. It counts every document. Both passes are narrow
scans apart from that aggregation.

Positions come from `split` and `regexp_extract_all` with one pattern: lengths of what stands between
matches and of matches, summed by doubling steps over the array (n log n), give code-point offsets.
Overlaps are found in one sorted array of spans with running greatest ends, texts are cut in blocks
before they are masked: nothing compares all spans of a text with each other. Patterns are written so
that Java's engine neither recurses nor retries inside a run of matching characters.

Edge cases: null and empty texts have no spans; very long texts and texts full of matches are read
whole, in time that grows with n log n; spans of one kind don't overlap, so ties within a kind cannot
occur, and a candidate that meets a base span is dropped; repeated rows are treated alike; with no
candidates at all, or an empty table, the classifier adds nothing; further columns pass through
`mask_personal` untouched.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds in the order of the result; base kinds first.
KINDS = ("email", "ip", "card", "phone", "secret")
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for the pattern to be tried at all.
NEEDS = {"email": "[@]", "ip": "[0-9]", "card": "[0-9]", "phone": r"\+[0-9]", "w_email": r"[(\[]at[)\]]", "w_phone": "[0-9]", "w_secret": "[0-9]"}
WIDE = {
    "w_email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+\x20?[(\[]at[)\]]\x20?[A-Za-z0-9-]{1,63}(?:\x20?(?:[(\[]dot[)\]]|\.)\x20?[A-Za-z0-9-]{1,63})++",
    "w_phone": r"(?<![0-9+.-])\(?[0-9]{2,4}\)?[\x20.-][0-9]{2,4}(?:[\x20.-][0-9]{2,4}){1,3}+(?![0-9])",
    "w_secret": r"(?<![A-Za-z0-9_-])[A-Za-z0-9_-]{20,}+",
}
WIDE_KIND = {"w_email": "email", "w_phone": "phone", "w_secret": "secret"}
#: Gazetteers and context words.
TOP_DOMAINS = "com org net edu gov info io eu de fr es it uk us nl be at ch pl".split()
TOKEN_PREFIXES = ("sk-", "ghp_", "xox", "AKIA", "pk_")
CUES = {"email": "mail|contact|write|reach", "phone": "phone|tel|call|mobile|fax|dial", "secret": "token|secret|key|password|passwd|credential|bearer"}
COUNTER_CUES = "isbn|version|page|fig|table|chapter|section|order|item|year|sha|commit|http"
VOTES = ("v_shape", "v_gazetteer", "v_context", "v_make")
BLOCK = 4096
NOWHERE = "array<struct<s:int,e:int,m:string,b:string>>"


def once(x: Column, f) -> Column:
    """f(x) with x worked out once: a lambda's argument is a value, where a column would be an expression again."""
    return F.get(F.transform(F.array(x), f), F.lit(0))


def running(a: Column, combine, forward: bool = True) -> Column:
    """combine over all elements up to each (or from each on), by doubling steps."""
    sign = -1 if forward else 1

    def of(v: Column) -> Column:
        rounds = F.ceil(F.log2(F.greatest(F.size(v), F.lit(2)).cast("double"))).cast("int")
        steps = F.transform(F.sequence(F.lit(0), rounds - 1), lambda k: F.pow(F.lit(2.0), k).cast("int"))
        return F.aggregate(steps, v, lambda acc, step: F.transform(acc, lambda x, i: combine(x, F.get(acc, i + sign * step))))

    return once(a, of)


def _found(text: Column, pattern: str, needs: str) -> Column:
    """array<struct<s,e,m,b>> of the pattern's matches: offsets in code points, match, and what stands before it."""
    m = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.transform(F.split(text, pattern, -1), lambda p: F.struct(F.length(p).alias("n"), F.lower(F.right(p, F.lit(24))).alias("b")))
    both = F.filter(F.zip_with(m, gaps, lambda a, b: F.struct(a.alias("m"), b["n"].alias("g"), b["b"].alias("b"))), lambda x: x["m"].isNotNull())

    def placed(p: Column) -> Column:
        ends = running(F.transform(p, lambda x: x["g"] + F.length(x["m"])), lambda x, y: x + F.coalesce(y, F.lit(0)))
        return once(ends, lambda e: F.transform(p, lambda x, i: F.struct((F.get(e, i) - F.length(x["m"])).alias("s"), F.get(e, i).alias("e"), x["m"].alias("m"), x["b"].alias("b"))))

    return F.when(text.rlike(needs) & text.rlike(pattern), once(both, placed)).otherwise(F.array().cast(NOWHERE))


def _with_matches(df: DataFrame, text: str, patterns: dict[str, str]) -> DataFrame:
    """df with a column of placed matches per pattern."""
    return df.withColumns({k: _found(F.col(text), p, NEEDS[k.removeprefix("_")]) for k, p in patterns.items()})


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(m: Column) -> Column:
    def of(d: Column) -> Column:
        n = F.length(d)
        digit = lambda i: F.substring(d, i, F.lit(1)).cast("int")
        twice = lambda x: F.when(x > 4, 2 * x - 9).otherwise(2 * x)
        total = F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda a, i: a + F.when((n - i) % 2 == 1, twice(digit(i))).otherwise(digit(i)))
        return F.when(n.between(13, 19), total % 10 == 0).otherwise(F.lit(False))

    return once(_digits(m), of)


def _byte(part: Column) -> Column:
    bare = F.ltrim(part, F.lit("0"))
    return (F.length(bare) < 3) | ((F.length(bare) == 3) & (bare <= "255"))


PASSES = {
    "email": lambda m: F.lit(True),
    "ip": lambda m: F.forall(F.split(m, r"\."), _byte),
    "card": _luhn,
    "phone": lambda m: F.length(_digits(m)).between(9, 15),
}


def _vote(up: Column, down: Column) -> Column:
    return F.when(F.coalesce(up, F.lit(False)), 1).when(F.coalesce(down, F.lit(False)), -1).otherwise(0)


def _votes(kind: str, m: Column, before: Column) -> dict[str, Column]:
    """The labelers' votes on a candidate of a kind."""
    n, digits = F.length(m), F.length(_digits(m))
    context = _vote(before.rlike(CUES[kind]), before.rlike(COUNTER_CUES))
    if kind == "email":
        last = F.element_at(F.split(F.lower(m), "[^a-z0-9]+"), -1)
        # Written alike on both sides of the name: (at) with (dot), [at] with [dot].
        alike = m.rlike(r"\(at\).*\(dot\)") | m.rlike(r"\[at\].*\[dot\]")
        mixed = (m.contains("(") & m.contains("[")) | m.rlike(r"at[)\]].*[a-z0-9]\.[a-z0-9]")
        return {"v_shape": _vote(m.rlike(r"^[A-Za-z][A-Za-z0-9._%+-]+"), m.rlike(r"^(?:[0-9._%+-]|.\x20?[(\[])")), "v_gazetteer": _vote(last.isin(TOP_DOMAINS), ~last.rlike("^[a-z]{2,6}$")), "v_context": context, "v_make": _vote(alike, mixed)}
    if kind == "phone":
        # What stands after an area code in brackets says whether the number is written in one way.
        after = F.regexp_replace(m, r"^\([0-9]+\)\x20?", "")
        separators = F.size(F.array_distinct(F.regexp_extract_all(after, F.lit(r"[\x20.-]"), F.lit(0))))
        return {"v_shape": _vote(digits.between(9, 15), ~digits.between(9, 15)), "v_gazetteer": _vote(m.rlike(r"^(?:\(|0)"), m.rlike(r"^(?:19|20)[0-9][0-9][\x20.-]|^97[89]")), "v_context": context, "v_make": _vote(separators == 1, separators > 1)}
    known = F.lit(False)
    for p in TOKEN_PREFIXES:
        known = known | m.startswith(p)
    mixed = (digits * 100).between(15 * n, 85 * n)
    return {"v_shape": _vote(m.rlike("^[0-9a-fA-F]{32,}$"), m.rlike("^[a-z]+(?:[_-][a-z0-9]+)+$")), "v_gazetteer": _vote(known, F.lit(False)), "v_context": context, "v_make": _vote(mixed, ~mixed)}


def _candidates(df: DataFrame, text: str) -> DataFrame:
    """df with _c: all candidates with their votes, by kind and start."""
    df = _with_matches(df, text, {f"_{w}": p for w, p in WIDE.items()})

    def judged(w: str) -> Column:
        kind = WIDE_KIND[w]

        def of(x: Column) -> Column:
            n = F.length(x["m"])
            long = F.when(n <= 11, 0).when(n <= 15, 1).when(n <= 20, 2).when(n <= 32, 3).otherwise(4)
            return F.struct(F.lit(KINDS.index(kind)).alias("k"), x["s"].alias("s"), x["e"].alias("e"), *[v.alias(name) for name, v in _votes(kind, x["m"], x["b"]).items()], long.alias("long"))

        mixed = F.filter(F.col(f"_{w}"), lambda x: x["m"].rlike("[0-9]") & x["m"].rlike("[A-Za-z]")) if kind == "secret" else F.col(f"_{w}")
        return F.transform(mixed, of)

    df = df.withColumn("_c", F.concat(*[judged(w) for w in WIDE]))
    return df.drop(*[f"_{w}" for w in WIDE])


def _free_of(base: Column, added: Column) -> Column:
    """Those of `added` that meet none of `base` (structs with s and e), by start."""
    part = lambda a, mine: F.transform(a, lambda x, i: F.struct(x["s"].alias("s"), F.lit(mine).alias("mine"), x["e"].alias("e"), i.alias("i")))

    def kept(a: Column) -> Column:
        # Base ends so far, base starts from here on; at equal starts the base comes first.
        ends = running(F.transform(a, lambda x: F.when(x["mine"] == 0, x["e"]).otherwise(0)), lambda x, y: F.greatest(x, y))
        starts = running(F.transform(a, lambda x: F.when(x["mine"] == 0, x["s"])), lambda x, y: F.least(x, y), forward=False)
        both = F.struct(ends.alias("ends"), starts.alias("starts"))
        alone = lambda b: F.filter(a, lambda x, i: (x["mine"] == 1) & (F.get(b["ends"], i) <= x["s"]) & (F.coalesce(F.get(b["starts"], i), x["e"]) >= x["e"]))
        return once(both, alone)

    free = once(F.sort_array(F.concat(part(base, 0), part(added, 1))), kept)
    return F.transform(free, lambda x: F.get(added, x["i"]))


def _base(text: str) -> Column:
    """All base spans, by kind and start."""
    span = lambda k: lambda x: F.struct(F.lit(k).alias("k"), x["s"].alias("s"), x["e"].alias("e"))
    found = lambda k: F.filter(_found(F.col(text), BASE[k], NEEDS[k]), lambda x: PASSES[k](x["m"]))
    return F.concat(*[F.transform(found(k), span(KINDS.index(k))) for k in BASE])


@dataclass
class SpanModel:
    """Reliabilities per kind and labeler, P(+1 | it votes, personal or not), and the classifier's weights."""

    reliability: dict = field(default_factory=dict)
    weights: dict = field(default_factory=dict)
    bias: float = 0.0
    threshold: float = 0.5

    def score(self, c: Column) -> Column:
        z = F.lit(float(self.bias))
        for (name, value), w in sorted(self.weights.items()):
            z = z + F.when(c[name] == value, F.lit(float(w))).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-z))


def expectation_maximisation(rows: list[tuple], rounds: int = 30, faith: float = 4.0) -> tuple[dict, list[float]]:
    """rows: (kind, votes..., long, count). Reliabilities and a posterior for each row.

    Votes are taken as independent given the class, and an abstention (0) as no evidence: a labeler that cannot
    speak about some candidates doesn't make them a class of their own. Estimates start from the majority and
    carry `faith` pseudo-votes for a labeler being right against one for its being wrong.
    """
    posts = [1 / (1 + math.exp(-sum(r[1:5]))) for r in rows]
    table: dict = {}
    for _ in range(rounds):
        table = {}
        for k in {r[0] for r in rows}:
            own = [(r, p) for r, p in zip(rows, posts) if r[0] == k]
            total = sum(r[6] for r, _ in own)
            table[k] = {"prior": (sum(r[6] * p for r, p in own) + 1) / (total + 2)}
            for j, name in enumerate(VOTES, 1):
                for y in (0, 1):
                    up, down = (sum(r[6] * (p if y else 1 - p) for r, p in own if r[j] == v) for v in (1, -1))
                    table[k][name, y] = (up + (faith if y else 1.0)) / (up + down + faith + 1.0)
        for i, r in enumerate(rows):
            t = table[r[0]]
            odds = math.log(t["prior"] / (1 - t["prior"]))
            for j, n in enumerate(VOTES, 1):
                if r[j]:
                    yes, no = (t[n, 1], t[n, 0]) if r[j] > 0 else (1 - t[n, 1], 1 - t[n, 0])
                    odds += math.log(yes / no)
            posts[i] = 1 / (1 + math.exp(-max(-40.0, min(40.0, odds))))
    return table, posts


def train_classifier(rows: list[tuple], posts: list[float], rounds: int = 300, rate: float = 0.5, ridge: float = 1e-3) -> tuple[dict, float]:
    """Logistic regression on the posteriors as soft labels, by gradient steps over the pattern table."""
    names = ("k", *VOTES, "long")
    total = sum(r[6] for r in rows) or 1
    weights = {(n, r[j]): 0.0 for r in rows for j, n in enumerate(names)}
    bias = 0.0
    for _ in range(rounds):
        grad, gb = {k: ridge * w for k, w in weights.items()}, 0.0
        for r, p in zip(rows, posts):
            z = bias + sum(weights[n, r[j]] for j, n in enumerate(names))
            d = (1 / (1 + math.exp(-max(-40.0, min(40.0, z)))) - p) * r[6] / total
            gb += d
            for j, n in enumerate(names):
                grad[n, r[j]] += d
        bias -= rate * gb
        for k in weights:
            weights[k] -= rate * grad[k]
    return weights, bias


def fit_spans(docs: DataFrame, text: str = "text") -> SpanModel:
    """One pass over all documents for the counts of vote patterns; the rest is small arithmetic.

    Candidates that meet a base span are settled already and have no vote.
    """
    t = docs.select(F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")).alias("_text"))
    both = F.struct(F.col("_c").alias("c"), _base("_text").alias("base"))
    open_ones = F.when(F.size("_c") > 0, once(both, lambda x: _free_of(x["base"], x["c"])))
    seen = _candidates(t, "_text").select(F.explode(open_ones).alias("c")).select("c.*")
    table = seen.groupBy("k", *VOTES, "long").agg(F.count(F.lit(1)).alias("n")).collect()
    rows = sorted(tuple(r) for r in table)
    if not rows:
        return SpanModel()
    reliability, posts = expectation_maximisation(rows)
    weights, bias = train_classifier(rows, posts)
    return SpanModel(reliability, weights, bias)


def find_spans(docs: DataFrame, model: SpanModel, text: str = "text") -> DataFrame:
    """docs with base and all: arrays of struct<k,s,e>, by kind and start; k indexes KINDS."""
    df = docs.withColumn("_text", F.coalesce(F.col(text).cast("string"), F.lit("")))
    df = _candidates(df.withColumn("base", _base("_text")), "_text")
    likely = F.transform(F.filter("_c", lambda c: model.score(c) > model.threshold), lambda c: F.struct(c["k"].alias("k"), c["s"].alias("s"), c["e"].alias("e")))
    both = F.struct(F.col("base").alias("base"), likely.alias("added"))
    every = once(both, lambda x: F.when(F.size(x["added"]) == 0, x["base"]).otherwise(F.sort_array(F.concat(x["base"], _free_of(x["base"], x["added"])))))
    return df.withColumn("all", every).drop("_text", "_c")


def span_string(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def mask_personal(docs: DataFrame, model: SpanModel, text: str = "text") -> DataFrame:
    """docs with every span replaced by its kind in angle brackets; n_chars, if present, follows.

    Overlapping spans are replaced as one, by the kind of the longest (the first of equally long ones), so
    that nothing of them stays.
    """
    boxed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")).alias("_raw"))
    df = find_spans(boxed, model, "_raw")
    names = F.array(*[F.lit(f"<{k.upper()}>") for k in KINDS])

    def apart(a: Column) -> Column:
        """Spans that meet become one: it begins where a start reaches past all ends before."""
        ends = running(F.transform(a, lambda x: x["e"]), lambda x, y: F.greatest(x, y))

        def groups(e: Column) -> Column:
            heads = F.filter(F.transform(a, lambda x, i: F.when((i == 0) | (F.get(e, i - 1) <= x["s"]), i)), lambda i: i.isNotNull())

            def fold(h: Column) -> Column:
                def one(i: Column, j: Column) -> Column:
                    last = F.coalesce(F.get(h, j + 1), F.size(a))
                    longest = F.array_max(F.transform(F.slice(a, i + 1, last - i), lambda x: F.struct((x["e"] - x["s"]).alias("n"), (-x["s"]).alias("s"), (-x["k"]).alias("k"))))
                    return F.struct(F.get(a, i)["s"].alias("s"), F.get(e, last - 1).alias("e"), (-longest["k"]).alias("k"))

                return F.transform(h, one)

            return once(heads, fold)

        return once(ends, groups)

    by_start = F.sort_array(F.transform("all", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k"))))

    def masked(spans: Column) -> Column:
        def with_blocks(blocks: Column) -> Column:
            def between(a: Column, b: Column) -> Column:
                """Code points a to b of the text, from the blocks that hold them."""
                at = F.floor(a / BLOCK).cast("int")
                held = F.array_join(F.slice(blocks, at + 1, F.floor(b / BLOCK).cast("int") - at + 1), "")
                return F.substring(held, a - at * BLOCK + 1, b - a)

            end = lambda i: F.coalesce(F.get(spans, i - 1)["e"], F.lit(0))
            pieces = F.transform(spans, lambda x, i: F.concat(between(end(i), x["s"]), F.get(names, x["k"])))
            return F.concat(F.array_join(pieces, ""), between(end(F.size(spans)), F.length(F.col("_raw"))))

        return once(F.regexp_extract_all(F.col("_raw"), F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0)), with_blocks)

    df = df.withColumn("_new", F.when(F.size("all") > 0, once(once(by_start, apart), masked)))
    new = {text: F.coalesce(F.col("_new"), F.col(f"_row.`{text}`"))}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("_new").isNull(), F.col("_row.n_chars")).otherwise(F.length("_new")).cast(docs.schema["n_chars"].dataType)
    return df.select(*[new.get(c, F.col(f"_row.`{c}`")).alias(c) for c in docs.columns])


def pii_report(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    found = find_spans(docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text")), fit_spans(docs, text), "text")
    count = lambda k: F.size(F.filter("base", lambda x: x["k"] == KINDS.index(k))).cast("long").alias(f"n_{k}")
    return found.select("doc_id", *[count(k) for k in BASE], F.sha2(span_string(F.col("base")), 256).alias("base_sha256"), span_string(F.col("all")).alias("spans"))
