"""Web filtering: routing by tier, document rules, paragraph rules, deduplication, the ladder.

Row-local rules stay inside one shuffle-free stage, cheap ones first. Deduplication shuffles
(key, id) pairs and joins the survivors back, so texts move once at most.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage
from . import near
from .language import MOST_BROADCAST

#: The tier of each language here; one of the four stands in for the remaining languages.
TIERS = (("en", "english"), ("fr", "high_resource"), ("de", "high_resource"), ("es", "remaining"))
MIN_CHARS, MAX_UPPER, MAX_SYMBOLS, MAX_LETTERLESS = 200, 0.40, 0.1, 0.2
PHRASE, WORD = "lorem ipsum", "javascript"


def route_by_tier(df: DataFrame, tiers=TIERS) -> DataFrame:
    """Each document's tier; a literal table of a few languages is broadcast."""
    return df.join(F.broadcast(df.sparkSession.createDataFrame(list(tiers), "lang string, tier string")), "lang", "left").withColumn("tier", F.coalesce("tier", F.lit("remaining")))


def min_chars(df: DataFrame, least: int = MIN_CHARS) -> DataFrame:
    """Documents of at least so many code points; n_chars lets the scan skip row groups."""
    return df.where((F.col("n_chars") if "n_chars" in df.columns else F.length("text")) >= least)


def has_phrase(text: Column, phrase: str = PHRASE) -> Column:
    return F.lower(text).contains(phrase)


def has_word(text: Column, word: str = WORD, whole: bool = True) -> Column:
    return F.lower(text).rlike(rf"(^|[^\p{{L}}\p{{N}}]){word}([^\p{{L}}\p{{N}}]|$)") if whole else F.lower(text).contains(word)


def has_braces(text: Column) -> Column:
    return text.rlike("[{}]")


def drop_phrase(df: DataFrame, phrase: str = PHRASE) -> DataFrame:
    return df.where(~has_phrase(F.col("text"), phrase))


def drop_word(df: DataFrame, word: str = WORD, whole: bool = True) -> DataFrame:
    return df.where(~has_word(F.col("text"), word, whole))


def drop_braces(df: DataFrame) -> DataFrame:
    return df.where(~has_braces(F.col("text")))


def share_above(part: Column, whole: Column, most: float) -> Column:
    """part / whole > most without dividing."""
    return part.cast("double") > F.lit(most) * whole


def upper_heavy(p: Column, most: float = MAX_UPPER, denom: str = "letters") -> Column:
    return share_above(T.count_class(p, r"\p{Lu}"), T.count_class(p, r"\p{L}") if denom == "letters" else F.length(p), most)


def symbol_heavy(p: Column, most: float = MAX_SYMBOLS, symbols: str = "hash") -> Column:
    n = T.count_class(F.regexp_replace(F.regexp_replace(p, r"\.\.\.", "#"), T.ELLIPSIS, "#"), "#") if symbols == "hash" else T.count_class(p, r"[\p{S}#&*%@|]")
    return share_above(n, F.size(T.words(p)), most)


def letterless_heavy(p: Column, most: float = MAX_LETTERLESS) -> Column:
    w = T.words(p)
    return share_above(F.size(F.filter(w, lambda x: ~x.rlike(r"\p{L}"))), F.size(w), most)


def paragraph_rules(df: DataFrame, denom: str = "letters", symbols: str = "hash", recheck: int | None = None) -> DataFrame:
    """Texts rebuilt from the paragraphs that pass every rule; documents left empty go.

    The rules are worked out once: Spark would copy them into a filter pushed below their projection, but
    pushes nothing below one that holds a random number.
    """
    keep = F.filter(T.paragraphs(F.col("text")), lambda p: ~(upper_heavy(p, denom=denom) | symbol_heavy(p, symbols=symbols) | letterless_heavy(p)))
    out = df.withColumns({"_kept": keep, "_once": F.rand(0)}).where((F.size("_kept") > 0) & (F.col("_once") >= 0))
    out = out.withColumn("text", F.array_join("_kept", "\n")).drop("_kept", "_once")
    out = out.withColumn("n_chars", F.length("text").cast("bigint"))
    return out if recheck is None else min_chars(out, recheck)


def paragraph_counts(df: DataFrame, rule, by: str = "lang") -> DataFrame:
    """Paragraphs and those that a rule drops, by group."""
    ps = df.select(by, T.paragraphs(F.col("text")).alias("ps"))
    return ps.groupBy(by).agg(F.sum(F.size("ps")).cast("bigint").alias("paragraphs"), F.sum(F.size(F.filter("ps", rule))).cast("bigint").alias("dropped"))


def rule_report(df: DataFrame) -> DataFrame:
    """Hits of each document rule by language: all, and as the first rule that fails."""
    t = F.col("text")
    rules = [("short", F.col("n_chars") < MIN_CHARS), ("phrase", has_phrase(t)), ("word", has_word(t)), ("braces", has_braces(t)), ("upper", F.exists(T.paragraphs(t), lambda p: upper_heavy(p))), ("symbols", F.exists(T.paragraphs(t), lambda p: symbol_heavy(p))), ("letterless", F.exists(T.paragraphs(t), lambda p: letterless_heavy(p)))]
    hit = df.select("lang", "n_chars", F.array_compact(F.array(*[F.when(c, F.lit(n)) for n, c in rules])).alias("reasons"))
    rows = hit.select("lang", "n_chars", F.posexplode("reasons").alias("i", "rule"), F.size("reasons").alias("n"))
    return rows.groupBy("lang", "rule").agg(F.count(F.lit(1)).alias("hits"), F.count_if(F.col("i") == 0).alias("first_hits"), F.count_if(F.col("n") == 1).alias("only_hits"), F.sum("n_chars").cast("bigint").alias("chars"))


def dedup(df: DataFrame, key: Column, scope: list[str] | None = None) -> DataFrame:
    """The smallest doc_id of each key (and scope). Shuffles 16-byte digests; copies combine map-side."""
    keyed = df.select(*(scope or []), F.unhex(F.md5(key)).alias("_k"), "doc_id")
    first = keyed.groupBy(*(scope or []), "_k").agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    return df.join(first, "doc_id", "left_semi")


def dedup_exact(df: DataFrame, scope: list[str] | None = None) -> DataFrame:
    return dedup(df, F.col("text"), scope)


def dedup_normalized(df: DataFrame) -> DataFrame:
    return dedup(df, T.normalized(F.col("text")))


def dedup_paragraphs(df: DataFrame, min_len: int = 0) -> DataFrame:
    """Only the first (doc_id, position) of each normalised paragraph stays; texts are rebuilt."""
    lines = df.select("doc_id", F.posexplode(T.paragraphs(F.col("text"))).alias("pos", "para"))
    keyed = lines.select("doc_id", "pos", F.length("para").alias("n"), F.unhex(F.md5(T.normalized(F.col("para")))).alias("k"))
    first = (keyed.where(F.col("n") >= min_len) if min_len else keyed).groupBy("k").agg(F.min(F.struct("doc_id", "pos")).alias("f")).select("f.*")
    if min_len:
        first = first.union(keyed.where(F.col("n") < min_len).select("doc_id", "pos"))
    kept = first.groupBy("doc_id").agg(F.sort_array(F.collect_list("pos")).alias("at"))
    out = df.join(kept, "doc_id").withColumn("_ps", T.paragraphs(F.col("text")))
    return out.withColumn("text", F.array_join(F.transform("at", lambda i: F.get("_ps", i)), "\n")).drop("_ps", "at")


def concat_sources(frames: dict[str, DataFrame]) -> DataFrame:
    """Union of corpora with their origin."""
    out = None
    for name, df in frames.items():
        df = df.withColumn("origin", F.lit(name))
        out = df if out is None else out.unionByName(df, allowMissingColumns=True)
    return out


def html_to_text(pages: DataFrame) -> DataFrame:
    """page_id, declared language and visible text of raw pages, by expressions only."""
    x = F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    x = F.regexp_replace(F.regexp_replace(x, r"(?s)<[^>]*>", " "), r"&[a-zA-Z]+;|&#[0-9]+;", " ")
    return pages.select("page_id", F.regexp_extract("html", r"<html[^>]*lang=.([a-z]+)", 1).alias("lang"), F.btrim(F.regexp_replace(x, r"[\x20\x09-\x0D]+", " ")).alias("text"))


def educational_filter(df: DataFrame, tau: float, strict: bool = True) -> DataFrame:
    return df.where(F.col("edu_score") > tau if strict else F.col("edu_score") >= tau)


def document_rules(df: DataFrame) -> DataFrame:
    t = F.col("text")
    return min_chars(df).where(~has_braces(t) & ~has_phrase(t) & ~has_word(t))


def web_ladder(df: DataFrame) -> DataFrame:
    """Length and document rules, paragraph rules, exact dedup of the rebuilt texts (landed, so that they are rebuilt once)."""
    return dedup_exact(cut_lineage(paragraph_rules(document_rules(df))))


#: What each tier goes through, in order, before the rules that all share.
ROUTES = {"english": ("score", "dedup"), "high_resource": ("perplexity",), "remaining": ("dedup", "language", "perplexity")}
STAGES = ("input", "score", "dedup", "language", "perplexity", "document rules", "paragraph rules")


def tier_ladder(df: DataFrame, scores: DataFrame, predicted: DataFrame, perplexities: DataFrame, phase: int = 1, bounds: dict[int, float] | None = None, keep: float = 2 / 3, tiers=TIERS) -> tuple[DataFrame, DataFrame]:
    """Documents that pass their tier's route, and the ledger of documents and characters left after each stage.

    english: educational score above the phase's bound, dedup inside each source (its dump);
    high_resource: arrives deduplicated, perplexity only; remaining: corpora together, dedup over all of
    them, declared language confirmed, perplexity. From the second phase on every tier is scored.
    All then pass the document and paragraph rules. scores: doc_id, edu_score; predicted: doc_id,
    predicted; perplexities: doc_id, perplexity. A document without a score, prediction or perplexity
    fails the stage that asks for it.

    Stages work on one narrow landed row a document; texts are read for the rules only, by the survivors.
    """
    bounds = bounds or {1: 2.0, 2: 3.0, 3: 3.0}
    facts = route_by_tier(df.select("doc_id", "lang", "source", "n_chars", F.unhex(F.md5("text")).alias("key")), tiers)
    facts = facts.join(scores.select("doc_id", "edu_score"), "doc_id", "left").join(predicted.select("doc_id", "predicted"), "doc_id", "left").join(perplexities.select("doc_id", "perplexity"), "doc_id", "left")
    at = {"input": cut_lineage(facts)}
    asked = lambda stage: F.col("tier").isin([t for t, r in ROUTES.items() if stage in r])
    passed = F.coalesce(F.col("edu_score") > bounds[phase], F.lit(False))
    at["score"] = at["input"].where(passed if phase > 1 else ~asked("score") | passed)
    scope = F.when(F.col("tier") == "english", F.col("source")).otherwise(F.lit(""))
    first = at["score"].where(asked("dedup")).groupBy("tier", scope.alias("scope"), "key").agg(F.min("doc_id").alias("doc_id"))
    at["dedup"] = cut_lineage(at["score"].where(~asked("dedup")).unionByName(at["score"].join(first.select("doc_id"), "doc_id", "left_semi")))
    at["language"] = at["dedup"].where(~asked("language") | F.coalesce(F.col("predicted") == F.col("lang"), F.lit(False)))
    bound = at["language"].where(asked("perplexity")).groupBy("lang").agg(F.percentile("perplexity", F.lit(keep)).alias("bound"))
    least = F.coalesce(F.col("perplexity") <= F.col("bound"), F.lit(False))
    at["perplexity"] = cut_lineage(at["language"].join(F.broadcast(bound), "lang", "left").where(~asked("perplexity") | least).drop("bound"))
    left = df.join(at["perplexity"].select("doc_id", "tier"), "doc_id")
    at["document rules"] = document_rules(left)
    out = at["paragraph rules"] = cut_lineage(paragraph_rules(at["document rules"]))
    ledger = None
    for i, stage in enumerate(STAGES):
        part = at[stage].groupBy("tier").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").cast("bigint").alias("chars")).select(F.lit(i).alias("step"), F.lit(stage).alias("stage"), "tier", "docs", "chars")
        ledger = part if ledger is None else ledger.unionByName(part)
    return out, ledger


#: Shingles that more than CROWD documents begin with go last in the order of all shingles; MOST_CROWDED of them at most.
CROWD, MOST_CROWDED = 100, 100_000
#: Shingles that a part of the join by heads has, about, and pairs that are listed at once.
HEADS, LISTED = 2_000_000, 1_000_000
#: A shingle's place in the order of all shingles has 63 bits, and one more if it is crowded; 40 bits of it travel.
_TOP, _KEY = np.uint64(1 << 63), np.uint64(24)


def _head_sizes(n: np.ndarray, percent: int) -> np.ndarray:
    return n - -(-n * percent // 100) + 1


def _described(percent: int) -> Callable:
    """doc_id, n and digest of every set; at last, without an id, the shingles that several different sets of the task begin with."""

    def run(sets):
        seen, heads = set(), []
        for ids, _, h, edges in sets:
            n = np.diff(edges)
            digests = [hashlib.blake2b(h[i:j].tobytes(), digest_size=16).digest() for i, j in zip(edges[:-1].tolist(), edges[1:].tolist())]
            for i, p, x in zip(edges[:-1].tolist(), _head_sizes(n, percent).tolist(), digests):
                if x not in seen:
                    seen.add(x)
                    heads.append(h[i : i + p])
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(digests, pa.binary()), pa.nulls(len(ids), pa.list_(pa.int64())), pa.nulls(len(ids), pa.list_(pa.int64()))], names=["doc_id", "n", "digest", "k", "c"])
            kind = ids.type
        if heads:
            k, c = np.unique(np.concatenate(heads), return_counts=True)
            k, c = (pa.ListArray.from_arrays(pa.array([0, int((c > 1).sum())], pa.int32()), pa.array(x[c > 1])) for x in (k, c))
            yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), k, c], names=["doc_id", "n", "digest", "k", "c"])

    return run


def _heads(percent: int, crowded: np.ndarray) -> Callable:
    """doc_id, n, the place of the last shingle of the head (32 bits) and the places of all of them (40 bits, packed)."""

    def run(sets):
        for ids, _, h, edges in sets:
            n = np.diff(edges)
            place = (h.view(np.uint64) ^ _TOP) >> np.uint64(1)
            put_off = np.isin(h, crowded) if len(crowded) else np.zeros(len(h), bool)
            heads = []
            late = np.logical_or.reduceat(put_off, edges[:-1])
            for i, j, p, some in zip(edges[:-1].tolist(), edges[1:].tolist(), _head_sizes(n, percent).tolist(), late.tolist()):
                if some:
                    off = put_off[i:j]
                    heads.append(np.concatenate([place[i:j][~off][:p], place[i:j][off] | _TOP])[:p])
                else:
                    heads.append(place[i : i + p])
            last = np.array([x[-1] >> np.uint64(32) for x in heads], np.int64)
            keys = [np.ascontiguousarray((x >> _KEY).view(np.uint8).reshape(-1, 8)[:, :5]).tobytes() for x in heads]
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(last), pa.array(keys, pa.binary())], names=["doc_id", "n", "last", "p"])

    return run


def _routed(parts: int) -> Callable:
    """Heads of a batch by the part that their shingles belong to: how many documents, their ids, sizes, last places and numbers of shingles, and the shingles."""

    def run(batches):
        for b in batches:
            p = b.column(3)
            raw = np.frombuffer(b"".join(x.as_py() for x in p), np.uint8).reshape(-1, 5)
            keys = np.zeros((len(raw), 8), np.uint8)
            keys[:, :5] = raw
            keys = keys.view(np.uint64)[:, 0]
            of = np.repeat(np.arange(len(p)), pc.binary_length(p).to_numpy(zero_copy_only=False) // 5)
            part = ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)) % np.uint64(parts)
            by = np.argsort(part, kind="stable")
            ids, n, last = b.column(0).cast(pa.int64()).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy()
            edges = np.searchsorted(part[by], np.arange(parts + 1, dtype=np.uint64))
            to, data = np.flatnonzero(np.diff(edges)), []
            for j in to.tolist():
                at = by[edges[j] : edges[j + 1]]
                docs, many = np.unique(of[at], return_counts=True)
                data.append(b"".join([np.int64(len(docs)).tobytes(), ids[docs].tobytes(), n[docs].astype(np.int32).tobytes(), last[docs].astype(np.uint32).tobytes(), many.astype(np.int32).tobytes(), raw[at].tobytes()]))
            yield pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), pa.array(data, pa.binary())], names=["part", "data"])

    return run


def _pairs_of(data: list[bytes], percent: int):
    """(a, b, c, want) arrays of one part: sets a and b share c of the part's shingles in their heads, and must share want in all parts."""
    got = [[] for _ in range(5)]
    for x in data:
        m, at = int(np.frombuffer(x, np.int64, 1)[0]), 8
        for k, kind in enumerate((np.int64, np.int32, np.uint32, np.int32)):
            got[k].append(np.frombuffer(x, kind, m, at))
            at += m * np.dtype(kind).itemsize
        got[4].append(np.frombuffer(x, np.uint8, -1, at).reshape(-1, 5))
    ids, n, last, many = (np.concatenate(x).astype(np.int64) for x in got[:4])
    keys = np.zeros((int(many.sum()), 8), np.uint8)
    np.concatenate(got[4], out=keys[:, :5])
    keys = keys.view(np.uint64)[:, 0]
    # Documents by size; entries by shingle, then size.
    by = np.argsort(n, kind="stable")
    rank = np.empty(len(n), np.int64)
    rank[by] = np.arange(len(n))
    ids, n, last, of = ids[by], n[by], last[by], np.repeat(rank, many)
    order = np.lexsort((of, keys))
    keys, of = keys[order], of[order]
    same = keys[1:] == keys[:-1]
    shared = np.append(same, False) | np.append(False, same)
    keys, of = keys[shared], of[shared]
    if not len(of):
        return
    group = np.cumsum(np.append(0, keys[1:] != keys[:-1]))
    most = np.searchsorted(n, 100 * n // percent, "right")  # documents that are not too large for one
    span = np.int64(len(n) + 1)
    stop = np.searchsorted(group * span + of, group * span + most[of], "left")
    count = np.maximum(stop - np.arange(len(of)) - 1, 0)
    ends, i = np.cumsum(count), 0
    rest = -(-n * percent // 100) - 1  # shingles after the head
    while i < len(of):
        j = max(i + 1, int(np.searchsorted(ends, ends[i] - count[i] + LISTED, "right")))
        c = count[i:j]
        x = np.repeat(np.arange(i, j), c)
        y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(c) - c, c)
        pair, c = np.unique(of[x] * span + of[y], return_counts=True)
        x, y = pair // span, pair % span
        keep = x != y
        x, y, c = x[keep], y[keep], c[keep]
        # What follows the head that ends first is all they can share besides.
        beyond = np.where(last[x] < last[y], rest[x], np.where(last[x] > last[y], rest[y], np.maximum(rest[x], rest[y])))
        want = -(-percent * (n[x] + n[y]) // (100 + percent)) - beyond
        yield np.minimum(ids[x], ids[y]), np.maximum(ids[x], ids[y]), c, want
        i = j


def _met(percent: int) -> Callable:
    def run(batches):
        now, data = None, []

        def done():
            for columns in _pairs_of(data, percent) if data else ():
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in columns], names=["a", "b", "c", "want"])

        for b in batches:
            for part, x in zip(b.column(0).to_pylist(), b.column(1)):
                if part != now:
                    yield from done()
                    now, data = part, []
                data.append(x.as_py())
        yield from done()

    return run


def near_pairs(df: DataFrame, percent: int = 75, n: int = 5) -> DataFrame:
    """(a, b, jaccard) of word shingles within one language, without a sketch: every pair that reaches the similarity.

    Documents of equal sets are one class, and only the smallest document of each is compared: the pairs of all members
    are written out at the end, from (class, document) rows. Two sets that reach the similarity share one of their first
    size - need + 1 shingles (the head) in any order of all shingles, so only those meet; the order is by hash, with crowded
    shingles at the end. Heads travel packed, and what two heads share is counted: what they can share besides is known, and
    pairs that can't reach the similarity go. The others are checked on the whole sets. Texts are shingled again where they
    are read rather than landed as sets.
    """
    rows = df.where("lang is not null and doc_id is not null")
    kind = df.schema["doc_id"].dataType.simpleString()
    every = cut_lineage(near.shingle_sets(rows, n, _described(percent), f"doc_id {kind}, n bigint, digest binary, k array<bigint>, c array<bigint>"))
    sets = every.where("doc_id is not null")
    classes = cut_lineage(sets.groupBy("digest").agg(F.min("doc_id").alias("a"), F.min("n").alias("n")))
    members = cut_lineage(sets.select("doc_id", "digest").join(classes, "digest").select("a", "doc_id"))
    firsts = classes.select(F.col("a").alias("doc_id"))
    only = lambda x, ids: x.join(F.broadcast(ids) if ids.count() <= MOST_BROADCAST else ids, "doc_id", "left_semi")
    counts = every.where("doc_id is null").select(F.explode(F.arrays_zip("k", "c")).alias("x")).groupBy("x.k").agg(F.sum("x.c").alias("c")).where(F.col("c") > CROWD)
    crowded = np.sort(np.array([r["k"] for r in counts.orderBy(F.desc("c"), "k").limit(MOST_CROWDED).collect()], np.int64))
    total = classes.agg(F.sum(F.expr(f"n - (n * {percent} + 99) div 100 + 1"))).first()[0] or 0
    parts = max(2 * df.sparkSession.sparkContext.defaultParallelism, -(-total // HEADS))
    heads, route = _heads(percent, crowded), _routed(parts)
    if firsts.count() <= MOST_BROADCAST:
        dealt = near.shingle_sets(only(rows, firsts), n, lambda sets: route(heads(sets)), "part int, data binary")
    else:  # texts are wider than their heads
        dealt = only(near.shingle_sets(rows, n, heads, f"doc_id {kind}, n bigint, last bigint, p binary"), firsts).mapInArrow(route, "part int, data binary")
    dealt = dealt.repartition(parts, "part").sortWithinPartitions("part")
    shared = dealt.mapInArrow(_met(percent), "a bigint, b bigint, c bigint, want bigint").groupBy("a", "b").agg(F.sum("c").alias("c"), F.max("want").alias("want"))
    met = cut_lineage(shared.where("c >= want").select("a", "b"))
    asked = cut_lineage(met.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    whole = near.shingle_sets(only(rows, asked), n)
    found = near.checked(met, whole.select(F.col("doc_id").alias("id"), "h"), percent)
    links = found.select("a", "b", F.round(F.col("c") / (F.col("na") + F.col("nb") - F.col("c")), 6).alias("jaccard"))
    links = links.unionByName(classes.select("a", F.col("a").alias("b"), F.lit(1.0).alias("jaccard")))
    both = links.join(members.toDF("a", "x"), "a").join(members.toDF("b", "y"), "b").where("a <> b or x < y")
    return both.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "jaccard")
