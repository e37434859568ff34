"""Near-duplicate removal in DataFrame functions: minima of hashed shingles, bands, exact check, components.

1. Each text becomes the sorted set of hashes of its word shingles; equal sets (of one language) are one
   representative, so exact copies cost nothing further.
2. BANDS x ROWS minima are hashed by bands. A pair at similarity 0.75 shares no band with probability 2e-6.
3. Buckets of up to SMALL members list their pairs. In larger ones every member meets the smallest
   member only (a star, salted by the bucket's size).
4. Pairs are checked on the whole sets; links give components.
5. In large buckets that still hold several components, members outside the largest one meet the members
   of other components; nothing that is already connected is compared. No cap, no sampling.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage
from .language import MOST_BROADCAST

BANDS, ROWS, SMALL, STAR = 24, 3, 32, 2048
#: Words of texts that are shingled together, beyond the first text.
WORDS = 250_000
#: Ids of a block of the exact check, about.
TILE = 256


def _mixed(x: np.ndarray) -> np.ndarray:
    """Every bit of a 64-bit number depends on every other; no two numbers become one."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _sets(words: np.ndarray, lens: np.ndarray, seeds: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of the n-word shingles of texts, one after the other, and where each text's begin; words: hashes of
    their words, lens: how many each has (one at least)."""
    weights = [np.uint64((0x9E3779B97F4A7C15 * (2 * j + 1) ** 3 + 0x632BE59BD9B4E019 * j) % 2**64 | 1) for j in range(n)]
    ends = np.cumsum(lens)
    many = np.maximum(lens - n + 1, 1)
    of = np.repeat(np.arange(len(lens)), many)
    at = np.arange(len(of)) - np.repeat(np.cumsum(many) - many, many) + (ends - lens)[of]
    words = np.concatenate([words, np.zeros(n, np.uint64)])
    h = words[at] * weights[0]
    short = np.flatnonzero(lens < n)
    for j in range(1, n):
        h += words[at + j] * weights[j]
    firsts = np.cumsum(many) - many
    for d in short.tolist():
        w = words[ends[d] - lens[d] : ends[d]]
        h[firsts[d]] = sum((w[j : j + 1] * weights[j] for j in range(len(w))), np.zeros(1, np.uint64))[0]
    h = _mixed(h + seeds[of]).view(np.int64)
    for i, j in zip(firsts.tolist(), (firsts + many).tolist()):
        h[i:j].sort()
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (of[1:] != of[:-1])
    return h[new], np.append(0, np.cumsum(np.bincount(of[new], minlength=len(lens))))


def shingle_sets(df: DataFrame, n: int = 5, then: Callable | None = None, schema: str = "") -> DataFrame:
    """doc_id, lang, h: sorted distinct hashes of n-word shingles (a shorter text is one shingle) of one language; texts without
    words have no row. then gets (ids, languages, hashes, edges) of some documents at a time where they are made, and returns
    batches of the schema instead."""
    w = df.select("doc_id", F.coalesce("lang", F.lit("")).alias("lang"), T.words(F.lower("text")).alias("w"))
    w = w.select("doc_id", "lang", F.xxhash64("lang"), F.transform("w", lambda x: F.xxhash64(x)))
    if then is None:
        schema = f"doc_id {df.schema['doc_id'].dataType.simpleString()}, lang string, h array<bigint>"

    def listed(sets):
        for ids, langs, h, edges in sets:
            yield pa.RecordBatch.from_arrays([ids, langs, pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(h))], names=["doc_id", "lang", "h"])

    def some(batches):
        for b in batches:
            words, edges = b.column(3).values.to_numpy(zero_copy_only=False).view(np.uint64), b.column(3).offsets.to_numpy()
            seeds, i = b.column(2).to_numpy(zero_copy_only=False).view(np.uint64), 0
            while i < b.num_rows:
                j = max(i + 1, int(np.searchsorted(edges, edges[i] + WORDS, "right")) - 1)
                lens = np.diff(edges[i : j + 1]).astype(np.int64)
                has = np.flatnonzero(lens)
                if len(has):
                    h, cuts = _sets(words[edges[i] : edges[j]], lens[has], seeds[i:j][has], n)
                    yield b.column(0)[i:j].take(pa.array(has)), b.column(1)[i:j].take(pa.array(has)), h, cuts
                i = j

    return w.mapInArrow(lambda batches: (then or listed)(some(batches)), schema)


def band_rows(sets: DataFrame) -> DataFrame:
    """(id, key) for every band of every set."""
    low = lambda i: F.array_min(F.transform("h", lambda x: F.xxhash64(x, F.lit(i))))
    minima = sets.select("id", "lang", F.array(*[low(i) for i in range(BANDS * ROWS)]).alias("m"))
    keys = F.array(*[F.xxhash64("lang", F.lit(b), *[F.get("m", F.lit(b * ROWS + r)) for r in range(ROWS)]) for b in range(BANDS)])
    return minima.select("id", F.explode(keys).alias("key"))


def _shared(sets: dict, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """How many hashes the sets a and b of each pair share, and how many each has."""
    ids = np.array(sorted(sets), np.int64)
    h = [sets[i] for i in ids.tolist()]
    n = np.array([len(x) for x in h], np.int64)
    starts = np.cumsum(n) - n
    kinds, flat = np.unique(np.concatenate(h), return_inverse=True)
    mark, c = np.zeros(len(kinds), bool), np.zeros(len(a), np.int64)
    a, b = np.searchsorted(ids, a), np.searchsorted(ids, b)
    by = np.argsort(a, kind="stable")
    cuts = np.append(np.flatnonzero(np.append(True, a[by][1:] != a[by][:-1])), len(by))
    for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
        x, y = int(a[by[i]]), b[by[i:j]]
        own = flat[starts[x] : starts[x] + n[x]]
        mark[own] = True
        ends = np.cumsum(n[y])
        at = np.arange(ends[-1]) + np.repeat(starts[y] - (ends - n[y]), n[y])
        c[by[i:j]] = np.add.reduceat(mark[flat[at]], ends - n[y], dtype=np.int64)
        mark[own] = False
    return c, n[a], n[b]


def checked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose sets reach the similarity, with it.

    A set doesn't travel once a pair: ids with the same smallest neighbour are a block (of about TILE ids; larger ones are sliced
    by hash), a pair belongs to the tile of its two blocks, and a set goes once to every tile that has a pair of it.
    """
    kind = pairs.schema["a"].dataType.simpleString()
    few = lambda x: F.broadcast(x) if x.count() <= MOST_BROADCAST else x
    ends = pairs.select("a", "b").union(pairs.select("b", "a")).groupBy("a").agg(F.least("a", F.min("b")).alias("label"))
    slices = ends.groupBy("label").agg(F.ceil(F.count(F.lit(1)) / TILE).alias("slices"))
    blocks = cut_lineage(ends.join(slices, "label").select(F.col("a").alias("id"), F.xxhash64("label", F.pmod(F.xxhash64("a"), "slices")).alias("block")))
    tiled = pairs.select("a", "b").join(few(blocks.toDF("a", "x")), "a").join(few(blocks.toDF("b", "y")), "b")
    tiled = cut_lineage(tiled.select(F.xxhash64(F.least("x", "y"), F.greatest("x", "y")).alias("tile"), "a", "b"))
    members = cut_lineage(tiled.select("tile", F.explode(F.array("a", "b")).alias("id")).distinct())
    sent = sets.select("id", "h").join(few(members), "id").select("tile", F.col("id").cast("bigint").alias("a"), F.lit(None).cast("bigint").alias("b"), "h")
    asked = tiled.select("tile", F.col("a").cast("bigint").alias("a"), F.col("b").cast("bigint").alias("b"), F.lit(None).cast("array<bigint>").alias("h"))

    def run(batches):
        now, own, links = None, {}, []

        def done():
            if links:
                a, b = (np.concatenate(x) for x in zip(*links))
                c, na, nb = _shared(own, a, b)
                to = 100 * c >= percent * (na + nb - c)
                yield pa.RecordBatch.from_arrays([pa.array(x[to]) for x in (a, b, c, na, nb)], names=["a", "b", "c", "na", "nb"])

        for x in batches:
            tile, a = x.column(0).to_numpy(), x.column(1).to_numpy()
            b, alone = x.column(2).fill_null(0).to_numpy(), x.column(2).is_null().to_numpy(zero_copy_only=False)
            cuts = np.append(np.flatnonzero(np.append(True, tile[1:] != tile[:-1])), len(tile)).tolist()
            for i, j in zip(cuts[:-1], cuts[1:]):
                if tile[i] != now:
                    yield from done()
                    now, own, links = tile[i], {}, []
                k = i + int(alone[i:j].sum())
                for at in range(i, k):
                    own[int(a[at])] = x.column(3)[at].values.to_numpy()
                if k < j:
                    links.append((a[k:j], b[k:j]))
        yield from done()

    parts = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    together = sent.unionByName(asked).repartition(parts, "tile").sortWithinPartitions("tile", F.col("b").asc_nulls_first())
    found = together.mapInArrow(run, "a bigint, b bigint, c bigint, na bigint, nb bigint")
    return found.select(F.col("a").cast(kind).alias("a"), F.col("b").cast(kind).alias("b"), "c", "na", "nb")


def components(links: DataFrame) -> DataFrame:
    """(id, component): the smallest id reachable from every id in links (a, b).

    Each round points every neighbour of a node, then every smaller neighbour, at the least of them, and
    lands the edges; rounds follow the logarithm of the longest path.
    """
    edges = cut_lineage(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    state = None
    while True:
        around = edges.union(edges.select("b", "a"))
        least = around.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        edges = around.join(least, "a").where("b > a and b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        least = edges.groupBy("a").agg(F.min("b").alias("m"))
        turned = edges.join(least, "a").select(F.explode(F.array(F.struct(F.col("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.*")
        edges = cut_lineage(turned.where("a <> b").distinct())
        now = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if now == state:
            break
        state = now
    return edges.select(F.col("a").alias("id"), F.col("b").alias("component")).union(edges.select("b", "b").distinct())


def near_components(df: DataFrame, percent: int = 75, n: int = 5, small: int = SMALL) -> DataFrame:
    """doc_id, component of every document with words: the smallest document that near copies of one language lead to."""
    sets = cut_lineage(shingle_sets(df, n).withColumn("digest", F.md5(F.concat_ws(",", "lang", F.col("h").cast("array<string>")))))
    copies = sets.groupBy("digest").agg(F.min("doc_id").alias("id"))
    reps = cut_lineage(sets.join(copies, "digest").where("doc_id = id").select("id", "lang", "h").dropDuplicates(["id"]))
    bands = cut_lineage(band_rows(reps))
    crowded = bands.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    members = cut_lineage(bands.join(crowded, "key"))
    listed = members.where(F.col("n") <= small).groupBy("key").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    few = listed.select(F.posexplode("ids").alias("i", "b"), "ids").select(F.explode(F.slice("ids", F.lit(1), F.col("i"))).alias("a"), "b")
    large = members.where(F.col("n") > small)
    salts = F.ceil(F.col("n") / STAR).cast("int")
    heads = large.groupBy("key", "n").agg(F.min("id").alias("a")).select("key", "a", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
    star = large.select("key", F.col("id").alias("b"), F.pmod(F.xxhash64("id"), salts).cast("int").alias("salt")).join(heads, ["key", "salt"]).where("a <> b").select("a", "b")
    links = cut_lineage(checked(few.union(star).distinct(), reps, percent).select("a", "b"))
    label = components(links)
    if large.take(1):
        inside = large.select("key", "id").join(label, "id", "left").withColumn("component", F.coalesce("component", "id"))
        sizes = inside.groupBy("key", "component").agg(F.count(F.lit(1)).alias("m"))
        main = sizes.groupBy("key").agg(F.max_by("component", F.struct("m", "component")).alias("main"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
        inside = inside.join(main.select("key", "main"), "key")
        outside = inside.where("component <> main").select("key", F.col("id").alias("x"), F.col("component").alias("cx"))
        met = outside.join(inside.select("key", "id", "component"), "key").where("cx <> component")
        more = checked(met.select(F.least("x", "id").alias("a"), F.greatest("x", "id").alias("b")).distinct(), reps, percent).select("a", "b")
        label = components(links.union(more))
    found = sets.select("doc_id", "digest").join(copies, "digest").join(label, "id", "left")
    return found.select("doc_id", F.coalesce("component", "id").alias("component"))


def dedup_near(df: DataFrame, percent: int = 75, n: int = 5) -> DataFrame:
    """df without documents that a smaller one leads to; texts without words stay."""
    gone = near_components(df, percent, n).where("doc_id <> component").select("doc_id")
    return df.join(gone, "doc_id", "left_anti")
