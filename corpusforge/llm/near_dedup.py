"""MinHash near-dedup with SetSketch registers, verified on full sets.

1. Each document's set of distinct 5-word shingles is hashed; m minima of m hash functions are kept
   on an exponential scale: register = floor(1 - log_b(minimum)), truncated at the 32-bit end. Such
   registers merge by maximum and equal each other about as often as sets overlap.
2. Documents with equal sets (128-bit digest) become one representative, so copies cost nothing more.
3. Bands of registers are hashed. Small buckets pair all members. In large buckets every member meets
   the bucket's leaders only (a star; buckets of many members are salted by their size), and what stays
   unconnected is settled in step 6.
4. For each pair the joint likelihood of the register order counts and both set sizes gives the most
   likely Jaccard similarity; pairs are dropped only where a similarity at the threshold is excluded
   by a log-likelihood gap of `doubt`.
5. The rest is verified on full sets. Verified links give components (large-star / small-star).
6. Large buckets that still hold several components: their members are compared exactly, in tiles of
   bounded members and bytes, straggler against member, and new links merge components. No cap, no
   sampling: a bucket of n documents that resemble each other without being linked costs n^2 comparisons
   of registers, spread over its tiles, and their texts are copied once a tile.

With 44 bands of 4, a pair at similarity 0.75 shares no band with probability 6e-8, one at 0.8 with 1e-10.
Of 24,000 simulated pairs between 0.75 and 0.80, step 4 dropped none (test_doubt_keeps_pairs).

Edge cases: null, empty and blank texts have an empty set, are linked with nothing and are kept;
fewer than five words are one shingle; a null doc_id can't name a component and is left out of
linking (component null, kept); repeated rows with one id form one document's component; very long
texts are read whole, a batch at a time; ties between equal sets go to the smallest id; empty tables
give no rows; further columns don't matter to `near_duplicates` and pass `drop_near_duplicates`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import gram_hashes, landed, mixed, word_hashes

SHINGLE, BANDS, ROWS = 5, 44, 4
BASE = 1.001
LARGE = 32  # members from which a bucket uses leaders
TILE, TILE_BYTES = 2048, 16 << 20  # most members and about most bytes of text on one side of a tile
STAR = 2048  # members of a bucket that one task of a star takes
LEADERS = 3
_LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
_M32 = np.array([(0x9E3779B1 * (2 * i + 1) ** 3 + 0x85EBCA77 * i) % 2**32 | 1 for i in range(BANDS * ROWS)], np.uint32)
_BAND = np.array([(0xC2B2AE3D27D4EB4F * (2 * i + 1) ** 3) % 2**64 for i in range(BANDS)], np.uint64)


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the 5-word shingles of a text, A-Z lower-cased."""
    words = text.encode("utf-8", "surrogatepass").translate(_LOWER).split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    h = word_hashes(words)
    return np.unique(gram_hashes(h, min(SHINGLE, len(h))))


def registers(shingles: np.ndarray) -> np.ndarray:
    """Exponentially spaced truncated minima of one set, as 16-bit numbers."""
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    low = np.full(len(_M32), 0xFFFFFFFF, np.uint32)
    for at in range(0, len(x), 256):
        part = x[at : at + 256, None] * _M32
        part ^= part >> np.uint32(15)
        part *= np.uint32(0x2C1B3C6D)
        np.minimum(low, part.min(0), out=low)
    return np.floor(1 - np.log((low.astype(np.float64) + 1) / 2**32) / np.log(BASE)).astype(np.uint16)


def merge_registers(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union."""
    return np.maximum(a, b)


def band_keys(regs: np.ndarray) -> np.ndarray:
    """One 64-bit key per row of registers and band."""
    r = regs.reshape(-1, BANDS, ROWS).astype(np.uint64)
    key = np.broadcast_to(_BAND, r.shape[:2]).copy()
    for i in range(ROWS):
        key = mixed(key + r[:, :, i] * np.uint64(0x9E3779B97F4A7C15))
    return key


def likely_similarity(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray, at: float) -> tuple[np.ndarray, np.ndarray]:
    """Most likely Jaccard similarity for rows of registers, and how far `at` or more lies below it in log-likelihood."""
    more, less = (a > b).sum(1).astype(float), (a < b).sum(1).astype(float)
    same = a.shape[1] - more - less
    u, v = na / (na + nb), nb / (na + nb)
    grid = np.linspace(0, 1, 101)[None, :]
    most = np.minimum(u / v, v / u)[:, None]
    log_b, c = np.log(BASE), (BASE - 1) / BASE
    p = lambda x: -np.log1p(-c * np.clip(x, 0, 1)) / log_b

    def value(j: np.ndarray) -> np.ndarray:
        j = np.minimum(j, most)
        up, down = p(u[:, None] - v[:, None] * j), p(v[:, None] - u[:, None] * j)
        tiny = 1e-6
        return more[:, None] * np.log(np.maximum(up, tiny)) + less[:, None] * np.log(np.maximum(down, tiny)) + same[:, None] * np.log(np.maximum(1 - up - down, tiny))

    ll = value(grid)
    best = ll.argmax(1)
    high = value(np.linspace(at, 1, 26)[None, :]).max(1)
    gap = np.where(most[:, 0] < at, np.inf, ll.max(1) - high)
    return np.minimum(grid[0][best], most[:, 0]), gap


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """100 * intersection >= percent * union, on sorted distinct hashes."""
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


SKETCH = "doc_id long, n_shingles long, d1 long, d2 long, regs binary"


def sketch(docs: DataFrame) -> DataFrame:
    """doc_id, set size, 128-bit digest of the set and registers of every document."""
    import hashlib

    names = [f.split()[0] for f in SKETCH.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            n, d, regs = [], [], []
            for t in b.column(1):
                s = shingle_set(t.as_py())
                n.append(len(s))
                d.append(np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), "<i8"))
                regs.append(registers(s).tobytes() if len(s) else None)
            d = np.array(d, np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(d[:, 0]), pa.array(d[:, 1]), pa.array(regs, pa.binary())], names=names)

    return docs.select("doc_id", "text").mapInArrow(run, SKETCH)


def _bands(reps: DataFrame) -> DataFrame:
    """(key, id) for every band of every representative."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                regs = np.frombuffer(b"".join(b.column(1).to_pylist()), np.uint16)
                keys = band_keys(regs)
                yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().view(np.int64)), pa.array(np.repeat(b.column(0).to_numpy(), BANDS))], names=["key", "id"])

    return reps.select("doc_id", "regs").mapInArrow(run, "key long, id long")


def likely_pairs(pairs: DataFrame, sketches: DataFrame, percent: int, doubt: float) -> DataFrame:
    """Pairs (a, b) whose similarity may reach the threshold, by joint likelihood of their registers."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            ra, rb = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint16).reshape(b.num_rows, -1) for c in ("ra", "rb"))
            na, nb = (b.column(c).to_numpy().astype(float) for c in ("na", "nb"))
            _, gap = likely_similarity(ra, rb, na, nb, percent / 100)
            keep = pa.array(gap <= doubt)
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], names=["a", "b"])

    s = sketches.select("doc_id", "n_shingles", "regs")
    both = pairs.join(s.toDF("a", "na", "ra"), "a").join(s.toDF("b", "nb", "rb"), "b")
    fits = (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    return both.where(fits).select("a", "b", "na", "nb", "ra", "rb").mapInArrow(run, "a long, b long")


class Sets:
    """Shingle sets of texts, the latest ones kept."""

    def __init__(self, keep: int = 64):
        self.keep, self.known = keep, {}

    def of(self, key: int, text: str) -> np.ndarray:
        got = self.known.get(key)
        if got is None:
            if len(self.known) >= self.keep:
                self.known.pop(next(iter(self.known)))
            got = self.known[key] = shingle_set(text)
        return got


def verified_links(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Pairs that reach the threshold on their full sets; texts: id, text of every document in pairs."""

    def run(batches):
        sets = Sets()
        for b in batches:
            rows = zip(*(b.column(c).to_pylist() for c in ("a", "b", "ta", "tb")))
            keep = pa.array([linked(sets.of(i, x), sets.of(j, y), percent) for i, j, x, y in rows], pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], names=["a", "b"])

    both = pairs.join(texts.toDF("a", "ta"), "a").join(texts.toDF("b", "tb"), "b")
    return both.select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """(id, component): smallest id reachable, for every id in links. Alternates large and small stars.

    Each round lands its links in the shared folder; the number of rounds grows with the logarithm
    of the longest path.
    """
    edges = landed(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links")
    state = None
    while True:
        both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.explode(F.array(F.struct("b", "m"), F.struct(F.col("a").alias("b"), F.col("m")))).alias("x"))
        edges = landed(small.select(F.col("x.b").alias("a"), F.col("x.m").alias("b")).where("a <> b").distinct(), "links")
        now = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if now == state:
            break
        state = now
    return edges.select(F.col("a").alias("id"), F.col("b").alias("component")).union(edges.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())


def _settle(members: DataFrame, texts: DataFrame, sketches: DataFrame, percent: int, doubt: float) -> DataFrame:
    """Links between members (key, id, component) of a bucket that are of different components.

    The bucket's largest component need not be compared with itself; stragglers meet everyone, in
    tiles of TILE x TILE members. A pair is compared in the first band that it shares only.
    """
    sizes = members.groupBy("key", "component").agg(F.count(F.lit(1)).alias("n"))
    main = sizes.groupBy("key").agg(F.max_by("component", "n").alias("main"), F.sum("n").alias("total"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
    m = landed(members.join(main.select("key", "main", "total"), "key").withColumn("straggler", F.col("component") != F.col("main")), "open")
    size = texts.select("id", F.octet_length("text").alias("size"))
    weight = m.join(size, "id").groupBy("key").agg(F.greatest(F.ceil(F.max("total") / TILE), F.ceil(F.sum("size") / TILE_BYTES)).cast("int").alias("tiles"))
    full = texts.join(sketches.select(F.col("doc_id").alias("id"), "regs"), "id")
    m = m.join(weight, "key").withColumn("tile", F.pmod(F.xxhash64("id"), F.col("tiles")).cast("int")).join(full, "id")
    # Tile (i, j): stragglers of part i against members of part j.
    left = m.where("straggler").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))).select("key", F.col("tile").alias("i"), F.col("other").alias("j"), "id", "component", "straggler", "text", "regs")
    # Renamed, so that the two sides of the self-join can be told apart.
    right = m.toDF(*[f"r_{c}" for c in m.columns]).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("r_tiles") - 1)))
    right = right.select(F.col("r_key").alias("key"), F.col("other").alias("i"), F.col("r_tile").alias("j"), *[F.col(f"r_{c}").alias(c) for c in ("id", "component", "straggler", "text", "regs")])

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = [], []
        if left.num_rows and right.num_rows:
            key = np.uint64(left.column("key")[0].as_py() % 2**64)
            lr, rr = (np.frombuffer(b"".join(t.column("regs").to_pylist()), np.uint16).reshape(t.num_rows, -1) for t in (left, right))
            lk, rk = band_keys(lr), band_keys(rr)
            band = int(np.nonzero(lk[0] == key)[0][0])
            ls, rs = ([shingle_set(x) for x in t.column("text").to_pylist()] for t in (left, right))
            li, ri, lc, rc = (x.to_numpy() for x in (left.column("id"), right.column("id"), left.column("component"), right.column("component")))
            r_straggler = right.column("straggler").to_numpy(zero_copy_only=False)
            sizes = np.array([len(x) for x in rs], float)
            root: dict[int, int] = {}

            def find(x: int) -> int:
                while root.get(x, x) != x:
                    x = root[x]
                return x

            for i in range(len(li)):
                # Two stragglers meet once, from the larger id.
                there = (rc != lc[i]) & (~r_straggler | (ri < li[i]))
                there &= ~(rk[:, :band] == lk[i, :band]).any(1)
                there = np.nonzero(there)[0]
                if not len(there):
                    continue
                near, gap = likely_similarity(np.broadcast_to(lr[i], (len(there), lr.shape[1])), rr[there], np.full(len(there), float(len(ls[i]))), sizes[there], percent / 100)
                order = np.argsort(-near, kind="stable")
                for j in there[order[gap[order] <= doubt]]:
                    x, y = find(int(lc[i])), find(int(rc[j]))
                    if x != y and linked(ls[i], rs[j], percent):
                        root[max(x, y)] = min(x, y)
                        a.append(int(li[i]))
                        b.append(int(ri[j]))
        return pa.Table.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return left.groupBy("key", "i", "j").cogroup(right.groupBy("key", "i", "j")).applyInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, *, text: str = "text", key: str = "doc_id", percent: int = 75, doubt: float = 18.0) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs."""
    docs = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    sketches = landed(sketch(docs), "sketches")
    copies = sketches.where("n_shingles > 0 and doc_id is not null").groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"))
    reps = landed(sketches.join(copies.select(F.col("rep").alias("doc_id"), "d1", "d2"), ["doc_id", "d1", "d2"], "left_semi").dropDuplicates(["doc_id"]), "reps")
    bands = _bands(reps)
    crowded = bands.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    members = landed(bands.join(crowded, "key"), "members")
    # Small buckets: every two members, by bucket.
    listed = members.where(F.col("n") <= LARGE).groupBy("key").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    small_pairs = listed.select(F.posexplode("ids").alias("i", "b"), "ids").select(F.explode(F.slice("ids", F.lit(1), F.col("i"))).alias("a"), "b")
    large = members.where(F.col("n") > LARGE).select("key", "id", "n")
    first = [F.min(F.struct(F.xxhash64("id", F.lit(i)).alias("o"), "id")).getField("id") for i in range(LEADERS)]
    leaders = large.groupBy("key", "n").agg(F.array(*first).alias("leaders"))
    salts = F.ceil(F.col("n") / STAR).cast("int")
    leaders = leaders.select("key", "leaders", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
    large = large.select("key", "id", F.pmod(F.xxhash64("id"), salts).cast("int").alias("salt"))
    star = large.join(leaders, ["key", "salt"]).select(F.explode("leaders").alias("l"), "id").where("l <> id").select(F.least("l", "id").alias("a"), F.greatest("l", "id").alias("b"))
    pairs = small_pairs.union(star).where("a <> b").distinct()
    likely = landed(likely_pairs(pairs, reps, percent, doubt), "likely")
    asked = likely.select(F.explode(F.array("a", "b")).alias("doc_id")).union(large.select("id")).distinct()
    texts = landed(docs.join(asked, "doc_id", "left_semi").select(F.col("doc_id").alias("id"), "text").dropDuplicates(["id"]), "texts")
    links = landed(verified_links(likely, texts, percent), "verified")
    label = landed(components(links), "components")
    open_members = landed(large.join(label, "id", "left").select("key", "id", F.coalesce("component", "id").alias("component")), "members")
    more = landed(_settle(open_members, texts, reps, percent, doubt), "settled")
    if more.take(1):
        label = landed(components(links.union(more)), "components")
    # Documents that share a set follow their representative.
    rep_label = copies.join(label, copies["rep"] == label["id"], "left").select("d1", "d2", F.coalesce("component", "rep").alias("component_id"))
    empty = (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
    full = sketches.select("doc_id", "n_shingles", "d1", "d2").where(~empty).join(rep_label, ["d1", "d2"]).select("doc_id", "n_shingles", "component_id")
    out = full.union(sketches.where(empty).select("doc_id", "n_shingles", F.col("doc_id").alias("component_id")))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """docs without the documents that aren't the first of their component; of repeats of one id, all stay."""
    gone = near_duplicates(docs, **options).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


__all__ = ["components", "drop_near_duplicates", "likely_similarity", "merge_registers", "near_duplicates", "registers", "shingle_set"]
