"""Substring dedup with FM-indexes: passages that already stand in an earlier document are cut out.

Every 13-word window is assigned an anchor, the smallest hash of its 4-word grams. Equal windows
have equal anchors wherever they stand, so each anchor can be treated by itself:

1. Documents are hashed into blocks. Each block reports its distinct anchors, about how often it has
   each and whether a second document of the block has it, packed by anchor shard (one row per block
   and shard).
2. An anchor shard answers every block with those anchors that two documents hold somewhere, and says
   which of them are crowded (more than CROWDED places).
3. Each block cuts, for those anchors only, the runs of windows that share the anchor (segments),
   keeps distinct segments with their smallest document, and sends them to the segment shards. Under a
   crowded anchor every window is a segment of its own and goes by its own hash: a frequent phrase in
   ever new surroundings is spread over all shards instead of filling one.
4. A segment shard builds a compressed FM-index of its distinct segments (Burrows-Wheeler transform in
   a wavelet matrix of packed bits with block ranks; of the suffix order only samples stay) and streams
   them through a backward search. Matching statistics (how long the longest match is that ends at a
   word and occurs again) of at least 13 words report an interval of equal windows; its places are
   located from the samples, and give the smallest document. Windows whose smallest document isn't
   the segment's own smallest, or that later documents may repeat, are answered to the blocks.
5. Each block marks windows whose first document is earlier, and rewrites its documents.

Everything sent is combined per block first: a passage in a third of all documents costs each block
one entry, so no task holds more than its share. Rows that repeat both id and text are worked on once
and counted. Nothing goes to the driver but the text's size and whether there are such rows.

Edge cases: null and empty texts have no words; texts under 13 words lose nothing; very long texts are
held whole, one at a time; a null doc_id is later than any other and removes nothing from others; rows
with equal doc_id don't cut each other (so ties between first documents can't matter); repeated rows
come back as often as they occur; an empty table gives no rows; further columns, whatever their names,
pass `cut_repeats` untouched (n_chars follows).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import block_count, gram_hashes, sliding_min, text_words, word_hashes

WINDOW, GRAM = 13, 4
LATEST = np.iinfo(np.int64).max
#: Places from which an anchor's windows are dealt by their own hashes.
CROWDED = 2048
#: Distance of the text positions whose place in the suffix order is kept.
SAMPLE = 8


class Bits:
    """A packed bit row with the ones before each 64-bit word."""

    def __init__(self, bit: np.ndarray):
        padded = np.zeros((len(bit) // 64 + 1) * 64, bool)
        padded[: len(bit)] = bit
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)])

    def ones(self, at: np.ndarray) -> np.ndarray:
        """Ones before each position."""
        word, bit = at >> 6, (at & 63).astype(np.uint64)
        return self.before[word] + np.bitwise_count(self.words[word] & ((np.uint64(1) << bit) - np.uint64(1)))

    def get(self, at: np.ndarray) -> np.ndarray:
        return (self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1


class WaveletMatrix:
    """Rank over symbols: one packed bit row per level."""

    def __init__(self, symbols: np.ndarray, sigma: int):
        self.n, self.levels = len(symbols), max(1, int(sigma - 1).bit_length())
        self.bits, self.zeros = [], []
        x = symbols.astype(np.uint32)
        for level in range(self.levels - 1, -1, -1):
            bit = ((x >> np.uint32(level)) & np.uint32(1)).astype(bool)
            self.bits.append(Bits(bit))
            self.zeros.append(self.n - int(bit.sum()))
            x = np.concatenate([x[~bit], x[bit]])

        # Where each symbol's run begins in the last level's order.
        every, at = np.arange(sigma), np.zeros(sigma, np.int64)
        for level in range(self.levels):
            at = self._down(level, (every >> (self.levels - 1 - level)) & 1 == 1, at)
        self.start = at

    def _down(self, level: int, bit: np.ndarray, at: np.ndarray) -> np.ndarray:
        one = self.bits[level].ones(at)
        return np.where(bit, self.zeros[level] + one, at - one)

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol before each position."""
        for level in range(self.levels):
            at = self._down(level, (symbol >> (self.levels - 1 - level)) & 1 == 1, at)
        return at - self.start[symbol]

    def read(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each position and its occurrences before."""
        symbol = np.zeros(len(at), np.int64)
        for level in range(self.levels):
            bit = self.bits[level].get(at)
            symbol = 2 * symbol + bit
            at = self._down(level, bit, at)
        return symbol, at - self.start[symbol]


class FMIndex:
    """Backward search over a text of symbols (0 ends each segment; ends are told apart by position)."""

    def __init__(self, text: np.ndarray, sigma: int, sample: int = SAMPLE):
        n, end = len(text), text == 0
        ends = int(end.sum())
        rank = text.astype(np.int64) + ends
        rank[end] = np.arange(ends)
        base, have = max(n, sigma + ends) + 2, 1

        def ahead(by: int) -> np.ndarray:
            """The rank `by` positions on; past the end counts as lowest."""
            out = np.zeros(n, np.int64)
            out[: max(0, n - by)] = rank[by:] + 1
            return out

        while True:
            # Prefix doubling: positions ordered by 2 * have symbols; three symbols at once to begin with, where they fit.
            three = have == 1 and base**3 < 1 << 62
            key = rank * base + ahead(have)
            if three:
                key = key * base + ahead(2)
            order = np.argsort(key)
            step = np.diff(key[order]) != 0
            rank = np.empty(n, np.int64)
            rank[order] = np.concatenate([[0], np.cumsum(step)])
            have *= 3 if three else 2
            if step.all():
                break
        self.bwt = WaveletMatrix(text[(order - 1) % n], sigma)
        self.first = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=sigma))])
        # Every segment's first position is kept, so that no walk back leaves its segment.
        begins = np.concatenate([[True], end[:-1]])
        kept = (order % sample == 0) | begins[order]
        self.kept, self.places = Bits(kept), order[kept].astype(np.uint32)

    def matching_statistics(self, text: np.ndarray, ends: np.ndarray, threshold: int, most: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each end: the length of the longest match that ends there and occurs more than once, and the interval
        of its last `threshold` symbols where it has that many (else empty).

        Patterns step back together; one whose interval has a single suffix left, or that meets a segment's
        begin, is settled. Lengths beyond `most` (the threshold, if not given) aren't told apart.
        """
        length, lo, hi = (np.zeros(len(ends), np.int64) for _ in range(3))
        a, b, live = np.zeros(len(ends), np.int64), np.full(len(ends), self.bwt.n, np.int64), np.arange(len(ends))
        for back in range(1, max(threshold, most or 0) + 1):
            live = live[ends[live] >= back]
            c = text[ends[live] - back].astype(np.int64)
            live, c = live[c > 0], c[c > 0]
            if not len(live):
                break
            at = self.first[c] + self.bwt.rank(c, np.concatenate([a[live], b[live]]).reshape(2, -1))
            again = at[1] - at[0] > 1
            live = live[again]
            a[live], b[live], length[live] = at[0][again], at[1][again], back
            if back == threshold:
                lo[live], hi[live] = a[live], b[live]
        return length, lo, hi

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of rows of the suffix order: steps back until a kept one."""
        out, rows, live, steps = np.zeros(len(rows), np.int64), rows.copy(), np.arange(len(rows)), 0
        while len(live):
            at = rows[live]
            here = self.kept.get(at)
            out[live[here]] = self.places[self.kept.ones(at[here])] + np.int64(steps)
            live = live[~here]
            c, before = self.bwt.read(at[~here])
            rows[live] = self.first[c] + before
            steps += 1
        return out


def window_anchors(words: list[bytes]) -> np.ndarray:
    """The anchor of each 13-word window."""
    return sliding_min(gram_hashes(word_hashes(words), GRAM), WINDOW - GRAM + 1)


def anchor_runs(anchors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last window of each run of windows with one anchor."""
    cut = np.nonzero(anchors[1:] != anchors[:-1])[0]
    return np.concatenate([[0], cut + 1]), np.concatenate([cut, [len(anchors) - 1]])


def first_documents(segments: list[bytes], docs: np.ndarray) -> list[np.ndarray]:
    """Per distinct segment, for each of its 13-word windows, the smallest document that holds the window.

    docs: each segment's smallest document. One FM-index of all segments; each is streamed through it.
    """
    words = [s.split(b" ") for s in segments]
    sizes = np.array([len(w) + 1 for w in words])
    known: dict[bytes, int] = {}
    text = np.array([known.setdefault(x, len(known) + 1) for w in words for x in [*w, b""]], np.int64)
    ends = np.cumsum(sizes) - 1
    text[ends] = 0
    index = FMIndex(text, len(known) + 1)
    counts = sizes - WINDOW  # windows of each segment
    at = np.repeat(ends - counts + 1, counts) + np.arange(int(counts.sum())) - np.repeat(np.cumsum(counts) - counts, counts)
    length, lo, hi = index.matching_statistics(text, at, WINDOW)
    # A window that occurs once belongs to its own segment; others take the smallest owner of their interval.
    low = np.repeat(docs, counts)
    many = np.nonzero(length >= WINDOW)[0]
    if len(many):
        # Intervals of one length are equal or apart: every row is located once.
        begin, which = np.unique(lo[many], return_inverse=True)
        span = np.zeros(len(begin), np.int64)
        span[which] = hi[many] - lo[many]
        heads = np.cumsum(span) - span
        rows = np.repeat(begin - heads, span) + np.arange(int(span.sum()))
        owner = docs[np.searchsorted(ends, index.locate(rows))]
        low[many] = np.minimum.reduceat(owner, heads)[which]
    return np.split(low, np.cumsum(counts)[:-1])


def _with_blocks(docs: DataFrame, text: str, key: str, blocks: int) -> DataFrame:
    """doc_id, text, text_hash, block, and how often the row stands in docs."""
    rows = docs.select(F.col(f"`{key}`").cast("long").alias("doc_id"), F.col(f"`{text}`").cast("string").alias("text"))
    rows = rows.withColumn("text_hash", F.xxhash64("text"))
    # Repeated rows would all meet in one block: they become one row. Most tables have none.
    repeated = rows.groupBy("doc_id", "text_hash").agg(F.count(F.lit(1)).alias("times")).where("times > 1")
    if repeated.take(1):
        names = repeated.select(F.col("doc_id").alias("r_id"), F.col("text_hash").alias("r_hash"))
        same = rows["doc_id"].eqNullSafe(names["r_id"]) & (rows["text_hash"] == names["r_hash"])
        once = rows.join(names, same, "left_semi").groupBy("doc_id", "text_hash").agg(F.first("text").alias("text"), F.count(F.lit(1)).alias("times"))
        rows = rows.join(names, same, "left_anti").withColumn("times", F.lit(1).cast("long")).unionByName(once)
    else:
        rows = rows.withColumn("times", F.lit(1).cast("long"))
    return rows.withColumn("block", F.pmod(F.xxhash64("doc_id", "text_hash"), F.lit(blocks)).cast("int"))


def _order(ids: pa.ChunkedArray) -> np.ndarray:
    return ids.fill_null(LATEST).to_numpy()


def _shared_anchors(rows: DataFrame, shards: int) -> DataFrame:
    """(block, anchors, crowded): for each block those of its anchors that two documents hold, and the crowded ones, packed."""

    def report(block: pa.Table) -> pa.Table:
        ids, found, owners = _order(block.column("doc_id")), [], []
        for d, t in zip(ids.tolist(), block.column("text")):
            a = window_anchors(text_words(t.as_py()))
            a = a[anchor_runs(a)[0]] if len(a) else a
            found.append(a)
            owners.append(np.full(len(a), d, np.int64))
        a, o = np.concatenate(found), np.concatenate(owners)
        if not len(a):
            return pa.Table.from_arrays([pa.array([], k) for k in (pa.int32(), pa.int32(), pa.binary(), pa.binary())], names=["shard", "block", "anchors", "marks"])
        # Rows that share an id count as one document; the null id's rows as several.
        order = np.lexsort((o, a))
        a, o = a[order], o[order]
        start = np.concatenate([[True], a[1:] != a[:-1]])
        differs = np.concatenate([[False], (a[1:] == a[:-1]) & ((o[1:] != o[:-1]) | (o[1:] == LATEST))])
        heads = np.nonzero(start)[0]
        # One byte an anchor: whether several documents have it, and how often, up to 127.
        times = np.minimum(np.diff(np.concatenate([heads, [len(a)]])), 127)
        marks = (np.logical_or.reduceat(differs, heads) | (times << 1)).astype(np.uint8)
        a = a[heads]
        shard = (a % np.uint64(shards)).astype(np.int32)
        order = np.argsort(shard, kind="stable")
        a, marks, shard = a[order], marks[order], shard[order]
        at = np.concatenate([[0], np.nonzero(np.diff(shard))[0] + 1, [len(a)]])
        pieces = list(zip(at[:-1].tolist(), at[1:].tolist()))
        me = block.column("block")[0].as_py()
        return pa.Table.from_arrays([pa.array(shard[at[:-1]]), pa.array([me] * len(pieces), pa.int32()), pa.array([a[x:y].tobytes() for x, y in pieces], pa.binary()), pa.array([marks[x:y].tobytes() for x, y in pieces], pa.binary())], names=["shard", "block", "anchors", "marks"])

    def answer(shard: pa.Table) -> pa.Table:
        parts = [np.frombuffer(x.as_py(), np.uint64) for x in shard.column("anchors")]
        marks = np.concatenate([np.frombuffer(x.as_py(), np.uint8) for x in shard.column("marks")])
        where = np.repeat(np.arange(len(parts)), [len(p) for p in parts])
        a = np.concatenate(parts)
        order = np.argsort(a, kind="stable")
        a, marks, where = a[order], marks[order], where[order]
        heads = np.nonzero(np.concatenate([[True], a[1:] != a[:-1]]))[0]
        sizes = np.diff(np.concatenate([heads, [len(a)]]))
        shared = np.repeat((sizes > 1) | np.logical_or.reduceat(marks & 1 == 1, heads), sizes)
        crowded = np.repeat(np.add.reduceat((marks >> 1).astype(np.int64), heads) > CROWDED, sizes)
        a, where, crowded = a[shared], where[shared], crowded[shared]
        order = np.argsort(where, kind="stable")
        a, where, crowded = a[order], where[order], crowded[order]
        at = np.concatenate([[0], np.nonzero(np.diff(where))[0] + 1, [len(a)]]) if len(a) else np.array([0])
        blocks = shard.column("block").to_numpy()
        packed = [[a[x:y][pick[x:y]].tobytes() for x, y in zip(at[:-1], at[1:])] for pick in (np.ones(len(a), bool), crowded)]
        return pa.Table.from_arrays([pa.array(blocks[where[at[:-1]]] if len(a) else np.empty(0, np.int32), pa.int32()), *[pa.array(p, pa.binary()) for p in packed]], names=["block", "anchors", "crowded"])

    sent = rows.groupBy("block").applyInArrow(report, "shard int, block int, anchors binary, marks binary")
    return sent.groupBy("shard").applyInArrow(answer, "block int, anchors binary, crowded binary")


def _unpacked(column: pa.ChunkedArray) -> np.ndarray:
    return np.unique(np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in column])) if len(column) else np.empty(0, np.uint64)


def _among(known: np.ndarray, x: np.ndarray) -> np.ndarray:
    if not len(known):
        return np.zeros(len(x), bool)
    return known[np.minimum(np.searchsorted(known, x), len(known) - 1)] == x


def _block_segments(block: pa.Table, anchors: pa.Table):
    """Yields (row, words, [(first window, key, segment)]) of each row with shared anchors."""
    shared, crowded = _unpacked(anchors.column("anchors")), _unpacked(anchors.column("crowded"))
    for i, t in enumerate(block.column("text")):
        words, segments = text_words(t.as_py()), []
        if len(words) >= WINDOW and len(shared):
            hashes = word_hashes(words)
            a = sliding_min(gram_hashes(hashes, GRAM), WINDOW - GRAM + 1)
            first, last = anchor_runs(a)
            hit = _among(shared, a[first])
            first, last = first[hit], last[hit]
            full = _among(crowded, a[first])
            segments = [(x, h, b" ".join(words[x : y + WINDOW])) for x, y, h in zip(first[~full].tolist(), last[~full].tolist(), a[first[~full]].tolist())]
            if full.any():
                own = gram_hashes(hashes, WINDOW)
                segments += [(w, int(own[w]), b" ".join(words[w : w + WINDOW])) for x, y in zip(first[full].tolist(), last[full].tolist()) for w in range(x, y + 1)]
        yield i, words, segments


def _name(segment: bytes) -> bytes:
    return hashlib.blake2b(segment, digest_size=16).digest()


def repeated_windows(docs: DataFrame, text: str, key: str, blocks: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows with their block, the anchors of each block, and the answers for its segments."""
    rows = _with_blocks(docs, text, key, blocks)
    anchors = _shared_anchors(rows, max(64, blocks // 4))

    def send(block: pa.Table, anchors: pa.Table) -> pa.Table:
        ids = _order(block.column("doc_id")).tolist() if block.num_rows else []
        held: dict[bytes, list] = {}
        for i, _, segments in _block_segments(block, anchors) if block.num_rows else ():
            for _, anchor, s in segments:
                got = held.get(s)
                if got is None:
                    held[s] = [anchor, ids[i], ids[i]]
                else:
                    got[1], got[2] = min(got[1], ids[i]), max(got[2], ids[i])
        me = block.column("block")[0].as_py() if block.num_rows else 0
        return pa.Table.from_arrays([pa.array([v[0] % blocks for v in held.values()], pa.int32()), pa.array([me] * len(held), pa.int32()), pa.array(list(held), pa.binary()), pa.array([v[1] for v in held.values()], pa.int64()), pa.array([v[2] for v in held.values()], pa.int64())], names=["shard", "block", "segment", "low", "high"])

    def match(shard: pa.Table) -> pa.Table:
        segments, at = shard.column("segment").to_pylist(), {}
        where = np.array([at.setdefault(s, len(at)) for s in segments])
        low = np.full(len(at), LATEST, np.int64)
        np.minimum.at(low, where, shard.column("low").to_numpy())
        first = first_documents(list(at), low)
        # An answer is of use to a block that has a document later than some window's first.
        least = np.array([f.min() for f in first])
        use = np.nonzero(least[where] < shard.column("high").to_numpy())[0]
        names = [_name(segments[i]) for i in use]
        return pa.Table.from_arrays([shard.column("block").combine_chunks().take(pa.array(use)), pa.array(names, pa.binary()), pa.array([first[where[i]].tobytes() for i in use], pa.binary())], names=["block", "name", "first"])

    by_block = rows.groupBy("block").cogroup(anchors.groupBy("block"))
    sent = by_block.applyInArrow(send, "shard int, block int, segment binary, low long, high long")
    answers = sent.groupBy("shard").applyInArrow(match, "block int, name binary, first binary")
    return rows, anchors, answers


def _kept_words(words: list[bytes], d: int, segments: list, answers: dict[bytes, np.ndarray]) -> list[bytes]:
    gone = np.zeros(len(words) + 1, np.int64)
    for x, _, s in segments:
        first = answers.get(_name(s))
        if first is not None:
            for w in np.nonzero(first < d)[0].tolist():
                gone[x + w] += 1
                gone[x + w + WINDOW] -= 1
    keep = np.cumsum(gone)[: len(words)] == 0
    return [w for w, k in zip(words, keep.tolist()) if k] if not keep.all() else words


def deduplicated(docs: DataFrame, *, text: str = "text", key: str = "doc_id", blocks: int | None = None, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row, and the kept words if with_text."""
    blocks = blocks or block_count(docs, text)
    rows, anchors, answers = repeated_windows(docs, text, key, blocks)
    # What a block needs comes in one frame: shared anchors and answers side by side.
    nothing = F.lit(None).cast("binary")
    news = anchors.select("block", nothing.alias("name"), F.col("anchors").alias("data"), "crowded").union(answers.select("block", "name", F.col("first").alias("data"), nothing))

    def finish(block: pa.Table, news: pa.Table) -> pa.Table:
        names, data = news.column("name").to_pylist(), news.column("data")
        known = {n: np.frombuffer(x.as_py(), np.int64) for n, x in zip(names, data) if n is not None}
        own = news.filter(pa.array([n is None for n in names], pa.bool_())).select(["data", "crowded"]).rename_columns(["anchors", "crowded"])
        n, cut, sha, kept_texts = [], [], [], []
        ids = _order(block.column("doc_id")).tolist() if block.num_rows else []
        for i, words, segments in _block_segments(block, own) if block.num_rows else ():
            kept = _kept_words(words, ids[i], segments, known)
            out = b" ".join(kept)
            n.append(len(words))
            cut.append(len(words) - len(kept))
            sha.append(hashlib.sha256(out).hexdigest())
            if with_text:
                kept_texts.append(out.decode("utf-8", "replace"))
        cols = [block.column("times"), block.column("doc_id"), pa.array(n, pa.int64()), pa.array(cut, pa.int64()), pa.array(sha, pa.string())]
        if with_text:
            cols += [block.column("text_hash"), pa.array(kept_texts, pa.string())]
        return pa.Table.from_arrays(cols, names=["times", "doc_id", "n_words", "n_removed", "kept_sha256", "text_hash", "kept"][: len(cols)])

    out = rows.groupBy("block").cogroup(news.groupBy("block")).applyInArrow(finish, "times long, doc_id long, n_words long, n_removed long, kept_sha256 string" + ", text_hash long, kept string" * with_text)
    return out.withColumn("times", F.explode(F.when(F.col("times") > 1, F.sequence(F.lit(1).cast("long"), "times")).otherwise(F.array(F.lit(1).cast("long"))))).drop("times")


def cut_repeats(docs: DataFrame, text: str = "text", key: str = "doc_id", **options) -> DataFrame:
    """docs with repeated passages cut out of the text; documents that lose nothing keep theirs as it is.

    A document of which nothing is left goes.
    """
    done = deduplicated(docs, text=text, key=key, with_text=True, **options).where("n_removed > 0").dropDuplicates(["doc_id", "text_hash"])
    cut = done.select(F.struct("doc_id", "text_hash", "n_words", "n_removed", "kept").alias("cut"))
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    same = F.col(f"row.`{key}`").cast("long").eqNullSafe(F.col("cut.doc_id")) & (F.xxhash64(F.col(f"row.`{text}`").cast("string")) == F.col("cut.text_hash"))
    out = row.join(cut, same, "left").where("cut is null or cut.n_removed < cut.n_words")
    new = {text: F.coalesce("cut.kept", f"row.`{text}`")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("cut").isNotNull(), F.length("cut.kept")).otherwise(F.col("row.n_chars")).cast(docs.schema["n_chars"].dataType)
    return out.select(*[new.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns])
