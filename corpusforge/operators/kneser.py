"""Kneser-Ney scores of any order, with numbers in place of words wherever something travels.

The words of the trusted text are numbered by language and frequency. Where a text is read its words become
numbers (0: not in the trusted text) and its n-grams go, sorted and packed, to the part of their last context
word, where every longer context of theirs is too; the trusted n-grams go there as distinct rows with counts.
An n-gram after an unknown word is scored where it is read. Back to each slice of texts travel their sums,
one from each part.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage

#: Trusted words whose numbers travel with the tasks, and trusted n-grams after one word that one task takes; see fits().
MOST_WORDS, MOST_AFTER = 8_000_000, 40_000_000
#: N-grams that are sorted and packed together, trusted n-grams a part, and parts at most.
TOGETHER, A_PART, MOST_PARTS = 1_250_000, 1_000_000, 4095
START, END = 0, 1
MODEL, SAID, READY = 0, 1, 2


def trusted_words(trusted: DataFrame) -> DataFrame:
    """(lang, word, cnt), landed; the end mark counts documents, so that every language of the trusted text is there."""
    words = F.concat(F.array(F.lit("</s>")), T.letter_words(F.col("text")))
    x = trusted.where("lang is not null and text is not null").select("lang", F.explode(words).alias("word"))
    return cut_lineage(x.groupBy("lang", "word").agg(F.count(F.lit(1)).alias("cnt")))


def fits(words: DataFrame) -> tuple[bool, int]:
    """Whether the numbered form takes this vocabulary, and the trusted n-grams."""
    r = words.agg(F.count(F.lit(1)).alias("n"), F.max("cnt").alias("most"), F.sum("cnt").alias("all")).first()
    return r["n"] <= MOST_WORDS and (r["most"] or 0) <= MOST_AFTER, r["all"] or 0


@dataclass
class Numbers:
    """Words of each language by falling frequency. A language's numbers begin at its start with both marks; 0 is no word of it."""

    langs: dict[str, int]
    words: list[pa.Array]
    starts: np.ndarray

    @classmethod
    def of(cls, words: DataFrame) -> Numbers:
        x = words.where("word <> '</s>'").toArrow()
        x = x.take(pc.sort_indices(x, [("cnt", "descending"), ("word", "ascending")]))
        langs = sorted(r["lang"] for r in words.select("lang").distinct().collect())
        lists = [pa.concat_arrays([pa.array([], pa.string()), *(c.cast(pa.string()) for c in x.filter(pc.equal(x["lang"], lang))["word"].chunks)]) for lang in langs]
        starts = np.cumsum([1, *[len(w) + 2 for w in lists]], dtype=np.int64)
        return cls({lang: i for i, lang in enumerate(langs)}, lists, starts)

    def lang_of(self, ids: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, ids, "right") - 1

    def ngrams(self, words: pa.ListArray, lang: np.ndarray, order: int) -> tuple[list[np.ndarray], np.ndarray]:
        """Columns of numbers, first word to last, of all n-grams of texts; and the text of each. lang: -1 for one without trusted text."""
        sizes = pc.list_value_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = words.flatten()
        of = np.repeat(lang.astype(np.int32), sizes)
        ids = np.zeros(len(flat), np.int32)
        for i in np.unique(lang[lang >= 0]).tolist():
            at = np.flatnonzero(of == i)
            found = pc.index_in(flat.take(pa.array(at)).cast(pa.string()), self.words[i]).fill_null(-1).to_numpy()
            ids[at] = np.where(found < 0, 0, found + self.starts[i] + 2)
        first = np.cumsum(sizes + order) - (sizes + order)
        marks = np.where(lang < 0, 0, self.starts[lang])
        seq = np.repeat(np.where(lang < 0, 0, marks + START), sizes + order).astype(np.int32)
        seq[np.repeat(first + order - 1 - (np.cumsum(sizes) - sizes), sizes) + np.arange(len(flat))] = ids
        seq[first + order - 1 + sizes] = np.where(lang < 0, 0, marks + END)
        n = sizes + 1
        at = np.repeat(first - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return [seq[at + k] for k in range(order)], np.repeat(np.arange(len(n), dtype=np.int32), n)


def pack(columns: list[np.ndarray]) -> bytes:
    """Columns of whole numbers under 2^31 by byte planes, compressed. Where the columns before say the same as in the row
    above, only the difference to the row above is kept: little is left of rows in lexicographic order."""
    same, planes = np.ones(max(0, len(columns[0]) - 1), bool), []
    for c in columns:
        c = c.astype(np.int32)
        step = np.diff(c)
        c[1:] = np.where(same, step, c[1:])
        same &= step == 0
        planes.append(c.view(np.uint8).reshape(-1, 4).T.tobytes())
    raw = b"".join(planes)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unpack(data: bytes, columns: int) -> list[np.ndarray]:
    size = int.from_bytes(data[:8], "little")
    planes = np.frombuffer(pa.decompress(data[8:], size, codec="zstd", asbytes=True), np.uint8).reshape(columns, 4, -1)
    out, first = [], np.arange(planes.shape[2]) == 0
    for p in planes:
        step = np.ascontiguousarray(p.T).view(np.int32)[:, 0]
        c = np.cumsum(step, dtype=np.int64)
        at = np.flatnonzero(first)
        c -= np.repeat(c[at] - step[at], np.diff(np.append(at, len(c))))
        out.append(c.astype(np.int32))
        first[1:] |= out[-1][1:] != out[-1][:-1]
    return out


def part_of(context: np.ndarray, parts: int) -> np.ndarray:
    return ((context.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) % np.uint64(parts)


def in_order(columns: list[np.ndarray], part: np.ndarray) -> np.ndarray:
    """An order by part, then near the lexicographic one of the columns: equal rows mostly meet, so that little is left to pack."""
    high = part << np.uint64(52)
    for c, bits in zip(columns, (26, 0)):
        high |= c.astype(np.uint64) << np.uint64(bits)
    low = np.zeros(len(part), np.uint64)
    for c in columns[2:]:
        low = (low << np.uint64(21)) ^ c.astype(np.uint64)
    return np.lexsort((low, high))


def distinct(columns: list[np.ndarray], counts: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Neighbouring equal rows as one, their counts added."""
    new = np.ones(len(counts), bool)
    if len(counts):
        new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    at = np.flatnonzero(new)
    return [c[at] for c in columns], np.add.reduceat(counts, at) if len(at) else counts


def texts(df: DataFrame) -> DataFrame:
    return df.where("lang is not null and text is not null").select("doc_id", "lang", T.letter_words(F.col("text")).alias("words"))


def slices(batches, numbers: Numbers, order: int, together: int):
    """Some texts at a time: their ids, languages, columns (last context word first, the n-gram's last word at the end) and texts."""
    for b in batches:
        sizes = pc.list_value_length(b.column(2)).to_numpy(zero_copy_only=False).astype(np.int64) + 1
        cut = np.cumsum(sizes) // (sizes.sum() // (sizes.sum() // together + 1) + 1)
        edges = [0, *(np.flatnonzero(np.diff(cut)) + 1).tolist(), b.num_rows]
        for i, j in zip(edges, edges[1:]):
            if i < j:
                some = b.slice(i, j - i)
                lang = np.array([numbers.langs.get(v, -1) for v in some.column(1).to_pylist()], np.int64)
                g, of = numbers.ngrams(some.column(2), lang, order)
                yield some, lang, [*g[-2::-1], g[-1]], of


class Model:
    """Trusted n-grams of a part, counted on every level: contexts are numbered by their shorter context and one more word."""

    def __init__(self, columns: list[np.ndarray], counts: np.ndarray):
        self.contexts, r = [], np.zeros(len(counts), np.int64)
        for c in columns[:-1]:
            keys, r = np.unique(r << 32 | c, return_inverse=True)
            self.contexts.append(keys)
        keys, back = np.unique(r << 32 | columns[-1], return_inverse=True)
        counts = np.bincount(back, counts, len(keys)).astype(np.int64)
        del r, back
        self.levels = []
        for known in reversed(self.contexts):
            of = keys >> 32
            # No number is above what one task takes.
            self.levels.append((keys, counts.astype(np.int32), *(np.bincount(of, n, len(known)).astype(np.int32) for n in (counts, None))))
            keys, counts = np.unique((known[of] >> 32) << 32 | keys & 0xFFFFFFFF, return_counts=True)
        self.levels.reverse()
        #: Last words of the distinct pairs; the pairs' first words are in this part only.
        self.after = self.levels[0][0] & 0xFFFFFFFF

    def rows(self) -> list[np.ndarray]:
        """The distinct n-grams with their counts, in lexicographic order, as contexts are numbered in it."""
        keys, counts = self.levels[-1][:2]
        out, r = [keys & 0xFFFFFFFF], keys >> 32
        for known in reversed(self.contexts):
            out.insert(0, known[r] & 0xFFFFFFFF)
            r = known[r] >> 32
        return [*out, counts]

    def tally(self, numbers: Numbers) -> np.ndarray:
        """By level and language, what was met once and twice; then the last words of pairs, by number."""
        kinds, out = len(numbers.langs), []
        for keys, counts, _, _ in self.levels:
            lang = numbers.lang_of(keys & 0xFFFFFFFF)
            out += [np.bincount(lang[counts == n], minlength=kinds) for n in (1, 2)]
        return np.concatenate([*out, np.bincount(self.after, minlength=int(numbers.starts[-1]))])

    def probabilities(self, columns: list[np.ndarray], p: np.ndarray, discounts: np.ndarray, lang: np.ndarray) -> np.ndarray:
        """Of n-grams with lowest-level probabilities p, going up as far as their contexts are known."""
        p, at, r, w = p.copy(), np.arange(len(p)), np.zeros(len(p), np.int64), columns[-1]
        for known, (keys, counts, total, kinds), c, d in zip(self.contexts, self.levels, columns, discounts):
            r, hit = found(known, r << 32 | c[at])
            at, r = at[hit], r[hit]
            i, met = found(keys, r << 32 | w[at])
            n, d = np.where(met, counts[i], 0), d[lang[at]]
            p[at] = (np.maximum(n - d, 0.0) + d * kinds[r] * p[at]) / total[r]
        return p


def found(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of what is wanted in ascending keys that aren't empty, and whether it is there."""
    i = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return i, keys[i] == wanted


def perplexities(df: DataFrame, trusted: DataFrame, order: int, words: DataFrame, total: int) -> DataFrame:
    """doc_id, lang, perplexity of every text in a known language, as language.perplexity_kneser_ney says."""
    spark, numbers = df.sparkSession, Numbers.of(words)
    parts = min(MOST_PARTS, max(int(spark.conf.get("spark.sql.shuffle.partitions")), total // A_PART + 1))
    shared, together = spark.sparkContext.broadcast(numbers), TOGETHER

    def count(batches):
        for _, lang, columns, of in slices(batches, shared.value, order, together):
            at = np.flatnonzero(lang[of] >= 0)
            columns = [c[at] for c in columns]
            part = part_of(columns[0], parts)
            by = in_order(columns, part)
            columns, part = [c[by] for c in columns], part[by]
            edges = np.searchsorted(part, np.arange(parts + 1, dtype=np.uint64))
            some = np.flatnonzero(np.diff(edges))
            data = [pack([*c, n]) for c, n in (distinct([c[edges[k] : edges[k + 1]] for c in columns], np.ones(edges[k + 1] - edges[k], np.int64)) for k in some)]
            yield pa.RecordBatch.from_pydict({"part": pa.array(some, pa.int32()), "data": pa.array(data, pa.binary())})

    def model_of(blobs: list[bytes]) -> Model:
        read = [unpack(b, order + 1) for b in blobs]
        *columns, n = [np.concatenate(c) for c in zip(*read)]
        return Model(columns, n)

    def by_part(batches):
        held, blobs = None, []
        for b in batches:
            for part, data in zip(b.column(0).to_pylist(), b.column(1)):
                if part != held and blobs:
                    yield held, blobs
                    blobs = []
                held = part
                blobs.append(data.as_py())
        if blobs:
            yield held, blobs

    def build(batches):
        for part, blobs in by_part(batches):
            m = model_of(blobs)
            tally = m.tally(shared.value)
            k = np.flatnonzero(tally)
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "data": pa.array([pack(m.rows())], pa.binary()), "tally": pa.array([pack([k, tally[k]])], pa.binary())})

    routed = texts(trusted).mapInArrow(count, "part int, data binary").repartition(parts, "part").sortWithinPartitions("part")
    models = cut_lineage(routed.mapInArrow(build, "part int, data binary, tally binary"))
    size = 2 * (order - 1) * len(numbers.langs) + int(numbers.starts[-1])

    def add_up(batches):
        out = np.zeros(size, np.int64)
        for b in batches:
            for x in b.column(0):
                k, n = unpack(x.as_py(), 2)
                out[k] += n
        yield pa.RecordBatch.from_pydict({"sums": pa.array([out.tobytes()], pa.binary())})

    sums = sum((np.frombuffer(r["sums"], np.int64) for r in models.select("tally").coalesce(4).mapInArrow(add_up, "sums binary").collect()), np.zeros(size, np.int64))
    met, after = sums[: size - numbers.starts[-1]].reshape(order - 1, 2, -1), sums[size - numbers.starts[-1] :]
    once, twice = met[:, 0], met[:, 1]
    discounts = np.where(once > 0, once / np.maximum(once + 2.0 * twice, 1), 0.5)
    # The lowest level, smoothed by one; a language without trusted text is smoothed over the words of all languages.
    spans = list(zip(numbers.starts[:-1], numbers.starts[1:]))
    kinds = np.array([np.count_nonzero(after[i:j]) for i, j in spans], np.int64)
    room = np.array([*(after[i:j].sum() + n + 1.0 for (i, j), n in zip(spans, kinds)), kinds.sum() + 1.0])
    lowest = spark.sparkContext.broadcast((after, room, discounts))

    def base(last: np.ndarray, lang: np.ndarray) -> np.ndarray:
        after, room, _ = lowest.value
        return np.where(last > 0, after[last] + 1.0, 1.0) / room[lang]

    def deal(batches):
        """What is known where a text is read, by slice of the texts, and packed n-grams for the parts."""
        task = TaskContext.get().partitionId() << 32
        for k, (some, lang, columns, of) in enumerate(slices(batches, shared.value, order, together)):
            goes = columns[0] > 0
            stays, at = np.flatnonzero(~goes), np.flatnonzero(goes)
            ready = np.bincount(of[stays], np.log(base(columns[-1][stays], lang[of[stays]])), len(lang))
            ready = ready.tobytes() + np.bincount(of, minlength=len(lang)).astype(np.int64).tobytes()
            columns, of = [c[at] for c in columns], of[at]
            part = part_of(columns[0], parts)
            by = in_order(columns, part)
            columns, of, part = [c[by] for c in columns], of[by], part[by]
            edges = np.searchsorted(part, np.arange(parts + 1, dtype=np.uint64))
            to = np.flatnonzero(np.diff(edges))
            data = [pack([*(c[edges[j] : edges[j + 1]] for c in columns), of[edges[j] : edges[j + 1]]]) for j in to]
            n = len(to)
            docs, langs = (pa.ListArray.from_arrays(pa.array([0, len(c)] + [len(c)] * n, pa.int32()), c) for c in (some.column(0), some.column(1).cast(pa.string())))
            yield pa.RecordBatch.from_arrays([pa.array([k % parts, *to], pa.int32()), pa.array([READY] + [SAID] * n, pa.int32()), pa.array([task + k] * (n + 1), pa.int64()), docs, langs, pa.array([ready, *data], pa.binary())], ["part", "kind", "slice", "docs", "langs", "data"])

    def score(batches):
        """By slice, sums of logarithms of this part's n-grams; what was ready goes on as it is."""
        held, m, numbers, discounts = None, None, shared.value, lowest.value[2]
        for b in batches:
            out = []
            for part, kind, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(5)):
                data = data.as_py()
                if part != held:
                    held, m = part, None
                if kind == MODEL:
                    m = model_of([data])
                elif kind == SAID:
                    *columns, of = unpack(data, order + 1)
                    lang = numbers.lang_of(columns[0])
                    p = base(columns[-1], lang)
                    if m is not None:
                        p = m.probabilities(columns, p, discounts, lang)
                    sums = np.bincount(of, np.log(p))
                    docs = np.flatnonzero(sums)
                    data = len(docs).to_bytes(8, "little") + sums[docs].tobytes() + pack([docs])
                out.append(data)
            b = pa.RecordBatch.from_arrays([*(b.column(i) for i in range(1, 5)), pa.array(out, pa.binary())], ["kind", "slice", "docs", "langs", "data"])
            yield b.filter(pc.not_equal(b.column(0), MODEL))

    def gather(batches):
        """The texts of each slice with the sums of all parts; a slice's texts come last."""
        total = np.zeros(0)
        for b in batches:
            for i, (kind, data) in enumerate(zip(b.column(0).to_pylist(), b.column(4))):
                data = data.as_py()
                if kind == READY:
                    docs, langs = b.column(2)[i].values, b.column(3)[i].values
                    s = np.frombuffer(data, np.float64, len(docs)).copy()
                    s[: len(total)] += total
                    yield pa.RecordBatch.from_arrays([docs, langs, pa.array(s), pa.array(np.frombuffer(data, np.int64, len(docs), 8 * len(docs)))], ["doc_id", "lang", "s", "n"])
                    total = np.zeros(0)
                else:
                    n = int.from_bytes(data[:8], "little")
                    docs = unpack(data[8 + 8 * n :], 1)[0]
                    total = np.append(total, np.zeros(max(0, docs.max(initial=-1) + 1 - len(total))))
                    total[docs] += np.frombuffer(data, np.float64, n, 8)

    kind = df.schema["doc_id"].dataType.simpleString()
    rows = f"slice bigint, docs array<{kind}>, langs array<string>, data binary"
    said = texts(df).mapInArrow(deal, f"part int, kind int, {rows}")
    known = models.select("part", F.lit(MODEL).alias("kind"), F.lit(0).cast("bigint").alias("slice"), F.lit(None).cast(f"array<{kind}>").alias("docs"), F.lit(None).cast("array<string>").alias("langs"), "data")
    dealt = said.unionByName(known).repartition(parts, "part").sortWithinPartitions("part", "kind")
    back = dealt.mapInArrow(score, f"kind int, {rows}").repartition(parts, "slice").sortWithinPartitions("slice", "kind")
    sums = back.mapInArrow(gather, f"doc_id {kind}, lang string, s double, n bigint")
    return sums.groupBy("doc_id", "lang").agg(F.exp(-F.sum("s") / F.sum("n")).alias("perplexity"))
