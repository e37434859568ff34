"""Subword training by repeated pair merging with byte fallback; encoding, decoding, fertility.

The corpus is read once for its word counts; by Heaps' law that table is small beside the corpus. One
executor task then runs the merges over the table in flat arrays; a table above SINGLE_ROWS is trained in
batches of merges spread over all tasks. No word is left out, however rare.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..sources.tables import cut_lineage

MARK = "▁"
#: Distinct words up to which one task trains (some 60 bytes each in flat arrays).
SINGLE_ROWS = 16_000_000


UNKNOWN = "<unk>"


def spell(word: str, alphabet: set[str], byte_fallback: bool = True) -> list[str]:
    """Characters of the alphabet, others as UTF-8 byte pieces, or as the unknown piece without the fallback."""
    out: list[str] = []
    for c in word:
        out += [c] if c in alphabet else [f"<0x{b:02X}>" for b in c.encode()] if byte_fallback else [UNKNOWN]
    return out


def merge_word(symbols: list[str], pair: tuple[str, str]) -> list[str]:
    out, i = [], 0
    while i < len(symbols):
        if i + 1 < len(symbols) and (symbols[i], symbols[i + 1]) == pair:
            out.append(symbols[i] + symbols[i + 1])
            i += 2
        else:
            out.append(symbols[i])
            i += 1
    return out


def pairs(s: list[str]):
    """Adjacent pairs; overlapping equal symbols count without overlap."""
    last = None
    for p in zip(s, s[1:]):
        if UNKNOWN in p:
            last = None
        elif p == last and p[0] == p[1]:
            last = None
        else:
            yield p
            last = p


def learn(words: list[tuple[str, int]], merges: int, alphabet: set[str], byte_fallback: bool = True) -> list[tuple[str, str, int]]:
    """Merge list (left, right, weight): heaviest pair first, ties to the smaller pair; stops under weight 2.

    Nothing merges with the unknown piece.
    """
    state = [(spell(MARK + w, alphabet, byte_fallback), n) for w, n in words]
    weight: Counter = Counter()
    where: dict = defaultdict(set)
    for i, (s, n) in enumerate(state):
        for p in pairs(s):
            weight[p] += n
            where[p].add(i)
    out = []
    heap = [(-n, p) for p, n in weight.items()]
    heapify(heap)
    while len(out) < merges and heap:
        n, best = heappop(heap)
        if weight.get(best, 0) != -n:
            continue  # an older weight of this pair; the current one has its own entry
        if -n < 2:
            break
        out.append((*best, weight[best]))
        touched = set()
        for i in list(where[best]):
            s, n = state[i]
            for p in pairs(s):
                touched.add(p)
                weight[p] -= n
                where[p].discard(i)
                if weight[p] <= 0:
                    del weight[p]
            s = merge_word(s, best)
            state[i] = (s, n)
            for p in pairs(s):
                touched.add(p)
                weight[p] += n
                where[p].add(i)
        for p in touched:
            if p in weight:
                heappush(heap, (-weight[p], p))
    return out


def alphabet(words: DataFrame, coverage: float = 0.9995) -> list[str]:
    """Characters that cover the share of all occurrences; the rest is left to bytes. Bounded by Unicode."""
    c = words.select("cnt", F.explode(F.split("word", "")).alias("c")).where("c <> ''").groupBy("c").agg(F.sum("cnt").alias("n"))
    rows = sorted(((r["n"], r["c"]) for r in c.collect()), reverse=True)
    total, run, out = sum(n for n, _ in rows), 0, []
    for n, ch in rows:
        if run >= coverage * total:
            break
        out.append(ch)
        run += n
    return sorted(out)


def train_bpe(words: DataFrame, merges: int, coverage: float = 0.9995, byte_fallback: bool = True, letters: list[str] | None = None) -> DataFrame:
    """(rank, left, right, freq) from (word, cnt); trained in one task, or spread where the table is above SINGLE_ROWS.

    Characters beyond the coverage are bytes, or the unknown piece without the fallback; `letters`: what alphabet() says, if it is known.
    """
    table = cut_lineage(words.groupBy("word").agg(F.sum("cnt").alias("cnt")))
    if table.count() > SINGLE_ROWS:
        rows = [(i, *r) for i, r in enumerate(train_bpe_batched(table, merges, coverage, byte_fallback=byte_fallback))]
        return words.sparkSession.createDataFrame(rows, "rank bigint, left string, right string, freq bigint")
    known = {MARK, *(alphabet(table, coverage) if letters is None else letters)}

    def run(batches):
        out = learn_arrays(((b.column(0).to_pylist(), b.column(1).to_numpy()) for b in batches if b.num_rows), merges, known, byte_fallback)
        yield pa.RecordBatch.from_pydict({"rank": pa.array(range(len(out)), pa.int64()), "left": pa.array([a for a, _, _ in out], pa.string()), "right": pa.array([b for _, b, _ in out], pa.string()), "freq": pa.array([n for _, _, n in out], pa.int64())})

    return table.select("word", F.col("cnt").cast("bigint").alias("cnt")).coalesce(1).mapInArrow(run, "rank bigint, left string, right string, freq bigint")


#: Code points that no text holds: the gap between words, and a mark that isn't part of the text.
GAP, SET_MARK = "\ud800", "\ud801"


class Symbols:
    """Numbers of symbols for arrays: 0 is the gap between words, 1 the unknown piece, then bytes and characters."""

    def __init__(self, known: set[str]):
        self.names = ["", UNKNOWN, *[f"<0x{b:02X}>" for b in range(256)], *sorted(known)]
        self.ids = {s: i for i, s in enumerate(self.names)}

    def id(self, name: str) -> int:
        if name not in self.ids:
            self.ids[name] = len(self.names)
            self.names.append(name)
        return self.ids[name]

    def table(self, known: set[str], byte_fallback: bool) -> np.ndarray:
        """The number of every code point: -1 for those that are spelled in bytes."""
        out = np.full(0x110000, -1 if byte_fallback else 1, np.int32)
        for c in known:
            out[ord(c)] = self.ids[c]
        out[ord(GAP)], out[ord(SET_MARK)] = 0, self.ids.get(MARK, 1)
        return out


def spell_all(words: list[str], table: np.ndarray) -> np.ndarray:
    """Numbers of the symbols of all words, each with a gap behind it: what spell() says, by the table of code points."""
    points = np.frombuffer((GAP.join(words) + GAP).encode("utf-32-le", "surrogatepass"), np.uint32)
    out = table[points]
    other = np.flatnonzero(out < 0)
    if len(other):
        spelled = [chr(p).encode() for p in points[other].tolist()]
        sizes = np.ones(len(out), np.int64)
        sizes[other] = [len(x) for x in spelled]
        raw = np.repeat(out < 0, sizes)
        out = np.repeat(out, sizes)
        out[raw] = np.frombuffer(b"".join(spelled), np.uint8) + np.int32(2)
    return out


class WordArrays:
    """Spelled words in one flat array. A word keeps its place: what it loses by merges is filled with gaps at its end."""

    def __init__(self, flat: np.ndarray, most: int):
        ends = np.flatnonzero(flat == 0)
        self.room = np.diff(ends, prepend=-1).astype(np.int32)
        self.start = ends - self.room + 1
        self.s = np.append(flat, 0).astype(np.uint16 if most < 1 << 16 else np.int32)

    def places(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of these words in the flat array, and which of the words each belongs to."""
        room = self.room[words]
        of = np.repeat(np.arange(len(words)), room)
        return np.arange(len(of)) - (np.cumsum(room, dtype=np.int64) - room)[of] + self.start[words][of], of

    def shrink(self, at: np.ndarray, of: np.ndarray, words: np.ndarray, sub: np.ndarray, first: np.ndarray, new) -> np.ndarray:
        """Symbols at `first` become `new`, those after them go; symbols move up inside their word."""
        sub = sub.copy()
        sub[first] = new
        sub[first + 1] = 0
        full = np.flatnonzero(sub)
        count = np.bincount(of[full], minlength=len(words))
        to = self.start[words][of[full]] + np.arange(len(full)) - (np.cumsum(count) - count)[of[full]]
        self.s[at] = 0
        self.s[to] = sub[full]
        return self.s[at]


def without_overlap(equal: np.ndarray) -> np.ndarray:
    """Every second one of a run of neighbours, beginning with the first."""
    i = np.arange(len(equal))
    return equal & ((i - np.maximum.accumulate(np.where(equal, -1, i))) % 2 == 1)


def pair_places(sub: np.ndarray) -> np.ndarray:
    """Places whose symbol makes a countable pair with the next one."""
    left, right = sub[:-1], sub[1:]
    valid = (left > 1) & (right > 1)
    equal = valid & (left == right)
    return np.flatnonzero(valid & (~equal | without_overlap(equal)))


#: Above any number of symbols: a pair of them is one whole number.
PAIR = 1 << 24


def counted_pairs(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs with their summed weights, without those at zero."""
    keys, back = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
    sums = np.zeros(len(keys), np.int64)
    np.add.at(sums, back, np.concatenate([n for _, n in parts]))
    return keys[sums != 0], sums[sums != 0]


class Cells:
    """Spelled words in one flat array, a gap behind each, for merges in place.

    A merged symbol stays in its first cell, the others become holes. A symbol's first and last cell hold how many
    cells it has, so that its neighbours are found without a search. Once half of the cells are holes they are closed up.
    """

    def __init__(self, flat: np.ndarray, weight: np.ndarray):
        self.hole, self.weight = np.iinfo(flat.dtype).max, weight
        self.s = flat
        self.close_up()

    def close_up(self) -> None:
        """Without holes, and without words of one symbol, which have no pair."""
        s = self.s[self.s != self.hole]
        room = np.diff(np.flatnonzero(s == 0), prepend=-1)
        kept = room > 2
        # An empty word at the end: beyond either end of a word there is a gap.
        self.s, self.weight = np.append(s[np.repeat(kept, room)], s.dtype.type(0)), self.weight[kept[: len(self.weight)]]
        self.place = np.int32 if len(self.s) < 1 << 31 else np.int64
        self.start = np.append(0, np.cumsum(room[kept])).astype(self.place)
        self.size = np.ones(len(self.s), np.uint8)
        self.count = np.bincount(self.s)
        self.holes, self.found = 0, {}

    def at(self, symbol: int) -> np.ndarray:
        """The symbol's first cells, ascending; those of symbols that aren't frequent are remembered."""
        found = self.found.get(symbol)
        found = np.flatnonzero(self.s == symbol).astype(self.place) if found is None else found[self.s[found] == symbol]
        self.remember(symbol, found)
        return found

    def remember(self, symbol: int, found: np.ndarray) -> None:
        if len(found) <= len(self.s) // 16:
            self.found[symbol] = found
        else:
            self.found.pop(symbol, None)

    def hits(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """First cells of both symbols wherever the pair is merged: from the left, without overlap."""
        s, size = self.s, self.size
        if self.count[a] <= self.count[b]:
            first = self.at(a)
            second = first + size[first]
            hit = s[second] == b
        else:
            second = self.at(b)
            first = second - size[second - 1]
            hit = s[first] == a
        first, second = first[hit], second[hit]
        if a == b:
            i, goes_on = np.arange(len(first)), np.append(False, first[1:] == second[:-1])[: len(first)]
            hit = (i - np.maximum.accumulate(np.where(goes_on, 0, i))) % 2 == 0
            first, second = first[hit], second[hit]
        return first, second

    def words_at(self, cells: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.start, cells, "right") - 1

    def counted(self, words: np.ndarray, sign: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """All pairs of these words with their weights, some words at a time."""
        out = []
        for i in range(0, len(words), AT_A_TIME):
            some = words[i : i + AT_A_TIME]
            room = self.start[some + 1] - self.start[some]
            of = np.repeat(np.arange(len(some)), room)
            sub = self.s[np.arange(len(of)) - (np.cumsum(room, dtype=np.int64) - room)[of] + self.start[some][of]]
            of, sub = of[sub != self.hole], sub[sub != self.hole]
            j = pair_places(sub)
            left, right, n = sub[j].astype(np.int64), sub[j + 1], sign * self.weight[some][of[j]]
            kinds = int(sub.max(initial=0)) + 1
            if kinds * kinds <= len(j):  # few symbols: no sorting
                sums = np.bincount(left * kinds + right, n)
                k = np.flatnonzero(sums)
                out.append((k // kinds * PAIR + k % kinds, sums[k].astype(np.int64)))
            else:
                out.append(counted_pairs([(left * PAIR + right, n)]))
        return out

    def merge(self, a: int, b: int, new: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """Changes of pair weights: by the neighbours of what is merged; words in which equal symbols meet are counted anew."""
        if len(self.count) <= new:
            self.count = np.append(self.count, np.zeros(new + 1, np.int64))
        if 2 * self.holes > len(self.s):
            self.close_up_for(new)
        first, second = self.hits(a, b)
        if np.add(self.size[first], self.size[second], dtype=np.uint16).max(initial=0) > 255:
            self.close_up_for(new)
            first, second = self.hits(a, b)
        if self.count[new]:
            self.found.pop(new, None)
        else:
            self.remember(new, first)
        self.count[[a, b]] -= len(first) if a != b else 2 * len(first)
        self.count[new] += len(first)
        self.holes += len(first)
        out, i = [], 0
        while i < len(first):
            end = min(i + AT_A_TIME, len(first))
            while end < len(first) and self.words_at(first[end]) == self.words_at(first[end - 1]):
                end += 1
            out += self.merge_at(first[i:end], second[i:end], a, b, new)
            i = end
        return out

    def close_up_for(self, new: int) -> None:
        self.close_up()
        self.count = np.append(self.count, np.zeros(max(0, new + 1 - len(self.count)), np.int64))

    def merge_at(self, first: np.ndarray, second: np.ndarray, a: int, b: int, new: int) -> list[tuple[np.ndarray, np.ndarray]]:
        s, size, words = self.s, self.size, self.words_at(first)
        after = second + size[second]
        before, behind = s[first - size[first - 1]], s[after]
        # Where equal symbols meet, before or after, a run of them changes, whose pairs count without overlap.
        odd = (before == a) | (behind == b) | (before == new) | (behind == new) | (a == b)
        meet = after[:-1] == first[1:]
        odd[:-1] |= meet
        odd[1:] |= meet
        whole = np.unique(words[odd])
        out = self.counted(whole, -1)
        plain = whole[np.minimum(np.searchsorted(whole, words), len(whole) - 1)] != words if len(whole) else np.ones(len(words), bool)
        n = self.weight[words[plain]]
        out.append((np.array([a * PAIR + b]), np.array([-n.sum()])))
        sums = np.bincount(before[plain], n)
        k = np.flatnonzero(sums[2:]) + 2
        out += [(k * PAIR + a, -sums[k].astype(np.int64)), (k * PAIR + new, sums[k].astype(np.int64))]
        sums = np.bincount(behind[plain], n)
        k = np.flatnonzero(sums[2:]) + 2
        out += [(b * PAIR + k, -sums[k].astype(np.int64)), (new * PAIR + k, sums[k].astype(np.int64))]
        s[first], s[second] = new, self.hole
        size[first] += size[second]
        size[after - 1] = size[first]
        return out + self.counted(whole, 1)


#: Places, or words, that are looked at together.
AT_A_TIME = 200_000


def learn_arrays(batches, merges: int, alphabet: set[str], byte_fallback: bool = True) -> list[tuple[str, str, int]]:
    """learn() over batches of (words, counts), in flat arrays: a merge looks at the places of its pair only."""
    symbols = Symbols(alphabet)
    table, most = symbols.table(alphabet, byte_fallback), len(symbols.names) + merges
    kind = np.uint16 if most < (1 << 16) - 1 else np.int32
    flat, weights = [np.zeros(0, kind)], [np.zeros(0, np.int64)]
    for words, n in batches:
        flat.append(spell_all([SET_MARK + w for w in words], table).astype(kind))
        weights.append(n)
    joined = [np.concatenate(flat), np.concatenate(weights)]
    del flat, weights
    x = Cells(*joined)
    del joined

    total: dict[int, int] = {}
    heap: list = []

    def change(parts: list[tuple[np.ndarray, np.ndarray]]) -> None:
        for k, n in zip(*[c.tolist() for c in counted_pairs(parts)]):
            n += total.get(k, 0)
            if n > 0:
                total[k] = n
                heappush(heap, (-n, (symbols.names[k // PAIR], symbols.names[k % PAIR])))
            else:
                total.pop(k, None)

    change([(np.zeros(0, np.int64), np.zeros(0, np.int64)), *x.counted(np.arange(len(x.weight)), 1)])
    out = []
    while len(out) < merges and heap:
        n, (left, right) = heappop(heap)
        a, b = symbols.ids[left], symbols.ids[right]
        if total.get(a * PAIR + b, 0) != -n:
            continue  # an older weight of this pair; the current one has its own entry
        if -n < 2:
            break
        out.append((left, right, -n))
        change(x.merge(a, b, symbols.id(left + right)))
    return out


#: Pairs of symbols up to which ranks are kept in a square.
MOST_SQUARE = 1 << 22


class Ranks:
    """A merge list with numbers, for encoding many words at once."""

    def __init__(self, merges, known: set[str]):
        self.symbols = Symbols(known)
        self.made = np.array([self.symbols.id(a + b) for a, b in merges] or [0], np.int32)
        rank: dict[int, int] = {}
        for i, (a, b) in enumerate(merges):
            if a in self.symbols.ids and b in self.symbols.ids:
                rank[self.symbols.ids[a] * PAIR + self.symbols.ids[b]] = i
        self.keys = np.array(sorted(rank), np.int64)
        self.ranks = np.array([rank[k] for k in self.keys.tolist()], np.int64)
        self.never, kinds = len(self.made) + 1, len(self.symbols.names)
        self.square = None
        if kinds * kinds <= MOST_SQUARE:
            self.square = np.full((kinds, kinds), self.never, np.int32)
            self.square[self.keys // PAIR, self.keys % PAIR] = self.ranks

    def of_pairs(self, sub: np.ndarray) -> np.ndarray:
        """The rank of each symbol with the next one, `never` where they don't merge."""
        if self.square is not None:
            return self.square[sub[:-1], sub[1:]]
        key = sub[:-1].astype(np.int64) * PAIR + sub[1:]
        i = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[i] == key, self.ranks[i], self.never)

    def run(self, flat: np.ndarray, sizes: tuple[int, ...] = ()) -> tuple[WordArrays, np.ndarray]:
        """Words after all merges, the lowest rank of each word first; and how many symbols each word has by the first
        `size` merges alone: the state before the first merge of that rank or above."""
        x = WordArrays(flat, len(self.symbols.names))
        n = x.room.astype(np.int64) - 1
        by_size = np.zeros((len(sizes), len(n)), np.int64)
        open_ = np.ones((len(sizes), len(n)), bool)
        words = np.arange(len(n))
        never = self.never
        while len(words) and len(self.keys):
            at, of = x.places(words)
            sub = x.s[at]
            rank = np.append(self.of_pairs(sub), never).astype(np.int32)
            room = x.room[words]
            least = np.minimum.reduceat(rank, np.cumsum(room, dtype=np.int64) - room)
            for j, size in enumerate(sizes):
                stops = words[(least >= size) & open_[j][words]]
                by_size[j][stops], open_[j][stops] = n[stops], False
            go = least < never
            hit = (rank == least[of]) & (rank < never)
            # Only a pair of equal symbols can overlap itself.
            first = np.flatnonzero(without_overlap(hit))
            x.shrink(at, of, words, sub, first, self.made[rank[first]])
            n[words] -= np.bincount(of[first], minlength=len(words))
            words = words[go]
        for j in range(len(sizes)):
            by_size[j][open_[j]] = n[open_[j]]
        return x, (by_size if sizes else n)


def encode_word(word: str, ranks: dict[tuple[str, str], int], known: set[str], byte_fallback: bool = True, mark: str = MARK) -> list[str]:
    s = spell(mark + word, known, byte_fallback)
    while len(s) > 1:
        best = min(((ranks.get(p, 1 << 60), p) for p in zip(s, s[1:])), default=None)
        if best is None or best[0] == 1 << 60:
            break
        s = merge_word(s, best[1])
    return s


def encode_words(words: DataFrame, merges: list[tuple[str, str]], known: set[str]) -> DataFrame:
    """(word, pieces) of distinct words; the merge list travels with the tasks (bounded by the vocabulary)."""

    def run(batches):
        ranks = Ranks(merges, known)
        names, table = np.array(ranks.symbols.names, object), ranks.symbols.table(known, True)
        for b in batches:
            x, n = ranks.run(spell_all([SET_MARK + w for w in b["word"]], table))
            yield pd.DataFrame({"word": b["word"], "pieces": [names[x.s[i : i + k]].tolist() for i, k in zip(x.start, n)]})

    return words.select("word").distinct().mapInPandas(run, "word string, pieces array<string>")


def count_pieces(words: DataFrame, merges: list[tuple[str, str]], known: set[str], sizes: tuple[int, ...]) -> DataFrame:
    """(word, n): the number of pieces of each distinct word by the first `size` merges, for every size, in one pass."""

    def run(batches):
        ranks = Ranks(merges, known)
        table = ranks.symbols.table(known, True)
        for b in batches:
            n = ranks.run(spell_all([SET_MARK + w for w in b["word"]], table), sizes)[1]
            yield pd.DataFrame({"word": b["word"], "n": list(n.T)})

    return words.select("word").distinct().mapInPandas(run, "word string, n array<bigint>")


def decode(pieces: list[str]) -> str:
    """Pieces to text: byte pieces joined, marks to spaces."""
    raw = bytearray()
    for p in pieces:
        if len(p) == 6 and p.startswith("<0x"):
            raw.append(int(p[3:5], 16))
        else:
            raw += p.encode()
    return raw.decode("utf-8", "replace").replace(MARK, " ").lstrip(" ")


def fertility(words: DataFrame, encoded: DataFrame) -> DataFrame:
    """Pieces per word by language: a ratio of sums."""
    x = words.join(encoded.select("word", F.size("pieces").alias("n")), "word")
    return x.groupBy("lang").agg(F.sum(F.col("cnt") * F.col("n")).alias("tokens"), F.sum("cnt").alias("words")).withColumn("fertility", F.round(F.col("tokens") / F.col("words"), 6))


def fertility_baselines(words: DataFrame) -> DataFrame:
    """Whitespace, character and byte tokenizers."""
    by = words.groupBy("lang").agg(F.sum("cnt").alias("words"), F.sum(F.col("cnt") * F.length("word")).alias("chars"), F.sum(F.col("cnt") * F.octet_length("word")).alias("bytes"))
    kinds = F.array(*[F.struct(F.lit(k).alias("tokenizer"), F.col(c).cast("bigint").alias("tokens")) for k, c in (("whitespace", "words"), ("character", "chars"), ("byte", "bytes"))])
    return by.select("lang", "words", F.explode(kinds).alias("k")).select("k.tokenizer", "lang", "k.tokens", "words", F.round(F.col("k.tokens") / F.col("words"), 6).alias("fertility"))


def words_of(df: DataFrame) -> DataFrame:
    return df.select("lang", F.explode(T.letter_words(F.col("text"))).alias("word")).groupBy("lang", "word").agg(F.count(F.lit(1)).alias("cnt"))


def safe_picks(rows: list[tuple[str, str, int]], floor: int, limit: int, made: set[str]) -> list[tuple[str, str, int]]:
    """The longest head of a ranked pair list that one-by-one training would take in the same order.

    A later pick must share no symbol with an earlier one (its weight then cannot change) and outweigh
    every pair an earlier merge can create: such a pair weighs at most as much as the pair that reaches
    the merged symbol's edge. `floor` bounds pairs below the list. A merge that spells an existing
    symbol ends the batch, as it adds to pairs that exist.
    """
    before, after = defaultdict(lambda: floor), defaultdict(lambda: floor)
    for a, b, n in rows:
        before[b], after[a] = max(before[b], n), max(after[a], n)
    out, used, bound = [], set(), 0
    for a, b, n in rows[:limit]:
        if n < 2 or (out and (a in used or b in used or n <= bound)):
            break
        out.append((a, b, n))
        if a + b in made or (a + b).startswith("<0x"):
            break
        made.add(a + b)
        used |= {a, b}
        bound = max(bound, min(n, max(before[a], after[b])))
    return out


def train_bpe_batched(words: DataFrame, merges: int, coverage: float = 0.9995, per_round: int = 32, listed: int = 512, cut_every: int = 2, byte_fallback: bool = True) -> list[tuple[str, str, int]]:
    """Merge list equal to train_bpe's, with the word table spread over all tasks.

    Each round counts pairs (combined inside a task before the shuffle), takes `listed` of them to the
    driver, and applies every merge that is safe at once. For word tables no single task can hold.
    """
    known = {MARK, *alphabet(words, coverage)}
    table = words.groupBy("word").agg(F.sum("cnt").alias("cnt"))

    def spelled(batches):
        for b in batches:
            yield pd.DataFrame({"cnt": b["cnt"], "s": [spell(MARK + w, known, byte_fallback) for w in b["word"]]})

    def counted(batches):
        weight: Counter = Counter()
        for b in batches:
            for s, n in zip(b["s"], b["cnt"]):
                for p in pairs(list(s)):
                    weight[p] += n
        if weight:  # a task may hold whole words only
            yield pd.DataFrame({"left": [a for a, _ in weight], "right": [b for _, b in weight], "n": list(weight.values())})

    def rewritten(picks):
        def run(batches):
            for b in batches:
                out = []
                for s in b["s"]:
                    s = list(s)
                    for p in picks:
                        if p[0] in s:
                            s = merge_word(s, p)
                    out.append(s)
                yield pd.DataFrame({"cnt": b["cnt"], "s": out})

        return run

    state, out, made, rounds = cut_lineage(table.mapInPandas(spelled, "cnt bigint, s array<string>")), [], set(), 0
    while len(out) < merges:
        top = state.mapInPandas(counted, "left string, right string, n bigint").groupBy("left", "right").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "left", "right").limit(listed).collect()
        rows = [(r["left"], r["right"], r["n"]) for r in top]
        picks = safe_picks(rows, rows[-1][2] if len(rows) == listed else 0, min(per_round, merges - len(out)), made)
        if not picks:
            break
        out += picks
        rounds += 1
        state = state.mapInPandas(rewritten([p[:2] for p in picks]), "cnt bigint, s array<string>")
        if rounds % cut_every == 0:
            state = cut_lineage(state)
    return out


def decode_words(encoded: DataFrame) -> DataFrame:
    """(word, decoded) of encoded words."""
    def run(batches):
        for b in batches:
            yield pd.DataFrame({"word": b["word"], "decoded": [decode(list(p)) for p in b["pieces"]]})

    return encoded.mapInPandas(run, "word string, decoded string")


@dataclass(frozen=True)
class TextCodec:
    """A merge list with ids, for whole texts: 0 is the unknown piece, 1 to 256 the bytes, then the alphabet and the
    merged pieces in order. A space before a word becomes its mark, other white space and a mark in the text are
    spelled in bytes, so that with the byte fallback every text comes back as it was."""

    merges: tuple[tuple[str, str], ...]
    alphabet: tuple[str, ...]
    byte_fallback: bool = True

    def pieces(self) -> list[str]:
        plain = [UNKNOWN, *[f"<0x{b:02X}>" for b in range(256)], MARK, *[c for c in self.alphabet if c != MARK]]
        return list(dict.fromkeys([*plain, *[a + b for a, b in self.merges]]))

    def prepared(self) -> tuple:
        """Ranks, the table of code points, and the id of each of the ranks' symbols."""
        ranks, ids = Ranks(self.merges, {MARK, *self.alphabet}), {p: i for i, p in enumerate(self.pieces())}
        known = {c for c in self.alphabet if c != MARK and not c.isspace()}
        return ranks, ranks.symbols.table(known, self.byte_fallback), np.array([ids.get(x, 0) for x in ranks.symbols.names], np.int32)

    def learn_tokens(self, tokens: list[str], prepared: tuple, seen: dict[str, bytes]) -> None:
        """The ids of these tokens (as bytes of 32-bit numbers) go into seen."""
        ranks, table, ids = prepared
        marked = lambda t: t[0] == " " and len(t) > 1 and not t[1].isspace()
        if tokens:
            x, n = ranks.run(spell_all([SET_MARK + t[1:] if marked(t) else t for t in tokens], table))
            flat = ids[x.s]
            for token, i, k in zip(tokens, x.start.tolist(), n.tolist()):
                seen[token] = flat[i : i + k].tobytes()

    def encode_many(self, texts: list[str], prepared: tuple, seen: dict[str, bytes]) -> list[bytes]:
        """Ids of each text, as bytes of 32-bit numbers."""
        tokens = [_TOKENS.findall(t) for t in texts]
        self.learn_tokens(list({t for ts in tokens for t in ts if t not in seen}), prepared, seen)
        return [b"".join([seen[t] for t in ts]) for ts in tokens]

    def encode(self, text: str, prepared: tuple, seen: dict[str, bytes]) -> list[int]:
        return np.frombuffer(self.encode_many([text], prepared, seen)[0], np.int32).tolist()

    def decode(self, ids: list[int], pieces: list[str]) -> str:
        raw = bytearray()
        for i in ids:
            raw += "\ufffd".encode() if i == 0 else bytes([i - 1]) if i <= 256 else pieces[i].replace(MARK, " ").encode()
        return raw.decode("utf-8", "replace")

    def piece_bytes(self) -> list[bytes]:
        return ["\ufffd".encode(), *[bytes([b]) for b in range(256)], *[p.replace(MARK, " ").encode() for p in self.pieces()[257:]]]


#: A word with the space before it, or a run of white space up to the next word's own space.
_TOKENS = re.compile(r" ?[^\s]+|\s+?(?= [^\s])|\s+")
#: Distinct tokens whose ids a task keeps.
SEEN = 200_000


#: Characters of texts that are cut into tokens at once.
AT_ONCE = 1_000_000


def encode_texts(df: DataFrame, codec: TextCodec, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, ids, n_tokens) of whole texts; null texts have no ids. The codec travels with the tasks, bounded by the vocabulary."""

    def run(batches):
        prepared, seen = codec.prepared(), {}
        for b in batches:
            keys, texts, i = b.column(0), b.column(1), 0
            while i < b.num_rows:
                some, n = [], 0
                while i + len(some) < b.num_rows and (not some or n < AT_ONCE):
                    some.append(texts[i + len(some)].as_py() or "")
                    n += len(some[-1])
                ids = codec.encode_many(some, prepared, seen)
                sizes = np.array([len(x) // 4 for x in ids], np.int64)
                values = pa.array(np.frombuffer(b"".join(ids), np.int32))
                lists = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(sizes)).astype(np.int32)), values)
                yield pa.RecordBatch.from_arrays([keys.slice(i, len(some)), lists, pa.array(sizes)], [key, "ids", "n_tokens"])
                i += len(some)
                if len(seen) > SEEN:
                    seen.clear()

    return df.select(F.col(key).cast("bigint").alias(key), F.col(text).alias("text")).mapInArrow(run, f"{key} bigint, ids array<int>, n_tokens bigint")


def decode_texts(encoded: DataFrame, codec: TextCodec, key: str = "doc_id") -> DataFrame:
    """(key, text) from ids."""

    def run(batches):
        pieces = codec.piece_bytes()
        for b in batches:
            ids, ends = b.column(1).values.to_numpy(), b.column(1).offsets.to_numpy()
            texts = [b"".join([pieces[i] for i in ids[x:y].tolist()]).decode("utf-8", "replace") for x, y in zip(ends, ends[1:])]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], [key, "text"])

    return encoded.select(F.col(key).cast("bigint").alias(key), "ids").mapInArrow(run, f"{key} bigint, text string")


def vocab_sweep(words: DataFrame, merges: list[tuple[str, str]], sizes: tuple[int, ...], known: set[str], width: int = 4096) -> DataFrame:
    """(size, embedding parameters, tokens, words, fertility): every size is a prefix of one merge list."""
    totals = words.groupBy("word").agg(F.sum("cnt").alias("cnt"))
    x = totals.join(count_pieces(totals, merges, known, tuple(sizes)), "word").select("cnt", F.posexplode("n").alias("i", "n"))
    by = x.groupBy("i").agg(F.sum(F.col("cnt") * F.col("n")).alias("tokens"), F.sum("cnt").alias("words"))
    size = F.get(F.array(*[F.lit(s) for s in sizes]), F.col("i"))
    return by.select(size.alias("size"), (F.lit(2 * width) * size).cast("bigint").alias("embedding"), "tokens", "words", F.round(F.col("tokens") / F.col("words"), 6).alias("fertility"))
