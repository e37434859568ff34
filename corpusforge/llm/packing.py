"""Variable-capacity best-fit packing of documents into training sequences.

Several sequence lengths are permitted. Documents longer than the longest are cut; full pieces are
bins of their own. The rest is packed in shards, longest first: a piece goes to the open bin with
the least room that still holds it (of several, the one filled last); if none does, the bin size with least cost per token it can
still fill is opened (cost = fixed + length + length^2 / attention_span). At the end every bin
shrinks to the smallest permitted length that holds its contents.

Only (document, length) rows are shuffled. Shards are hashed on document, piece and length, about
`shard_pieces` rows each, so a hot source or a repeated id doesn't make one task; each shard leaves
at most its last few bins loose.

Edge cases: null and empty texts have one piece of length 1 (the end mark); very long texts become as
many pieces as they need; null ids are packed like others; repeated rows are packed once each; ties in
length are ordered by id and piece, ties in cost go to the smaller size; an empty table gives no rows;
further columns don't matter.
"""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import landed
from .tokens import LibraryEncoder, kept

PLAN = "doc_id long, piece int, n_tokens int, shard int, bin int, capacity int, position int"


@dataclass(frozen=True)
class Costs:
    """Cost of running one sequence of a length."""

    fixed: float = 64.0
    attention_span: float = 32768.0

    def of(self, length: int) -> float:
        return self.fixed + length + length * length / self.attention_span


def pack_shard(lengths: list[int], sizes: tuple[int, ...], costs: Costs = Costs()) -> list[tuple[int, int, int]]:
    """(bin, capacity, position) of each length; sizes ascend and the largest holds every length."""
    order = sorted(range(len(lengths)), key=lambda i: (-lengths[i], i))
    left = sum(lengths)
    open_bins: dict[int, list[int]] = {}  # room -> bins
    rooms = 0  # bit r is set if some bin has room r
    used: list[int] = []
    out: list[tuple[int, int]] = [(0, 0)] * len(lengths)
    for i in order:
        n = lengths[i]
        above = rooms >> n
        if above:
            room = n + (above & -above).bit_length() - 1
            bins = open_bins[room]
            b = bins.pop()
            if not bins:
                rooms ^= 1 << room
        else:
            room = min(sizes[bisect_left(sizes, n) :], key=lambda c: (costs.of(c) / min(c, left), c))
            b = len(used)
            used.append(0)
        out[i] = (b, used[b])
        used[b] += n
        left -= n
        if room > n:
            if not open_bins.get(room - n):
                rooms |= 1 << (room - n)
            open_bins.setdefault(room - n, []).append(b)
    return [(b, sizes[bisect_left(sizes, used[b])], at) for b, at in out]


def token_lengths(docs: DataFrame, tokenizer: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id and tokens of each text plus its end mark."""

    def run(batches):
        encoder = kept(LibraryEncoder, tokenizer)
        for b in batches:
            _, n = encoder.column(b.column(1))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n + 1)], names=["doc_id", "n_tokens"])

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long")


def pack_lengths(lengths: DataFrame, sizes: tuple[int, ...] = (2048, 4096, 8192), costs: Costs = Costs(), shard_pieces: int = 100_000) -> DataFrame:
    """Rows of (doc_id, n_tokens) to pieces with their bins. lengths is read twice: land it first."""
    sizes = tuple(sorted(set(sizes)))
    longest = sizes[-1]
    n = lengths.agg(F.sum(F.ceil(F.col("n_tokens") / longest))).first()[0] or 0
    shards = max(8, -(-int(n) // shard_pieces))
    pieces = lengths.select("doc_id", "n_tokens", F.explode(F.sequence(F.lit(0), (F.ceil(F.col("n_tokens") / longest) - 1).cast("int"))).alias("piece"))
    pieces = pieces.select("doc_id", "piece", F.least(F.lit(longest), F.col("n_tokens") - F.col("piece") * longest).cast("int").alias("n_tokens"))
    pieces = pieces.withColumn("shard", F.pmod(F.hash("doc_id", "piece", "n_tokens"), F.lit(shards)))

    def run(shard: pd.DataFrame) -> pd.DataFrame:
        shard = shard.sort_values(["n_tokens", "doc_id", "piece"], ascending=[False, True, True], kind="stable", na_position="first")
        bins = pack_shard(shard["n_tokens"].tolist(), sizes, costs)
        return shard.assign(bin=[b for b, _, _ in bins], capacity=[c for _, c, _ in bins], position=[p for _, _, p in bins])[[f.split()[0] for f in PLAN.split(", ")]]

    return pieces.groupBy("shard").applyInPandas(run, PLAN)


def pack_documents(docs: DataFrame, tokenizer: str, sizes: tuple[int, ...] = (2048, 4096, 8192), **options) -> DataFrame:
    return pack_lengths(landed(token_lengths(docs, tokenizer), "lengths"), sizes, **options)


def packing_report(plan: DataFrame, costs: Costs = Costs()) -> DataFrame:
    """Per capacity: bins, tokens, fill and cost."""
    bins = plan.groupBy("shard", "bin").agg(F.max("capacity").alias("capacity"), F.sum("n_tokens").alias("n_tokens"))
    c = F.col("capacity")
    return bins.groupBy("capacity").agg(F.count(F.lit(1)).alias("bins"), F.sum("n_tokens").alias("n_tokens"), (F.sum("n_tokens") / F.sum(c)).alias("fill"), F.sum(costs.fixed + c + c * c / costs.attention_span).alias("cost"))
