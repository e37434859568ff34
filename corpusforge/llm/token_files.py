"""Token ids in Simple-8b files: 64-bit words, each a 4-bit selector and as many ids as fit.

A file is a shard of ascending documents, stored as rows of a Parquet container, so that Spark's
commit protocol protects it and any Hadoop store can hold it. A row is a block of about 130,000
ids: documents, ids per document, the word at which each document starts (so one document can be
decoded alone), the ids before the block in its shard, and the packed words. Selector 0 is the
escape: the next word holds one raw 64-bit id.

Writing range-partitions the texts by document (ties by text hash, so that one repeated id doesn't
make one task), sorts within partitions and encodes there; every partition is a shard and shards
ascend. Reading joins each block with the ids before its shard (one row a shard, broadcast only while
there are at most BROADCAST_SHARDS of them) and decodes blocks with array operations.

Edge cases: null and empty texts hold the end id only; rows with a null doc_id come first; rows that
share a doc_id are ordered by text hash (equal ones are interchangeable); texts of any length are
encoded whole, and a block ends with the document that fills it; further columns don't matter; an empty table writes no blocks and reads as no rows.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import block_count, shared_folder
from .tokens import LibraryEncoder, kept

#: Ids per word and bits per id, by selector; 0 is the escape.
COUNTS = (1, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
BITS = (64, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
BLOCK_IDS = 1 << 17
BROADCAST_SHARDS = 100_000
FILE_SCHEMA = "shard int, block int, before long, n_ids long, doc_ids array<long>, id_counts array<long>, word_offsets array<long>, words binary"


def pack(ids: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words of concatenated documents (ends: past each one's last id) and the word each one ends before.

    Greedy: every word takes the selector with most ids that fits and doesn't cross a document's end.
    """
    n = len(ids)
    if not n:
        return np.empty(0, np.uint64), np.zeros(len(ends), np.int64)
    if not len(ids) or int(ids.max()) < 1 << 32:
        ids = ids.astype(np.uint32, copy=False)
        select = np.full(n, 15, np.uint8)
    else:
        select = np.where(ids < np.uint64(1 << 60), 15, 0).astype(np.uint8)
    room = (np.repeat(ends, np.diff(ends, prepend=0)) - np.arange(n)).astype(np.int32)
    top, have = ids, 1
    for s in range(14, 0, -1):
        count, bits = COUNTS[s], BITS[s]
        if count > n:
            break
        while 2 * have <= count:
            top = np.maximum(top[:-have], top[have:])
            have *= 2
        rest = count - have
        most = np.maximum(top[:-rest], top[rest:]) if rest else top
        fits = (most < most.dtype.type(1 << bits)) & (room[: len(most)] >= count) if bits < 32 or most.dtype == np.uint64 else room[: len(most)] >= count
        if not fits.any():
            break  # a longer run with fewer bits fits only where this one does
        select[: len(most)][fits] = s
    step = np.array(COUNTS, np.int64)[select].tolist()
    at, chain = 0, []
    while at < n:
        chain.append(at)
        at += step[at]
    chain = np.array(chain, np.int64)
    chosen = select[chain]
    slots = np.cumsum(np.where(chosen == 0, 2, 1))
    words = np.zeros(int(slots[-1]), np.uint64)
    first = slots - np.where(chosen == 0, 2, 1)
    for s in np.unique(chosen):
        own = np.nonzero(chosen == s)[0]
        if s == 0:
            words[first[own] + 1] = ids[chain[own]]
            continue
        word, at = np.full(len(own), int(s) << 60, np.uint64), chain[own]
        if BITS[s]:
            for k in range(COUNTS[s]):
                word |= ids[at + k].astype(np.uint64) << np.uint64(k * BITS[s])
        words[first[own]] = word
    upto = np.searchsorted(chain, ends, "left")
    return words, np.concatenate([[0], slots])[upto]


def unpack(words: np.ndarray) -> np.ndarray:
    """All ids of a run of words that starts at a word boundary of a document."""
    if not len(words):
        return np.empty(0, np.uint64)
    select = (words >> np.uint64(60)).astype(np.uint8)
    if (select == 0).any():  # what follows an escape is no selector
        raw, k = np.zeros(len(words), bool), 0
        for k in np.nonzero(select == 0)[0]:
            if not raw[k]:
                raw[k + 1] = True
        heads = np.nonzero(~raw)[0]
    else:
        heads = np.arange(len(words))
    chosen = select[heads]
    counts = np.array(COUNTS, np.int64)[chosen]
    starts = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()), np.uint64)
    for s in np.unique(chosen):
        own = np.nonzero(chosen == s)[0]
        if s == 0:
            out[starts[own]] = words[heads[own] + 1]
        elif BITS[s]:
            mask, word = np.uint64((1 << BITS[s]) - 1), words[heads[own]]
            for k in range(COUNTS[s]):
                out[starts[own] + k] = (word >> np.uint64(k * BITS[s])) & mask
    return out


def write_token_files(docs: DataFrame, path: str, tokenizer: str, *, end_id: int = 0, text: str = "text", key: str = "doc_id", shards: int | None = None) -> None:
    """Encode, order and write; `tokenizer` is the content of a tokenizers JSON file."""
    shards = shards or block_count(docs, text, target=40 << 20, least=24)

    def run(batches):
        from pyspark import TaskContext

        encoder = kept(LibraryEncoder, tokenizer)
        shard, block, before = TaskContext.get().partitionId(), 0, 0
        kinds = {"shard": pa.int32(), "block": pa.int32(), "before": pa.int64(), "n_ids": pa.int64(), "words": pa.binary()}
        for b in (x.slice(i, 7000) for x in batches for i in range(0, x.num_rows, 7000)):
            keys = b.column(0).to_pylist()
            ids, counts = encoder.column(b.column(1))
            # Each document's ids, then its end mark.
            counts = counts + 1
            ends = np.cumsum(counts)
            all_ids = np.full(int(ends[-1]) if len(ends) else 0, end_id, np.uint32)
            inner = np.ones(len(all_ids), bool)
            inner[ends - 1] = False
            all_ids[inner] = ids
            first = 0
            while first < len(keys):
                base = int(ends[first] - counts[first])
                last = max(first + 1, int(np.searchsorted(ends, base + BLOCK_IDS, "right")))
                words, upto = pack(all_ids[base : ends[last - 1]], ends[first:last] - base)
                n = int(ends[last - 1]) - base
                row = {"shard": [shard], "block": [block], "before": [before], "n_ids": [n], "doc_ids": [keys[first:last]], "id_counts": [counts[first:last]], "word_offsets": [np.concatenate([[0], upto[:-1]])], "words": [words.astype("<u8").tobytes()]}
                yield pa.RecordBatch.from_arrays([pa.array(v, kinds.get(k, pa.list_(pa.int64()))) for k, v in row.items()], names=list(row))
                first, block, before = last, block + 1, before + n

    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    ordered = rows.withColumn("_tie", F.xxhash64("text")).repartitionByRange(shards, "doc_id", "_tie").sortWithinPartitions("doc_id", "_tie").select("doc_id", "text")
    ordered.mapInArrow(run, FILE_SCHEMA).write.option("compression", "zstd").parquet(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the files."""
    files = spark.read.schema(FILE_SCHEMA).parquet(path)
    totals = files.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    ahead = totals.select("shard", (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("ahead"))

    def run(batches):
        for b in batches:
            for r in b.to_pylist():
                ids = unpack(np.frombuffer(r["words"], "<u8")).astype("<u4")
                counts = np.array(r["id_counts"], np.int64)
                ends = np.cumsum(counts)
                starts = ends - counts
                crc = [zlib.crc32(ids[s:e].tobytes()) for s, e in zip(starts.tolist(), ends.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array(r["doc_ids"], pa.int64()), pa.array(starts + r["before"] + r["ahead"], pa.int64()), pa.array(counts, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    small = totals.count() <= BROADCAST_SHARDS
    blocks = files.join(F.broadcast(ahead) if small else ahead, "shard").select("doc_ids", "id_counts", "before", "ahead", "words")
    return blocks.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_file_report(docs: DataFrame, tokenizer: str, **options) -> DataFrame:
    path = f"{shared_folder(docs.sparkSession)}/token-files-{uuid.uuid4().hex}"
    write_token_files(docs, path, tokenizer, **options)
    return read_token_files(docs.sparkSession, path)
