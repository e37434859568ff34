"""Byte-level BPE: a sentencepiece model written straight from a rank file, and cached encoders.

A rank file lists byte strings with ranks. `sentencepiece_model` serialises a BPE model proto whose
pieces are those strings with every byte mapped to one printable character, scored by negative rank,
with identity normalisation. Merging by highest score is then merging by lowest rank, so pre-tokens
encode to the ids of the rank file; decoding looks the bytes up again.

Encoders cut texts into pre-tokens and encode each distinct one once per cache lifetime. The cache is
kept by the worker process and emptied at `limit` pre-tokens, so memory stays bounded.

Edge cases: null and empty texts have no ids (n_tokens 0, digests of nothing); special tokens in a
text are ordinary text; repeated rows are encoded alike; further columns don't matter.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
from collections.abc import Callable, Iterator
from itertools import filterfalse

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Characters of text that are cut and looked up at once.
CHUNK = 2_000_000


def byte_letters() -> list[str]:
    """A printable character for every byte: itself where printable in Latin-1, else one from 256 up."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b if b in shown else next(rest)) for b in range(256)]


def read_ranks(data: bytes) -> list[bytes]:
    pairs = sorted((int(rank), base64.b64decode(piece)) for piece, rank in map(bytes.split, data.splitlines()) if piece)
    if [r for r, _ in pairs] != list(range(len(pairs))):
        raise ValueError("ranks must run from 0 without gaps")
    return [p for _, p in pairs]


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes([*out, n])


def _field(number: int, value: bytes | int | float) -> bytes:
    """One field in protobuf wire format."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def sentencepiece_model(pieces: list[bytes]) -> bytes:
    """A serialised model: id = rank, one unknown piece after the last rank."""
    letters = byte_letters()
    normal, unknown, bpe = 1, 2, 2
    body = [_field(1, _field(1, "".join(letters[b] for b in p).encode()) + _field(2, -float(i)) + _field(3, normal)) for i, p in enumerate(pieces)]
    body.append(_field(1, _field(1, b"<unk>") + _field(2, 0.0) + _field(3, unknown)))
    body.append(_field(2, _field(3, bpe) + _field(4, len(pieces) + 1) + _field(40, len(pieces))))
    body.append(_field(3, _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)))
    return b"".join(body)


#: The pattern of GPT-2-like byte-level pre-tokenisers, as their published vocabularies use it. A fixed value.
PRE_TOKENS = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


class UnitEncoder:
    """Texts to little-endian unsigned 32-bit ids, through a bounded cache of pre-tokens.

    `encode` maps a list of distinct pre-tokens to the ids of each.
    """

    def __init__(self, encode: Callable[[list[str]], list[bytes]], pattern: str = PRE_TOKENS, limit: int = 500_000):
        import regex

        self.encode, self.limit, self.cut = encode, limit, regex.compile(pattern).findall
        self.known: dict[str, bytes] = {}

    def texts(self, texts: list[str]) -> list[bytes]:
        if len(self.known) > self.limit:
            self.known = {}
        parts = [self.cut(t) for t in texts]
        new: set[str] = set()
        for p in parts:
            new.update(filterfalse(self.known.__contains__, p))
        tokens = [*new]
        self.known.update(zip(tokens, self.encode(tokens)))
        get = self.known.__getitem__
        out = [b"".join(map(get, p)) for p in parts]
        for t in tokens:
            if len(t) > 100:  # long runs are not kept
                del self.known[t]
        return out

    def columns(self, texts: pa.Array) -> Iterator[tuple[int, list[bytes]]]:
        """(position of the first, ids of each) for runs of texts of bounded size."""
        at, n = 0, len(texts)
        lengths = pa.compute.fill_null(pa.compute.binary_length(texts), 0).to_numpy(zero_copy_only=False)
        while at < n:
            end = at + max(1, int(np.searchsorted(np.cumsum(lengths[at : at + 4096]), CHUNK)))
            end = min(end, n)
            yield at, self.texts([t or "" for t in texts.slice(at, end - at).to_pylist()])
            at = end


_KEPT: dict[tuple, object] = {}


def kept(make: Callable, *spec):
    """make(*spec), kept in the worker process from task to task; one at a time."""
    key = make.__qualname__, hash(spec)
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = make(*spec)
    return _KEPT[key]


def piece_texts(model: bytes, pattern: str) -> UnitEncoder:
    return UnitEncoder(piece_encoder(model), pattern)


def piece_encoder(model: bytes) -> Callable[[list[str]], list[bytes]]:
    """Encodes pre-tokens with a sentencepiece model over byte letters."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_proto=model)
    letters = dict(enumerate(byte_letters()))

    def encode(tokens: list[str]) -> list[bytes]:
        if not tokens:
            return []
        ids = sp.encode([t.encode().decode("latin-1").translate(letters) for t in tokens], out_type=int, num_threads=1)
        sizes = np.cumsum([0, *map(len, ids)]) * 4
        flat = np.fromiter((i for x in ids for i in x), "<u4", int(sizes[-1]) // 4).tobytes()
        return [flat[a:b] for a, b in zip(sizes[:-1].tolist(), sizes[1:].tolist())]

    return encode


#: What Unicode counts as white space, with the separators U+001C to U+001F.
_WHITE = r"\x09-\x0D\x1C-\x20\x{85}\x{A0}\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}"
#: ASCII punctuation without the apostrophe, which may open a contraction.
_CLOSING = r"[!-&(-/:-@\[-`{-~]"


class LibraryEncoder:
    """Columns of texts to ids with the tokenizers library, without special tokens.

    A text is cut before every space that stands alone: no pre-token crosses such a place. Arrow cuts
    and finds the distinct units of a batch, then cuts these at line feeds that stand alone and before
    their closing punctuation, which are pre-tokens of their own. The library encodes each unit once,
    many in one string with line feeds between them; ids are gathered by index. Units that hold other
    white space, and texts with white space on both sides of a space, are encoded alone.

    Ids of short units are kept from batch to batch as flat arrays, and dropped when they are more than
    `limit`; all other memory follows the batch.
    """

    def __init__(self, spec: str, limit: int = 1 << 20, longest: int = 64):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_str(spec)
        self.tok.encode_special_tokens = True
        self.tok.no_padding()
        self.tok.no_truncation()
        self.mark = self.tok.encode("\n", add_special_tokens=False).ids
        self.limit, self.longest = limit, longest
        self.known: dict[str, tuple[pa.Array, np.ndarray, np.ndarray]] = {}

    def _each(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        if not texts:
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        ids = [np.array(e.ids, np.uint32) for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]
        return np.concatenate(ids), np.array([len(x) for x in ids], np.int64)

    def _joined(self, units: pa.Array, lead: str, size: int = 512) -> tuple[np.ndarray, np.ndarray]:
        """Ids and counts of units without white space, each after `lead`."""
        if len(self.mark) != 1:
            return self._each([lead + u for u in units.to_pylist()])
        ids, counts = [np.empty(0, np.uint32)], [np.empty(0, np.int64)]
        bounds = pa.array([*range(0, len(units), size), len(units)], pa.int64())
        groups = pa.compute.binary_join(pa.LargeListArray.from_arrays(bounds, units), pa.scalar("\n" + lead, pa.large_string())) if len(units) else []
        for i, group in enumerate(groups):
            group = lead + group.as_py()
            got = np.array(self.tok.encode_batch_fast([group], add_special_tokens=False)[0].ids, np.uint32)
            feeds = np.nonzero(got == self.mark[0])[0]
            if len(feeds) != min(size, len(units) - i * size) - 1:
                got, n = self._each(group.split("\n"))
            else:
                n = np.diff(np.concatenate([[-1], feeds, [len(got)]])) - 1
                got = np.delete(got, feeds)
            ids.append(got)
            counts.append(n)
        return np.concatenate(ids), np.concatenate(counts)

    def _lines(self, units: pa.Array, lead: str) -> tuple[np.ndarray, np.ndarray]:
        """Ids (in order of the units) and counts of units, each after `lead`, cut at line feeds that stand alone."""
        lone = pa.compute.match_substring_regex(units, f"^[^{_WHITE}]+(?:\n[^{_WHITE}]+)+$").to_numpy(zero_copy_only=False)
        if not lone.any():
            return self._units(units, lead)
        lines = pa.compute.split_pattern(units.filter(pa.array(lone)), "\n")
        size = np.ones(len(units), np.int64)
        size[lone] = pa.compute.list_value_length(lines).to_numpy()
        begin = np.cumsum(size) - size
        opens = np.zeros(int(size.sum()), bool)
        opens[begin] = True
        flat = lines.flatten()
        own = opens[np.repeat(lone, size)]
        heads = pa.concat_arrays([units.filter(pa.array(~lone)), flat.filter(pa.array(own))]).dictionary_encode()
        later = flat.filter(pa.array(~own)).dictionary_encode()
        ids_a, n_a = self._units(heads.dictionary, lead)
        ids_b, n_b = self._units(later.dictionary, "")
        # Two slices a line: the line feed before it, empty for a unit's first line, and its ids.
        pool = np.concatenate([np.array(self.mark, np.uint32), ids_a, ids_b])
        start, count = np.zeros((len(opens), 2), np.int64), np.zeros((len(opens), 2), np.int64)
        count[~opens, 0] = len(self.mark)
        firsts, at = begin[np.concatenate([np.nonzero(~lone)[0], np.nonzero(lone)[0]])], heads.indices.to_numpy()
        start[firsts, 1], count[firsts, 1] = (np.cumsum(n_a) - n_a + len(self.mark))[at], n_a[at]
        at = later.indices.to_numpy()
        start[~opens, 1], count[~opens, 1] = (np.cumsum(n_b) - n_b + len(self.mark) + len(ids_a))[at], n_b[at]
        return pool[_slices(start.ravel(), count.ravel())], np.add.reduceat(count.sum(1), begin)

    def _units(self, units: pa.Array, lead: str) -> tuple[np.ndarray, np.ndarray]:
        """Ids (in order of the units) and counts of units, each after `lead`.

        A pre-token ends between a letter or digit and the punctuation that closes a unit, so bodies and
        endings are encoded apart: fewer of them are distinct.
        """
        parts = pa.compute.extract_regex(units, rf"(?s)^(?P<body>.*[\p{{L}}\p{{N}}])(?P<tail>{_CLOSING}+)$")
        split = pa.compute.is_valid(parts).to_numpy(zero_copy_only=False)
        if not split.any():
            return self._cached(units, lead)
        bodies = pa.compute.coalesce(pa.compute.struct_field(parts, "body"), units).dictionary_encode()
        tails = pa.compute.struct_field(parts.filter(pa.array(split)), "tail").dictionary_encode()
        ids_b, n_b = self._cached(bodies.dictionary, lead)
        ids_t, n_t = self._cached(tails.dictionary, "")
        # Two slices a unit, the second empty where there is no ending.
        start, count = np.zeros((len(units), 2), np.int64), np.zeros((len(units), 2), np.int64)
        at = bodies.indices.to_numpy()
        start[:, 0], count[:, 0] = (np.cumsum(n_b) - n_b)[at], n_b[at]
        at = tails.indices.to_numpy()
        start[split, 1], count[split, 1] = (np.cumsum(n_t) - n_t + len(ids_b))[at], n_t[at]
        return np.concatenate([ids_b, ids_t])[_slices(start.ravel(), count.ravel())], count.sum(1)

    def _cached(self, units: pa.Array, lead: str) -> tuple[np.ndarray, np.ndarray]:
        """Ids and counts of distinct units; those not met before are encoded, and short ones kept."""
        keys, ids, counts = self.known.get(lead) or (pa.array([], pa.large_string()), np.empty(0, np.uint32), np.empty(0, np.int64))
        found = pa.compute.index_in(units, value_set=keys)
        fresh = pa.compute.is_null(found)
        new = units.filter(fresh)
        new_ids, new_counts = self._whole(new, lead)
        at = pa.compute.fill_null(found, 0).to_numpy().astype(np.int64)
        at[fresh.to_numpy(zero_copy_only=False)] = len(keys) + np.arange(len(new))
        all_ids, all_counts = np.concatenate([ids, new_ids]), np.concatenate([counts, new_counts])
        starts = np.cumsum(all_counts) - all_counts
        short = pa.compute.less_equal(pa.compute.binary_length(new), self.longest)
        new = new.filter(short)
        if len(keys) + len(new) > self.limit:
            self.known.pop(lead, None)
        elif len(new):
            stay = np.concatenate([np.ones(len(keys), bool), short.to_numpy(zero_copy_only=False)])
            held = all_ids if stay.all() else all_ids[_slices(starts[stay], all_counts[stay])]
            self.known[lead] = pa.concat_arrays([keys, new]), held, all_counts[stay]
        return all_ids[_slices(starts[at], all_counts[at])], all_counts[at]

    def _whole(self, units: pa.Array, lead: str) -> tuple[np.ndarray, np.ndarray]:
        joins = pa.compute.match_substring_regex(units, f"^[^{_WHITE}]+$").to_numpy(zero_copy_only=False)
        where, plain = np.nonzero(~joins)[0], np.nonzero(joins)[0]
        a, na = self._joined(units.filter(pa.array(joins)), lead)
        b, nb = self._each([lead + u for u in units.filter(pa.array(~joins)).to_pylist()])
        counts = np.empty(len(units), np.int64)
        counts[plain], counts[where] = na, nb
        if not len(where):
            return a, counts
        starts = np.empty(len(units), np.int64)
        starts[plain], starts[where] = np.cumsum(na) - na, np.cumsum(nb) - nb + len(a)
        return np.concatenate([a, b])[_slices(starts, counts)], counts

    def column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of a column of texts, and how many each text has; null is empty."""
        texts = texts.fill_null("").cast(pa.large_string())
        if not len(texts):
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        crowded = pa.compute.match_substring_regex(texts, f"[{_WHITE}] (?:[{_WHITE}]|\\z)").to_numpy(zero_copy_only=False)
        whole = np.nonzero(crowded)[0]
        cut = np.nonzero(~crowded)[0]
        pieces = pa.compute.split_pattern(texts.take(pa.array(cut)), " ")
        offsets = pieces.offsets.to_numpy()
        flat = pieces.flatten()
        first = np.zeros(len(flat), bool)
        first[offsets[:-1] - offsets[0]] = True
        coded = flat.filter(pa.array(~first)).dictionary_encode()
        heads = flat.filter(pa.array(first)).dictionary_encode()
        ids_u, n_u = self._lines(coded.dictionary, " ")
        ids_h, n_h = self._lines(heads.dictionary, "") if len(heads) else (np.empty(0, np.uint32), np.empty(0, np.int64))
        ids_w, n_w = self._each(texts.take(pa.array(whole)).to_pylist())
        # Every piece of every text as a slice of one pool.
        pool = np.concatenate([ids_u, ids_h, ids_w])
        begin_u, begin_h = np.cumsum(n_u) - n_u, np.cumsum(n_h) - n_h + len(ids_u)
        start, count = np.empty(len(flat), np.int64), np.empty(len(flat), np.int64)
        at = coded.indices.to_numpy()
        start[~first], count[~first] = begin_u[at], n_u[at]
        at = heads.indices.to_numpy()
        start[first], count[first] = begin_h[at], n_h[at]
        before = np.concatenate([[0], np.cumsum(count)])
        counts = np.zeros(len(texts), np.int64)
        counts[cut] = before[offsets[1:] - offsets[0]] - before[offsets[:-1] - offsets[0]]
        counts[whole] = n_w
        ids = pool[_slices(start, count)]
        if len(whole):
            own = np.empty(len(texts), np.int64)
            own[cut], own[whole] = np.cumsum(counts[cut]) - counts[cut], np.cumsum(n_w) - n_w + len(ids)
            ids = np.concatenate([ids, ids_w])[_slices(own, counts)]
        return ids, counts


def _slices(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Indices of the concatenated ranges [start, start + count)."""
    ends = np.cumsum(counts)
    total = int(ends[-1]) if len(ends) else 0
    kind = np.int32 if total + int(starts.max(initial=0)) < 1 << 31 else np.int64
    out = np.repeat((starts - (ends - counts)).astype(kind), counts)
    out += np.arange(total, dtype=kind)
    return out


def encode_decode(docs: DataFrame, ranks: bytes, pattern: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: ids by the rank file, and back."""
    pieces = read_ranks(ranks)
    model = sentencepiece_model(pieces)

    def run(batches):
        encoder = kept(piece_texts, model, pattern)
        for b in batches:
            n, ids_sha, text_sha = [], [], []
            for _, out in encoder.columns(b.column(1)):
                for ids in out:
                    n.append(len(ids) // 4)
                    ids_sha.append(hashlib.sha256(ids).hexdigest())
                    text_sha.append(hashlib.sha256(decode_ids(ids, pieces)).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def decode_ids(ids: bytes, pieces: list[bytes]) -> bytes:
    return b"".join(map(pieces.__getitem__, np.frombuffer(ids, "<u4").tolist()))
