"""Licence scans: an Aho-Corasick automaton finds notice phrases and identifier tags.

Texts are lower-cased (A-Z) and cut into words; phrases are searched in the stream of words joined
by single spaces, so only whole consecutive words match. Identifier tags are searched in the raw
text; what follows them on the line goes to a shunting-yard parser, which evaluates
and/or/with/parentheses/'+' into a set of licences and tells whether the expression is well formed.

Narrow: one `mapInArrow` over the scan, one automaton per task, memory bounded by a batch.

Edge cases: null and empty texts have no words, no labels, null first and last word and score 0;
texts of any length are scanned whole, one at a time; overlapping phrases all count; ties between
labels don't exist, as they are sets; repeated rows are scanned each; an empty table gives no rows;
further columns don't matter.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Base phrases and the labels they carry.
BASE_PHRASES = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))
#: Further notices and short names, with labels of the method's own.
MORE_PHRASES = (
    ("lesser general public license", "lgpl"),
    ("affero general public license", "agpl"),
    ("mozilla public license", "mpl"),
    ("bsd license", "bsd"),
    ("creative commons", "cc"),
    ("permission is hereby granted free of charge", "mit-notice"),
    ("redistribution and use in source and binary forms", "bsd-notice"),
    ("licensed under the apache license", "apache-notice"),
    ("all rights reserved", "all-rights-reserved"),
)
#: Identifiers of licences whose terms are permissive.
PERMISSIVE = frozenset("mit apache-2.0 bsd-2-clause bsd-3-clause isc zlib unlicense cc0-1.0 0bsd".split())
TAGS = ("spdx-license-identifier:", "license-expression:")
_NOT_WORD = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
#: A-Z to a-z; what no word holds to a space; the rest stays.
_TABLE = bytes(c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in _NOT_WORD)
_LEXEMES = re.compile(r"[()]|[a-z0-9.+:-]+")
_RANK = {"or": 1, "and": 2, "with": 3}
FIELDS = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def evaluate_expression(text: str, permissive: frozenset[str] = PERMISSIVE) -> tuple[frozenset[str], bool, bool]:
    """Of a lower-case expression: the licences named, whether permissive terms suffice, whether it is well formed.

    `or` needs one side to be permissive, `and` both; `with` binds an exception to one licence and
    keeps that licence's verdict. A malformed rest is ignored; what was read up to there counts.
    """
    values: list[tuple[frozenset[str], bool]] = []
    waiting: list[str] = []
    good, operand_next = True, True

    def reduce() -> bool:
        op = waiting.pop()
        if len(values) < 2:
            return False
        (b, free_b), (a, free_a) = values.pop(), values.pop()
        if op == "with":
            fits = len(a) == 1 and len(b) == 1
            values.append((frozenset({f"{min(a)} with {min(b)}"}) if fits else a | b, free_a))
            return fits
        values.append((a | b, free_a or free_b if op == "or" else free_a and free_b))
        return True

    for token in _LEXEMES.findall(text):
        if token == "(":
            if not operand_next:
                break
            waiting.append(token)
        elif token == ")":
            if operand_next or "(" not in waiting:
                good = False
                break
            while waiting[-1] != "(":
                good &= reduce()
            waiting.pop()
        elif token in _RANK:
            if operand_next:
                good = False
                break
            while waiting and waiting[-1] != "(" and _RANK[waiting[-1]] >= _RANK[token]:
                good &= reduce()
            waiting.append(token)
            operand_next = True
        elif operand_next:
            name = token.rstrip(".")
            values.append((frozenset({name}), name.rstrip("+") in permissive))
            operand_next = False
        else:
            break  # the expression has ended; prose follows
    good &= not operand_next
    while waiting:
        if waiting[-1] == "(":
            waiting.pop()
            good = False
        else:
            good &= reduce()
    names, free = values[-1] if values else (frozenset(), False)
    return names, free, good and len(values) == 1


def _automaton(phrases, pad: bool):
    import ahocorasick

    a = ahocorasick.Automaton()
    for p, label in phrases:
        key = f" {p} " if pad else p
        a.add_word(key, (p, label, len(key)))
    a.make_automaton()
    return a


def scan_text(text: str | None, words_ac, tags_ac, base: dict[str, str]) -> tuple:
    raw = (text or "").encode("utf-8", "surrogatepass").translate(_NOT_WORD)
    words = raw.translate(_TABLE).split()
    stream = " " + b" ".join(words).decode("utf-8", "replace") + " "
    starts, own, labels = [], set(), set()
    for end, (phrase, label, n) in words_ac.iter(stream):
        if phrase in base:
            starts.append(end - n + 1)
            own.add(base[phrase])
        labels.add(label)
    places, at, upto = [], 0, 0
    for start in sorted(starts):  # the spaces before a place count its words
        at += stream.count(" ", upto, start)
        upto = start
        places.append(at)
    sound = None
    if b"license-" in raw:
        lower = raw.decode("utf-8", "replace")
        for end, _ in tags_ac.iter(lower):
            stop = lower.find("\n", end + 1)
            names, free, good = evaluate_expression(lower[end + 1 : stop if stop >= 0 else len(lower)])
            labels.update(f"id:{x}" for x in names)
            if names and free:
                labels.add("permissive")
            sound = good if sound is None else sound and good
    labels |= own
    # Certainty: identifier tags tell most, then base phrases, then other notices.
    score = 0.0 if not labels else 1.0 if sound else 0.75 if own else 0.5
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(own)), ",".join(sorted(labels)), score


def scan_licenses(docs: DataFrame, text: str = "text", key: str = "doc_id", phrases=BASE_PHRASES, more=MORE_PHRASES) -> DataFrame:
    base = dict(phrases)

    def run(batches):
        words_ac, tags_ac = _automaton([*phrases, *[m for m in more if m[0] not in base]], True), _automaton([(t, t) for t in TAGS], False)
        for b in batches:
            rows = [scan_text(t.as_py(), words_ac, tags_ac, base) for t in b.column(1)]
            cols = list(zip(*rows)) if rows else [[] for _ in range(7)]
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.float64())
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, k) for c, k in zip(cols, kinds)]], names=[f.split()[0] for f in FIELDS.split(", ")])

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, FIELDS)
