"""Column expressions for words, paragraphs and normal forms; each has an SQL text with the same meaning.

Everything here is row-local and built in: no user functions. Regular expressions name explicit
classes that Java's engine and RE2 read alike.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BLANK = " \t\n\x0b\f\r"
#: Accented letters and what they become.
ACCENTED = "àáâãäåçèéêëìíîïñòóôõöøùúûüýÿ"
PLAIN = "aaaaaaceeeeiiiinoooooouuuuyy"
ELLIPSIS = "…"


def words(text: Column) -> Column:
    """Maximal runs without white space."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANK))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, r"[\x20\x09-\x0D]+", -1))


def words_sql(text: str) -> str:
    return rf"regexp_extract_all(coalesce({text}, ''), '[^\x20\x09-\x0D]+')"


def letter_words(text: Column) -> Column:
    """Lower-cased runs of letters."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"(\p{L}+)"), F.lit(1))


def letter_words_sql(text: str) -> str:
    return rf"regexp_extract_all(lower({text}), '\p{{L}}+')"


def paragraphs(text: Column) -> Column:
    """Lines that aren't blank."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n", -1), lambda p: p.rlike(r"[^\x20\x09-\x0D]"))


def paragraphs_sql(text: str) -> str:
    return rf"list_filter(string_split(coalesce({text}, ''), chr(10)), lambda p: regexp_matches(p, '[^\x20\x09-\x0D]'))"


def count_class(text: Column, pattern: str) -> Column:
    """Characters of a class: one pass of the engine, no array of matches."""
    return F.length(text) - F.length(F.regexp_replace(text, pattern, ""))


def count_class_sql(text: str, pattern: str) -> str:
    return f"(length({text}) - length(regexp_replace({text}, '{pattern}', '', 'g')))"


def normalized(text: Column) -> Column:
    """Lower case, no accents, digits as 0, no punctuation or symbols, single spaces."""
    x = F.translate(F.lower(text), ACCENTED, PLAIN)
    x = F.regexp_replace(F.regexp_replace(x, r"\p{N}", "0"), r"[\p{P}\p{S}]", "")
    return F.btrim(F.regexp_replace(x, r"[\x20\x09-\x0D]+", " "))


def normalized_sql(text: str) -> str:
    return rf"trim(regexp_replace(regexp_replace(regexp_replace(translate(lower({text}), '{ACCENTED}', '{PLAIN}'), '\p{{N}}', '0', 'g'), '[\p{{P}}\p{{S}}]', '', 'g'), '[\x20\x09-\x0D]+', ' ', 'g'))"


def uniform(*parts: Column) -> Column:
    """A number in [0, 1) from a hash of the parts: the same under any partitioning and retry."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("double") / 4294967296.0


def uniform_sql(*parts: str) -> str:
    return "(('0x' || substr(md5(concat_ws('|', " + ", ".join(f"({p})::varchar" for p in parts) + ")), 1, 8))::bigint / 4294967296.0)"
