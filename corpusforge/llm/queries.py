"""The registered queries of this subpackage, one per operator, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import licenses, near_dedup, packing, pii, quality_rules, substring_dedup, token_files, tokens, topk, url_filter

EMPTY_SHA = "e3b0c44298fc1c149afbf4c8996fb92427ae41e4649b934ca495991b7852b855"


def tokenizer_file(name: str) -> bytes:
    """A vocabulary file by the installed package's path; read on the driver, sent with the tasks."""
    import public_tokenizers

    return Path(public_tokenizers.path(name)).read_bytes()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.deduplicated(table(spark, sf_dir, "documents"))


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_file_report(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.json").decode())


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_report(table(spark, sf_dir, "documents"))


def op4_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(table(spark, sf_dir, "embeddings"), lambda v: v % 100 == 0)


def op5_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"))


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return tokens.encode_decode(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return quality_rules.apply_rules(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, piece, n_tokens, shard, bin, capacity, position of every piece of every document."""
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.json").decode())


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url"), url_filter.rules_frame(spark))


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_substring_dedup, op2_token_files, op3_pii, op4_top_k, op5_near_dedup, op6_byte_bpe, op7_quality_rules, op8_packing, op9_url_filter, op10_licenses, pipeline)}

_UNSPACED = quality_rules.UNSPACED.replace("{Is", "{")
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

SQL = {
    "op1_substring_dedup": f"""
with w as (select doc_id, {_WORDS} ws from documents),
win as (select doc_id, i, array_to_string(ws[i:i + 12], ' ') k from w, unnest(range(1, len(ws) - 11)) t(i)),
f as (select k, min(doc_id) lead from win group by k),
gone as (select distinct win.doc_id, win.i + j as p from win join f using (k), range(13) r(j) where f.lead < win.doc_id),
word as (select doc_id, p, ws[p] as word from w, unnest(range(1, len(ws) + 1)) t(p)),
kept as (select word.doc_id, count(*) n, string_agg(word, ' ' order by word.p) s from word anti join gone on gone.doc_id = word.doc_id and gone.p = word.p group by word.doc_id)
select w.doc_id, len(ws)::bigint n_words, (len(ws) - coalesce(n, 0))::bigint n_removed, sha256(coalesce(s, '')) kept_sha256
from w left join kept using (doc_id)""",
    "op4_top_k": """
with v as (select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) x from embeddings
           where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
p as (select q.vec_id query_id, d.vec_id, list_sum(list_transform(range(1, least(len(q.x), len(d.x)) + 1), lambda i: q.x[i] * d.x[i]))::bigint score
      from v q, v d where q.vec_id % 100 = 0 and q.vec_id <> d.vec_id),
r as (select query_id, row_number() over (partition by query_id order by score desc, vec_id) as rank, vec_id, score from p)
select query_id, rank::int as rank, vec_id, score from r where rank <= 10""",
    "op5_near_dedup": """
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') ws from documents),
s as (select distinct doc_id, array_to_string(ws[i:i + 4], ' ') k from w, unnest(range(1, greatest(len(ws) - 3, 2))) t(i) where len(ws) > 0),
n as (select doc_id, count(*) c from s group by doc_id),
common as (select a.doc_id a, b.doc_id b, count(*) c from s a join s b on a.k = b.k and a.doc_id < b.doc_id group by all),
e as (select a, b from common join n x on x.doc_id = a join n y on y.doc_id = b where 100 * common.c >= 75 * (x.c + y.c - common.c)),
sym as (select a, b from e union all select b, a from e),
reach as (select a, b from sym union select reach.a, sym.b from reach join sym on reach.b = sym.a)
select w.doc_id, coalesce(n.c, 0)::bigint n_shingles, least(w.doc_id, coalesce(m.lowest, w.doc_id)) component_id, w.doc_id = least(w.doc_id, coalesce(m.lowest, w.doc_id)) as kept
from w left join n using (doc_id) left join (select a, min(b) lowest from reach group by a) m on m.a = w.doc_id""",
    "op7_quality_rules": f"""
with w as (select doc_id, lang, coalesce(text, '') t, {_WORDS} ws from documents),
g as (select doc_id, i, array_to_string(ws[i:i + 4], ' ') k from w, unnest(range(1, len(ws) - 3)) t(i)),
twice as (select doc_id, k from g group by doc_id, k having count(*) > 1),
rep as (select doc_id, count(distinct i + j) n from g semi join twice using (doc_id, k), range(5) r(j) group by doc_id),
f as (select w.doc_id, len(ws)::bigint n_words, length(array_to_string(ws, ''))::bigint word_chars,
        (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::bigint n_symbols,
        list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) lines,
        len(list_filter(ws, lambda x: lower(x) in ({", ".join(f"'{x}'" for x in sorted(set(quality_rules.STOP_WORDS)))}))) stops,
        coalesce(rep.n, 0)::bigint n_repeat_words, length(regexp_replace(t, '{_UNSPACED}', '', 'g')) unspaced,
        coalesce(regexp_extract(lower(lang), '^[a-z]+') in ({", ".join(f"'{x}'" for x in quality_rules.STOP_LANGUAGES)}), false) judged
      from w left join rep using (doc_id)),
x as (select *, (len(lines) - len(list_distinct(lines)))::bigint n_dup_lines, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed from f)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and n_symbols / n_words <= 0.25 and (word_chars / n_words between 2.0 and 20.0 or 10 * unspaced >= greatest(word_chars, 1))
  and (n_words < 300 or stops / n_words >= 0.005 or not judged) and (len(lines) = 0 or n_dup_lines / len(lines) <= 0.6) as kept
from x""",
    "op9_url_filter": """
with r(r_host, r_path, v) as (values ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
u as (select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end rest from pages),
h as (select page_id, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') host, regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) path from u),
m as (select page_id, arg_max(r_host || r_path, length(r_host || r_path)) rule, arg_max(v, length(r_host || r_path)) v
      from h join r on (host = r_host or ends_with(host, '.' || r_host)) and starts_with(path, r_path) group by page_id)
select h.page_id, host, path, rule, coalesce(v, 'allow') verdict from h left join m using (page_id)""",
}
