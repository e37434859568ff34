"""Web filtering, deduplication and language-model workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import language, near, quality, web
from ..sources.tables import check, cut_lineage, table
from .registry import query, values_sql

P, W = T.paragraphs_sql("text"), T.words_sql("text")
#: Rows on which the phrase, word and bracket rules fire; the tables have none.
INLINE = ((-1, "Lorem Ipsum " + "a" * 250), (-2, "see JavaScript here " + "b" * 250), (-3, "javascripts only " + "c" * 250), (-4, "open { brace " + "d" * 250), (-5, "close } brace " + "e" * 250), (-6, "none of them " + "f" * 250))
WITH_INLINE = f"(select doc_id, text from documents union all select doc_id, text from {values_sql(INLINE, 'doc_id, text')})"


def docs(spark, d):
    return check(table(spark, d, "documents"), "documents")


def with_inline(spark, d):
    return docs(spark, d).select("doc_id", "text").union(spark.createDataFrame(list(INLINE), "doc_id bigint, text string"))


def heavy_sql(kind: str) -> str:
    upper = lambda den: f"{T.count_class_sql('p', chr(92) + 'p{Lu}')} > 0.4 * {den}"
    w = T.words_sql("p")
    return {
        "upper": upper(T.count_class_sql("p", r"\p{L}")),
        "upper_chars": upper("length(p)"),
        "symbols": f"(length(replace(replace(p, '...', '#'), '{T.ELLIPSIS}', '#')) - length(replace(replace(replace(p, '...', '#'), '{T.ELLIPSIS}', '#'), '#', ''))) > 0.1 * len({w})",
        "symbols_any": f"{T.count_class_sql('p', r'[\p{S}#&*%@|]')} > 0.1 * len({w})",
        "letterless": rf"len(list_filter({w}, lambda x: not regexp_matches(x, '\p{{L}}'))) > 0.2 * len({w})",
    }[kind]


BAD = " or ".join(f"({heavy_sql(k)})" for k in ("upper", "symbols", "letterless"))
KEPT = f"list_filter({P}, lambda p: not ({BAD}))"

TIER_SQL = values_sql(web.TIERS, "lang, tier")


@query("web_route", f"select tier, lang, count(*) docs, sum(n_chars)::bigint chars from documents join {TIER_SQL} using (lang) group by all")
def web_route(spark, d):
    return web.route_by_tier(docs(spark, d)).groupBy("tier", "lang").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("chars"))


@query("web_min_chars", "select doc_id, n_chars from documents where n_chars >= 200")
def web_min_chars(spark, d):
    return web.min_chars(docs(spark, d)).select("doc_id", "n_chars")


@query("web_drop_phrase", f"select doc_id from {WITH_INLINE} where not contains(lower(text), 'lorem ipsum')")
def web_drop_phrase(spark, d):
    return web.drop_phrase(with_inline(spark, d)).select("doc_id")


@query("web_drop_word", rf"select doc_id from {WITH_INLINE} where not regexp_matches(lower(text), '(^|[^\p{{L}}\p{{N}}])javascript([^\p{{L}}\p{{N}}]|$)')")
def web_drop_word(spark, d):
    return web.drop_word(with_inline(spark, d)).select("doc_id")


@query("web_drop_word_substring", f"select doc_id from {WITH_INLINE} where not contains(lower(text), 'javascript')")
def web_drop_word_substring(spark, d):
    return web.drop_word(with_inline(spark, d), whole=False).select("doc_id")


@query("web_drop_braces", f"select doc_id from {WITH_INLINE} where not regexp_matches(text, '[{{}}]')")
def web_drop_braces(spark, d):
    return web.drop_braces(with_inline(spark, d)).select("doc_id")


RULES = {"upper": lambda p: web.upper_heavy(p), "upper_chars": lambda p: web.upper_heavy(p, denom="chars"), "symbols": lambda p: web.symbol_heavy(p), "symbols_any": lambda p: web.symbol_heavy(p, symbols="any"), "letterless": lambda p: web.letterless_heavy(p)}
for _kind, _rule in RULES.items():
    _sql = f"select lang, sum(len(ps))::bigint paragraphs, sum(len(list_filter(ps, lambda p: {heavy_sql(_kind)})))::bigint dropped from (select lang, {P} ps from documents) group by lang"
    query(f"web_para_{_kind}", _sql)(lambda spark, d, rule=_rule: web.paragraph_counts(docs(spark, d), rule))


@query("web_rebuild", f"select doc_id, md5(array_to_string(k, chr(10))) digest, length(array_to_string(k, chr(10)))::bigint n_chars from (select doc_id, {KEPT} k from documents where n_chars >= 200) where len(k) > 0")
def web_rebuild(spark, d):
    return web.paragraph_rules(web.min_chars(docs(spark, d))).select("doc_id", F.md5("text").alias("digest"), "n_chars")


@query(
    "web_rule_report",
    rf"""with r as (select lang, n_chars, list_filter([case when n_chars < 200 then 'short' end, case when contains(lower(text), 'lorem ipsum') then 'phrase' end,
      case when regexp_matches(lower(text), '(^|[^\p{{L}}\p{{N}}])javascript([^\p{{L}}\p{{N}}]|$)') then 'word' end, case when regexp_matches(text, '[{{}}]') then 'braces' end,
      case when len(list_filter({P}, lambda p: {heavy_sql('upper')})) > 0 then 'upper' end, case when len(list_filter({P}, lambda p: {heavy_sql('symbols')})) > 0 then 'symbols' end,
      case when len(list_filter({P}, lambda p: {heavy_sql('letterless')})) > 0 then 'letterless' end], lambda x: x is not null) reasons from documents)
    select lang, reasons[i] rule, count(*) hits, count(*) filter (where i = 1) first_hits, count(*) filter (where len(reasons) = 1) only_hits, sum(n_chars)::bigint chars from r, unnest(range(1, len(reasons) + 1)) t(i) group by all""",
)
def web_rule_report(spark, d):
    return web.rule_report(docs(spark, d))


@query("web_dedup_exact", "select min(doc_id) doc_id from documents group by text")
def web_dedup_exact(spark, d):
    return web.dedup_exact(docs(spark, d)).select("doc_id")


@query("web_dedup_source", "select min(doc_id) doc_id from documents group by source, text")
def web_dedup_source(spark, d):
    return web.dedup_exact(docs(spark, d), ["source"]).select("doc_id")


@query("web_dedup_normalized", f"select min(doc_id) doc_id from documents group by {T.normalized_sql('text')}")
def web_dedup_normalized(spark, d):
    return web.dedup_normalized(docs(spark, d)).select("doc_id")


@query(
    "web_dedup_paragraphs",
    f"""with p as (select doc_id, i, ps[i] para from (select doc_id, {P} ps from documents), unnest(range(1, len(ps) + 1)) t(i)),
    r as (select *, row_number() over (partition by {T.normalized_sql('para')} order by doc_id, i) n from p)
    select doc_id, md5(string_agg(para, chr(10) order by i)) digest from r where n = 1 group by doc_id""",
)
def web_dedup_paragraphs(spark, d):
    return web.dedup_paragraphs(docs(spark, d)).select("doc_id", F.md5("text").alias("digest"))


PAGE = r"trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&[a-zA-Z]+;|&#[0-9]+;', ' ', 'g'), '[\x20\x09-\x0D]+', ' ', 'g'))"


@query("web_page_text", rf"select page_id, regexp_extract(html, '<html[^>]*lang=.([a-z]+)', 1) lang, {PAGE} as text from pages")
def web_page_text(spark, d):
    return web.html_to_text(table(spark, d, "pages"))


@query("web_concat_sources", f"select origin, count(*) n, count(distinct text) kinds from (select 'documents' origin, text from documents union all select 'pages', {PAGE} from pages) group by origin")
def web_concat_sources(spark, d):
    both = web.concat_sources({"documents": docs(spark, d), "pages": web.html_to_text(table(spark, d, "pages"))})
    return both.groupBy("origin").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("text").alias("kinds"))


@query(
    "web_ladder",
    f"""with k as (select doc_id, lang, source, {KEPT} k from documents where n_chars >= 200 and not regexp_matches(text, '[{{}}]') and not contains(lower(text), 'lorem ipsum') and not contains(lower(text), 'javascript')),
    t as (select doc_id, lang, source, array_to_string(k, chr(10)) t from k where len(k) > 0)
    select doc_id, lang, source, md5(t) digest, length(t)::bigint n_chars from (select *, row_number() over (partition by t order by doc_id) n from t) where n = 1""",
)
def web_ladder(spark, d):
    return web.web_ladder(docs(spark, d)).select("doc_id", "lang", "source", F.md5("text").alias("digest"), "n_chars")


@query(
    "web_near_bruteforce",
    r"""with w as (select doc_id, lang, regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+') w from documents),
    s as (select distinct doc_id, lang, array_to_string(w[i:i + 4], ' ') k from w, unnest(range(1, greatest(len(w) - 3, 2))) t(i) where len(w) > 0),
    n as (select doc_id, count(*) n from s group by doc_id),
    c as (select a.doc_id a, b.doc_id b, count(*) c from s a join s b on a.k = b.k and a.lang = b.lang and a.doc_id < b.doc_id group by all)
    select a, b, round(c / (x.n + y.n - c), 6) jaccard from c join n x on x.doc_id = a join n y on y.doc_id = b where 100 * c >= 75 * (x.n + y.n - c)""",
)
def web_near_bruteforce(spark, d):
    return web.near_pairs(docs(spark, d))


HELD = "doc_id % 5 = 0"
LW = T.letter_words_sql("text")
DW = f"(select doc_id, lang, word, count(*) cnt from (select doc_id, lang, unnest({LW}) word from documents) group by all)"
GRAMS = "unnest(list_concat(list_transform(range(1, length(p) + 1), lambda i: substr(p, i, 1)), list_transform(range(1, length(p)), lambda i: substr(p, i, 2)), list_transform(range(1, length(p) - 1), lambda i: substr(p, i, 3))))"


def nb_sql(said: str | None = None) -> str:
    """Score of every language for every document (or for what is said), by a model of the documents that aren't held out."""
    judged = f"q as {said}, " if said else ""
    of = "q" if said else "dw"
    return f"""with dw as {DW}, {judged}g as (select lang, gram, sum(cnt)::bigint c from (select lang, cnt, {GRAMS} gram from (select lang, '^' || word || '$' p, sum(cnt) cnt from dw where not {HELD} group by all)) group by all),
    t as (select lang guess, sum(c) total from g group by lang), k as (select count(distinct gram) kinds from g),
    wg as (select word, {GRAMS} gram from (select distinct word, '^' || word || '$' p from {of})),
    s as (select word, guess, count(*) n, sum(ln((coalesce(c, 0) + 1) / (total + kinds))) s from wg cross join t cross join k left join g on g.gram = wg.gram and g.lang = t.guess group by all),
    d as (select doc_id, lang, guess, sum(cnt * s) s, sum(cnt * n) n from {of} join s using (word) group by all)"""


NB = nb_sql()


@query("web_langid_nb", f"{NB} select x.doc_id, x.lang, guess predicted from documents x left join (select *, row_number() over (partition by doc_id order by s desc, guess) r from d) y on x.doc_id = y.doc_id and r = 1")
def web_langid_nb(spark, d):
    x = docs(spark, d)
    return language.predict_langid(x, language.fit_langid(x.where(f"not {HELD}"))).select("doc_id", "lang", "predicted")


@query(
    "web_langid_words",
    f"""with dw as {DW}, f as (select lang guess, word from (select lang, word, row_number() over (partition by lang order by sum(cnt) desc, word) r from dw where not {HELD} group by lang, word) where r <= 50),
    v as (select doc_id, lang, guess, sum(cnt)::bigint votes from dw join f using (word) group by all)
    select x.doc_id, x.lang, guess predicted, coalesce(votes, 0)::bigint votes from documents x left join (select *, row_number() over (partition by doc_id order by votes desc, guess) r from v) y on x.doc_id = y.doc_id and r = 1""",
)
def web_langid_words(spark, d):
    x = docs(spark, d)
    return language.vote_langid(x, x.where(f"not {HELD}"))


@query("web_langid_filter", f"{NB} select doc_id, lang from (select *, row_number() over o r, lead(s) over o nxt from d window o as (partition by doc_id order by s desc, guess)) where r = 1 and guess = lang and round((s - coalesce(nxt, s)) / n, 6) >= 0.01")
def web_langid_filter(spark, d):
    x = docs(spark, d)
    return language.filter_lang(x, language.predict_langid(x, language.fit_langid(x.where(f"not {HELD}"))), 0.01).select("doc_id", "lang")


LINES = f"(select doc_id * 100000 + i - 1 doc_id, lang, ps[i] text from (select doc_id, lang, {P} ps from documents), unnest(range(1, len(ps) + 1)) t(i))"


@query("web_langid_paragraphs", f"{nb_sql(f'(select doc_id, lang, word, count(*) cnt from (select doc_id, lang, unnest({LW}) word from {LINES}) group by all)')} select x.doc_id para_id, x.lang, guess predicted from {LINES} x left join (select *, row_number() over (partition by doc_id order by s desc, guess) r from d) y on x.doc_id = y.doc_id and r = 1")
def web_langid_paragraphs(spark, d):
    """The document's method on every paragraph."""
    x = docs(spark, d)
    lines = x.select("doc_id", "lang", F.posexplode(T.paragraphs(F.col("text"))).alias("pos", "text")).withColumn("doc_id", F.col("doc_id") * 100_000 + F.col("pos"))
    return language.predict_langid(lines, language.fit_langid(x.where(f"not {HELD}"))).select(F.col("doc_id").alias("para_id"), "lang", "predicted")


TRUSTED = "(select d.* from documents d join labels using (doc_id) where quality = 1)"
PPL1 = f"""(with dw as {DW}, c as (select lang, word, sum(cnt) c from dw where doc_id in (select doc_id from labels where quality = 1) group by all), z as (select lang, sum(c) total, count(*) kinds from c group by lang)
  select x.doc_id, x.lang, perplexity from documents x left join (select doc_id, round(exp(-sum(cnt * ln((coalesce(c, 0) + 1) / (coalesce(total, 0) + coalesce(kinds, every) + 1))) / sum(cnt)), 6) perplexity
    from dw left join c using (lang, word) left join z on z.lang = dw.lang cross join (select coalesce(sum(kinds), 0) every from z) group by doc_id) y using (doc_id))"""


def trusted(spark, d):
    return docs(spark, d).join(table(spark, d, "labels").where("quality = 1").select("doc_id"), "doc_id", "left_semi")


@query("web_ppl_unigram", f"select doc_id, lang, round(ln(perplexity), 6) log_perplexity from {PPL1}")
def web_ppl_unigram(spark, d):
    return language.perplexity_unigram(docs(spark, d), language.fit_unigram(trusted(spark, d))).select("doc_id", "lang", F.round(F.log("perplexity"), 6).alias("log_perplexity"))


BI = lambda src: f"(select doc_id, lang, ws[i] u, ws[i + 1] w, count(*) cnt from (select doc_id, lang, list_concat(['<s>'], {LW}, ['</s>']) ws from {src}), unnest(range(1, len(ws))) t(i) group by all)"


@query(
    "web_ppl_bigram",
    f"""with b as {BI('documents')}, c as (select lang, u, w, sum(cnt)::bigint c from {BI(TRUSTED)} group by all), x as (select lang, u, sum(c)::bigint cu, count(*) nu from c group by all), n as (select lang, w, count(*) nw from c group by all),
    z as (select lang, count(*) filter (where c = 1) n1, count(*) filter (where c = 2) n2, count(*) types, count(distinct w) kinds from c group by lang),
    p as (select doc_id, b.lang, cnt, n1 / (n1 + 2.0 * n2) d, (coalesce(nw, 0) + 1.0) / (types + kinds + 1) low, c, cu, nu from b left join c using (lang, u, w) left join x on x.lang = b.lang and x.u = b.u left join n on n.lang = b.lang and n.w = b.w join z on z.lang = b.lang)
    select doc_id, lang, round(exp(-sum(cnt * ln(case when cu is null then low else (greatest(coalesce(c, 0) - d, 0) + d * nu * low) / cu end)) / sum(cnt)), 3) perplexity from p group by all""",
)
def web_ppl_bigram(spark, d):
    return language.perplexity_bigram(docs(spark, d), trusted(spark, d)).withColumn("perplexity", F.round("perplexity", 3))


def kneser_ney_sql(n: int) -> str:
    """Log-perplexities of an order-n model; an n-gram's words are w1 to wn, level k has its last k."""
    last = lambda k, upto=n: ", ".join(f"w{i}" for i in range(n - k + 1, upto + 1))
    cut = lambda src: f"(select doc_id, lang, {', '.join(f'ws[i + {k}] w{k + 1}' for k in range(n))}, count(*) cnt from (select doc_id, lang, list_concat({['<s>'] * (n - 1)}, {LW}, ['</s>']) ws from {src}), unnest(range(1, len(ws) - {n - 2})) t(i) group by all)"
    parts = [f"b as {cut('documents')}", f"c{n} as (select lang, {last(n)}, sum(cnt)::bigint c from {cut(TRUSTED)} group by all)"]
    for k in range(n - 1, 0, -1):
        parts.append(f"c{k} as (select lang, {last(k)}, count(*) c from c{k + 1} group by all)")
    parts.append(f"p1 as (select b.*, (coalesce(c, 0) + 1.0) / (types + kinds + 1) p from b left join c1 using (lang, w{n}) join (select lang, sum(c)::bigint types, count(*) kinds from c1 group by lang) using (lang))")
    for k in range(2, n + 1):
        parts.append(f"z{k} as (select lang, case when n1 > 0 then n1 / (n1 + 2.0 * n2) else 0.5 end d from (select lang, count(*) filter (where c = 1) n1, count(*) filter (where c = 2) n2 from c{k} group by lang))")
        parts.append(f"x{k} as (select lang, {last(k, n - 1)}, sum(c)::bigint cu, count(*) nu from c{k} group by all)")
        parts.append(f"p{k} as (select doc_id, lang, {last(n)}, cnt, case when cu is null then p else (greatest(coalesce(c, 0) - d, 0) + d * nu * p) / cu end p from p{k - 1} left join c{k} using (lang, {last(k)}) left join x{k} using (lang, {last(k, n - 1)}) join z{k} using (lang))")
    return f"with {', '.join(parts)} select doc_id, lang, round(-sum(cnt * ln(p)) / sum(cnt), 6) log_perplexity from p{n} group by all"


#: Ids of trusted documents that are broadcast.
MOST_IDS = 10_000_000


def _kneser_ney(n: int):
    def scored(spark, d):
        x = docs(spark, d).fillna("", "text")  # a document without a text says the end mark
        ids = table(spark, d, "labels").where("quality = 1").select("doc_id")
        # Texts stay where they are while the ids fit into memory.
        seen = x.join(F.broadcast(ids) if ids.count() <= MOST_IDS else ids, "doc_id", "left_semi")
        return language.perplexity_kneser_ney(x, seen, n).select("doc_id", "lang", F.round(F.log("perplexity"), 6).alias("log_perplexity"))

    return scored


for _n in (3, 5):
    query(f"web_ppl_order{_n}", kneser_ney_sql(_n))(_kneser_ney(_n))


@query("web_ppl_tail", f"with p as {PPL1} select doc_id, lang from p join (select lang, quantile_cont(perplexity, 2 / 3) bound from p group by lang) using (lang) where perplexity <= bound")
def web_ppl_tail(spark, d):
    return language.perplexity_tail(language.perplexity_unigram(docs(spark, d), language.fit_unigram(trusted(spark, d)))).select("doc_id", "lang")


@query("qual_annotate", "select lang, count(*) n, sum(quality * 5.0)::double total from documents join labels using (doc_id) group by lang")
def qual_annotate(spark, d):
    return quality.annotate(docs(spark, d), table(spark, d, "labels")).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("edu_score").alias("total"))


LETTER_SHARE = rf"round(5.0 * {T.count_class_sql('text', chr(92) + 'p{L}')} / greatest(length(text), 1), 6)::double"
#: Every document's score: half from the label where there is one, the rest from the share of letters.
SCORED = f"(select d.*, round(case when quality is null then {LETTER_SHARE} else 2.5::double * quality + {LETTER_SHARE} / 2 end, 6) edu_score from documents d left join labels using (doc_id))"


def scored(spark, d):
    return quality.all_scores(docs(spark, d), table(spark, d, "labels"))


for _p, _cond in ((1, "edu_score > 2 or lang <> 'en'"), (2, "edu_score > 3"), (3, "edu_score > 3")):
    query(f"qual_gate_p{_p}", f"select doc_id, edu_score from {SCORED} where {_cond}")(lambda spark, d, p=_p: quality.quality_gate(scored(spark, d), p).select("doc_id", "edu_score"))
for _p, _cond in ((1, "edu_score >= 2 or lang <> 'en'"), (2, "edu_score >= 3")):
    query(f"qual_gate_inclusive_p{_p}", f"select doc_id, edu_score from {SCORED} where {_cond}")(lambda spark, d, p=_p: quality.quality_gate(scored(spark, d), p, strict=False).select("doc_id", "edu_score"))
for _tau in (2, 3):
    query(f"web_educational_{_tau}", f"select doc_id from {SCORED} where lang = 'en' and edu_score > {_tau}")(lambda spark, d, t=_tau: web.educational_filter(scored(spark, d).where("lang = 'en'"), float(t)).select("doc_id"))


@query("qual_score_rest")
def qual_score_rest(spark, d):
    """Documents without a label, in every language, scored by the classifier that all labels train."""
    x, labels = docs(spark, d), table(spark, d, "labels")
    model = quality.fit_quality(quality.annotate(x, labels))
    rest = x.join(labels.select("doc_id"), "doc_id", "left_anti").select("doc_id", "lang", "text")
    return quality.score_quality(rest, model).select("doc_id", "lang", F.round("edu_proxy", 3).alias("edu_proxy"))


def tiers_sql(phase: int) -> str:
    """The tiered ladder stage by stage; t1 to t6 are what each stage leaves."""
    tau, gate = (2, "tier <> 'english' or edu_score > 2") if phase == 1 else (3, "edu_score > 3")
    bare = NB.removeprefix("with ")
    return rf"""with {bare}, guess as (select doc_id, guess predicted from d qualify row_number() over (partition by doc_id order by s desc, guess) = 1),
    t0 as (select f.*, coalesce(tier, 'remaining') tier, predicted, perplexity from {SCORED} f left join {TIER_SQL} using (lang) left join guess using (doc_id) left join (select doc_id, perplexity from {PPL1}) using (doc_id)),
    t1 as (select * from t0 where {gate}),
    t2 as (select * from t1 qualify tier = 'high_resource' or row_number() over (partition by tier, case when tier = 'english' then source else '' end, text order by doc_id) = 1),
    t3 as (select * from t2 where tier <> 'remaining' or coalesce(predicted = lang, false)),
    b as (select lang, quantile_cont(perplexity, 2 / 3) bound from t3 where tier <> 'english' group by lang),
    t4 as (select t3.* from t3 left join b using (lang) where tier = 'english' or coalesce(perplexity <= bound, false)),
    t5 as (select * from t4 where n_chars >= 200 and not regexp_matches(text, '[{{}}]') and not contains(lower(text), 'lorem ipsum') and not regexp_matches(lower(text), '(^|[^\p{{L}}\p{{N}}])javascript([^\p{{L}}\p{{N}}]|$)')),
    t6 as (select doc_id, lang, tier, array_to_string(k, chr(10)) text, length(array_to_string(k, chr(10)))::bigint n_chars from (select *, {KEPT} k from t5) where len(k) > 0)"""


def _tiers(spark, d, phase):
    x = docs(spark, d)
    predicted = language.predict_langid(x, language.fit_langid(x.where(f"not {HELD}")))
    return web.tier_ladder(x, scored(spark, d), predicted, language.perplexity_unigram(x, language.fit_unigram(trusted(spark, d))), phase)


for _p in (1, 2):
    query(f"web_ladder_tiers_p{_p}", f"{tiers_sql(_p)} select doc_id, lang, tier, md5(text) digest, n_chars from t6")(lambda spark, d, p=_p: _tiers(spark, d, p)[0].select("doc_id", "lang", "tier", F.md5("text").alias("digest"), "n_chars"))
    query(f"web_ledger_p{_p}", f"{tiers_sql(_p)} " + " union all ".join(f"select {i}::int step, '{s}' stage, tier, count(*) docs, sum(n_chars)::bigint chars from t{i} group by tier" for i, s in enumerate(web.STAGES)))(lambda spark, d, p=_p: _tiers(spark, d, p)[1])


@query("qual_lexicon", f"with c as (select lang, word, sum(cnt) c from {DW} group by all), r as (select *, row_number() over (partition by lang order by c desc, word) rank from c) select a.rank, a.word src_word, b.word tgt_word from r a join r b using (rank) where a.lang = 'en' and b.lang = 'fr'")
def qual_lexicon(spark, d):
    return language.rank_lexicon(docs(spark, d), "en", "fr")


@query(
    "qual_translate",
    f"""with c as (select lang, word, sum(cnt) c from {DW} group by all), r as (select *, row_number() over (partition by lang order by c desc, word) rank from c), l as (select a.word s, b.word t from r a join r b using (rank) where a.lang = 'en' and b.lang = 'de'),
    w as (select item_id, i, ws[i] w from (select item_id, {W} ws from benchmark), unnest(range(1, len(ws) + 1)) t(i))
    select item_id, string_agg(coalesce(t, w), ' ' order by i) as text from w left join l on lower(w) = s group by item_id""",
)
def qual_translate(spark, d):
    """The benchmark rendered in another language through the rank lexicon."""
    return language.translate(table(spark, d, "benchmark"), language.rank_lexicon(docs(spark, d), "en", "de"), "item_id")


@query(
    "qual_report_letters",
    rf"""with s as (select lang, round(5.0 * {T.count_class_sql('text', chr(92) + 'p{L}')} / greatest(length(text), 1), 6) p, quality * 5.0 y from documents join labels using (doc_id)),
    c as (select lang, count(*) filter (where p > 3.75 and y > 3.75) tp, count(*) filter (where p > 3.75 and y <= 3.75) fp, count(*) filter (where p <= 3.75 and y > 3.75) fn, count(*) filter (where p <= 3.75 and y <= 3.75) tn, corr(p, y) r from s group by lang)
    select lang, tp, fp, fn, tn, round(tp / (tp + fp), 6) as precision, round(tp / (tp + fn), 6) recall, round(2.0 * (tp / (tp + fp)) * (tp / (tp + fn)) / ((tp / (tp + fp)) + (tp / (tp + fn))), 6) f1, round(r, 6) pearson from c""",
)
def qual_report_letters(spark, d):
    x = quality.letter_share_score(quality.annotate(docs(spark, d), table(spark, d, "labels")))
    return quality.quality_report(x, "edu_proxy", "edu_score", 3.75)


@query("qual_scorer_regimes")
def qual_scorer_regimes(spark, d):
    """Translate-train, source-only, all-label and per-language training, judged on the same held-out rows of languages other than English."""
    x = cut_lineage(quality.annotate(docs(spark, d), table(spark, d, "labels")).select("doc_id", "lang", "text", "edu_score"))
    train, judged = x.where(f"not {HELD}"), x.where(f"{HELD} and lang <> 'en'")
    english = train.where("lang = 'en'")
    carried = quality.project(train, docs(spark, d), ["fr", "de", "es"]).select("doc_id", "lang", "text", "edu_score")
    out = None
    for name, rows in (("source_only", english), ("translate_train", english.unionByName(carried)), ("all_labels", train)):
        part = quality.quality_report(quality.score_quality(judged, quality.fit_quality(rows)), "edu_proxy", "edu_score", 2.5).withColumn("regime", F.lit(name))
        out = part if out is None else out.unionByName(part)
    for lang in ("fr", "de", "es"):
        own = quality.score_quality(judged.where(F.col("lang") == lang), quality.fit_quality(train.where(F.col("lang") == lang)))
        out = out.unionByName(quality.quality_report(own, "edu_proxy", "edu_score", 2.5).withColumn("regime", F.lit("per_language")))
    return out


COMPONENTS = """with recursive w as (select doc_id, lang, regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+') w from documents),
    s as (select distinct doc_id, lang, array_to_string(w[i:i + 4], ' ') k from w, unnest(range(1, greatest(len(w) - 3, 2))) t(i) where len(w) > 0),
    n as (select doc_id, count(*) n from s group by doc_id),
    c as (select a.doc_id a, b.doc_id b, count(*) c from s a join s b on a.k = b.k and a.lang = b.lang and a.doc_id < b.doc_id group by all),
    e as (select a, b from c join n x on x.doc_id = a join n y on y.doc_id = b where 100 * c >= 75 * (x.n + y.n - c)),
    sym as (select a, b from e union all select b, a from e), reach as (select a, b from sym union select reach.a, sym.b from reach join sym on reach.b = sym.a)"""


@query("web_dedup_near", f"{COMPONENTS} select doc_id from documents where doc_id not in (select a from reach group by a having min(b) < a)")
def web_dedup_near(spark, d):
    return near.dedup_near(docs(spark, d)).select("doc_id")


@query("web_near_components", f"{COMPONENTS} select n.doc_id, least(n.doc_id, coalesce(m, n.doc_id)) component from n left join (select a, min(b) m from reach group by a) on a = n.doc_id")
def web_near_components(spark, d):
    return near.near_components(docs(spark, d))


@query("web_dedup_union", f"select min(origin || ':' || id) id from (select 'documents' origin, doc_id id, text from documents union all select 'pages', page_id, {PAGE} from pages) group by text")
def web_dedup_union(spark, d):
    """Exact dedup over several corpora put together."""
    pages = web.html_to_text(table(spark, d, "pages")).withColumnRenamed("page_id", "id")
    both = web.concat_sources({"documents": docs(spark, d).select(F.col("doc_id").alias("id"), "text"), "pages": pages.select("id", "text")})
    return both.groupBy(F.unhex(F.md5("text")).alias("k")).agg(F.min(F.concat_ws(":", "origin", F.col("id").cast("string"))).alias("id")).select("id")


@query("web_dedup_pass_through", f"select doc_id from (select doc_id, coalesce(tier, 'remaining') tier, text from documents left join {TIER_SQL} using (lang)) qualify tier = 'high_resource' or row_number() over (partition by tier, text order by doc_id) = 1")
def web_dedup_pass_through(spark, d):
    """A tier that arrives deduplicated is left as it is; the others are deduplicated within themselves."""
    x = web.route_by_tier(docs(spark, d))
    return x.where("tier = 'high_resource'").select("doc_id").unionByName(web.dedup_exact(x.where("tier <> 'high_resource'"), ["tier"]).select("doc_id"))


@query("web_ppl_paragraphs", f"""with dw as {DW}, c as (select lang, word, sum(cnt) c from dw where doc_id in (select doc_id from labels where quality = 1) group by all), z as (select lang, sum(c) total, count(*) kinds from c group by lang),
  l as (select doc_id, lang, i - 1 pos, ps[i] text from (select doc_id, lang, {P} ps from documents), unnest(range(1, len(ps) + 1)) t(i)), pw as (select doc_id, pos, lang, unnest({T.letter_words_sql('text')}) word from l)
  select l.doc_id, l.pos, l.lang, round(ln(y.p), 5) log_perplexity from l left join (select doc_id, pos, round(exp(-avg(ln((coalesce(c, 0) + 1) / (total + kinds + 1)))), 6) p from pw left join c using (lang, word) join z using (lang) group by all) y using (doc_id, pos)""")
def web_ppl_paragraphs(spark, d):
    lines = language.perplexity_paragraphs(docs(spark, d), language.fit_unigram(trusted(spark, d)))
    return lines.select("doc_id", "pos", "lang", F.round(F.log("perplexity"), 5).alias("log_perplexity"))
