"""Language models, pair cleaning, instruction curation and evaluation, with SQL of the same results."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import account, bpe, evalkit, language, mixture, parallel, posttrain, quality, synth
from ..sources.tables import cut_lineage, table
from .mix_queries import AVAIL, CANDS, LWORDS, MASK, PACK, PAIRED, PS, SAMPLE, STRATIFIED, W, _pairs, _scores_sql, cands, masks, scores, source_scores, weights_sql
from .mix_queries import _sampled as sampled
from .registry import query, values_sql
from .web_queries import BI, COMPONENTS, DW, GRAMS, HELD, P, PPL1, TRUSTED, docs, trusted


def labelled(spark, d):
    return quality.annotate(docs(spark, d), table(spark, d, "labels"))


@query(
    "web_langid_distance",
    f"""with dw as {DW}, wg as (select word, {GRAMS} gram from (select distinct word, '^' || word || '$' p from dw)),
    g as (select lang guess, gram, row_number() over (partition by lang order by sum(cnt) desc, gram) l from dw join wg using (word) where not {HELD} group by lang, gram qualify l <= 300),
    m as (select doc_id, lang, gram, row_number() over (partition by doc_id order by sum(cnt) desc, gram) r from dw join wg using (word) group by doc_id, lang, gram qualify r <= 300),
    s as (select doc_id, lang, guess, sum(300 - abs(r - l))::bigint gain from m join g using (gram) group by all), n as (select doc_id, count(*) n from m group by all)
    select x.doc_id, x.lang, guess predicted, n * 300 - coalesce(gain, 0) distance from documents x left join n using (doc_id) left join (select * from s qualify row_number() over (partition by doc_id order by gain desc, guess) = 1) y using (doc_id)""",
)
def web_langid_distance(spark, d):
    x = docs(spark, d)
    return language.distance_langid(x, x.where(f"not {HELD}"))


@query(
    "web_ppl_backoff",
    f"""with b as {BI('documents')}, c as (select lang, u, w, sum(cnt)::bigint c from {BI(TRUSTED)} group by all), x as (select lang, u, sum(c)::bigint cu from c group by all), v as (select lang, w, sum(c)::bigint cw from c group by all), z as (select lang, sum(c)::bigint total from c group by lang)
    select doc_id, b.lang, round(exp(-sum(cnt * ln(case when c is not null then c / cu else 0.4::double * coalesce(cw, 1) / total end)) / sum(cnt)), 3) perplexity
    from b left join c using (lang, u, w) left join x on x.lang = b.lang and x.u = b.u left join v on v.lang = b.lang and v.w = b.w join z on z.lang = b.lang group by all""",
)
def web_ppl_backoff(spark, d):
    return language.perplexity_backoff(docs(spark, d), trusted(spark, d))


def unigram(spark, d):
    return language.perplexity_unigram(docs(spark, d), language.fit_unigram(trusted(spark, d)))


@query("web_ppl_bands", f"with p as {PPL1} select lang, case when perplexity <= lo then 'head' when perplexity <= hi then 'middle' else 'tail' end band, count(*) n from p join (select lang, quantile_cont(perplexity, 1 / 3) lo, quantile_cont(perplexity, 2 / 3) hi from p group by lang) using (lang) group by all")
def web_ppl_bands(spark, d):
    return language.perplexity_bands(unigram(spark, d)).groupBy("lang", "band").agg(F.count(F.lit(1)).alias("n"))


@query("web_ppl_absolute", f"select doc_id, lang from {PPL1} where perplexity <= case lang when 'en' then 4000 else 2000 end")
def web_ppl_absolute(spark, d):
    return language.perplexity_below(unigram(spark, d), {"en": 4000.0}, 2000.0).select("doc_id", "lang")


LAB = "(select lang, quality * 5.0 y from documents join labels using (doc_id))"


@query("qual_majority", f"select lang, case when g then y > 2.5 else y <= 2.5 end as correct, count(*) n from {LAB} join (select lang, 2 * count(*) filter (where y > 2.5) >= count(*) g from {LAB} group by lang) using (lang) group by all")
def qual_majority(spark, d):
    x = quality.majority_score(labelled(spark, d))
    return x.groupBy("lang", ((F.col("edu_proxy") > 2.5) == (F.col("edu_score") > 2.5)).alias("correct")).agg(F.count(F.lit(1)).alias("n"))


LETTERS = rf"(select lang, quality * 5.0 y, round(5.0 * {T.count_class_sql('text', chr(92) + 'p{L}')} / greatest(length(text), 1), 6)::double s from documents join labels using (doc_id))"


@query("qual_auc_letters", f"with x as {LETTERS}, a as (select lang, y, s, rank() over (partition by lang order by s) + (count(*) over (partition by lang, s) - 1) / 2.0 r from x), b as (select lang, sum(r) filter (where y > 2.5) rs, count(*) filter (where y > 2.5) p, count(*) filter (where y <= 2.5) q from a group by lang) select lang, round(((rs - p * (p + 1) / 2.0) / (p * q))::double, 6) auc from b where p > 0 and q > 0")
def qual_auc_letters(spark, d):
    return quality.area_under_curve(quality.letter_share_score(labelled(spark, d)), "edu_proxy", "edu_score", 2.5)


@query("qual_kept_by_bound", f"select lang, b::double bound, count(*) filter (where s > b) kept, count(*) n from {LETTERS}, unnest([1.0, 2.0, 3.0, 4.0]) t(b) group by all")
def qual_kept_by_bound(spark, d):
    return quality.kept_by_threshold(quality.letter_share_score(labelled(spark, d)), "edu_proxy", (1.0, 2.0, 3.0, 4.0))


def pairs_sql(tgt: str) -> str:
    """The derived pairs, repaired, with both scores."""
    fixed = lambda c: rf"trim(regexp_replace(regexp_replace(replace(translate({c}, '‘’“”', '''''""'), '&amp;', '&'), '[\x00-\x08\x0E-\x1F]', '', 'g'), '[\x20\x09-\x0D]+', ' ', 'g'))"
    sizes = lambda c: f"list_transform({T.words_sql(c)}, lambda x: least(length(x), 12))"
    profile = lambda c: "[" + ", ".join(f"len(list_filter({c}, lambda x: x = {k}))::double" for k in range(1, 13)) + "]"
    return rf"""(with c as (select lang, word, sum(cnt) c from {DW} group by all), r as (select *, row_number() over (partition by lang order by c desc, word) rank from c),
    lex as (select a.word s, b.word t from r a join r b using (rank) where a.lang = 'en' and b.lang = '{tgt}'),
    l as (select doc_id, i - 1 pos, doc_id * 100000 + i - 1 pair_id, ps[i] src_text from (select doc_id, {P} ps from documents where lang = 'en'), unnest(range(1, len(ps) + 1)) t(i)),
    o as (select pair_id, string_agg(coalesce(t, w), ' ' order by i) own from (select pair_id, i, ws[i] w from (select pair_id, {T.words_sql('src_text')} ws from l), unnest(range(1, len(ws) + 1)) u(i)) left join lex on lower(w) = s group by pair_id),
    n as (select *, lead(own) over (partition by doc_id order by pos) nxt from l join o using (pair_id)),
    p as (select pair_id, doc_id, pos, src_text, case when pair_id % 5 = 0 and nxt is not null then nxt when pair_id % 10 = 1 then src_text else own end tgt_text, own ref_text, (not (pair_id % 5 = 0 and nxt is not null or pair_id % 10 = 1))::int is_aligned from n),
    f as (select pair_id, doc_id, pos, is_aligned, {fixed('src_text')} src_text, {fixed('tgt_text')} tgt_text, {fixed('ref_text')} ref_text from p),
    k as (select *, len({T.words_sql('src_text')}) wa, len({T.words_sql('tgt_text')}) wb, length(src_text) la, length(tgt_text) lb, regexp_replace(src_text, '[^0-9]', '', 'g') = regexp_replace(tgt_text, '[^0-9]', '', 'g') dg, {sizes('src_text')} sa, {sizes('tgt_text')} sb from f where src_text <> '' and tgt_text <> ''),
    v as (select *, {profile('sa')} va, {profile('sb')} vb from k)
    select pair_id, doc_id, pos, 'en' src_lang, '{tgt}' tgt_lang, src_text, tgt_text, ref_text, is_aligned,
    round(case when src_text = tgt_text then 0 else 0.3::double * (least(la, lb) / greatest(la, lb)) + 0.4::double * (least(wa, wb) / greatest(wa, wb)) + 0.3::double * dg::int::double end, 6)::double clean_proxy,
    round(list_dot_product(va, vb) / sqrt(list_dot_product(va, va) * list_dot_product(vb, vb)), 6) qe_proxy from v)"""


def lexicon_sql(tgt: str) -> str:
    return f"(with c as (select lang, word, sum(cnt) c from {DW} group by all), r as (select *, row_number() over (partition by lang order by c desc, word) rank from c) select a.word s, b.word t from r a join r b using (rank) where a.lang = 'en' and b.lang = '{tgt}')"


FR, DE, ES = pairs_sql("fr"), pairs_sql("de"), pairs_sql("es")


@query("par_scores", f"select pair_id, is_aligned, md5(tgt_text) digest, clean_proxy, qe_proxy from {FR}")
def par_scores(spark, d):
    return _pairs(spark, d).select("pair_id", "is_aligned", F.md5("tgt_text").alias("digest"), "clean_proxy", "qe_proxy")


@query("par_directions", f"select pair_id, 'from_en' direction, src_lang, tgt_lang, md5(src_text) src, md5(tgt_text) tgt from {DE} union all select pair_id, 'to_en', tgt_lang, src_lang, md5(tgt_text), md5(src_text) from {DE}")
def par_directions(spark, d):
    return parallel.both_directions(_pairs(spark, d, "de")).select("pair_id", "direction", "src_lang", "tgt_lang", F.md5("src_text").alias("src"), F.md5("tgt_text").alias("tgt"))


_KEYS = {"exact": "src_text, tgt_text", "normalized": f"{T.normalized_sql('src_text')}, {T.normalized_sql('tgt_text')}", "source": T.normalized_sql("src_text")}
for _k, _keys in _KEYS.items():
    query(f"par_dedup_{_k}", f"select pair_id from {FR} qualify row_number() over (partition by {_keys} order by clean_proxy desc, pair_id) = 1")(lambda spark, d, k=_k: parallel.dedup_pairs(_pairs(spark, d), k).select("pair_id"))
query("par_thresholds", f"select pair_id, clean_proxy, qe_proxy from {ES} where clean_proxy >= 0.6 and qe_proxy >= 0.7")(lambda spark, d: parallel.filter_pairs(_pairs(spark, d, "es")).select("pair_id", "clean_proxy", "qe_proxy"))
query("par_ablation_clean", f"select pair_id from {FR} where clean_proxy >= 0.5")(lambda spark, d: parallel.filter_pairs(_pairs(spark, d), qe=False).select("pair_id"))
query("par_ablation_qe", f"select pair_id from {FR} where qe_proxy >= 0.7")(lambda spark, d: parallel.filter_pairs(_pairs(spark, d), clean=False).select("pair_id"))
# Totals, not means, are shown: sums of six-digit scores have no rounding ties.
query("par_documents", f"select doc_id, src_lang, tgt_lang, segments, round(c, 6) clean_total, round(q, 6) qe_total from (select doc_id, src_lang, tgt_lang, count(*) segments, sum(clean_proxy) c, sum(qe_proxy) q from {FR} group by all) where c / segments >= 0.5 and q / segments >= 0.7")(
    lambda spark, d: parallel.doc_pairs(_pairs(spark, d)).select("doc_id", "src_lang", "tgt_lang", "segments", F.round(F.col("clean_proxy") * F.col("segments"), 6).alias("clean_total"), F.round(F.col("qe_proxy") * F.col("segments"), 6).alias("qe_total"))
)
query(
    "par_report",
    f"""with x as (select tgt_lang, is_aligned a, (clean_proxy >= case tgt_lang when 'es' then 0.6 else 0.5 end and qe_proxy >= 0.7)::int k from (select * from {FR} union all select * from {ES}))
    select coalesce(tgt_lang, '(all)') tgt_lang, count(*) pairs, sum(k)::bigint kept, round(sum(k * a)::double / sum(k), 6) as precision, round(sum(k * a)::double / sum(a), 6) recall from x group by rollup (tgt_lang)""",
)(lambda spark, d: parallel.pair_report(_pairs(spark, d).unionByName(_pairs(spark, d, "es"))))

_BOTH = "(tgt_lang <> '' and clean_proxy >= 0.5 and qe_proxy >= 0.7)"
_DEDUP = f"(select * from {FR} qualify row_number() over (partition by {_KEYS['normalized']} order by clean_proxy desc, pair_id) = 1)"
_FORMS = {"none": FR, "dedup": _DEDUP, "clean": f"(select * from {FR} where clean_proxy >= 0.5)", "quality": f"(select * from {FR} where qe_proxy >= 0.7)", "both": f"(select * from {FR} where {_BOTH})", "dedup and both": f"(select * from {_DEDUP} where {_BOTH})"}
query("par_ablation", " union all ".join(f"select '{k}' form, count(*) pairs, coalesce(sum(is_aligned), 0)::bigint aligned from {v}" for k, v in _FORMS.items()))(lambda spark, d: parallel.ablation(_pairs(spark, d)))



@query("par_dedup_near", f"""{COMPONENTS.replace('select doc_id, lang, regexp_extract_all(lower(text)', 'select pair_id doc_id, tgt_lang lang, regexp_extract_all(lower(src_text)').replace('from documents)', f'from {FR})')},
    g as (select n.doc_id pair_id, least(n.doc_id, coalesce(m, n.doc_id)) component from n left join (select a, min(b) m from reach group by a) on a = n.doc_id)
    select pair_id from g join {FR} using (pair_id) qualify row_number() over (partition by component order by clean_proxy desc, pair_id) = 1""")
def par_dedup_near(spark, d):
    return parallel.dedup_near_pairs(cut_lineage(_pairs(spark, d))).select("pair_id")


_COVER = f"(select pair_id, round(count(*) filter (where list_contains(there, t)) / nullif(count(t), 0), 6) coverage from (select pair_id, unnest(list_distinct({LWORDS('src_text')})) w, list_distinct({LWORDS('tgt_text')}) there from {FR}) left join {lexicon_sql('fr')} on w = s group by pair_id)"


@query("par_scores_lexicon", f"""select pair_id, coverage, round(case when src_text = tgt_text or list_sort(regexp_extract_all(src_text, 'https?://[^\\x20\\x09-\\x0D]+')) <> list_sort(regexp_extract_all(tgt_text, 'https?://[^\\x20\\x09-\\x0D]+')) then 0::double
      else 1 / (1 + exp(-(6.0::double * coalesce(coverage, 0.5) + 2.0::double * least(length(src_text), length(tgt_text)) / greatest(length(src_text), length(tgt_text)) + (regexp_replace(src_text, '[^0-9]', '', 'g') = regexp_replace(tgt_text, '[^0-9]', '', 'g'))::int - 5.0::double))) end, 6) clean_lexicon_proxy
    from {FR} left join {_COVER} using (pair_id)""")
def par_scores_lexicon(spark, d):
    lexicon = cut_lineage(language.rank_lexicon(docs(spark, d), "en", "fr"))
    x = _pairs(spark, d, lexicon=lexicon).select("pair_id", "src_text", "tgt_text")
    return parallel.clean_score_lexicon(x, lexicon).select("pair_id", "coverage", "clean_lexicon_proxy")


EDITIONS = f"(select *, 2020 + pair_id % 5 edition from {FR})"


@query("sft_mt_items", f"select pair_id, edition from {EDITIONS} where edition <= 2022 and src_text not in (select src_text from {EDITIONS} where edition > 2022)")
def sft_mt_items(spark, d):
    return posttrain.mt_items(_pairs(spark, d).withColumn("edition", 2020 + F.col("pair_id") % 5)).select("pair_id", "edition")


def back_sql(tgt: str, pairs: str) -> str:
    """Targets rendered back into English."""
    lex = f"(with c as (select lang, word, sum(cnt) c from {DW} group by all), r as (select *, row_number() over (partition by lang order by c desc, word) rank from c) select a.word s, b.word t from r a join r b using (rank) where a.lang = '{tgt}' and b.lang = 'en')"
    return f"(select pair_id, string_agg(coalesce(t, w), ' ' order by i) hyp from (select pair_id, i, ws[i] w from (select pair_id, {T.words_sql('tgt_text')} ws from {pairs}), unnest(range(1, len(ws) + 1)) u(i)) left join {lex} on lower(w) = s group by pair_id)"


TRANSLATED = "(" + " union all ".join(f"select pair_id, '{x}' tgt_lang, 'from_en' direction, is_aligned, tgt_text hyp, ref_text ref from {p} union all select pair_id, '{x}', 'to_en', is_aligned, hyp, src_text from {p} join {back_sql(x, p)} using (pair_id)" for x, p in (("fr", FR), ("de", DE), ("es", ES))) + ")"
MT_KEYS = ["pair_id", "tgt_lang", "direction", "is_aligned"]
#: Character n-grams of the registered score.
CHRF_ORDER = 3


def translated(spark, d):
    """Pairs of every target language in both directions, from one landed table of ranks."""
    ranked, out = cut_lineage(language.ranked_words(docs(spark, d), ("en", "fr", "de", "es"))), None
    for tgt in ("fr", "de", "es"):
        part = parallel.translations(_pairs(spark, d, tgt, language.lexicon_of(ranked, "en", tgt)), language.lexicon_of(ranked, tgt, "en"), tgt)
        out = part if out is None else out.unionByName(part)
    return out


def _bare(side: str) -> str:
    return rf"regexp_replace(lower({side}), '[\x20\x09-\x0D]+', '', 'g')"


def _overlap_sql(k: int) -> str:
    """Clipped matches of order k of each row, and how many n-grams either side has."""
    side = lambda c: f"(select rid, substr({c}, i, {k}) g, count(*)::int c from x, unnest(range(1, length({c}) - {k} + 2)) u(i) where h <> r group by all)"
    return f"(select rid, sum(least(gh.c, gr.c))::double m from {side('h')} gh join {side('r')} gr using (rid, g) group by rid)"


def chrf_sql(n: int, source: str | None = None) -> str:
    parts = " union all ".join(f"select x.rid, coalesce(m, 0) / nullif(greatest(length(h) - {k - 1}, 0), 0) p, coalesce(m, 0) / nullif(greatest(length(r) - {k - 1}, 0), 0) q from x left join {_overlap_sql(k)} using (rid) where h <> r" for k in range(1, n + 1))
    return f"""(with x as materialized (select row_number() over () rid, {', '.join(MT_KEYS)}, {_bare('hyp')} h, {_bare('ref')} r from {source or TRANSLATED}),
      s as (select rid, coalesce(sum(p), 0) / {n} p, coalesce(sum(q), 0) / {n} q from ({parts}) group by rid)
      select {', '.join(MT_KEYS)}, round(case when h = r then least(length(h), {n}) / {n}::double else coalesce(5 * p * q / nullif(4 * p + q, 0), 0) end, 6) chrf from x left join s using (rid))"""


@query("eval_mt_chrf", f"select tgt_lang, direction, is_aligned, round(avg(chrf), 5) chrf_proxy, count(*) n from {chrf_sql(CHRF_ORDER)} group by all")
def eval_mt_chrf(spark, d):
    """Both directions of three languages: a shifted or copied target scores below an aligned one."""
    return evalkit.chrf(translated(spark, d), "hyp", "ref", MT_KEYS, CHRF_ORDER).groupBy("tgt_lang", "direction", "is_aligned").agg(F.round(F.avg("chrf_proxy"), 5).alias("chrf_proxy"), F.count(F.lit(1)).alias("n"))


_RENDERED = f"(select pair_id, 'fr' tgt_lang, 'from_en' direction, is_aligned, tgt_text hyp, ref_text ref from {FR})"


@query("par_qe_lexicon", f"select pair_id, is_aligned, chrf qe_lexicon_proxy from {chrf_sql(CHRF_ORDER, _RENDERED)}")
def par_qe_lexicon(spark, d):
    """Variant of the quality estimate: how much of the target's n-grams the lexicon's rendering has."""
    return evalkit.chrf(_pairs(spark, d), "tgt_text", "ref_text", ["pair_id", "is_aligned"], CHRF_ORDER).withColumnRenamed("chrf_proxy", "qe_lexicon_proxy")


def _side(c: str, alias: str) -> str:
    return f"(select rid, k, array_to_string({c}[i:i + k - 1], ' ') g, count(*) {alias} from x, unnest(range(1, 5)) t(k), unnest(range(1, len({c}) - k + 2)) u(i) where h <> r group by all)"


@query(
    "eval_mt_bleu",
    f"""with x as materialized (select row_number() over () rid, tgt_lang, direction, is_aligned, {LWORDS('hyp')} h, {LWORDS('ref')} r from {TRANSLATED}),
    o as (select rid, k, sum(least(ch, coalesce(cr, 0)))::double m, sum(ch)::double t from {_side('h', 'ch')} gh left join {_side('r', 'cr')} gr using (rid, k, g) group by all union all select rid, k, greatest(len(h) - k + 1, 0), greatest(len(h) - k + 1, 0) from x, unnest(range(1, 5)) t(k) where h = r),
    m as (select tgt_lang, direction, is_aligned, k, sum(m) m, sum(t) t from o join x using (rid) where t > 0 group by all),
    p as (select tgt_lang, direction, is_aligned, sum(case when m > 0 then ln(m / t) else -1e9 end) / 4 p from m group by all), s as (select tgt_lang, direction, is_aligned, sum(len(h)) lh, sum(len(r)) lr from x group by all)
    select tgt_lang, direction, is_aligned, round(100 * exp(p + least(0, 1 - lr / lh)), 4) bleu_proxy from p join s using (tgt_lang, direction, is_aligned)""",
)
def eval_mt_bleu(spark, d):
    """Corpus BLEU of the same pairs."""
    return evalkit.bleu(translated(spark, d), "hyp", "ref", ["tgt_lang", "direction", "is_aligned"])


_RUN = f"(select doc_id, lang, n_chars, sum(n_chars) over (order by {T.uniform_sql('doc_id')}, doc_id)::bigint running from documents)"


@query("acct_assign_phase", f"select doc_id, lang, n_chars, running, case when running <= 1000000 then 1 when running <= 2000000 then 2 else 3 end phase from {_RUN}")
def acct_assign_phase(spark, d):
    return account.assign_phase(docs(spark, d).select("doc_id", "lang", "n_chars"), "n_chars", [1_000_000, 2_000_000])


@query("acct_sft_steps", f"select sum(rows)::bigint as rows, sum(tokens)::bigint tokens, 3 * ceil(sum(rows) / 32.0)::bigint steps from (select max(last_row) + 1 as rows, sum(n_tokens) tokens from {PACK} group by shard)")
def acct_sft_steps(spark, d):
    """Steps of tuning: packed rows, not conversations, fill a batch."""
    r = posttrain.pack_report(masks(spark, d)).agg(F.sum("rows").alias("rows"), F.sum("tokens").alias("tokens"))
    return r.withColumn("steps", (account.EPOCHS * F.ceil(F.col("rows") / 32)).cast("bigint"))


for _p, (_en, _code) in mixture.PHASE_SHARES.items():
    _fixed = {"code_math": _code} | ({"higher_quality": mixture.HIGH_SHARE} if _p > 1 else {})
    _names = ", ".join(f"'{k}'" for k in _fixed)
    _case = " ".join(f"when '{k}' then {v}" for k, v in _fixed.items())
    query(f"mix_category_p{_p}", f"select category, round(case category {_case} else {1 - sum(_fixed.values())!r}::double * n / sum(n) filter (where category not in ({_names})) over () end, 6)::double share from (select category, sum(tokens)::double n from {AVAIL} group by category)")(
        lambda spark, d, fixed=_fixed: mixture.category_shares(mixture.available_tokens(docs(spark, d)), fixed)
    )


@query("mix_category_third", f"select category, round(case category when 'parallel' then 0.02 else 0.98 * n / sum(n) filter (where category <> 'parallel') over () end, 6)::double share from (select category, sum(tokens)::double n from {AVAIL} group by category)")
def mix_category_third(spark, d):
    return mixture.category_shares(mixture.available_tokens(docs(spark, d)), {"parallel": mixture.PARALLEL_THIRD})


@query("mix_category_high", f"select category, round(case category when 'higher_quality' then 0.34 else 0.66 * n / sum(n) filter (where category <> 'higher_quality') over () end, 6)::double share from (select category, sum(tokens)::double n from {AVAIL} group by category)")
def mix_category_high(spark, d):
    return mixture.category_shares(mixture.available_tokens(docs(spark, d)), {"higher_quality": mixture.HIGH_SHARE})


@query("mix_joint")
def mix_joint(spark, d):
    """Joint weights for the margins of phase 2 over the tables' languages and categories: a few rows on the driver."""
    cells = [(r["lang"], r["category"], r["tokens"]) for r in mixture.available_tokens(docs(spark, d)).collect()]
    langs = sorted({c[0] for c in cells})
    by_lang = {x: 0.4 if x == "en" else 0.6 / (len(langs) - 1) for x in langs}
    by_cat = {"higher_quality": mixture.HIGH_SHARE, "code_math": 0.07, "parallel": 0.05, "web": 1 - mixture.HIGH_SHARE - 0.12}
    x = mixture.fit_joint(cells, by_lang, by_cat)
    return spark.createDataFrame([(a, c, round(v, 9)) for (a, c), v in sorted(x.items())], "lang string, category string, weight double")


@query("mix_shuffle", f"select doc_id, {T.uniform_sql('doc_id', '0')} shuffle_key from documents")
def mix_shuffle(spark, d):
    return mixture.shuffle_key(docs(spark, d)).select("doc_id", "shuffle_key")


@query("mix_distance", f"with g as (select stratum lang, sum(len({W}))::double n from (select doc_id, stratum from {SAMPLE}) join documents using (doc_id) group by all), r as (select weight, round(coalesce(n / sum(n) over (), 0), 6) a, round(abs(weight - coalesce(n / sum(n) over (), 0)), 6) e from {weights_sql(0.5, 0.05)} w left join g using (lang)) select round(sum(e), 5) l1, round(-sum(case when a > 0 then a * ln(a) end), 5) entropy from r")
def mix_distance(spark, d):
    s, _ = sampled(spark, d)
    weights = mixture.language_weights(mixture.available_tokens(docs(spark, d)), 0.5, 0.05)
    return mixture.mix_distance(mixture.mix_report(s.withColumn("n_tok", F.size(T.words(F.col("text")))), weights, "n_tok"))


@query("tok_balanced_sample", f"select doc_id, lang from documents join (select lang, round(min(n) over () / n, 6) rate from (select lang, sum(len({W}))::double n from documents group by lang)) using (lang) where {T.uniform_sql('doc_id', chr(39) + 'tokenizer' + chr(39), '0')} < rate")
def tok_balanced_sample(spark, d):
    return mixture.balanced_sample(docs(spark, d)).select("doc_id", "lang")


@query("tok_alphabet", f"select c from (select c, n, sum(n) over (order by n desc, c desc) run, sum(n) over () total from (select c, count(*) n from (select unnest(string_split(word, '')) c from (select unnest({T.letter_words_sql('text')}) word from documents)) group by c)) where run - n < 0.9995::double * total")
def tok_alphabet(spark, d):
    """Characters that cover the share of all occurrences; the rest falls back to bytes."""
    return spark.createDataFrame([(c,) for c in bpe.alphabet(bpe.words_of(docs(spark, d)))], "c string")


@query("tok_train_batched")
def tok_train_batched(spark, d):
    """Batched rounds over a spread word table; tests hold the list against one-by-one training."""
    out = bpe.train_bpe_batched(bpe.words_of(docs(spark, d)), 24)
    return spark.createDataFrame([(i, *m) for i, m in enumerate(out)], "rank bigint, left string, right string, freq bigint")


def _trained(spark, d, size):
    x = docs(spark, d)
    train, held = cut_lineage(bpe.words_of(x.where("doc_id % 5 <> 0"))), bpe.words_of(x.where("doc_id % 5 = 0"))
    letters = bpe.alphabet(train)
    return held, [(r["left"], r["right"]) for r in bpe.train_bpe(train, size, letters=letters).orderBy("rank").collect()], {bpe.MARK, *letters}


@query("tok_vocab_sweep")
def tok_vocab_sweep(spark, d):
    held, merges, known = _trained(spark, d, 1200)
    return bpe.vocab_sweep(held, merges, (75, 150, 300, 600, 1200), known)


@query("tok_round_trip", f"select count(*) n, 0::bigint wrong from (select distinct unnest({T.letter_words_sql('text')}) w from documents)")
def tok_round_trip(spark, d):
    _, merges, known = _trained(spark, d, 300)
    back = bpe.decode_words(bpe.encode_words(bpe.words_of(docs(spark, d)), merges, known))
    return back.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("word") != F.col("decoded")).alias("wrong"))


U0 = T.uniform_sql("prompt_id", "cand_no", "0")


@query("sft_collect", f"select 'human' origin, conv_id * 1000 + turn prompt_id, null generator, md5(answer) digest from {PAIRED} union all select 'synthetic', prompt_id, generator, md5(answer) from {CANDS} where judge_proxy >= 9")
def sft_collect(spark, d):
    human = posttrain.human_pairs(table(spark, d, "conversations")).select((F.col("conv_id") * 1000 + F.col("turn")).alias("prompt_id"), F.md5("answer").alias("digest"))
    made = synth.judge_filter(cands(spark, d)).select("prompt_id", "generator", F.md5("answer").alias("digest"))
    return posttrain.collect_instructions({"synthetic": made, "human": human}).select("origin", "prompt_id", "generator", "digest")


@query("sft_license_gate", f"select prompt_id, cand_no from {CANDS} where generator in ('gen0', 'gen2')")
def sft_license_gate(spark, d):
    return posttrain.license_gate(cands(spark, d), ("gen0", "gen2")).select("prompt_id", "cand_no")


@query("sft_dedup", f"select min(conv_id) conv_id from (select conv_id, arg_min(text, turn) as text from conversations where role = 'user' group by conv_id) group by {T.normalized_sql('text')}")
def sft_dedup(spark, d):
    return posttrain.dedup_instructions(table(spark, d, "conversations"))


@query("sft_reward_robustness")
def sft_reward_robustness(spark, d):
    conv = table(spark, d, "conversations")
    keyed = conv.withColumn("k", F.col("conv_id") * 1000 + F.col("turn"))
    said = language.translate(keyed, language.rank_lexicon(docs(spark, d), "en", "de"), "k").withColumnRenamed("text", "said")
    rendered = keyed.join(said, "k", "left").select("conv_id", "turn", "role", F.coalesce("said", "text").alias("text"))
    return posttrain.reward_robustness(scores(spark, d), posttrain.prompt_scores(rendered))


@query(
    "sft_grounded_answer",
    f"""with x as (select doc_id, ps, {LWORDS('ps[1]')} q from (select doc_id, {P} ps from documents) where len(ps) > 1),
    s as (select doc_id, ps[1] instruction, i, ps[i] p, len(list_distinct(list_intersect({LWORDS('ps[i]')}, q))) s from x, unnest(range(2, len(ps) + 1)) t(i)),
    b as (select * from s qualify row_number() over (partition by doc_id order by s desc, i) <= 2)
    select doc_id, md5(instruction) instruction, md5(string_agg(p, chr(10) order by i)) answer from b group by all""",
)
def sft_grounded_answer(spark, d):
    return posttrain.answer_from_doc(docs(spark, d)).select("doc_id", F.md5("instruction").alias("instruction"), F.md5("answer").alias("answer"))


query("sft_pack_none", f"select sum(ceil(n_tokens / 4096.0))::bigint as rows, sum(n_tokens)::bigint tokens, round(sum(n_tokens) / (sum(ceil(n_tokens / 4096.0)) * 4096), 6) fill from {MASK} where n_tokens > 0")(lambda spark, d: posttrain.bin_report(posttrain.pack_bins(masks(spark, d), "none")).drop("fullest"))
for _m in ("next_fit", "first_fit_decreasing"):
    query(f"sft_pack_{_m}")(lambda spark, d, m=_m: posttrain.pack_bins(masks(spark, d), m))
query("sft_scores_by_corpus", f"select corpus, count(*) n, round(avg(complexity), 6) complexity, round(avg(readability), 5) readability from {PS} group by corpus")(lambda spark, d: scores(spark, d).groupBy("corpus").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("complexity"), 6).alias("complexity"), F.round(F.avg("readability"), 5).alias("readability")))

BUCKETS = f"greatest({synth.LEAST_BUCKETS}, (select ceil(count(*) / {synth.BUCKET_ITEMS}.0)::bigint from {CANDS} where cand_no = 1))"
ITEMS = f"(select prompt_id, answer, ('0x' || substr(md5(prompt_id::varchar), 1, 8))::bigint % {BUCKETS} bucket from {CANDS} where cand_no = 1)"


@query(
    "syn_mcq",
    f"""with x as (select prompt_id, answer, [lead(answer, 1) over w, lead(answer, 2) over w, lead(answer, 3) over w] o, floor({T.uniform_sql('prompt_id', '0')} * 4)::bigint gold from {ITEMS} window w as (partition by bucket order by prompt_id))
    select prompt_id, gold, md5(array_to_string(list_concat(o[1:gold], [answer], o[gold + 1:]), chr(10))) options from x where o[3] is not null""",
)
def syn_mcq(spark, d):
    return synth.make_mcq(cands(spark, d).where("cand_no = 1")).withColumn("options", F.md5(F.array_join("options", "\n")))


MCQ = f"""(with x as (select prompt_id, answer, [lead(answer, 1) over w, lead(answer, 2) over w, lead(answer, 3) over w] o, floor({T.uniform_sql('prompt_id', '0')} * 4)::bigint gold from {ITEMS} window w as (partition by bucket order by prompt_id))
    select prompt_id, gold, answer, list_concat(o[1:gold], [answer], o[gold + 1:]) options from x where o[3] is not null)"""


def harness_sql(shots: int) -> str:
    shown = f"(select prompt_id, word, count(*) k from (select prompt_id, unnest(regexp_extract_all(lower(array_to_string(a, ' ')), '[^\\x20\\x09-\\x0D]+')) word from (select prompt_id, array_agg(answer) over (partition by ('0x' || substr(md5(prompt_id::varchar), 1, 8))::bigint % 16 order by prompt_id rows between {shots} preceding and 1 preceding) a from {MCQ}) where a is not null) group by all)" if shots else "(select 0 prompt_id, '' word, 0 k where false)"
    return f"""(with shown as {shown}, size as (select prompt_id, sum(k) size from shown group by all), w as (select word, count(*) c from (select unnest({LWORDS('text')}) word from conversations) group by word), z as (select sum(c) total, count(*) kinds from w),
      said as (select prompt_id, gold, o, unnest({LWORDS('txt')}) word from (select prompt_id, gold, o - 1 o, options[o] txt from {MCQ}, unnest(range(1, 5)) t(o))),
      s as (select said.prompt_id, gold, o, round(avg(ln((coalesce(c, 0) + coalesce(k, 0) + 1.0::double) / (total + coalesce(size, 0) + kinds + 1))), 9) s from said left join w using (word) left join shown using (prompt_id, word) left join size on size.prompt_id = said.prompt_id cross join z group by all)
      select {shots} shots, count(*) n, count(*) filter (where chosen = gold) as "right" from (select prompt_id, gold, arg_max(o, {{'s': s, 'o': -o}}) chosen from s group by all))"""


@query("eval_mcq_harness", "select shots, n, \"right\", round(greatest(0, (\"right\" / n - 0.25) / 0.75) * 100, 6)::double score from (" + " union all ".join(f"select * from {harness_sql(k)}" for k in (25, 10, 5, 0)) + ")")
def eval_mcq_harness(spark, d):
    """Accuracy with 25, 10, 5 and no examples, and the score above chance."""
    words = cut_lineage(language.word_counts(table(spark, d, "conversations").select(F.lower("text").alias("text")), None).withColumnRenamed("cnt", "c"))
    return evalkit.harness(cut_lineage(synth.make_mcq(cands(spark, d).where("cand_no = 1"))), words)


@query("syn_generators", f"select generator, count(*) n, round(avg(length(answer)), 6) chars from (select 'best' generator, arg_max(answer, {{'a': judge_proxy, 'b': {U0}, 'c': cand_no}}) answer from {CANDS} group by prompt_id union all select 'first', answer from {CANDS} where cand_no = 1) group by generator")
def syn_generators(spark, d):
    c = cands(spark, d)
    best = c.join(synth.best_of_n(c).select("prompt_id", "cand_no"), ["prompt_id", "cand_no"], "left_semi")
    mixed = synth.mix_generators({"best": best.select("answer"), "first": c.where("cand_no = 1").select("answer")})
    return mixed.groupBy("generator").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.length("answer")), 6).alias("chars"))


_KINDS = values_sql(synth.KINDS, "kind, category, from_phase, languages")
for _p in (1, 2, 3):
    query(f"mix_sources_p{_p}", f"select kind, category, l lang from (select kind, category, from_phase, string_split(languages, ' ') ls from {_KINDS}), unnest(ls) t(l) where from_phase <= {_p}")(lambda spark, d, p=_p: synth.sources_for_phase(synth.source_kinds(spark), p).select("kind", "category", F.explode("languages").alias("lang")))


def said_sql(rows: str, key: str, text: str, tgt: str) -> str:
    """Texts of rows rendered through the rank lexicon, by key; texts without words have no row."""
    return f"(select {key}, string_agg(coalesce(t, w), ' ' order by i) said from (select {key}, i, ws[i] w from (select {key}, {T.words_sql(text)} ws from {rows}), unnest(range(1, len(ws) + 1)) u(i)) left join {lexicon_sql(tgt)} on lower(w) = s group by {key})"


_HIGH = f"(select doc_id, text from {STRATIFIED} where lang = 'en' and category = 'higher_quality')"
_TARGETS = ("de", "es", "fr")


@query("syn_translate_documents", " union all ".join(f"select doc_id, '{x}' lang, md5(said) digest from {said_sql(_HIGH, 'doc_id', 'text', x)}" for x in _TARGETS))
def syn_translate_documents(spark, d):
    """Higher-quality English documents rendered in the tables' other languages."""
    high = mixture.with_cell(docs(spark, d)).where("category = 'higher_quality'")
    return synth.translate_documents(high, _TARGETS, docs(spark, d)).select("doc_id", "lang", F.md5("text").alias("digest"))


@query("eval_translated_benchmark", " union all ".join(f"select item_id, '{x}' lang, said as text from {said_sql('benchmark', 'item_id', 'text', x)}" for x in _TARGETS))
def eval_translated_benchmark(spark, d):
    """Every item in every target language, with its id."""
    out = None
    for lang in _TARGETS:
        part = language.translate(table(spark, d, "benchmark"), language.rank_lexicon(docs(spark, d), "en", lang), "item_id").withColumn("lang", F.lit(lang))
        out = part if out is None else out.unionByName(part)
    return out


_OPTIONS = f"(select prompt_id * 10 + o - 1 k, options[o] txt from {MCQ}, unnest(range(1, 5)) t(o))"


@query("eval_translated_items", f"select prompt_id, gold, md5(string_agg(coalesce(said, ''), chr(10) order by k)) options from {MCQ} join (select k // 10 prompt_id, k, said from {_OPTIONS} left join {said_sql(_OPTIONS, 'k', 'txt', 'de')} using (k)) using (prompt_id) group by all")
def eval_translated_items(spark, d):
    """Multiple-choice items with all their options rendered in another language."""
    items = synth.make_mcq(cands(spark, d).where("cand_no = 1"))
    return synth.translate_items(items, language.rank_lexicon(docs(spark, d), "en", "de")).select("prompt_id", "gold", F.md5(F.array_join("options", "\n")).alias("options"))


_ENGLISH = "(select doc_id, text, quality * 5.0 y from documents join labels using (doc_id) where lang = 'en')"


@query("qual_project", " union all ".join(f"select doc_id, '{x}' lang, y::double edu_score, md5(said) digest from {_ENGLISH} join {said_sql(_ENGLISH, 'doc_id', 'text', x)} using (doc_id)" for x in ("fr", "de", "es")))
def qual_project(spark, d):
    """English annotations carried over renderings in the other languages."""
    x = docs(spark, d)
    return quality.project(labelled(spark, d).select("doc_id", "lang", "text", "edu_score"), x, ["fr", "de", "es"]).select("doc_id", "lang", "edu_score", F.md5("text").alias("digest"))


_FIRST = f"(select prompt_id, prompt, answer from {CANDS} where cand_no = 1)"


@query("syn_rewrite", f"select prompt_id, answer, 'Please answer: ' || said prompt from {_FIRST} join {said_sql(_FIRST, 'prompt_id', 'prompt', 'fr')} using (prompt_id)")
def syn_rewrite(spark, d):
    c = cands(spark, d).where("cand_no = 1").select("prompt_id", "prompt", "answer")
    return synth.rewrite_questions(c, language.rank_lexicon(docs(spark, d), "en", "fr"))


_PAIRS = f"(select conv_id * 1000 + turn k, prompt, answer from {PAIRED})"


@query("sft_translate_pairs", f"select k // 1000 conv_id, k % 1000 turn, md5(coalesce(p.said, '')) prompt, md5(coalesce(a.said, '')) answer from {_PAIRS} x left join {said_sql(_PAIRS, 'k', 'prompt', 'de')} p using (k) left join {said_sql(_PAIRS, 'k', 'answer', 'de')} a using (k)")
def sft_translate_pairs(spark, d):
    pairs = posttrain.human_pairs(table(spark, d, "conversations"))
    out = posttrain.translate_pairs(pairs, language.rank_lexicon(docs(spark, d), "en", "de"))
    return out.select("conv_id", "turn", F.md5("prompt").alias("prompt"), F.md5("answer").alias("answer"))


RULES = (("has question mark", "regex", "[?]"), ("names data", "keyword", "the"), ("short", "max_words", "40"))


@query("eval_instruction_checks", f"select r as rule, count(*) filter (where ok) passed, count(*) n from (select unnest([{{'r': 'has question mark', 'ok': contains(text, '?')}}, {{'r': 'names data', 'ok': contains(lower(text), 'the')}}, {{'r': 'short', 'ok': len({W}) <= 40}}], recursive := true) from conversations where role = 'assistant') group by r")
def eval_instruction_checks(spark, d):
    return evalkit.ifeval_checks(table(spark, d, "conversations").where("role = 'assistant'"), RULES)


@query("eval_accuracy", f"select lang, {HELD} held, round(avg((guess = lang)::int), 6) accuracy, count(*) n from (select x.doc_id, x.lang, coalesce(guess, '') guess from documents x left join (select doc_id, guess from (with dw as {DW}, f as (select lang guess, word from (select lang, word, row_number() over (partition by lang order by sum(cnt) desc, word) r from dw where not {HELD} group by lang, word) where r <= 50) select doc_id, guess, sum(cnt) votes from dw join f using (word) group by all) qualify row_number() over (partition by doc_id order by votes desc, guess) = 1) using (doc_id)) group by all")
def eval_accuracy(spark, d):
    x = docs(spark, d)
    got = language.vote_langid(x, x.where(f"not {HELD}"))
    return evalkit.accuracy(got.withColumns({"correct": F.coalesce(F.col("predicted") == F.col("lang"), F.lit(False)), "held": F.expr(HELD)}), ["lang", "held"])


_TUNED = values_sql(evalkit.long_rows("tuned"), "model, model_group, task, score")
query("eval_borda_dense_base", f"select model, round(avg(r), 1) borda from (select model, dense_rank() over (partition by model_group, task order by score desc) r from {_scores_sql('base')}) group by model")(lambda spark, d: evalkit.borda(source_scores(spark, d, "base"), dense=True))
query("eval_rank_of", f"select * from (select model, task, rank() over (order by score desc) place from {_TUNED} where task = 'TruthfulQA') where model = 'reference instruct 9B'")(lambda spark, d: evalkit.rank_of(evalkit.score_frame(spark, "tuned"), "reference instruct 9B", "TruthfulQA"))
query("eval_registry", f"select distinct model, model_group = 'E' european, base from {_TUNED} left join {values_sql(evalkit.MADE_FROM, 'model, base').replace('as v(', 'as b(')} using (model) where not starts_with(model, 'reference')")(lambda spark, d: evalkit.model_registry(spark))
_COLS = ", ".join(f"max(score) filter (where task = '{t}')::double as \"{t}\"" for t in evalkit.TUNED_TASKS)
_MEANS = ", ".join(f"round(avg(score) filter (where task = '{t}'), 6)::double as \"{t}\"" for t in evalkit.TUNED_TASKS)
query("eval_scoreboard", f"select model_group, model, {_COLS} from {_TUNED} group by all union all select model_group, '(mean)', {_MEANS} from {_TUNED} group by model_group")(lambda spark, d: evalkit.scoreboard(evalkit.score_frame(spark, "tuned"), evalkit.TUNED_TASKS))
