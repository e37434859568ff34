"""Literals, boundary rows and properties of the engine's own operators."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusforge.operators import account, bpe, evalkit, kneser, language, mixture, parallel, posttrain, synth, web
from corpusforge.plans import curation_queries, mix_queries, surface_queries, web_queries  # noqa: F401
from corpusforge.plans.registry import QUERIES, SQL
from corpusforge.sources.tables import check, table
from corpusforge.streaming import ingest

SF = "/root/testdata/sf0.001"
#: Printed average ranks.
BASE_RANKS = (1.3, 3.0, 4.0, 2.2, 5.8, 4.7, 2.3, 3.7, 3.0, 1.0)
TUNED_RANKS = (1.1, 3.0, 4.1, 3.0, 5.9, 3.9, 4.0, 4.1, 6.4, 3.8, 6.8, 4.8, 4.6, 1.6)


def test_average_ranks(spark):
    for which, scores, printed in (("base", evalkit.BASE_SCORES, BASE_RANKS), ("tuned", evalkit.TUNED_SCORES, TUNED_RANKS)):
        got = {r.model: r.borda for r in evalkit.borda(evalkit.score_frame(spark, which)).collect()}
        assert [got[s[0]] for s in scores] == list(printed)


def test_accounts(spark):
    rows = {r.model: r for r in account.param_account(account.config_frame(spark)).collect()}
    assert rows["reference"].embedding == 524_288_000 and rows["reference"].body == 8_103_743_488
    assert account.embedding_params(256_000, 4096) == 2 * account.embedding_params(128_000, 4096)
    s = account.Schedule()
    at = spark.createDataFrame([(x,) for x in (0, round(0.1 * s.main), round(0.5 * s.main), round(0.9 * s.main), s.main, s.main + s.last)], "s bigint")
    got = [r.r for r in at.select(s.rate(F.col("s")).alias("r")).collect()]
    assert got == pytest.approx([0, 3e-4, 3e-4, 3e-4, 3e-5, 0], abs=1e-8)  # the knots fall between whole steps


def test_boundaries(spark):
    long = "word " * 60
    df = spark.createDataFrame([(1, "é" * 199), (2, "é" * 200), (3, long + "Lorem Ipsum"), (4, long + "JavaScript"), (5, long + "javascripts"), (6, long + "{"), (7, "ABCDefghij"), (8, "ABCDEfghij"), (9, "# " + "w " * 9), (10, "# # " + "w " * 8), (11, "1 a b c d"), (12, "1 2 a b c"), (13, "123")], "doc_id bigint, text string")
    ids = lambda x: {r.doc_id for r in x.select("doc_id").collect()}
    assert not {1} & ids(web.min_chars(df)) and {2} <= ids(web.min_chars(df))
    assert 3 not in ids(web.drop_phrase(df)) and 4 not in ids(web.drop_word(df)) and 5 in ids(web.drop_word(df)) and 5 not in ids(web.drop_word(df, whole=False)) and 6 not in ids(web.drop_braces(df))
    kept = ids(df.where(~web.upper_heavy(F.col("text")))), ids(df.where(~web.symbol_heavy(F.col("text")))), ids(df.where(~web.letterless_heavy(F.col("text"))))
    assert 7 in kept[0] and 8 not in kept[0] and 13 in kept[0]
    assert 9 in kept[1] and 10 not in kept[1]
    assert 11 in kept[2] and 12 not in kept[2]


def test_ladder_anchor_and_idempotence(spark):
    d = table(spark, SF, "documents")
    once = web.web_ladder(check(d, "documents"))
    assert once.count() == 169
    assert web.paragraph_rules(once).select("doc_id", "text").exceptAll(once.select("doc_id", "text")).count() == 0
    with pytest.raises(ValueError):
        check(d.drop("text"), "documents")


def test_partition_count_does_not_matter(spark):
    d = table(spark, SF, "documents")
    want = sorted(r.doc_id for r in web.web_ladder(d).collect())
    for n in (1, 16):
        assert sorted(r.doc_id for r in web.web_ladder(d.repartition(n)).collect()) == want


def test_ladder_plan_has_no_python_or_product(spark):
    d = table(spark, SF, "documents")
    rules = web.paragraph_rules(web.document_rules(d))._jdf.queryExecution().executedPlan().toString()
    for plan in (rules, web.web_ladder(d)._jdf.queryExecution().executedPlan().toString()):
        assert "CartesianProduct" not in plan and "Python" not in plan
    assert "GreaterThanOrEqual(n_chars,200)" in rules
    assert rules.count("...") and rules.count("\\p{Lu}") == 1  # the paragraph rules are worked out once


def test_weights_and_joint_fit(spark):
    avail = mixture.available_tokens(table(spark, SF, "documents"))
    for s in mixture.PHASE_SHARES.values():
        assert sum(r.weight for r in mixture.language_weights(avail, *s).collect()) == pytest.approx(1, abs=1e-5)
    cells = [("en", "web", 5.0), ("en", "code", 1.0), ("fr", "web", 3.0), ("fr", "code", 2.0)]
    x = mixture.fit_joint(cells, {"en": 0.5, "fr": 0.5}, {"web": 0.7, "code": 0.3})
    assert sum(v for (a, _), v in x.items() if a == "en") == pytest.approx(0.5, abs=1e-9)
    with pytest.raises(ValueError):
        mixture.fit_joint([("en", "web", 1.0), ("fr", "code", 1.0)], {"en": 0.5, "fr": 0.5}, {"web": 0.7, "code": 0.3})


def test_merges_by_hand(spark):
    words = [("low", 5), ("lower", 2), ("newest", 6), ("widest", 3)]
    known = set("lowernstid") | {bpe.MARK}
    got = bpe.learn(words, 3, known)
    assert got[0] == ("e", "s", 9) and got[1] == ("es", "t", 9)
    ranks = {(a, b): i for i, (a, b, _) in enumerate(bpe.learn(words, 20, known))}
    for w in ("lowest", "naïve", "widest"):
        assert bpe.decode(bpe.encode_word(w, ranks, known)) == w
    frame = spark.createDataFrame([("en", w, n) for w, n in words], "lang string, word string, cnt bigint")
    trained = [(r.left, r.right, r.freq) for r in bpe.train_bpe(frame, 3).orderBy("rank").collect()]
    assert trained == bpe.learn(words, 3, known)


def test_language_model_sums_to_one(spark):
    df = spark.createDataFrame([(1, "en", "a b a c"), (2, "en", "a b")], "doc_id bigint, lang string, text string")
    counts, sizes = language.fit_unigram(df)
    z = sizes.first()
    assert sum((r.c + 1) / (z.total + z.kinds + 1) for r in counts.collect()) + 1 / (z.total + z.kinds + 1) == pytest.approx(1)


def test_best_of_n_ties(spark):
    df = spark.createDataFrame([(p, c, 7) for p in range(200) for c in (1, 2)], "prompt_id bigint, cand_no bigint, judge_proxy bigint")
    n = synth.best_of_n(df).where("cand_no = 1").count()
    assert 70 < n < 130


def test_stream_equals_batch(spark, tmp_path):
    d = table(spark, SF, "documents")
    d.repartition(3).write.parquet(str(tmp_path / "in"))
    q = ingest.ladder_stream(ingest.document_stream(spark, str(tmp_path / "in"))).writeStream.format("memory").queryName("ladder").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = ingest.ladder_stream(d).select("doc_id", "text")
    got = spark.table("ladder").select("doc_id", "text")
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_batched_training_equals_one_by_one(spark):
    text = "the cat sat on the mat and the dog ate the cat food aaaa aaa abab abcabc newest widest lowest low lower " * 3
    words: dict = {}
    for w in text.split():
        words[w] = words.get(w, 0) + 1
    frame = spark.createDataFrame([("en", w, n) for w, n in words.items()], "lang string, word string, cnt bigint")
    want = bpe.learn(sorted(words.items()), 20, {bpe.MARK, *bpe.alphabet(frame)})
    assert bpe.train_bpe_batched(frame, 20) == want
    assert bpe.train_bpe_batched(frame, 20, listed=5) == want


def test_words_met_once_are_trained_on(spark, tmp_path, monkeypatch):
    rows = [(1, "newest widest lowest", "en"), (2, "newest widest lowest", "fr"), (5, "newest", "en")]
    x = spark.createDataFrame([(i, t, lang, "src0", len(t)) for i, t, lang in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    x.write.parquet(str(tmp_path / "documents.parquet"))
    got = [(r.left, r.right, r.freq) for r in QUERIES["tok_train_bpe"](spark, str(tmp_path)).orderBy("rank").collect()]
    words = [("lowest", 2), ("newest", 3), ("widest", 2)]
    want = bpe.learn(words, 600, {bpe.MARK, *"lowestnid"})
    assert got == want and got[0] == ("e", "s", 7)
    spark.createDataFrame([(1, 0, "user", "widest")], "conv_id bigint, turn bigint, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    fertility = {(r.corpus, r.tokenizer, r.lang): r.fertility for r in QUERIES["tok_fertility_bpe"](spark, str(tmp_path)).collect()}
    assert fertility["documents", "all-300", "en"] == 1 and ("conversations", "english-1200", "en") in fertility
    monkeypatch.setattr(bpe, "SINGLE_ROWS", 2)
    assert [(r.left, r.right, r.freq) for r in QUERIES["tok_train_bpe"](spark, str(tmp_path)).orderBy("rank").collect()] == want


def test_training_looks_at_the_neighbours_of_a_merge_only(monkeypatch):
    draw = random.Random(5)
    for n in range(60):
        monkeypatch.setattr(bpe, "AT_A_TIME", draw.choice([1, 3, 200_000]), raising=False)
        letters = draw.choice(["ab", "abcdefgh", "a\u2581b", "a\u00e9b"])
        words = {"".join(draw.choices(letters, k=draw.randint(0, 700 if n == 7 else 12))): draw.randint(1, 9) for _ in range(25)}
        known = {bpe.MARK, *letters[: draw.randint(1, len(letters))]}
        batches = [(list(words)[i::2], np.array(list(words.values())[i::2])) for i in (0, 1)]
        assert bpe.learn_arrays(iter(batches), 60, known, n % 2 == 0) == bpe.learn(list(words.items()), 60, known, n % 2 == 0)
    monkeypatch.setattr(bpe, "AT_A_TIME", 200_000, raising=False)
    seen, counted = [], bpe.counted_pairs
    monkeypatch.setattr(bpe, "counted_pairs", lambda parts: seen.append(sum(len(k) for k, _ in parts)) or counted(parts))
    words = [f"xy{i:06d}".replace("0", "k").translate(str.maketrans("123456789", "abcdefghi")) + "qrstuvwz" * 40 for i in range(300)]
    assert len(bpe.learn_arrays(iter([(words, np.ones(300, np.int64))]), 5, {bpe.MARK, *"abcdefghijklmnopqrstuvwxyz"})) == 5
    assert sum(seen) < 300 * 300  # every pair of every word a merge meets would be more


def test_mixture_trials_grow_and_keep_languages(spark, tmp_path):
    rows = [(i, f"the cat sat on mat number x{i % 7} and y{i % 3}", "en") for i in range(40)] + [(5, "hyvää päivää", "fi")]
    x = spark.createDataFrame([(i, t, lang, "src0", len(t)) for i, t, lang in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    x.coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    avail = mixture.available_tokens(x)
    assert mixture.trial_tokens(avail) == round(0.2 * (40 * 9 + 2)) and mixture.trial_tokens(avail.union(avail)) == round(0.4 * (40 * 9 + 2))
    for phase in (2, 3):
        got = {(r.task, r.variant): r.score for r in QUERIES[f"mix_trial_p{phase}"](spark, str(tmp_path)).collect()}
        assert set(got) == {(lang, v) for lang in ("en", "fi") for v in (1, 2, 3)}
        assert all(got["fi", v] < got["en", v] < 0 for v in (1, 2, 3))


def test_safe_picks():
    rows = [("a", "b", 9), ("c", "d", 7), ("b", "e", 6), ("f", "g", 5)]
    assert [r[:2] for r in bpe.safe_picks(rows, 0, 9, set())] == [("a", "b"), ("c", "d")]  # (b, e) shares b
    assert [r[:2] for r in bpe.safe_picks(rows[:2], 7, 9, set())] == [("a", "b")]  # a pair below the list may tie
    assert bpe.safe_picks([("a", "b", 1)], 0, 9, set()) == []


def test_bins(spark):
    sizes = [4096, 4097, 1, 4095, 0, 2000, 2096, 9000]
    items = spark.createDataFrame(list(enumerate(sizes)), "conv_id bigint, n_tokens bigint")
    rows = {}
    for mode in ("none", "next_fit", "first_fit_decreasing"):
        got = posttrain.pack_bins(items, mode).toPandas()
        assert got.groupby("conv_id").n_tokens.sum().to_dict() == {i: n for i, n in enumerate(sizes) if n}
        fill = got.groupby(["shard", "bin"]).n_tokens.sum()
        assert fill.max() <= 4096
        rows[mode] = len(fill)
    assert rows["first_fit_decreasing"] <= rows["next_fit"] <= rows["none"] and rows["first_fit_decreasing"] == 7


def test_pair_filters(spark):
    rows = [(1, "a b", "x y", 2020), (2, "c d", "z", 2022), (3, "a b", "q", 2023)]
    pairs = spark.createDataFrame(rows, "pair_id bigint, src_text string, tgt_text string, edition int")
    assert [r.pair_id for r in posttrain.mt_items(pairs).collect()] == [2]  # the first leaks into a later edition
    scored = parallel.qe_score(spark.createDataFrame([("aa bb", "cc dd"), ("a", "bbbb"), ("", "x")], "src_text string, tgt_text string"))
    assert [r.qe_proxy for r in scored.collect()] == [1.0, 0.0, 0.0]


def test_bleu_and_areas(spark):
    pairs = spark.createDataFrame([(1, "g", "a b c d e", "a b c d e"), (2, "h", "a b c d x", "a b c d e f")], "pair_id bigint, k string, h string, r string")
    got = {r.k: r.bleu_proxy for r in evalkit.bleu(pairs, "h", "r", ["k"]).collect()}
    assert got["g"] == 100 and got["h"] == pytest.approx(100 * (4 / 5 * 3 / 4 * 2 / 3 * 1 / 2) ** 0.25 * 2.718281828 ** (1 - 6 / 5), abs=1e-3)
    from corpusforge.operators import quality

    s = spark.createDataFrame([("en", 1.0, 5.0), ("en", 2.0, 0.0), ("en", 3.0, 5.0), ("en", 3.0, 0.0)], "lang string, s double, y double")
    assert quality.area_under_curve(s, "s", "y", 2.5).first().auc == pytest.approx((0 + 1.5) / 4)


def test_robustness_of_word_for_word_renderings(spark):
    r = QUERIES["sft_reward_robustness"](spark, SF).first()
    assert r.reward > 0.7 and r.complexity > 0.7 and r.readability > 0.7


def test_joint_weights_meet_their_margins(spark):
    rows = QUERIES["mix_joint"](spark, SF).collect()
    assert sum(r.weight for r in rows) == pytest.approx(1, abs=1e-6)
    assert sum(r.weight for r in rows if r.category == "higher_quality") == pytest.approx(0.34, abs=1e-6)


def test_larger_vocabularies_need_fewer_pieces(spark):
    rows = QUERIES["tok_vocab_sweep"](spark, SF).orderBy("size").collect()
    assert all(a.fertility >= b.fertility for a, b in zip(rows, rows[1:])) and rows[-1].embedding == 16 * rows[0].embedding


def test_training_words_are_spelled_out_once(spark, monkeypatch):
    calls, alphabet = [], bpe.alphabet
    monkeypatch.setattr(bpe, "alphabet", lambda *a: calls.append(a) or alphabet(*a))
    held, merges, known = curation_queries._trained(spark, SF, 20)
    assert len(calls) == 1 and len(merges) == 20 and {a for a, _ in merges if len(a) == 1} <= known


def test_unknown_pieces_are_counted_before_they_travel(spark):
    out = QUERIES["tok_unknown"](spark, SF)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("filter(ids") > plan.index("Join")
    assert all(0 < r.unknown < r.tokens for r in out.collect())


def test_kneser_ney_orders(spark):
    docs = spark.createDataFrame([(1, "en", "the cat sat on the mat the cat ran"), (2, "en", "the dog sat on a mat"), (3, "en", ""), (4, "en", None), (5, "fr", "le chat"), (6, "en", "wholly unseen words")], "doc_id bigint, lang string, text string")
    seen = docs.where("doc_id <= 2")
    two = {r.doc_id: r.perplexity for r in language.perplexity_kneser_ney(docs, seen, 2).collect()}
    assert two == pytest.approx({r.doc_id: r.perplexity for r in language.perplexity_bigram(docs, seen).collect() if r.perplexity is not None}, abs=1e-5)
    assert two[5] > 1  # no trusted French: smoothed over the words of all languages
    three = {r.doc_id: r.perplexity for r in language.perplexity_kneser_ney(docs, seen, 3).collect()}
    assert three[1] < two[1] and three[6] > three[1]
    assert language.perplexity_kneser_ney(docs.where("false"), seen, 3).count() == 0


def test_ngrams_travel_as_numbers(spark, monkeypatch):
    draw = random.Random(3)
    say = lambda: " ".join(draw.choices(["the", "cat", "sat", "on", "A", "mat", "\u00e9t\u00e9", "x1y"], [9, 5, 4, 3, 3, 2, 1, 1], k=draw.randint(0, 30)))
    rows = [(i, draw.choice(["en", "fr"]), say()) for i in range(60)] + [(60, "en", None), (61, None, "the cat"), (62, "de", "the cat"), (63, "en", "unheard of the cat"), (64, "en", "..."), (7, "fr", "the mat")]
    docs = spark.createDataFrame(rows, "doc_id bigint, lang string, text string").repartition(3)
    seen = docs.where("doc_id % 3 = 0")
    value = lambda x: {(r.doc_id, r.lang): r.perplexity for r in x.collect()}
    want = {n: value(language.joined_kneser_ney(docs, seen, n)) for n in (3, 5)}
    assert len(want[3]) == 63 and (63, "en") in want[3] and (62, "de") in want[3]
    moved = []
    said = language.said_ngrams
    monkeypatch.setattr(language, "said_ngrams", lambda *a: moved.append(a) or said(*a))
    for n, together, a_part in ((3, 2_000_000, 1_000_000), (5, 40, 10)):
        with monkeypatch.context() as m:
            m.setattr(kneser, "TOGETHER", together)
            m.setattr(kneser, "A_PART", a_part)
            assert value(language.perplexity_kneser_ney(docs, seen, n)) == pytest.approx(want[n], rel=1e-9)
    assert value(language.perplexity_kneser_ney(docs, docs.where("false"), 3)) == pytest.approx(value(language.joined_kneser_ney(docs, docs.where("false"), 3)))
    assert len([a for a in moved if a[0] is docs]) == 1  # the joins that it was compared with
    for name in ("MOST_WORDS", "MOST_AFTER"):
        with monkeypatch.context() as m:
            m.setattr(kneser, name, 3)
            assert value(language.perplexity_kneser_ney(docs, seen, 3)) == pytest.approx(want[3], rel=1e-9)


def test_rows_of_a_model_are_in_order(monkeypatch):
    draw = np.random.default_rng(2)
    monkeypatch.setattr(np, "lexsort", None)  # contexts are numbered in order: nothing is sorted again
    for n in (1, 50, 5000):
        columns = [draw.integers(1, 6, n).astype(np.int32) for _ in range(5)]
        *rows, counts = kneser.Model(columns, np.ones(n, np.int32)).rows()
        want, met = np.unique(np.stack(columns, 1), axis=0, return_counts=True)
        assert np.array_equal(np.stack(rows, 1), want) and np.array_equal(counts, met)
        back = kneser.unpack(kneser.pack([*rows, counts]), 6)
        assert all(np.array_equal(a, b) for a, b in zip(back, [*rows, counts]))


def test_documents_without_a_text_have_perplexities(spark, tmp_path):
    rows = [(1, "the cat sat", "en", "src0", 11), (2, None, "en", "src0", 0), (3, "", "en", "src0", 0)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, 1, 0), (2, 1, 0)], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    for n in (3, 5):
        got = {r.doc_id: r.log_perplexity for r in QUERIES[f"web_ppl_order{n}"](spark, str(tmp_path)).collect()}
        assert set(got) == {1, 2, 3} and got[2] == got[3]


def test_documents_without_words_keep_their_rows(spark):
    docs = spark.createDataFrame([(1, "en", "the cat sat on the mat"), (2, "fr", "le chat est sur la table"), (3, "en", "12 34"), (4, "en", None), (5, "xx", "the mat"), (6, None, "cat")], "doc_id bigint, lang string, text string")
    train = docs.where("doc_id <= 2")
    for got in (language.predict_langid(docs, language.fit_langid(train)), language.vote_langid(docs, train), language.distance_langid(docs, train)):
        rows = {r.doc_id: r.predicted for r in got.collect()}
        assert set(rows) == {1, 2, 3, 4, 5, 6} and rows[1] == "en" and rows[2] == "fr" and rows[3] is None and rows[4] is None
    ppl = {r.doc_id: r.perplexity for r in language.perplexity_unigram(docs, language.fit_unigram(train)).collect()}
    assert set(ppl) == {1, 2, 3, 4, 5, 6} and ppl[3] is None and ppl[5] > ppl[1]
    old = language.MOST_BROADCAST
    try:
        language.MOST_BROADCAST = 0
        again = {r.doc_id: (r.predicted, r.margin) for r in language.predict_langid(docs, language.fit_langid(train)).collect()}
    finally:
        language.MOST_BROADCAST = old
    assert again == {r.doc_id: (r.predicted, r.margin) for r in language.predict_langid(docs, language.fit_langid(train)).collect()}


def test_frequency_ranks(spark):
    rows = [("en", w, c) for w, c in (("b", 3), ("a", 3), ("abc", 1), ("abd", 1), ("ab", 1), ("zz", 1), ("top", 9))] + [("fr", "x", 1)]
    got = {(r.lang, r.word): r["rank"] for r in language.frequency_ranks(spark.createDataFrame(rows, "lang string, word string, cnt bigint")).collect()}
    assert got == {("en", "top"): 1, ("en", "a"): 2, ("en", "b"): 3, ("en", "ab"): 4, ("en", "abc"): 5, ("en", "abd"): 6, ("en", "zz"): 7, ("fr", "x"): 1}


def test_gates_keep_unlabelled(spark):
    from corpusforge.operators import quality

    docs = spark.createDataFrame([(1, "en", "plain letters only"), (2, "en", "1234 5678 90"), (3, "fr", "1234 5678 90"), (4, "en", "plain letters only"), (5, "de", None)], "doc_id bigint, lang string, text string")
    labels = spark.createDataFrame([(1, 1), (4, 0)], "doc_id bigint, quality int")
    x = quality.all_scores(docs, labels)
    score = {r.doc_id: r.edu_score for r in x.collect()}
    assert set(score) == {1, 2, 3, 4, 5} and score[1] > 4 and score[4] < 2.5 and score[2] == 0
    ids = lambda p: {r.doc_id for r in quality.quality_gate(x, p).collect()}
    assert ids(1) == {1, 3, 4, 5} and ids(2) == ids(3) == {1}


def test_tiers(spark):
    text = lambda i: f"some quite ordinary words number {i} " * 12
    rows = [(1, "en", "a", text(1)), (2, "en", "a", text(1)), (3, "en", "b", text(1)), (4, "en", "a", text(2)), (5, "es", "a", text(3)), (6, "es", "b", text(3)), (7, "es", "a", text(4)), (8, "fr", "a", text(5)), (9, "fr", "b", text(5)), (10, "fr", "a", "short"), (11, "xx", "a", text(6) + "{"), (12, "es", "a", text(7))]
    docs = spark.createDataFrame([(i, lang, s, t, len(t)) for i, lang, s, t in rows], "doc_id bigint, lang string, source string, text string, n_chars bigint")
    frame = lambda pairs, name, kind: spark.createDataFrame(pairs, f"doc_id bigint, {name} {kind}")
    scores = frame([(i, 2.5 if i != 4 else 2.0) for i in range(1, 13)], "edu_score", "double")
    predicted = frame([(i, "en" if i == 7 else dict((r[0], r[1]) for r in rows)[i]) for i in range(1, 13)], "predicted", "string")
    ppl = frame([(i, 10.0 if i != 12 else 99.0) for i in range(1, 13)], "perplexity", "double")
    out, ledger = web.tier_ladder(docs, scores, predicted, ppl, 1, keep=0.5)
    assert {r.doc_id for r in out.collect()} == {1, 3, 5, 8, 9}
    left = {(r.stage, r.tier): r.docs for r in ledger.collect()}
    assert left["input", "english"] == 4 and left["score", "english"] == 3 and left["dedup", "english"] == 2
    assert left["dedup", "remaining"] == 4 and left["language", "remaining"] == 3 and left["perplexity", "remaining"] == 2 and left["document rules", "remaining"] == 1
    assert left["dedup", "high_resource"] == 3 and left["document rules", "high_resource"] == 2
    assert web.tier_ladder(docs, scores, predicted, ppl, 2)[0].count() == 0


def test_near_dedup_against_pairs(spark):
    import random

    from corpusforge.operators import near

    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(200)]
    base = [[rng.choice(vocabulary) for _ in range(80)] for _ in range(3)]
    rows = [(0, "en", None), (1, "en", " "), (2, "en", "one two"), (3, "fr", "one two"), (4, "en", "one two")]
    for i in range(5, 120):
        w = list(base[i % 3])
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(80)] = rng.choice(vocabulary)
        rows.append((i, "en", " ".join(w)))
    docs = spark.createDataFrame(rows, "doc_id bigint, lang string, text string")
    pairs = [(r.a, r.b) for r in web.near_pairs(docs.where("text is not null")).collect()]
    root = {i: i for i, _, _ in rows if i > 1}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    want = {i: find(i) for i in root}
    for small in (near.SMALL, 2):
        assert {r.doc_id: r.component for r in near.near_components(docs, small=small).collect()} == want
    assert {r.doc_id for r in near.dedup_near(docs).collect()} == {0, 1} | {i for i in want if want[i] == i}
    assert len({*want.values()}) < len(want)


def test_as_of_across_slots(spark):
    from corpusforge.operators import relational

    left = spark.createDataFrame([(1, 7, "2020-01-05"), (2, 7, "2021-06-01"), (3, 7, "2019-01-01"), (4, 8, "2020-01-01"), (5, None, "2020-01-01"), (6, 7, "2020-01-05")], "event_id bigint, k bigint, t string").withColumn("t", F.col("t").cast("timestamp_ntz"))
    right = spark.createDataFrame([(7, "2020-01-04", 1.0), (7, "2020-01-05", 2.0), (7, "2020-03-01", 3.0), (8, "2020-01-02", 9.0)], "k bigint, t string, price double").withColumn("t", F.col("t").cast("timestamp_ntz"))
    for days in (1, 30, 10_000):
        assert {r.event_id: r.price for r in relational.asof_join(left, right, "k", "t", "price", days).collect()} == {1: 2.0, 2: 3.0, 3: None, 4: None, 5: None, 6: 2.0}


def test_text_codec():
    words = [("low", 5), ("lower", 2), ("newest", 6), ("widest", 3)]
    merges = bpe.learn(words, 20, set("lowernstid") | {bpe.MARK})
    codec = bpe.TextCodec(tuple((a, b) for a, b, _ in merges), tuple("lowernstid"))
    pieces, ready = codec.pieces(), codec.prepared()
    for t in ("newest lower", "  two  spaces\n\tand\r lines ", "naïve ▁ mark ▁▁x", "", " ", "日本\u3000x\u2003", "low" * 50):
        assert codec.decode(codec.encode(t, ready, {}), pieces) == t
    assert len(codec.encode(" newest", ready, {})) == 1
    bare = bpe.TextCodec(codec.merges, codec.alphabet, byte_fallback=False)
    ids = bare.encode("low é low", bare.prepared(), {})
    assert 0 in ids and bare.decode(ids, bare.pieces()) == "low \ufffd low"
    unknown = bpe.learn([("éé", 9), ("low", 2)], 5, set("low") | {bpe.MARK}, byte_fallback=False)
    assert all(bpe.UNKNOWN not in m[:2] for m in unknown)


def test_cells_hold_their_shares(spark):
    avail = mixture.available_tokens(table(spark, "/root/testdata/sf0.01", "documents"))  # every cell has documents
    for phase in ("p2", "p3"):
        for shares, fixed in zip(mixture.TRIALS[phase], mixture.TRIAL_CATEGORIES[phase]):
            rows = mixture.cell_weights(avail, *shares, fixed).collect()
            assert sum(r.weight for r in rows) == pytest.approx(1, abs=1e-5)
            assert sum(r.weight for r in rows if r.lang == "code_math") == pytest.approx(shares[1], abs=1e-6)
            for k, v in fixed.items():
                assert sum(r.weight for r in rows if r.category == k) == pytest.approx(v, abs=1e-4)
    third, second = (mixture.cell_weights(avail, *s, f).collect() for s, f in list(zip(mixture.TRIALS["p3"], mixture.TRIAL_CATEGORIES["p3"]))[:0:-1])
    assert third != second


def test_every_document_has_a_cell(spark):
    x = spark.createDataFrame([(1, "en", "src0", "a b"), (2, None, "src16", "c"), (3, "fr", None, "d e f"), (4, "fr", "elsewhere", "g")], "doc_id bigint, lang string, source string, text string")
    rows = {(r.lang, r.category): (r.tokens, r.docs) for r in mixture.available_tokens(x).collect()}
    assert rows == {("en", "web"): (2, 1), ("und", "code_math"): (1, 1), ("fr", "web"): (4, 2)}
    got = mixture.sample_to_budget(x, spark.createDataFrame([("en", 1.0), ("code_math", 2.0), ("fr", 1.0)], "lang string, rate double")).collect()
    assert sorted(r.doc_id for r in got) == [1, 2, 2, 3, 4]


def test_harness_and_few_shots(spark):
    items = spark.createDataFrame([(i, 1, ["x y", "right words here", "p q", "m n"]) for i in range(40)], "prompt_id bigint, gold bigint, options array<string>")
    words = spark.createDataFrame([("x", 5), ("y", 5)], "word string, c bigint")
    none, many = (evalkit.mcq_eval(items, words, k, buckets=1).agg(F.count_if("correct")).first()[0] for k in (0, 25))
    assert none == 0 and many == 34  # from six examples on: they raise what is like them
    score = evalkit.harness(items, words, (0,)).first()
    assert score.score == 0 and score.n == 40


def test_chrf_counts_are_clipped(spark):
    x = spark.createDataFrame([(1, "aaaa", "a"), (2, "ab c", "abc"), (3, "", ""), (4, "ABC", "abc"), (5, "xyz", "abc")], "pair_id bigint, h string, r string")
    got = {r.pair_id: r.chrf_proxy for r in evalkit.chrf(x, "h", "r", ["pair_id"], 2).collect()}
    p, q = (1 / 4) / 2, 1 / 2
    assert got[1] == pytest.approx(5 * p * q / (4 * p + q), abs=1e-6) and got[2] == got[4] == 1 and got[3] == got[5] == 0


def test_curation_reasons(spark):
    got = QUERIES["sft_curate"](spark, SF).groupBy("reason").count().collect()
    assert {r.reason for r in got} >= {"kept", "licence", "low prompt"}


def test_streams_join(spark, tmp_path):
    docs = spark.createDataFrame([(i, f"text {i}", "en" if i % 2 else "fr", f"src{i}", 6) for i in range(6)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.write.parquet(str(tmp_path / "in"))
    ran = lambda df, name: df.writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start().awaitTermination(120)
    static = spark.createDataFrame([("en", "english")], "lang string, tier string")
    ran(ingest.with_static(ingest.document_stream(spark, str(tmp_path / "in")), static, "lang"), "enriched")
    assert {(r.doc_id, r.tier) for r in spark.table("enriched").collect()} == {(i, "english" if i % 2 else None) for i in range(6)}
    at = lambda m: f"2020-01-01 00:{m:02d}:00"
    for name, rows in (("asked", [(1, at(0)), (2, at(1)), (3, at(2))]), ("answered", [(1, at(5)), (2, at(50)), (9, at(3))])):
        spark.createDataFrame(rows, "key bigint, t string").select("key", F.col("t").cast("timestamp").alias("t")).write.parquet(str(tmp_path / name))
    read = lambda name: spark.readStream.schema("key bigint, t timestamp").parquet(str(tmp_path / name))
    ran(ingest.matched_streams(read("asked"), read("answered"), "key", "t", "10 minutes"), "matched")
    assert [(r.key, r.waited) for r in spark.table("matched").collect()] == [(1, 300)]
    counted = ingest.token_ledger(ingest.document_stream(spark, str(tmp_path / "in")), {"en": 5}).writeStream.format("memory").queryName("ledger").outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    counted.awaitTermination(180)
    last = {r.lang: (r.tokens, r.taken, r.full) for r in spark.table("ledger").collect()}
    assert last["en"] == (6, 3, True) and last["fr"] == (6, 3, False)


def test_bucketed_tables_join_without_shuffle(spark):
    from corpusforge.sources.tables import write_bucketed

    x = spark.range(1000).select("id", (F.col("id") % 7).alias("v"))
    try:
        a, b = write_bucketed(x, "corpusforge_a", "id", 8), write_bucketed(x, "corpusforge_b", "id", 8)
        plan = a.join(b.hint("merge"), "id")._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and a.join(b, "id").count() == 1000
    finally:
        spark.sql("drop table if exists corpusforge_a")
        spark.sql("drop table if exists corpusforge_b")


def test_shared_folder_is_asked_for(spark):
    from corpusforge.sources import tables

    class Cluster:
        conf, sparkContext = type("C", (), {"get": staticmethod(lambda *a: None)}), type("S", (), {"master": "yarn"})

    with pytest.raises(ValueError):
        tables.shared_folder(Cluster)


def test_every_sql_has_a_query():
    assert set(SQL) <= set(QUERIES) and len(QUERIES) > 90


def test_array_training_and_encoding_agree_with_the_plain_forms():
    import random

    import numpy as np

    draw = random.Random(5)
    for letters, known, fallback in (("ab", "ab", True), ("abé<unk>▁\0", "ab<", True), ("abé<unk>", "ab<unk>", False)):
        rows = sorted({"".join(draw.choice(letters) for _ in range(draw.randint(1, 12))): draw.randint(1, 9) for _ in range(200)}.items())
        known = {bpe.MARK, *known}
        want = bpe.learn(rows, 60, known, fallback)
        batches = [([w for w, _ in part], np.array([n for _, n in part])) for part in (rows[:50], rows[50:])]
        assert bpe.learn_arrays(batches, 60, known, fallback) == want
        merges = [(a, b) for a, b, _ in want]
        ranks, sizes = bpe.Ranks(merges, known), (0, 5, 20, 60)
        table = ranks.symbols.table(known, fallback)
        flat = bpe.spell_all([bpe.SET_MARK + w for w, _ in rows], table)
        (x, n), by = ranks.run(flat), ranks.run(flat, sizes)[1]
        for j, (w, _) in enumerate(rows):
            plain = lambda k: bpe.encode_word(w, {p: i for i, p in enumerate(merges[:k])}, known, fallback)  # noqa: B023, E731
            assert [ranks.symbols.names[i] for i in x.s[x.start[j] : x.start[j] + n[j]]] == plain(60)
            assert [by[i][j] for i in range(len(sizes))] == [len(plain(k)) for k in sizes]


def test_an_encoding_pass_counts_all_sizes(spark):
    words = spark.createDataFrame([("low", 3), ("lower", 2), ("newest", 4)], "word string, cnt bigint")
    merges = [(bpe.MARK, "l"), ("o", "w"), (bpe.MARK + "l", "ow")]
    got = {r.word: list(r.n) for r in bpe.count_pieces(words, merges, {bpe.MARK, *"lowernst"}, (0, 1, 3)).collect()}
    assert got == {"low": [4, 3, 1], "lower": [6, 5, 3], "newest": [7, 7, 7]}


def test_accounts_and_ranks_read_a_table(spark):
    for name in ("acct_params", "acct_phase_steps", *[f"acct_lr_{k}" for k in ("constant", "cosine", "trapezoid", "two_phase")], "eval_borda_base", "eval_borda_tuned", "eval_borda_all_base", "eval_borda_all_tuned", "eval_borda_dense_base", "eval_leads_base"):
        assert any("documents" in f for f in QUERIES[name](spark, SF).inputFiles()), name


def test_documents_are_laid_over_the_calendar(spark):
    docs = spark.createDataFrame([(i, 10) for i in range(404)], "doc_id bigint, n_chars bigint")
    s = account.Schedule()
    rows = account.laid_over(docs, "n_chars").orderBy("step").collect()
    assert rows[0].step == 0 and rows[0].lr == 0 and rows[-1].step == 403 * (s.main + s.last) // 404 and [r.phase for r in rows] == sorted(r.phase for r in rows)
    steps = {r.phase: (r.tokens, r.steps) for r in account.phase_steps_of(docs, "n_chars", sequences=1, length=100).collect()}
    assert steps == {1: (3600, 36), 2: (400, 4), 3: (40, 1)}


def test_sources_are_scored_by_their_letters(spark):
    docs = spark.createDataFrame([("a", "en", "AbcD12"), ("a", "en", "xy"), ("b", "en", None), ("c", "fr", "1é")], "source string, lang string, text string")
    groups = spark.createDataFrame([("a", "code")], "source string, category string")
    got = {(r.model, r.model_group, r.task): r.score for r in evalkit.source_scores(docs, groups).collect()}
    assert got == {("a", "code", "en letters"): 75.0, ("a", "code", "en lower"): 66.6667, ("c", "web", "fr letters"): 50.0, ("c", "web", "fr lower"): 100.0}


def test_distances_shuffle_no_document(spark):
    docs = spark.createDataFrame([(1, "en", "the cat sat on the mat"), (2, "fr", "le chat été 12"), (3, "en", "12")], "doc_id bigint, lang string, text string")
    found = language.distance_langid(docs, docs.where("doc_id < 3"), top=9)
    assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
    from collections import Counter

    def profile(text):
        grams = Counter(p[i : i + n] for w in text.split() for p in [f"^{w}$"] for n in (1, 2, 3) for i in range(len(p) - n + 1))
        return sorted(grams, key=lambda g: (-grams[g], g))[:9]

    en, fr = profile("the cat sat on the mat"), profile("le chat été")
    gain = {1: {"en": 81}, 2: {"fr": 81}, 3: {}}
    got = {r.doc_id: (r.predicted, r.distance) for r in found.collect()}
    assert got == {1: ("en", 9 * len(en) - gain[1]["en"]), 2: ("fr", 9 * len(fr) - gain[2]["fr"]), 3: (None, None)}
    crossed = sum(9 - abs(en.index(g) - fr.index(g)) for g in en if g in fr)
    only = language.distance_langid(docs.where("doc_id = 1"), docs.where("doc_id = 2"), top=9).first()
    assert (only.predicted, only.distance) == ("fr", 81 - crossed)


def test_pairs_are_rendered_and_scored_where_they_are_read(spark, monkeypatch):
    """Neither a word nor an n-gram of the pairs is shuffled, and a lexicon too large to travel gives the same rows."""
    docs = spark.createDataFrame([(1, "en", "The cat\n\nsat on https://a.b\nThe  the cat."), (2, "en", "on cat\nCAT on 7"), (3, "en", None)], "doc_id bigint, lang string, text string")
    lexicon = spark.createDataFrame([("the", "le"), ("cat", "chat"), ("on", "sur")], "src_word string, tgt_word string")
    back = lexicon.toDF("tgt_word", "src_word")

    def made():
        pairs = parallel.derived_pairs(docs, "fr", lexicon)
        both = parallel.translations(pairs, back, "fr")
        return pairs, parallel.clean_score_lexicon(pairs, lexicon), both, evalkit.chrf(both, "hyp", "ref", ["pair_id", "direction"], 3), evalkit.bleu(both, "hyp", "ref", ["direction"])

    found = made()
    for x in found[:4]:
        assert "Exchange" not in x._jdf.queryExecution().executedPlan().toString()
    assert found[4]._jdf.queryExecution().executedPlan().toString().count("Exchange hash") == 1  # of sums
    rows = [sorted(map(tuple, x.collect()), key=str) for x in found]
    got = {r.pair_id: (r.tgt_text, r.ref_text, r.is_aligned) for r in found[0].collect()}
    assert got == {100_000: ("sat sur https://a.b", "le chat", 0), 100_001: ("sat on https://a.b", "sat sur https://a.b", 0), 100_002: ("le le cat.", "le le cat.", 1), 200_000: ("chat sur 7", "sur chat", 0), 200_001: ("CAT on 7", "chat sur 7", 0)}
    assert {r.pair_id: r.coverage for r in found[1].collect()} == {100_000: 0, 100_001: 0, 100_002: 1, 200_000: 1, 200_001: 0}
    monkeypatch.setattr(language, "MOST_BROADCAST", 2)
    assert [sorted(map(tuple, x.collect()), key=str) for x in made()] == rows


def test_matches_are_counted_exactly():
    from collections import Counter

    import numpy as np

    draw = np.random.default_rng(3)
    for kinds in (2, 5, 1 << 30):  # the last needs its n-grams numbered anew
        h, r = [[draw.integers(0, 3, int(n)) * (kinds // 3 + 1) for n in draw.integers(0, 9, 40)] for _ in range(2)]
        got = evalkit.clipped_matches(np.concatenate(h), np.array([len(x) for x in h]), np.concatenate(r), np.array([len(x) for x in r]), 4)
        grams = lambda x, k: Counter(tuple(x[i : i + k].tolist()) for i in range(len(x) - k + 1))
        assert got.tolist() == [[(grams(x, k) & grams(y, k)).total() for x, y in zip(h, r)] for k in range(1, 5)]


def test_near_pairs_compare_classes_and_lose_none(spark, monkeypatch):
    """Copies meet nobody but as one class, common beginnings go last, and the pairs are those of all sets compared."""
    import random

    draw = random.Random(7)
    base = [[f"w{draw.randint(0, 400)}" for _ in range(40)] for _ in range(6)]
    texts = [" ".join(base[i % 6][:30] + (["x" + str(i)] if i % 4 == 0 else []) + base[i % 6][30:]) for i in range(24)] + ["a common phrase of five words " + " ".join(b) for b in base] + ["one two", "One  two", "", None]
    docs = spark.createDataFrame([(i, "en" if i % 11 else "fr", t) for i, t in enumerate(texts)], "doc_id bigint, lang string, text string")
    words = [(t or "").lower().split() for t in texts]
    sets = [{tuple(w[i : i + 5]) for i in range(max(len(w) - 4, 1))} if w else set() for w in words]
    lang = lambda i: bool(i % 11)
    want = sorted((i, j, round(len(sets[i] & sets[j]) / len(sets[i] | sets[j]), 6)) for j in range(len(texts)) for i in range(j) if sets[i] and sets[j] and lang(i) == lang(j) and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]))
    assert len(want) > 40
    for crowd in (100, 1):
        monkeypatch.setattr(web, "CROWD", crowd)
        assert sorted(map(tuple, web.near_pairs(docs).collect())) == want
    compared = []
    monkeypatch.setattr(web.near, "checked", lambda pairs, s, percent, f=web.near.checked: compared.append(pairs.count()) or f(pairs, s, percent))
    copies = spark.createDataFrame([(i, "en", texts[0] + " end" * (i == 50)) for i in range(51)], "doc_id bigint, lang string, text string")
    assert web.near_pairs(copies).count() == 51 * 50 // 2 and compared == [1]


def test_near_pairs_that_share_too_little_in_their_heads_are_not_checked(spark, monkeypatch):
    """A common phrase brings no pair to the exact check; without broadcasts the pairs are the same."""
    from corpusforge.operators import near

    phrase = " ".join(f"common{i}" for i in range(10))
    texts = [phrase + " " + " ".join(f"d{i}w{j}" for j in range(60)) for i in range(40)]
    texts += [texts[0] + " end", "one two three", "one two three"]
    docs = spark.createDataFrame([(i, "en", t) for i, t in enumerate(texts)], "doc_id bigint, lang string, text string")
    want = [(0, 40, round(66 / 67, 6)), (41, 42, 1.0)]
    compared = []
    monkeypatch.setattr(web.near, "checked", lambda pairs, s, percent, f=near.checked: compared.append(pairs.count()) or f(pairs, s, percent))
    assert sorted(map(tuple, web.near_pairs(docs).collect())) == want and compared == [1]
    for module in (web, near):
        monkeypatch.setattr(module, "MOST_BROADCAST", 0)
    assert sorted(map(tuple, web.near_pairs(docs).collect())) == want


def test_a_set_goes_once_to_a_tile(spark, monkeypatch):
    """30 near copies are 435 pairs, and their sets go to the exact check 30 times; tiles of any size lose no pair."""
    import random

    from corpusforge.operators import near

    draw = random.Random(5)
    sets = {i: sorted(draw.sample(range(120), 100)) for i in range(30)} | {i: sorted(draw.sample(range(1000, 1020), 18)) for i in range(40, 60)}
    pairs = [(i, j) for j in sets for i in sets if i < j and (i < 40) == (j < 40)]
    share = lambda i, j: len({*sets[i]} & {*sets[j]})
    want = sorted((i, j, share(i, j), len(sets[i]), len(sets[j])) for i, j in pairs if 100 * share(i, j) >= 75 * (len(sets[i]) + len(sets[j]) - share(i, j)))
    assert 0 < len(want) < len(pairs)
    both = spark.createDataFrame(pairs, "a bigint, b bigint"), spark.createDataFrame([*sets.items()], "id bigint, h array<bigint>")
    sent = []
    monkeypatch.setattr(near, "cut_lineage", lambda df, f=near.cut_lineage: (sent.append(df.count()) if df.columns == ["tile", "id"] else None) or f(df))
    for tile, most in ((256, 50), (4, 50 * 14)):
        monkeypatch.setattr(near, "TILE", tile)
        assert sorted(map(tuple, near.checked(*both, 75).collect())) == want
        assert sent.pop() <= most
