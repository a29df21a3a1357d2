"""Worked examples, by hand arithmetic."""

import pytest
from pyspark.sql import functions as F

from lexbridge.operators import attention as A
from lexbridge.operators import bank as B
from lexbridge.operators import facts as G
from lexbridge.operators import inject as I
from lexbridge.operators import metrics as M
from lexbridge.operators import pivots as P
from lexbridge.plans import paper_tables as PT


def test_polarity_of_three_against_one(spark):
    docs = spark.createDataFrame([(i, "good", "N1", 1 if i < 3 else -1, "train") for i in range(4)], "doc_id long, text string, domain string, label int, split string")
    assert P.polarity(P.word_counts(P.incidence(docs))).first().p == 0.5


def test_pair_score_cancels_opposite_signs(spark):
    pool = spark.createDataFrame([("S", "T", "a", 9, 9), ("S", "T", "b", 9, 9)], "src string, tgt string, word string, df_s long, df_t long")
    pol = spark.createDataFrame([("S", "a", 0.5), ("T", "a", -0.5), ("S", "b", -0.4), ("T", "b", -0.6)], "domain string, word string, p double")
    got = {r.word: r.score for r in P.pair_score(pool, pol).collect()}
    assert got["a"] == 0 and got["b"] == pytest.approx(0.5)
    assert P.top_pivots(P.pair_score(pool, pol), 1).first().word == "b"


def bank_of(spark, p, labels):
    bank = spark.createDataFrame([("S", "T", "S", "w", p)], "src string, tgt string, side string, word string, p double")
    ups = spark.createDataFrame([("S", "T", "S", "w", i // 2, i, x) for i, x in enumerate(labels)], "src string, tgt string, side string, word string, step long, doc_id long, label int")
    return bank, ups


@pytest.mark.parametrize("labels,want", [([-1], 0.17), ([-1, 1], 0.253)])
def test_update_rule(spark, labels, want):
    bank, ups = bank_of(spark, 0.3, labels)
    assert B.td_exact(bank, ups, 0.9).first().p == pytest.approx(want)


def test_all_forms_of_the_update_agree_with_the_loop(spark):
    labels = [1, 1, -1, 1, -1, -1, -1, 1, 1]
    p = 0.2
    for x in labels:
        p = 0.8 * p + 0.2 * x
    bank, ups = bank_of(spark, 0.2, labels)
    exact = B.td_exact(bank, ups, 0.8).first()
    assert exact.p == pytest.approx(p) and exact.n_updates == 9 and -1 <= exact.p <= 1
    for size in (1, 2, 3):
        assert B.td_fold(bank, B.td_blocks(ups, 0.8, size), 0.8).first().p == pytest.approx(p)
    assert B.td_tail(bank, ups, 0.8, 100).first().p == pytest.approx(p)
    hist = {r.block: r.p for r in B.history(bank, ups, 0.8, 1).collect()}
    assert hist[4] == pytest.approx(p)


def test_keep_share_takes_one_of_two_names():
    assert B.keep_share(alpha=0.9) == 0.9 and B.keep_share(rate=0.1) == pytest.approx(0.9)
    with pytest.raises(ValueError):
        B.keep_share(0.9, 0.1)


def test_pseudo_labels_are_strictly_over_the_threshold(spark):
    s = spark.createDataFrame([(1, 0.89), (2, 0.9), (3, 0.91), (4, 0.05)], "doc_id long, p_pos double")
    assert {r.doc_id: r.label for r in B.pseudo_label(s, 0.9).collect()} == {3: 1, 4: -1}


def test_first_scores_are_the_source_polarity(spark):
    pool = spark.createDataFrame([("S", "T", "a", 9, 9), ("S", "T", "b", 9, 9)], "src string, tgt string, word string, df_s long, df_t long")
    pol = spark.createDataFrame([("S", "a", -0.7)], "domain string, word string, p double")
    got = {r.word: r.score for r in B.refresh(B.init_banks(pool, pol), pool, 5).collect()}
    assert got == {"a": pytest.approx(0.7), "b": 0}


MATRIX = [[0.0] * 5, [0.0] * 5, [0.0] * 5, [0.05, 0.40, 0.10, 0.0, 0.45], [0.0] * 5]


def test_fact_of_a_five_word_sentence(spark):
    df = spark.createDataFrame([(["a", "b", "c", "d", "e"], MATRIX)], "words array<string>, m array<array<double>>")
    f = df.select(G.fact_of(F.col("words"), F.col("m"), F.lit(3)).alias("f")).first().f
    assert (f.w_a, f.w_b, f.w_c, f.slot) == ("b", "d", "e", 1) and f.conf == pytest.approx(0.85)


def test_fact_leaves_out_the_function_word(spark):
    words = ["it", "makes", "things", "simple", "great"]
    m = [[0.0] * 5] * 4 + [[0.1, 0.3, 0.1, 0.45, 0.05]]
    f = spark.createDataFrame([(words, m)], "words array<string>, m array<array<double>>").select(G.fact_of(F.col("words"), F.col("m"), F.lit(4)).alias("f")).first().f
    assert {f.w_a, f.w_b, f.w_c} == {"makes", "simple", "great"}


def test_head_and_piece_means(spark):
    heads = [[[1.0, 0.0, 0.0], [0.2, 0.3, 0.5], [0.0, 0.5, 0.5]], [[0.0, 1.0, 0.0], [0.4, 0.1, 0.5], [1.0, 0.0, 0.0]]]
    df = spark.createDataFrame([(heads, [0, 1, 1])], "att array<array<array<double>>>, owner array<int>")
    r = df.select(A.head_mean(F.col("att")).alias("m"), A.piece_mean(A.head_mean(F.col("att")), F.col("owner")).alias("w")).first()
    assert r.m[1] == pytest.approx([0.3, 0.2, 0.5])
    assert r.w[0] == pytest.approx([0.5, 0.25]) and r.w[1] == pytest.approx([(0.3 + 0.5) / 2, (0.2 + 0.5 + 0.25 + 0.25) / 4])


def tree(spark, words, facts, strategy="map"):
    docs = spark.createDataFrame([("S", "T", 1, words)], "src string, tgt string, doc_id long, words array<string>")
    g = spark.createDataFrame([("S", "T", *f) for f in facts], "src string, tgt string, pivot string, b int, w_a string, w_b string, w_c string, slot int")
    return I.inject(docs, g, strategy).select("tokens", I.strip(F.col("tokens")).alias("back"), I.visible(F.col("tokens")).alias("v")).first()


@pytest.mark.parametrize("strategy", ["map", "join"])
def test_branch_and_next_word_share_a_position(spark, strategy):
    r = tree(spark, ["good", "book", "today"], [("good", 1, "good", "makes", "easy", 0)], strategy)
    assert [t.tok for t in r.tokens] == ["good", "makes", "easy", "book", "today"]
    assert [t.pos for t in r.tokens] == [0, 1, 2, 1, 2]
    assert [t.branch for t in r.tokens] == [0, 1, 1, 0, 0]
    assert r.back == ["good", "book", "today"]
    assert r.v[1] == [True, True, True, False, False] and r.v[3] == [True, False, False, True, True]


def test_branches_before_and_around_a_pivot(spark):
    r = tree(spark, ["x", "good"], [("good", 1, "a", "b", "good", 2), ("good", 2, "c", "good", "d", 1)])
    assert [(t.tok, t.pos) for t in r.tokens] == [("x", 0), ("a", 3), ("b", 2), ("c", 2), ("good", 1), ("d", 2)]


def test_text_without_pivot_is_unchanged(spark):
    r = tree(spark, ["p", "q"], [("good", 1, "good", "makes", "easy", 0)])
    assert [(t.tok, t.pos, t.branch) for t in r.tokens] == [("p", 0, 0), ("q", 1, 0)]


def test_truncation_drops_branches_first(spark):
    docs = spark.createDataFrame([("S", "T", 1, ["good", "book"])], "src string, tgt string, doc_id long, words array<string>")
    g = spark.createDataFrame([("S", "T", "good", 1, "good", "makes", "easy", 0)], "src string, tgt string, pivot string, b int, w_a string, w_b string, w_c string, slot int")
    cut = lambda n: [t.tok for t in I.inject(docs, g).select(I.truncate(F.col("tokens"), n).alias("t")).first().t]
    assert cut(3) == ["good", "makes", "book"] and cut(2) == ["good", "book"] and cut(1) == ["good"]


def test_published_averages_winners_and_gains(spark):
    avg = {r.method: r.average for r in M.grid_average(PT.frame(spark, "near")).collect()}
    assert avg["full"] == pytest.approx(91.59, abs=0.02) and avg["plain"] == pytest.approx(90.70, abs=0.02)
    assert avg["full"] - avg["plain"] == pytest.approx(0.89, abs=0.02)
    won = {(r.pair, r.method) for r in M.winners(PT.frame(spark, "near")).collect()}
    assert ("E-D", "posttrain") in won and len([w for w in won if w[1] in ("inject", "full")]) == 11
    far = {r.method: r.average for r in M.grid_average(PT.frame(spark, "far")).collect()}
    assert far["full"] == max(far.values())


def test_higher_threshold_never_adds_facts(spark):
    facts = spark.createDataFrame([("T", 0.1 * i) for i in range(10)], "domain string, conf double")
    kept = [G.filter_facts(facts, t).count() for t in (0.1, 0.3, 0.45)]
    assert kept == sorted(kept, reverse=True)
