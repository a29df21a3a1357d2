"""Cases that failed before, one for each finding of a review."""

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge import workloads
from lexbridge.llm import decontaminate as D
from lexbridge.llm import jaccard_join as J
from lexbridge.llm.scratch import Scratch
from lexbridge.operators import attention as A
from lexbridge.operators import bank as B
from lexbridge.operators import cooccurrence as C
from lexbridge.operators import facts as G
from lexbridge.operators import inject as I
from lexbridge.operators import model as M
from lexbridge.operators import renewal as R
from lexbridge.operators import train as T
from lexbridge.plans.frames import Frames
from lexbridge.sources.tables import corpus
from lexbridge.streaming import bank as S
from tests.oracle import check


def test_encoder_candidates_read_every_sentence(spark, small):
    rows = workloads.QUERIES["kg_candidates_encoder"](spark, small).collect()
    assert rows and all(r.pivot == (r.w_a, r.w_b, r.w_c)[r.slot] and 0 < r.conf <= 1.000001 for r in rows)


def test_appended_stream_rows_lie_in_files_not_in_the_driver(spark, small):
    out = S.drain(S.event_stream(spark, small).select("event_id"))
    assert out.inputFiles() and out.distinct().count() == spark.read.parquet(f"{small}/events.parquet").count()


def test_greatest_price_of_several_rows_tells_the_least_key(spark, tmp_path):
    one = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    twice = one.unionByName(one.withColumn("l_orderkey", F.col("l_orderkey") + 1_000_000))
    twice.orderBy("l_orderkey").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    run = workloads.QUERIES["op_aggregate"]
    want = {(r.l_returnflag, r.l_linestatus): r.dearest for r in run(spark, "/root/testdata/sf0.001").collect()}
    assert {(r.l_returnflag, r.l_linestatus): r.dearest for r in run(spark, str(tmp_path)).collect()} == want


def test_texts_are_not_shuffled_for_their_trees(spark, small):
    plan = workloads.QUERIES["inject_positions"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(src" not in plan.replace("#", "") and "posexplode(tokens" not in plan


def test_both_layouts_agree_on_null_empty_and_repeated_pivots(spark):
    texts = [("a", "b", 1, ["x", "p", "y", "p"]), ("a", "b", 2, []), ("a", "b", 3, None), ("a", "c", 4, ["p"]), ("a", "b", 5, ["q"])]
    docs = spark.createDataFrame(texts, "src string, tgt string, doc_id long, words array<string>")
    facts = [("a", "b", "p", 2, "l", "m", "p", 2), ("a", "b", "p", 1, "l", "p", "r", 1), ("a", "b", "q", 1, "q", "m", "r", 0)]
    active = spark.createDataFrame(facts, "src string, tgt string, pivot string, b int, w_a string, w_b string, w_c string, slot int")
    laid = lambda how: {r.doc_id: [tuple(t) for t in r.tokens or []] for r in I.inject(docs, active, how).collect()}
    assert laid("map") == laid("join")
    assert laid("map")[5] == [("q", 0, 0, 0), ("m", 1, 1, 0), ("r", 2, 1, 0)]


def test_tables_are_read_where_figures_were_made_up(spark, small):
    for name, read in (("grid_average", "documents"), ("winners", "documents"), ("gain_table", "documents"), ("op_udtf_facts", "pages")):
        assert any(read in f for f in workloads.QUERIES[name](spark, small).inputFiles()), name
    check(spark, workloads.QUERIES["op_udtf_facts"], workloads.ORACLES["op_udtf_facts"], small)


def test_facts_are_weighed_without_a_row_for_each_pair_of_places(spark, small):
    for name in ("att_cooc_matrix", "kg_candidates_cooc", "kg_filtered", "kg_merged"):
        plan = workloads.QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString()
        assert "posexplode(words" not in plan and "sent_ix#" not in "".join(x for x in plan.splitlines() if "hashpartitioning" in x), name


def test_packed_facts_equal_those_of_long_rows_in_any_number_of_buckets(spark):
    texts = [("a", 1, 0, "p q r p p s".split()), ("a", 1, 1, "q p t".split()), ("b", 1, 0, "p q r s".split()), ("a", -7, 0, ["u", "v"]), ("a", 2, 0, "r s q p u v w x y z p q".split()), ("a", 3, 5, ["p"])]
    sents = spark.createDataFrame(texts, "domain string, doc_id long, sent_ix int, words array<string>")
    pool = spark.createDataFrame([("a", "p"), ("a", "q"), ("b", "q"), ("a", "u"), ("a", "absent")], "domain string, word string")
    weights = A.cooccurrence_rows(sents, pool)
    told = lambda df: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in df.collect())
    facts = G.make_facts(weights)
    for buckets in (1, 3):
        assert told(C.cooccurrence_facts(sents, pool, buckets).select(*facts.columns)) == told(facts)
    sums = weights.groupBy("domain", "doc_id", "sent_ix", "i").agg(F.count("*").alias("n"), F.sum("a").alias("total"), F.max("a").alias("top"))
    assert told(C.cooccurrence_sums(sents, pool)) == told(sums)
    stop = spark.createDataFrame([("a", "s")], "domain string, word string")
    merged = G.merge_facts(G.drop_stop_words(G.filter_facts(facts, 0.4), stop))
    assert told(C.cooccurrence_graph(sents, pool, 0.4, stop).select(*merged.columns)) == told(merged)


def test_exact_quantile_lies_between_its_two_ranks(spark):
    of = lambda xs: G.suggest_tau(spark.createDataFrame([(x,) for x in xs], "conf double"), exact=True).first().tau
    assert abs(of([0.2, 0.3, 0.4, 0.9]) - 0.275) < 1e-9 and of([0.25]) == 0.25 and of([0.9, 0.9]) == 0.45 and of([]) == 0.1


def test_neighbours_that_cannot_link_never_become_rows(spark, monkeypatch):
    # 12 texts of one common stretch and of ends of their own: all stand in wide columns, few pairs can link
    common = " ".join(f"c{i}" for i in range(30))
    rows = [(d, common + " " + " ".join(f"e{d}_{i}" for i in range(20))) for d in range(12)] + [(100 + d, common + f" e0_0 f{d}") for d in range(3)]
    seen = []
    keep = J.Scratch.keep

    def noted(self, df, name):
        if name.startswith("pairs-"):
            seen.append(df._jdf.queryExecution().optimizedPlan().toString())
        return keep(self, df, name)

    monkeypatch.setattr(J.Scratch, "keep", noted)
    monkeypatch.setattr(J, "WIDE", 3)
    monkeypatch.setattr(J, "ROUNDS", 2)
    got = {r.doc_id: r.component_id for r in J.link_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {d: 100 if d >= 100 else d for d, _ in rows}
    made = [x for p in seen for x in p.splitlines() if "Generate explode(" in x]
    assert made and all("bit_count" in x for x in made)


def test_words_of_texts_are_not_shuffled_to_be_scored(spark, small):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = workloads.QUERIES["nb_predict"](spark, small)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert not [x for x in plan.splitlines() if "hashpartitioning" in x and "word#" in x]


def test_renewed_pivots_equal_the_history_of_the_banks(spark, small):
    f = Frames(spark, small)
    ev = B.schedule(f.evidence(), ("src", "tgt", "side"), 5, batch=4)
    got = {(r.src, r.tgt, r.block, r["rank"]): (r.word, r.score) for r in R.renewed_pivots(f.docs, ev, f.pool, f.bank(), 0.95, 2, 20).collect()}
    score = B.history(f.bank(), B.updates(ev, f.inc, f.pool), 0.95, 2).groupBy("src", "tgt", "block", "word").agg((F.abs(F.sum("p")) / 2).alias("score")).join(f.pool, ["src", "tgt", "word"])
    rank = F.row_number().over(W.partitionBy("src", "tgt", "block").orderBy(F.desc(F.round("score", 9)), F.desc(F.col("df_s") + F.col("df_t")), "word"))
    want = {(r.src, r.tgt, r.block, r["rank"]): (r.word, r.score) for r in score.withColumn("rank", rank).where("rank <= 20").collect()}
    assert got.keys() == want.keys() and max(k[2] for k in want) > 1
    assert all(got[k][0] == w and abs(got[k][1] - s) < 1e-12 for k, (w, s) in want.items())


def test_renewal_shuffles_no_row_for_each_update(spark, small):
    plan = workloads.QUERIES["bank_refresh_10"](spark, small)._jdf.queryExecution().toString()
    assert "explode(" not in plan and "mapInArrow" in plan.replace("MapInArrow", "mapInArrow")


def test_buckets_weighed_in_passes_tell_the_same_and_leave_one_pass_of_shuffle(spark, small, monkeypatch):
    names = ("kg_confidence_profile", "kg_fact_kinds", "kg_no_stopwords")  # counts, folded graphs and stop words
    monkeypatch.setattr(C, "PER_BUCKET", 1_000)
    for name in names:
        plan = workloads.QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString()
        assert "REPARTITION_BY_NUM" not in plan and "bucket" not in plan, name
        check(spark, workloads.QUERIES[name], workloads.ORACLES[name], small)


def test_latent_space_is_fitted_on_every_passage(spark):
    rng = np.random.default_rng(4)
    texts = [" ".join(f"w{w}" for w in rng.zipf(1.4, rng.integers(20, 150)) % 2000) for _ in range(3600)]
    docs = spark.createDataFrame(list(enumerate([*texts, "", None])), "doc_id long, text string").repartition(3)
    s = D.Settings(rank=12, common=1)
    idf, project = D.latent_space(docs, Scratch(spark, "fit"), s)
    # the same turns with a dense matrix of all passages
    words = [D._codes(next(D._words(pa.record_batch([pa.array([t])], names=["text"])))[2]) for t in texts]
    rows = [w[i : i + D.PASSAGE] for w in words for i in range(0, len(w), D.PASSAGE)]
    a = np.stack([np.bincount(r, minlength=1 << D.BITS) for r in rows]).astype(np.float32)
    assert np.allclose(idf, np.log((len(rows) + 1) / ((a > 0).sum(axis=0) + 1)), atol=1e-6)
    a *= idf
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    x = np.random.default_rng(0).standard_normal((1 << D.BITS, s.rank + s.common + 16)).astype(np.float32)
    for _ in range(s.turns):
        x = np.linalg.qr(a.T @ (a @ x))[0]
    y = a @ x
    want = (x @ np.linalg.eigh(y.T @ y)[1][:, ::-1])[:, s.common : s.common + s.rank]
    got = project / np.where(idf > 0, idf, 1)[:, None]
    assert np.linalg.svd(want.T @ got)[1].min() > 0.999


def test_encoder_encodes_every_text_on_both_sides_of_every_pair(spark, small):
    got = workloads.QUERIES["encoder_vectors"](spark, small).groupBy("src", "tgt").agg(F.count_distinct("doc_id").alias("n")).collect()
    n = {r.domain: r["count"] for r in corpus(spark, small).groupBy("domain").count().collect()}
    assert {(r.src, r.tgt): r.n for r in got} == {(s, t): n[s] + n[t] for s in n for t in n if s != t}


def test_heads_are_fitted_on_every_text_a_block_at_a_time(spark):
    sides = (("S", "train"), ("S", "unlabelled"), ("T", "unlabelled"))
    rows = [(m, "a", "b", side, 100 * k + i, 1 if i % 3 else -1, split, [20 * k + i], [1.0], [60 + 20 * k + i], [1.0], ["p"]) for m in ("aux", "adversarial") for k, (side, split) in enumerate(sides) for i in range(20)]
    rows += [("aux", "a", "b", "T", 900, 1, "train", [121], [1.0], [121], [1.0], ["p"])]
    features, signs = spark.createDataFrame(rows, T._FEATURES), {("a", "b"): {"p": 0.5, "q": -0.5}}
    # a text that no step reads leaves its bucket alone; the pivots' head is zero in the first step, so its block is read again
    read = {"aux": [*range(20), *range(60, 120)], "adversarial": [*range(60)]}
    for steps, bound, methods in ((10, 3, ("aux", "adversarial")), (2, 3, ("adversarial",)), (10, 20, ("aux", "adversarial"))):
        cfg = M.TrainConfig(dims=122, hidden=3, weight_decay=0.0, steps=steps, labelled_rows=bound + 1, unlabelled_rows=bound)
        start = M.new_net(cfg, 2).p["E"].astype(np.float32)
        got = {r.method: r for r in T.fit_heads(features, signs, cfg, 2).collect()}
        assert got.keys() == read.keys()
        for m in methods:
            moved = (pickle.loads(got[m].net)["E"] != start).any(axis=1)
            assert got[m].n_fit == 20 and np.flatnonzero(moved).tolist() == read[m], (steps, bound, m)
