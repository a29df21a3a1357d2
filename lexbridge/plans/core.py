"""Registered queries of text, pivots, banks, closed-form classifiers and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from lexbridge.functions import text as X
from lexbridge.operators import bank as B
from lexbridge.operators import metrics as M
from lexbridge.operators import naive_bayes as NB
from lexbridge.operators import pivots as P
from lexbridge.operators import renewal as R
from lexbridge.plans.frames import ALPHA, BANK, CORPUS, EVIDENCED, INC, K, MIN_DF, NAIVE, PAIRS, POL, POOL, PSEUDO, SENTENCES, SEED, WORDS, Frames, td_sql, with_
from lexbridge.sources.stage import stage
from lexbridge.sources.tables import DOMAINS, corpus, html_text, table

INSULTS = ["moron", "stupid", "trash", "loser", "worthless", "clown", "scum"]
QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


# ---------------------------------------------------------------- text


@query(with_(CORPUS, SENTENCES, select="SELECT doc_id, domain, sent_ix::INTEGER AS sent_ix, length(sentence)::INTEGER AS n_chars FROM sentences"))
def text_sentences(spark, sf_dir):
    return X.sentences(corpus(spark, sf_dir), "domain").select("doc_id", "domain", "sent_ix", F.length("sentence").alias("n_chars"))


@query(with_(CORPUS, select=r"SELECT word, count(*) AS n, count(DISTINCT doc_id) AS docs FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM corpus) GROUP BY word"))
def text_words(spark, sf_dir):
    words = corpus(spark, sf_dir).select("doc_id", F.explode(X.word_list(F.col("text"))).alias("word"))
    return words.groupBy("word").agg(F.count("*").alias("n"), F.count_distinct("doc_id").alias("docs"))


@query(with_(CORPUS, select=r"SELECT piece, count(*) AS n FROM (SELECT substr(w, (i * 4 + 1)::BIGINT, 4) AS piece FROM (SELECT w, unnest(range((length(w) + 3) // 4)) AS i FROM (SELECT unnest(regexp_extract_all(lower(text), '\p{L}+')) AS w FROM corpus))) GROUP BY piece"))
def text_pieces(spark, sf_dir):
    pieces = corpus(spark, sf_dir).select(F.explode(F.flatten(X.pieces(X.word_list(F.col("text"))))).alias("piece"))
    return pieces.groupBy("piece").agg(F.count("*").alias("n"))


@query(with_(CORPUS, select=r"SELECT token, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '\p{L}+|[^\p{L}\s.,]+')) AS token FROM corpus) WHERE NOT regexp_matches(token, '\p{L}') GROUP BY token"))
def text_symbols(spark, sf_dir):
    tokens = corpus(spark, sf_dir).select(F.explode(X.word_list(F.col("text"), symbols=True)).alias("token"))
    return tokens.where(~F.col("token").rlike(r"\p{L}")).groupBy("token").agg(F.count("*").alias("n"))


@query()
def text_phrases(spark, sf_dir):
    return X.phrases(corpus(spark, sf_dir))


@query(with_(CORPUS, select="SELECT domain, count(*) AS docs, count(label) AS labelled, count(*) FILTER (WHERE label = 1) AS positive FROM corpus GROUP BY domain"))
def domain_counts(spark, sf_dir):
    return corpus(spark, sf_dir).groupBy("domain").agg(F.count("*").alias("docs"), F.count("label").alias("labelled"), F.count_if(F.col("label") == 1).alias("positive"))


@query(with_(CORPUS, select="SELECT domain, split, count(*) AS docs FROM corpus GROUP BY ALL"))
def split_counts(spark, sf_dir):
    return corpus(spark, sf_dir).groupBy("domain", "split").agg(F.count("*").alias("docs"))


@query()
def html_text_of_pages(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", html_text(F.col("html")).alias("text"))


# ---------------------------------------------------------------- pivots


@query(with_(CORPUS, INC, select="SELECT domain, word, df FROM wc"))
def pivot_incidence_df(spark, sf_dir):
    return Frames(spark, sf_dir).counts.select("domain", "word", "df")


@query(with_(CORPUS, INC, PAIRS["all"], POOL, select="SELECT src, tgt, word, df_s, df_t FROM pool"))
def pivot_pool(spark, sf_dir):
    return Frames(spark, sf_dir, "all").pool


@query(with_(CORPUS, INC, select=f"SELECT word FROM wc WHERE domain = 'N1' AND df >= {MIN_DF} INTERSECT SELECT word FROM wc WHERE domain = 'N3' AND df >= {MIN_DF}"))
def pivot_pool_intersect(spark, sf_dir):
    often = Frames(spark, sf_dir).counts.where(F.col("df") >= MIN_DF)
    return often.where("domain = 'N1'").select("word").intersect(often.where("domain = 'N3'").select("word"))


@query(with_(CORPUS, INC, POL, select="SELECT domain, word, n_pos, n_neg, p FROM pol"))
def pivot_polarity(spark, sf_dir):
    return Frames(spark, sf_dir).pol


@query(with_(CORPUS, select=r"""SELECT domain, word, n_pos, n_neg, (n_pos - n_neg)::DOUBLE / (n_pos + n_neg) AS p FROM (
  SELECT domain, word, count(*) FILTER (WHERE label = 1) AS n_pos, count(*) FILTER (WHERE label = -1) AS n_neg
  FROM (SELECT domain, label, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM corpus) GROUP BY ALL) WHERE n_pos + n_neg >= 1"""))
def pivot_polarity_occurrence(spark, sf_dir):
    return P.polarity(P.word_counts(P.incidence(corpus(spark, sf_dir), count_mode="occurrence")))


@query(with_(CORPUS, INC, POL, "prior AS (SELECT domain, avg(label) AS prior FROM corpus WHERE label IS NOT NULL GROUP BY 1)", select="SELECT domain, word, n_pos, n_neg, p - prior AS p FROM pol JOIN prior USING (domain) WHERE n_pos + n_neg >= 3"))
def pivot_polarity_centred(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return P.centred(P.polarity(f.counts, min_labelled=3), P.label_prior(f.docs))


@query(with_(CORPUS, INC, select="""SELECT domain, word, (n_pos + n_neg) AS n,
  0 - (CASE WHEN n_pos > 0 THEN n_pos::DOUBLE / (n_pos + n_neg) * log2(n_pos::DOUBLE / (n_pos + n_neg)) ELSE 0 END + CASE WHEN n_neg > 0 THEN n_neg::DOUBLE / (n_pos + n_neg) * log2(n_neg::DOUBLE / (n_pos + n_neg)) ELSE 0 END) AS entropy,
  CASE WHEN n_pos >= n_neg THEN 1 ELSE -1 END AS top_label FROM wc WHERE n_pos + n_neg > 0"""))
def pivot_entropy(spark, sf_dir):
    return P.label_entropy(Frames(spark, sf_dir).inc)


@query()
def pivot_entropy_topk(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return P.entropy_pivots(P.label_entropy(f.inc), f.pool, K)


_SCORED = "sc AS (SELECT pool.src, pool.tgt, pool.word, df_s, df_t, a.p AS p_s, b.p AS p_t, abs(a.p + b.p) / 2 AS score FROM pool JOIN pol a ON a.domain = src AND a.word = pool.word JOIN pol b ON b.domain = tgt AND b.word = pool.word)"


@query(with_(CORPUS, INC, PAIRS["near"], POOL, POL, _SCORED, select="SELECT * FROM sc"))
def pivot_pair_score(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return P.pair_score(f.pool, f.pol)


def _top(score: str, source: str) -> str:
    return f"SELECT src, tgt, rank, word, score FROM (SELECT src, tgt, word, {score} AS score, row_number() OVER (PARTITION BY src, tgt ORDER BY round({score}, 9) DESC, df_s + df_t DESC, word)::INTEGER AS rank FROM {source}) WHERE rank <= {K}"


@query(with_(CORPUS, INC, PAIRS["near"], POOL, POL, "j AS (SELECT pool.*, coalesce(p, 0.0) AS p FROM pool LEFT JOIN pol ON domain = src AND pol.word = pool.word)", select=_top("abs(p)", "j")))
def pivot_initial_topk(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return P.initial_pivots(f.pool, f.pol, K)


@query(with_(CORPUS, INC, PAIRS["near"], POOL, POL, _SCORED, select=_top("score", "sc")))
def pivot_true_topk(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return P.top_pivots(P.pair_score(f.pool, f.pol), K)


@query(with_(CORPUS, INC, POL, select="SELECT word, " + ", ".join(f"max(p) FILTER (WHERE domain = '{d}') AS \"{d}\"" for d in DOMAINS) + f" FROM pol WHERE word IN ({', '.join(repr(w) for w in INSULTS)}) GROUP BY word"))
def pivot_behaviour(spark, sf_dir):
    return P.behaviour(Frames(spark, sf_dir).pol, INSULTS, DOMAINS)


# ---------------------------------------------------------------- banks


@query(with_(CORPUS, INC, PAIRS["near"], POOL, POL, BANK, select="SELECT src, tgt, side, word, p FROM bank"))
def bank_init(spark, sf_dir):
    return Frames(spark, sf_dir).bank()


@query(with_(*EVIDENCED, td_sql(), select="SELECT src, tgt, side, word, p, n_updates FROM folded_bank"))
def bank_td_exact(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return B.td_exact(f.bank(), f.updates(), ALPHA)


@query(with_(*EVIDENCED, td_sql(), select="SELECT src, tgt, side, word, p, n_updates FROM folded_bank"))
def bank_td_fold(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return B.td_fold(f.bank(), B.td_blocks(f.updates(), ALPHA, 2), ALPHA)


@query(with_(*EVIDENCED, "per AS (SELECT src, tgt, side, word, step, count(*) AS k, avg(label) AS m FROM ups GROUP BY ALL)",
    f"fold AS (SELECT src, tgt, side, word, sum(k) AS n, sum((1 - pow({ALPHA}, k)) * m * pow({ALPHA}, later)) AS s FROM (SELECT *, sum(k) OVER (PARTITION BY src, tgt, side, word) - sum(k) OVER (PARTITION BY src, tgt, side, word ORDER BY step) AS later FROM per) GROUP BY ALL)",
    select=f"SELECT b.src, b.tgt, b.side, b.word, pow({ALPHA}, coalesce(n, 0)) * p + coalesce(s, 0) AS p, coalesce(n, 0)::BIGINT AS n_updates FROM bank b LEFT JOIN fold f ON f.src = b.src AND f.tgt = b.tgt AND f.side = b.side AND f.word = b.word"))
def bank_td_stepmean(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return B.td_step_mean(f.bank(), f.updates(), ALPHA)


@query(with_(*EVIDENCED, "tail AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src, tgt, side, word ORDER BY step DESC, doc_id DESC) AS back FROM ups) WHERE back <= 10)", td_sql("tail"), select="SELECT src, tgt, side, word, p, n_updates FROM folded_bank"))
def bank_td_tail(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return B.td_tail(f.bank(), f.updates(), ALPHA, 10)


_REFRESHED = "sc AS (SELECT src, tgt, word, df_s, df_t, abs(sum(p)) / 2 AS score FROM folded_bank JOIN pool USING (src, tgt, word) GROUP BY ALL)"


@query(with_(*EVIDENCED, td_sql(), _REFRESHED, select=_top("score", "sc")))
def bank_refresh_epoch(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return B.refresh(B.td_exact(f.bank(), f.updates(), ALPHA), f.pool, K)


@query()
def bank_refresh_10(spark, sf_dir):
    """Pivots renewed every ten steps: the bank after each block of ten, for all pairs in one pass."""
    f = Frames(spark, sf_dir)
    f.counts = stage(f.counts, "counts")  # pool, polarity and scores read them
    f.pool, f.pol = stage(P.candidate_pool(f.counts, f.pairs, f.min_df), "pool"), P.polarity(f.counts)
    ev = B.schedule(f.evidence(), ("src", "tgt", "side"), SEED)
    return R.renewed_pivots(f.docs, ev, f.pool, f.bank(), ALPHA, 10, K)


@query(with_(*EVIDENCED, td_sql(), "t AS (SELECT 'learnt' AS bank, * FROM (SELECT src, tgt, side, word, p FROM folded_bank) UNION ALL SELECT 'initial', src, tgt, side, word, p FROM bank)",
    select="SELECT bank, src, tgt, count(*) AS n, avg(abs(t.p - pol.p)) AS error FROM t JOIN pol ON pol.domain = tgt AND pol.word = t.word WHERE side = 'T' GROUP BY ALL"))
def bank_error(spark, sf_dir):
    f = Frames(spark, sf_dir)
    learnt = B.bank_error(B.td_exact(f.bank(), f.updates(), ALPHA), f.pol).withColumn("bank", F.lit("learnt"))
    return learnt.unionByName(B.bank_error(f.bank(), f.pol).withColumn("bank", F.lit("initial"))).select("bank", "src", "tgt", "n", "error")


@query(with_(CORPUS, INC, PAIRS["near"], POOL, NAIVE, PSEUDO, select="SELECT src, tgt, side, doc_id, conf, label FROM pseudo"))
def pseudo_labels(spark, sf_dir):
    return Frames(spark, sf_dir).pseudo().select("src", "tgt", "side", "doc_id", "conf", "label")


@query(with_(CORPUS, INC, PAIRS["near"], POOL, NAIVE, PSEUDO, select="""SELECT c.src, c.tgt, c.side, c.texts, coalesce(p.taken, 0) AS taken, coalesce(p.known, 0) AS known, p.precision FROM
  (SELECT src, tgt, side, count(*) AS texts FROM nb WHERE side = 'T' OR label IS NULL GROUP BY ALL) c LEFT JOIN
  (SELECT src, tgt, side, count(*) AS taken, count(c.label) AS known, avg(CASE WHEN c.label = pseudo.label THEN 1 WHEN c.label IS NOT NULL THEN 0 END) AS precision FROM pseudo JOIN corpus c USING (doc_id) GROUP BY ALL) p USING (src, tgt, side)"""))
def pseudo_quality(spark, sf_dir):
    f = Frames(spark, sf_dir)
    free = f.docs.select("doc_id", F.col("label").isNull().alias("free"))
    return M.pseudo_quality(f.pseudo(), f.docs, f.nb().join(free, "doc_id").where("side = 'T' or free"))


@query(with_(*EVIDENCED, select="SELECT src, tgt, side, step, count(*) AS texts, sum(label)::BIGINT AS balance FROM evs GROUP BY ALL"))
def evidence_routing(spark, sf_dir):
    ev = B.schedule(Frames(spark, sf_dir).evidence(), ("src", "tgt", "side"), SEED)
    return ev.groupBy("src", "tgt", "side", "step").agg(F.count("*").alias("texts"), F.sum("label").alias("balance"))


# ---------------------------------------------------------------- closed-form classifiers and measures


@query(with_(CORPUS, INC, PAIRS["all"], POOL, NAIVE, select="SELECT src, tgt, side, doc_id, score, p_pos, pred FROM nb"))
def nb_predict(spark, sf_dir):
    return Frames(spark, sf_dir, "all").nb()


_MEASURED = """100.0 * avg(CASE WHEN pred = label THEN 1.0 ELSE 0 END) AS accuracy,
  100.0 * (coalesce(avg(CASE WHEN pred = 1 THEN 1.0 ELSE 0 END) FILTER (WHERE label = 1), avg(CASE WHEN pred = -1 THEN 1.0 ELSE 0 END) FILTER (WHERE label = -1)) + coalesce(avg(CASE WHEN pred = -1 THEN 1.0 ELSE 0 END) FILTER (WHERE label = -1), avg(CASE WHEN pred = 1 THEN 1.0 ELSE 0 END) FILTER (WHERE label = 1))) / 2 AS balanced,
  coalesce(2.0 * count(*) FILTER (WHERE pred = 1 AND label = 1) / nullif(2 * count(*) FILTER (WHERE pred = 1 AND label = 1) + count(*) FILTER (WHERE pred = 1 AND label = -1) + count(*) FILTER (WHERE pred = -1 AND label = 1), 0), 0.0) AS f1"""


@query(with_(CORPUS, INC, PAIRS["all"], POOL, NAIVE, select=f"SELECT src, tgt, count(*) AS n, {_MEASURED} FROM nb WHERE side = 'T' AND label IS NOT NULL GROUP BY ALL"))
def nb_accuracy(spark, sf_dir):
    f = Frames(spark, sf_dir, "all")
    return M.accuracy(f.nb().where("side = 'T'").join(f.docs.select("doc_id", "label"), "doc_id"), ["src", "tgt"])


@query(with_(CORPUS, PAIRS["all"], "m AS (SELECT domain AS src, CASE WHEN sum(label) > 0 THEN 1 ELSE -1 END AS pred FROM corpus WHERE label IS NOT NULL GROUP BY 1)",
    select=f"SELECT pairs.src, tgt, count(*) AS n, {_MEASURED} FROM pairs JOIN m ON m.src = pairs.src JOIN corpus ON domain = tgt WHERE label IS NOT NULL GROUP BY ALL"))
def majority_accuracy(spark, sf_dir):
    f = Frames(spark, sf_dir, "all")
    said = NB.majority(f.docs, f.pairs)
    return M.accuracy(f.docs.where("label is not null").select(F.col("domain").alias("tgt"), "label").join(F.broadcast(said), "tgt"), ["src", "tgt"])


@query(with_(CORPUS, INC, PAIRS["near"], POOL, POL, "j AS (SELECT pool.*, coalesce(p, 0.0) AS p FROM pool LEFT JOIN pol ON domain = src AND pol.word = pool.word)", "pv AS (" + _top("abs(p)", "j") + ")",
    "v AS (SELECT pv.src, pv.tgt, i.doc_id, sum(pol.p) AS v FROM inc i JOIN pv ON pv.tgt = i.domain AND pv.word = i.word JOIN pol ON pol.domain = pv.src AND pol.word = pv.word GROUP BY ALL)",
    "e AS (SELECT pairs.src, pairs.tgt, c.label, CASE WHEN round(coalesce(v, 0.0), 9) > 0 THEN 1 ELSE -1 END AS pred FROM pairs JOIN corpus c ON c.domain = pairs.tgt LEFT JOIN v ON v.src = pairs.src AND v.tgt = pairs.tgt AND v.doc_id = c.doc_id)",
    select=f"SELECT src, tgt, count(*) AS n, {_MEASURED} FROM e WHERE label IS NOT NULL GROUP BY ALL"))
def pivot_vote_accuracy(spark, sf_dir):
    f = Frames(spark, sf_dir)
    vote = NB.pivot_vote(f.docs, f.inc, P.initial_pivots(f.pool, f.pol, K), f.pol)
    return M.accuracy(vote.join(f.docs.select("doc_id", "label"), "doc_id"), ["src", "tgt"])


@query(with_(CORPUS, INC, PAIRS["near"], POOL, NAIVE, select="SELECT src, tgt, count(*) FILTER (WHERE pred = 1 AND label = 1) AS tp, count(*) FILTER (WHERE pred = 1 AND label = -1) AS fp, count(*) FILTER (WHERE pred = -1 AND label = 1) AS fn, count(*) FILTER (WHERE pred = -1 AND label = -1) AS tn FROM nb WHERE side = 'T' AND label IS NOT NULL GROUP BY ALL"))
def metrics_confusion(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return M.confusion(f.nb().where("side = 'T'").join(f.docs.select("doc_id", "label"), "doc_id"), ["src", "tgt"])


@query(with_(CORPUS, INC, PAIRS["near"], POOL, NAIVE, "l AS (SELECT src, tgt, label, round(score, 9) AS s FROM nb WHERE side = 'T' AND label IS NOT NULL)",
    select="SELECT a.src, a.tgt, avg(CASE WHEN a.s > b.s THEN 1.0 WHEN a.s = b.s THEN 0.5 ELSE 0 END) AS auc FROM l a JOIN l b ON a.src = b.src AND a.tgt = b.tgt WHERE a.label = 1 AND b.label = -1 GROUP BY ALL"))
def metrics_auc(spark, sf_dir):
    f = Frames(spark, sf_dir)
    return M.auc(f.nb().where("side = 'T'").join(f.docs.select("doc_id", "label"), "doc_id"), ["src", "tgt"])


# word scores of non-text tables: words of part names, text = order, domain = region of the customer, label = returned or accepted


@query(r"""WITH lines AS (SELECT l_orderkey AS doc_id, r_name AS domain, CASE l_returnflag WHEN 'R' THEN 1 WHEN 'A' THEN -1 END AS label, unnest(string_split(lower(p_name || ' ' || p_brand), ' ')) AS word
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey),
c AS (SELECT domain, word, count(*) FILTER (WHERE label = 1) AS n_pos, count(*) FILTER (WHERE label = -1) AS n_neg FROM lines GROUP BY ALL)
SELECT domain, word, n_pos, n_neg, (n_pos - n_neg)::DOUBLE / (n_pos + n_neg) AS p FROM c WHERE n_pos + n_neg >= 1""")
def wl_orders_polarity(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    places = t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", F.col("r_name").alias("domain"))
    orders = t("orders").join(places, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "domain")
    parts = t("part").select("p_partkey", F.split(F.lower(F.concat_ws(" ", "p_name", "p_brand")), " ").alias("words"))
    lines = t("lineitem").select("l_orderkey", "l_partkey", F.when(F.col("l_returnflag") == "R", 1).when(F.col("l_returnflag") == "A", -1).alias("label"))
    inc = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("l_orderkey").alias("doc_id"), "domain", "label", F.explode("words").alias("word"))
    return P.polarity(P.word_counts(inc))


def flagship(spark, sf_dir):
    """Top initial pivots of the twelve near pairs; the smallest tables need a lower cut of the pool."""
    f = Frames(spark, sf_dir, min_df=2)
    return P.initial_pivots(f.pool, f.pol, K)
