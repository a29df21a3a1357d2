"""Registered queries of attention, facts, injection and pivot masking."""

from __future__ import annotations

from pyspark.sql import functions as F

from lexbridge.functions import text as X
from lexbridge.operators import attention as A
from lexbridge.operators import cooccurrence as C
from lexbridge.operators import facts as G
from lexbridge.operators import inject as I
from lexbridge.operators import pivot_mask as PM
from lexbridge.operators import pivots as P
from lexbridge.plans.frames import CORPUS, INC, K, POL, POOL, SENTENCES, WORDS, Frames, with_
from lexbridge.sources.stage import stage
from lexbridge.sources.tables import html_text, table

TAU = 0.3
#: The three pairs whose pivots and facts are looked at one by one.
CHAIN = (("N1", "N3"), ("N3", "N4"), ("N4", "N2"))
ENTITY = "stupid"
QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


class GraphFrames(Frames):
    """The frames of some pairs, the chain's if none are named, with sentences, pivots and graphs."""

    def __init__(self, spark, sf_dir, pairs=CHAIN):
        super().__init__(spark, sf_dir)
        self.counts = stage(self.counts, "counts")  # pool, polarity and stop words read them
        self.pol = P.polarity(self.counts)
        self.pairs = spark.createDataFrame(list(pairs), "src string, tgt string")
        self.pool = stage(P.candidate_pool(self.counts, self.pairs, self.min_df), "pool")
        targets = sorted({t for _, t in pairs})
        self.sents = X.whole_words(self.docs.where(F.col("domain").isin(targets)), "domain")
        self.pool_words = self.pool.select(F.col("tgt").alias("domain"), "word").distinct()
        self.pivots = P.initial_pivots(self.pool, self.pol, K)
        self.pivot_words = self.pivots.select(F.col("tgt").alias("domain"), "word").distinct()
        self.stop = G.stop_words(self.counts)

    def vectors(self):
        return table(self.spark, self.sf_dir, "embeddings")

    def facts(self, words=None):
        """Candidate facts of the pool words, or of fewer ``words``: a place's facts depend on no other place's."""
        return C.cooccurrence_facts(self.sents, self.pool_words if words is None else words)

    def graph(self, words=None, fold=None):
        """The merged graph for each pair; ``fold`` keeps of some pivots' facts what is wanted of them."""
        each = lambda g: G.for_pairs(g, F.broadcast(self.pool))
        if fold is None:
            return each(C.cooccurrence_graph(self.sents, self.pool_words if words is None else words, TAU, self.stop))
        return C.cooccurrence_graph(self.sents, self.pool_words if words is None else words, TAU, self.stop, fold=lambda g: fold(each(g)))

    def active(self, pivots="scoped"):
        return I.active_facts(self.graph(self.pivot_words), self.pivots) if pivots == "scoped" else I.active_facts(self.graph(), None)

    def texts(self):
        """Source and target texts of each pair, with the whole text's words as the trunk."""
        both = self.pairs.select("src", "tgt", F.explode(F.array("src", "tgt")).alias("domain"))
        return self.docs.select("doc_id", "domain", "label", "split", X.word_list(F.col("text")).alias("words")).join(F.broadcast(both), "domain")

    def trees(self, pivots="scoped", strategy="map"):
        return I.inject(self.texts(), self.active(pivots), strategy)


PAIRS = "pairs AS (SELECT * FROM (VALUES " + ", ".join(f"('{s}', '{t}')" for s, t in CHAIN) + ") v(src, tgt))"
BASE = (CORPUS, SENTENCES, WORDS, INC, PAIRS, POOL, POL)
PIVOTS = f"""piv AS (SELECT * FROM (SELECT pool.src, pool.tgt, pool.word, row_number() OVER (PARTITION BY pool.src, pool.tgt ORDER BY round(abs(coalesce(p, 0.0)), 9) DESC, df_s + df_t DESC, pool.word) AS rank
  FROM pool LEFT JOIN pol ON pol.domain = pool.src AND pol.word = pool.word) WHERE rank <= {K})"""
TOKENS = """ts AS (SELECT * FROM sent WHERE domain IN (SELECT tgt FROM pairs)),
tok AS (SELECT domain, doc_id, sent_ix, generate_subscripts(words, 1) - 1 AS i, unnest(words) AS w, len(words) AS n FROM ts)"""
COOC = """pw AS (SELECT DISTINCT tgt AS domain, word FROM pool),
c1 AS (SELECT domain, w, count(*) AS c FROM tok GROUP BY ALL),
cell AS (SELECT a.domain, a.doc_id, a.sent_ix, a.i, b.i AS j, a.w AS w_i, b.w AS w_j FROM tok a JOIN pw ON pw.domain = a.domain AND pw.word = a.w JOIN tok b ON a.domain = b.domain AND a.doc_id = b.doc_id AND a.sent_ix = b.sent_ix AND a.i <> b.i),
c2 AS (SELECT domain, w_i, w_j, count(*) AS c_ij FROM cell WHERE abs(i - j) <= 5 GROUP BY ALL),
t AS (SELECT cell.*, (1 + coalesce(c_ij, 0)) / sqrt(x.c * y.c) * exp(-0.1 * abs(i - j)) AS t FROM cell JOIN c1 x ON x.domain = cell.domain AND x.w = cell.w_i JOIN c1 y ON y.domain = cell.domain AND y.w = cell.w_j
      LEFT JOIN c2 ON c2.domain = cell.domain AND c2.w_i = cell.w_i AND c2.w_j = cell.w_j),
att AS (SELECT domain, doc_id, sent_ix, i, j, w_i, w_j, t / sum(t) OVER (PARTITION BY domain, doc_id, sent_ix, i) AS a FROM t)"""
FACTS = """rk AS (SELECT *, row_number() OVER (PARTITION BY domain, doc_id, sent_ix, i ORDER BY round(a, 9) DESC, j) AS r FROM att),
two AS (SELECT domain, doc_id, sent_ix, i, w_i, min(j) AS j1, max(j) AS j2, arg_min(w_j, j) AS x1, arg_max(w_j, j) AS x2, sum(round(a, 9)) AS conf FROM rk WHERE r <= 2 GROUP BY ALL HAVING count(*) = 2),
facts AS (SELECT domain, doc_id, sent_ix, i, w_i AS pivot, CASE WHEN i < j1 THEN w_i ELSE x1 END AS w_a, CASE WHEN i < j1 THEN x1 WHEN i < j2 THEN w_i ELSE x2 END AS w_b, CASE WHEN i > j2 THEN w_i ELSE x2 END AS w_c,
                 (i > j1)::INTEGER + (i > j2)::INTEGER AS slot, conf FROM two)"""
STOP = "stop AS (SELECT domain, word FROM (SELECT domain, word, row_number() OVER (PARTITION BY domain ORDER BY df DESC, word) AS r FROM wc) WHERE r <= 30)"
KEPT = f"""kept AS (SELECT * FROM facts f WHERE round(conf, 9) >= {TAU} AND NOT EXISTS (SELECT 1 FROM stop s WHERE s.domain = f.domain AND s.word IN (f.w_a, f.w_b, f.w_c)))"""
MERGED = """merged AS (SELECT domain, pivot, slot, w_a, w_b, w_c, count(*) AS support, max(conf) AS conf, avg(conf) AS mean_conf FROM kept GROUP BY ALL),
graph AS (SELECT pool.src, pool.tgt, m.* EXCLUDE (domain) FROM merged m JOIN pool ON pool.tgt = m.domain AND pool.word = m.pivot)"""
TREE = """txt AS (SELECT p.src, p.tgt, c.doc_id, c.domain, regexp_extract_all(lower(c.text), '\\p{L}+') AS words FROM corpus c JOIN pairs p ON c.domain = p.src OR c.domain = p.tgt),
trunk AS (SELECT src, tgt, doc_id, generate_subscripts(words, 1) - 1 AS k, unnest(words) AS tok FROM txt),
hung AS (SELECT t.src, t.tgt, t.doc_id, t.k, a.b, a.w_a, a.w_b, a.w_c, a.slot FROM trunk t JOIN active a ON a.src = t.src AND a.tgt = t.tgt AND a.pivot = t.tok),
parts AS (
  SELECT src, tgt, doc_id, k, 1 AS part, 0 AS b, 0 AS o, tok, k AS pos, 0 AS branch FROM trunk
  UNION ALL SELECT src, tgt, doc_id, k, CASE slot WHEN 0 THEN 2 ELSE 0 END, b, 1, CASE slot WHEN 0 THEN w_b ELSE w_a END, k + CASE slot WHEN 2 THEN 2 ELSE 1 END, k * 64 + b FROM hung
  UNION ALL SELECT src, tgt, doc_id, k, CASE slot WHEN 2 THEN 0 ELSE 2 END, b, 2, CASE slot WHEN 2 THEN w_b ELSE w_c END, k + CASE slot WHEN 0 THEN 2 ELSE 1 END, k * 64 + b FROM hung),
tree AS (SELECT src, tgt, doc_id, tok, pos::INTEGER AS pos, branch::INTEGER AS branch, k::INTEGER AS trunk, (row_number() OVER (PARTITION BY src, tgt, doc_id ORDER BY k, part, b, o) - 1)::INTEGER AS seq FROM parts)"""


def active_sql(scope: str) -> str:
    source = "graph JOIN piv ON piv.src = graph.src AND piv.tgt = graph.tgt AND piv.word = graph.pivot" if scope == "scoped" else "graph"
    return f"active AS (SELECT * FROM (SELECT graph.*, row_number() OVER (PARTITION BY graph.src, graph.tgt, pivot ORDER BY round(conf, 6) DESC, support DESC, w_a, w_b, w_c, slot) AS b FROM {source}) WHERE b <= 2)"


GRAPH = (*BASE, PIVOTS, TOKENS, COOC, FACTS, STOP, KEPT, MERGED)
_TREES = (*GRAPH, active_sql("scoped"), TREE)


# ---------------------------------------------------------------- attention


@query(with_(*BASE, TOKENS, COOC, select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, i::INTEGER AS i, count(*) AS n, sum(a) AS total, max(a) AS top FROM att GROUP BY ALL"))
def att_cooc_matrix(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return C.cooccurrence_sums(f.sents, f.pool_words)


def _vector_sql(unit: str) -> str:
    """Softmax rows of the vector provider for the pivots, over words or over their pieces."""
    pieces = """pc AS (SELECT domain, doc_id, sent_ix, i AS word_ix, w, unnest(range((length(w) + 3) // 4)) AS piece FROM tok),
units AS (SELECT domain, doc_id, sent_ix, word_ix, w, substr(w, (piece * 4 + 1)::BIGINT, 4) AS u, row_number() OVER (PARTITION BY domain, doc_id, sent_ix ORDER BY word_ix, piece) - 1 AS place FROM pc)"""
    words = "units AS (SELECT domain, doc_id, sent_ix, i AS word_ix, w, w AS u, i AS place FROM tok)"
    return f"""pv AS (SELECT DISTINCT tgt AS domain, word FROM piv),
{pieces if unit == "piece" else words},
vec AS (SELECT u.*, e.embedding::DOUBLE[] AS v FROM units u JOIN embeddings e ON e.vec_id = ('0x' || substr(md5(u.u), 1, 8))::BIGINT % (SELECT count(*) FROM embeddings)),
z AS (SELECT a.domain, a.doc_id, a.sent_ix, h.head, a.place AS p, b.place AS q, a.word_ix AS i, b.word_ix AS j,
             4 * list_dot_product(list_slice(a.v, h.head * 16 + 1, h.head * 16 + 16), list_slice(b.v, h.head * 16 + 1, h.head * 16 + 16)) - 0.1 * abs(a.place - b.place) AS z
      FROM vec a JOIN pv ON pv.domain = a.domain AND pv.word = a.w JOIN vec b ON a.domain = b.domain AND a.doc_id = b.doc_id AND a.sent_ix = b.sent_ix, (SELECT unnest([0, 1, 2, 3]) AS head) h),
soft AS (SELECT *, exp(z) / sum(exp(z)) OVER (PARTITION BY domain, doc_id, sent_ix, head, p) AS a FROM z)"""


@query(with_(*BASE, PIVOTS, TOKENS, _vector_sql("word"), select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, head::INTEGER AS head, i::INTEGER AS i, j::INTEGER AS j, a FROM soft"))
def att_vector_heads(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return A.vector_weights(f.sents, f.pivot_words, f.vectors(), per_head=True)


@query(with_(*BASE, PIVOTS, TOKENS, _vector_sql("word"), select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, i::INTEGER AS i, j::INTEGER AS j, avg(a) AS a FROM soft GROUP BY ALL"))
def att_head_mean(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return A.vector_weights(f.sents, f.pivot_words, f.vectors()).drop("head")


@query(with_(*BASE, PIVOTS, TOKENS, _vector_sql("piece"), select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, i::INTEGER AS i, j::INTEGER AS j, avg(a) AS a FROM soft GROUP BY ALL"))
def att_piece_mean(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return A.vector_weights(f.sents, f.pivot_words, f.vectors(), piece=4).drop("head")


# ---------------------------------------------------------------- graph


@query(with_(*BASE, TOKENS, COOC, FACTS, select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, i::INTEGER AS i, pivot, w_a, w_b, w_c, slot, round(conf * 1e9)::BIGINT AS conf_nano FROM facts"))
def kg_candidates_cooc(spark, sf_dir):
    """Candidate facts; the confidence, a sum of two values of nine digits, in whole billionths."""
    return GraphFrames(spark, sf_dir).facts().withColumn("conf_nano", F.round(F.col("conf") * 1e9).cast("long")).drop("conf")


@query(with_(*BASE, PIVOTS, TOKENS, _vector_sql("word"), "m AS (SELECT domain, doc_id, sent_ix, i, j, avg(a) AS a FROM soft GROUP BY ALL)",
    "att AS (SELECT m.domain, m.doc_id, m.sent_ix, m.i, m.j, x.w AS w_i, y.w AS w_j, a FROM m JOIN tok x ON x.doc_id = m.doc_id AND x.sent_ix = m.sent_ix AND x.i = m.i JOIN tok y ON y.doc_id = m.doc_id AND y.sent_ix = m.sent_ix AND y.i = m.j WHERE m.i <> m.j)",
    FACTS, select="SELECT domain, doc_id, sent_ix::INTEGER AS sent_ix, i::INTEGER AS i, pivot, w_a, w_b, w_c, slot, conf FROM facts"))
def kg_candidates_vector(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return A.vector_facts(f.sents, f.pivot_words, f.vectors())


@query(with_(*BASE, TOKENS, COOC, FACTS, select=f"SELECT domain, pivot, count(*) AS n FROM facts WHERE round(conf, 9) >= {TAU} GROUP BY ALL"))
def kg_filtered(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return C.cooccurrence_counts(f.sents, f.pool_words, TAU)


@query(with_(*BASE, TOKENS, COOC, FACTS, STOP, KEPT, select="SELECT domain, pivot, count(*) AS n FROM kept GROUP BY ALL"))
def kg_no_stopwords(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return C.cooccurrence_counts(f.sents, f.pool_words, TAU, f.stop)


@query(with_(*GRAPH, select="SELECT src, tgt, pivot, slot, w_a, w_b, w_c, support, round(conf * 1e9)::BIGINT AS conf_nano, round(mean_conf * support * 1e9)::BIGINT AS sum_nano FROM graph"))
def kg_merged(spark, sf_dir):
    """The merged graph; best and summed confidence in whole billionths, on which two engines agree."""
    nano = lambda c: F.round(c * 1e9).cast("long")
    g = GraphFrames(spark, sf_dir).graph()
    return g.select("src", "tgt", "pivot", "slot", "w_a", "w_b", "w_c", "support", nano(F.col("conf")).alias("conf_nano"), nano(F.col("mean_conf") * F.col("support")).alias("sum_nano"))


_TAUS = [0.1, 0.2, 0.3, 0.45]


@query(with_(*BASE, TOKENS, COOC, FACTS, select=f"SELECT domain, tau, count(*) FILTER (WHERE round(conf, 9) >= tau) AS kept, avg((round(conf, 9) >= tau)::INTEGER) AS share FROM facts, (SELECT unnest({_TAUS}::DOUBLE[]) AS tau) GROUP BY ALL"))
def kg_confidence_profile(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return C.cooccurrence_profile(f.sents, f.pool_words, _TAUS)


@query(with_(*BASE, TOKENS, COOC, FACTS, select="SELECT least(greatest(quantile_cont(conf, 0.25), 0.1), 0.45) AS tau FROM facts"))
def kg_suggested_tau(spark, sf_dir):
    return G.suggest_tau(GraphFrames(spark, sf_dir).facts(), exact=True)


@query(with_(*GRAPH, select=f"SELECT src, tgt, pivot, w_a, w_b, w_c, support, conf FROM graph WHERE '{ENTITY}' IN (w_a, w_b, w_c)"))
def kg_entity_facts(spark, sf_dir):
    return GraphFrames(spark, sf_dir).graph(fold=lambda g: G.facts_of(g, ENTITY)).select("src", "tgt", "pivot", "w_a", "w_b", "w_c", "support", "conf")


@query(with_(*GRAPH, select="SELECT g.src, g.tgt, 3 - (a.word IS NOT NULL)::INTEGER - (b.word IS NOT NULL)::INTEGER - (c.word IS NOT NULL)::INTEGER AS links, count(*) AS n FROM graph g LEFT JOIN piv a ON a.src = g.src AND a.tgt = g.tgt AND a.word = w_a LEFT JOIN piv b ON b.src = g.src AND b.tgt = g.tgt AND b.word = w_b LEFT JOIN piv c ON c.src = g.src AND c.tgt = g.tgt AND c.word = w_c GROUP BY ALL"))
def kg_fact_kinds(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    pivots = stage(f.pivots, "pivots")
    parts = f.graph(fold=lambda g: G.fact_kind(g, pivots).groupBy("src", "tgt", "links").agg(F.count("*").alias("n")))
    return parts.groupBy("src", "tgt", "links").agg(F.sum("n").alias("n"))


_OPEN = r"""ot AS (SELECT text FROM benchmark UNION ALL SELECT text FROM conversations),
ow AS (SELECT regexp_extract_all(s, '\p{L}+') AS ws FROM (SELECT unnest(string_split_regex(lower(text), '[.!?\n]+')) AS s FROM ot)),
op AS (SELECT ws, (len(ws) + 63) // 64 AS np, unnest(range((len(ws) + 63) // 64)) AS part FROM ow),
os AS (SELECT ws[(len(ws) * part // np + 1):(len(ws) * (part + 1) // np)] AS words FROM op),
trio AS (SELECT words[i] AS head, words[i + 1] AS relation, words[i + 2] AS tail FROM (SELECT words, unnest(range(1, len(words) - 1)) AS i FROM os WHERE len(words) >= 3)),
edges AS (SELECT head, relation, tail, count(*) AS weight FROM trio WHERE head <> tail GROUP BY ALL HAVING count(*) >= 2),
voc AS (SELECT DISTINCT word FROM inc WHERE domain = 'N3'),
hop AS (SELECT DISTINCT * FROM edges WHERE head IN (SELECT word FROM voc) OR tail IN (SELECT word FROM voc))"""


def open_sentences(spark, sf_dir, pages: bool = False):
    """Sentences of the open-domain tables."""
    texts = table(spark, sf_dir, "benchmark").select("text").unionByName(table(spark, sf_dir, "conversations").select("text"))
    texts = texts.unionByName(table(spark, sf_dir, "pages").select(html_text(F.col("html")).alias("text"))) if pages else texts
    return X.whole_words(texts.withColumn("doc_id", F.lit(0).cast("long")))


@query(with_(CORPUS, INC, _OPEN, select="SELECT head, relation, tail, weight FROM hop"))
def kg_generic_onehop(spark, sf_dir):
    vocabulary = Frames(spark, sf_dir).inc.where("domain = 'N3'").select("word").distinct()
    return G.one_hop(G.generic_graph(open_sentences(spark, sf_dir)), vocabulary)


@query(with_(*GRAPH, _OPEN, "e AS (SELECT 'general' AS graph, head AS w_a, relation AS w_b, tail AS w_c FROM hop UNION ALL SELECT 'learnt', w_a, w_b, w_c FROM graph WHERE tgt = 'N3')",
    select="SELECT graph, count(*) AS edges, avg((w_a NOT IN (SELECT word FROM voc) OR w_b NOT IN (SELECT word FROM voc) OR w_c NOT IN (SELECT word FROM voc))::INTEGER) AS outside_share, count(DISTINCT w_b)::DOUBLE / count(*) AS diversity FROM e GROUP BY graph"))
def kg_noise(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    vocabulary = f.counts.where("domain = 'N3'").select("word")
    general = G.one_hop(G.generic_graph(open_sentences(spark, sf_dir)), vocabulary).select(F.col("head").alias("w_a"), F.col("relation").alias("w_b"), F.col("tail").alias("w_c"))
    a = G.graph_noise(general, vocabulary).withColumn("graph", F.lit("general"))
    return a.unionByName(G.graph_noise(f.graph().where("tgt = 'N3'"), vocabulary).withColumn("graph", F.lit("learnt")))


def _graph_of(spark, sf_dir, texts):
    """The graph over an unlabelled corpus of another table, for the N1 vocabulary that is frequent there as well."""
    f = Frames(spark, sf_dir)
    docs = texts.select("doc_id", "text", F.lit("T").alias("domain"), F.lit(None).cast("int").alias("label"), F.lit("unlabelled").alias("split"))
    counts = f.counts.where("domain = 'N1'").unionByName(P.word_counts(P.incidence(docs)))
    pool = P.candidate_pool(counts, spark.createDataFrame([("N1", "T")], "src string, tgt string"), 3)
    return G.for_pairs(C.cooccurrence_graph(X.whole_words(docs, "domain"), pool.select(F.col("tgt").alias("domain"), "word"), TAU), F.broadcast(pool))


@query()
def wl_graph_chat(spark, sf_dir):
    chat = table(spark, sf_dir, "conversations").where("role = 'assistant'")
    return _graph_of(spark, sf_dir, chat.select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), "text"))


@query()
def wl_graph_web(spark, sf_dir):
    return _graph_of(spark, sf_dir, table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), html_text(F.col("html")).alias("text")))


@query(with_(*GRAPH, _OPEN, "p5 AS (SELECT src, tgt, word FROM piv WHERE rank <= 5)",
    select="SELECT p5.src, p5.tgt, p5.word AS entity, 'learnt' AS graph, w_a, w_b, w_c FROM graph g JOIN p5 ON p5.src = g.src AND p5.tgt = g.tgt AND p5.word IN (w_a, w_b, w_c) UNION ALL SELECT p5.src, p5.tgt, p5.word, 'general', head, relation, tail FROM hop JOIN p5 ON p5.word IN (head, relation, tail) WHERE p5.tgt = 'N3'"))
def wl_graph_sample(spark, sf_dir):
    """Facts of each pair's five first pivots in the learnt graph, beside the general one's."""
    f = GraphFrames(spark, sf_dir)
    top = F.broadcast(f.pivots.where("rank <= 5").select(F.col("src"), F.col("tgt"), F.col("word").alias("entity")))
    holds = F.expr("entity in (w_a, w_b, w_c)")
    learnt = f.graph().select("src", "tgt", "w_a", "w_b", "w_c").join(top, ["src", "tgt"]).where(holds).withColumn("graph", F.lit("learnt"))
    vocabulary = f.inc.where("domain = 'N3'").select("word").distinct()
    hop = G.one_hop(G.generic_graph(open_sentences(spark, sf_dir)), vocabulary).select(F.col("head").alias("w_a"), F.col("relation").alias("w_b"), F.col("tail").alias("w_c"))
    general = hop.join(top.where("tgt = 'N3'"), holds).withColumn("graph", F.lit("general"))
    cols = ["src", "tgt", "entity", "graph", "w_a", "w_b", "w_c"]
    return learnt.select(*cols).unionByName(general.select(*cols))


# ---------------------------------------------------------------- injection


def _long(trees):
    t = trees.select("src", "tgt", "doc_id", F.posexplode("tokens").alias("seq", "t"))
    return t.select("src", "tgt", "doc_id", "seq", "t.tok", "t.pos", "t.branch", "t.trunk")


@query(with_(*_TREES, select="SELECT src, tgt, doc_id, seq, tok, pos, branch, trunk FROM tree"))
def inject_scoped(spark, sf_dir):
    return _long(GraphFrames(spark, sf_dir).trees())


@query(with_(*_TREES, select="SELECT src, tgt, doc_id, seq, tok, pos, branch, trunk FROM tree"))
def inject_scoped_join(spark, sf_dir):
    return _long(GraphFrames(spark, sf_dir).trees(strategy="join"))


@query(with_(*GRAPH, active_sql("all"), TREE, select="SELECT src, tgt, doc_id, count(*) AS tokens, count(*) FILTER (WHERE branch > 0) AS hung FROM tree GROUP BY ALL"))
def inject_everywhere(spark, sf_dir):
    t = GraphFrames(spark, sf_dir).trees("all")
    return t.where(F.size("tokens") > 0).select("src", "tgt", "doc_id", F.size("tokens").cast("long").alias("tokens"), F.size(F.filter("tokens", lambda x: x.branch > 0)).cast("long").alias("hung"))


@query(with_(*_TREES, select="SELECT src, tgt, doc_id, max(pos)::INTEGER AS top, sum(pos)::BIGINT AS total, count(DISTINCT pos) AS places FROM tree GROUP BY ALL"))
def inject_positions(spark, sf_dir):
    t = GraphFrames(spark, sf_dir).trees().where(F.size("tokens") > 0).select("src", "tgt", "doc_id", F.col("tokens.pos").alias("pos"))
    total = F.aggregate("pos", F.lit(0).cast("long"), lambda a, p: a + p)
    return t.select("src", "tgt", "doc_id", F.array_max("pos").alias("top"), total.alias("total"), F.size(F.array_distinct("pos")).cast("long").alias("places"))


@query(with_(*_TREES, select="""SELECT a.src, a.tgt, a.doc_id, count(*) AS cells, count(*) FILTER (WHERE (a.branch = b.branch) OR ((a.branch = 0 OR b.branch = 0) AND a.trunk = b.trunk)) AS seen
  FROM tree a JOIN tree b ON a.src = b.src AND a.tgt = b.tgt AND a.doc_id = b.doc_id JOIN txt ON txt.src = a.src AND txt.tgt = a.tgt AND txt.doc_id = a.doc_id WHERE len(words) <= 64 GROUP BY ALL"""))
def inject_visible_pairs(spark, sf_dir):
    """Texts of up to 64 words, the length an encoder takes at once."""
    t = GraphFrames(spark, sf_dir).trees().where(F.size("words").between(1, 64)).withColumn("v", I.visible(F.col("tokens")))
    seen = F.aggregate("v", F.lit(0), lambda a, row: a + F.size(F.filter(row, lambda x: x)))
    return t.select("src", "tgt", "doc_id", (F.size("tokens") * F.size("tokens")).cast("long").alias("cells"), seen.cast("long").alias("seen"))


@query(with_(*BASE, "txt AS (SELECT p.src, p.tgt, c.doc_id, regexp_extract_all(lower(c.text), '\\p{L}+') AS words FROM corpus c JOIN pairs p ON c.domain = p.src OR c.domain = p.tgt)", select="SELECT src, tgt, doc_id, array_to_string(words, ' ') AS trunk FROM txt"))
def inject_strip_identity(spark, sf_dir):
    return GraphFrames(spark, sf_dir).trees().select("src", "tgt", "doc_id", F.array_join(I.strip(F.col("tokens")), " ").alias("trunk"))


@query(with_(*_TREES, "own AS (SELECT DISTINCT domain AS src, word FROM inc)", select="SELECT t.src, t.tgt, count(DISTINCT t.doc_id) AS texts, count(*) FILTER (WHERE branch > 0) AS branch_words, count(*) FILTER (WHERE branch > 0 AND own.word IS NULL) AS new_words FROM tree t LEFT JOIN own ON own.src = t.src AND own.word = t.tok GROUP BY ALL"))
def inject_stats(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return I.injection_stats(f.trees().where(F.size("words") > 0), f.inc.select(F.col("domain").alias("src"), "word").distinct())


# ---------------------------------------------------------------- masking and false links


@query(with_(*_TREES, select="SELECT t.src, t.tgt, t.doc_id, count(*) FILTER (WHERE branch = 0 AND piv.word IS NOT NULL) AS masked, count(*) AS tokens FROM tree t LEFT JOIN piv ON piv.src = t.src AND piv.tgt = t.tgt AND piv.word = t.tok GROUP BY ALL"))
def mask_pivots(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    m = PM.mask_pivots(f.trees(), f.pivots).where(F.size("tokens") > 0)
    return m.select("src", "tgt", "doc_id", F.size("masked").cast("long").alias("masked"), F.size("tokens").cast("long").alias("tokens"))


_PREDICTORS = """pc AS (SELECT piv.src, piv.tgt, piv.word AS pivot, o.word, count(*) AS n FROM inc i JOIN piv ON piv.tgt = i.domain AND piv.word = i.word JOIN inc o ON o.doc_id = i.doc_id
  WHERE NOT EXISTS (SELECT 1 FROM piv x WHERE x.src = piv.src AND x.tgt = piv.tgt AND x.word = o.word) GROUP BY ALL)"""


@query(with_(*BASE, PIVOTS, _PREDICTORS, select="SELECT src, tgt, pivot, word, n FROM pc"))
def pivot_predictor_counts(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    return PM.predictor_counts(f.inc, f.pivots)


@query()
def pivot_predictor_weights(spark, sf_dir):
    f = GraphFrames(spark, sf_dir)
    sizes = f.docs.groupBy("domain").agg(F.count("*").alias("texts"))
    return PM.pivot_predictors(f.counts, PM.predictor_counts(f.inc, f.pivots), sizes)


@query(with_(*GRAPH, _PREDICTORS,
    "top AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src, tgt, pivot ORDER BY n DESC, word) AS r FROM pc) WHERE r <= 10)",
    "links AS (SELECT 'co-occurrence' AS kind, src, tgt, pivot, word FROM top UNION ALL SELECT 'facts', g.src, g.tgt, g.pivot, w FROM (SELECT src, tgt, pivot, unnest([w_a, w_b, w_c]) AS w FROM graph) g JOIN piv ON piv.src = g.src AND piv.tgt = g.tgt AND piv.word = g.pivot WHERE w <> g.pivot)",
    select="SELECT kind, l.src, l.tgt, count(*) AS links, count(s.word) AS false_links FROM links l LEFT JOIN stop s ON s.domain = l.tgt AND s.word = l.word GROUP BY ALL"))
def wl_false_links(spark, sf_dir):
    """Function words among what predicts a pivot best by counts, and among what its facts hold."""
    from pyspark.sql import Window as W

    f = GraphFrames(spark, sf_dir)
    rank = F.row_number().over(W.partitionBy("src", "tgt", "pivot").orderBy(F.desc("n"), "word"))
    counted = PM.predictor_counts(f.inc, f.pivots).withColumn("r", rank).where("r <= 10").select(F.lit("co-occurrence").alias("kind"), "src", "tgt", "pivot", "word")
    held = f.graph(f.pivot_words).join(F.broadcast(f.pivots.select("src", "tgt", F.col("word").alias("pivot"))), ["src", "tgt", "pivot"], "left_semi")
    held = held.select(F.lit("facts").alias("kind"), "src", "tgt", "pivot", F.explode(F.array("w_a", "w_b", "w_c")).alias("word")).where("word != pivot")
    stop = F.broadcast(f.stop.select(F.col("domain").alias("tgt"), "word", F.lit(1).alias("s")))
    return counted.unionByName(held).join(stop, ["tgt", "word"], "left").groupBy("kind", "src", "tgt").agg(F.count("*").alias("links"), F.count("s").alias("false_links"))
