"""Frames that several registered queries share, and the SQL that says the same for the oracles."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexbridge.operators import bank as B
from lexbridge.operators import naive_bayes as NB
from lexbridge.operators import pivots as P
from lexbridge.sources.tables import corpus, domain_pairs

MIN_DF = 5
K = 50
ALPHA = 0.95
SEED = 11
THETA = 0.9


class Frames:
    """Lazily built frames over one folder of tables."""

    def __init__(self, spark: SparkSession, sf_dir: str, grid: str = "near", min_df: int = MIN_DF):
        self.spark, self.sf_dir, self.min_df = spark, sf_dir, min_df
        self.docs = corpus(spark, sf_dir)
        self.pairs = domain_pairs(spark, grid)
        self.inc = P.incidence(self.docs)
        self.counts = P.word_counts(self.inc)
        self.pool = P.candidate_pool(self.counts, self.pairs, min_df)
        self.pol = P.polarity(self.counts)

    def bank(self) -> DataFrame:
        return B.init_banks(self.pool, self.pol)

    def nb(self) -> DataFrame:
        return NB.naive_bayes(self.docs, self.inc, self.counts, self.pool, self.pairs)

    def pseudo(self) -> DataFrame:
        """Pseudo-labels of the texts whose label is unknown or belongs to the target."""
        free = self.docs.select("doc_id", F.col("label").isNull().alias("free"))
        return B.pseudo_label(self.nb().join(free, "doc_id").where("side = 'T' or free"), THETA)

    def evidence(self) -> DataFrame:
        true_s = self.docs.where("label is not null").select("doc_id", "label", F.col("domain").alias("src")).join(F.broadcast(self.pairs), "src")
        pseudo = self.pseudo()
        return B.evidence(true_s, pseudo.where("side = 'S'"), pseudo.where("side = 'T'"))

    def updates(self) -> DataFrame:
        ev = B.schedule(self.evidence(), ("src", "tgt", "side"), SEED)
        return B.updates(ev, self.inc, self.pool)


CORPUS = r"""corpus AS MATERIALIZED (
  SELECT d.doc_id, d.text, d.lang, CASE WHEN d.lang = 'en' THEN 'N' || (CAST(substr(d.source, 4) AS INTEGER) // 5 + 1)::VARCHAR ELSE 'FAR' END AS domain,
         2 * l.toxic - 1 AS label,
         CASE WHEN l.toxic IS NULL THEN 'unlabelled' WHEN ('0x' || substr(md5(d.text || '|7'), 1, 8))::BIGINT % 5 = 0 THEN 'dev' ELSE 'train' END AS split
  FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)"""
SENTENCES = r"""cut AS (SELECT doc_id, domain, generate_subscripts(string_split_regex(lower(text), '[.!?\n]+'), 1) - 1 AS sent_ix, unnest(string_split_regex(lower(text), '[.!?\n]+')) AS sentence FROM corpus),
sentences AS (SELECT * FROM cut WHERE trim(sentence, ' ') <> '')"""
# sentences of over 64 words stand in even parts, and the parts of a text are numbered
WORDS = r"""sw AS (SELECT doc_id, domain, sent_ix, regexp_extract_all(sentence, '\p{L}+') AS ws FROM cut),
sp AS (SELECT *, greatest(1, (len(ws) + 63) // 64) AS np FROM sw),
parts_of AS (SELECT *, unnest(range(np)) AS part FROM sp),
sent AS MATERIALIZED (SELECT * FROM (SELECT doc_id, domain, row_number() OVER (PARTITION BY doc_id ORDER BY sent_ix, part) - 1 AS sent_ix, ws[(len(ws) * part // np + 1):(len(ws) * (part + 1) // np)] AS words FROM parts_of) WHERE len(words) >= 3)"""
INC = r"""inc AS MATERIALIZED (SELECT doc_id, domain, label, split, unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+'))) AS word FROM corpus),
wc AS MATERIALIZED (SELECT domain, word, count(*) AS df, count(*) FILTER (WHERE label = 1) AS n_pos, count(*) FILTER (WHERE label = -1) AS n_neg FROM inc GROUP BY ALL)"""
DOMAIN_ROWS = "dom AS (SELECT unnest(['N1', 'N2', 'N3', 'N4', 'FAR']) AS d)"
PAIRS = {
    "near": DOMAIN_ROWS + ",\npairs AS (SELECT a.d AS src, b.d AS tgt FROM dom a, dom b WHERE a.d <> b.d AND a.d <> 'FAR' AND b.d <> 'FAR')",
    "all": DOMAIN_ROWS + ",\npairs AS (SELECT a.d AS src, b.d AS tgt FROM dom a, dom b WHERE a.d <> b.d)",
}
POOL = f"""often AS MATERIALIZED (SELECT domain, word, df FROM wc WHERE df >= {MIN_DF}),
shared AS MATERIALIZED (SELECT s.domain AS src, t.domain AS tgt, s.word, s.df AS df_s, t.df AS df_t FROM often s JOIN often t ON s.word = t.word),
pool AS MATERIALIZED (SELECT src, tgt, word, df_s, df_t FROM shared JOIN pairs USING (src, tgt))"""
POL = "pol AS MATERIALIZED (SELECT domain, word, n_pos, n_neg, (n_pos - n_neg)::DOUBLE / (n_pos + n_neg) AS p FROM wc WHERE n_pos + n_neg >= 1)"
BANK = "bank AS (SELECT src, tgt, side, pool.word, coalesce(p, 0.0) AS p FROM pool CROSS JOIN (SELECT unnest(['S', 'T']) AS side) LEFT JOIN pol ON pol.domain = src AND pol.word = pool.word)"
NAIVE = r"""tot AS (SELECT domain AS src, count(*) FILTER (WHERE label = 1) AS n1, count(*) FILTER (WHERE label = -1) AS n0 FROM corpus WHERE label IS NOT NULL GROUP BY 1),
nbw AS MATERIALIZED (SELECT pool.src, tgt, pool.word, ln((n_pos + 1)::DOUBLE / (n1 + 2)) - ln((n_neg + 1)::DOUBLE / (n0 + 2)) AS term FROM pool JOIN wc ON wc.domain = pool.src AND wc.word = pool.word JOIN tot ON tot.src = pool.src),
sides AS (SELECT src, tgt, 'S' AS side, src AS domain FROM pairs UNION ALL SELECT src, tgt, 'T', tgt FROM pairs),
nbh AS MATERIALIZED (SELECT s.src, s.tgt, s.side, i.doc_id, sum(term) AS t, count(*) AS m FROM inc i JOIN sides s ON s.domain = i.domain JOIN nbw w ON w.src = s.src AND w.tgt = s.tgt AND w.word = i.word GROUP BY ALL),
nbs AS (SELECT s.src, s.tgt, s.side, c.doc_id, c.label, ln((n1 + 1)::DOUBLE / (n0 + 1)) + coalesce(t / sqrt(m), 0.0) AS score
        FROM corpus c JOIN sides s ON s.domain = c.domain JOIN tot ON tot.src = s.src LEFT JOIN nbh h ON h.src = s.src AND h.tgt = s.tgt AND h.side = s.side AND h.doc_id = c.doc_id),
nb AS MATERIALIZED (SELECT src, tgt, side, doc_id, label, score, 1 / (1 + exp(-score)) AS p_pos, CASE WHEN round(score, 9) > 0 THEN 1 ELSE -1 END AS pred FROM nbs)"""
PSEUDO = f"""pseudo AS MATERIALIZED (SELECT src, tgt, side, doc_id, greatest(p_pos, 1 - p_pos) AS conf, CASE WHEN p_pos > 0.5 THEN 1 ELSE -1 END AS label
            FROM nb WHERE (side = 'T' OR label IS NULL) AND greatest(p_pos, 1 - p_pos) > {THETA})"""
EVIDENCE = f"""ev AS (SELECT src, tgt, 'S' AS side, doc_id, label FROM corpus JOIN pairs ON domain = src WHERE label IS NOT NULL UNION ALL SELECT src, tgt, side, doc_id, label FROM pseudo),
evs AS MATERIALIZED (SELECT *, (row_number() OVER (PARTITION BY src, tgt, side ORDER BY md5(doc_id::VARCHAR || '|{SEED}'), doc_id) - 1) // 32 AS step FROM ev),
ups AS MATERIALIZED (SELECT e.src, e.tgt, e.side, i.word, e.step, e.doc_id, e.label FROM evs e JOIN inc i ON i.doc_id = e.doc_id JOIN pool ON pool.src = e.src AND pool.tgt = e.tgt AND pool.word = i.word)"""


def td_sql(updates: str = "ups", name: str = "folded") -> str:
    return f"""{name} AS (
  SELECT src, tgt, side, word, count(*) AS n, sum({1 - ALPHA!r} * label * pow({ALPHA}, later)) AS s
  FROM (SELECT *, count(*) OVER (PARTITION BY src, tgt, side, word) - row_number() OVER (PARTITION BY src, tgt, side, word ORDER BY step, doc_id) AS later FROM {updates}) GROUP BY ALL),
{name}_bank AS (SELECT b.src, b.tgt, b.side, b.word, pow({ALPHA}, coalesce(n, 0)) * p + coalesce(s, 0) AS p, coalesce(n, 0)::BIGINT AS n_updates
  FROM bank b LEFT JOIN {name} f ON f.src = b.src AND f.tgt = b.tgt AND f.side = b.side AND f.word = b.word)"""


def with_(*parts: str, select: str) -> str:
    # a word that DuckDB keeps for itself
    return re.sub(r"(?<![\w\"'-])pivot(?![\w\"'])", '"pivot"', "WITH " + ",\n".join(parts) + "\n" + select)


EVIDENCED = (CORPUS, INC, PAIRS["near"], POOL, POL, BANK, NAIVE, PSEUDO, EVIDENCE)
