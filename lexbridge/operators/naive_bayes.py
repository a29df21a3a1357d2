"""Closed-form classifiers on pool words: damped naive Bayes, the vote of pivots and the majority class."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.sources.stage import stage

#: Words of domains that are sent to every task with their terms.
SMALL_ROWS = 1_000_000


def naive_bayes(docs: DataFrame, inc: DataFrame, counts: DataFrame, pool: DataFrame, pairs: DataFrame) -> DataFrame:
    """(src, tgt, doc_id, side, score, p_pos, pred): source label counts score the texts of both domains of each pair.

    A text's word terms are damped by the root of their number; a text without pool words has the prior alone.
    """
    totals = docs.where("label is not null").groupBy(F.col("domain").alias("src")).agg(F.count_if(F.col("label") == 1).alias("n1"), F.count_if(F.col("label") == -1).alias("n0"))
    s = counts.select(F.col("domain").alias("src"), "word", "n_pos", "n_neg")
    weights = pool.join(s, ["src", "word"]).join(F.broadcast(totals), "src")
    term = F.log((F.col("n_pos") + 1) / (F.col("n1") + 2)) - F.log((F.col("n_neg") + 1) / (F.col("n0") + 2))
    weights = weights.select("src", "tgt", "word", term.alias("term"))
    sides = F.broadcast(pairs.select("src", "tgt", F.explode(F.array(F.struct(F.lit("S").alias("side"), F.col("src").alias("domain")), F.struct(F.lit("T").alias("side"), F.col("tgt").alias("domain")))).alias("x")).select("src", "tgt", "x.side", "x.domain"))
    # what a word adds to each side of each pair, in one row of its domain, so that a text's words stay in their task
    terms = weights.join(sides, ["src", "tgt"]).groupBy("domain", "word").agg(F.collect_list(F.struct("src", "tgt", "side", "term")).alias("terms"))
    terms = stage(terms, "terms")
    terms = F.broadcast(terms) if terms.count() <= SMALL_ROWS else terms
    hits = inc.select("doc_id", "domain", "word").join(terms, ["domain", "word"]).select("doc_id", F.inline("terms"))
    sums = hits.groupBy("src", "tgt", "side", "doc_id").agg(F.sum("term").alias("t"), F.count("*").alias("m"))
    every = docs.select("doc_id", "domain").join(sides, "domain").join(F.broadcast(totals), "src").join(sums, ["src", "tgt", "side", "doc_id"], "left")
    score = F.log((F.col("n1") + 1) / (F.col("n0") + 1)) + F.coalesce(F.col("t") / F.sqrt("m"), F.lit(0.0))
    out = every.withColumn("score", score)
    return out.select("src", "tgt", "side", "doc_id", "score", (1 / (1 + F.exp(-F.col("score")))).alias("p_pos"), F.when(F.round("score", 9) > 0, 1).otherwise(-1).alias("pred"))


def pivot_vote(docs: DataFrame, inc: DataFrame, pivots: DataFrame, pol: DataFrame) -> DataFrame:
    """(src, tgt, doc_id, vote, pred): the sum of the source polarities of a target text's pivots decides by sign."""
    p = pivots.join(pol.select(F.col("domain").alias("src"), "word", "p"), ["src", "word"]).select("src", "tgt", "word", "p")
    votes = inc.select("doc_id", F.col("domain").alias("tgt"), "word").join(F.broadcast(p), ["tgt", "word"]).groupBy("src", "tgt", "doc_id").agg(F.sum("p").alias("v"))
    every = docs.select("doc_id", F.col("domain").alias("tgt")).join(F.broadcast(pivots.select("src", "tgt").distinct()), "tgt")
    out = every.join(votes, ["src", "tgt", "doc_id"], "left").withColumn("vote", F.coalesce("v", F.lit(0.0)))
    return out.select("src", "tgt", "doc_id", "vote", F.when(F.round("vote", 9) > 0, 1).otherwise(-1).alias("pred"))


def majority(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(src, tgt, pred): the source's commoner label; -1 if they are as many."""
    sign = docs.where("label is not null").groupBy(F.col("domain").alias("src")).agg(F.when(F.sum("label") > 0, 1).otherwise(-1).alias("pred"))
    return pairs.join(sign, "src").select("src", "tgt", "pred")
