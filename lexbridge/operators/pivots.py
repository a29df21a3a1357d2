"""Pivot statistics: counts of words over labelled texts, polarity, pair scores and the choice of pivots.

All domain pairs share one pass: :func:`word_counts` is the only shuffle of incidences, everything after it works on one row for each
word and domain.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.functions.text import word_list


def incidence(docs: DataFrame, count_mode: str = "text", symbols: bool = False) -> DataFrame:
    """(doc_id, domain, label, split, word): once for each text and word, or for each occurrence."""
    words = word_list(F.col("text"), symbols)
    words = F.array_distinct(words) if count_mode == "text" else words
    return docs.select("doc_id", "domain", "label", "split", F.explode(words).alias("word"))


def word_counts(inc: DataFrame) -> DataFrame:
    """(domain, word, df, n_pos, n_neg): texts that hold the word, and those of them with each label."""
    return inc.groupBy("domain", "word").agg(F.count("*").alias("df"), F.count_if(F.col("label") == 1).alias("n_pos"), F.count_if(F.col("label") == -1).alias("n_neg"))


def candidate_pool(counts: DataFrame, pairs: DataFrame, min_df: int = 5, max_df: int | None = None) -> DataFrame:
    """(src, tgt, word, df_s, df_t): words frequent in both domains of a pair."""
    often = counts.where(F.col("df") >= min_df)
    often = often if max_df is None else often.where(F.col("df") <= max_df)
    src = often.select(F.col("domain").alias("src"), "word", F.col("df").alias("df_s"))
    tgt = often.select(F.col("domain").alias("tgt"), "word", F.col("df").alias("df_t"))
    return src.join(tgt, "word").join(F.broadcast(pairs), ["src", "tgt"]).select("src", "tgt", "word", "df_s", "df_t")


def polarity_of(n_pos: Column, n_neg: Column, alpha: float = 0.0) -> Column:
    """Share of label 1 less share of label -1 among the labelled texts; null without any."""
    return (n_pos - n_neg) / F.nullif(n_pos + n_neg + F.lit(alpha), F.lit(0.0))


def polarity(counts: DataFrame, min_labelled: int = 1, alpha: float = 0.0) -> DataFrame:
    """(domain, word, n_pos, n_neg, p); ``alpha`` damps words of little support."""
    out = counts.where(F.col("n_pos") + F.col("n_neg") >= min_labelled)
    return out.select("domain", "word", "n_pos", "n_neg", polarity_of(F.col("n_pos"), F.col("n_neg"), alpha).alias("p"))


def label_prior(docs: DataFrame) -> DataFrame:
    """(domain, prior): the polarity of a domain as a whole."""
    return docs.where("label is not null").groupBy("domain").agg(F.avg("label").alias("prior"))


def centred(pol: DataFrame, prior: DataFrame) -> DataFrame:
    """Polarity less the domain's prior, for labels that are far from balanced."""
    return pol.join(F.broadcast(prior), "domain").withColumn("p", F.col("p") - F.col("prior")).drop("prior")


def label_entropy(inc: DataFrame) -> DataFrame:
    """(domain, word, n, entropy in bits, top label), for any number of classes."""
    by_label = inc.where("label is not null").groupBy("domain", "word", "label").agg(F.count("*").alias("c"))
    total = F.sum("c").over(W.partitionBy("domain", "word"))
    shares = by_label.withColumn("n", total).withColumn("q", F.col("c") / F.col("n"))
    return shares.groupBy("domain", "word").agg(
        F.first("n").alias("n"), (0 - F.sum(F.col("q") * F.log2("q"))).alias("entropy"), F.max_by("label", F.struct("c", "label")).alias("top_label")
    )


def entropy_pivots(entropy: DataFrame, pool: DataFrame, k: int) -> DataFrame:
    """(src, tgt, word, worst entropy, rank): low-entropy words whose majority label agrees in both domains."""
    s = entropy.select(F.col("domain").alias("src"), "word", F.col("entropy").alias("h_s"), F.col("top_label").alias("l_s"))
    t = entropy.select(F.col("domain").alias("tgt"), "word", F.col("entropy").alias("h_t"), F.col("top_label").alias("l_t"))
    both = pool.join(s, ["src", "word"]).join(t, ["tgt", "word"]).where("l_s = l_t").withColumn("h", F.round(F.greatest("h_s", "h_t"), 9))
    rank = F.row_number().over(W.partitionBy("src", "tgt").orderBy("h", F.desc(F.col("df_s") + F.col("df_t")), "word"))
    return both.withColumn("rank", rank).where(F.col("rank") <= k).select("src", "tgt", "word", "h", "rank")


def pair_score(pool: DataFrame, pol: DataFrame) -> DataFrame:
    """(src, tgt, word, p_s, p_t, score): absolute mean of the two polarities, so opposite signs cancel."""
    s = pol.select(F.col("domain").alias("src"), "word", F.col("p").alias("p_s"))
    t = pol.select(F.col("domain").alias("tgt"), "word", F.col("p").alias("p_t"))
    return pool.join(s, ["src", "word"]).join(t, ["tgt", "word"]).select("src", "tgt", "word", "df_s", "df_t", "p_s", "p_t", (F.abs(F.col("p_s") + F.col("p_t")) / 2).alias("score"))


def top_pivots(scored: DataFrame, k: int) -> DataFrame:
    """(src, tgt, rank, word, score): the k words of highest score of each pair; ties go to the more frequent, then by word."""
    order = W.partitionBy("src", "tgt").orderBy(F.desc(F.round("score", 9)), F.desc(F.col("df_s") + F.col("df_t")), "word")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("src", "tgt", "rank", "word", "score")


def initial_pivots(pool: DataFrame, pol: DataFrame, k: int = 500, drop_unseen: bool = False) -> DataFrame:
    """Pivots before training: both domains start from the source's polarity, so the score is its absolute value."""
    s = pol.select(F.col("domain").alias("src"), "word", F.col("p").alias("p_s"))
    joined = pool.join(s, ["src", "word"], "inner" if drop_unseen else "left")
    return top_pivots(joined.withColumn("score", F.abs(F.coalesce("p_s", F.lit(0.0)))), k)


def pivot_diff(before: DataFrame, after: DataFrame) -> DataFrame:
    """(src, tgt, side, word): pivots that went and pivots that came."""
    a, b = (x.select("src", "tgt", "word") for x in (before, after))
    return a.exceptAll(b).withColumn("side", F.lit("initial")).unionByName(b.exceptAll(a).withColumn("side", F.lit("learnt")))


def pivot_quality(pivots: DataFrame, pol: DataFrame, counts: DataFrame, strong: float = 0.5, lean: float = 2.0) -> DataFrame:
    """(src, tgt, n, polar_share, source_share): pivots of strong target polarity, and pivots used mostly in the source."""
    t = pol.select(F.col("domain").alias("tgt"), "word", F.abs("p").alias("abs_t"))
    cs = counts.select(F.col("domain").alias("src"), "word", F.col("df").alias("df_s"))
    ct = counts.select(F.col("domain").alias("tgt"), "word", F.col("df").alias("df_t"))
    joined = pivots.select("src", "tgt", "word").join(t, ["tgt", "word"], "left").join(cs, ["src", "word"], "left").join(ct, ["tgt", "word"], "left")
    return joined.groupBy("src", "tgt").agg(
        F.count("*").alias("n"), F.avg((F.coalesce("abs_t", F.lit(0.0)) >= strong).cast("int")).alias("polar_share"), F.avg((F.coalesce("df_s", F.lit(0)) > lean * F.coalesce("df_t", F.lit(0))).cast("int")).alias("source_share")
    )


def behaviour(pol: DataFrame, words: list[str], domains: tuple[str, ...]) -> DataFrame:
    """One row for each asked word, its polarity in every domain side by side."""
    return pol.where(F.col("word").isin(words)).groupBy("word").pivot("domain", list(domains)).agg(F.first("p"))
