"""The pivot-prediction task: masked pivots, and the original linear predictors of each pivot from all non-pivots."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MASK = "[MASK]"


def mask_words(words: Column, pivots: Column) -> Column:
    """Pivot words replaced by the mask symbol."""
    return F.transform(words, lambda w: F.when(F.array_contains(pivots, w), F.lit(MASK)).otherwise(w))


def mask_pivots(trees: DataFrame, pivots: DataFrame) -> DataFrame:
    """``trees`` with pivots of the trunk masked in ``tokens`` and listed, in order, in ``masked``. The pivots of a pair are a bounded list."""
    named = pivots.groupBy("src", "tgt").agg(F.collect_set("word").alias("pv"))
    hit = lambda t: (t.branch == 0) & F.array_contains(F.col("pv"), t.tok)
    out = trees.join(F.broadcast(named), ["src", "tgt"])
    out = out.withColumn("masked", F.transform(F.filter("tokens", hit), lambda t: t.tok))
    return out.withColumn("tokens", F.transform("tokens", lambda t: F.struct(F.when(hit(t), F.lit(MASK)).otherwise(t.tok).alias("tok"), t.pos.alias("pos"), t.branch.alias("branch"), t.trunk.alias("trunk")))).drop("pv")


def predictor_counts(inc: DataFrame, pivots: DataFrame) -> DataFrame:
    """(src, tgt, pivot, word, n): target texts that hold both a pivot and a non-pivot. The pivots are the small side."""
    p = F.broadcast(pivots.select("src", "tgt", F.col("word").alias("pivot")))
    with_pivot = inc.select("doc_id", F.col("domain").alias("tgt"), F.col("word").alias("pivot")).join(p, ["tgt", "pivot"])
    others = inc.select("doc_id", "word")
    both = with_pivot.join(others, "doc_id").join(F.broadcast(pivots.select("src", "tgt", "word")), ["src", "tgt", "word"], "left_anti")
    return both.groupBy("src", "tgt", "pivot", "word").agg(F.count("*").alias("n"))


def pivot_predictors(counts: DataFrame, predictor: DataFrame, domain_size: DataFrame) -> DataFrame:
    """Log-odds weight of each non-pivot for each pivot, from the counts: (src, tgt, pivot, word, n, weight). ``domain_size``: (domain, texts)."""
    c = counts.select(F.col("domain").alias("tgt"), "word", "df")
    joined = predictor.join(c.withColumnRenamed("df", "df_w"), ["tgt", "word"]).join(F.broadcast(c.select("tgt", F.col("word").alias("pivot"), F.col("df").alias("df_p"))), ["tgt", "pivot"]).join(F.broadcast(domain_size.withColumnRenamed("domain", "tgt")), "tgt")
    inside = (F.col("n") + 0.5) / (F.col("df_p") + 1)
    outside = (F.col("df_w") - F.col("n") + 0.5) / (F.col("texts") - F.col("df_p") + 1)
    return joined.select("src", "tgt", "pivot", "word", "n", F.log(inside / outside).alias("weight"))
