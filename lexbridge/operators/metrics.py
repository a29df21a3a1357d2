"""Measures over predictions and over accuracy tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def confusion(pred: DataFrame, by: list[str]) -> DataFrame:
    """``pred`` has pred and label (1, -1): tp, fp, fn, tn of each group."""
    is_ = lambda p, y: F.count_if((F.col("pred") == p) & (F.col("label") == y))
    return pred.where("label is not null").groupBy(*by).agg(is_(1, 1).alias("tp"), is_(1, -1).alias("fp"), is_(-1, 1).alias("fn"), is_(-1, -1).alias("tn"))


def accuracy(pred: DataFrame, by: list[str]) -> DataFrame:
    """Accuracy in percent with balanced accuracy and F1 beside it; a class without texts leaves the mean of recalls to the other."""
    c = confusion(pred, by)
    pos, neg = F.col("tp") + F.col("fn"), F.col("tn") + F.col("fp")
    recall_1, recall_0 = F.col("tp") / F.nullif(pos, F.lit(0)), F.col("tn") / F.nullif(neg, F.lit(0))
    balanced = (F.coalesce(recall_1, recall_0) + F.coalesce(recall_0, recall_1)) / 2
    f1 = 2 * F.col("tp") / F.nullif(2 * F.col("tp") + F.col("fp") + F.col("fn"), F.lit(0))
    return c.select(*by, (pos + neg).alias("n"), (100 * (F.col("tp") + F.col("tn")) / (pos + neg)).alias("accuracy"), (100 * balanced).alias("balanced"), F.coalesce(f1, F.lit(0.0)).alias("f1"))


def auc(scored: DataFrame, by: list[str], score: str = "score") -> DataFrame:
    """Area under the ROC curve by rank sums, ties at their mean rank; null with one class."""
    w = W.partitionBy(*by)
    s = scored.where("label is not null").withColumn("s", F.round(score, 9))
    tied = F.count("*").over(W.partitionBy(*by, "s"))
    ranked = s.withColumn("r", F.rank().over(w.orderBy("s")) + (tied - 1) / 2)
    out = ranked.groupBy(*by).agg(F.sum(F.when(F.col("label") == 1, F.col("r"))).alias("rs"), F.count_if(F.col("label") == 1).alias("n1"), F.count_if(F.col("label") == -1).alias("n0"))
    return out.select(*by, ((F.col("rs") - F.col("n1") * (F.col("n1") + 1) / 2) / F.nullif(F.col("n1") * F.col("n0"), F.lit(0))).alias("auc"))


def grid_average(table: DataFrame) -> DataFrame:
    """(method, pairs, average): the plain mean over the pairs of a grid."""
    return table.groupBy("method").agg(F.count("*").alias("pairs"), F.avg("accuracy").alias("average"))


def winners(table: DataFrame) -> DataFrame:
    """(pair, method, accuracy): the best method of each pair, ties shared."""
    rank = F.rank().over(W.partitionBy("pair").orderBy(F.desc(F.round("accuracy", 9))))
    return table.withColumn("r", rank).where("r = 1").select("pair", "method", "accuracy")


def gain_table(averages: DataFrame) -> DataFrame:
    """(method, over, gain): differences of averages in points."""
    a, b = averages.select("method", F.col("average").alias("x")), averages.select(F.col("method").alias("over"), F.col("average").alias("y"))
    return a.crossJoin(F.broadcast(b)).where("method != over").select("method", "over", (F.col("x") - F.col("y")).alias("gain"))


def pseudo_quality(pseudo: DataFrame, truth: DataFrame, candidates: DataFrame) -> DataFrame:
    """(src, tgt, side, texts, taken, known, precision): how many texts got a pseudo-label, and how many of those with a hidden label got the right one."""
    by = ["src", "tgt", "side"]
    got = pseudo.select(*by, "doc_id", F.col("label").alias("guess")).join(truth.select("doc_id", "label"), "doc_id", "left")
    taken = got.groupBy(*by).agg(F.count("*").alias("taken"), F.count("label").alias("known"), F.avg((F.col("guess") == F.col("label")).cast("int")).alias("precision"))
    return candidates.groupBy(*by).agg(F.count("*").alias("texts")).join(taken, by, "left").select(*by, "texts", F.coalesce("taken", F.lit(0)).alias("taken"), F.coalesce("known", F.lit(0)).alias("known"), "precision")
