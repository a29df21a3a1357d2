"""Memory banks of word polarity and their temporal-difference updates.

An update moves a score to ``alpha * p + (1 - alpha) * label``. A run of n updates is the affine map p -> alpha^n p + s, and such maps compose,
so the sequential rule becomes an aggregate: :func:`td_fold` folds blocks in any grouping, :func:`td_exact` is the one-window form.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

KEY = ("src", "tgt", "side", "word")


def keep_share(alpha: float | None = None, rate: float | None = None) -> float:
    """The share of the old score that an update keeps, from either way of naming it."""
    if (alpha is None) == (rate is None):
        raise ValueError("give either alpha or rate")
    return alpha if alpha is not None else 1.0 - rate


def init_banks(pool: DataFrame, pol: DataFrame) -> DataFrame:
    """(src, tgt, side, word, p): source and target side both start from the source's polarity, 0 where it has none."""
    s = pol.select(F.col("domain").alias("src"), "word", "p")
    joined = pool.select("src", "tgt", "word").join(s, ["src", "word"], "left")
    return joined.select("src", "tgt", F.explode(F.array(F.lit("S"), F.lit("T"))).alias("side"), "word", F.coalesce("p", F.lit(0.0)).alias("p"))


def pseudo_label(scored: DataFrame, theta: float = 0.9) -> DataFrame:
    """Texts whose greater class probability is strictly over ``theta``, with the likelier label."""
    conf = F.greatest("p_pos", 1 - F.col("p_pos"))
    return scored.withColumn("conf", conf).where(F.col("conf") > theta).withColumn("label", F.when(F.col("p_pos") > 0.5, 1).otherwise(-1))


def evidence(labelled_s: DataFrame, pseudo_s: DataFrame, pseudo_t: DataFrame) -> DataFrame:
    """(src, tgt, side, doc_id, label): true and pseudo source labels for the source bank, target pseudo-labels for the other."""
    cols = ["src", "tgt", "doc_id", "label"]
    return (
        labelled_s.select(*cols, F.lit("S").alias("side"))
        .unionByName(pseudo_s.select(*cols, F.lit("S").alias("side")))
        .unionByName(pseudo_t.select(*cols, F.lit("T").alias("side")))
    )


def schedule(items: DataFrame, by: tuple[str, ...], seed: int, batch: int = 32) -> DataFrame:
    """Adds ``step``: the number of the batch that a text falls in, in a seeded md5 order."""
    order = F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(f"|{seed}")))
    rank = F.row_number().over(W.partitionBy(*by).orderBy(order, "doc_id"))
    return items.withColumn("step", F.floor((rank - 1) / batch))


def updates(ev: DataFrame, inc: DataFrame, pool: DataFrame) -> DataFrame:
    """(src, tgt, side, word, step, doc_id, label): one update for each evidenced text and candidate word in it."""
    words = inc.select("doc_id", "word")
    return ev.join(words, "doc_id").join(pool.select("src", "tgt", "word"), ["src", "tgt", "word"], "left_semi")


def _applied(bank: DataFrame, folded: DataFrame, alpha: float) -> DataFrame:
    out = bank.join(folded, list(KEY), "left")
    n = F.coalesce("n", F.lit(0))
    return out.select(*KEY, (F.pow(F.lit(alpha), n) * F.col("p") + F.coalesce("s", F.lit(0.0))).alias("p"), n.cast("long").alias("n_updates"))


def td_exact(bank: DataFrame, ups: DataFrame, alpha: float, order: tuple[str, ...] = ("step", "doc_id")) -> DataFrame:
    """The bank after all updates in order, as one closed sum for each word."""
    w = W.partitionBy(*KEY)
    later = F.count("*").over(w) - F.row_number().over(w.orderBy(*order))
    weighed = ups.withColumn("v", (1 - alpha) * F.col("label") * F.pow(F.lit(alpha), later))
    return _applied(bank, weighed.groupBy(*KEY).agg(F.count("*").alias("n"), F.sum("v").alias("s")), alpha)


def td_blocks(ups: DataFrame, alpha: float, block_steps: int, order: tuple[str, ...] = ("step", "doc_id")) -> DataFrame:
    """(key, block, n, s): the affine map of each block of steps."""
    ups = ups.withColumn("block", F.floor(F.col("step") / block_steps))
    w = W.partitionBy(*KEY, "block")
    later = F.count("*").over(w) - F.row_number().over(w.orderBy(*order))
    return ups.withColumn("v", (1 - alpha) * F.col("label") * F.pow(F.lit(alpha), later)).groupBy(*KEY, "block").agg(F.count("*").alias("n"), F.sum("v").alias("s"))


def compose(maps: Column, alpha: float) -> Column:
    """Composes an ordered array of (block, n, s) maps into one (n, s)."""
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0.0).alias("s"))
    return F.aggregate(maps, zero, lambda a, x: F.struct((a.n + x.n).alias("n"), (F.pow(F.lit(alpha), x.n) * a.s + x.s).alias("s")))


def td_fold(bank: DataFrame, blocks: DataFrame, alpha: float) -> DataFrame:
    """The bank after the blocks, in block order: the same result as :func:`td_exact`, from partial folds."""
    maps = blocks.groupBy(*KEY).agg(F.array_sort(F.collect_list(F.struct("block", "n", "s"))).alias("maps"))
    folded = maps.withColumn("f", compose(F.col("maps"), alpha)).select(*KEY, F.col("f.n").alias("n"), F.col("f.s").alias("s"))
    return _applied(bank, folded, alpha)


def td_step_mean(bank: DataFrame, ups: DataFrame, alpha: float) -> DataFrame:
    """Free of order inside a step: its n labels act as n updates with their mean."""
    per = ups.groupBy(*KEY, "step").agg(F.count("*").alias("k"), F.avg("label").alias("m"))
    w = W.partitionBy(*KEY)
    later = F.sum("k").over(w) - F.sum("k").over(w.orderBy("step"))
    weighed = per.withColumn("v", (1 - F.pow(F.lit(alpha), F.col("k"))) * F.col("m") * F.pow(F.lit(alpha), later))
    return _applied(bank, weighed.groupBy(*KEY).agg(F.sum("k").alias("n"), F.sum("v").alias("s")), alpha)


def td_tail(bank: DataFrame, ups: DataFrame, alpha: float, tail: int, order: tuple[str, ...] = ("step", "doc_id")) -> DataFrame:
    """Only the last ``tail`` updates of a word, which bounds its state; older ones weigh less than alpha^tail."""
    last = W.partitionBy(*KEY).orderBy(*[F.desc(c) for c in order])
    return td_exact(bank, ups.withColumn("back", F.row_number().over(last)).where(F.col("back") <= tail).drop("back"), alpha, order)


def refresh(bank: DataFrame, pool: DataFrame, k: int) -> DataFrame:
    """(src, tgt, rank, word, score): the pivots that the two sides of a bank name."""
    from lexbridge.operators.pivots import top_pivots

    score = bank.groupBy("src", "tgt", "word").agg((F.abs(F.sum("p")) / 2).alias("score"))
    return top_pivots(score.join(pool, ["src", "tgt", "word"]), k)


def history(bank: DataFrame, ups: DataFrame, alpha: float, every: int) -> DataFrame:
    """(key, block, p): the bank after each block of ``every`` steps, all blocks in one pass.

    Every block's map is sent to itself and to the blocks after it, so this is for as many renewals as an epoch has, not for every step.
    """
    blocks = td_blocks(ups, alpha, every)
    spans = blocks.groupBy("src", "tgt").agg(F.max("block").alias("top"))
    reach = blocks.join(F.broadcast(spans), ["src", "tgt"]).withColumn("upto", F.explode(F.sequence("block", "top")))
    maps = reach.groupBy(*KEY, "upto").agg(F.array_sort(F.collect_list(F.struct("block", "n", "s"))).alias("maps")).withColumn("f", compose(F.col("maps"), alpha))
    grid = bank.join(F.broadcast(spans), ["src", "tgt"]).withColumn("upto", F.explode(F.sequence(F.lit(0).cast("long"), "top")))
    joined = grid.join(maps.select(*KEY, "upto", "f"), [*KEY, "upto"], "left")
    p = F.pow(F.lit(alpha), F.coalesce("f.n", F.lit(0))) * F.col("p") + F.coalesce("f.s", F.lit(0.0))
    return joined.select(*KEY, F.col("upto").alias("block"), p.alias("p"))


def best_epoch(pivots: DataFrame, dev: DataFrame) -> DataFrame:
    """The pivots of each pair's best epoch; ``dev`` has (src, tgt, epoch, accuracy). The earliest of equals wins."""
    best = dev.groupBy("src", "tgt").agg(F.max_by("epoch", F.struct("accuracy", -F.col("epoch"))).alias("epoch"))
    return pivots.join(F.broadcast(best), ["src", "tgt", "epoch"])


def bank_error(bank: DataFrame, true_pol: DataFrame) -> DataFrame:
    """(src, tgt, n, error): mean distance of the target side to the target's own polarity."""
    t = true_pol.select(F.col("domain").alias("tgt"), "word", F.col("p").alias("true_p"))
    joined = bank.where("side = 'T'").join(t, ["tgt", "word"])
    return joined.groupBy("src", "tgt").agg(F.count("*").alias("n"), F.avg(F.abs(F.col("p") - F.col("true_p"))).alias("error"))
