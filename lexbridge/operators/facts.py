"""Facts: a pivot occurrence with the two words of its sentence that it attends to most, and the graph they make."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.sources.stage import stage

TAU_RANGE = (0.1, 0.45)
#: Billionths in one step of the counts that an exact quantile begins with.
STEP = 100_000
FACT = ("pivot", "slot", "w_a", "w_b", "w_c")


def top_two(m: Column, place: Column) -> Column:
    """Places of the two greatest weights of row ``place`` of a matrix column, itself left out; ties go to the earlier place."""
    ranked = F.array_sort(F.filter(F.transform(F.get(m, place), lambda x, j: F.struct((-F.round(x, 9)).alias("a"), j.alias("j"))), lambda s: s.j != place))
    return F.transform(F.slice(ranked, 1, 2), lambda s: s.j)


def fact_of(words: Column, m: Column, place: Column) -> Column:
    """The fact at a place: its words in sentence order, the pivot's slot and the sum of the two weights."""
    picked = F.array_sort(F.concat(F.array(place), top_two(m, place)))
    at = lambda k: F.get(words, F.get(picked, F.lit(k)))
    conf = F.aggregate(top_two(m, place), F.lit(0.0), lambda a, j: a + F.round(F.get(F.get(m, place), j), 9))
    return F.struct(at(0).alias("w_a"), at(1).alias("w_b"), at(2).alias("w_c"), (F.array_position(picked, place) - 1).cast("int").alias("slot"), conf.alias("conf"))


def make_facts(weights: DataFrame) -> DataFrame:
    """(domain, doc_id, sent_ix, i, pivot, w_a, w_b, w_c, slot, conf) from long weights (.., i, j, w_i, w_j, a).

    A sentence of fewer than three words has no second neighbour and gives no fact.
    """
    own = ["domain", "doc_id", "sent_ix", "i"]
    rank = F.row_number().over(W.partitionBy(*own).orderBy(F.desc(F.round("a", 9)), "j"))
    best = weights.withColumn("r", rank).where("r <= 2")
    pair = best.groupBy(*own, F.col("w_i").alias("pivot")).agg(F.array_sort(F.collect_list(F.struct("j", "w_j"))).alias("n"), F.sum(F.round("a", 9)).alias("conf")).where(F.size("n") == 2)
    three = F.array_sort(F.concat(F.array(F.struct(F.col("i").alias("j"), F.col("pivot").alias("w_j"))), F.col("n")))
    slot = (F.col("i") > F.col("n")[0]["j"]).cast("int") + (F.col("i") > F.col("n")[1]["j"]).cast("int")
    return pair.withColumn("t", three).select(*own, "pivot", F.col("t")[0]["w_j"].alias("w_a"), F.col("t")[1]["w_j"].alias("w_b"), F.col("t")[2]["w_j"].alias("w_c"), slot.alias("slot"), "conf")


def filter_facts(facts: DataFrame, tau: float) -> DataFrame:
    return facts.where(F.round("conf", 9) >= tau)


def suggest_tau(facts: DataFrame, q: float = 0.25, exact: bool = False) -> DataFrame:
    """One row, tau: a quantile of the confidences, kept inside the usual range."""
    quantile = F.lit(_quantile(facts, q)) if exact else F.percentile_approx("conf", F.lit(q), F.lit(10_000))
    least, most = (F.lit(t) for t in TAU_RANGE)
    rows = facts.sparkSession.range(1) if exact else facts
    held = F.least(F.greatest(quantile, least), most).alias("tau")
    return rows.select(held) if exact else rows.agg(held)


def _quantile(facts: DataFrame, q: float) -> float | None:
    """The interpolated quantile of confidences of nine digits: counts of coarse steps tell where its two ranks lie, and only those steps are looked at one by one."""
    nano = stage(facts.select(F.round(F.col("conf") * 1e9).cast("long").alias("v")), "confidences").withColumn("step", F.floor(F.col("v") / STEP))
    steps = sorted(nano.where("v is not null").groupBy("step").agg(F.count("*").alias("n")).collect())
    total = sum(r.n for r in steps)
    if not total:
        return None
    place = q * (total - 1)
    ranks, found, before = (math.floor(place), math.ceil(place)), {}, 0
    for r in steps:
        here = [k for k in ranks if before <= k < before + r.n]
        if here:
            at = before
            for v in sorted(nano.where(F.col("step") == r.step).groupBy("v").agg(F.count("*").alias("n")).collect()):
                found |= {k: v.v / 1e9 for k in here if at <= k < at + v.n}
                at += v.n
        before += r.n
    low, high = (found[k] for k in ranks)
    return low + (high - low) * (place - ranks[0])


def stop_words(counts: DataFrame, k: int = 30) -> DataFrame:
    """(domain, word): the k words that stand in most texts of each domain."""
    rank = F.row_number().over(W.partitionBy("domain").orderBy(F.desc("df"), "word"))
    return counts.withColumn("r", rank).where(F.col("r") <= k).select("domain", "word")


def drop_stop_words(facts: DataFrame, stop: DataFrame) -> DataFrame:
    """Facts none of whose words is a stop word of the domain."""
    out = facts
    for w in ("w_a", "w_b", "w_c"):
        out = out.join(F.broadcast(stop.select("domain", F.col("word").alias(w))), ["domain", w], "left_anti")
    return out


def merge_facts(facts: DataFrame) -> DataFrame:
    """One row for each distinct fact of a domain: support, greatest and mean confidence."""
    return facts.groupBy("domain", *FACT).agg(F.count("*").alias("support"), F.max("conf").alias("conf"), F.avg("conf").alias("mean_conf"))


def for_pairs(graph: DataFrame, pool: DataFrame) -> DataFrame:
    """The target domain's facts for each pair, of the pivots in that pair's pool; so pivots may change and the graph stays."""
    return graph.withColumnRenamed("domain", "tgt").join(pool.select("src", "tgt", F.col("word").alias("pivot")), ["tgt", "pivot"])


def facts_of(graph: DataFrame, entity: str) -> DataFrame:
    """All facts that hold a word, as pivot or not."""
    return graph.where((F.col("w_a") == entity) | (F.col("w_b") == entity) | (F.col("w_c") == entity))


def fact_kind(graph: DataFrame, pivots: DataFrame) -> DataFrame:
    """Adds ``links``: how many of a fact's words are no pivot of its pair."""
    out = graph
    for w in ("w_a", "w_b", "w_c"):
        out = out.join(F.broadcast(pivots.select("src", "tgt", F.col("word").alias(w), F.lit(1).alias(f"p_{w}"))), ["src", "tgt", w], "left")
    return out.withColumn("links", 3 - sum((F.coalesce(f"p_{w}", F.lit(0)) for w in ("w_a", "w_b", "w_c")), F.lit(0))).drop("p_w_a", "p_w_b", "p_w_c")


def confidence_profile(facts: DataFrame, taus: list[float]) -> DataFrame:
    """(domain, tau, kept, share): how much each threshold keeps."""
    return facts.withColumn("tau", F.explode(F.array(*[F.lit(t) for t in taus]))).groupBy("domain", "tau").agg(F.count_if(F.round("conf", 9) >= F.col("tau")).alias("kept"), F.avg((F.round("conf", 9) >= F.col("tau")).cast("int")).alias("share"))


def generic_graph(sents: DataFrame, min_count: int = 2) -> DataFrame:
    """(head, relation, tail, weight) from open-domain sentences: a word, the one between, and the word after that."""
    trio = F.transform(F.sequence(F.lit(1), F.size("words") - 2), lambda i: F.struct(F.element_at("words", i).alias("head"), F.element_at("words", i + 1).alias("relation"), F.element_at("words", i + 2).alias("tail")))
    return sents.where(F.size("words") >= 3).select(F.inline(trio)).where("head != tail").groupBy("head", "relation", "tail").agg(F.count("*").alias("weight")).where(F.col("weight") >= min_count)


def one_hop(graph: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """Edges with at least one end in the vocabulary (word)."""
    heads = graph.join(vocabulary.withColumnRenamed("word", "head"), "head", "left_semi")
    tails = graph.join(vocabulary.withColumnRenamed("word", "tail"), "tail", "left_semi")
    return heads.unionByName(tails).distinct()


def generic_facts(edges: DataFrame, pool: DataFrame) -> DataFrame:
    """One-hop edges in the form of facts, with the pool word at either end as the pivot, so both graphs inject alike."""
    cols = [F.col("head").alias("w_a"), F.col("relation").alias("w_b"), F.col("tail").alias("w_c"), (F.col("weight") / (F.col("weight") + 1)).alias("conf"), F.col("weight").alias("support")]
    ends = edges.select(F.col("head").alias("pivot"), F.lit(0).alias("slot"), *cols).unionByName(edges.select(F.col("tail").alias("pivot"), F.lit(2).alias("slot"), *cols))
    return ends.join(pool.select("src", "tgt", F.col("word").alias("pivot")), "pivot").withColumn("mean_conf", F.col("conf"))


def graph_noise(edges: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """One row: edges, the share with a word outside the vocabulary, and distinct middle words over edges."""
    known = vocabulary.select("word").distinct().withColumn("in", F.lit(1))
    out = edges.select("w_a", "w_b", "w_c")
    for w in ("w_a", "w_b", "w_c"):
        out = out.join(F.broadcast(known.select(F.col("word").alias(w), F.col("in").alias(f"k_{w}"))), w, "left")
    outside = F.col("k_w_a").isNull() | F.col("k_w_b").isNull() | F.col("k_w_c").isNull()
    return out.agg(F.count("*").alias("edges"), F.avg(outside.cast("int")).alias("outside_share"), (F.count_distinct("w_b") / F.count("*")).alias("diversity"))
