"""Registered queries of the experiment workloads: method grids, ablations, shift matrix, pivots and settings."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.operators import encoder as E
from lexbridge.operators import metrics as M
from lexbridge.operators import pivots as P
from lexbridge.operators import train as T
from lexbridge.operators.model import TrainConfig
from lexbridge.plans.frames import Frames
from lexbridge.plans.graph import GraphFrames, open_sentences
from lexbridge.sources.stage import stage
from lexbridge.sources.tables import DOMAINS, corpus, domain_pairs, rename_vocabulary, table

QUERIES, ORACLES = {}, {}
CFG = TrainConfig()
#: Ordered pairs of the component ablation and of the pivot comparison, in the shape of the published ones.
ABLATION_PAIRS = [("FAR", "N1"), ("N1", "N3"), ("N3", "N4"), ("N4", "N2"), ("N2", "FAR")]
PIVOT_PAIRS = [("N1", "N3"), ("N3", "N4"), ("N4", "N2")]


def query(f):
    QUERIES[f.__name__] = f
    return f


def pairs_of(spark, rows) -> DataFrame:
    return spark.createDataFrame(rows, "src string, tgt string")


def accuracies(docs: DataFrame, pairs: DataFrame, methods: list[str], cfg: TrainConfig = CFG, open_sents: DataFrame | None = None) -> DataFrame:
    """(method, src, tgt, n, accuracy, balanced, f1) on labelled target texts."""
    graph = any(T.METHODS[m].inject for m in methods)
    done = T.run(T.prepare(docs, pairs, cfg, open_sents=open_sents, graph=graph), methods, cfg)
    return M.accuracy(done.predictions(), ["method", "src", "tgt"])


def _grid(name: str, grid: str, method: str) -> None:
    def run(spark, sf_dir):
        return accuracies(corpus(spark, sf_dir), domain_pairs(spark, grid), [method])

    run.__name__, run.__doc__ = name, f"Target accuracy of one method on each {grid} pair."
    QUERIES[name] = run


for _m in ("plain", "hier", "adversarial", "posttrain", "inject", "full"):
    _grid(f"wl_near_grid_{_m}", "near", _m)
for _m in ("plain", "adversarial", "inject", "full"):
    _grid(f"wl_far_grid_{_m}", "far", _m)


@query
def wl_near_summary(spark, sf_dir):
    """Averages, gains over the plain method and numbers of pairs won, six methods side by side."""
    table_ = accuracies(corpus(spark, sf_dir), domain_pairs(spark, "near"), ["plain", "hier", "adversarial", "posttrain", "inject", "full"])
    named = table_.select("method", F.concat_ws("-", "src", "tgt").alias("pair"), "accuracy", "balanced")
    won = M.winners(named).groupBy("method").agg(F.count("*").alias("won"))
    averages = named.groupBy("method").agg(F.avg("accuracy").alias("average"), F.avg("balanced").alias("balanced"))
    plain = averages.where("method = 'plain'").select(F.col("average").alias("base"))
    return averages.crossJoin(F.broadcast(plain)).join(won, "method", "left").select("method", "average", "balanced", (F.col("average") - F.col("base")).alias("gain"), F.coalesce("won", F.lit(0)).alias("won"))


@query
def wl_ablation_components(spark, sf_dir):
    """Injection, auxiliary task and dynamic pivots switched on one after the other."""
    return accuracies(corpus(spark, sf_dir), pairs_of(spark, ABLATION_PAIRS), ["plain", "aux", "inject_static", "inject_aux_static", "full"])


@query
def wl_ablation_graph(spark, sf_dir):
    """Injection everywhere or at pivots, from the general graph or the learnt one."""
    pairs = pairs_of(spark, [("FAR", "N1"), ("N1", "N3")])
    return accuracies(corpus(spark, sf_dir), pairs, ["plain", "all_general", "all_learnt", "pivots_general", "inject"], open_sents=open_sentences(spark, sf_dir, pages=True))


@query
def wl_full_adversarial(spark, sf_dir):
    """The full method with the adversarial loss on top."""
    return accuracies(corpus(spark, sf_dir), pairs_of(spark, PIVOT_PAIRS), ["full", "full_adversarial"])


@query
def wl_renamed_grid(spark, sf_dir):
    """Near pairs after half of each domain's words were renamed: a shift that the raw near domains do not have."""
    docs = stage(rename_vocabulary(corpus(spark, sf_dir)), "renamed")
    # one method at a time: the features of twelve pairs and three methods at once were too much for one driver's memory
    plain, inject, full = (accuracies(docs, domain_pairs(spark, "near"), [m]) for m in ("plain", "inject", "full"))
    return plain.unionByName(inject).unionByName(full)


@query
def wl_quality_grid(spark, sf_dir):
    """The second label of the tables."""
    return accuracies(corpus(spark, sf_dir, "quality"), pairs_of(spark, PIVOT_PAIRS), ["plain", "full"])


@query
def wl_shift_matrix(spark, sf_dir):
    """Accuracy of the plain method on every ordered pair, and in-domain on each domain's own held-out part."""
    docs = corpus(spark, sf_dir)
    done = T.run(T.prepare(docs, domain_pairs(spark, "all"), CFG, graph=False), ["plain"], CFG)
    cross = M.accuracy(done.predictions(), ["src", "tgt"])
    own = done.scored.where("side = 'S' and split = 'dev'").withColumn("tgt", F.col("src")).dropDuplicates(["src", "doc_id"])
    return cross.unionByName(M.accuracy(own, ["src", "tgt"]))


@query
def wl_pivot_diff(spark, sf_dir):
    """Pivots that only the initial or only the learnt set holds."""
    data = T.prepare(corpus(spark, sf_dir), pairs_of(spark, PIVOT_PAIRS), CFG)
    done = T.run(data, ["inject"], CFG)
    last = done.pivots.agg(F.max("epoch").alias("e"))
    learnt = done.pivots.join(F.broadcast(last), F.col("epoch") == F.col("e"))
    return P.pivot_diff(done.pivots.where("epoch = 0"), learnt)


@query
def wl_pivot_quality(spark, sf_dir):
    """Polarity in the target and lean to the source, for initial and learnt pivots."""
    f = Frames(spark, sf_dir)
    data = T.prepare(f.docs, pairs_of(spark, PIVOT_PAIRS), CFG)
    done = T.run(data, ["inject"], CFG)
    q = lambda e: P.pivot_quality(done.pivots.where(f"epoch = {e}"), f.pol, f.counts).withColumn("epoch", F.lit(e))
    return q(0).unionByName(q(1))


@query
def wl_dev_curve(spark, sf_dir):
    """Source dev accuracy by epoch, by which the epoch is chosen."""
    done = T.run(T.prepare(corpus(spark, sf_dir), pairs_of(spark, PIVOT_PAIRS), CFG), ["inject", "full"], replace(CFG, epochs=3))
    return done.dev


@query
def wl_grid(spark, sf_dir):
    """Settings one at a time: weight decay, reversal strength, fact threshold, auxiliary weight, head interval and score step size."""
    tries = [("weight_decay", v) for v in (1e-4, 1e-2)] + [("gamma", v) for v in (0.15, 1.0)] + [("lam", v) for v in (0.1, 0.5)] + [("head_every", v) for v in (1, 5)] + [("tau", 0.45), ("alpha", 1 - 1e-4)]
    docs, pairs = corpus(spark, sf_dir), pairs_of(spark, [("N1", "N3")])
    data = {tau: T.prepare(docs, pairs, replace(CFG, tau=tau)) for tau in (CFG.tau, 0.45)}
    out = None
    for name, value in tries:
        cfg = replace(CFG, **{name: value})
        done = T.run(data[cfg.tau], ["adversarial" if name == "gamma" else "full"], cfg)
        row = M.accuracy(done.predictions(), ["method", "src", "tgt"]).withColumn("setting", F.lit(name)).withColumn("value", F.lit(float(value)))
        out = row if out is None else out.unionByName(row)
    return out


@query
def wl_lang_grid(spark, sf_dir):
    """Languages as domains: the far case twelve times over."""
    docs = corpus(spark, sf_dir).withColumn("domain", F.col("lang"))
    langs = ["en", "de", "fr", "es"]
    return accuracies(docs, pairs_of(spark, [(a, b) for a in langs for b in langs if a != b]), ["plain", "full"])


@query
def encoder_vectors(spark, sf_dir):
    """Text vectors of the visible-attention encoder over injected trees: every text of both domains of each of the twenty pairs."""
    f = GraphFrames(spark, sf_dir, [(s, t) for s in DOMAINS for t in DOMAINS if s != t])
    return E.encode(f.trees(), table(spark, sf_dir, "embeddings"))


@query
def kg_candidates_encoder(spark, sf_dir):
    """Candidate facts from the encoder's last layer."""
    f = GraphFrames(spark, sf_dir)
    return E.encoder_facts(f.sents, f.pivot_words, table(spark, sf_dir, "embeddings"))


@query
def wl_search(spark, sf_dir):
    """Settings compared on source dev texts only."""
    data = T.prepare(corpus(spark, sf_dir), pairs_of(spark, [("N1", "N3")]), CFG)
    return T.search(data, "full", {f"lam={v}": replace(CFG, lam=v) for v in (0.1, 0.3, 0.5)} | {f"weight_decay={v}": replace(CFG, weight_decay=v) for v in (1e-4, 3e-4)})
