"""Joint training over many domain pairs at once: features, heads, pseudo-labels, banks and pivots, epoch by epoch.

The corpus side stays distributed: injection, features and scoring are map-only over all texts, banks and pivots are the aggregates of
:mod:`lexbridge.operators.bank`. A head is fitted on all its texts, one task for each pair and method: the texts lie in files of the task, and
each step reads the next block of a bounded number of them.
"""

from __future__ import annotations

import pickle
import tempfile
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.functions import text as X
from lexbridge.operators import bank as B
from lexbridge.operators import cooccurrence as C
from lexbridge.operators import encoder as E
from lexbridge.operators import facts as G
from lexbridge.operators import inject as I
from lexbridge.operators import model as M
from lexbridge.operators import pivots as P
from lexbridge.sources.stage import stage


@dataclass(frozen=True)
class Method:
    """What a method switches on."""

    inject: bool = False
    aux: bool = False
    dynamic: bool = False
    adversarial: bool = False
    post: bool = False
    hier: bool = False
    scope: str = "pivots"
    graph: str = "learnt"


METHODS = {
    "plain": Method(),
    "hier": Method(hier=True, aux=True),
    "adversarial": Method(adversarial=True),
    "posttrain": Method(adversarial=True, post=True),
    "inject": Method(inject=True, dynamic=True),
    "full": Method(inject=True, aux=True, dynamic=True),
    "full_adversarial": Method(inject=True, aux=True, dynamic=True, adversarial=True),
    "aux": Method(aux=True),
    "inject_static": Method(inject=True),
    "inject_aux_static": Method(inject=True, aux=True),
    "all_general": Method(inject=True, dynamic=True, scope="all", graph="general"),
    "all_learnt": Method(inject=True, dynamic=True, scope="all"),
    "pivots_general": Method(inject=True, dynamic=True, graph="general"),
}


@dataclass
class Data:
    """The frames a run needs: texts of each pair with roles, pool, source polarity and the two graphs (src, tgt, pivot, w_a, ..)."""

    docs: DataFrame
    pairs: DataFrame
    inc: DataFrame
    pool: DataFrame
    pol: DataFrame
    learnt: DataFrame | None
    general: DataFrame | None
    texts: DataFrame
    prior: DataFrame


def prepare(docs: DataFrame, pairs: DataFrame, cfg: M.TrainConfig, min_df: int = 5, open_sents: DataFrame | None = None, graph: bool = True, transductive: bool = False) -> Data:
    """Builds a run's frames. Only source labels enter the pool's polarity and the banks; target labels are for the measures alone.

    Target texts that are tested stay out of the graph unless ``transductive``.
    """
    inc = stage(P.incidence(docs), "inc")
    counts = P.word_counts(inc)
    pool = stage(P.candidate_pool(counts, pairs, min_df), "pool")
    fit_counts = P.word_counts(inc.where("split = 'train'"))
    pol, prior = P.polarity(fit_counts, cfg.min_labelled), P.label_prior(docs.where("split = 'train'"))
    pol = stage(P.centred(pol, prior) if cfg.centred else pol, "pol")
    learnt = general = None
    if graph:
        targets = pairs.select(F.col("tgt").alias("domain")).distinct()
        corpus = docs.join(F.broadcast(targets), "domain", "left_semi")
        corpus = corpus if transductive else corpus.where("label is null")
        words = pool.select(F.col("tgt").alias("domain"), "word").distinct()
        merged = C.cooccurrence_graph(X.chunked_words(corpus, "domain"), words, cfg.tau, G.stop_words(counts))
        learnt = stage(G.for_pairs(merged, pool), "graph")
    if open_sents is not None:
        vocabulary = inc.select("word").distinct()
        general = stage(G.generic_facts(G.one_hop(G.generic_graph(open_sents), vocabulary), pool), "general")
    both = pairs.select("src", "tgt", F.explode(F.array(F.struct(F.lit("S").alias("side"), F.col("src").alias("domain")), F.struct(F.lit("T").alias("side"), F.col("tgt").alias("domain")))).alias("x"))
    both = both.select("src", "tgt", "x.side", "x.domain")
    texts = docs.select("doc_id", "domain", "label", "split", X.word_list(F.col("text")).alias("words")).join(F.broadcast(both), "domain")
    return Data(docs, pairs, inc, pool, pol, learnt, general, texts, prior if cfg.centred else prior.withColumn("prior", F.lit(0.0)))


_FEATURES = "method string, src string, tgt string, side string, doc_id long, label int, split string, ix array<int>, v array<float>, mix array<int>, mv array<float>, piv array<string>"


def _features(trees: DataFrame, methods: list[str], pivots: DataFrame, cfg: M.TrainConfig) -> DataFrame:
    """Bags of each text, as it is and with its pivots hidden, once for each method that shares the trees."""
    named = pivots.groupBy("src", "tgt").agg(F.collect_list("word").alias("pv"))
    rows = trees.join(F.broadcast(named), ["src", "tgt"], "left").select("src", "tgt", "side", "doc_id", "label", "split", "tokens", F.coalesce("pv", F.expr("cast(array() as array<string>)")).alias("pv"))

    hides = any(METHODS[m].aux or METHODS[m].hier for m in methods)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in _slices(whole):
                sets, of = {}, []
                for r, key in enumerate(zip(batch.column("src").to_pylist(), batch.column("tgt").to_pylist(), strict=True)):
                    if key not in sets:
                        sets[key] = (len(sets), frozenset(batch.column("pv")[r].as_py()))
                    of.append(sets[key][0])
                found = list(E.bags(batch.column("tokens"), cfg.dims, cfg.branch_gamma, [own for _, own in sets.values()] if hides else None, np.array(of, np.int64)))
                cols = [pa.array([f[k] for f in found], t) for k, t in enumerate((pa.list_(pa.int32()), pa.list_(pa.float32()), pa.list_(pa.int32()), pa.list_(pa.float32()), pa.list_(pa.string())))]
                own = [batch.column(k) for k in ("src", "tgt", "side", "doc_id", "label", "split")]
                for m in methods:
                    yield pa.record_batch([pa.array([m] * batch.num_rows, pa.string()), *own, *cols], names=[c.split()[0] for c in _FEATURES.split(", ")])

    return rows.mapInArrow(run, _FEATURES)


def _slices(batch: pa.RecordBatch, most: int = 300_000) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of about ``most`` tokens each."""
    ends = np.cumsum(batch.column("tokens").value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield batch.slice(at, to - at)
        at = to


def _dense(ix, v, dims: int) -> np.ndarray:
    """In the precision of the nets, so that no step of a fit converts the block again."""
    x = np.zeros((len(ix), dims))
    for r, (i, w) in enumerate(zip(ix, v, strict=True)):
        x[r, np.asarray(i, dtype=np.int64)] = w
    return x


def _fit_rows(features: DataFrame, cfg: M.TrainConfig) -> DataFrame:
    """Every text that a head is fitted on, in its role and with its place in a seeded order. Target labels are dropped here, and what a method's losses do not read."""
    role = F.when((F.col("side") == "S") & (F.col("split") == "train"), "lab").when(F.col("split") == "unlabelled", F.when(F.col("side") == "S", "unl_s").otherwise("unl_t"))
    of = lambda test: F.col("method").isin([m for m, s in METHODS.items() if test(s)])
    lab = F.col("role") == "lab"
    plain, hidden, named = lab | of(lambda s: s.adversarial or s.post), of(lambda s: s.aux) | (of(lambda s: s.hier) & lab), of(lambda s: s.aux)
    kept = [F.when(test, F.col(c)).alias(c) for test, cols in ((lab, ["label"]), (plain, ["ix", "v"]), (hidden, ["mix", "mv"]), (named, ["piv"])) for c in cols]
    order = F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(f"|{cfg.seed}"))).alias("at")
    return features.withColumn("role", role).where("role is not null").select("method", "src", "tgt", "role", order, "doc_id", *kept)


class _Ragged:
    """Lists of numbers in a file of the task's own, read back by their rows."""

    def __init__(self, *types):
        self.parts = [(np.dtype(t), tempfile.TemporaryFile()) for t in types]
        self.sizes, self.ends = [], np.zeros(1, np.int64)

    def add(self, sizes: np.ndarray, *values: np.ndarray) -> None:
        self.sizes.append(sizes)
        for (dtype, file), v in zip(self.parts, values, strict=True):
            file.write(np.ascontiguousarray(v, dtype).tobytes())

    def seal(self) -> None:
        self.ends = np.concatenate(([0], np.cumsum(np.concatenate([np.zeros(0, np.int64), *self.sizes]))))
        self.sizes = []

    def read(self, lo: int, hi: int) -> tuple[np.ndarray, ...]:
        """(row of each number from ``lo`` on, the numbers of each kind)."""
        out = [np.repeat(np.arange(hi - lo), np.diff(self.ends[lo : hi + 1]))]
        for dtype, file in self.parts:
            file.seek(int(self.ends[lo]) * dtype.itemsize)
            out.append(np.frombuffer(file.read(int(self.ends[hi] - self.ends[lo]) * dtype.itemsize), dtype))
        return tuple(out)

    def dense(self, lo: int, hi: int, dims: int) -> np.ndarray:
        row, ix, v = self.read(lo, hi)
        x = np.zeros((hi - lo, dims))
        x[row, ix] = v
        return x

    def close(self) -> None:
        for _, file in self.parts:
            file.close()


class _Texts:
    """The texts of one role of a fit, in their order."""

    def __init__(self, size: int):
        self.size, self.n, self.labels = size, 0, []
        self.bags, self.masked, self.pivots = _Ragged(np.int32, np.float32), _Ragged(np.int32, np.float32), _Ragged(np.int32)

    def add(self, batch: pa.RecordBatch, names: pa.Array) -> None:
        self.n += batch.num_rows
        self.labels.append(batch.column("label").fill_null(0).to_numpy(zero_copy_only=False).astype(np.int8))
        for held, cols in ((self.bags, ("ix", "v")), (self.masked, ("mix", "mv"))):
            held.add(_sizes(batch.column(cols[0])), *(batch.column(c).flatten().to_numpy(zero_copy_only=False) for c in cols))
        self.pivots.add(_sizes(batch.column("piv")), pc.index_in(batch.column("piv").flatten(), value_set=names).fill_null(-1).to_numpy(zero_copy_only=False))

    def seal(self) -> None:
        self.labels = np.concatenate([np.zeros(0, np.int8), *self.labels])
        for held in (self.bags, self.masked, self.pivots):
            held.seal()

    def close(self) -> None:
        for held in (self.bags, self.masked, self.pivots):
            held.close()

    @property
    def blocks(self) -> int:
        return max(1, -(-self.n // self.size))

    def span(self, step: int) -> tuple[int, int]:
        """The rows of a step: even blocks, one after the other and over again."""
        i = step % self.blocks
        return self.n * i // self.blocks, self.n * (i + 1) // self.blocks


def _sizes(col: pa.ListArray) -> np.ndarray:
    return col.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)


def _fit_group(key: tuple, roles: dict[str, _Texts], names: list[str], positive: np.ndarray, cfg: M.TrainConfig) -> tuple:
    """One head, fitted on all the texts of its pair: (method, src, tgt, n_fit, loss, net)."""
    spec = METHODS[key[0]]
    lab, s, t = (roles[r] for r in ("lab", "unl_s", "unl_t"))
    other = spec.adversarial or spec.post  # only the blocks that the method's losses read

    def hidden(u: _Texts, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        row, ix = u.pivots.read(lo, hi)
        size = np.diff(u.pivots.ends[lo : hi + 1])
        k, sg, known = np.zeros((hi - lo, max(len(names), 1))), np.zeros((hi - lo, 2)), ix >= 0
        row, ix = row[known], ix[known]
        k[row, ix] = 1 / size[row]
        sg[row, np.where(positive[ix], 0, 1)] = 1
        return u.masked.dense(lo, hi, cfg.dims)[size > 0], k[size > 0], sg[size > 0]

    def block(step: int) -> M.Batch:
        lo, hi = lab.span(step)
        x = lab.bags.dense(lo, hi, cfg.dims)
        xs, xt = (u.bags.dense(*u.span(step), cfg.dims) if other else x[:0] for u in (s, t))
        parts = [hidden(u, *u.span(step)) for u in (lab, s, t)] if spec.aux else [(x[:0], np.zeros((0, max(len(names), 1))), np.zeros((0, 2)))]
        m, k, sg = (np.concatenate(p) for p in zip(*parts, strict=True))
        m_lab = lab.masked.dense(lo, hi, cfg.dims) if spec.hier else None
        return M.Batch(x, lab.labels[lo:hi].astype(float), np.concatenate((x, xs)) if other else xs, xt, m, k, m_lab, sg)

    read = [lab, s, t] if other or spec.aux else [lab]
    several = max(u.blocks for u in read)
    net = M.new_net(cfg, len(names), spec.hier)
    if spec.post:
        net = M.post_train(net, lambda i: t.bags.dense(*t.span(i), cfg.dims), t.blocks, cfg)
    net = M.fit(net, block if several > 1 else block(0), cfg, spec.adversarial, spec.aux, max(cfg.steps, several))
    used = {n: net.p[n].astype(np.float32) for n in ("E", "W", "b", "u", "N") if n in net.p}
    return (*key, lab.n, float(net.history[-1]) if net.history else 0.0, pickle.dumps(used))


def fit_heads(features: DataFrame, signs: dict, cfg: M.TrainConfig, groups: int) -> DataFrame:
    """(method, src, tgt, n_fit, loss, net) of each pair and method; ``groups`` tells about how many there are."""
    schema = "method string, src string, tgt string, n_fit long, loss double, net binary"
    key = ["method", "src", "tgt"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, roles, names, positive = None, {}, [], np.zeros(0, bool)

        def done() -> Iterator[pa.RecordBatch]:
            if now is not None:
                for u in roles.values():
                    u.seal()
                row = _fit_group(now, roles, names, positive, cfg)
                for u in roles.values():
                    u.close()
                yield pa.record_batch([pa.array([v], t) for v, t in zip(row, (pa.string(), pa.string(), pa.string(), pa.int64(), pa.float64(), pa.binary()), strict=True)], names=[c.split()[0] for c in schema.split(", ")])

        for batch in batches:
            owner = list(zip(*(batch.column(c).to_pylist() for c in (*key, "role")), strict=True))
            cuts = [i for i in range(len(owner)) if not i or owner[i] != owner[i - 1]]
            for lo, hi in zip(cuts, [*cuts[1:], len(owner)], strict=True):
                if owner[lo][:3] != now:
                    yield from done()
                    now = owner[lo][:3]
                    own = signs.get(now[1:], {})
                    names = sorted(own)
                    positive = np.array([own[w] > 0 for w in names], bool)
                    roles = {r: _Texts(cfg.labelled_rows if r == "lab" else cfg.unlabelled_rows) for r in ("lab", "unl_s", "unl_t")}
                roles[owner[lo][3]].add(batch.slice(lo, hi - lo), pa.array(names, pa.string()))
        yield from done()

    # more parts than groups, so that few groups share a task
    return _fit_rows(features, cfg).repartition(min(4 * groups, 1000), *key).sortWithinPartitions(*key, "role", "at", "doc_id").mapInArrow(run, schema)


def _score(features: DataFrame, nets: DataFrame, cfg: M.TrainConfig) -> DataFrame:
    """(method, src, tgt, side, doc_id, label, split, p_pos, pred). The nets are a few hundred kilobytes for each pair and method."""
    held = {(r.method, r.src, r.tgt): M.Net(pickle.loads(r.net), METHODS[r.method].hier) for r in nets.collect()}
    shared = features.sparkSession.sparkContext.broadcast(held)
    schema = "method string, src string, tgt string, side string, doc_id long, label int, split string, p_pos double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                pdf = whole.slice(at, 500).to_pandas()
                p = np.full(len(pdf), 0.5)
                for key, own in pdf.groupby(["method", "src", "tgt"], sort=False):
                    net = shared.value.get(key)
                    if net is not None:
                        rows = own.index.to_numpy()
                        masked = _dense(own.mix, own.mv, cfg.dims) if net.hier else None
                        p[rows] = net.p_pos(_dense(own.ix, own.v, cfg.dims), masked)
                pdf["p_pos"] = p
                yield pa.RecordBatch.from_pandas(pdf[[c.split()[0] for c in schema.split(", ")]], schema=pa.schema([("method", pa.string()), ("src", pa.string()), ("tgt", pa.string()), ("side", pa.string()), ("doc_id", pa.int64()), ("label", pa.int32()), ("split", pa.string()), ("p_pos", pa.float64())]), preserve_index=False)

    return features.mapInArrow(run, schema).withColumn("pred", F.when(F.col("p_pos") > 0.5, 1).otherwise(-1))


@dataclass
class Run:
    """A finished run: all epochs' predictions, pivots of each epoch, and the dev accuracies."""

    scored: DataFrame
    pivots: DataFrame
    dev: DataFrame
    banks: DataFrame | None

    def predictions(self) -> DataFrame:
        """Target texts with their method's prediction at its pair's best dev epoch."""
        best = self.dev.groupBy("method", "src", "tgt").agg(F.max_by("epoch", F.struct("accuracy", -F.col("epoch"))).alias("epoch"))
        return self.scored.where("side = 'T'").join(F.broadcast(best), ["method", "src", "tgt", "epoch"])

    def learnt_pivots(self) -> DataFrame:
        best = self.dev.groupBy("method", "src", "tgt").agg(F.max_by("epoch", F.struct("accuracy", -F.col("epoch"))).alias("epoch"))
        return self.pivots.join(F.broadcast(best), ["method", "src", "tgt", "epoch"])


def run(data: Data, methods: list[str], cfg: M.TrainConfig) -> Run:
    """Trains the named methods on every pair; static methods stop after the first epoch."""
    first = P.initial_pivots(data.pool, data.pol, cfg.k)
    pivots = {m: first for m in methods}
    banks = {m: B.init_banks(data.pool, data.pol) for m in methods if METHODS[m].dynamic}
    scored, kept, devs = [], [], []
    n_pairs = data.pairs.count()
    for epoch in range(cfg.epochs):
        active = [m for m in methods if epoch == 0 or METHODS[m].dynamic]
        if not active:
            break
        views: dict[tuple, list[str]] = {}
        for m in active:
            s = METHODS[m]
            views.setdefault((s.inject, s.scope, s.graph, m if epoch and s.dynamic else ""), []).append(m)
        features = None
        for (inj, scope, graph, _), group in views.items():
            now = pivots[group[0]]
            facts = I.active_facts(data.learnt if graph == "learnt" else data.general, now if scope == "pivots" else None, cfg.per_pivot) if inj else None
            if inj:
                trees = I.inject(data.texts, facts, "map" if scope == "pivots" else "join") if scope == "pivots" else _inject_all(data.texts, facts)
            else:
                trees = data.texts.withColumn("tokens", F.transform("words", lambda w, i: F.struct(w.alias("tok"), i.alias("pos"), F.lit(0).alias("branch"), i.alias("trunk"))))
            part = _features(trees, group, now, cfg)
            features = part if features is None else features.unionByName(part)
        features = stage(features, "features")
        signs = _signs(first, data.pol)
        nets = stage(fit_heads(features, signs, cfg, len(active) * n_pairs), "nets")
        out = stage(_score(features, nets, cfg).withColumn("epoch", F.lit(epoch)), "scored")
        scored.append(out)
        dev = out.where("side = 'S' and split = 'dev'").groupBy("method", "src", "tgt", "epoch").agg((100 * F.avg((F.col("pred") == F.col("label")).cast("int"))).alias("accuracy"))
        every = out.select("method", "src", "tgt", "epoch").distinct().join(dev, ["method", "src", "tgt", "epoch"], "left")
        devs.append(stage(every.withColumn("accuracy", F.coalesce("accuracy", F.lit(0.0))), "dev"))
        for m in active:
            kept.append(pivots[m].select(F.lit(m).alias("method"), "src", "tgt", F.lit(epoch).alias("epoch"), "rank", "word", "score"))
            if METHODS[m].dynamic and epoch + 1 < cfg.epochs:
                banks[m] = stage(_learn(data, out.where(F.col("method") == m), banks[m], cfg, epoch), f"bank-{epoch}")
                pivots[m] = stage(B.refresh(banks[m], data.pool, cfg.k), f"pivots-{epoch}")
    union = lambda frames: frames[0] if len(frames) == 1 else frames[0].unionByName(union(frames[1:]))
    learnt = union([b.withColumn("method", F.lit(m)) for m, b in banks.items()]) if banks else None
    return Run(union(scored), union(kept), union(devs), learnt)


def _inject_all(texts: DataFrame, facts: DataFrame) -> DataFrame:
    """Injection at every word: too many facts for a map in every task, so by joins; a text keeps its side."""
    trees = I.inject(texts.select("src", "tgt", "doc_id", "words").distinct(), facts, "join").select("src", "tgt", "doc_id", "tokens")
    return texts.join(trees, ["src", "tgt", "doc_id"])


def _signs(pivots: DataFrame, pol: DataFrame) -> dict:
    """The pivots of each pair with their source sign: a bounded list for each pair."""
    rows = pivots.join(pol.select(F.col("domain").alias("src"), "word", "p"), ["src", "word"], "left").select("src", "tgt", "word", F.coalesce("p", F.lit(0.0)).alias("p")).collect()
    out: dict = {}
    for r in rows:
        out.setdefault((r.src, r.tgt), {})[r.word] = r.p
    return out


def _learn(data: Data, scored: DataFrame, bank: DataFrame, cfg: M.TrainConfig, epoch: int) -> DataFrame:
    """Moves the banks by true source labels and confident pseudo-labels, in a seeded order of steps."""
    true_s = scored.where("side = 'S' and split = 'train'").select("src", "tgt", "doc_id", "label")
    free = scored.where("split = 'unlabelled'").drop("label")
    pseudo = B.pseudo_label(free, cfg.theta)
    ev = B.schedule(B.evidence(true_s, pseudo.where("side = 'S'"), pseudo.where("side = 'T'")), ("src", "tgt", "side"), cfg.seed + epoch)
    ev = ev.join(F.broadcast(data.prior.withColumnRenamed("domain", "src")), "src").withColumn("label", F.col("label") - F.col("prior")).drop("prior")
    return B.td_exact(bank.select(*B.KEY, "p"), B.updates(ev, data.inc, data.pool), cfg.alpha).drop("n_updates")


def search(data: Data, method: str, configs: dict[str, M.TrainConfig]) -> DataFrame:
    """(setting, src, tgt, epoch, accuracy): source dev accuracy of each setting, by which one is to be chosen; target labels play no part.

    Settings that change the graph or the pool need their own ``data``.
    """
    out = None
    for name, cfg in configs.items():
        best = run(data, [method], cfg).dev.groupBy("src", "tgt").agg(F.max_by(F.struct("epoch", "accuracy"), F.struct("accuracy", -F.col("epoch"))).alias("b"))
        row = best.select(F.lit(name).alias("setting"), "src", "tgt", "b.*")
        out = row if out is None else out.unionByName(row)
    return out
