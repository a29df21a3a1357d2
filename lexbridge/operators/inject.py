"""Knowledge injection: facts of the current pivots hang on a text as branches, then the tree is laid out as one sequence.

A token of the result is (tok, pos, branch, trunk): the trunk has branch 0 and its own place as position; a branch word's position is its pivot's
plus its distance along the branch, so it may share an index with trunk words that follow. Visibility stays implicit in the branch ids
and is spelled out only where an encoder needs it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Texts that are laid out at once.
SLICE = 512
TOKEN = "struct<tok:string,pos:int,branch:int,trunk:int>"


def active_facts(graph: DataFrame, pivots: DataFrame | None, per_pivot: int | None = 2) -> DataFrame:
    """(src, tgt, pivot, b, w_a, w_b, w_c, slot): the facts to hang on each current pivot, best first; all words if ``pivots`` is None."""
    g = graph if pivots is None else graph.join(F.broadcast(pivots.select("src", "tgt", F.col("word").alias("pivot"))), ["src", "tgt", "pivot"], "left_semi")
    rank = F.row_number().over(W.partitionBy("src", "tgt", "pivot").orderBy(F.desc(F.round("conf", 6)), F.desc("support"), "w_a", "w_b", "w_c", "slot"))
    out = g.withColumn("b", rank)
    out = out if per_pivot is None else out.where(F.col("b") <= per_pivot)
    return out.select("src", "tgt", "pivot", "b", "w_a", "w_b", "w_c", "slot")


class _Hung:
    """What one pair's pivots carry, in runs: words left of the pivot, and words right of it, each with its distance and branch number."""

    def __init__(self, facts: pa.Table):
        named = facts.column("pivot").combine_chunks().dictionary_encode()
        self.pivots = named.dictionary.cast(pa.string())
        at, b, slot = (x.to_numpy(zero_copy_only=False).astype(np.int64) for x in (named.indices, facts.column("b"), facts.column("slot")))
        n, every = len(self.pivots), np.arange(len(b))
        # (fact, which of its words, distance): words before the pivot and after it, a fact's own in sentence order
        left = [(every[slot > 0], 0, slot[slot > 0]), (every[slot == 2], 1, 1)]
        right = [(every[slot == 0], 1, 1), (every[slot < 2], 2, 2 - slot[slot < 2])]
        sizes, starts, picked, far, branch, done = [], [], [], [], [], 0
        for side in (left, right):
            f = np.concatenate([x[0] for x in side])
            k = np.concatenate([np.full(len(x[0]), x[1]) for x in side])
            d = np.concatenate([np.broadcast_to(x[2], len(x[0])) for x in side])
            order = np.lexsort((k, b[f], at[f]))
            f, k, d = f[order], k[order], d[order]
            picked.append(k * len(b) + f)
            far.append(d)
            branch.append(b[f])
            # one more run, of nothing, at the end of each side for words that are no pivots
            size = np.bincount(at[f], minlength=n)
            sizes.append(np.append(size, 0))
            starts.append(np.append(done + np.cumsum(size) - size, 0))
            done += len(f)
        self.size, self.start = sizes, starts
        self.far, self.branch = np.concatenate(far).astype(np.int64), np.concatenate(branch)
        words = pa.concat_arrays([facts.column(w).combine_chunks().cast(pa.string()) for w in ("w_a", "w_b", "w_c")])
        self.words = words.take(pa.array(np.concatenate(picked)))

    def grow(self, words: pa.ListArray, width: int) -> pa.ListArray:
        """The flattened trees of texts given as their words, all words of a slice at once."""
        lengths = words.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = words.flatten().cast(pa.string())
        ends, n = np.cumsum(lengths), len(flat)
        k = np.arange(n) - np.repeat(ends - lengths, lengths)
        at = pc.index_in(flat, value_set=self.pivots).fill_null(len(self.pivots)).to_numpy(zero_copy_only=False).astype(np.int64)
        left, right = self.size[0][at], self.size[1][at]
        stop = np.cumsum(left + 1 + right)
        first = stop - (left + 1 + right)
        total = int(stop[-1]) if n else 0
        source, pos, branch, trunk = (np.zeros(total, dtype=np.int64) for _ in range(4))
        own = first + left
        source[own], pos[own], trunk[own] = np.arange(n), k, k
        hits = np.flatnonzero(at < len(self.pivots))
        for side, base in ((0, first), (1, own + 1)):
            count = self.size[side][at[hits]]
            host = np.repeat(hits, count)
            step = np.arange(len(host)) - np.repeat(np.cumsum(count) - count, count)
            f, to = self.start[side][at[host]] + step, base[host] + step
            source[to], pos[to], branch[to], trunk[to] = n + f, k[host] + self.far[f], k[host] * width + self.branch[f], k[host]
        tok = pa.concat_arrays([flat, self.words]).take(pa.array(source))
        numbers = [pa.array(x.astype(np.int32)) for x in (pos, branch, trunk)]
        tree = pa.StructArray.from_arrays([tok, *numbers], names=["tok", "pos", "branch", "trunk"])
        offsets = np.append(0, np.append(0, stop)[ends]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(offsets), tree, mask=words.is_null())


class _Facts:
    """The facts of each pair; what they hang is worked out once in each process."""

    def __init__(self, rows: pa.Table):
        self.by = {pair: _part(rows, pair) for pair in sorted(set(zip(rows.column("src").to_pylist(), rows.column("tgt").to_pylist(), strict=True)))}
        self.bare = rows.slice(0, 0)
        self.hung: dict[tuple, _Hung] = {}

    def of(self, pair: tuple) -> _Hung:
        if pair not in self.hung:
            self.hung[pair] = _Hung(self.by.get(pair, self.bare))
        return self.hung[pair]


def _part(rows: pa.Table, pair: tuple) -> pa.Table:
    return rows.filter(pc.and_(pc.equal(rows.column("src"), pair[0]), pc.equal(rows.column("tgt"), pair[1]))).drop_columns(["src", "tgt"])


def _inject_by_map(docs: DataFrame, active: DataFrame, width: int) -> DataFrame:
    """The facts go to every task; a text never leaves its own."""
    shared = docs.sparkSession.sparkContext.broadcast(_Facts(active.select("src", "tgt", "pivot", "b", "w_a", "w_b", "w_c", "slot").toArrow()))
    schema = T.StructType([*docs.schema.fields, T.StructField("tokens", T._parse_datatype_string(f"array<{TOKEN}>"))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        facts = shared.value
        for batch in batches:
            for start in range(0, batch.num_rows, SLICE):
                part = batch.slice(start, SLICE)
                pairs = list(zip(part.column("src").to_pylist(), part.column("tgt").to_pylist(), strict=True))
                for pair in dict.fromkeys(pairs):
                    rows = part.filter(pa.array([p == pair for p in pairs]))
                    tokens = facts.of(pair).grow(rows.column("words"), width)
                    yield pa.RecordBatch.from_arrays([*rows.columns, tokens], names=[*rows.schema.names, "tokens"])

    return docs.mapInArrow(run, schema)


def _before(fs: Column, k: Column, width: Column) -> Column:
    """Branch words left of the pivot at k, branch by branch; the nearest word is one step away."""
    one = lambda f: F.when(f.slot == 2, F.array(_tok(f.w_a, k + 2, k * width + f.b, k), _tok(f.w_b, k + 1, k * width + f.b, k))).when(f.slot == 1, F.array(_tok(f.w_a, k + 1, k * width + f.b, k))).otherwise(_none())
    return F.flatten(F.transform(fs, one))


def _after(fs: Column, k: Column, width: Column) -> Column:
    one = lambda f: F.when(f.slot == 0, F.array(_tok(f.w_b, k + 1, k * width + f.b, k), _tok(f.w_c, k + 2, k * width + f.b, k))).when(f.slot == 1, F.array(_tok(f.w_c, k + 1, k * width + f.b, k))).otherwise(_none())
    return F.flatten(F.transform(fs, one))


def _none() -> Column:
    return F.expr(f"cast(array() as array<{TOKEN}>)")


def _tok(tok: Column, pos: Column, branch: Column, trunk: Column) -> Column:
    return F.struct(tok.alias("tok"), pos.cast("int").alias("pos"), branch.cast("int").alias("branch"), trunk.cast("int").alias("trunk"))


def inject(docs: DataFrame, active: DataFrame, strategy: str = "map", width: int = 64) -> DataFrame:
    """``docs`` (src, tgt, doc_id, words, ..) with ``tokens``, the flattened tree.

    Strategy "map" sends the facts of each pair to every task, which is right for a bounded number of pivots or the few best facts of each word of a vocabulary; "join"
    explodes and regroups, for facts of any number. Both give the same tokens. A text without pivots comes back as its own trunk.
    ``width`` bounds the branches of one pivot, and makes branch ids unique in a text.
    """
    if strategy == "map":
        return _inject_by_map(docs, active, width)
    key = ["src", "tgt", "doc_id"]
    trunk = docs.select(*key, F.posexplode_outer("words").alias("k", "tok"))
    per = active.groupBy("src", "tgt", F.col("pivot").alias("tok")).agg(F.array_sort(F.collect_list(F.struct("b", "w_a", "w_b", "w_c", "slot"))).alias("fs"))
    none = F.expr("cast(array() as array<struct<b:int,w_a:string,w_b:string,w_c:string,slot:int>>)")
    grown = trunk.join(per, ["src", "tgt", "tok"], "left").withColumn("fs", F.coalesce("fs", none))
    k, w = F.col("k"), F.lit(width)
    parts = grown.select(*key, "k", F.when(k.isNull(), _none()).otherwise(F.concat(_before(F.col("fs"), k, w), F.array(_tok(F.col("tok"), k, F.lit(0), k)), _after(F.col("fs"), k, w))).alias("part"))
    whole = parts.groupBy(*key).agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("k", "part"))), lambda s: s.part)).alias("tokens"))
    return docs.join(whole, key)


def strip(tokens: Column) -> Column:
    """The trunk's words: what was there before injection."""
    return F.transform(F.filter(tokens, lambda t: t.branch == 0), lambda t: t.tok)


def truncate(tokens: Column, most: int) -> Column:
    """At most ``most`` tokens: branches go first, from the end, then the trunk's end."""
    trunk = F.slice(F.filter(tokens, lambda t: t.branch == 0), 1, most)
    room = F.lit(most) - F.size(trunk)
    kept = F.slice(F.filter(tokens, lambda t: t.branch > 0), F.lit(1), F.greatest(room, F.lit(0)))
    return F.filter(tokens, lambda t: F.when(t.branch == 0, t.trunk < most).otherwise((F.size(kept) > 0) & (F.array_contains(kept, t))))


def visible(tokens: Column) -> Column:
    """The visibility matrix of a short sequence: trunk sees trunk, a branch sees itself and its pivot."""
    see = lambda a, b: ((a.branch == 0) & (b.branch == 0)) | (a.branch == b.branch) | ((a.branch == 0) & (b.trunk == a.trunk)) | ((b.branch == 0) & (a.trunk == b.trunk))
    return F.transform(tokens, lambda a: F.transform(tokens, lambda b: see(a, b)))


def visible_mask(branch: np.ndarray, trunk: np.ndarray) -> np.ndarray:
    """The same for the encoder."""
    on_trunk = branch == 0
    same = branch[:, None] == branch[None, :]
    hangs = (on_trunk[:, None] | on_trunk[None, :]) & (trunk[:, None] == trunk[None, :])
    return same | hangs


def injection_stats(trees: DataFrame, vocabulary_s: DataFrame) -> DataFrame:
    """(src, tgt, texts, branch_words, new_words): words hung on texts, and those of them that the source never uses. ``vocabulary_s``: (src, word).

    Hung words are counted before they meet the vocabulary, so what is shuffled follows the facts and not the texts.
    """
    texts = trees.groupBy("src", "tgt").agg(F.count_distinct("doc_id").alias("texts"))
    hung = trees.select("src", "tgt", F.explode(F.filter("tokens", lambda t: t.branch > 0)).alias("t")).groupBy("src", "tgt", F.col("t.tok").alias("word")).agg(F.count("*").alias("n"))
    known = hung.join(vocabulary_s.withColumn("k", F.lit(1)), ["src", "word"], "left").groupBy("src", "tgt").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("k").isNull(), F.col("n"))).alias("new"))
    none = F.lit(0).cast("long")
    return texts.join(known, ["src", "tgt"], "left").select("src", "tgt", "texts", F.coalesce("n", none).alias("branch_words"), F.coalesce("new", none).alias("new_words"))
