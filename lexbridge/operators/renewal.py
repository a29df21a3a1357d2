"""Pivots renewed every few steps, without a row for each update.

The texts of a block stand together with the numbers of their words, so a block's affine map of each word is made where they stand. The maps go
packed to buckets of words, which carry the banks from block to block and name each block's best words of the bucket.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.functions.text import word_list
from lexbridge.sources.stage import stage

#: Words of a pair that are scored at once.
PER_BUCKET = 4096
_MAPS = "pair int, bucket int, side int, block long, words binary, n binary, s binary"
_BEST = "src string, tgt string, block long, word string, df long, score double"


class _Pool:
    """The pool's words in order, and for each pair its own words, their texts and what the two banks start from."""

    def __init__(self, rows: pa.Table):
        src, tgt, word = (rows.column(k).to_pylist() for k in ("src", "tgt", "word"))
        values = sorted(set(word))
        self.words = pa.array(values, pa.string())
        number = {w: i for i, w in enumerate(values)}
        of = np.array([number[w] for w in word], np.int64)
        self.pairs = sorted(set(zip(src, tgt, strict=True)))
        pair_of = {p: i for i, p in enumerate(self.pairs)}
        pair = np.array([pair_of[p] for p in zip(src, tgt, strict=True)], np.int64)
        df = rows.column("df").to_numpy().astype(np.int64)
        start = np.stack([rows.column(k).to_numpy() for k in ("p_s", "p_t")])
        self.own, self.df, self.start, self.at = [], [], [], []
        for i in range(len(self.pairs)):
            here = np.flatnonzero(pair == i)
            here = here[np.argsort(of[here])]
            self.own.append(of[here])
            self.df.append(df[here])
            self.start.append(start[:, here])
            at = np.full(len(values), -1, np.int32)
            at[of[here]] = np.arange(len(here))
            self.at.append(at)


def _numbered(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("words")
            ids = pc.index_in(lists.flatten(), value_set=shared.value.words).fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int32)
            cuts = np.concatenate(([0], np.cumsum(lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))))
            packed = [(own[own >= 0]).tobytes() for own in (ids[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True))]
            yield pa.record_batch([batch.column("doc_id"), pa.array(packed, pa.binary())], names=["doc_id", "ids"])

    return run


def _folded(shared, alpha: float):
    """The affine map of each word in each block, from rows in order of their block, step and text."""

    def told(key: tuple, texts: list) -> Iterator[pa.RecordBatch]:
        pool, (src, tgt, side, block) = shared.value, key
        pair = pool.pairs.index((src, tgt)) if (src, tgt) in pool.pairs else None
        if pair is None:
            return
        ids = [np.frombuffer(raw, np.int32) for raw, _ in texts]
        label = np.repeat([float(y) for _, y in texts], [len(x) for x in ids])
        word = pool.at[pair][np.concatenate(ids)]
        label, word = label[word >= 0], word[word >= 0]
        order = np.argsort(word, kind="stable")
        label, word = label[order], word[order]
        starts = np.flatnonzero(np.diff(word, prepend=-1))
        if not len(starts):
            return
        n = np.diff(np.append(starts, len(word)))
        later = np.repeat(starts + n - 1, n) - np.arange(len(word))
        s = np.add.reduceat((1 - alpha) * label * alpha ** later.astype(float), starts)
        word = word[starts]
        cuts = np.searchsorted(word, np.arange(0, word[-1] + PER_BUCKET + 1, PER_BUCKET))
        for b in np.flatnonzero(np.diff(cuts)).tolist():
            own = slice(cuts[b], cuts[b + 1])
            row = (pair, b, 0 if side == "S" else 1, block, (word[own] - b * PER_BUCKET).astype(np.uint16).tobytes(), n[own].astype(np.uint32).tobytes(), s[own].tobytes())
            yield pa.record_batch([pa.array([x], t) for x, t in zip(row, (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary()), strict=True)], names=[c.split()[0] for c in _MAPS.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, texts = None, []
        for batch in batches:
            for *key, raw, y in zip(*(batch.column(k).to_pylist() for k in ("src", "tgt", "side", "block", "ids", "label")), strict=True):
                if key != now:
                    if texts:
                        yield from told(tuple(now), texts)
                    now, texts = key, []
                texts.append((raw, y))
        if texts:
            yield from told(tuple(now), texts)

    return run


def _best(shared, tops: dict, alpha: float, k: int):
    """What a bucket's words are worth after each block: those that may be among the pair's ``k`` best."""

    def told(pair: int, bucket: int, maps: dict) -> Iterator[pa.RecordBatch]:
        pool, (src, tgt) = shared.value, shared.value.pairs[pair]
        own = slice(bucket * PER_BUCKET, (bucket + 1) * PER_BUCKET)
        word, df, start = pool.own[pair][own], pool.df[pair][own], pool.start[pair][:, own]
        rank = np.empty(len(word), np.int64)
        rank[np.lexsort((word, -df))] = np.arange(len(word))
        n, s = np.zeros(start.shape), np.zeros(start.shape)
        for block in range(tops[pair] + 1):
            for side in (0, 1):
                if (side, block) in maps:
                    at, more, add = maps.pop((side, block))
                    s[side, at] = alpha**more * s[side, at] + add
                    n[side, at] += more
            score = np.abs((alpha**n * start + s).sum(axis=0)) / 2
            c = np.arange(len(score))
            if len(c) > k:
                # a score of nine digits may stand a little higher or lower; of equal ones only the first can be wanted
                c = np.flatnonzero(score >= np.partition(score, -k)[-k] - 2e-9)
                c = c[np.lexsort((rank[c], -score[c]))]
                starts = np.flatnonzero(np.diff(score[c], prepend=np.inf))
                c = c[np.arange(len(c)) - np.repeat(starts, np.diff(np.append(starts, len(c)))) < k]
            cols = [pa.array([x] * len(c), t) for x, t in ((src, pa.string()), (tgt, pa.string()), (block, pa.int64()))]
            yield pa.record_batch([*cols, pool.words.take(pa.array(word[c])), pa.array(df[c]), pa.array(score[c])], names=[x.split()[0] for x in _BEST.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, maps = None, {}
        for batch in batches:
            for pair, bucket, side, block, words, n, s in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (pair, bucket) != now:
                    if now is not None:
                        yield from told(*now, maps)
                    now, maps = (pair, bucket), {}
                if block >= 0:
                    maps[side, block] = (np.frombuffer(words, np.uint16).astype(np.int64), np.frombuffer(n, np.uint32).astype(float), np.frombuffer(s))
        if now is not None:
            yield from told(*now, maps)

    return run


def renewed_pivots(docs: DataFrame, ev: DataFrame, pool: DataFrame, bank: DataFrame, alpha: float, every: int, k: int) -> DataFrame:
    """(src, tgt, block, rank, word, score): the ``k`` pivots after each block of ``every`` steps of the scheduled evidence ``ev``."""
    spark = docs.sparkSession
    start = bank.groupBy("src", "tgt", "word").agg(*[F.max(F.when(F.col("side") == x, F.col("p"))).alias(c) for x, c in (("S", "p_s"), ("T", "p_t"))])
    rows = pool.select("src", "tgt", "word", (F.col("df_s") + F.col("df_t")).alias("df")).join(start, ["src", "tgt", "word"])
    held = _Pool(rows.toArrow())
    shared = spark.sparkContext.broadcast(held)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.array_distinct(word_list(F.col("text"))).alias("words")).mapInArrow(_numbered(shared), "doc_id long, ids binary").where(F.length("ids") > 0)
    steps = ev.select("src", "tgt", "side", "doc_id", F.col("label").cast("double").alias("label"), "step", F.floor(F.col("step") / every).cast("long").alias("block"))
    key = ["src", "tgt", "side", "block"]
    dealt = steps.join(texts, "doc_id").select(*key, "step", "doc_id", "label", "ids").repartition(*key).sortWithinPartitions(*key, "step", "doc_id")
    maps = stage(dealt.mapInArrow(_folded(shared, alpha), _MAPS), "maps")
    tops = {r.pair: r.top for r in maps.groupBy("pair").agg(F.max("block").alias("top")).collect()}
    # every bucket of a pair that has a block, whether or not a text holds its words
    all_ = [(p, b, 0, -1, None, None, None) for p in tops for b in range(-(-len(held.own[p]) // PER_BUCKET))]
    maps = maps.unionByName(spark.createDataFrame(all_, _MAPS))
    best = maps.repartition("pair", "bucket").sortWithinPartitions("pair", "bucket").mapInArrow(_best(shared, tops, alpha, k), _BEST)
    rank = F.row_number().over(W.partitionBy("src", "tgt", "block").orderBy(F.desc(F.round("score", 9)), F.desc("df"), "word"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("src", "tgt", "block", "rank", "word", "score")
