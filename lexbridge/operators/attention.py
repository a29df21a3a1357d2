"""Attention providers: where a sentence's word-to-word weights come from.

The methods need, for a pivot at place i, a row of weights over the sentence's words. A user with a trained encoder supplies a column of
heads x n x n weights; two stand-ins ship with the engine. The co-occurrence provider is joins and aggregates only. The vector provider
looks each word up in a table of vectors by hash, a mechanical substitute for an encoder's last layer, and says nothing about meaning.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

DECAY = 0.1
REACH = 5


# ---- supplied weights, as column expressions


def head_mean(att: Column) -> Column:
    """heads x n x n to n x n: the mean over heads."""
    add = lambda a, b: F.zip_with(a, b, lambda x, y: F.zip_with(x, y, lambda p, q: p + q))
    total = F.aggregate(F.slice(att, 2, F.size(att)), F.element_at(att, 1), add)
    return F.transform(total, lambda row: F.transform(row, lambda x: x / F.size(att)))


def piece_mean(m: Column, owner: Column) -> Column:
    """Piece-by-piece weights to word-by-word: the mean over the pieces of both words. ``owner`` names each piece's word, from 0."""
    words = F.sequence(F.lit(0), F.array_max(owner))
    of = lambda w: F.filter(F.sequence(F.lit(0), F.size(owner) - 1), lambda p: F.get(owner, p) == w)
    mean = lambda xs: F.aggregate(xs, F.lit(0.0), lambda a, x: a + x) / F.size(xs)
    cells = lambda a, b: F.flatten(F.transform(of(a), lambda p: F.transform(of(b), lambda q: F.get(F.get(m, p), q))))
    return F.transform(words, lambda a: F.transform(words, lambda b: mean(cells(a, b))))


# ---- co-occurrence provider


def cooccurrence_rows(sents: DataFrame, pool_words: DataFrame) -> DataFrame:
    """(domain, doc_id, sent_ix, i, j, w_i, w_j, a) for the places i of pool words and all other places j of their sentences.

    ``sents`` has words; ``pool_words`` (domain, word). Weights of a row add up to 1 without the place itself.
    """
    tokens = sents.select("domain", F.explode("words").alias("word"))
    single = tokens.groupBy("domain", "word").agg(F.count("*").alias("c"))
    rows = sents.select("domain", "doc_id", "sent_ix", "words", F.posexplode("words").alias("i", "w_i")).join(
        F.broadcast(pool_words.select("domain", F.col("word").alias("w_i"))), ["domain", "w_i"], "left_semi"
    )
    cells = rows.select("domain", "doc_id", "sent_ix", "i", "w_i", F.posexplode("words").alias("j", "w_j")).where("i != j")
    together = cells.where(F.abs(F.col("i") - F.col("j")) <= REACH).groupBy("domain", "w_i", "w_j").agg(F.count("*").alias("c_ij"))
    own = F.broadcast(single.join(F.broadcast(pool_words), ["domain", "word"], "left_semi").select("domain", F.col("word").alias("w_i"), F.col("c").alias("c_i")))
    joined = cells.join(own, ["domain", "w_i"]).join(single.select("domain", F.col("word").alias("w_j"), F.col("c").alias("c_j")), ["domain", "w_j"]).join(together, ["domain", "w_i", "w_j"], "left")
    t = (1 + F.coalesce("c_ij", F.lit(0))) / F.sqrt(F.col("c_i") * F.col("c_j")) * F.exp(-DECAY * F.abs(F.col("i") - F.col("j")))
    total = F.sum("t").over(W.partitionBy("domain", "doc_id", "sent_ix", "i"))
    return joined.withColumn("t", t).withColumn("a", F.col("t") / total).select("domain", "doc_id", "sent_ix", "i", "j", "w_i", "w_j", "a")


# ---- vector provider


def _row_of(word: str, n: int) -> int:
    return int(hashlib.md5(word.encode()).hexdigest()[:8], 16) % n


def attention_rows(x: np.ndarray, rows: np.ndarray, heads: int, temperature: float = 1.0) -> np.ndarray:
    """heads x rows x n softmax weights of the vectors ``x`` (n, d), own place included."""
    n, d = x.shape
    width = d // heads
    out = np.empty((heads, len(rows), n))
    far = DECAY * np.abs(rows[:, None] - np.arange(n)[None, :])
    for h in range(heads):
        part = x[:, h * width : (h + 1) * width]
        z = part[rows] @ part.T * np.sqrt(width) / temperature - far
        z = np.exp(z - z.max(axis=1, keepdims=True))
        out[h] = z / z.sum(axis=1, keepdims=True)
    return out


def _cut(word: str, size: int) -> list[str]:
    return [word[i : i + size] for i in range(0, len(word), size)]


def word_rows(words: list[str], at: np.ndarray, table: np.ndarray, heads: int, piece: int | None, temperature: float = 1.0) -> np.ndarray:
    """rows x n weights of the words at ``at``: heads averaged, and pieces of ``piece`` characters averaged into words if asked for."""
    if piece is None:
        x = table[[_row_of(w, len(table)) for w in words]]
        return attention_rows(x, at, heads, temperature).mean(axis=0)
    parts = [_cut(w, piece) for w in words]
    owner = np.repeat(np.arange(len(words)), [len(p) for p in parts])
    x = table[[_row_of(p, len(table)) for ps in parts for p in ps]]
    rows = np.flatnonzero(np.isin(owner, at))
    m = attention_rows(x, rows, heads, temperature).mean(axis=0)
    starts = np.searchsorted(owner, np.arange(len(words)))
    m = np.add.reduceat(m, starts, axis=1) / np.bincount(owner)[None, :]
    own = owner[rows]
    return np.stack([m[own == i].mean(axis=0) for i in at])


def load_vectors(vectors: DataFrame, most: int = 1_000_000) -> np.ndarray:
    """The vector table in order of its id; refused beyond ``most`` rows, since every task holds it."""
    n = vectors.count()
    if n > most:
        raise ValueError(f"{n} vectors are more than a task may hold; give weights as a column instead")
    return np.array([r.embedding for r in vectors.orderBy("vec_id").select("embedding").collect()], dtype=np.float64)


def vector_facts(sents: DataFrame, pool_words: DataFrame, vectors: DataFrame, heads: int = 4, piece: int | None = None) -> DataFrame:
    """Candidate facts in one fused pass: weights never leave the task. Columns as :func:`lexbridge.operators.facts.make_facts`.

    Sentences without a pool word are dropped before Python sees them.
    """
    shared = sents.sparkSession.sparkContext.broadcast(load_vectors(vectors))
    return _fact_pass(_with_places(sents, pool_words), shared, heads, piece)


def _with_places(sents: DataFrame, pool_words: DataFrame) -> DataFrame:
    """(domain, doc_id, sent_ix, words, places): places of pool words, by a join on words and not by a list in every row."""
    rows = sents.select("domain", "doc_id", "sent_ix", "words", F.posexplode("words").alias("i", "word"))
    rows = rows.join(F.broadcast(pool_words), ["domain", "word"], "left_semi")
    return rows.groupBy("domain", "doc_id", "sent_ix", "words").agg(F.array_sort(F.collect_list("i")).alias("places"))


def _fact_pass(rows: DataFrame, shared, heads: int, piece: int | None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                words, at = r["words"], np.array(r["places"])
                m = np.round(word_rows(words, at, table, heads, piece), 9)
                m[np.arange(len(at)), at] = -1.0  # a pivot is not its own neighbour
                order = np.argsort(-m, axis=1, kind="stable")[:, :2]
                for k, i in enumerate(at):
                    j = order[k]
                    a, b, c = sorted((int(i), int(j[0]), int(j[1])))
                    out.append((r["domain"], r["doc_id"], r["sent_ix"], int(i), words[i], words[a], words[b], words[c], (a, b, c).index(int(i)), float(m[k, j[0]] + m[k, j[1]])))
            types = [pa.string(), pa.int64(), pa.int32(), pa.int32(), *[pa.string()] * 4, pa.int32(), pa.float64()]
            yield pa.record_batch([pa.array([o[n] for o in out], t) for n, t in enumerate(types)], names=["domain", "doc_id", "sent_ix", "i", "pivot", "w_a", "w_b", "w_c", "slot", "conf"])

    return rows.mapInArrow(run, "domain string, doc_id long, sent_ix int, i int, pivot string, w_a string, w_b string, w_c string, slot int, conf double")


def vector_weights(sents: DataFrame, pool_words: DataFrame, vectors: DataFrame, heads: int = 4, piece: int | None = None, per_head: bool = False) -> DataFrame:
    """Long form of the vector provider: (domain, doc_id, sent_ix, head, i, j, a); head is -1 for the mean."""
    shared = sents.sparkSession.sparkContext.broadcast(load_vectors(vectors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            for r in batch.to_pylist():
                words, at = r["words"], np.array(r["places"])
                if per_head:
                    m = attention_rows(table[[_row_of(w, len(table)) for w in words]], at, heads)
                else:
                    m = word_rows(words, at, table, heads, piece)[None]
                h, k, j = (x.ravel() for x in np.indices(m.shape))
                n = len(h)
                yield pa.record_batch([pa.array([r["domain"]] * n), pa.array([r["doc_id"]] * n, pa.int64()), pa.array([r["sent_ix"]] * n, pa.int32()), pa.array((h if per_head else h - 1).astype(np.int32)), pa.array(at[k].astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(m.ravel())], names=["domain", "doc_id", "sent_ix", "head", "i", "j", "a"])

    return _with_places(sents, pool_words).mapInArrow(run, "domain string, doc_id long, sent_ix int, head int, i int, j int, a double")
