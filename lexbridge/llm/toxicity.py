"""Toxicity (operator 5) by multiple-instance learning.

A document is a bag of sentences, a sentence a bag of hashed words and of their beginnings of four and five bytes, so that the forms of
a stem share what is learned of any of them. A sentence's score is a logistic function of these features; the document's is the noisy-or
of its sentences' scores. Only documents have labels: the gradient of the noisy-or shares each label out among the sentences, so the
fitted sentence scores locate the offending ones. L1 keeps ordinary words at zero.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexbridge.llm import tokens
from lexbridge.llm.sampling import first_by_hash, held_out

BITS = 18
_NOT_WORD = np.ones(256, dtype=bool)
_NOT_WORD[list(range(65, 91)) + list(range(97, 123)) + list(range(128, 256))] = False
_ENDS = np.zeros(256, dtype=bool)
_ENDS[[10, 33, 46, 63]] = True  # newline ! . ?


BEGINNINGS = (4, 5)


def _beginnings(text: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> list[np.ndarray]:
    """Hashes of the first bytes of each word, one array per length; ``ends`` bounds each word's document."""
    inside, h, out = np.ones(len(starts), dtype=bool), np.zeros(len(starts), np.uint64), []
    for k in range(max(BEGINNINGS)):
        at = np.minimum(starts + k, len(text) - 1)
        inside &= (starts + k < ends) & ~_NOT_WORD[text[at]]
        h = h * np.uint64(0x9E3779B97F4A7C15) + np.where(inside, text[at].astype(np.uint64) + np.uint64(1), np.uint64(0))
        if k + 1 in BEGINNINGS:
            out.append(tokens.mix(h + np.uint64(k)))
    return out


def _bags(batch: pa.RecordBatch, weights: np.ndarray | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(row, number of sentences, feature codes, sentence numbers from 0) of each document, by sentence and code, each code once a sentence.

    A sentence without a word counts too, but for those after the last word. With ``weights``, features of no weight are left out.
    """
    raw, offsets = tokens.buffers(batch.column("text"))
    for a, b in tokens.chunks(offsets):
        words, bounds, starts = tokens.word_hashes(raw, offsets[a : b + 1], _NOT_WORD)
        base = int(offsets[a])
        text = tokens.lowered(raw[base : int(offsets[b])])
        stops = np.flatnonzero(_ENDS[text])
        doc = np.repeat(np.arange(b - a), np.diff(bounds))
        sentence = np.searchsorted(stops, starts) - np.searchsorted(stops, offsets[a:b] - base)[doc]
        n = np.ones(b - a, dtype=np.int64)
        full = np.diff(bounds) > 0
        n[full] = sentence[bounds[1:][full] - 1] + 1
        first = np.concatenate(([0], np.cumsum(n)))
        place = first[doc] + sentence  # sentences of the chunk, numbered on
        found = []
        for f in [words, *_beginnings(text, starts, (offsets[a + 1 : b + 1] - base)[doc])] if len(starts) else []:
            codes = (f >> np.uint64(64 - BITS)).astype(np.int64)
            used = slice(None) if weights is None else np.flatnonzero(weights[codes])
            found.append((place[used] << BITS) + codes[used])
        pair = np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)
        cuts = np.searchsorted(pair, first << BITS)
        for i in range(b - a):
            own = pair[cuts[i] : cuts[i + 1]]
            yield a + i, int(n[i]), own & ((1 << BITS) - 1), (own >> BITS) - first[i]


def _bag_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A document's features, sentence after sentence, and how many each sentence has."""
    for batch in batches:
        ids, labels, c, s = batch.column("doc_id").to_pylist(), batch.column("toxic").to_pylist(), [], []
        for _, n, codes, sentence in _bags(batch):
            c.append(codes.astype(np.int32).tobytes())
            s.append(np.bincount(sentence, minlength=n).astype(np.int32).tobytes())
        yield pa.record_batch([pa.array(ids, pa.int64()), pa.array(labels, pa.int32()), pa.array(c, pa.binary()), pa.array(s, pa.binary())], names=["doc_id", "toxic", "codes", "sizes"])


@dataclass
class ToxicModel:
    weights: np.ndarray
    bias: float

    def sentences(self, n: int, codes: np.ndarray, sentence: np.ndarray) -> np.ndarray:
        """The logit of each of ``n`` sentences; one without words has the bias alone."""
        return self.bias + np.bincount(sentence, weights=self.weights[codes], minlength=n)


def _softplus(x: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, x)


def _fit(bags, y, epochs: int, alpha: float, l1: float, l2: float, start: float) -> ToxicModel:
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    bias, nb = start, 1.0
    order = np.arange(len(bags))
    for epoch in range(epochs):
        np.random.default_rng(epoch).shuffle(order)
        for i in order:
            codes, sizes = (np.frombuffer(x, np.int32) for x in bags[i])
            m, sentence = len(sizes), np.repeat(np.arange(len(sizes)), sizes)
            words, where = np.unique(codes, return_inverse=True)
            zz, nn = z[words], n[words]
            w = np.where(np.abs(zz) <= l1, 0.0, -(zz - np.sign(zz) * l1) / ((1 + np.sqrt(nn)) / alpha + l2))
            logit = bias + np.bincount(sentence, weights=w[where], minlength=m)
            clean = _softplus(logit).sum()  # -log of the chance that no sentence offends
            pull = 1.0 if not y[i] else -np.exp(-clean) / max(-np.expm1(-clean), 1e-12)
            g_s = pull / (1 + np.exp(-logit))
            g = np.bincount(where, weights=g_s[sentence], minlength=len(words))
            more = nn + g * g
            z[words] = zz + g - (np.sqrt(more) - np.sqrt(nn)) / alpha * w
            n[words] = more
            gb = g_s.sum()
            nb += gb * gb
            bias = min(bias - 0.1 * gb / np.sqrt(nb), -1.0)
    w = np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((1 + np.sqrt(n)) / alpha + l2))
    return ToxicModel(w.astype(np.float32), float(bias))


def _fitted(*settings):
    """One row, weights and bias, of all bags that the task holds, learned from in order of id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for batch in batches for r in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "toxic", "codes", "sizes")), strict=True)]
        rows.sort(key=lambda r: r[0])
        model = _fit([r[2:] for r in rows], [r[1] == 1 for r in rows], *settings)
        yield pa.record_batch([pa.array([model.weights.tobytes()], pa.binary()), pa.array([model.bias])], names=["weights", "bias"])

    return run


def fit_toxicity(docs: DataFrame, labels: DataFrame, max_rows: int = 8_000, epochs: int = 4, alpha: float = 0.5, l1: float = 0.6, l2: float = 0.1, start: float = -6.0) -> ToxicModel:
    """Learns from ``labels`` (doc_id, toxic) of documents that are not held out: at most ``max_rows`` labelled ids, the first by hash.

    A document labelled twice counts as toxic if any label is 1; null labels are left out. Of several rows of one id one is learned from,
    whichever has the least features. Without labels every sentence keeps the start bias.
    """
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked = first_by_hash(known.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic"), max_rows)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(picked), "doc_id")
    bags = rows.mapInArrow(_bag_rows, "doc_id long, toxic int, codes binary, sizes binary").groupBy("doc_id", "toxic").agg(F.min(F.struct("codes", "sizes")).alias("bag"))
    # at most max_rows documents, which one task holds; the driver sees the weights alone
    settings = (epochs, alpha, l1, l2, start)
    fitted = bags.select("doc_id", "toxic", "bag.*").coalesce(1).mapInArrow(_fitted(*settings), "weights binary, bias double").first()
    return ToxicModel(np.frombuffer(fitted.weights, np.float32), fitted.bias) if fitted else _fit([], [], *settings)


def _scored(m: ToxicModel, batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    score, worst, most = np.zeros(batch.num_rows), np.full(batch.num_rows, -1, np.int32), np.zeros(batch.num_rows)
    for i, n, codes, sentence in _bags(batch, m.weights):
        logit = m.sentences(n, codes, sentence)
        score[i] = -np.expm1(-_softplus(logit).sum())
        if len(codes):
            worst[i] = int(logit.argmax())
        most[i] = 1 / (1 + np.exp(-logit.max()))
    return score, worst, most


def toxic_score(spark: SparkSession, model: ToxicModel):
    """A column function from a text to its score, for filters."""
    shared = spark.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return pd.Series(_scored(shared.value, pa.record_batch([pa.array(text, pa.string())], names=["text"]))[0])

    return score


def score_toxicity(docs: DataFrame, model: ToxicModel) -> DataFrame:
    """doc_id, score, worst_sentence (its number, from 0), worst_score for every row of ``docs`` (doc_id, text).

    Sentences end at ``.``, ``!``, ``?`` and newlines. A null or empty text has the score of one wordless sentence; a text
    without a word that the model knows has no worst sentence.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score, worst, most = _scored(shared.value, batch)
            yield pa.record_batch([batch.column("doc_id"), pa.array(score), pa.array(worst, mask=worst < 0), pa.array(most)], names=["doc_id", "score", "worst_sentence", "worst_score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double, worst_sentence int, worst_score double")


def toxicity_report(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """Fits on labelled rows that are not held out and scores all: doc_id, held_out, score, predicted, worst_sentence, worst_score."""
    model = fit_toxicity(docs, labels)
    return score_toxicity(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "worst_sentence", "worst_score")
