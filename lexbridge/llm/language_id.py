"""Language identification (operator 1): sparse multinomial logistic regression on TF-IDF character n-grams.

Features are hashed 1- to 3-grams of letters and single blanks. Document frequencies come from every learnable document. The weights
are fitted with follow-the-regularised-leader under an elastic net (L1 and L2) on a sample of at most
``per_label`` documents of each language; a fifth of the sample is set aside and fixes the temperature that calibrates the scores.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.llm import tables
from lexbridge.llm.sampling import held_out, sample_ids

BITS = 15
PIECE = 1 << 20
_letters: np.ndarray | None = None


def _letter_table() -> np.ndarray:
    """Code point to its lower-case letter, or a blank for anything else."""
    global _letters
    if _letters is None:
        table = np.full(0x110000, 32, dtype=np.uint32)
        for cp in range(0x110000):
            c = chr(cp)
            if c.isalpha():
                low = c.lower()
                table[cp] = ord(low) if len(low) == 1 else cp
        _letters = table
    return _letters


def gram_counts(text: str | None) -> np.ndarray | None:
    """Counts of hashed n-grams of a whole text; None where it has no letter."""
    if not text:
        return None
    total = None
    for at in range(0, len(text), PIECE):  # long texts go piece by piece; a piece starts two characters early
        part = text[max(0, at - 2) : at + PIECE].encode("utf-32-le", "surrogatepass")
        c = _letter_table()[np.frombuffer(part, dtype=np.uint32)]
        keep = np.ones(len(c), dtype=bool)
        keep[1:] = (c[1:] != 32) | (c[:-1] != 32)
        c = c[keep]
        if not (c != 32).any():
            continue
        h, grams = c * np.uint32(0x9E3779B1), []
        grams.append(h)
        for _ in range(2):
            h = h[:-1] * np.uint32(0x85EBCA6B) + c[len(c) - len(h) + 1 :] * np.uint32(0xC2B2AE35)
            grams.append(h)
        codes = np.concatenate(grams)
        codes = ((codes ^ (codes >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - BITS)
        found = np.bincount(codes, minlength=1 << BITS)
        total = found if total is None else total + found
    return total


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    df = np.zeros((1 << BITS) + 1, dtype=np.int64)  # the last cell counts documents
    for batch in batches:
        for text in batch.column("text"):
            counts = gram_counts(text.as_py())
            if counts is not None:
                df[:-1] += counts > 0
                df[-1] += 1
    found = tables.pieces(df)
    if found:
        yield tables.as_batch(found)


def _sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for i, text, lang in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("lang").to_pylist(), strict=True):
            counts = gram_counts(text.as_py())
            if counts is not None:
                ix = np.flatnonzero(counts)
                rows.append((i, lang, ix.astype(np.int32).tobytes(), counts[ix].astype(np.int32).tobytes()))
        types = [pa.int64(), pa.string(), pa.binary(), pa.binary()]
        yield pa.record_batch([pa.array([r[j] for r in rows], t) for j, t in enumerate(types)], names=["doc_id", "lang", "ix", "n"])


@dataclass
class LanguageModel:
    langs: list[str]
    idf: np.ndarray
    weights: np.ndarray  # (features, languages)
    bias: np.ndarray
    temperature: float

    def logits(self, ix: np.ndarray, counts: np.ndarray) -> np.ndarray:
        x = np.log1p(counts).astype(np.float32) * self.idf[ix]
        return (x / max(float(np.sqrt(x @ x)), 1e-9)) @ self.weights[ix] + self.bias


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def _follow_leader(rows, y, n_lang: int, idf, epochs: int, alpha: float, beta: float, l1: float, l2: float):
    """FTRL-proximal, one document at a time; only the document's own features move."""
    z, n = (np.zeros((1 << BITS, n_lang), dtype=np.float64) for _ in range(2))
    zb, nb = np.zeros(n_lang), np.zeros(n_lang)
    solve = lambda z, n, l1: np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2))
    order = np.arange(len(rows))
    for epoch in range(epochs):
        np.random.default_rng(epoch).shuffle(order)
        for i in order:
            ix, counts = rows[i]
            x = np.log1p(counts) * idf[ix]
            x /= max(np.sqrt(x @ x), 1e-9)
            w, b = solve(z[ix], n[ix], l1), solve(zb, nb, 0.0)
            err = _softmax(x @ w + b)
            err[y[i]] -= 1
            for zz, nn, ww, g, at in ((z, n, w, np.outer(x, err), ix), (zb, nb, b, err, slice(None))):
                more = nn[at] + g * g
                zz[at] += g - (np.sqrt(more) - np.sqrt(nn[at])) / alpha * ww
                nn[at] = more
    return solve(z, n, l1).astype(np.float32), solve(zb, nb, 0.0).astype(np.float32)


def _temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The divisor of the logits that makes the set-aside labels likeliest."""
    if not len(y):
        return 1.0
    grid = np.exp(np.linspace(np.log(0.05), np.log(20), 200))
    loss = [-np.log(np.maximum(_softmax(logits / t)[np.arange(len(y)), y], 1e-12)).mean() for t in grid]
    return float(grid[int(np.argmin(loss))])


def fit_language_model(docs: DataFrame, per_label: int = 1000, epochs: int = 3, alpha: float = 0.5, beta: float = 1.0, l1: float = 1e-3, l2: float = 1e-4) -> LanguageModel | None:
    """Learns from rows of ``docs`` (doc_id, text, lang) with a language; None if there is none.

    ``per_label`` bounds the fitted documents of each language, whatever the table's size.
    """
    learn = docs.where(F.col("lang").isNotNull())
    df = tables.add_up(learn.select("text").mapInArrow(_frequencies, tables.SCHEMA), np.zeros((1 << BITS) + 1, dtype=np.int64))
    idf = np.log((1 + df[-1]) / (1 + df[:-1])).astype(np.float32) + 1
    ids = sample_ids(learn, "lang", per_label).select("doc_id")
    picked = learn.join(F.broadcast(ids), "doc_id", "left_semi").select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang").mapInArrow(_sparse, "doc_id long, lang string, ix binary, n binary")
    one = picked.groupBy("doc_id").agg(F.min(F.struct("lang", "ix", "n")).alias("r"))  # of several rows of one id the least is learned from
    got = sorted((r.r.lang, r.r.ix, r.r.n) for r in one.collect())  # at most per_label of each language
    if not got:
        return None
    langs = sorted({g[0] for g in got})
    rows = [(np.frombuffer(ix, np.int32), np.frombuffer(n, np.int32)) for _, ix, n in got]
    y = np.array([langs.index(g[0]) for g in got])
    aside = np.arange(len(rows)) % 5 == 4
    fit_rows = [r for r, a in zip(rows, aside, strict=True) if not a]
    w, b = _follow_leader(fit_rows, y[~aside], len(langs), idf, epochs, alpha, beta, l1, l2)
    model = LanguageModel(langs, idf, w, b, 1.0)
    test = [model.logits(*r) for r, a in zip(rows, aside, strict=True) if a]
    model.temperature = _temperature(np.array(test), y[aside]) if test else 1.0
    return model


def identify(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """doc_id, lang_pred, score for every row of ``docs`` (doc_id, text).

    A null text, or one without a letter, is ``und`` with score 0, as is every text where nothing could be learned.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            lang, score = [], []
            for text in batch.column("text"):
                counts = gram_counts(text.as_py()) if m else None
                if counts is None:
                    lang.append("und")
                    score.append(0.0)
                    continue
                ix = np.flatnonzero(counts)
                p = _softmax(m.logits(ix, counts[ix]).astype(np.float64) / m.temperature)
                lang.append(m.langs[int(p.argmax())])
                score.append(float(p.max()))
            yield pa.record_batch([batch.column("doc_id"), pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def language_report(docs: DataFrame, per_label: int = 1000) -> DataFrame:
    """Fits on the rows that are not held out and predicts all: doc_id, held_out, lang_pred, score."""
    model = fit_language_model(docs.select("doc_id", "text", "lang").where(~held_out()), per_label)
    return identify(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
