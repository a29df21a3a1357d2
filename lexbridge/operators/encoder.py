"""Text representations: the visible-attention encoder over injected trees, and the hashed bag that scales linearly."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.operators.attention import _row_of, load_vectors
from lexbridge.operators.inject import SLICE, visible_mask
from lexbridge.operators.pivot_mask import MASK


def bag(tokens: list[dict], dims: int, gamma: float, hidden: frozenset[str] = frozenset()) -> tuple[np.ndarray, np.ndarray]:
    """(buckets, values): trunk words weigh 1, branch words gamma to the power of their distance; the vector has length 1.

    Words of ``hidden`` on the trunk stand as the mask symbol. With gamma 0 the branches vanish.
    """
    if not tokens:
        return np.zeros(0, np.int32), np.zeros(0, np.float32)
    codes = np.array([zlib.crc32((MASK if t["branch"] == 0 and t["tok"] in hidden else t["tok"]).encode()) % dims for t in tokens])
    values = np.array([1.0 if t["branch"] == 0 else gamma ** (t["pos"] - t["trunk"]) for t in tokens])
    ix, inverse = np.unique(codes, return_inverse=True)
    v = np.bincount(inverse, weights=values)
    keep = v > 0
    ix, v = ix[keep], v[keep]
    return ix.astype(np.int32), (v / max(np.sqrt((v * v).sum()), 1e-12)).astype(np.float32)


def bags(tokens: pa.ListArray, dims: int, gamma: float, hidden: list[frozenset[str]] | None = None, of: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[str]]]:
    """(buckets, values, buckets with hidden words, their values, hidden words on the trunk) of each text: :func:`bag` for many at once.

    ``of`` tells which set of ``hidden`` is a text's own; without sets the last three are empty.
    """
    n = tokens.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = tokens.flatten()
    pos, branch, trunk = (flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in ("pos", "branch", "trunk"))
    tok = flat.field("tok").dictionary_encode()
    words, word = tok.dictionary.to_pylist(), tok.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    row = np.repeat(np.arange(len(n)), n)
    codes = np.array([zlib.crc32(w.encode()) % dims for w in words], np.int64)[word]
    values = np.where(branch == 0, 1.0, float(gamma) ** (pos - trunk))
    plain = _summed(row, codes, values, dims, len(n))
    if hidden is None:
        none = (np.zeros(0, np.int32), np.zeros(0, np.float32), [])
        for ix, v in plain:
            yield ix, v, *none
        return
    held = np.array([[w in own for w in words] for own in hidden], bool).reshape(len(hidden), len(words))
    hides = (branch == 0) & held[of[row], word]
    masked = _summed(row, np.where(hides, zlib.crc32(MASK.encode()) % dims, codes), values, dims, len(n))
    seen = np.unique(row[hides] * max(len(words), 1) + word[hides])
    cuts = np.searchsorted(seen, np.arange(len(n) + 1) * max(len(words), 1))
    for r, ((ix, v), (mix, mv)) in enumerate(zip(plain, masked, strict=True)):
        yield ix, v, mix, mv, sorted(words[w - r * len(words)] for w in seen[cuts[r] : cuts[r + 1]].tolist())


def _summed(row: np.ndarray, codes: np.ndarray, values: np.ndarray, dims: int, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    keys, inverse = np.unique(row * dims + codes, return_inverse=True)
    v = np.bincount(inverse, weights=values, minlength=len(keys))
    keys, v = keys[v > 0], v[v > 0]
    cuts = np.searchsorted(keys, np.arange(n + 1) * dims)
    for r in range(n):
        own = v[cuts[r] : cuts[r + 1]]
        yield (keys[cuts[r] : cuts[r + 1]] - r * dims).astype(np.int32), (own / max(np.sqrt((own * own).sum()), 1e-12)).astype(np.float32)


class VisibleEncoder:
    """Self-attention layers in which a token sees only what its tree lets it see; weights are fixed by the seed."""

    def __init__(self, table: np.ndarray, layers: int = 2, heads: int = 4, seed: int = 0):
        self.table, self.heads, d = table, heads, table.shape[1]
        rng = np.random.default_rng(seed)
        self.layers = [tuple(rng.standard_normal((d, d)) / np.sqrt(d) for _ in range(3)) for _ in range(layers)]

    def positions(self, pos: np.ndarray) -> np.ndarray:
        d = self.table.shape[1]
        angle = pos[:, None] / 10_000 ** (2 * (np.arange(d) // 2)[None, :] / d)
        return np.where(np.arange(d) % 2 == 0, np.sin(angle), np.cos(angle)) / np.sqrt(d)

    def run(self, words: list[str], pos: np.ndarray, branch: np.ndarray, trunk: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(token vectors, last layer's heads x n x n attention)."""
        return self.run_rows(np.array([_row_of(w, len(self.table)) for w in words], np.int64), pos, branch, trunk)

    def run_rows(self, rows: np.ndarray, pos: np.ndarray, branch: np.ndarray, trunk: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for words given as rows of the table."""
        x = self.table[rows] + self.positions(pos)
        n, d = len(rows), self.table.shape[1]
        hides = np.where(visible_mask(branch, trunk), 0.0, -np.inf)
        width, att = d // self.heads, np.zeros((self.heads, n, n))
        for wq, wk, wv in self.layers:
            q, k, v = x @ wq * np.sqrt(width), x @ wk, x @ wv
            out = np.empty_like(x)
            for h in range(self.heads):
                at, z = slice(h * width, (h + 1) * width), att[h]
                np.matmul(q[:, at], k[:, at].T, out=z)
                z += hides
                z -= z.max(axis=1, keepdims=True)
                np.exp(z, out=z)
                z /= z.sum(axis=1, keepdims=True)
                out[:, at] = z @ v[:, at]
            x = x + out
            x = (x - x.mean(axis=1, keepdims=True)) / (x.std(axis=1, keepdims=True) + 1e-6)
        return x, att


def encode(trees: DataFrame, vectors: DataFrame, most: int = 128, layers: int = 2) -> DataFrame:
    """(src, tgt, doc_id, vector): the mean of the trunk's token vectors. Long trees are encoded in chunks of ``most`` tokens and averaged by length."""
    shared = trees.sparkSession.sparkContext.broadcast(load_vectors(vectors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = VisibleEncoder(shared.value, layers)
        for whole in batches:
            for at in range(0, whole.num_rows, SLICE):
                batch = whole.slice(at, SLICE)
                yield pa.record_batch([batch.column("src"), batch.column("tgt"), batch.column("doc_id"), pa.array(vectors_of(net, batch.column("tokens")), pa.list_(pa.float64()))], names=["src", "tgt", "doc_id", "vector"])

    def vectors_of(net: VisibleEncoder, tokens: pa.ListArray) -> list[np.ndarray]:
        ends = np.cumsum(tokens.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
        flat = tokens.flatten()
        pos, branch, trunk = (flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in ("pos", "branch", "trunk"))
        tok = flat.field("tok").dictionary_encode()
        rows = np.array([_row_of(w, len(net.table)) for w in tok.dictionary.to_pylist()], np.int64)[tok.indices.to_numpy(zero_copy_only=False)]
        out = []
        for start, end in zip(np.append(0, ends[:-1]).tolist(), ends.tolist(), strict=True):
            total, count = np.zeros(net.table.shape[1]), 0
            for at in range(start, end, most):
                part = slice(at, min(at + most, end))
                x, _ = net.run_rows(rows[part], pos[part], branch[part], trunk[part])
                own = branch[part] == 0
                total, count = total + x[own].sum(axis=0), count + int(own.sum())
            out.append(total / max(count, 1))
        return out

    return trees.select("src", "tgt", "doc_id", "tokens").mapInArrow(run, "src string, tgt string, doc_id long, vector array<double>")


def encoder_facts(sents: DataFrame, pool_words: DataFrame, vectors: DataFrame) -> DataFrame:
    """Candidate facts from the encoder's own last layer, heads averaged; columns as the other providers."""
    from lexbridge.operators.attention import _with_places

    shared = sents.sparkSession.sparkContext.broadcast(load_vectors(vectors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = VisibleEncoder(shared.value)
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                n = len(r["words"])
                _, att = net.run(r["words"], np.arange(n), np.zeros(n, int), np.arange(n))
                m = np.round(att.mean(axis=0), 9)
                np.fill_diagonal(m, -1.0)
                for i in r["places"]:
                    j = np.argsort(-m[i], kind="stable")[:2]
                    a, b, c = sorted((i, int(j[0]), int(j[1])))
                    w = r["words"]
                    out.append((r["domain"], r["doc_id"], r["sent_ix"], i, w[i], w[a], w[b], w[c], (a, b, c).index(i), float(m[i, j].sum())))
            types = [pa.string(), pa.int64(), pa.int32(), pa.int32(), *[pa.string()] * 4, pa.int32(), pa.float64()]
            yield pa.record_batch([pa.array([o[k] for o in out], t) for k, t in enumerate(types)], names=["domain", "doc_id", "sent_ix", "i", "pivot", "w_a", "w_b", "w_c", "slot", "conf"])

    return _with_places(sents, pool_words).mapInArrow(run, "domain string, doc_id long, sent_ix int, i int, pivot string, w_a string, w_b string, w_c string, slot int, conf double")
