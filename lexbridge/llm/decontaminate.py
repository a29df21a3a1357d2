"""Benchmark decontamination (operator 7) by latent semantic retrieval.

Words are runs of letters and digits. Passage frequencies come from every document. A distributed randomised SVD of TF-IDF passages gives
the latent space: each turn multiplies the sparse passage matrix and its transpose with a thin block, task by task, and only the thin
product is summed. It is fitted on every passage of every document, and every word of every document is then projected with it.
Benchmark passages are the queries, taken in blocks. A document's overlapping windows, of each query's size, become candidates by
cosine, against a gate that follows how much of the window the query could fill; a candidate counts if it has enough of the query's words by their weight, their longest common subsequence covers enough of
the query, and the query's rarest words, which carry its answer, are there. So reworded copies are found and chance resemblance is not.
A stretch of a document that lacks too many of a query's rarest words could never pass that last check, so it is neither projected nor
compared with that query; nothing is lost by that.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.llm import tables, tokens
from lexbridge.llm.scratch import Scratch

BITS = 14
PASSAGE = 64
STEP = 16
#: Passages that a task multiplies at once, and rows that it gathers at once.
BLOCK = 8192
GATHER = 1024
_NOT_WORD = np.ones(256, dtype=bool)
_NOT_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


@dataclass(frozen=True)
class Settings:
    """``rank`` latent directions after ``common`` ones that most passages share; turns of the fit; thresholds; the bound of a query block."""

    rank: int = 112
    common: int = 4
    turns: int = 2
    min_cosine: float = 0.4
    min_cover: float = 0.6
    min_answer: float = 0.5
    query_block: int = 20_000


def _words(batch: pa.RecordBatch, limit: int = tokens.CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    raw, offsets = tokens.buffers(batch.column("text"))
    for a, b in tokens.chunks(offsets, limit):
        words, bounds, _ = tokens.word_hashes(raw, offsets[a : b + 1], _NOT_WORD)
        yield a, b, words, bounds


def _codes(words: np.ndarray) -> np.ndarray:
    return (words >> np.uint64(64 - BITS)).astype(np.int64)


def _steps(bounds: np.ndarray, step: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the consecutive blocks of ``step`` words inside each document, and each document's first block."""
    n = -(-np.diff(bounds) // step)
    first = np.concatenate(([0], np.cumsum(n)))
    doc = np.repeat(np.arange(len(n)), n)
    return bounds[doc] + (np.arange(first[-1]) - first[doc]) * step, first


def _passages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each document's word codes, passage after passage, in the order of the codes inside a passage."""
    for batch in batches:
        for _, _, words, bounds in _words(batch):
            starts, _ = _steps(bounds, PASSAGE)
            size = np.diff(np.append(starts, len(words)))
            codes = np.sort((np.repeat(np.arange(len(starts)), size) << BITS) + _codes(words)) & ((1 << BITS) - 1)
            col = pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer((2 * bounds).astype(np.int32)), pa.py_buffer(codes.astype(np.uint16))])
            yield pa.record_batch([col], names=["codes"])


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(codes, start of each passage, its size), a bounded number of passages at a time."""
    for batch in batches:
        col = batch.column("codes").cast(pa.large_binary())
        _, off, data = col.buffers()
        bounds = np.frombuffer(off, np.int64)[col.offset : col.offset + len(col) + 1] // 2 if len(col) else np.zeros(1, np.int64)
        if bounds[-1] == bounds[0]:
            continue
        codes = np.frombuffer(data, np.uint16, count=int(bounds[-1]))[bounds[0] :]
        starts, _ = _steps(bounds - bounds[0], PASSAGE)
        ends = np.append(starts[1:], len(codes))
        for at in range(0, len(starts), BLOCK):
            own, end = starts[at : at + BLOCK], ends[at : at + BLOCK]
            yield codes[own[0] : end[-1]], own - own[0], end - own


def _firsts(codes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Places of the distinct codes of each passage."""
    new = np.concatenate(([True], codes[1:] != codes[:-1]))
    new[starts] = True
    return np.flatnonzero(new)


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    df = np.zeros((1 << BITS) + 1, dtype=np.int64)
    for codes, starts, _ in _blocks(batches):
        df[:-1] += np.bincount(codes[_firsts(codes, starts)], minlength=1 << BITS)
        df[-1] += len(starts)
    found = tables.pieces(df)
    if found:
        yield tables.as_batch(found)


def _scales(codes: np.ndarray, starts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """One over the length of each passage's TF-IDF vector."""
    at = _firsts(codes, starts)
    squares = (np.diff(np.append(at, len(codes))) * idf[codes[at]]) ** 2
    return (1 / np.maximum(np.sqrt(np.add.reduceat(squares, np.searchsorted(at, starts))), 1e-9)).astype(np.float32)


def _run_sums(rows: np.ndarray, ix: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The sum of ``rows`` at the indices of each run of ``ix``; runs of one size are gathered together, so much at a time as a cache holds."""
    out = np.zeros((len(size), rows.shape[1]), np.float32)
    order = np.argsort(size, kind="stable")
    order = order[size[order] > 0]
    sizes, cuts = np.unique(size[order], return_index=True)
    ones = np.ones((1, GATHER), np.float32)
    for n, lo, hi in zip(sizes.tolist(), cuts.tolist(), [*cuts[1:].tolist(), len(order)], strict=True):
        step = max(1, GATHER // n)
        for at in range(lo, hi, step):
            own = order[at : min(hi, at + step)]
            for left in range(0, n, GATHER):
                some = min(n - left, GATHER)
                here = ix[(start[own][:, None] + np.arange(left, left + some)).ravel()]
                out[own] += np.matmul(ones[:, :some], rows.take(here, axis=0).reshape(len(own), some, -1))[:, 0]
    return out


def _times(shared, gram: bool):
    """A task's part of A'(A X), or of (A X)'(A X)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        idf, x = shared.value
        weighed, total = x * idf[:, None], None
        for codes, starts, size in _blocks(batches):
            scale = _scales(codes, starts, idf)[:, None]
            y = _run_sums(weighed, codes, starts, size) * scale
            if gram:
                part = (y.T @ y).astype(np.float64)
            else:  # the same sums with passages and codes in each other's place
                of = np.repeat(np.arange(len(size)), size)[np.argsort(codes, kind="stable")]
                n = np.bincount(codes, minlength=1 << BITS)
                part = _run_sums(y * scale, of, np.cumsum(n) - n, n)
            total = part.astype(np.float64) if total is None else np.add(total, part, out=total)
        if total is not None:
            total = total if gram else total * idf[:, None]
            yield tables.as_batch(tables.pieces(total.astype(np.float32).ravel()))

    return run


def _product(rows: DataFrame, idf: np.ndarray, x: np.ndarray, gram: bool) -> np.ndarray:
    shared = rows.sparkSession.sparkContext.broadcast((idf, x))
    shape = (x.shape[1] if gram else x.shape[0], x.shape[1])
    total = tables.add_up(rows.mapInArrow(_times(shared, gram), tables.SCHEMA), np.zeros(shape[0] * shape[1], np.float32), few=True).reshape(shape)
    shared.destroy()
    return total


def latent_space(docs: DataFrame, scratch: Scratch, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """(idf, projection) over all passages of all documents: word frequencies, and a words-by-rank matrix with the idf inside."""
    rows = scratch.keep(docs.select("text").mapInArrow(_passages, "codes binary"), "passages")
    df = tables.add_up(rows.mapInArrow(_frequencies, tables.SCHEMA), np.zeros((1 << BITS) + 1, dtype=np.int64))
    idf = np.log((df[-1] + 1) / (df[:-1] + 1)).astype(np.float32)
    width = s.rank + s.common + 16
    x = np.random.default_rng(0).standard_normal((1 << BITS, width)).astype(np.float32)
    for _ in range(s.turns):
        x = np.linalg.qr(_product(rows, idf, x, False))[0].astype(np.float32)
    _, vectors = np.linalg.eigh(_product(rows, idf, x, True))
    scratch.drop("passages")
    v = (x @ vectors[:, ::-1])[:, s.common : s.common + s.rank]
    return idf, np.ascontiguousarray((v * idf[:, None]).astype(np.float32))


@dataclass
class _Query:
    n: int
    bits: dict[int, int]
    answer: set[int]
    weight: dict[int, float]


def _queries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, out = batch.column("item_id").to_pylist(), []
        for a, b, words, bounds in _words(batch):
            for i in range(b - a):
                own = words[bounds[i] : bounds[i + 1]]
                n = max(1, -(-len(own) // PASSAGE))
                out += [(ids[a + i], piece.tobytes()) for piece in np.array_split(own, n) if len(piece)]
        yield pa.record_batch([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.binary())], names=["item_id", "words"])


def _answer(words: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """The rarest third of a query's distinct words."""
    distinct = np.unique(words)
    return distinct[np.argsort(-idf[_codes(distinct)], kind="stable")[: max(1, len(distinct) // 3)]]


def _query(words: np.ndarray, idf: np.ndarray) -> _Query:
    bits: dict[int, int] = {}
    for i, w in enumerate(words.tolist()):
        bits[w] = bits.get(w, 0) | (1 << i)
    distinct = np.unique(words)
    total = max(float(idf[_codes(distinct)].sum()), 1e-9)
    weight = dict(zip(distinct.tolist(), (idf[_codes(distinct)] / total).tolist(), strict=True))
    return _Query(len(words), bits, set(_answer(words, idf).tolist()), weight)


class _Block:
    """A block of queries in arrays: their words, latent vectors, window sizes, and the postings of their answer words."""

    def __init__(self, rows: list, idf: np.ndarray, project: np.ndarray, s: Settings):
        self.idf, self.project = idf, project
        self.items = np.array([r[0] for r in rows], np.int64)
        self.words = [np.frombuffer(r[1], np.uint64) for r in rows]
        z = np.stack([project[_codes(w)].sum(axis=0) for w in self.words])
        self.z = z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-9)
        n = np.array([len(w) for w in self.words])
        self.blocks = -(-n // STEP) + 1
        self.gate = s.min_cosine * np.sqrt(n / (self.blocks * STEP))
        answers = [_answer(w, idf) for w in self.words]
        self.need = np.array([np.ceil(s.min_answer * len(a) - 1e-9) for a in answers]).astype(np.int64)
        owner = np.repeat(np.arange(len(rows)), [len(a) for a in answers])
        flat = np.concatenate(answers)
        order = np.argsort(flat, kind="stable")
        self.owner = owner[order]  # of each posting
        self.rare, first = np.unique(flat[order], return_index=True)
        self.first = np.append(first, len(flat))
        self.maybe = np.zeros(1 << 20, dtype=bool)
        self.maybe[(self.rare >> np.uint64(44)).astype(np.int64)] = True
        self.made: dict[int, _Query] = {}

    def query(self, j: int) -> _Query:
        if j not in self.made:
            if len(self.made) > 5000:
                self.made.clear()
            self.made[j] = _query(self.words[j], self.idf)
        return self.made[j]

    def stretches(self, words: np.ndarray, place: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(stretch, query) wherever two stretches in a row hold enough of a query's answer; ``place`` is each word's stretch, ``last`` tells a document's last one."""
        at = np.flatnonzero(self.maybe[(words >> np.uint64(44)).astype(np.int64)])
        k = np.minimum(np.searchsorted(self.rare, words[at]), len(self.rare) - 1)
        at, k = (x[self.rare[k] == words[at]] for x in (at, k))
        many = self.first[k + 1] - self.first[k]
        posting = np.repeat(self.first[k] - np.concatenate(([0], np.cumsum(many)))[:-1], many) + np.arange(many.sum())
        key = np.unique(np.repeat(place[at], many) * len(self.owner) + posting)
        here, posting = key // len(self.owner), key % len(self.owner)
        back = (here > 0) & ~last[np.maximum(here - 1, 0)]  # a stretch counts for the one before it in its document as well
        key = np.unique(np.concatenate((key, key[back] - len(self.owner))))
        here, posting = key // len(self.owner), key % len(self.owner)
        pair, found = np.unique(here * len(self.z) + self.owner[posting], return_counts=True)
        pair = pair[found >= self.need[pair % len(self.z)]]
        return pair // len(self.z), pair % len(self.z)


def common_words(bits: dict[int, int], n: int, words: list[int]) -> int:
    """Length of the longest common subsequence, bit-parallel over the query."""
    mask, v = (1 << n) - 1, (1 << n) - 1
    for w in words:
        m = bits.get(w)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & mask
    return n - v.bit_count()


#: Steps of a stretch: what is read round a window of the longest query lies in the stretch it begins in and the next.
STRETCH = PASSAGE // STEP + 3


def _near(block: _Block, words: np.ndarray, bounds: np.ndarray) -> Iterator[tuple[int, int, int, float]]:
    """(document, query, first step of the window, cosine) of every window that reaches its query's gate."""
    starts, first = _steps(bounds, STEP)
    if not len(starts):
        return
    steps = np.diff(first)
    count = -(-steps // STRETCH)
    doc_of = np.repeat(np.arange(len(count)), count)
    base = np.concatenate(([0], np.cumsum(count)))
    last = np.zeros(base[-1], dtype=bool)
    last[base[1:][count > 0] - 1] = True
    doc = np.repeat(np.arange(len(steps)), np.diff(bounds))
    place = base[doc] + (np.arange(len(words)) - bounds[doc]) // (STEP * STRETCH)
    here, query = block.stretches(words, place, last)
    for at in range(0, len(here), 500):
        own, which = np.unique(here[at : at + 500], return_inverse=True)
        q, d = query[at : at + 500], doc_of[own]
        lo = first[d] + (own - base[d]) * STRETCH  # first step of each stretch, and the end of the one after
        hi = np.minimum(lo + 2 * STRETCH, first[d + 1])
        n = hi - lo
        off = np.concatenate(([0], np.cumsum(n)))
        step = np.repeat(lo - off[:-1], n) + np.arange(off[-1])
        ends = np.append(starts[1:], len(words))
        size = ends[step] - starts[step]
        cut = np.concatenate(([0], np.cumsum(size)))
        flat = np.repeat(starts[step] - cut[:-1], size) + np.arange(cut[-1])
        sums = np.add.reduceat(block.project[_codes(words[flat])], cut[:-1], axis=0)
        sums = np.concatenate((np.zeros((1, sums.shape[1]), np.float32), np.cumsum(sums, axis=0, dtype=np.float64)))
        # every window whose surroundings begin in the stretch; a document's first step begins its first one
        shift = np.arange(STRETCH + 1)[None, :]
        begin, m = lo[which][:, None] + shift, block.blocks[q][:, None]
        top = first[d + 1][which][:, None]
        is_first = begin == first[d][which][:, None]
        fits = ((shift > 0) | is_first) & (begin < top) & ((begin + m <= top) | is_first)
        row, col = np.nonzero(fits)
        a = off[which[row]] + col
        b = np.minimum(off[which[row]] + col + block.blocks[q[row]], off[which[row]] + (first[d + 1] - lo)[which[row]])
        w = sums[b] - sums[a]
        cos = np.einsum("ij,ij->i", w, block.z[q[row]]) / np.maximum(np.sqrt(np.einsum("ij,ij->i", w, w)), 1e-9)
        for i in np.flatnonzero(cos >= block.gate[q[row]]):
            r = row[i]
            yield int(d[which[r]]), int(q[r]), int(lo[which[r]] + col[i] - first[d[which[r]]]), float(cos[i])


def _holds(q: _Query, words: list[int], s: Settings) -> float:
    """The share of the query's answer among ``words``; 0 if that, or what they have of the query by weight, is too little."""
    have = q.bits.keys() & set(words)
    told = len(q.answer & have) / len(q.answer)
    # common words alone, which any text shares, do not make a copy
    return told if told >= s.min_answer and sum(q.weight[w] for w in have) >= s.min_cover else 0.0


def _search(shared, s: Settings):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = shared.value
        for batch in batches:
            ids, out = batch.column("doc_id").to_numpy(zero_copy_only=False), []
            for a, _, words, bounds in _words(batch):
                found: dict[tuple[int, int], tuple] = {}
                for d, j, step, cos in _near(block, words, bounds):
                    p = bounds[d] + max(0, step - 1) * STEP
                    e = min(bounds[d + 1], p + (int(block.blocks[j]) + 2) * STEP)
                    region, q, item = words[p:e].tolist(), block.query(j), int(block.items[j])
                    if not _holds(q, region, s):
                        continue
                    # a copy is at most half as long again as the query; a longer region holds more of its words by chance
                    size = q.n + q.n // 2 + 4
                    for at in [*range(0, len(region) - size, max(1, q.n // 8)), max(0, len(region) - size)]:
                        part = region[at : at + size]
                        told = _holds(q, part, s)
                        share = common_words(q.bits, q.n, part) / q.n if told else 0.0
                        # a query of a few words must stand there whole; chance would find a part of it
                        if share >= (s.min_cover if q.n >= 8 else 1.0):
                            own = found.get((d, item))
                            if own is None or share > own[0]:
                                lo = int(p - bounds[d]) + at
                                found[d, item] = (share, told, cos, lo, lo + len(part))
                out += [(int(ids[a + d]), item, *v) for (d, item), v in found.items()]
            cols = list(zip(*out, strict=True)) if out else [[]] * 7
            types = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["doc_id", "item_id", "cover", "answer", "cosine", "start_word", "end_word"])

    return run


def find_leaks(docs: DataFrame, benchmark: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """doc_id, item_id, cover, answer, cosine, start_word, end_word: one row for each document and benchmark item it holds.

    ``docs`` has doc_id and text, ``benchmark`` item_id and text. Null and empty texts hold nothing and are held by nothing; rows of a null doc_id are
    searched but not named, and are left out. ``cover`` is the longest common subsequence over the item's words, ``start_word`` and
    ``end_word`` bound the region it was found in. Repeated rows give repeated results once.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "leaks")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")
    idf, project = latent_space(docs, scratch, settings)
    pieces = scratch.keep(benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null").mapInArrow(_queries, "item_id long, words binary").distinct(), "queries")
    n = pieces.count()
    out = None
    for block in range(max(1, -(-n // settings.query_block))):  # the queries reach every task a bounded block at a time
        part = pieces.where(F.pmod(F.xxhash64("words"), F.lit(max(1, -(-n // settings.query_block)))) == block)
        rows = [(r.item_id, bytes(r.words)) for r in part.orderBy("item_id", "words").collect()]
        if not rows:
            continue
        block_of = spark.sparkContext.broadcast(_Block(rows, idf, project, settings))
        found = docs.mapInArrow(_search(block_of, settings), "doc_id long, item_id long, cover double, answer double, cosine double, start_word long, end_word long")
        out = found if out is None else out.unionByName(found)
    if out is None:
        return spark.createDataFrame([], "doc_id long, item_id long, cover double, answer double, cosine double, start_word long, end_word long")
    best = F.max_by(F.struct("cover", "answer", "cosine", "start_word", "end_word"), F.struct("cover", "answer", "cosine", -F.col("start_word"))).alias("best")
    return out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "best.*")
