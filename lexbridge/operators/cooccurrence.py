"""The co-occurrence provider in one pass: what :func:`lexbridge.operators.attention.cooccurrence_rows` weighs, without a row for each pair of places.

Words are numbered, the most frequent first, and the words whose rows are asked for are dealt to buckets of like size. A map over the sentences
sends each bucket the counts of its words' pairs, added up as far as a task sees them, and each sentence that holds one of its words, once. There the
counts are added up and every row is weighed in place, so the only shuffle is of packed counts and packed sentences. What is told of whole buckets is
made in passes over the numbered sentences, each for its own share of the buckets, and a pass's shuffle is given up before the next one begins.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.operators.attention import DECAY, REACH
from lexbridge.sources.stage import release, stage

#: Places that a bucket should hold, words that are packed at once and cells that are weighed at once.
PER_BUCKET, SLICE, CELLS = 1_500_000, 700_000, 700_000
#: Passes over the sentences at most, and buckets of each pass for every core: a sentence meets nearly all the buckets it ever will, so the shuffle follows the input.
PASSES, PER_CORE = 4, 2
_SENTENCES = "size long, blob binary"
_PACKED = "bucket int, kind int, size long, blob binary"
_FACTS = "domain string, doc_id long, sent_ix int, i int, pivot string, w_a string, w_b string, w_c string, slot int, conf double"
_GRAPH = "domain string, pivot string, slot int, w_a string, w_b string, w_c string, support long, conf double, mean_conf double"
_COUNTS = "domain string, pivot string, n long"
_PROFILE = "domain string, tau double, kept long, n long"
_SUMS = "domain string, doc_id long, sent_ix int, i int, n long, total double, top double"


class _Words:
    """The numbered words, and for each domain how often each stands there and which bucket weighs its rows (-1: none); stop words stand out."""

    def __init__(self, rows: pa.Table, buckets: int, cores: int, most: int):
        named, word = rows.column("domain").combine_chunks().dictionary_encode(), rows.column("word").combine_chunks().dictionary_encode()
        self.domains, distinct = named.dictionary, word.dictionary
        d, w, c = (x.to_numpy(zero_copy_only=False).astype(np.int64) for x in (named.indices, word.indices, rows.column("c").combine_chunks()))
        asked = rows.column("asked").combine_chunks().to_numpy(zero_copy_only=False).astype(bool)
        order = np.argsort(-np.bincount(w, weights=c, minlength=len(distinct)), kind="stable")
        number = np.empty(len(distinct), np.int64)
        number[order] = np.arange(len(distinct))
        self.words = distinct.take(pa.array(order))
        self.count = np.zeros((len(self.domains), len(distinct)), np.uint32)
        self.count[d, number[w]] = c
        self.stop = np.zeros(self.count.shape, bool)
        self.stop[d, number[w]] = rows.column("stop").combine_chunks().to_numpy(zero_copy_only=False).astype(bool)
        places = int(c[asked].sum())
        self.passes = max(1, min(most, -(-places // PER_BUCKET)))
        self.buckets = max(cores * (PER_CORE * self.passes if self.passes > 1 else 1), -(-places // PER_BUCKET)) if buckets == 0 else buckets
        self.bucket = np.full(self.count.shape, -1, np.int16 if self.buckets < 1 << 15 else np.int32)
        rows_of = np.flatnonzero(asked)
        load = [(0, b) for b in range(self.buckets)]
        for r in rows_of[np.argsort(-c[rows_of], kind="stable")].tolist():
            full, b = load[0]
            heapq.heapreplace(load, (full + int(c[r]), b))
            self.bucket[d[r], number[w[r]]] = b


def _planes(x: np.ndarray) -> bytes:
    """Numbers byte by byte: first all lowest bytes, then all next ones."""
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes()


def _unplaned(raw: memoryview, n: int, kind) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * size).reshape(size, n).T).view(kind).ravel()


def _blob(*parts: np.ndarray) -> tuple[int, bytes]:
    raw = b"".join(_planes(x) for x in parts)
    return len(raw), pa.Codec("zstd").compress(raw, asbytes=True)


def _unblob(size: int, blob: bytes, kinds: list) -> list[np.ndarray]:
    """Arrays of one length each, given as (dtype, length)."""
    raw, at, out = memoryview(pa.Codec("zstd").decompress(blob, size, asbytes=True)), 0, []
    for kind, n in kinds:
        out.append(_unplaned(raw[at:], n, kind))
        at += n * np.dtype(kind).itemsize
    return out


def _pair_counts(ids: np.ndarray, sent: np.ndarray, dom: np.ndarray, own: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys (domain, word of an asked row, word near it), sorted, and their counts."""
    keys = []
    for step in range(1, min(REACH, len(ids) - 1) + 1):
        same = sent[step:] == sent[:-step]
        for here, there in ((slice(None, -step), slice(step, None)), (slice(step, None), slice(None, -step))):
            at = same & (own[here] >= 0)
            keys.append((dom[here][at] * width + ids[here][at]) * width + ids[there][at])
    if not keys:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.unique(np.concatenate(keys), return_counts=True)


def _numbered(shared) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            size += len(batch.column("words").flatten())
            if size >= SLICE:
                yield _sentence_blob(pa.Table.from_batches(held).combine_chunks(), shared.value)
                held, size = [], 0
        if held:
            yield _sentence_blob(pa.Table.from_batches(held).combine_chunks(), shared.value)

    return run


def _packed(shared, turn: int, passes: int) -> Callable:
    """What the buckets of one pass get of each blob of sentences."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for size, blob in zip(batch.column("size"), batch.column("blob"), strict=True):
                yield from _slice_blobs(_opened_sentences(size.as_py(), blob.as_py()), shared.value, turn, passes)

    return run


def _row(b: int, kind: int, n: int, blob: bytes) -> pa.RecordBatch:
    return pa.record_batch([pa.array([b], pa.int32()), pa.array([kind], pa.int32()), pa.array([n], pa.int64()), pa.array([blob], pa.binary())], names=["bucket", "kind", "size", "blob"])


def _packed_sentences(doc, known, ix, domain, length, ids) -> tuple[int, bytes]:
    return _blob(np.array([len(doc), len(ids)]), np.diff(doc, prepend=0), known, ix, domain.astype(np.uint16), length.astype(np.uint32), ids.astype(np.uint32))


def _sentence_blob(table: pa.Table, words: _Words) -> pa.RecordBatch:
    lists = table.column("words").combine_chunks()
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
    ids = pc.index_in(lists.flatten(), value_set=words.words).to_numpy(zero_copy_only=False)
    domain = pc.index_in(table.column("domain").combine_chunks(), value_set=words.domains).to_numpy(zero_copy_only=False)
    doc = table.column("doc_id").combine_chunks()
    known = doc.is_valid().to_numpy(zero_copy_only=False).astype(np.uint8)
    doc = doc.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    ix = table.column("sent_ix").combine_chunks().to_numpy(zero_copy_only=False).astype(np.int32)
    size, blob = _packed_sentences(doc, known, ix, domain, lists.value_lengths().to_numpy(zero_copy_only=False), ids)
    return pa.record_batch([pa.array([size]), pa.array([blob], pa.binary())], names=["size", "blob"])


def _slice_blobs(sentences: tuple, words: _Words, turn: int, passes: int) -> Iterator[pa.RecordBatch]:
    doc, known, ix, domain, n, ids = sentences
    sent = np.repeat(np.arange(len(n)), n)
    dom = domain[sent]
    own = words.bucket[dom, ids]
    own = np.where(own % passes == turn, own, -1)
    width, many = len(words.words), words.buckets
    keys, counts = _pair_counts(ids, sent, dom, own, width)
    of = words.bucket.ravel()[keys // width]
    order = np.argsort(of, kind="stable")
    cuts = np.searchsorted(of[order], np.arange(many + 1))
    for b in np.flatnonzero(np.diff(cuts)).tolist():
        at = order[cuts[b] : cuts[b + 1]]
        step = np.diff(keys[at], prepend=0)
        size, blob = _blob(np.array([len(at)]), step, counts[at].astype(np.uint32))
        yield _row(b, 0, size, blob)
    first = np.cumsum(n) - n
    asked = own >= 0
    held = np.unique(own[asked].astype(np.int64) * len(n) + sent[asked])
    cuts = np.searchsorted(held, np.arange(many + 1) * len(n))
    for b in np.flatnonzero(np.diff(cuts)).tolist():
        s = held[cuts[b] : cuts[b + 1]] - b * len(n)
        length = n[s]
        at = np.repeat(first[s] - (np.cumsum(length) - length), length) + np.arange(length.sum())
        size, blob = _packed_sentences(doc[s], known[s], ix[s], domain[s], length, ids[at])
        yield _row(b, 1, size, blob)


def _added(parts: list) -> tuple[np.ndarray, np.ndarray]:
    keys, counts = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    starts = np.flatnonzero(np.diff(keys, prepend=-1))
    return keys[starts], np.add.reduceat(counts, starts)


def _opened_pairs(size: int, blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = (size - 8) // 12
    _, step, counts = _unblob(size, blob, [(np.int64, 1), (np.int64, n), (np.uint32, n)])
    return np.cumsum(step), counts.astype(np.int64)


def _opened_sentences(size: int, blob: bytes) -> tuple:
    raw = pa.Codec("zstd").decompress(blob, size, asbytes=True)
    n, m = _unplaned(memoryview(raw), 2, np.int64).tolist()
    _, doc, known, ix, domain, length, ids = _unblob(size, blob, [(np.int64, 2), (np.int64, n), (np.uint8, n), (np.int32, n), (np.uint16, n), (np.uint32, n), (np.uint32, m)])
    return np.cumsum(doc), known, ix, domain.astype(np.int64), length.astype(np.int64), ids.astype(np.int64)


def _weighed(shared, tell: Callable, merge: Callable | None = None) -> Callable:
    """``tell`` makes the result's rows of what is weighed at once; with ``merge`` they are kept until the bucket ends, and it makes rows of all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = shared.value
        now, parts, keys, counts, held = None, [], None, None, []
        for batch in batches:
            for b, kind, size, blob in zip(*(batch.column(k) for k in range(4)), strict=True):
                b, kind, size, blob = b.as_py(), kind.as_py(), size.as_py(), blob.as_py()
                if b != now:
                    if held:
                        yield merge(words, held)
                    now, parts, keys, counts, held = b, [], None, None, []
                if kind == 0:
                    parts.append(_opened_pairs(size, blob))
                    if len(parts) >= 32:
                        parts = [_added(parts)]
                    continue
                if keys is None:
                    keys, counts = _added(parts) if parts else (np.full(1, -1), np.zeros(1, np.int64))
                    parts = []
                told = _weighed_sentences(words, b, keys, counts, _opened_sentences(size, blob), tell)
                if merge is None:
                    yield from told
                else:
                    held.extend(told)
        if held:
            yield merge(words, held)

    return run


def _weighed_sentences(words: _Words, b: int, keys: np.ndarray, counts: np.ndarray, sentences: tuple, tell: Callable) -> Iterator:
    doc, known, ix, domain, length, ids = sentences
    width = len(words.words)
    start = np.cumsum(length) - length
    sent = np.repeat(np.arange(len(length)), length)
    place = np.flatnonzero((words.bucket[domain[sent], ids] == b) & (length[sent] > 1))
    row = domain[sent[place]] * width + ids[place]
    place = place[np.argsort(row, kind="stable")]  # rows of one word look up the same stretch of the table
    ends = np.cumsum(length[sent[place]])
    at = 0
    far = np.exp(-DECAY * np.arange(length.max() if len(length) else 1))
    while at < len(place):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + CELLS, side="right")))
        p = place[at:to]
        at = to
        s = sent[p]
        n, first = length[s], start[s]
        heads = np.cumsum(n) - n
        own = np.repeat(np.arange(len(p)), n)
        j = np.arange(len(own)) - heads[own]
        i = p - first
        other = ids[first[own] + j]
        row = domain[s] * width + ids[p]
        key = row[own] * width + other
        found = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
        together = np.where(keys[found] == key, counts[found], 0)
        c = words.count.ravel()
        base = c[row][own].astype(np.int64) * c[domain[s][own] * width + other]
        t = (1 + together) / np.sqrt(base) * far[np.abs(i[own] - j)]
        itself = heads + i
        t[itself] = 0.0
        a = t / np.add.reduceat(t, heads)[own]
        yield tell(words, p, s, (doc, known, ix, domain), i, n, first, ids, heads, own, j, itself, a)


def _named(s, told, words: _Words) -> list[pa.Array]:
    doc, known, ix, domain = told
    return [words.domains.take(pa.array(domain[s])).cast(pa.string()), pa.array(doc[s], mask=known[s] == 0), pa.array(ix[s])]


def _tell_sums(words, p, s, told, i, n, first, ids, heads, own, j, itself, a) -> pa.RecordBatch:
    total, top = np.add.reduceat(a, heads), np.maximum.reduceat(a, heads)
    return pa.record_batch([*_named(s, told, words), pa.array(i.astype(np.int32)), pa.array(n - 1), pa.array(total), pa.array(top)], names=[x.split()[0] for x in _SUMS.split(", ")])


def _best(r: np.ndarray, heads: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The greatest value of each row, and its first cell."""
    most = np.maximum.reduceat(r, heads)
    cells = np.flatnonzero(r == most[own])
    return most, cells[np.searchsorted(cells, heads)]


def _facts(p, s, domain, i, n, first, ids, heads, own, j, itself, a) -> tuple[np.ndarray, ...]:
    """Which places have a fact, and these facts: domain, pivot, slot, the three words and the confidence."""
    r = np.round(a, 9)
    r[itself] = -1.0
    one, x = _best(r, heads, own)
    r[x] = -1.0
    r[itself] = -2.0
    two, y = _best(r, heads, own)
    whole = n > 2  # a sentence of two words has no second neighbour
    lo, hi = np.minimum(j[x], j[y]), np.maximum(j[x], j[y])
    slot = (i > lo).astype(np.int64) + (i > hi)
    three = [ids[(first + k)[whole]] for k in np.sort(np.stack((i, lo, hi)), axis=0)]
    return whole, domain[s][whole], ids[p][whole], slot[whole], *three, (one + two)[whole]


def _tell_facts(words, p, s, told, i, n, first, ids, heads, own, j, itself, a) -> pa.RecordBatch:
    whole, _, pivot, slot, *three, conf = _facts(p, s, told[3], i, n, first, ids, heads, own, j, itself, a)
    named = [words.words.take(pa.array(k)).cast(pa.string()) for k in (pivot, *three)]
    cols = [*_named(s[whole], told, words), pa.array(i[whole].astype(np.int32)), *named, pa.array(slot.astype(np.int32)), pa.array(conf)]
    return pa.record_batch(cols, names=[x.split()[0] for x in _FACTS.split(", ")])


def _kept(tau: float) -> Callable:
    def tell(words, p, s, told, i, n, first, ids, heads, own, j, itself, a) -> tuple[np.ndarray, ...]:
        _, domain, pivot, slot, *three, conf = _facts(p, s, told[3], i, n, first, ids, heads, own, j, itself, a)
        good = np.round(conf, 9) >= tau
        for k in three:
            good &= ~words.stop[domain, k]
        return tuple(x[good] for x in (domain, pivot, slot, *three, conf))

    return tell


def _merged(words, held: list) -> pa.RecordBatch:
    """One row for each distinct fact; all of a pivot's facts lie in its bucket."""
    *fact, conf = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.lexsort(fact[::-1])
    fact, conf = [x[order] for x in fact], conf[order]
    new = np.ones(len(conf), bool)
    new[1:] = np.logical_or.reduce([x[1:] != x[:-1] for x in fact])
    starts = np.flatnonzero(new)
    support = np.diff(np.append(starts, len(conf)))
    total, most = (f.reduceat(conf, starts) if len(starts) else conf for f in (np.add, np.maximum))
    domain, pivot, slot, *three = (x[starts] for x in fact)
    named = [words.words.take(pa.array(k)).cast(pa.string()) for k in (pivot, *three)]
    cols = [words.domains.take(pa.array(domain)).cast(pa.string()), named[0], pa.array(slot.astype(np.int32)), *named[1:], pa.array(support), pa.array(most), pa.array(total / support)]
    return pa.record_batch(cols, names=[x.split()[0] for x in _GRAPH.split(", ")])


def _counting(tau: float) -> Callable:
    """Of each kept fact, its domain and pivot."""
    kept = _kept(tau)
    return lambda *weighed: kept(*weighed)[:2]


def _counted(words, held: list) -> pa.RecordBatch:
    domain, pivot = (np.concatenate(x) for x in zip(*held, strict=True))
    keys, n = np.unique(domain * len(words.words) + pivot, return_counts=True)
    domain, pivot = keys // len(words.words), keys % len(words.words)
    return pa.record_batch([words.domains.take(pa.array(domain)).cast(pa.string()), words.words.take(pa.array(pivot)).cast(pa.string()), pa.array(n)], names=["domain", "pivot", "n"])


def _profile(taus: list[float]) -> tuple[Callable, Callable]:
    def tell(words, p, s, told, i, n, first, ids, heads, own, j, itself, a) -> np.ndarray:
        _, domain, _, _, *_, conf = _facts(p, s, told[3], i, n, first, ids, heads, own, j, itself, a)
        conf = np.round(conf, 9)
        count = lambda good: np.bincount(domain[good], minlength=len(words.domains))
        return np.stack([count(conf >= t) for t in taus] + [count(np.ones(len(conf), bool))])

    def merge(words, held: list) -> pa.RecordBatch:
        sums = np.sum(held, axis=0)
        d = np.flatnonzero(sums[-1])
        cols = [pa.array(np.repeat(words.domains.take(pa.array(d)).to_numpy(zero_copy_only=False), len(taus)), pa.string()), pa.array(np.tile(np.array(taus, float), len(d)))]
        return pa.record_batch([*cols, pa.array(sums[:-1, d].T.ravel()), pa.array(np.repeat(sums[-1, d], len(taus)))], names=["domain", "tau", "kept", "n"])

    return tell, merge


def _run(sents: DataFrame, pool_words: DataFrame, tell: Callable, schema: str, buckets: int, stop: DataFrame | None = None, merge: Callable | None = None, fold: Callable | None = None) -> DataFrame:
    """With ``merge``, the buckets are weighed in passes; ``fold`` is applied to what each pass tells before that is written."""
    spark = sents.sparkSession
    single = sents.select("domain", F.explode("words").alias("word")).groupBy("domain", "word").agg(F.count("*").alias("c"))
    asked = F.broadcast(pool_words.select("domain", "word").distinct().withColumn("asked", F.lit(True)))
    none = F.lit(False)
    rows = single.join(asked, ["domain", "word"], "left")
    rows = rows.withColumn("stop", none) if stop is None else rows.join(F.broadcast(stop.select("domain", "word").distinct().withColumn("stop", F.lit(True))), ["domain", "word"], "left")
    rows = rows.select("domain", "word", "c", F.coalesce("asked", none).alias("asked"), F.coalesce("stop", none).alias("stop"))
    words = _Words(rows.toArrow(), buckets, spark.sparkContext.defaultParallelism, 1 if merge is None else PASSES)
    del rows, single  # their shuffles too
    passes, many = words.passes, words.buckets
    shared = spark.sparkContext.broadcast(words)
    told = sents.select("domain", F.col("doc_id").cast("long").alias("doc_id"), "sent_ix", "words").mapInArrow(_numbered(shared), _SENTENCES)
    told = stage(told, "sentences") if passes > 1 else told

    def weighed(turn: int) -> DataFrame:
        packed = told.mapInArrow(_packed(shared, turn, passes), _PACKED)
        dealt = packed.repartitionById(-(-many // passes), (F.col("bucket") / passes).cast("int")).sortWithinPartitions("bucket", "kind")
        out = dealt.mapInArrow(_weighed(shared, tell, merge), schema)
        return out if fold is None else fold(out)

    if passes == 1:
        return weighed(0)
    out = None
    for turn in range(passes):
        release(spark)
        part = stage(weighed(turn), f"pass-{turn}")
        out = part if out is None else out.unionByName(part)
    release(spark)
    return out


def cooccurrence_facts(sents: DataFrame, pool_words: DataFrame, buckets: int = 0) -> DataFrame:
    """What :func:`lexbridge.operators.facts.make_facts` makes of the co-occurrence rows; ``buckets`` of 0 follows the number of places."""
    return _run(sents, pool_words, _tell_facts, _FACTS, buckets)


def cooccurrence_graph(sents: DataFrame, pool_words: DataFrame, tau: float, stop: DataFrame | None = None, buckets: int = 0, fold: Callable | None = None) -> DataFrame:
    """The facts of at least ``tau`` without stop words, merged as :func:`lexbridge.operators.facts.merge_facts` does, where they are weighed.

    ``fold`` turns merged facts of some pivots into the rows that are wanted of them.
    """
    return _run(sents, pool_words, _kept(tau), _GRAPH, buckets, stop, _merged, fold)


def cooccurrence_counts(sents: DataFrame, pool_words: DataFrame, tau: float, stop: DataFrame | None = None, buckets: int = 0) -> DataFrame:
    """(domain, pivot, n): how many facts of at least ``tau`` without stop words each pivot has, counted where they are weighed."""
    return _run(sents, pool_words, _counting(tau), _COUNTS, buckets, stop, _counted)


def cooccurrence_profile(sents: DataFrame, pool_words: DataFrame, taus: list[float], buckets: int = 0) -> DataFrame:
    """What :func:`lexbridge.operators.facts.confidence_profile` makes of the facts, counted where they are weighed."""
    tell, merge = _profile(taus)
    parts = _run(sents, pool_words, tell, _PROFILE, buckets, None, merge)
    sums = parts.groupBy("domain", "tau").agg(F.sum("kept").alias("kept"), F.sum("n").alias("n"))
    return sums.select("domain", "tau", "kept", (F.col("kept") / F.col("n")).alias("share"))


def cooccurrence_sums(sents: DataFrame, pool_words: DataFrame, buckets: int = 0) -> DataFrame:
    """(domain, doc_id, sent_ix, i, n, total, top): each co-occurrence row's number of weights, their sum and the greatest."""
    return _run(sents, pool_words, _tell_sums, _SUMS, buckets)
