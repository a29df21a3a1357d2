"""Substring dedup (operator 4) by compact windows.

Tokens are 5-word shingles. For one hash function, the wide upper nodes of the Cartesian tree over a document's token hashes are its
compact windows: (left, centre, right) stands for every passage inside [left, right] that holds the centre, all of which
have the centre's hash as their minimum. Each passage of at least ``min_words`` words lies in exactly one window of a function, so
two equal passages share a signature under every function, and near-equal ones under most.

A window is filed under its minimum together with the minimum of the half window before its centre, and again with the one after; a
passage of the least length fills one of the two halves. Windows of one signature form a chain in order of document, so n
occurrences give n - 1 pairs. Where a link of a chain fails, the windows of its signature are chained anew by the content of each stretch of the
least length, so what stands between two equal passages never parts them. The windows of a pair of documents are then joined by overlap across all functions into candidate passages,
and these are verified on the documents' own tokens. Equal documents are one document until the end.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.llm import tokens
from lexbridge.llm.graph import components
from lexbridge.llm.scratch import Scratch, small

FUNCTIONS = 3
MINIMA = 4
SHINGLE = 5


def _shingles(batch: pa.RecordBatch, limit: int = tokens.CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """Shingles of documents of at least five words; shorter ones have none here."""
    raw, offsets = tokens.buffers(batch.column("text"))
    for a, b in tokens.chunks(offsets, limit):
        words, bounds, _ = tokens.word_hashes(raw, offsets[a : b + 1])
        s, ends = tokens.shingle_hashes(words, bounds, SHINGLE)
        yield a, b, s, ends, np.diff(bounds)


def _sliding_min(v: np.ndarray, w: int) -> np.ndarray:
    """Minimum of the w values from each place on (fewer at the end)."""
    out, have = v.copy(), 1
    while have < w:
        step = min(have, w - have)
        out[:-step] = np.minimum(out[:-step], out[step:])
        have += step
    return out


def _half_min(v: np.ndarray, ends: np.ndarray, w: int) -> np.ndarray:
    """As :func:`_sliding_min`, but no further than the document's end, so it never depends on which document stands next."""
    out, m = _sliding_min(v, w), np.full(len(ends) - 1, np.iinfo(np.uint64).max, np.uint64)
    for k in range(1, w):
        at = ends[1:] - k
        inside = np.flatnonzero(at >= ends[:-1])
        m[inside] = np.minimum(m[inside], v[at[inside]])
        out[at[inside]] = m[inside]
    return out


def compact_windows(v: np.ndarray, bounds: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(left, centre, right), right inclusive, of all windows at least ``t`` wide; none crosses a document bound.

    Only places that are the minimum of a half window to one side can be centres. Their exact reach within ``t`` sorts out the
    wide nodes; those are an upper part of the Cartesian tree, so one stack over them alone finds the true borders. Of equal
    values the left one counts as smaller.
    """
    n = len(v)
    none = np.zeros(0, np.int64)
    if n < t:
        return none, none, none
    half = t // 2
    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    pad = np.full(half, np.iinfo(np.uint64).max)
    ahead = _sliding_min(v, half)
    behind = _sliding_min(np.concatenate((pad, v)), half)[1 : n + 1]  # of the half values up to each place
    # near a bound the one-sided test would look into the next document; those places are all tried
    low, high = bounds[:-1][doc], bounds[1:][doc] - 1
    place = np.arange(n)
    c = np.flatnonzero((v == ahead) | (v == behind) | (place - low < half) | (high - place < half))
    c = c[(high - low + 1)[c] >= t]
    if not len(c):
        return none, none, none
    keep = []
    fill = np.zeros(t - 1, v.dtype)
    near = np.lib.stride_tricks.sliding_window_view(np.concatenate((fill, v, fill)), t - 1)  # row p: the t - 1 values before place p
    for at in range(0, len(c), 20_000):
        p = c[at : at + 20_000]
        own, row = v[p][:, None], np.arange(len(p))
        reach = []
        for stop, bound in (((near[p] <= own)[:, ::-1], p - low[p]), (near[p + t] < own, high[p] - p)):
            first = stop.argmax(axis=1)
            reach.append(np.minimum(np.where(stop[row, first], first, t - 1), bound))
        keep.append(p[reach[0] + reach[1] + 1 >= t])
    c = np.concatenate(keep)
    left, right = low[c].copy(), high[c].copy()
    stack: list[int] = []
    values, docs = v[c].tolist(), doc[c].tolist()
    for i in range(len(c)):
        while stack and (docs[stack[-1]] != docs[i] or values[stack[-1]] > values[i]):
            j = stack.pop()
            if docs[j] == docs[i]:
                right[j] = c[i] - 1
        if stack:
            left[i] = c[stack[-1]] + 1
        stack.append(i)
    return left, c, right


def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, fp = np.zeros(batch.num_rows, np.int64), np.zeros((2, batch.num_rows), np.uint64)
        for a, b, s, ends, words in _shingles(batch):
            n[a:b] = words
            order = tokens.mix(s ^ tokens.mix((np.arange(len(s)) - np.repeat(ends[:-1], np.diff(ends))).astype(np.uint64)))
            for k, m in enumerate((order, tokens.mix(order ^ np.uint64(0x2545F4914F6CDD1D)))):
                sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(m, dtype=np.uint64)))
                fp[k, a:b] = sums[ends[1:]] - sums[ends[:-1]]
        yield pa.record_batch([batch.column("doc_id"), pa.array(n), pa.array(fp[0].view(np.int64)), pa.array(fp[1].view(np.int64))], names=["doc_id", "n", "fp1", "fp2"])


def _signed(s: np.ndarray, ends: np.ndarray, doc: np.ndarray, t: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(g, left, centre, right) of each function and side."""
    half = t // 2
    for k in range(FUNCTIONS):
        v = tokens.mix(s ^ tokens.mix(np.array([k + 1], np.uint64))[0])
        l, c, r = compact_windows(v, ends, t)  # noqa: E741
        if not len(c):
            continue
        # the halves' minima under the next function; a half ends with its document
        w = tokens.mix(s ^ tokens.mix(np.array([k + 101], np.uint64))[0])
        ahead = _half_min(w, ends, half + 1)
        for side, low in enumerate((ahead[np.maximum(c - half, ends[:-1][doc[c]])], ahead[c])):
            yield tokens.mix(v[c] * np.uint64(3) + tokens.mix(low + np.uint64(2 * k + side))), l, c, r


def _filed(t: int):
    """(g, d, l, c, r): each window twice, under its two signatures."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_numpy()
            for a, b, s, ends, _ in _shingles(batch, 1 << 19):
                doc = np.repeat(np.arange(b - a), np.diff(ends))
                for g, l, c, r in _signed(s, ends, doc, t):  # noqa: E741
                    yield _as_filed(g, ids[a + doc[c]], l, c, r, ends[:-1][doc[c]])

    return run


def _as_filed(g, d, l, c, r, first) -> pa.RecordBatch:  # noqa: E741
    return pa.record_batch([pa.array(g.view(np.int64)), pa.array(d), *[pa.array((x - first).astype(np.int32)) for x in (l, c, r)]], names=["g", "d", "l", "c", "r"])


def _stretch_hashes(s: np.ndarray, t: int) -> np.ndarray:
    """A hash of the t values from each place on, put together from those of half the length."""
    factor = 0x9E3779B97F4A7C15
    out, have = s, 1
    for bit in bin(t)[3:]:
        out, have = out[: len(out) - have] * np.uint64(pow(factor, have, 1 << 64)) + out[have:], 2 * have
        if bit == "1":
            out, have = out[: len(out) - 1] * np.uint64(factor) + s[have:], have + 1
    return out


def _refiled(t: int):
    """(g, d, l, c, r) as :func:`_filed`, of the wanted signatures only, under the content of every stretch of t round a centre, which
    then stands at its start.

    Whoever holds the same stretch stands side by side there, whatever else shares the signature. Minima of the halves under further
    functions are further keys, under which nearly equal stretches meet.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        half = t // 2
        for batch in batches:
            ids, wanted = batch.column("doc_id").to_numpy(), batch.column("signatures")
            for a, b, s, ends, _ in _shingles(batch, 1 << 19):
                if len(s) < t:
                    continue
                doc = np.repeat(np.arange(b - a), np.diff(ends))
                own = wanted.slice(a, b - a)
                # a signature belongs to its own document only
                keys = np.unique(tokens.mix(own.flatten().to_numpy().view(np.uint64)) + np.repeat(np.arange(b - a), own.value_lengths().to_numpy()).astype(np.uint64))
                whole = _stretch_hashes(s, t)
                # every function and side names the same stretches: each is filed once, with the widest reach of the windows that hold it
                lowest, highest = np.full(len(s), len(s)), np.full(len(s), -1)
                minima = [_half_min(tokens.mix(s ^ tokens.mix(np.array([j], np.uint64))[0]), ends, half + 1) for j in range(201, 201 + MINIMA)]
                for g, l, c, r in _signed(s, ends, doc, t):  # noqa: E741
                    here = np.isin(tokens.mix(g) + doc[c].astype(np.uint64), keys)
                    g, l, c, r = g[here], l[here], c[here], r[here]  # noqa: E741
                    if not len(c):
                        continue
                    for i in range(t):
                        fits = (c - i >= l) & (c - i + t - 1 <= r)
                        at = c[fits] - i
                        lowest[at] = np.minimum(lowest[at], l[fits])
                        highest[at] = np.maximum(highest[at], r[fits])
                    d, first = ids[a + doc[c]], ends[:-1][doc[c]]
                    for j, low in enumerate(minima):
                        for side in (np.maximum(c - half, first), c):
                            yield _as_filed(tokens.mix(g + tokens.mix(low[side] + np.uint64(j))), d, l, c, r, first)
                at = np.flatnonzero(highest >= 0)
                if len(at):
                    yield _as_filed(tokens.mix(whole[at]), ids[a + doc[at]], lowest[at], at, highest[at], ends[:-1][doc[at]])

    return run


def _chained(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links inside each signature, from rows sorted by g, d and c: every row of a document with the last row of the document before it,
    and the rows of the first document with the first row of the next. What is carried over is the last document's rows and the one before them."""
    kept, old = None, 0  # the first ``old`` kept rows are linked already
    for batch in batches:
        if not batch.num_rows:
            continue
        if kept is not None:
            batch = pa.Table.from_batches([kept, batch]).combine_chunks().to_batches()[0]
        kept, old = yield from _linked(batch, old, False)
    if kept is not None:
        yield from _linked(kept, old, True)


def _linked(batch: pa.RecordBatch, old: int, end: bool):
    g, d = batch.column("g").to_numpy(), batch.column("d").to_numpy()
    n = len(g)
    starts = np.concatenate(([0], np.flatnonzero((g[1:] != g[:-1]) | (d[1:] != d[:-1])) + 1))
    run = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, n)))
    before = np.maximum(starts - 1, 0)
    has = (starts > 0) & (g[before] == g[starts])
    after = np.append(starts[1:], n - 1)
    last = starts[-1]
    row = np.arange(n if end else last)
    row = row[row >= old]
    back = row[has[run[row]]]
    first = row[~has[run[row]] & (after[run[row]] > row + 1)]  # all but the last row of a first document
    first = first[(g[after[run[first]]] == g[first]) & (run[after[run[first]]] != run[first])]
    a = np.concatenate((before[run[back]], first))
    b = np.concatenate((back, after[run[first]]))
    l, c, r = (batch.column(x).to_numpy() for x in "lcr")  # noqa: E741
    left, right = np.minimum((c - l)[a], (c - l)[b]), np.minimum((r - c)[a], (r - c)[b])
    if len(a):
        yield pa.record_batch([pa.array(g[a]), pa.array(d[a]), pa.array(d[b]), pa.array((c[a] - left).astype(np.int32)), pa.array((c[a] + right).astype(np.int32)), pa.array((c[b] - c[a]).astype(np.int32))], names=["g", "a", "b", "lo", "hi", "shift"])
    at = int(last - 1 if has[-1] else last)
    return batch.slice(at), int(last - at)


def _joined_windows(spans: DataFrame, gap: int) -> DataFrame:
    """Windows of a pair of documents that overlap or lie within ``gap`` become one candidate: (a, b, alo, ahi, blo, bhi)."""
    ordered = F.array_sort(F.collect_set(F.struct("lo", "hi", "shift")))
    start = F.expr("cast(array() as array<struct<lo:int,hi:int,blo:int,bhi:int>>)")

    def step(acc, x):
        last = F.element_at(acc, -1)
        fresh = F.struct(x.lo.alias("lo"), x.hi.alias("hi"), (x.lo + x["shift"]).alias("blo"), (x.hi + x["shift"]).alias("bhi"))
        grown = F.struct(last.lo.alias("lo"), F.greatest(last.hi, x.hi).alias("hi"), F.least(last.blo, x.lo + x["shift"]).alias("blo"), F.greatest(last.bhi, x.hi + x["shift"]).alias("bhi"))
        near = (F.size(acc) > 0) & (x.lo <= last.hi + gap) & (x.lo + x["shift"] <= last.bhi + gap) & (last.blo <= x.hi + x["shift"] + gap)
        return F.when(near, F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(grown))).otherwise(F.concat(acc, F.array(fresh)))

    merged = spans.groupBy("a", "b").agg(ordered.alias("w")).select("a", "b", F.aggregate("w", start, step).alias("m"))
    return merged.select("a", "b", F.inline("m")).select("a", "b", F.col("lo").alias("alo"), F.col("hi").alias("ahi"), "blo", "bhi")


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(pair, side, lo, part): the wanted stretches of each document's shingles, as 32-bit prints."""
    for batch in batches:
        wants, out = batch.column("wants"), []
        for a, b, s, ends, _ in _shingles(batch):
            s = (s >> np.uint64(32)).astype(np.uint32)
            for i in range(b - a):
                own = s[ends[i] : ends[i + 1]]
                for w in wants[a + i].as_py():
                    lo, hi = max(0, w["lo"]), min(len(own), w["hi"] + 1)
                    out.append((w["pair"], w["side"], lo, own[lo:hi].tobytes()))
                if len(out) > 2000:
                    yield _sliced(out)
                    out = []
        if out:
            yield _sliced(out)


def _sliced(out) -> pa.RecordBatch:
    return pa.record_batch([pa.array([o[j] for o in out], t) for j, t in enumerate((pa.int64(), pa.int32(), pa.int32(), pa.binary()))], names=["pair", "side", "lo", "part"])


def _runs(hit: np.ndarray, t: int, miss: int) -> list[tuple[int, int]]:
    """Stretches of t or more, end exclusive, in which a miss is made up for by ``miss`` matches."""
    out, todo = [], [(0, len(hit))]
    score = np.where(hit, 1, -miss)
    while todo:
        lo, hi = todo.pop()
        if hi - lo < t or np.count_nonzero(hit[lo:hi]) * (miss + 1) < t * miss:  # too few hits for any stretch
            continue
        sums = np.concatenate(([0], np.cumsum(score[lo:hi])))
        gain = sums - np.minimum.accumulate(sums)
        e = int(gain.argmax())
        if gain[e] <= 0:
            continue
        b = int(np.flatnonzero(sums[: e + 1] == sums[: e + 1].min())[-1])
        if e - b >= t:
            out.append((lo + b, lo + e))
        todo += [(lo, lo + b), (lo + e, hi)]
    return sorted(out)


def _shares(hit: np.ndarray, t: int, miss: int) -> list[tuple[int, int]]:
    """Stretches of t or more, end exclusive and longest first, whose own share of hits is miss / (miss + 1) or more."""
    out, todo = [], [(0, len(hit))]
    score = np.where(hit, 1, -miss)
    while todo:
        lo, hi = todo.pop()
        if hi - lo < t or np.count_nonzero(hit[lo:hi]) * (miss + 1) < t * miss:  # too few hits for any stretch
            continue
        sums = np.concatenate(([0], np.cumsum(score[lo:hi])))
        # the first place from which the sum up to each end is not negative
        since = np.searchsorted(-np.minimum.accumulate(sums), -sums)
        e = int((np.arange(len(sums)) - since).argmax())
        b = int(since[e])
        if e - b < t:
            continue
        out.append((lo + b, lo + e))
        todo += [(lo, lo + b), (lo + e, hi)]
    return sorted(out, key=lambda r: (r[0] - r[1], r[0]))


def _opposite(x: np.ndarray, hit: np.ndarray, y: np.ndarray, first: np.ndarray, b: int, e: int, t: int) -> list[tuple[int, int]]:
    """Stretches of y that lie as x[b:e] does: by the usual shift of its hits, and from the first of these hits to the last."""
    at = b + np.flatnonzero(hit[b:e])
    to = first[x[at]]
    shift = int(np.median(to - at))
    near = np.abs(to - at - shift) <= t // 4
    out = [(b + shift, e + shift)]
    if near.any():
        out.append((int(to[near].min() - (at[near][0] - b)), int(to[near].max() + e - at[near][-1])))
    out = [(max(0, lo), min(len(y), hi)) for lo, hi in out]
    return [(lo, hi) for lo, hi in out if hi - lo >= t]


def _coded(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """x and y as numbers of their distinct values, and how many these are."""
    values, codes = np.unique(np.concatenate((x, y)), return_inverse=True)
    return codes[: len(x)], codes[len(x) :], len(values)


def _marked(codes: np.ndarray, k: int) -> np.ndarray:
    out = np.zeros(k, dtype=bool)
    out[codes] = True
    return out


def _alike(x: np.ndarray, y: np.ndarray, t: int, similarity: float) -> list[tuple[int, int, int, int, float]]:
    """(start, end, other start, other end, similarity) of the stretches of x that stand in y."""
    return _alike_codes(*_coded(x, y), t, similarity)


def _alike_codes(x: np.ndarray, y: np.ndarray, k: int, t: int, similarity: float) -> list[tuple[int, int, int, int, float]]:
    hit_x, out = _marked(y, k)[x], []
    done, exact = np.zeros(len(x), dtype=bool), len(x) + len(y)
    # equal lengths with a share of 6/7 in common have the similarity 3/4, and neither side may have a lower share than 3/4; the
    # stretch with the best score may be a short part of one that qualifies as a whole, so whole ones are looked at too
    finders = ((_runs, 6), (_runs, exact), (_shares, 6), (_shares, 3))
    runs_y, first = None, None
    for find, miss in finders:
        for b, e in find(hit_x & ~done, t, miss):
            if not (hit_x[b:e] & ~done[b:e]).any():
                continue
            if runs_y is None:
                hit_y = _marked(x, k)[y]
                runs_y = [(yb, ye, own, np.count_nonzero(own)) for yb, ye in sorted({r for f, m in finders for r in f(hit_y, t, m)}) for own in (_marked(y[yb:ye], k),)]
                first = np.full(k, -1)
                first[y[::-1]] = np.arange(len(y) - 1, -1, -1)
            sx = _marked(x[b:e], k)
            size = np.count_nonzero(sx)
            opposite = [(yb, ye, own, np.count_nonzero(own)) for yb, ye in _opposite(x, hit_x, y, first, b, e, t) for own in (_marked(y[yb:ye], k),)]
            best = (0.0, 0, 0)
            for yb, ye, sy, other in [*runs_y, *opposite]:
                most = min(size, other) / max(size, other)
                if most < similarity or most <= best[0]:
                    continue
                both = np.count_nonzero(sx & sy)
                j = both / (size + other - both)
                if j > best[0]:
                    best = (j, yb, ye)
            if best[0] >= similarity:
                done[b:e] = True
                out.append((b, e, best[1], best[2], best[0]))
    return out


def _verified(t: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                x, y, k = _coded(np.frombuffer(row["pa"], np.uint32), np.frombuffer(row["pb"], np.uint32))
                found = _alike_codes(x, y, k, t, similarity)
                left = _marked(x, k)[y]
                for _, _, yb, ye, _ in found:
                    left[yb:ye] = False
                if left.sum() >= similarity * t:  # the other side may hold the passage more than once
                    found += [(xb, xe, b, e, j) for b, e, xb, xe, j in _alike_codes(y, x, k, t, similarity)]
                for b, e, yb, ye, j in found:
                    own = (row["alo"] + b, row["alo"] + e + SHINGLE - 1)
                    other = (row["blo"] + yb, row["blo"] + ye + SHINGLE - 1)
                    out.append((row["a"], *own, row["b"], *other, j))
                    out.append((row["b"], *other, row["a"], *own, j))
            types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64()]
            yield pa.record_batch([pa.array([o[j] for o in out], ty) for j, ty in enumerate(types)], names=["doc_id", "start_word", "end_word", "other_id", "other_start", "other_end", "similarity"])

    return run


def _chain(filed: DataFrame) -> DataFrame:
    return filed.repartition("g").sortWithinPartitions("g", "d", "c").mapInArrow(_chained, "g long, a long, b long, lo int, hi int, shift int")


def _candidates(spans: DataFrame, t: int) -> DataFrame:
    return _joined_windows(spans, t).where(F.col("ahi") - F.col("alo") + 1 >= t // 2).withColumn("pair", F.xxhash64("a", "b", "alo", "ahi", "blo", "bhi"))


def _compared(docs: DataFrame, pairs: DataFrame, t: int, similarity: float, scratch: Scratch) -> DataFrame:
    """What the candidates hold in common, told from both sides."""
    # a changed shingle may end a window inside the passage, so what lies around a candidate is compared as well
    around = lambda lo, hi: ((F.col(lo) - t // 2).alias("lo"), (F.col(hi) + t // 2).alias("hi"))
    wants = pairs.select(F.col("a").alias("doc_id"), F.struct("pair", F.lit(0).alias("side"), *around("alo", "ahi")).alias("w")).unionByName(
        pairs.select(F.col("b").alias("doc_id"), F.struct("pair", F.lit(1).alias("side"), *around("blo", "bhi")).alias("w"))
    )
    wants = scratch.keep(wants.groupBy("doc_id").agg(F.collect_list("w").alias("wants")), "wants")
    cut = docs.join(small(wants.select("doc_id")), "doc_id", "left_semi").join(wants, "doc_id").mapInArrow(_slices, "pair long, side int, lo int, part binary")
    cut = scratch.keep(cut, "slices")
    scratch.drop("wants")
    both = (
        pairs.select("pair", "a", "b")
        .join(cut.where("side = 0").select("pair", F.col("lo").alias("alo"), F.col("part").alias("pa")), "pair")
        .join(cut.where("side = 1").select("pair", F.col("lo").alias("blo"), F.col("part").alias("pb")), "pair")
        .dropDuplicates(["pair"])
    )
    schema = "doc_id long, start_word long, end_word long, other_id long, other_start long, other_end long, similarity double"
    return both.mapInArrow(_verified(t, similarity), schema)


def _classes(told: DataFrame, t: int, scratch: Scratch) -> DataFrame:
    """(doc_id, start_word, end_word, class_doc, class_start) of each told stretch: the first place, by id and start, of all that its links reach.

    Stretches of a document that share half the least length or more are one place.
    """
    own = W.partitionBy("doc_id").orderBy("start_word", "end_word")
    before = F.max("end_word").over(own.rowsBetween(W.unboundedPreceding, -1))
    places = told.select("doc_id", "start_word", "end_word").distinct()
    places = places.withColumn("opens", F.when(before.isNull() | (F.col("start_word") > before - t // 2), F.col("start_word")))
    places = places.withColumn("place", F.max("opens").over(own.rowsBetween(W.unboundedPreceding, 0))).withColumn("node", F.xxhash64("doc_id", "place")).drop("opens")
    places = scratch.keep(places, "places")
    other = places.select(F.col("doc_id").alias("other_id"), F.col("start_word").alias("other_start"), F.col("end_word").alias("other_end"), F.col("node").alias("met"))
    links = told.join(places, ["doc_id", "start_word", "end_word"]).join(other, ["other_id", "other_start", "other_end"]).select("node", "met")
    reached = places.join(components(links, "node", "met", scratch, "classes"), "node")
    first = reached.groupBy("comp").agg(F.min(F.struct("doc_id", "place")).alias("f")).select("comp", F.col("f.doc_id").alias("class_doc"), F.col("f.place").alias("class_start"))
    return reached.join(first, "comp").select("doc_id", "start_word", "end_word", "class_doc", "class_start")


def repeated_passages(docs: DataFrame, min_words: int = 50, similarity: float = 0.75) -> DataFrame:
    """Passages of at least ``min_words`` words that stand, nearly alike, in another document too.

    Returns doc_id, start_word, end_word (words as ``[^\\x20\\x09-\\x0D]+``, end exclusive), other_id, other_start, other_end, similarity (of the
    two passages' shingle sets), class_doc, class_start (the first place of all that are linked with this one; what the chain leaves
    untold between two of its places is told by their class). A passage with n occurrences, any number of them in one document, gives the n - 1 pairs of a chain at least, each told from both sides, or some more where others share a part of it; a document
    equal to others is told once over its whole length, against the smallest id, and that one against the next. A null, empty or shorter text has no passages,
    nor has a row of null id; repeats inside one document are left to line dedup. Rows of one id are one document.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "passages")
    t = min_words - SHINGLE + 1
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")
    prints = scratch.keep(docs.mapInArrow(_prints, "doc_id long, n long, fp1 long, fp2 long").where(F.col("n") >= min_words), "prints")
    classes = prints.groupBy("fp1", "fp2").agg(F.min("doc_id").alias("rep"))
    copies = scratch.keep(prints.join(classes, ["fp1", "fp2"]).where("doc_id != rep").select("doc_id", "rep", "n").distinct(), "copies")
    alone = docs.join(small(copies.select("doc_id").distinct()), "doc_id", "left_anti")
    window = "g long, d long, l int, c int, r int"
    spans = scratch.keep(_chain(alone.mapInArrow(_filed(t), window)), "spans")
    pairs = scratch.keep(_candidates(spans, t), "pairs")
    near = scratch.keep(_compared(docs, pairs, t, similarity, scratch), "near")
    # a link of a signature that nothing verified may part others that are alike: all who share it are filed again, by content
    told = near.select(F.col("doc_id").alias("a"), F.col("other_id").alias("b"), "start_word", "end_word")
    failed = spans.join(told, (spans.a == told.a) & (spans.b == told.b) & (told.start_word <= spans.hi) & (told.end_word > spans.lo), "left_anti").select("g").distinct()
    parted = scratch.keep(spans.groupBy("g").agg(F.count("*").alias("k")).where("k > 1").join(failed, "g").select("g"), "parted")
    members = spans.join(small(parted), "g", "left_semi").select("g", F.explode(F.array("a", "b")).alias("doc_id"))
    members = scratch.keep(members.groupBy("doc_id").agg(F.collect_set("g").alias("signatures")), "members")
    scratch.only("pairs", "near", "members", "copies")
    # only texts that hold a wanted signature move, and they move alike at every size
    held = docs.join(small(members.select("doc_id")), "doc_id", "left_semi").join(members, "doc_id")
    again = _chain(held.mapInArrow(_refiled(t), window)).drop("g").distinct()
    seen = pairs.select("a", "b", F.col("alo").alias("_lo"), F.col("ahi").alias("_hi"), F.col("blo").alias("_blo"), F.col("bhi").alias("_bhi"))
    inside = (F.col("lo") >= F.col("_lo")) & (F.col("hi") <= F.col("_hi")) & (F.col("lo") + F.col("shift") >= F.col("_blo")) & (F.col("hi") + F.col("shift") <= F.col("_bhi"))
    again = again.alias("n").join(seen.alias("s"), (F.col("n.a") == F.col("s.a")) & (F.col("n.b") == F.col("s.b")) & inside, "left_anti")
    more = scratch.keep(_candidates(again, t), "more")
    near = near.unionByName(scratch.keep(_compared(docs, more, t, similarity, scratch), "near-again"))
    told = scratch.keep(near.distinct(), "told")
    scratch.only("told", "copies")
    named = _classes(told, t, scratch)
    zero, whole = F.lit(0).cast("long"), F.col("n")
    first = copies.groupBy("rep").agg(F.min(F.struct("doc_id", "n")).alias("m")).select(F.col("rep").alias("doc_id"), F.col("m.n").alias("n"), F.col("m.doc_id").alias("rep"))
    equal = copies.select("doc_id", "n", "rep").unionByName(first)
    equal = equal.select("doc_id", zero.alias("start_word"), whole.alias("end_word"), F.col("rep").alias("other_id"), zero.alias("other_start"), whole.alias("other_end"), F.lit(1.0).alias("similarity"))
    equal = equal.select("*", F.least("doc_id", "other_id").alias("class_doc"), zero.alias("class_start"))
    return told.join(named, ["doc_id", "start_word", "end_word"]).select(*equal.columns).unionByName(equal)
