"""N-gram Jaccard join (operator 3): a blocked sparse product of the document by shingle incidence.

Every document is a set of distinct 5-word shingles. Two link when ``100 * overlap >= 75 * union``, that is
``7 * overlap >= 3 * (n_a + n_b)`` at the default. The join is exact:

1. one pass makes each set's size and 128-bit print, and a fixed-size table of how many documents hold a shingle of
   each hash bucket, over all documents. Equal sets fall together; the smallest id speaks for its class.
2. shingles are put in one global order, rarely used buckets first. If two sets link, they share a shingle among the first
   ``n - ceil(t * n) + 1`` of each (the size-derived bound), so only those entries of the matrix are multiplied.
   The bucket table decides the order and nothing else: a collision there costs time and never a link.
3. rows of the product are formed shingle by shingle. First every document meets one leader of each shingle's column,
   then a few neighbours in a random order of the column, so a column of m documents gives a few times m pairs a round; columns
   whose documents are already in one component leave. Only wide columns need those rounds. What is left is multiplied out between
   components, as far as positions allow. A pair goes on only if sizes, positions and the counted overlap of
   the first entries still allow enough, and is then verified on the two whole sets.

Links inside one component need not be listed, so groups of thousands of copies cost a few pairs per copy.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.llm import tables, tokens
from lexbridge.llm.graph import components
from lexbridge.llm.scratch import Scratch, small

SKETCH_BITS = 20
#: One round of leaders and then chains, before what is left is multiplied out: as long as one pair in ``WORTH`` of a chain links, at most so many.
ROUNDS = 12
WORTH = 50
#: Columns of so many documents take part in those rounds.
WIDE = 16
#: Neighbours that a document meets in a column's order, in the first chain, the second and later ones, which have fewer open pairs.
NEIGHBOURS = (4, 8, 32)
#: A set's bitmap, 64 bits each.
BITS = ("x0", "x1", "x2", "x3")
POST = ("h", "d", "n", "pos", "bits")


def _sets(batch: pa.RecordBatch, k: int) -> Iterator[tuple[int, np.ndarray]]:
    for a, b, words, bounds, _ in tokens.documents_of(batch):
        s, ends = tokens.shingle_hashes(words, bounds, k)
        for i in range(b - a):
            yield a + i, np.unique(s[ends[i] : ends[i + 1]])


def _bucket(h: np.ndarray) -> np.ndarray:
    return (h & np.uint64((1 << SKETCH_BITS) - 1)).astype(np.int64)


def _prints(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.zeros(1 << SKETCH_BITS, dtype=np.int64)
        names = ["doc_id", "n", "fp1", "fp2", *BITS, "part", "blob"]
        for batch in batches:
            n, fp1, fp2 = (np.zeros(batch.num_rows, dtype=t) for t in (np.int32, np.uint64, np.uint64))
            bits = np.zeros((batch.num_rows, 64 * len(BITS)), dtype=bool)
            held, size = [], 0
            for i, s in _sets(batch, k):
                n[i] = len(s)
                bits[i, (s >> np.uint64(40)).astype(np.int64) % bits.shape[1]] = True
                fp1[i] = np.add.reduce(tokens.mix(s), dtype=np.uint64)
                fp2[i] = np.add.reduce(tokens.mix(s ^ np.uint64(0x5851F42D4C957F2D)), dtype=np.uint64)
                held.append(_bucket(s))
                size += len(s)
                if size > 1_000_000:
                    table += np.bincount(np.concatenate(held), minlength=len(table))
                    held, size = [], 0
            if held:
                table += np.bincount(np.concatenate(held), minlength=len(table))
            none = pa.nulls(batch.num_rows)
            packed = np.packbits(bits, axis=1).view(np.int64)
            maps = [pa.array(np.ascontiguousarray(packed[:, j])) for j in range(len(BITS))]
            yield pa.record_batch([batch.column("doc_id"), pa.array(n), pa.array(fp1.view(np.int64)), pa.array(fp2.view(np.int64)), *maps, none.cast(pa.int32()), none.cast(pa.binary())], names=names)
        for part, blob in tables.pieces(table):
            empty = [pa.array([None], pa.int64()) for _ in BITS]
            yield pa.record_batch([pa.array([None], pa.int64()), pa.array([None], pa.int32()), pa.array([None], pa.int64()), pa.array([None], pa.int64()), *empty, pa.array([part], pa.int32()), pa.array([blob], pa.binary())], names=names)

    return run


def _levels(pieces: DataFrame) -> np.ndarray:
    """How over-used each bucket is, in powers of two: 0 for the ordinary ones. One megabyte whatever the input."""
    table = tables.add_up(pieces, np.zeros(1 << SKETCH_BITS, dtype=np.int64))
    mean = table.mean()
    usual = mean + 8 * np.sqrt(mean) + 16
    return np.ceil(np.log2(np.maximum(table / usual, 1))).astype(np.uint8)


def _entries(k: int, t: Fraction, levels):
    """The first entries of each set in the global order: (h, d, n, pos)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = levels.value
        for batch in batches:
            ids = batch.column("doc_id").to_numpy()
            hs, ds, ns, ps, size = [], [], [], [], 0
            for i, s in _sets(batch, k):
                if not len(s):
                    continue
                lead = len(s) - -(-t.numerator * len(s) // t.denominator) + 1
                first = s[np.argsort(level[_bucket(s)], kind="stable")[:lead]]
                hs.append(first)
                ds.append(np.full(lead, ids[i]))
                ns.append(np.full(lead, len(s), np.int32))
                ps.append(np.arange(lead, dtype=np.int32))
                size += lead
                if size > 100_000:
                    yield _packed(hs, ds, ns, ps)
                    hs, ds, ns, ps, size = [], [], [], [], 0
            if size:
                yield _packed(hs, ds, ns, ps)

    return run


def _packed(hs, ds, ns, ps) -> pa.RecordBatch:
    return pa.record_batch([pa.array(np.concatenate(hs).view(np.int64)), pa.array(np.concatenate(ds)), pa.array(np.concatenate(ns)), pa.array(np.concatenate(ps))], names=["h", "d", "n", "pos"])


def _rest(t: Fraction) -> str:
    """What ``o`` shared first entries must allow: past its first entries a set can add no more than what is left of it."""
    p, q = t.numerator, t.denominator
    left = lambda n: f"(({p} * {n} + {q - 1}) div {q} - 1)"
    return f"{p + q} * (o + greatest({left('na')}, {left('nb')})) >= {p} * (na + nb)"


def _whole_sets(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, own, held, size = batch.column("doc_id").to_numpy(), [], [], 0
            for i, s in _sets(batch, k):
                own.append(ids[i])
                held.append(s.view(np.int64))
                size += len(s)
                if size > 200_000:
                    yield _listed(own, held)
                    own, held, size = [], [], 0
            if own:
                yield _listed(own, held)

    return run


def _listed(own, held) -> pa.RecordBatch:
    ends = np.concatenate(([0], np.cumsum([len(s) for s in held]))).astype(np.int32)
    return pa.record_batch([pa.array(own, pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(held)))], names=["doc_id", "s"])


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Marks the rows whose shingle another row holds as well. Rows come sorted by h; only the last row is kept back."""
    kept, hot_tail = None, False
    for batch in batches:
        if not batch.num_rows:
            continue
        if kept is not None:
            batch = pa.Table.from_batches([kept, batch]).combine_chunks().to_batches()[0]
        h = batch.column("h").to_numpy()
        same = h[1:] == h[:-1]
        twin = np.zeros(len(h), dtype=bool)
        twin[1:] |= same
        twin[:-1] |= same
        twin[0] |= kept is not None and hot_tail
        kept, hot_tail = batch.slice(len(h) - 1), bool(twin[-1])
        yield batch.slice(0, len(h) - 1).filter(pa.array(twin[:-1]))
    if kept is not None and hot_tail:
        yield kept


def _room(t: Fraction) -> str:
    """What sizes and positions must allow for a pair (a, b) to link: overlap * (p + q) >= p * (na + nb) for t = p / q."""
    p, q = t.numerator, t.denominator
    return f"{q} * least(na, nb) >= {p} * greatest(na, nb) and {p + q} * (1 + least(na - pa, nb - pb) - 1) >= {p} * (na + nb)"


def _bitmaps_allow(t: Fraction) -> str:
    """What the bitmaps of a pair allow: a bit that only one of them has stands for a shingle that the other set lacks."""
    p, q = t.numerator, t.denominator
    lacks = lambda one, other: " + ".join(f"bit_count({one}.{x} & ~{other}.{x})" for x in BITS)
    return f"{p + q} * least(n - ({lacks('bits', 'bits2')}), n2 - ({lacks('bits2', 'bits')})) >= {p} * (n + n2)"


def link_components(docs: DataFrame, k: int = 5, threshold: Fraction = Fraction(3, 4)) -> DataFrame:
    """Groups documents by shingle-set links.

    ``docs`` has ``doc_id`` and ``text`` (others are left alone). Returns doc_id, n_shingles, component_id, one row per
    input row. A null or blank text has an empty set and stands alone; so does a row of null id, whose component is null.
    Repeated ids come back once per row; different texts of one id link for the id they share. ``threshold`` must exceed 0.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "jaccard")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    maps = "".join(f"{x} long, " for x in BITS)
    first = scratch.keep(docs.mapInArrow(_prints(k), f"doc_id long, n int, fp1 long, fp2 long, {maps}part int, blob binary"), "prints")
    prints = first.where("part is null").select("doc_id", "n", "fp1", "fp2", F.struct(*BITS).alias("bits"))
    sole = prints.where("n > 0 and doc_id is not null").groupBy("doc_id").agg(F.min(F.struct("fp1", "fp2")).alias("lo"), F.max(F.struct("fp1", "fp2")).alias("hi"))
    several = scratch.keep(sole.where("lo != hi").select(F.col("doc_id").alias("id")), "several")
    if not several.isEmpty():
        return _with_several_texts(docs, several, k, threshold, scratch)
    levels = spark.sparkContext.broadcast(_levels(first.where("part is not null").select("part", "blob")))
    classes = scratch.keep(prints.where("n > 0 and doc_id is not null").groupBy("fp1", "fp2").agg(F.min("doc_id").alias("rep"), F.first("bits").alias("bits")), "classes")

    spare = scratch.keep(prints.where("n > 0").join(classes, ["fp1", "fp2"]).where("doc_id != rep").select("doc_id").distinct(), "spare")
    entries = docs.where("doc_id is not null").join(small(spare), "doc_id", "left_anti").mapInArrow(_entries(k, threshold, levels), "h long, d long, n int, pos int")
    held = entries.repartition("h").sortWithinPartitions("h").mapInArrow(_shared, "h long, d long, n int, pos int")
    posts = scratch.keep(held, "posts-0")
    # each document's entries that another document shares: a small part of its first ones
    lists = scratch.keep(posts.groupBy("d").agg(F.first("n").alias("n"), F.collect_set("h").alias("hs")), "lists")
    maps = lists.select("d").join(classes.select(F.col("rep").alias("d"), "bits"), "d")
    posts = scratch.keep(posts.join(maps, "d").select(*POST), "posts")
    scratch.drop("posts-0")

    room, allow = _room(threshold), _bitmaps_allow(threshold)
    at_place = room
    for new, old in (("na", "n"), ("nb", "n2"), ("pa", "pos"), ("pb", "pos2")):
        at_place = re.sub(rf"\b{new}\b", old, at_place)
    sides = [F.least("d", "d2").alias("a"), F.greatest("d", "d2").alias("b"), F.col("n").alias("na"), F.col("n2").alias("nb"), F.col("pos").alias("pa"), F.col("pos2").alias("pb")]
    edges, tested, comps = None, None, None
    wide = posts.groupBy("h").agg(F.count("*").alias("m")).where(F.col("m") >= WIDE).select("h")
    wide = scratch.keep(posts.join(wide, "h", "left_semi").withColumn("comp", F.col("d")), "wide-0")
    for turn in range(ROUNDS):
        if turn:
            wide = scratch.keep(_open_columns(wide, comps), f"wide-{turn}")
        if wide.isEmpty():
            break
        if turn == 0:
            lead = wide.groupBy("h").agg(F.min(F.struct(F.xxhash64("d").alias("o"), "d", "n", "pos", "comp", "bits")).alias("l"))
            met = wide.join(lead, "h")
        else:
            order = W.partitionBy("h").orderBy(F.xxhash64("d", "h", F.lit(turn)), "d")
            near = F.array(*[F.lag(F.struct("d", "n", "pos", "comp", "bits"), i).over(order) for i in range(1, NEIGHBOURS[min(turn, len(NEIGHBOURS)) - 1] + 1)])
            # a neighbour is tested where it stands, so only pairs that sizes, positions and bitmaps allow become rows
            fits = re.sub(r"\b(d|n|pos|comp|bits)2\b", r"l.\1", f"comp != comp2 and d != d2 and {at_place} and {allow}")
            met = wide.withColumn("near", near).select("*", F.explode(F.expr(f"filter(near, l -> l is not null and {fits})")).alias("l"))
        met = met.select("d", "n", "pos", "comp", "bits", *[F.col(f"l.{x}").alias(f"{x}2") for x in ("d", "n", "pos", "comp", "bits")])
        pairs = met.where("comp != comp2 and d != d2").where(allow).select(*sides).where(room).select("a", "b").distinct()
        pairs = scratch.keep(pairs if tested is None else pairs.join(tested, ["a", "b"], "left_anti"), f"pairs-{turn}")
        tested = pairs if tested is None else tested.unionByName(pairs)
        found = _verified(docs, pairs, lists, k, threshold, scratch, turn)
        edges = found if edges is None else edges.unionByName(found)
        comps = components(edges, "a", "b", scratch, f"components-{turn}")
        if turn and found.count() * WORTH < pairs.count():
            break
    rest = scratch.keep(_open_columns(posts, comps), "open") if comps is not None else posts.withColumn("comp", F.col("d"))
    other = rest.select("h", *[F.col(x).alias(f"{x}2") for x in ("d", "n", "pos", "comp", "bits")])
    met = rest.join(other, "h").where(F.expr("d < d2 and comp != comp2") & F.expr(at_place) & F.expr(allow))
    pairs = met.select(*sides).select("a", "b").distinct()
    pairs = scratch.keep(pairs if tested is None else pairs.join(tested, ["a", "b"], "left_anti"), "pairs-rest")
    found = _verified(docs, pairs, lists, k, threshold, scratch, ROUNDS)
    edges = found if edges is None else edges.unionByName(found)
    comps = components(edges, "a", "b", scratch, "components")
    scratch.only("prints", "classes", "components")
    tagged = classes.join(comps, classes.rep == comps.node, "left").select("fp1", "fp2", F.coalesce("comp", "rep").alias("component_id"))
    return prints.join(tagged, ["fp1", "fp2"], "left").select(
        "doc_id", F.col("n").cast("long").alias("n_shingles"), F.when((F.col("n") > 0) & F.col("doc_id").isNotNull(), F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id")
    )


def _with_several_texts(docs: DataFrame, several: DataFrame, k: int, threshold: Fraction, scratch: Scratch) -> DataFrame:
    """:func:`link_components` where some ids stand for several texts.

    Each text of such an id is joined under a number of its own, a hash of id and text, and the components that one id touches are one.
    """
    named = docs.join(small(several), F.col("doc_id") == F.col("id"), "left")
    own = F.when(F.col("id").isNotNull(), F.xxhash64("doc_id", "text")).otherwise(F.col("doc_id"))
    owners = scratch.keep(named.where("id is not null").select(own.alias("number"), F.col("id").alias("owner")).distinct(), "owners")
    found = scratch.keep(link_components(named.select(own.alias("doc_id"), "text"), k, threshold), "texts")
    whole = found.join(small(owners), F.col("doc_id") == F.col("number"), "left").select(F.col("component_id").alias("c"), "n_shingles", "owner", F.coalesce("owner", "doc_id").alias("doc_id"))
    whole = scratch.keep(whole, "whole")
    touched = whole.where("owner is not null and n_shingles > 0").groupBy("owner").agg(F.min("c").alias("lo"))
    edges = whole.where("n_shingles > 0").join(touched, "owner").select("c", "lo").where("c != lo").distinct()
    merged = components(edges, "c", "lo", scratch, "merged")
    whole = whole.join(merged, F.col("c") == F.col("node"), "left").withColumn("c", F.coalesce("comp", "c"))
    least = whole.where("doc_id is not null and n_shingles > 0").groupBy(F.col("c").alias("root")).agg(F.min("doc_id").alias("component_id"))
    return whole.join(least, (F.col("c") == F.col("root")) & (F.col("n_shingles") > 0), "left").select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def _open_columns(posts: DataFrame, comps: DataFrame) -> DataFrame:
    """The entries of columns that still touch several components, with each entry's component."""
    named = posts.drop("comp").join(comps, F.col("d") == F.col("node"), "left").select(*POST, F.coalesce("comp", "d").alias("comp"))
    still = named.groupBy("h").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo != hi").select("h")
    return named.join(still, "h", "left_semi")


def _verified(docs: DataFrame, pairs: DataFrame, lists: DataFrame, k: int, t: Fraction, scratch: Scratch, turn: int) -> DataFrame:
    """The pairs that link. The overlap of their first entries, which is known in full, sorts out most others before whole sets are moved."""
    left, right = lists.select(F.col("d").alias("a"), F.col("n").alias("na"), F.col("hs").alias("ha")), lists.select(F.col("d").alias("b"), F.col("n").alias("nb"), F.col("hs").alias("hb"))
    near = pairs.join(left, "a").join(right, "b").withColumn("o", F.size(F.array_intersect("ha", "hb"))).where(_rest(t)).select("a", "b")
    near = scratch.keep(near, f"near-{turn}")
    ids = scratch.keep(near.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), f"ids-{turn}")
    sets = scratch.keep(docs.join(small(ids), "doc_id", "left_semi").mapInArrow(_whole_sets(k), "doc_id long, s array<long>").dropDuplicates(["doc_id"]), f"sets-{turn}")
    left, right = sets.select(F.col("doc_id").alias("a"), F.col("s").alias("sa")), sets.select(F.col("doc_id").alias("b"), F.col("s").alias("sb"))
    both = near.join(left, "a").join(right, "b")
    common = F.size(F.array_intersect("sa", "sb"))
    links = both.where((t.numerator + t.denominator) * common >= t.numerator * (F.size("sa") + F.size("sb"))).select("a", "b")
    out = scratch.keep(links, f"edges-{turn}")
    scratch.drop(f"sets-{turn}", f"near-{turn}", f"ids-{turn}")
    return out
