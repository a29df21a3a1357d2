"""Embedding near-dedup (operator 8): cross-polytope hashing after fast Hadamard rotations, with multiprobe buckets.

Equal vectors of one label are a class with its count. A class's hash in a table joins ``hashes`` cross-polytope codes: the axis, with
its sign, that lies nearest after three rounds of random signs and a fast Hadamard transform. A class stands in its home bucket and looks
into the buckets of its next-likeliest codes; pairs that meet are made distinct and verified by cosine in double precision. Links
weigh by class counts, so copies are never paired with each other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lexbridge.llm.graph import components
from lexbridge.llm.scratch import Scratch


def hadamard(x: np.ndarray) -> np.ndarray:
    """The Walsh-Hadamard transform of each row, unscaled; the width is a power of two."""
    n, p = x.shape
    h = 1
    while h < p:
        x = x.reshape(n, p // (2 * h), 2, h)
        x = np.stack((x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]), axis=2).reshape(n, p)
        h *= 2
    return x


def _codes(x: np.ndarray, seed: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best and second code of each row, and how much is lost with the second."""
    p = x.shape[1]
    signs = np.random.default_rng(seed).choice([-1.0, 1.0], size=(3, p))
    for s in signs:
        x = hadamard(x * s) / np.sqrt(p)
    size = np.abs(x)
    top = np.argpartition(-size, 1, axis=1)[:, :2] if p > 1 else np.zeros((len(x), 2), int)
    rows = np.arange(len(x))
    swap = size[rows, top[:, 0]] < size[rows, top[:, 1]]
    top[swap] = top[swap][:, ::-1]
    code = lambda j: 2 * j + (x[rows, j] < 0)
    return code(top[:, 0]), code(top[:, 1]), size[rows, top[:, 0]] - size[rows, top[:, 1]]


def _bucket_rows(tables: int, hashes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1000):
                batch = whole.slice(at, 1000)
                ids, vecs = batch.column("cid").to_numpy(), batch.column("v").to_pylist()
                dims = np.array([len(v) for v in vecs])
                for d in np.unique(dims):
                    own = np.flatnonzero(dims == d)
                    p = 1 << max(1, int(d - 1).bit_length())
                    x = np.zeros((len(own), p))
                    x[:, :d] = [vecs[i] for i in own]
                    x /= np.abs(x).max(axis=1, keepdims=True)
                    x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
                    for t in range(tables):
                        best, second, loss = zip(*[_codes(x, (t, h, int(p))) for h in range(hashes)], strict=True)
                        home = np.zeros(len(own), np.int64)
                        for h in range(hashes):
                            home = home * (2 * p) + best[h]
                        keys, base = [home], np.int64(2 * p)
                        for h in range(hashes):  # one code exchanged for its second choice
                            keys.append(home + (second[h] - best[h]) * base ** (hashes - 1 - h))
                        both = home.copy()  # the two cheapest exchanges together
                        if hashes > 1:
                            cheap = np.argsort(np.stack(loss), axis=0)[:2]
                            for h in range(hashes):
                                both = both + ((cheap == h).any(axis=0)) * (second[h] - best[h]) * base ** (hashes - 1 - h)
                            keys.append(both)
                        for k, key in enumerate(keys):
                            yield pa.record_batch([pa.array(ids[own]), pa.array(np.full(len(own), t, np.int32)), pa.array(np.full(len(own), d, np.int32)), pa.array(key), pa.array(np.full(len(own), k == 0))], names=["cid", "tab", "dim", "bucket", "home"])

    return run


def _cosines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, 2000):
            batch = whole.slice(at, 2000)
            a, b = batch.column("va").flatten().to_numpy(), batch.column("vb").flatten().to_numpy()
            n = np.array([len(v) for v in batch.column("va")])
            starts = np.concatenate(([0], np.cumsum(n)))[:-1]
            dot, aa, bb = (np.add.reduceat(v, starts) for v in (a * b, a * a, b * b))
            yield pa.record_batch([batch.column("a"), batch.column("b"), pa.array(dot / (np.sqrt(aa) * np.sqrt(bb)))], names=["a", "b", "cosine"])


def near_duplicate_vectors(vectors: DataFrame, threshold: float = 0.93, tables: int = 12, hashes: int = 2) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of ``vectors`` (vec_id, embedding, label).

    Only vectors of one label and one length are compared. A vector that is null, empty, zero, or holds a null or a non-finite
    component, and one without label or id, links with nothing and is kept; its component is its id. Repeated rows are equal vectors.
    The search is the same at every size: ``hashes`` codes in each of ``tables`` tables. A class meets the home buckets of its own and its next-likeliest codes.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "vectors")
    v = F.transform(F.col("embedding"), lambda x: x.cast("double"))
    sound = F.size("embedding").between(1, 1 << 20) & F.forall(F.col("embedding"), lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(F.col("embedding"), lambda x: x != 0)
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label"), F.col("embedding"), F.coalesce(sound & F.col("label").isNotNull() & F.col("vec_id").isNotNull(), F.lit(False)).alias("sound"))
    # two hashes name a class; equal vectors share them
    rows = rows.withColumn("k1", F.xxhash64("label", "embedding")).withColumn("k2", F.xxhash64(F.lit(7), "embedding", "label"))
    classes = rows.where("sound").groupBy("k1", "k2").agg(F.min("vec_id").alias("cid"), F.count("*").alias("copies"))
    classes = scratch.keep(classes, "classes")
    speakers = rows.where("sound").select("vec_id", "label", v.alias("v"), "k1", "k2").join(classes, ["k1", "k2"]).where("vec_id = cid").dropDuplicates(["cid"]).select("cid", "label", "v", "copies")
    speakers = scratch.keep(speakers, "speakers")
    buckets = speakers.select("cid", "v").mapInArrow(_bucket_rows(tables, hashes), "cid long, tab int, dim int, bucket long, home boolean")
    buckets = scratch.keep(buckets.join(speakers.select("cid", "label"), "cid"), "buckets")
    key = ["tab", "dim", "bucket", "label"]
    met = buckets.where("home").withColumnRenamed("cid", "x").join(buckets.withColumnRenamed("cid", "y").drop("home"), key).where("x != y")
    pairs = met.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
    both = pairs.join(speakers.select(F.col("cid").alias("a"), F.col("v").alias("va")), "a").join(speakers.select(F.col("cid").alias("b"), F.col("v").alias("vb")), "b")
    links = scratch.keep(both.mapInArrow(_cosines, "a long, b long, cosine double").where(F.col("cosine") >= threshold).select("a", "b"), "links")
    scratch.drop("buckets")
    comps = components(links, "a", "b", scratch, "components")
    counts = speakers.select("cid", "copies")
    ways = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).join(counts.withColumnRenamed("cid", "b"), "b").groupBy("a").agg(F.sum("copies").alias("others"))
    known = (
        classes.join(ways, F.col("cid") == F.col("a"), "left").join(comps, F.col("cid") == F.col("node"), "left")
        .select("k1", "k2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n"), F.coalesce("comp", "cid").alias("root"))
    )
    keyed = rows.select("vec_id", F.when(F.col("sound"), F.col("k1")).alias("k1"), F.when(F.col("sound"), F.col("k2")).alias("k2"))
    out = keyed.join(known, ["k1", "k2"], "left")
    comp = F.coalesce("root", "vec_id")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), comp.alias("component_id"), F.coalesce(F.col("vec_id") == comp, F.lit(True)).alias("kept"))
