from pyspark.sql import functions as F

from lexbridge.operators import bank as B
from lexbridge.streaming import bank as S


def batch_bank(spark, folder, alpha):
    t = S.tokens(spark.read.parquet(f"{folder}/events.parquet"))
    ups = t.select(F.lit("a").alias("src"), F.lit("b").alias("tgt"), "side", "word", F.unix_micros(F.col("ts").cast("timestamp")).alias("step"), F.col("event_id").alias("doc_id"), "label")
    start = ups.select("src", "tgt", "side", "word").distinct().withColumn("p", F.lit(0.0))
    return {(r.word, r.side): (r.n_updates, round(r.p, 9)) for r in B.td_exact(start, ups, alpha).collect()}


def test_stream_equals_batch(spark, small):
    out = S.drain(S.stream_bank(S.tokens(S.event_stream(spark, small)), 0.9), "update")
    got = {(r.word, r.side): (r.n, round(r.p, 9)) for r in out.groupBy("word", "side").agg(F.max("n").alias("n"), F.max_by("p", "n").alias("p")).collect()}
    assert got == batch_bank(spark, small, 0.9)


def test_folded_batches_equal_batch(spark, small):
    folds = []
    S.fold_batches(S.tokens(S.event_stream(spark, small)), 0.9, lambda df, number: folds.extend((number, *r) for r in df.select("word", "side", "n", "s").collect()))
    bank = {}
    for _, word, side, n, s in sorted(folds):
        count, p = bank.get((word, side), (0, 0.0))
        bank[word, side] = (count + n, 0.9**n * p + s)
    assert {k: (n, round(p, 9)) for k, (n, p) in bank.items()} == batch_bank(spark, small, 0.9)
