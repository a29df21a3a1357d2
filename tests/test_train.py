from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from lexbridge.operators import train as T
from lexbridge.operators.model import TrainConfig
from lexbridge.plans import core
from lexbridge.sources.tables import corpus, rename_vocabulary

CFG = replace(TrainConfig(), steps=20, dims=256, k=20)
FOLDER = "/root/testdata/sf0.01"


def predictions(spark, docs):
    pairs = spark.createDataFrame([("N1", "N3")], "src string, tgt string")
    done = T.run(T.prepare(docs, pairs, CFG), ["full"], CFG)
    return {(r.doc_id, r.epoch): round(r.p_pos, 9) for r in done.scored.where("side = 'T'").collect()}


def test_target_labels_do_not_reach_the_predictions(spark):
    docs = corpus(spark, FOLDER)
    flipped = docs.withColumn("label", F.when(F.col("domain") == "N3", -F.col("label")).otherwise(F.col("label")))
    assert predictions(spark, docs) == predictions(spark, flipped)


def test_equal_texts_share_a_split(spark):
    d = corpus(spark, FOLDER).where("label is not null").groupBy("text").agg(F.count_distinct("split").alias("n"))
    assert d.where("n > 1").count() == 0


def test_renaming_shifts_some_words_only(spark):
    d = corpus(spark, FOLDER).where("domain = 'N1'").select("doc_id", "text", "domain")
    words = rename_vocabulary(d).select(F.explode(F.split("text", " ")).alias("w"))
    share = words.agg(F.avg(F.col("w").endswith("n1").cast("int"))).first()[0]
    assert 0.2 < share < 0.8


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    f = core.QUERIES["pivot_initial_topk"](spark, FOLDER)
    plan = plan_of(f)
    assert "WindowGroupLimit" in plan and "Python" not in plan and "Broadcast" in plan
    scan = plan_of(spark.read.parquet(f"{FOLDER}/documents.parquet").where("n_chars > 2000 and lang = 'en'").select("doc_id", "lang"))
    assert "PushedFilters: [IsNotNull(n_chars)" in scan and "text" not in scan.split("ReadSchema")[1]


@pytest.mark.parametrize("name", ["bank_td_exact", "kg_merged", "inject_scoped"])
def test_corpus_side_stays_in_the_jvm(spark, name):
    from lexbridge import workloads

    assert "Python" not in plan_of(workloads.QUERIES[name](spark, FOLDER))
