"""The corpus pipeline: five stages over ``documents``, each calling one operator of :mod:`lexbridge.llm`.

Every stage takes (spark, docs, sf_dir), works on all that its predecessor kept, and all but the last return the columns of
``documents``. An empty table passes through every stage; rows with null ids are judged like others where a stage works row by
row and are kept by the stages that work on ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lexbridge import reach
from lexbridge.llm.decontaminate import find_leaks
from lexbridge.llm.jaccard_join import link_components
from lexbridge.llm.line_dedup import dedup_lines
from lexbridge.llm.mixing import mix_sources
from lexbridge.llm.scratch import Scratch, fresh, small
from lexbridge.llm.toxicity import fit_toxicity, toxic_score

TOXIC = 0.3


def _without(docs: DataFrame, ids: DataFrame, scratch: Scratch) -> DataFrame:
    """``docs`` less the rows of the given ids."""
    (drop,) = fresh(docs, "dropped_id")
    ids = scratch.keep(ids.select(F.col("doc_id").alias(drop)).distinct(), "dropped")
    return docs.join(small(ids), F.col("doc_id") == F.col(drop), "left_anti")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the multiple-instance model scores under the threshold."""
    reach(spark)
    model = fit_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return docs.where(toxic_score(spark, model)("text") < TOXIC)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later repeats of line runs are cut out of the texts; a document goes only if nothing but such repeats was in it."""
    all_lines, lost = fresh(docs, "line_count", "lost_lines")
    cut = dedup_lines(docs, names=(all_lines, lost))
    cut = cut.where((F.col(lost) == 0) | (F.trim(F.translate("text", "\n\t\r\f\x0b", "     ")) != ""))
    chars = F.when(F.col(lost) > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cut.withColumn("n_chars", chars).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest id of each group of linked documents, in one row."""
    reach(spark)
    scratch = Scratch(spark, "pipeline-near")
    groups = scratch.keep(link_components(docs), "groups")
    kept = _without(docs, groups.where("component_id != doc_id").select("doc_id"), scratch)
    counts = groups.where("doc_id is not null").agg(F.count("*"), F.count_distinct("doc_id")).first()
    if counts[0] > counts[1]:  # one id in several rows: they are one document
        kept = kept.where("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(kept.where("doc_id is null"))
    return kept


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    reach(spark)
    scratch = Scratch(spark, "pipeline-leaks")
    return _without(docs, find_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select("doc_id"), scratch)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents of the mix, with how often each is taken (``copies``) and the words that makes (``taken``); columns of these names are replaced."""
    docs = docs.drop("copies", "taken")
    (own,) = fresh(docs, "taken_id")
    shares = mix_sources(docs.select("doc_id", "text", "source")).where("copies > 0").groupBy(F.col("doc_id").alias(own)).agg(F.max("copies").alias("copies"), F.max("taken").alias("taken"))
    return docs.join(shares.hint("merge"), F.col("doc_id").eqNullSafe(F.col(own))).drop(own)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard", drop_near_duplicates),
    ("decontamination", drop_leaks),
    ("mix_sources", mix),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order, each written and read again."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = scratch.keep(docs, name)
            if i:
                scratch.drop(STAGES[i - 1][0])
    return docs


QUERIES = {"pipeline": run}
ORACLES: dict[str, str] = {}
