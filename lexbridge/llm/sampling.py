"""Bounded training samples, and the rule that keeps a quarter of the documents out of every fit.

Samples are the first rows by hash of a key. A threshold on the hash, set from the counted keys with room to spare, leaves little more than
the sample to be put in order, whatever the table's size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.llm.scratch import small

_SCALE = float(1 << 62)


def held_out() -> Column:
    """crc32 of the id's text leaves 2 when divided by 4. A null id is not held out."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _order(by: str) -> Column:
    return F.pmod(F.xxhash64(F.col(by)), F.lit(1 << 62))


def _room(n: int) -> float:
    """Keys to let pass so that ``n`` remain although the count of keys is an estimate and the hash is random."""
    return 1.25 * n + 8 * n**0.5 + 64


def first_by_hash(rows: DataFrame, n: int, by: str = "doc_id") -> DataFrame:
    """The first ``n`` distinct rows in the order of the hash of ``by``; null keys are left out."""
    rows = rows.where(F.col(by).isNotNull())
    total = rows.agg(F.approx_count_distinct(by)).first()[0]
    near = rows if total <= 2 * _room(n) else rows.where(_order(by) < F.lit(int(_SCALE / total * _room(n))))
    return near.distinct().orderBy(_order(by), *rows.columns).limit(n)


def sample_ids(rows: DataFrame, label: str, per_label: int) -> DataFrame:
    """(doc_id, label): at most ``per_label`` ids of each label, the first by hash; an id with several labels has the least one."""
    ids = rows.select("doc_id", F.col(label).alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isNotNull())
    totals = ids.groupBy("label").agg(F.approx_count_distinct("doc_id").alias("total"))
    near = ids.join(small(totals), "label").where((F.col("total") <= 2 * _room(per_label)) | (_order("doc_id") < _SCALE / F.col("total") * _room(per_label)))
    near = near.groupBy("doc_id").agg(F.min("label").alias("label"))
    rank = F.row_number().over(W.partitionBy("label").orderBy(_order("doc_id"), "doc_id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= per_label).select("doc_id", F.col("label").alias(label))
