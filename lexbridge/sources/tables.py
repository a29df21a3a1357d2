"""Readers, writers and the corpora that the methods run on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lexbridge import reach

NEAR = ("N1", "N2", "N3", "N4")
DOMAINS = (*NEAR, "FAR")
#: Labels that are sent to every task: 12 bytes each.
SMALL_ROWS = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reach(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def domain_of(lang: Column, source: Column) -> Column:
    """English sources by number in four near domains of five sources each; every other language is the far one."""
    number = F.substring(source, 4, 10).cast("int")
    return F.when(lang == "en", F.concat(F.lit("N"), (F.floor(number / 5) + 1).cast("string"))).otherwise("FAR")


def hash_bucket(text: Column, seed: int, n: int) -> Column:
    """A bucket from md5, alike in every engine and on every run."""
    return F.pmod(F.conv(F.substring(F.md5(F.concat(text, F.lit(f"|{seed}"))), 1, 8), 16, 10).cast("long"), F.lit(n))


def corpus(spark: SparkSession, sf_dir: str, target: str = "toxic", seed: int = 7, dev_parts: int = 5) -> DataFrame:
    """doc_id, text, lang, domain, label (1, -1 or null), split (train, dev, unlabelled).

    The split follows a hash of the text, so equal texts never part.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    labels = table(spark, sf_dir, "labels").select("doc_id", (2 * F.col(target) - 1).alias("label"))
    if labels.count() <= SMALL_ROWS:  # texts stay where they are
        labels = F.broadcast(labels)
    held = F.when(F.col("label").isNull(), "unlabelled").when(hash_bucket(F.col("text"), seed, dev_parts) == 0, "dev").otherwise("train")
    joined = docs.join(labels, "doc_id", "left")
    return joined.select("doc_id", "text", "lang", domain_of(F.col("lang"), F.col("source")).alias("domain"), "label", held.alias("split"))


def domain_pairs(spark: SparkSession, grid: str = "all") -> DataFrame:
    """(src, tgt): the ordered pairs, so that all of them run in one job."""
    rows = [(s, t) for s in DOMAINS for t in DOMAINS if s != t]
    near = [(s, t) for s, t in rows if "FAR" not in (s, t)]
    return spark.createDataFrame({"all": rows, "near": near, "far": [p for p in rows if p not in near]}[grid], "src string, tgt string")


def rename_vocabulary(docs: DataFrame, share: float = 0.5) -> DataFrame:
    """Shifts the vocabulary: an md5-chosen share of the words carries the domain's name, so some markers stay shared and others become the target's own."""
    cut = int(round(share * 1000))
    words = F.split(F.lower("text"), " ")
    renamed = F.transform(words, lambda w: F.when((hash_bucket(w, 3, 1000) < cut) & w.rlike(r"^\p{L}+[.,!?]?$"), F.concat(F.regexp_replace(w, r"[.,!?]$", ""), F.lower(F.col("domain")))).otherwise(w))
    return docs.withColumn("text", F.array_join(renamed, " "))


def html_text(html: Column) -> Column:
    """Visible text of a page: scripts, styles and comments go first, then tags, then the common entities."""
    out = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def save_versioned(df: DataFrame, path: str, by: list[str]) -> None:
    """Overwrites only the partitions that ``df`` holds."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*by).parquet(path)
