"""Sentences, words and pieces as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SENTENCE_END = r"[.!?\n]+"
WORD = r"\p{L}+"
WORD_OR_SYMBOL = r"\p{L}+|[^\p{L}\s.,]+"


def word_list(text: Column, symbols: bool = False) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(WORD_OR_SYMBOL if symbols else WORD), F.lit(0))


def sentences(docs: DataFrame, *keep: str) -> DataFrame:
    """(doc_id, *keep, sent_ix, sentence): the non-blank sentences of each text, numbered as cut."""
    cut = docs.select("doc_id", *keep, F.posexplode(F.split(F.lower("text"), SENTENCE_END)).alias("sent_ix", "sentence"))
    return cut.where(F.trim("sentence") != "")


def pieces(words: Column, size: int = 4) -> Column:
    """Each word's consecutive pieces of ``size`` code points."""
    return F.transform(words, lambda w: F.transform(F.sequence(F.lit(0), F.floor((F.length(w) - 1) / size).cast("int")), lambda i: F.substring(w, i * size + 1, F.lit(size))))


def sentence_words(docs: DataFrame, *keep: str, least: int = 4, most: int = 64) -> DataFrame:
    """(doc_id, *keep, sent_ix, words) of sentences with ``least`` to ``most`` words."""
    cut = sentences(docs, *keep).withColumn("words", word_list(F.col("sentence"))).drop("sentence")
    return cut.where(F.size("words").between(least, most))


def chunked_words(docs: DataFrame, *keep: str, least: int = 4, most: int = 64) -> DataFrame:
    """As :func:`sentence_words`, but longer sentences are cut into chunks of ``most`` words, so no word is lost."""
    cut = sentences(docs, *keep).withColumn("words", word_list(F.col("sentence"))).drop("sentence").where(F.size("words") > 0)
    starts = F.sequence(F.lit(0), F.floor((F.size("words") - 1) / most).cast("int"))
    parts = cut.withColumn("part", F.explode(starts)).withColumn("words", F.slice("words", F.col("part") * most + 1, most))
    return parts.where(F.size("words") >= least)


def whole_words(docs: DataFrame, *keep: str, least: int = 3, most: int = 64) -> DataFrame:
    """(doc_id, *keep, sent_ix, words) of all sentences of ``least`` words, which a fact needs. Longer ones are cut into even parts of ``most`` words or fewer, and ``sent_ix`` numbers the parts of a text, so each stands for itself."""
    parts = lambda w: F.ceil(F.size(w) / most).cast("int")
    edge = lambda w, p: F.floor(F.size(w) * p / parts(w)).cast("int")
    cut = lambda w: F.transform(F.sequence(F.lit(0), parts(w) - 1), lambda p: F.slice(w, edge(w, p) + 1, edge(w, p + 1) - edge(w, p)))
    each = F.flatten(F.transform(F.split(F.lower("text"), SENTENCE_END), lambda x: F.transform(F.array(word_list(x)), lambda w: F.when(F.size(w) > most, cut(w)).otherwise(F.array(w)))[0]))
    return docs.select("doc_id", *keep, F.posexplode(each).alias("sent_ix", "words")).where(F.size("words") >= least)


def phrases(docs: DataFrame, min_count: int = 5, min_pmi: float = 3.0) -> DataFrame:
    """(first, second, n, pmi): adjacent words that occur together more than chance has it."""
    sents = chunked_words(docs, least=1).select("words")
    singles = sents.select(F.explode("words").alias("w")).groupBy("w").agg(F.count("*").alias("c"))
    pairs = sents.where(F.size("words") > 1).select(F.explode(F.arrays_zip(F.slice("words", 1, F.size("words") - 1).alias("first"), F.slice("words", 2, F.size("words") - 1).alias("second"))).alias("p"))
    counted = pairs.groupBy("p.first", "p.second").agg(F.count("*").alias("n")).where(F.col("n") >= min_count)
    total = singles.agg(F.sum("c").alias("total"))
    out = counted.join(singles.select(F.col("w").alias("first"), F.col("c").alias("c1")), "first").join(singles.select(F.col("w").alias("second"), F.col("c").alias("c2")), "second")
    return out.crossJoin(F.broadcast(total)).select("first", "second", "n", F.log(F.col("n") * F.col("total") / (F.col("c1") * F.col("c2"))).alias("pmi")).where(F.col("pmi") >= min_pmi)
