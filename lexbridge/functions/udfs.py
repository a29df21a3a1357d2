"""User-defined forms of what the column expressions do: each has a built-in twin and is checked against it."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udf(T.ArrayType(T.StringType()))
def pieces_plain(word, size):
    return None if word is None else [word[i : i + size] for i in range(0, len(word), size)]


@F.pandas_udf(T.LongType())
def piece_count(words: pd.Series) -> pd.Series:
    return (words.str.len() + 3) // 4


@F.pandas_udf(T.DoubleType())
def td_result(step: pd.Series, doc_id: pd.Series, label: pd.Series, start: pd.Series, alpha: pd.Series) -> float:
    """The sequential update rule itself, over one word's updates."""
    order = pd.DataFrame({"s": step, "d": doc_id, "l": label}).sort_values(["s", "d"]).l
    p, a = float(start.iloc[0]), float(alpha.iloc[0])
    for label_ in order:
        p = a * p + (1 - a) * label_
    return p


@F.udtf(returnType=T.StructType([T.StructField(n, T.StringType()) for n in ("w_a", "w_b", "w_c")] + [T.StructField("slot", T.IntegerType())]))
class FactsOfRow:
    """Facts of one sentence as a table function: words, a weight row for each place, and the places of the pivots."""

    def eval(self, words, weights, places):
        for i in places or []:
            row = [(-round(a, 9), j) for j, a in enumerate(weights[i]) if j != i]
            if len(row) >= 2:
                three = sorted([i, *[j for _, j in sorted(row)[:2]]])
                yield (*[words[j] for j in three], three.index(i))


def register(spark) -> None:
    """The SQL surface: functions by name for use in SQL text."""
    spark.udf.register("pieces_plain", pieces_plain)
    spark.udf.register("piece_count", piece_count)
    spark.udtf.register("facts_of_row", FactsOfRow)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION polarity(n_pos BIGINT, n_neg BIGINT) RETURNS DOUBLE RETURN (n_pos - n_neg) / nullif(n_pos + n_neg, 0)")
