"""The online form: streams of labelled tokens, keyed affine state, windows with watermarks."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from lexbridge.sources.stage import drop_at_exit, shared_folder
from lexbridge import reach


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, with zoned timestamps for watermarks."""
    reach(spark)
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    files = reader.parquet(path) if _is_folder(spark, path) else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return files.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote.

    Appended rows go to files under the shared folder, so the driver holds none of them. The other modes rewrite rows, which no file sink
    can; they keep the driver's table, one row for each key and batch.
    """
    spark, name = stream.sparkSession, f"stream_{uuid.uuid4().hex[:10]}"
    where = f"{shared_folder(spark)}/{name}"
    drop_at_exit(spark, where)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True)
    if mode != "append":
        writer.format("memory").queryName(name).start().awaitTermination()
        return spark.table(name)
    writer.format("parquet").option("path", f"{where}/rows").start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{where}/rows")


def tokens(events: DataFrame, cut: float = 50.0) -> DataFrame:
    """(word, side, label, ts, event_id): an event's type as the word, its user's parity as the side, its value's side of a cut as the label."""
    return events.select(F.col("event_type").alias("word"), F.when(F.col("user_id") % 2 == 0, "S").otherwise("T").alias("side"), F.when(F.col("value") > cut, 1).otherwise(-1).alias("label"), "ts", "event_id")


def stream_bank(stream: DataFrame, alpha: float) -> DataFrame:
    """(word, side, n, p): the bank after each micro-batch, from state (n, p) for each key. Rows of a batch are put in order of time first."""

    def step(key: tuple, chunks: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, p = state.get if state.exists else (0, 0.0)
        rows = pd.concat(list(chunks)).sort_values(["ts", "event_id"])
        for label in rows.label:
            n, p = n + 1, alpha * p + (1 - alpha) * label
        state.update((n, p))
        yield pd.DataFrame({"word": [key[0]], "side": [key[1]], "n": [n], "p": [p]})

    return stream.groupBy("word", "side").applyInPandasWithState(step, "word string, side string, n long, p double", "n long, p double", "update", GroupStateTimeout.NoTimeout)


def fold_batches(stream: DataFrame, alpha: float, sink) -> None:
    """Fallback without Python state: each micro-batch is folded to (n, s) by key and handed to ``sink`` to compose."""
    from pyspark.sql import Window as W

    def one(batch: DataFrame, number: int) -> None:
        w = W.partitionBy("word", "side")
        later = F.count("*").over(w) - F.row_number().over(w.orderBy("ts", "event_id"))
        folded = batch.withColumn("v", (1 - alpha) * F.col("label") * F.pow(F.lit(alpha), later)).groupBy("word", "side").agg(F.count("*").alias("n"), F.sum("v").alias("s"))
        sink(folded, number)

    stream.writeStream.foreachBatch(one).trigger(availableNow=True).start().awaitTermination()
