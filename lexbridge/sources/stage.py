"""Written intermediate tables, under the folder that the session's checkpoints go to."""

from __future__ import annotations

import atexit
import gc
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The context's checkpoint folder, else the one the session names; a local session without either uses its warehouse."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch")
    return sc.getCheckpointDir().rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if jvm is None:
        return
    try:
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the context may be gone at exit; the folder is disposable
        pass


def drop_at_exit(spark: SparkSession, path: str) -> None:
    atexit.register(_delete, spark, path)


def stage(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` once and reads it back: the lineage ends here, and lost executors read it again. Deleted when the interpreter ends."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stage-{name}-{uuid.uuid4().hex[:12]}"
    drop_at_exit(spark, path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Frees frames that nothing uses any more; Spark deletes the files of their shuffles when the JVM collects them."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
