"""Shared intermediate tables: every lineage cut is a parquet table under the session's checkpoint folder."""

from __future__ import annotations

import atexit
import ctypes
import gc
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the context's checkpoint folder, else the one that the session names.

    Where neither is set, a local session uses a folder of its warehouse; a cluster must name one.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch")
    return sc.getCheckpointDir().rstrip("/")


def give_back() -> None:
    """Frees what the driver's Python no longer uses, the JVM objects that it held too, and hands free pages back to the system."""
    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


#: Cells of keys that may be broadcast: 8 bytes each, so some megabytes whatever the corpus.
SMALL_CELLS = 500_000


def small(keys: DataFrame, cells: str = "1") -> DataFrame:
    """A table of keys, marked for broadcast only if its counted cells (``cells`` of each row) are within the bound.

    Beyond the bound it is left to a shuffled join.
    """
    n = keys.agg(F.sum(F.expr(cells))).first()[0] or 0
    return F.broadcast(keys) if n <= SMALL_CELLS else keys


#: Keys with more than this part of all rows are hot, so there are at most so many of them.
HOT_KEYS = 10_000


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, with underscores in front of those that ``df`` already uses."""
    used, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in used:
            name = f"_{name}"
        used.add(name.lower())
        out.append(name)
    return out


def join_counted(rows: DataFrame, keys: DataFrame, on: str, count: str) -> DataFrame:
    """Inner join of ``rows`` with ``keys``, which are unique in ``on`` and hold how many rows each of them meets.

    Few keys are broadcast. Of many, the hot ones are: there are at most ``HOT_KEYS`` of those whatever the input. The others are
    shuffled, and none of them can fill a task. Both tables should be staged, as they are read more than once.
    """
    n, total = keys.agg(F.count("*"), F.sum(count)).first()
    if n * len(keys.columns) <= SMALL_CELLS:
        return rows.join(F.broadcast(keys), on)
    hot = F.broadcast(keys.where(F.col(count) > max(1, total // HOT_KEYS)))
    cold = rows.join(hot.select(on), on, "left_anti").join(keys.where(F.col(count) <= max(1, total // HOT_KEYS)), on)
    return rows.join(hot, on).unionByName(cold)


class Scratch:
    """Named parquet tables of one operator call.

    A table that the returned DataFrame still reads stays until the interpreter ends; :meth:`drop` removes
    the others as soon as the next one is written, so disk use follows the live tables only.
    """

    def __init__(self, spark: SparkSession, owner: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{owner}-{uuid.uuid4().hex[:12]}"
        self.names: set[str] = set()
        atexit.register(self._delete, self.root)

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        self.names.add(name)
        df.write.mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            self._delete(f"{self.root}/{name}")
        self.names -= {*names}
        give_back()
        # the shuffles behind dropped tables are garbage now; Spark deletes their files when the JVM collects them
        self.spark.sparkContext._jvm.System.gc()

    def only(self, *names: str) -> None:
        """Drops all tables but those that the result still reads."""
        self.drop(*(self.names - {*names}))

    def _delete(self, path: str) -> None:
        jvm = self.spark.sparkContext._jvm
        if jvm is None:
            return
        try:
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the context may be gone at exit; the folder is disposable
            pass
