"""Tables that outlive executors: written once to the folder the cluster shares, then reread."""

from __future__ import annotations

import gc
import tempfile
import threading
import time
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The cluster's `spark.checkpoint.dir`; a private folder only where that is unset (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    held = getattr(spark, "_groupmatch_folder", None)
    if held is None:
        held = spark._groupmatch_folder = "file://" + tempfile.mkdtemp(prefix="groupmatch-")
    return held


def settle_counted(df: DataFrame, label: str = "table") -> tuple[DataFrame, int]:
    """`settle`, and the number of rows, observed while they were written."""
    seen = Observation()
    written = settle(df.observe(seen, F.count(F.lit(1)).alias("n")), label)
    return written, int(seen.get["n"])


_lock = threading.Lock()


def _written(spark: SparkSession) -> list[tuple[str, list]]:
    """This application's tables: (folder, weak references to what reads it in the JVM)."""
    context = spark.sparkContext
    if not hasattr(context, "_groupmatch_written"):
        context._groupmatch_written = []
    return context._groupmatch_written


#: Least seconds between two collections of the driver's garbage by `settle`.
COLLECT_S = 8.0


def _collect(spark: SparkSession) -> bool:
    """Collect the driver's garbage if that was not done lately. Spark deletes shuffle files, and `sweep` written
    tables, only when the driver's JVM has collected what refers to them, which a large heap puts off; classes of
    plans that ended are unloaded too."""
    context, now = spark.sparkContext, time.monotonic()
    if not hasattr(context, "_groupmatch_collected"):
        context._groupmatch_collected = now
    if now - context._groupmatch_collected < COLLECT_S:
        return False
    gc.collect()
    context._jvm.System.gc()
    context._groupmatch_collected = time.monotonic()
    return True


def settle(df: DataFrame, label: str = "table") -> DataFrame:
    """Write `df` to the shared folder and return the written table, which cuts the lineage.

    The files stay as long as some DataFrame or plan in the JVM can read them; those of tables that
    were collected as garbage are deleted by a later call, the rest when the JVM ends."""
    spark = df.sparkSession
    _collect(spark)
    sweep(spark)
    place = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(place)
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(path)
    written = spark.read.schema(df.schema).parquet(place)
    relation = written._jdf.queryExecution().analyzed().relation()
    _written(spark).append((place, [jvm.java.lang.ref.WeakReference(x) for x in (relation, relation.location())]))
    return written


def sweep(spark: SparkSession) -> int:
    """Delete written tables that nothing can read any more; their number."""
    jvm = spark.sparkContext._jvm
    with _lock:
        every = _written(spark)
        gone = [x for x in every if all(ref.get() is None for ref in x[1])]
        every[:] = [x for x in every if x not in gone]
    for place, _ in gone:
        path = jvm.org.apache.hadoop.fs.Path(place)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return len(gone)
