"""Session helpers: lineage cuts, size-checked broadcasts."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only when its row count times its row width is proven to stay below this.
BROADCAST_LIMIT_BYTES = 32 << 20


def shared_dir(spark: SparkSession) -> str:
    """The shared checkpoint folder of the session; a private one only where none is set in local mode (tests)."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if found is None:
        found = spark.conf.get("spark.checkpoint.dir", None)
        if not found:
            if not sc.master.startswith("local"):
                raise ValueError("a cluster needs spark.checkpoint.dir: a folder that the driver and all executors share")
            found = tempfile.mkdtemp(prefix="ctxrelease-")
            atexit.register(shutil.rmtree, found, ignore_errors=True)
        sc.setCheckpointDir(found)
    return found


def stored(df: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """Writes a table to the shared folder, for results of which later plans read few columns; the second value deletes it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    # hashes don't compress, and the codec's buffers lie outside the heap until a collection
    df.write.option("compression", "uncompressed").parquet(path)

    def forget() -> None:
        jvm = spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)

    return spark.read.schema(df.schema).parquet(path), forget


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: survives lost executors, ends the lineage."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def bounded_broadcast(df: DataFrame, rows: int, row_bytes: int = 64) -> DataFrame:
    """Broadcast hint when `rows` (a proven bound) keeps the side small, else a plain shuffled side."""
    return F.broadcast(df) if rows * row_bytes <= BROADCAST_LIMIT_BYTES else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def give_back() -> None:
    """Returns freed memory of this Python process to the system."""
    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner drop shuffles and checkpoints that no live DataFrame refers to any more.

    The cleaner learns of them from the driver's garbage collections only, which may be far apart on an idle heap.
    """
    give_back()
    spark.sparkContext._jvm.System.gc()


def relax(spark: SparkSession) -> None:
    """Lets executors return heap that is free to the system, and buffers outside it that only collections free.

    A heap grows to its limit over stages and stays there, beside the Python workers of the next one. There is a task for
    each core, so on an idle cluster every executor gets one.
    """
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.call_function("java_method", F.lit("java.lang.System"), F.lit("gc"))).collect()
