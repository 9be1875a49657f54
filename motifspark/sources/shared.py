"""Intermediate tables in the folder that all machines of a cluster share."""

from __future__ import annotations

import contextlib
import functools
import gc
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Folders made inside the innermost open :func:`scratch`, outermost first.
_open: list[list[str]] = []


def shared_folder(spark: SparkSession) -> str:
    """This application's folder in ``spark.checkpoint.dir``, or in the checkpoint directory set on the context.

    Only a local master may do without either and takes a temporary folder; on a cluster that would lose data.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            named = held.get()
        elif spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
            named = _local_folder()
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return f"{named.rstrip('/')}/motifspark-{spark.sparkContext.applicationId}"


@functools.cache
def _local_folder() -> str:
    return "file://" + tempfile.mkdtemp(prefix="motifspark-")


def new_folder(spark: SparkSession, name: str = "") -> str:
    """A fresh path in the shared folder; it goes with the innermost :func:`scratch`."""
    path = f"{shared_folder(spark)}/{name}{uuid.uuid4().hex}"
    if _open:
        _open[-1].append(path)
    return path


def durable(df: DataFrame) -> DataFrame:
    """Write ``df`` once as a Parquet table in the shared folder and read it back.

    This cuts the lineage: a lost executor costs a reread of its splits, and no user function runs twice.
    """
    path = new_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


@contextlib.contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Remove at the end all folders made inside; results must be written elsewhere before."""
    _open.append([])
    try:
        yield
    finally:
        for path in _open.pop():
            remove(spark, path)


def release(spark: SparkSession) -> None:
    """Collect garbage on the driver, Python's first, as its objects hold those of the JVM, then on each executor.

    Spark drops broadcast tables and shuffle files only once the driver's garbage is collected, and a heap that grew on
    earlier steps is given back by a full collection only: without one, an executor keeps what its largest join took
    and the buffers and workers of later steps come on top.
    """
    gc.collect()
    sc = spark.sparkContext
    sc._jvm.System.gc()
    executors = sc._jsc.sc().getExecutorMemoryStatus().size() - 1  # all but the driver; none under a local master
    if executors > 0:  # one task each, as all are idle between the steps of a job
        collected = spark.range(0, executors, 1, executors).select(F.reflect(F.lit("java.lang.System"), F.lit("gc")).alias("done"))
        collected.write.format("noop").mode("overwrite").save()
