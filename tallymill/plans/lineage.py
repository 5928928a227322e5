"""Cutting lineage in the folder that driver and executors share; the size of batches."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in a
    single-JVM session without that setting a temporary one."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        current = sc._jsc.sc().getCheckpointDir()
        named = current.get() if current.isDefined() else None
    if not named:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="tallymill-"))
        named = sc._jsc.sc().getCheckpointDir().get()
    return named.rstrip("/")


_SWEPT: set[str] = set()


def own_dir(spark: SparkSession) -> str:
    """This application's part of the shared folder. What is still there when the driver's Python
    ends goes then; a driver that is killed leaves it."""
    top = f"{shared_dir(spark)}/tallymill/{spark.sparkContext.applicationId}"
    if top not in _SWEPT:
        _SWEPT.add(top)
        atexit.register(_sweep, spark._jvm, top)
    return top


def _sweep(jvm, top: str) -> None:
    # the gateway may be gone by then
    with contextlib.suppress(Exception):
        path = jvm.org.apache.hadoop.fs.Path(top)
        path.getFileSystem(jvm.org.apache.hadoop.conf.Configuration()).delete(path, True)


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame, name: str = "cut", **options: str) -> DataFrame:
    """Writes df as Parquet in the shared folder and reads it again, so that what follows
    neither recomputes it nor depends on an executor that may be lost. The shuffle files of the
    write go when it ends; nothing else reads them. options are those of the writer."""
    spark = df.sparkSession
    path = f"{own_dir(spark)}/{name}-{uuid.uuid4().hex}"
    # None unless the session has set it, whatever Spark's own default is
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.options(**options).parquet(path)
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        else:
            spark.conf.set(_CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def drop(df: DataFrame) -> None:
    """Deletes a table that cut() has written and nothing reads any more."""
    spark = df.sparkSession
    for file in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(file)
        if "/tallymill/" in file:
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


#: Bytes of a batch between the JVM and a Python worker; each worker and its JVM side hold one.
BATCH_BYTES = "8m"
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def modest(spark: SparkSession) -> None:
    """Sets the session's Arrow batches to BATCH_BYTES, a runtime setting, so that whole texts
    of many rows do not fill an executor's memory beside its heap."""
    if spark.conf.isModifiable(_BATCH):
        spark.conf.set(_BATCH, BATCH_BYTES)
