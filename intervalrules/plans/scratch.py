"""Intermediate results of iterative plans: checkpoints and Parquet tables in the cluster's shared folder."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BROADCAST_ROWS = 500_000


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir. Only a local session (tests) may leave it unset and gets one of its own."""
    context = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", context.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoint-"))
        found = context.getCheckpointDir()
    return found.rstrip("/")


def fixed_plans(spark: SparkSession) -> SparkSession:
    """Another session with the settings of this one, but without adaptive execution; the caller's session stays as it is."""
    work = spark.newSession()
    for key, value in spark.conf.getAll.items():
        if key.startswith("spark.sql.") and work.conf.isModifiable(key):
            work.conf.set(key, value)
    work.conf.set("spark.sql.adaptive.enabled", "false")
    return work


def in_session(df: DataFrame, spark: SparkSession) -> DataFrame:
    """The same plan, bound to another session of the same context."""
    rows = spark.sparkContext._jvm.org.apache.spark.sql.classic.Dataset
    return DataFrame(rows.ofRows(spark._jsparkSession, df._jdf.queryExecution().analyzed()), spark)


def partitioned_checkpoint(df: DataFrame) -> DataFrame:
    """Writes df to the shared folder; lineage is cut, partitioning and order stay (adaptive execution would lose them)."""
    spark = df.sparkSession
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    return in_session(in_session(df, fixed_plans(spark)).checkpoint(eager=True), spark)


def release(df: DataFrame) -> None:
    """Deletes the files of a checkpoint that nothing reads any more; other frames are left alone."""
    plan = df._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRDD" or not (found := plan.rdd().getCheckpointFile()).isDefined():
        return
    jvm = df.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(found.get())
    path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


_open: list[list[Tables]] = []


@contextmanager
def temporary(spark: SparkSession):
    """Tables that the block makes are removed at its end, and the shuffle files of its plans with them."""
    _open.append([])
    try:
        yield
    finally:
        for tables in _open.pop():
            tables.drop("")
        gc.collect()  # frees the plans, so that Spark's cleaner may delete what they shuffled
        spark.sparkContext._jvm.System.gc()


class Tables:
    """Parquet tables below the shared folder, one sub-folder for each use. drop() removes one early; what is left goes when the driver ends."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.root = spark, f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
        path, files = self._at(self.root)
        files.mkdirs(path)
        files.deleteOnExit(path)
        if _open:
            _open[-1].append(self)

    def _at(self, name: str):
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
        return path, path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def put(self, name: str, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.option("compression", "zstd").mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, name: str) -> None:
        path, files = self._at(f"{self.root}/{name}")
        files.delete(path, True)


def small(df: DataFrame, rows: int, most: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint behind a check of the counted size; larger sides are joined by a shuffle."""
    return F.broadcast(df) if rows <= most else df
