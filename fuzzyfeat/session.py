"""Session helpers: a local session for tests, the shared folder, and importability on executors."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from itertools import count
from pathlib import Path
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession

ARROW_ROWS, BATCH_ROWS = 2000, "spark.sql.execution.arrow.maxRecordsPerBatch"
ROOT = str(Path(__file__).resolve().parent.parent)


def local_session(cores: int | str = 8, memory: str = "12g", partitions: int = 8) -> SparkSession:
    """A local[cores] session for tests and the bench."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )


def prepare(spark: SparkSession) -> SparkSession:
    """Let Python workers import this package. On a cluster without a shared file system, ship it with --py-files.

    Batches for Python are kept to ARROW_ROWS rows: whole documents travel in them, and each task holds several at a time.
    """
    if int(spark.conf.get(BATCH_ROWS)) > ARROW_ROWS:
        spark.conf.set(BATCH_ROWS, str(ARROW_ROWS))
    environment = spark.sparkContext.environment
    known = environment.get("PYTHONPATH", os.environ.get("PYTHONPATH", ""))
    if ROOT not in known.split(os.pathsep):
        environment["PYTHONPATH"] = os.pathsep.join(x for x in (ROOT, known) if x)
    return spark


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which driver and executors share; a temporary one only in local mode, where it is unset."""
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        if not context.getCheckpointDir():
            context.setCheckpointDir(named)
        return named
    if not context.getCheckpointDir():
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="fuzzyfeat-"))
    return context.getCheckpointDir()


def materialise(df: DataFrame) -> DataFrame:
    """Compute once, cut the lineage, and keep the rows in the shared folder, so that a lost executor costs nothing."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def release(*tables: DataFrame) -> None:
    """Delete the files of materialised tables that nothing reads any more."""
    for df in tables:
        plan = df._jdf.queryExecution().analyzed()
        file = plan.rdd().getCheckpointFile() if plan.getClass().getSimpleName() == "LogicalRDD" else None
        if file is not None and file.isDefined():
            remove(df.sparkSession, file.get())


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """A function that writes a table to the shared folder and reads it back; its tables are deleted at the end of the block.

    Unlike checkpoints, these are compressed columns, of which later reads take only those they need.
    """
    folder = f"{shared_folder(spark).rstrip('/')}/scratch-{uuid4().hex}"
    number = count()

    def keep(df: DataFrame) -> DataFrame:
        path = f"{folder}/{next(number)}"
        df.write.parquet(path)
        return spark.read.schema(df.schema).parquet(path)

    try:
        yield keep
    finally:
        remove(spark, folder)


def remove(spark: SparkSession, folder: str) -> None:
    """Delete a folder that this package wrote, by way of Spark's file systems."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
