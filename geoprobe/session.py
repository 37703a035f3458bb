"""Session helpers: nothing here changes a setting that is fixed at start."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = str(Path(__file__).resolve().parent.parent)


#: Rows and bytes that a Python worker is handed at a time, at most; texts and rasters are wide rows.
BATCH_ROWS, BATCH_BYTES = 1000, 16 << 20


def workers_can_import(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver found it (a cluster deploys it with --py-files), and
    hand them wide rows in small batches (settings of the running session, which a smaller value of the user's overrides)."""
    rows, size = "spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch"
    if not 0 < int(spark.conf.get(rows, "10000")) <= BATCH_ROWS:
        spark.conf.set(rows, str(BATCH_ROWS))
        spark.conf.set(size, str(BATCH_BYTES))
    environment = spark.sparkContext.environment
    environment.setdefault("OMP_NUM_THREADS", "1")  # a task has one core
    paths = [p for p in environment.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        environment["PYTHONPATH"] = os.pathsep.join([*paths, ROOT])


def spread(scan: DataFrame) -> DataFrame:
    """A scan dealt to all cores if its files give fewer partitions than there are cores (one small file with a single row
    group); a large input has more and stays where it is. For plain scans only: it looks at the partitions of the plan."""
    cores = scan.sparkSession.sparkContext.defaultParallelism
    return scan.repartition(cores) if scan.rdd.getNumPartitions() < cores else scan


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; where that is unset a local temporary folder, on one machine only."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        wanted = spark.conf.get("spark.checkpoint.dir", None)
        if not wanted and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(wanted or tempfile.mkdtemp(prefix="checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


_WRITTEN: list[tuple[SparkSession, str]] = []


def _remove(tables: list[tuple[SparkSession, str]]) -> None:
    for spark, path in tables:
        with contextlib.suppress(Exception):  # the session may have ended before
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def scratch(spark: SparkSession) -> str:
    """A new path in the shared folder; what is written there goes when Python exits, if not before."""
    if not _WRITTEN:
        atexit.register(lambda: _remove(_WRITTEN))
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    _WRITTEN.append((spark, path))
    return path


def checkpointed(df: DataFrame) -> DataFrame:
    """Write `df` as a table in the shared checkpoint folder and read it again, which cuts its lineage.

    A table is taken rather than Dataset.checkpoint() because the latter carries the planner's size estimates along:
    joined from round to round they grow without bound, and planning an iterative job comes to take minutes. The
    tables go when Python exits, or before if `swept`; until then every lazily derived result can read them."""
    spark = df.sparkSession
    path = scratch(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def tables_written() -> int:
    """A mark for `swept`."""
    return len(_WRITTEN)


def swept(result: DataFrame | None, since: int) -> DataFrame | None:
    """The result, after the tables that were written since a mark and that it doesn't read have been removed."""
    read = {path.rstrip("/").rsplit("/", 1)[0].rsplit("/", 1)[-1] for path in result.inputFiles()} if result is not None else set()
    gone = [t for t in _WRITTEN[since:] if t[1].rsplit("/", 1)[-1] not in read]
    _remove(gone)
    _WRITTEN[since:] = [t for t in _WRITTEN[since:] if t not in gone]
    return result
