"""Cutting lineage through storage that every executor shares.

A table that several later plans read is written once as Parquet below the session's
``spark.checkpoint.dir`` and read again: a lost executor then costs a re-read, never a recomputation
of everything before it. Nothing here uses executor-local checkpoints.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LIVE: dict[str, list[tuple[SparkSession, str]]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder for intermediate tables: the session's own, or (local masters only) a fresh one."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not sc.master.startswith("local[") and sc.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="curvature-"))
    return sc.getCheckpointDir().rstrip("/")


#: Spark's own switch for removing a query's shuffle files when the query ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: Rows that a Python worker receives at once: texts are long.
BATCH, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", "2000"


@contextmanager
def _writing(spark: SparkSession) -> Iterator[None]:
    """While a table is written: its shuffle files go when it is there, not when the driver happens to collect garbage."""
    before = {key: spark.conf.get(key, None) for key in (CLEANUP, BATCH)}
    spark.conf.set(CLEANUP, "true")
    spark.conf.set(BATCH, BATCH_ROWS)
    try:
        yield
    finally:
        for key, value in before.items():
            if value is None:
                spark.conf.unset(key)
            else:
                spark.conf.set(key, value)


def written(df: DataFrame, tag: str, owner: str = "session") -> DataFrame:
    """`df` as a written table: computed once here, read from shared storage by every later plan."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tables/{tag}-{uuid.uuid4().hex}"
    with _writing(spark):
        df.write.parquet(path)
    _LIVE.setdefault(owner, []).append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder through the file system that holds it."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def release(owner: str = "session") -> int:
    """Delete the tables of `owner`, once everything that reads them has run; says how many went."""
    gone = 0
    for spark, path in _LIVE.pop(owner, []):
        try:
            remove(spark, path)
            gone += 1
        except Exception:  # noqa: BLE001  the session may have ended, and its folder with it
            continue
    return gone


@atexit.register
def _release_all() -> None:
    for owner in list(_LIVE):
        release(owner)
