"""The given tables, always through Spark's own readers so that any file system works."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)


ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def workers_can_import(spark: SparkSession) -> None:
    """Let Python workers find this package where the driver found it, whatever folder they start in.

    On a cluster the package is installed on the executors, or shipped once with addPyFile.
    """
    environment = spark.sparkContext.environment
    known = environment.get("PYTHONPATH", "").split(os.pathsep)
    if ROOT not in known:
        environment["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, known)])


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table `name` below `sf_dir`; columns are pruned by whatever is selected from it."""
    if name not in TABLES:
        raise KeyError(f"unknown table {name!r}")
    workers_can_import(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
