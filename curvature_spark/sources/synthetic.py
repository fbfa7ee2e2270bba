"""Synthetic convex problems as a Spark data source, and the sparse text format.

    spark.dataSource.register(SyntheticProblem)
    spark.read.format("synthetic_problem").option("rows", 1000).option("d", 5).option("kind", "logistic").load()
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.prng import SPAN, draw_column
from ..functions.vectors import dot, sigmoid


def planted(d: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, 0]).normal(size=d)


def planted_labels(samples: DataFrame, d: int, seed: int) -> DataFrame:
    """samples with the margin under planted parameters, and labels drawn from it by the portable draw of the key."""
    truth = F.array(*[F.lit(float(v)) for v in planted(d, seed)])
    rows = samples.withColumn("margin", dot(F.col("features"), truth))
    return rows.withColumn("label", F.when(draw_column(seed, F.col("sample_key")) / SPAN < sigmoid(F.col("margin")), 1.0).otherwise(-1.0))


class SyntheticReader(DataSourceReader):
    def __init__(self, options: dict):
        self.rows, self.d = int(options.get("rows", 1000)), int(options.get("d", 5))
        self.seed, self.parts, self.kind = int(options.get("seed", 1)), int(options.get("partitions", 4)), options.get("kind", "logistic")

    def partitions(self) -> list[InputPartition]:
        edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [InputPartition((a, b)) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        truth = planted(self.d, self.seed)
        for i in range(*partition.value):  # a row depends on its number alone, not on the partitioning
            rng = np.random.default_rng([self.seed, 1, i])
            a = np.append(rng.normal(size=self.d - 1), 1.0)
            m = float(a @ truth)
            label = (1.0 if rng.random() < 1 / (1 + np.exp(-m)) else -1.0) if self.kind == "logistic" else m + 0.01 * float(rng.normal())
            yield str(i), label, a.tolist()


class SyntheticProblem(DataSource):
    """Rows (sample_key, label, features) of a logistic or quadratic problem with known parameters."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_problem"

    def schema(self) -> str:
        return "sample_key string, label double, features array<double>"

    def reader(self, schema) -> SyntheticReader:
        return SyntheticReader(dict(self.options))


def write_sparse_text(samples: DataFrame, path: str) -> None:
    """label index:value ... with 1-based indices of the non-zero features, one sample a line."""
    cells = F.transform("features", lambda v, i: F.when(v != 0, F.concat_ws(":", (i + 1).cast("string"), v.cast("string"))))
    line = F.concat_ws(" ", F.col("label").cast("string"), F.concat_ws(" ", F.filter(cells, lambda c: c.isNotNull())))
    samples.select(line.alias("value")).write.mode("overwrite").text(path)


def read_sparse_text(spark: SparkSession, path: str, d: int) -> DataFrame:
    """label, features; giving the dimension saves the pass that would find it."""
    from pyspark.ml.functions import vector_to_array

    rows = spark.read.format("libsvm").option("numFeatures", str(d)).load(path)
    return rows.select("label", vector_to_array("features").alias("features"))
