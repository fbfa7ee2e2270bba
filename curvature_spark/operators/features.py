"""Training samples from the given tables: sample_key, label (+1 or -1), features (last one the constant 1).

Binary workloads carry `hot` instead of `features`: the positions of the ones, the constant's among them. Such
rows stay short through every shuffle; the block packer scatters them, and `expanded` gives the long form.

Vocabularies of one-hot attributes are fixed, so the dimension is known from the specification and no pass
over the data finds it. Every builder selects its columns first, which prunes the scan.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructField, StructType

from ..functions.prng import draw_column
from ..functions.vectors import norm
from ..sources.catalog import load

#: The vocabularies of the string attributes.
TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")

DIMENSIONS = {"tiny": 3, "users": 5, "dense": 69, "onehot": 124, "sparse": 301, "quad": 3}
BUCKETS = 300


def sign(condition: Column) -> Column:
    return F.when(condition, 1.0).otherwise(-1.0)


def line_key() -> Column:
    """lineitem has no two-column key; these five identify a row."""
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return F.concat_ws(":", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], cents.cast("string"))


def tiny(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem")
    return rows.select(line_key().alias("sample_key"), sign(F.col("l_returnflag") == "R").alias("label"), F.array(F.col("l_discount") * 10, F.col("l_tax") * 12.5, F.lit(1.0)).alias("features"))


def quad(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least squares: the fourth feature is the target."""
    rows = load(spark, sf_dir, "lineitem")
    return rows.select(line_key().alias("sample_key"), F.array(F.col("l_quantity") / 50, F.col("l_discount") * 10, F.lit(1.0), F.col("l_extendedprice") / 1e5).alias("features"))


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return user_samples(load(spark, sf_dir, "events"))


def user_samples(events: DataFrame) -> DataFrame:
    """Samples of event rows, whether they come from the table or from a batch of a stream."""
    k = F.get_json_object("props", "$.k").cast("double")
    features = F.array(F.col("value") / 500, k / 100, F.hour("ts") / 24, (F.dayofweek("ts") - 1) / 7, F.lit(1.0))
    return events.select(F.col("event_id").cast("string").alias("sample_key"), "user_id", "ts", sign(F.col("event_type") == "purchase").alias("label"), features.alias("features"))


def dense(spark: SparkSession, sf_dir: str, positive: int = 0) -> DataFrame:
    v = F.transform("embedding", lambda x: x.cast("double"))
    rows = load(spark, sf_dir, "embeddings").where(F.col("embedding").isNotNull()).select("vec_id", "label", v.alias("v"))
    total = F.aggregate("v", F.lit(0.0), lambda s, x: s + F.abs(x))
    features = F.concat("v", F.array(norm(F.col("v")), F.array_max("v"), F.array_min("v"), total / 8, F.lit(1.0)))
    return rows.select(F.col("vec_id").cast("string").alias("sample_key"), sign(F.col("label") == positive).alias("label"), features.alias("features"))


def sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """300 binary attributes: whether a token falls into a bucket of the portable hash."""
    tokens = F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+"))
    rows = load(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.filter(tokens, lambda t: t != "").alias("tokens"))
    bucket = lambda t: F.conv(F.substring(F.md5(t), 1, 8), 16, 10).cast("long") % BUCKETS
    present = F.array_distinct(F.transform("tokens", bucket)).cast("array<int>")
    return rows.select(F.col("doc_id").cast("string").alias("sample_key"), "source", sign(F.col("lang") == "en").alias("label"), F.array_append(present, F.lit(BUCKETS)).alias("hot"))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with the attributes of its dimensions; Catalyst broadcasts the small ones by their size."""
    line = load(spark, sf_dir, "lineitem")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus")
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_size")
    supplier = load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    nation = load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    return (
        line.join(orders, line.l_orderkey == orders.o_orderkey)
        .join(customer, F.col("o_custkey") == F.col("c_custkey"))
        .join(part, F.col("l_partkey") == F.col("p_partkey"))
        .join(supplier.join(nation, F.col("s_nationkey") == F.col("n_nationkey")), F.col("l_suppkey") == F.col("s_suppkey"))
    )


def attributes() -> list[tuple[Column, int]]:
    """Attribute numbers (0-based category) and how many categories each has; 123 in all."""
    cents = lambda c: F.round(F.col(c) * 100).cast("int")
    capped = lambda x, n: F.least(F.greatest(x.cast("int"), F.lit(0)), F.lit(n - 1))
    return [
        (capped(F.col("l_linenumber") - 1, 7), 7),
        (capped(cents("l_discount"), 11), 11),
        (capped(cents("l_tax"), 9), 9),
        (capped(F.floor((F.col("l_quantity") - 1) / 5), 10), 10),
        ((F.col("l_linestatus") == "O").cast("int"), 2),
        (F.month("l_shipdate") - 1, 12),
        (F.dayofweek("l_shipdate") - 1, 7),
        (capped(F.substring("p_brand", 7, 2).cast("int") - 1, 25), 25),
        _listed("p_type", TYPES),
        _listed("o_orderpriority", PRIORITIES),
        _listed("o_orderstatus", ("F", "O", "P")),
        _listed("c_mktsegment", SEGMENTS),
        (capped(F.col("n_regionkey"), 5), 5),
        (capped(F.floor(F.col("l_extendedprice") / 1e4), 11), 11),
        (capped(F.floor((F.col("p_size") - 1) / 10), 5), 5),
    ]


def _listed(column: str, values: tuple[str, ...]) -> tuple[Column, int]:
    """A string attribute's category: its place in a fixed vocabulary."""
    return F.array_position(F.array(*[F.lit(v) for v in values]), F.col(column)).cast("int") - 1, len(values)


def onehot(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts, total = attributes(), 0
    positions = []
    for value, n in parts:
        positions.append(value + total)
        total += n
    positions.append(F.lit(total))
    return star(spark, sf_dir).select(line_key().alias("sample_key"), "l_suppkey", sign(F.col("l_returnflag") == "R").alias("label"), F.array(*[p.cast("int") for p in positions]).alias("hot"))


def scattered(hot: pa.Array, d: int) -> np.ndarray:
    """Rows of zeros with ones at the positions of a list column; a missing position or list sets none."""
    z = np.zeros((len(hot), d))
    lengths = np.nan_to_num(hot.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
    at = hot.flatten().to_numpy(zero_copy_only=False)
    rows = np.repeat(np.arange(len(hot)), lengths)
    known = ~np.isnan(at) if at.dtype.kind == "f" else slice(None)
    z[rows[known], at[known].astype(np.int64)] = 1.0
    return z


def expanded(samples: DataFrame, d: int) -> DataFrame:
    """samples with `features` in place of `hot`."""
    if "features" in samples.columns:
        return samples
    kept = [f for f in samples.schema.fields if f.name != "hot"]

    def expand(batches):
        for batch in batches:
            z = scattered(batch.column("hot"), d)
            long = pa.ListArray.from_arrays(np.arange(0, z.size + 1, d, dtype=np.int32), z.ravel())
            yield pa.RecordBatch.from_arrays([*[batch.column(f.name) for f in kept], long], [*[f.name for f in kept], "features"])

    return samples.mapInArrow(expand, StructType([*kept, StructField("features", ArrayType(DoubleType()))]))


BUILDERS = {"tiny": tiny, "users": users, "dense": dense, "onehot": onehot, "sparse": sparse, "quad": quad}


def portable_split(samples: DataFrame, clients: int, seed: int = 7) -> DataFrame:
    """Clients by the portable draw of the key: no shuffle, and the same clients in SQL."""
    return samples.withColumn("client_id", draw_column(seed, F.col("sample_key")) % clients)


def intercept(features: Column) -> Column:
    return F.concat(features, F.array(F.lit(1.0)))


def absorb_label(samples: DataFrame) -> DataFrame:
    """Features times label: the form in which blocks are kept."""
    return samples.withColumn("features", F.transform("features", lambda v: v * F.col("label")))


def statistics(samples: DataFrame) -> DataFrame:
    """rows, positives, dimension, share of non-zeros, mean and variance of all feature values (`features`; see `expanded`)."""
    non_zero = F.size(F.filter("features", lambda v: v != 0))
    total = F.aggregate("features", F.lit(0.0), lambda s, v: s + v)
    squares = F.aggregate("features", F.lit(0.0), lambda s, v: s + v * v)
    d = F.size("features")
    sums = samples.agg(
        F.count(F.lit(1)).alias("n"), F.sum((F.col("label") > 0).cast("long")).alias("positives"), F.max(d).alias("d"),
        F.sum(non_zero).alias("non_zero"), F.sum(d).alias("cells"), F.sum(total).alias("total"), F.sum(squares).alias("squares"),
    )
    mean = F.col("total") / F.col("cells")
    return sums.select("n", "positives", "d", (F.col("non_zero") / F.col("cells")).alias("density"), mean.alias("mean"), (F.col("squares") / F.col("cells") - mean * mean).alias("variance"))
