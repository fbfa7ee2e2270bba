"""Mixing sources to target weights by weighted sampling without replacement.

Every document draws an exponential key -ln(u)/w, u a hash of its id and w its quality weight; taking
the smallest keys first is Efraimidis-Spirakis sampling. A source whose target holds e whole epochs
gives each document e times, then documents in key order until the rest of the target is used up; the
document at that boundary gives its first words only, so the budget is met to the word.

Only the boundary needs sorted rows. Sizes are summed per (source, key bucket), the running sums of
those few rows find the bucket where a source's budget ends, and a window sorts that bucket alone: a
source with a third of all rows is never in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cuts import written
from .hot import beside
from .words import word_array

KEY_BUCKETS = 4096
MOST_EPOCHS = 3
FEW_SOURCES = 50_000
#: u = (first 13 hex digits of the hash + 1) / (2^52 + 2) lies strictly between 0 and 1.
HEX_DIGITS, SPAN = 13, float(2**52 + 2)


def quality_weight(words: Column) -> Column:
    """Share of distinct words, at least a quarter: repeated lines and junk weigh less. Empty texts weigh 1."""
    n = F.size(words)
    return F.when(n == 0, 1.0).otherwise(F.greatest(F.lit(0.25), F.size(F.array_distinct(words)) / n))


def exponential_key(doc_id: Column, weight: Column, seed: int, body: Column) -> Column:
    """-ln(u)/weight with u from the md5 of the seed and the id; where the id is null, of the text `body`."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.concat(F.lit("null:"), F.md5(F.coalesce(body, F.lit(""))))))
    u = (F.conv(F.substring(F.md5(text), 1, HEX_DIGITS), 16, 10).cast("double") + 1.0) / SPAN
    return -F.log(u) / weight


def source_targets(sizes: DataFrame) -> DataFrame:
    """`sizes` (source_key, source, source_size; one row a source) with column target.

    Sources by code point, null last, weigh 1, 2, 3, repeating. Sharing, stopping at MOST_EPOCHS times
    a source's size and resharing the excess ends at target = min(stop, level * weight); the level
    follows from running sums over sources sorted by stop / weight, one row a source.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    stop, weight = F.col("stop"), F.col("weight")
    ranked = sizes.withColumn("weight", ((F.row_number().over(by_name) - 1) % 3 + 1).cast("double"))
    ranked = ranked.withColumn("stop", (MOST_EPOCHS * F.col("source_size")).cast("double"))
    order = Window.orderBy((stop / weight), F.col("source").asc_nulls_last())
    below, rest = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy()
    ranked = ranked.withColumn(
        "level",
        (F.sum("source_size").over(everything).cast("double") - F.coalesce(F.sum("stop").over(below), F.lit(0.0)))
        / F.sum("weight").over(rest),
    )
    holds = F.when(F.col("level") * weight <= stop, F.col("level"))
    level = F.coalesce(F.first(holds, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), F.lit(float("inf")))
    return ranked.withColumn("target", F.least(stop, level * weight)).select("source_key", "source_size", "target")


def mix(docs: DataFrame, seed: int = 17, owner: str = "session") -> DataFrame:
    """One row per row of `docs`: doc_id, size, source_size, target, epochs, taken.

    docs needs doc_id, text and source; other columns are ignored. size is the number of words (0 for
    null or blank text), taken the words the mix takes from the document, repeats counted, at most
    MOST_EPOCHS times its size. Null sources form one source, null ids and repeated rows are documents
    like others (ties of the key go by doc_id, then size, and any order of equal rows gives the same
    rows). An empty table gives no rows. Runs with one seed agree, however the table is split.
    """
    return _mix(docs, seed, owner).drop("print")


def _mix(docs: DataFrame, seed: int, owner: str) -> DataFrame:
    """`mix` with a fingerprint of the text in column print."""
    keyed = docs.select("doc_id", "source", _source_key().alias("source_key"), "text", word_array(F.col("text")).alias("words")).select(
        "doc_id",
        "source",
        "source_key",
        _print().alias("print"),
        F.size("words").cast("long").alias("size"),
        exponential_key(F.col("doc_id"), quality_weight(F.col("words")), seed, F.col("text")).alias("key"),
    )
    # exp(-key/2) spreads keys of weights from 0.25 to 1 over all buckets.
    keyed = keyed.withColumn("bucket", F.floor(KEY_BUCKETS * (1.0 - F.exp(-F.col("key") / 2))).cast("int"))
    keyed = written(keyed, "mix-keys", owner)

    by_bucket = keyed.groupBy("source_key", "source", "bucket").agg(F.sum("size").alias("bucket_size"))
    by_bucket = written(by_bucket, "mix-buckets", owner)
    sizes = by_bucket.groupBy("source_key", "source").agg(F.sum("bucket_size").alias("source_size"))
    targets = source_targets(sizes)
    targets = targets.withColumn(
        "epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    ).withColumn("budget", F.floor(F.col("target") - F.col("epochs") * F.col("source_size") + 0.5).cast("long"))
    running = Window.partitionBy("source_key").orderBy("bucket")
    edges = (
        by_bucket.withColumn("upto", F.sum("bucket_size").over(running))
        .withColumn("before", F.col("upto") - F.col("bucket_size"))
        .join(targets, "source_key")
        .where(F.col("upto") > F.col("budget"))
        .groupBy("source_key")
        .agg(F.min(F.struct("bucket", "before")).alias("edge"))
    )
    plan = written(
        targets.join(edges, "source_key", "left").select(
            "source_key", "source_size", "target", "epochs", "budget",
            F.coalesce("edge.bucket", F.lit(KEY_BUCKETS + 1)).alias("edge_bucket"),
            F.coalesce("edge.before", F.lit(0)).cast("long").alias("edge_before"),
        ),
        "mix-plan",
        owner,
    )
    # One short row a source: broadcast if counted to be few, else a plain join, which splits hot sources.
    planned = keyed.join(F.broadcast(plan) if plan.count() <= FEW_SOURCES else plan, "source_key")
    shown = ["doc_id", "source", "print", "size", "source_size", "target", "epochs"]
    away = planned.where(F.col("bucket") != F.col("edge_bucket")).select(
        *shown, (F.col("epochs") * F.col("size") + F.when(F.col("bucket") < F.col("edge_bucket"), F.col("size")).otherwise(0)).alias("taken")
    )
    in_order = Window.partitionBy("source_key").orderBy("key", "doc_id", "size", "print").rowsBetween(Window.unboundedPreceding, -1)
    at_edge = (
        planned.where(F.col("bucket") == F.col("edge_bucket"))
        .withColumn("left", F.col("budget") - F.col("edge_before") - F.coalesce(F.sum("size").over(in_order), F.lit(0)))
        .select(*shown, (F.col("epochs") * F.col("size") + F.greatest(F.lit(0), F.least(F.col("size"), F.col("left")))).alias("taken"))
    )
    return away.unionByName(at_edge)


def mixed_documents(docs: DataFrame, seed: int = 17, owner: str = "session") -> DataFrame:
    """`docs` with every document repeated as often as the mix takes it, a cut one counting from one half on.

    The columns stay those of `docs`, whatever their names; documents without words are in no mix. Rows that share id,
    source and text are taken as often as the one of them that is taken most; rows that share only the id are apart.
    """
    taken = F.floor(F.col("taken") / F.col("size") + 0.5).cast("int")
    times = _mix(docs.select("doc_id", "text", "source"), seed, owner).where(F.col("size") > 0)
    times = times.groupBy(F.struct(_id().alias("id"), _source_key().alias("source"), "print").alias("key")).agg(F.max(taken).alias("times")).where("times > 0")
    keyed = beside(docs, key=F.struct(_id().alias("id"), _source_key().alias("source"), _print().alias("print")))
    return keyed.join(times, "key").select("row", F.explode(F.sequence(F.lit(1), F.col("times"))).alias("turn")).select("row.*")


def _id() -> Column:
    return F.coalesce(F.col("doc_id").cast("string"), F.lit(""))


def _print() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def _source_key() -> Column:
    """Tells the null source from every other."""
    return F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("n"))


ORACLE = """
WITH d AS (
  SELECT doc_id, source, text, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), k AS (
  SELECT doc_id, source, CAST(len(w) AS BIGINT) AS size,
    -ln((CAST(CAST('0x' || substr(md5('17:' || coalesce(CAST(doc_id AS VARCHAR), 'null:' || md5(coalesce(text, '')))), 1, 13) AS BIGINT) AS DOUBLE) + 1.0) / 4503599627370498.0)
      / CASE WHEN len(w) = 0 THEN 1.0 ELSE greatest(0.25, CAST(list_unique(w) AS DOUBLE) / len(w)) END AS key
  FROM d
), s AS (
  SELECT source, sum(size) AS n FROM k GROUP BY source
), r AS (
  SELECT source, n, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS wt, CAST(3 * n AS DOUBLE) AS stop FROM s
), l AS (
  SELECT *, (CAST(sum(n) OVER () AS DOUBLE) - coalesce(sum(stop) OVER (ORDER BY stop / wt, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
      / sum(wt) OVER (ORDER BY stop / wt, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level,
    row_number() OVER (ORDER BY stop / wt, source NULLS LAST) AS rn FROM r
), t AS (
  SELECT source, n, least(stop, coalesce((SELECT arg_min(level, rn) FROM l WHERE level * wt <= stop), 1e300) * wt) AS target FROM l
), e AS (
  SELECT source, n, target, CASE WHEN n > 0 THEN CAST(floor(target / n) AS BIGINT) ELSE 0 END AS epochs FROM t
), b AS (
  SELECT *, CAST(floor(target - epochs * n + 0.5) AS BIGINT) AS budget FROM e
)
SELECT k.doc_id, k.source, k.size, CAST(b.n AS BIGINT) AS source_size, b.target, b.epochs,
  CAST(b.epochs * k.size + greatest(0, least(k.size, b.budget - coalesce(sum(k.size) OVER (PARTITION BY k.source ORDER BY k.key, k.doc_id, k.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))) AS BIGINT) AS taken
FROM k JOIN b ON k.source IS NOT DISTINCT FROM b.source
"""
