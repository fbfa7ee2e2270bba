"""Streams over `events`: windows, late rows, deduplication, joins, per-client state, and partial-participation training.

Files of the table are the stream; `available now` triggers run it to its end. State lives in checkpoints below
the shared folder, so a restarted query goes on where it stopped.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import packed
from ..operators.compressors import TopK
from ..operators.problems import LogisticProblem
from ..operators.server import cholesky_solve
from ..plans.cuts import shared_dir
from ..sources.catalog import load

#: Bytes of a row group in a part that is a single file.
ROW_GROUP = 4 << 20
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, sf_dir: str, parts: int = 1) -> tuple[DataFrame, str]:
    """The events as a stream of `parts` batches in order of time, and its folder.

    One part is one batch of as many files as tasks wrote. Several parts have one file each, one a trigger, whose row
    groups are read by several tasks.
    """
    folder = f"{shared_dir(spark)}/tables/stream-{uuid.uuid4().hex}"
    rows = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    for p in range(parts):
        day = F.dayofmonth("ts") - 1
        piece = rows if parts == 1 else rows.where((day * parts / 31).cast("int") == p).coalesce(1)
        piece.write.option("parquet.block.size", ROW_GROUP).parquet(f"{folder}/part={p}")
    stream = spark.readStream.schema(SCHEMA)
    return (stream if parts == 1 else stream.option("maxFilesPerTrigger", "1")).parquet(f"{folder}/part=*"), folder


def run(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what there is into a written table, and return that table.

    Tasks write the rows; none pass through the driver. A batch that is repeated replaces its own folder.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/tables/stream-{uuid.uuid4().hex}"
    done: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows-{number}")
        done.append(number)

    with _state_on_disk(spark):
        writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
        writer.foreachBatch(keep).start().awaitTermination()
    kept = done[-1:] if mode == "complete" else sorted(set(done))
    return spark.read.schema(stream.schema).parquet(*[f"{base}/rows-{number}" for number in kept]) if kept else spark.createDataFrame([], stream.schema)


@contextmanager
def _state_on_disk(spark: SparkSession) -> Iterator[None]:
    """While a stream starts and runs: keys lie in RocksDB, not on the heap."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def _windows(window) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark, sf_dir):
        stream, _ = source(spark, sf_dir)
        agg = stream.withWatermark("ts", "1 hour").groupBy(window(), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("v"))
        return run(agg.select(F.col("w.start").alias("start"), "event_type", "n", "v"), "complete")

    return query


stream_tumbling = _windows(lambda: F.window("ts", "1 day").alias("w"))
stream_sliding = _windows(lambda: F.window("ts", "2 days", "1 day").alias("w"))


def stream_session(spark, sf_dir):
    stream, _ = source(spark, sf_dir)
    agg = stream.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return run(agg.select(F.col("w.start").alias("start"), "user_id", "n"), "complete")


def stream_dedup(spark, sf_dir):
    """Repeated ids within the watermark pass once; the stream is the table twice."""
    one, folder = source(spark, sf_dir)
    again = spark.readStream.schema(SCHEMA).parquet(f"{folder}/part=*")
    both = one.unionByName(again).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return run(both.select("event_id", "user_id"), "append")


def stream_static_join(spark, sf_dir):
    stream, _ = source(spark, sf_dir)
    kinds = load(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.avg("value"), 6).alias("mean"))
    return run(stream.join(kinds, "event_type").select("event_id", "mean"), "append")


def stream_watermark_late(spark, sf_dir):
    """Rows later than the watermark are left out: of a stream in four parts, the third has old rows, which no window takes
    any more, and the fourth moves time on so that the windows close. The filter for late rows lags one batch."""
    rows = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    folder = f"{shared_dir(spark)}/tables/late-{uuid.uuid4().hex}"
    later = rows.where("day(ts) >= 29").withColumn("ts", F.col("ts") + F.expr("INTERVAL 60 DAYS"))
    for n, part in enumerate((rows.where("day(ts) BETWEEN 20 AND 28"), rows.where("day(ts) >= 29"), rows.where("day(ts) < 5"), later)):
        part.coalesce(1).write.parquet(f"{folder}/part={n}")
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", "1").parquet(f"{folder}/part=*")
    agg = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return run(agg.select(F.col("w.start").alias("start"), "n"), "append").where("month(start) = 1")


def stream_stateful_shift(spark, sf_dir):
    """Per user, a running mean of the value kept as state: H moves by the compressed (here whole) difference."""
    stream, _ = source(spark, sf_dir, parts=3)

    def update(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, cents = state.get if state.exists else (0, 0)
        for pdf in batches:
            n, cents = n + len(pdf), cents + int(np.round(pdf["value"] * 100).sum())
        state.update((n, cents))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "shift": [cents / 100 / n]})

    out = stream.select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, shift double", "n long, cents long", "update", GroupStateTimeout.NoTimeout)
    table = run(out, "update")
    return table.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("shift", "n"), 6).alias("shift"))


def stream_hsn_pp(spark, sf_dir, parts: int = 6, lam: float = 1e-3):
    """Partial participation on a stream: the users of a micro-batch are the clients of the round.

    Rows accumulate per user in a table; a round solves for x, then the active users update shift, error norm
    and corrected gradient from their rows so far. A batch commits by its number, so a repeated batch changes nothing.
    """
    import pyarrow as pa

    from ..operators.features import user_samples

    stream, _ = source(spark, sf_dir, parts)
    problem, compressor, d = LogisticProblem(lam), TopK(5), 5
    w = packed.length(d)
    base = f"{shared_dir(spark)}/tables/stream-model-{uuid.uuid4().hex}"
    model = {"h": np.zeros(w), "l": 0.0, "g": np.zeros(d), "n": 0, "state": None, "log": [], "done": set()}

    def step(batch: DataFrame, number: int) -> None:
        if number in model["done"] or batch.isEmpty():
            return
        path = f"{base}/rows-{number}"
        user_samples(batch).select("user_id", "label", "features").repartition("user_id").write.mode("overwrite").parquet(path)
        rows = spark.read.parquet(*[f"{base}/rows-{i}" for i in sorted(model["done"] | {number})])
        active = spark.read.parquet(path).select("user_id").distinct()
        x = cholesky_solve(packed.unpack(model["h"], d) + model["l"] * np.eye(d), model["g"]) if model["n"] else np.zeros(d)

        def sums(batches):
            for rows in batches:
                ids, group = np.unique(rows.column("user_id").to_numpy(zero_copy_only=False), return_inverse=True)
                z = rows.column("features").flatten().to_numpy(zero_copy_only=False).reshape(-1, d) * rows.column("label").to_numpy(zero_copy_only=False)[:, None]
                g, h = problem.grouped(z, x, group, len(ids))
                lists = [pa.ListArray.from_arrays(np.arange(0, v.size + 1, v.shape[1], dtype=np.int32), v.ravel()) for v in (g, h)]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.bincount(group, minlength=len(ids)), pa.int64()), *lists], ["user_id", "n", "g", "h"])

        def advance(batches):
            for pdf in batches:
                out = []
                for user, n, g, h, shift, l, q in zip(pdf["user_id"], pdf["n"], pdf["g"], pdf["h"], pdf["shift"], pdf["l"], pdf["q"], strict=True):
                    _, g, h = problem.finish(n, (0.0, np.array(g), np.array(h)), x)
                    new = shift is None
                    old = h.copy() if new else np.array(shift, dtype=float)
                    moved = old + compressor(h - old, d, (0,)).dense(w)
                    gap = packed.frobenius(h - moved, d)
                    corrected = packed.unpack(moved, d) @ x + gap * x - g
                    out.append((user, moved.tolist(), gap, corrected.tolist(), (moved - (0 if new else old)).tolist(), gap - (0 if new else l), (corrected - (0 if new else np.array(q))).tolist(), int(new)))
                yield pd.DataFrame(out, columns=["user_id", "shift", "l", "q", "dh", "dl", "dq", "new"])

        # Rows become sums where they are read; a user with many events sends one row of sums a batch.
        parts = rows.join(active, "user_id", "left_semi").mapInArrow(sums, "user_id long, n long, g array<double>, h array<double>")
        total = lambda c, size: F.array(*[F.sum(F.col(c)[i]) for i in range(size)]).alias(c)
        own = parts.groupBy("user_id").agg(F.sum("n").alias("n"), total("g", d), total("h", w).alias("h"))
        blank = {"shift": F.lit(None).cast("array<double>"), "l": F.lit(0.0), "q": F.lit(None).cast("array<double>")}
        joined = own.join(model["state"], "user_id", "left") if model["state"] is not None else own.withColumns(blank)

        schema = "user_id long, shift array<double>, l double, q array<double>, dh array<double>, dl double, dq array<double>, new int"
        joined.select("user_id", "n", "g", "h", "shift", "l", "q").mapInPandas(advance, schema).write.mode("overwrite").parquet(f"{base}/made-{number}")
        made = spark.read.parquet(f"{base}/made-{number}")
        state = made.select("user_id", "shift", "l", "q")
        if model["state"] is not None:
            state = model["state"].join(made.select("user_id"), "user_id", "left_anti").unionByName(state)
        state.write.mode("overwrite").parquet(f"{base}/state-{number}")
        sums = made.agg(F.sum("new"), F.sum("dl"), *[F.sum(F.col("dh")[i]) for i in range(w)], *[F.sum(F.col("dq")[i]) for i in range(d)], F.count(F.lit(1))).first()
        n = model["n"] + sums[0]
        model["h"] = (model["h"] * model["n"] + np.array(sums[2 : 2 + w])) / n
        model["l"] = (model["l"] * model["n"] + sums[1]) / n
        model["g"] = (model["g"] * model["n"] + np.array(sums[2 + w : 2 + w + d])) / n
        model["n"], model["state"] = n, spark.read.parquet(f"{base}/state-{number}")
        model["log"].append((number, int(sums[-1]), int(n), *x.tolist()))
        model["done"].add(number)

    stream.writeStream.foreachBatch(step).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint").start().awaitTermination()
    return spark.createDataFrame(model["log"], "batch int, active int, clients int, " + ", ".join(f"x{i} double" for i in range(d)))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (stream_session, stream_dedup, stream_static_join, stream_watermark_late, stream_stateful_shift, stream_hsn_pp)
    return {"stream_tumbling": stream_tumbling, "stream_sliding": stream_sliding} | {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {
        "stream_tumbling": "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY 1, 2",
        "stream_sliding": "SELECT CAST(date_trunc('day', ts) - o * INTERVAL 1 DAY AS TIMESTAMP) AS start, event_type, count(*) AS n, round(sum(value), 4) AS v FROM events, (SELECT unnest([0, 1]) AS o) GROUP BY 1, 2",
        "stream_session": "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS b FROM events), s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT min(ts) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k",
        "stream_dedup": "SELECT event_id, user_id FROM events",
        "stream_static_join": "SELECT event_id, m.mean FROM events e JOIN (SELECT event_type, round(avg(value), 6) AS mean FROM events GROUP BY 1) m ON e.event_type = m.event_type",
        "stream_stateful_shift": "SELECT user_id, count(*) AS n, round(sum(CAST(round(value * 100) AS BIGINT)) / 100.0::DOUBLE / count(*), 6) AS shift FROM events GROUP BY user_id",
        "stream_watermark_late": "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, count(*) AS n FROM events WHERE day(ts) >= 20 GROUP BY 1",
    }
