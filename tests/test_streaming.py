"""Partial participation on a stream approaches the answer of the whole table."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvature_spark.operators import features
from curvature_spark.operators.partition import pin
from curvature_spark.operators.problems import LogisticProblem
from curvature_spark.operators.rounds import global_gradient
from curvature_spark.streaming.events import stream_dedup, stream_hsn_pp, stream_static_join


def test_streamed_rounds_reduce_the_gradient(spark, small):
    log = stream_hsn_pp(spark, small, parts=4).orderBy("batch").collect()
    clients = pin(features.users(spark, small).withColumn("client_id", F.col("user_id")), 5)
    norm = lambda x: np.linalg.norm(global_gradient(clients, LogisticProblem(1e-3), np.array(x))[1])
    xs = [[r[f"x{i}"] for i in range(5)] for r in log]
    assert [r.batch for r in log] == list(range(4)) and all(r.active <= r.clients for r in log)
    assert norm(xs[-1]) < 0.2 * norm(xs[0])


@pytest.mark.parametrize("query", [stream_dedup, stream_static_join])
def test_stream_rows_stay_out_of_the_driver(spark, small, query):
    rows = query(spark, small)
    plan = rows._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan and "MemoryPlan" not in plan and "LocalRelation" not in plan
    want = spark.read.parquet(f"{small}/events.parquet").select("event_id").collect()
    assert sorted(r.event_id for r in rows.select("event_id").collect()) == sorted(r.event_id for r in want)


def test_sums_of_many_users_at_once():
    rng = np.random.default_rng(4)
    z, x, user = rng.normal(size=(50, 5)), rng.normal(size=5), rng.integers(0, 7, 50)
    g, h = LogisticProblem().grouped(z, x, user, 8)
    for u in range(8):
        _, own_g, own_h = LogisticProblem().sums(z[user == u], x)
        assert np.allclose(g[u], own_g) and np.allclose(h[u], own_h)
