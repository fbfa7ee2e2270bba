"""Rounds of some clients, and binary blocks that are multiplied without a matrix."""

import numpy as np
import pyarrow as pa
import pytest

from curvature_spark.operators import compressors, features
from curvature_spark.operators.partition import Clients, Ones, hot_rows, pin
from curvature_spark.operators.rounds import Engine
from curvature_spark.plans.workloads import PROBLEM


@pytest.mark.parametrize("even", [True, False])
def test_positions_multiply_as_their_matrix(even):
    rng = np.random.default_rng(5)
    places = [sorted(rng.choice(20, 4 if even else rng.integers(0, 6), replace=False).tolist()) for _ in range(50)]
    ones = Ones(rng.choice([-1.0, 1.0], 50), np.array([len(p) for p in places], np.uint32), np.array(sum(places, []), np.uint16), 20)
    z, x, s = ones.matrix(), rng.normal(size=20), rng.normal(size=50)
    assert ones @ x == pytest.approx(z @ x) and ones.T @ s == pytest.approx(z.T @ s)
    for count in (1, 7):
        points = rng.normal(size=(count, 20))
        assert PROBLEM.values(ones, points) == pytest.approx(PROBLEM.values(z, points))
    for a, b in zip(PROBLEM.sums(ones, x), PROBLEM.sums(z, x), strict=True):
        assert a == pytest.approx(b)


def test_repeated_positions_count_once():
    _, counts, at = hot_rows(pa.array([[3, 1, 3], [], [2, 2]]), np.ones(3), 4)
    assert counts.tolist() == [2, 0, 1] and sorted(at[:2].tolist()) == [1, 3] and at[2] == 2


def test_resting_clients_pass_through_a_round(spark):
    """A round of some clients makes no union with the shifts of the others and leaves these as they were."""
    rng = np.random.default_rng(6)
    rows = [(str(i), int(i % 6), 1.0 if rng.random() < 0.5 else -1.0, [*map(int, np.nonzero(rng.random(12) < 0.3)[0]), 12]) for i in range(240)]
    clients = pin(spark.createDataFrame(rows, "sample_key string, client_id long, label double, hot array<int>"), 13)
    results = []
    for salted in (False, True):
        held = Clients(clients.blocks, clients.d, clients.rows, hot=clients.hot, together=not salted, parts=clients.parts)
        engine, x = Engine(held, PROBLEM, compressors.make("topk", 20), 1.0), np.zeros(13)
        engine.start(x, "hessian")
        before = {r.client_id: r.h for r in engine.shifts.collect()}
        x = x + 0.3
        means = [engine.round(x, k, only, track=True) for k, only in enumerate(([1, 4], [0, 1, 2], [5]))]
        after = {r.client_id: r.h for r in engine.shifts.collect()}
        assert [m.clients for m in means] == [2, 3, 1] and sorted(after) == list(range(6))
        assert after[3] == before[3] and all(after[c] != before[c] for c in (0, 1, 2, 4, 5))
        assert "Union" not in engine.shifts._jdf.queryExecution().optimizedPlan().toString()
        results.append({c: np.frombuffer(h) for c, h in after.items()})
        engine.release()
    assert all(results[0][c] == pytest.approx(results[1][c]) for c in range(6))
    clients.release()


def test_pinned_blocks_forget_how_samples_were_made(spark, small):
    """What every round plans on is a table of blocks, not the joins behind the samples."""
    samples = features.portable_split(features.onehot(spark, small), 4)
    clients = pin(samples, features.DIMENSIONS["onehot"])
    assert "Join" in samples._jdf.queryExecution().analyzed().toString()
    assert "Join" not in clients.blocks._jdf.queryExecution().analyzed().toString()
    assert sum(clients.rows.values()) == samples.count()
    clients.release()
