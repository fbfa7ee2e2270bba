"""Slow baselines reach the minimiser that SQL finds, on gradients computed in this process."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from curvature_spark.operators import baselines
from curvature_spark.plans import workloads


@pytest.mark.parametrize("name", ["baseline_accelerated_gradient", "baseline_compressed_differences"])
def test_slow_baselines_meet_the_minimiser(spark, small, monkeypatch, name):
    clients, problem, data = workloads.tiny_clients(spark, small), workloads.PROBLEM, {}
    for r in clients.blocks.collect():
        data.setdefault(r.client_id, []).append(np.frombuffer(r.z).reshape(r.n_rows, -1))
    data = {c: np.concatenate(z) for c, z in data.items()}

    def local(_clients, _problem, x):
        return {c: problem.finish(len(z), problem.sums(z, x), x)[1] for c, z in data.items()}

    monkeypatch.setattr(baselines, "client_gradients", local)
    monkeypatch.setattr(baselines, "global_gradient", lambda c, p, x: (0.0, sum(clients.weight[i] * g for i, g in local(c, p, x).items())))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{small}/lineitem.parquet')")
    assert np.array(con.execute(entry.oracle_sql()[name]).fetchone()[1:]) == pytest.approx(workloads.CONVERGING[name](clients), abs=1.5e-6)


def test_no_baseline_is_held_against_a_literal():
    sql = entry.oracle_sql()
    assert all("x8" in sql[name] for name in sql if name.startswith("baseline_"))
