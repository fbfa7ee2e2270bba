"""What registered experiments ask of the methods, seen by stand-ins that only note it."""

from types import SimpleNamespace

import numpy as np
import pytest

import __spark_entry__ as entry
from curvature_spark.operators.rounds import RoundLog
from curvature_spark.plans import experiments

KINDS = ["identity", "topk", "randk", "windowk", "tight", "natural"]
ROW = {"run_id": "r", "round": 0, "f": 0.0, "grad_norm": 0.0, "l": 0.0, "items": 0, "bytes": 0, "step_s": 0, "seconds": 0.0}


@pytest.fixture
def asked(monkeypatch):
    """Bounds on rounds by method, in the order of the calls."""
    notes: dict[str, list[int]] = {}
    log = RoundLog([ROW])

    def method(name, result):
        def run(*_, rounds=None, **__):
            notes.setdefault(name, []).append(rounds)
            return result

        return run

    fit = SimpleNamespace(log=log, seconds=0.0, rounds=1, bytes=0)
    clients = SimpleNamespace(release=lambda: None)
    monkeypatch.setattr(experiments, "_clients", lambda spark, sf_dir, workload, n: (clients, None, 0.0))
    monkeypatch.setattr(experiments, "_library", lambda *_: ("mllib", 0.0, 0.0, 0, 0.0, 0, True))
    for name in ("train_shifts", "train_partial"):
        monkeypatch.setattr(experiments, name, method(name, fit))
    for name in ("damped_newton", "admm", "lbfgs"):
        monkeypatch.setattr(experiments.baselines, name, method(name, (np.zeros(1), log)))
    return notes


def test_onehot_curves_are_not_cut(spark, small, asked):
    """All kinds, three methods, and no bound below the published thousand rounds."""
    assert entry.queries()["experiment_curves_onehot"](spark, small).count() == 3 * len(KINDS)
    assert asked["train_shifts"] == [1000] * 2 * len(KINDS) and asked["train_partial"] == [1000] * len(KINDS)


def test_sparse_solvers_are_not_cut(spark, small, asked):
    """Window messages need 178 rounds of search at sf0.1, splitting is at 5e-4 after 120: no bound below a thousand."""
    rows = entry.queries()["experiment_solvers_sparse"](spark, small).collect()
    assert len(rows) == len(KINDS) + 4 and asked["train_shifts"] == [1000] * len(KINDS)
    assert asked["admm"] == [1000] and asked["lbfgs"] == [1000] and len(asked["damped_newton"]) == 1
