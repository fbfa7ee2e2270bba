"""The experiments as queries: comparisons of methods, curves, ablations, memory, cost figures.

Times are this machine's, so these have no SQL; what must hold whatever the machine (who sends less, who
needs more rounds, equalities of the theory) is given as booleans with SQL. Client counts, budgets and tolerances are
those listed for the three workloads; the bounds on rounds are parameters of the functions here. `experiment_curves_onehot`
and `experiment_solvers_sparse` are registered without smaller ones, the others with those named below, each run telling
whether it reached its tolerance.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import packed
from ..operators import baselines, compressors, costmodel, features, metrics, server
from ..operators.methods import Fit, train_partial, train_shifts
from ..operators.partition import Clients, pin
from ..operators.rounds import RoundLog, global_oracles
from .workloads import DENSE, ORDER_CLIENTS, PROBLEM, _rows, dense_clients, moments, order_clients

Query = Callable[[SparkSession, str], DataFrame]
K = 8 * DENSE
WORKLOADS = ("dense", "onehot", "sparse")
SEARCH = (0.49, 0.5)
LOG = "run string, init_s double, solve_s double, rounds int, grad_norm double, bytes long, reached boolean"
#: Rounds of a registered run: base method, line search, curves and multi-node (the curves of `onehot` and the solvers of
#: `sparse` end at their tolerance), and the first-order and splitting baselines.
BASE_ROUNDS, SEARCH_ROUNDS, CURVE_ROUNDS, BASELINE_ROUNDS, SPLITTING_ROUNDS = 20, 20, 6, 40, 8


def _log(name: str, init: float, fit: Fit, tol: float) -> tuple:
    norm = fit.log.rows[-1]["grad_norm"]
    return name, init, fit.seconds, fit.rounds, norm, fit.bytes, norm < tol


def _baseline(name: str, init: float, seconds: float, log: RoundLog, tol: float) -> tuple:
    norm = log.rows[-1]["grad_norm"]
    return name, init, seconds, len(log.rows), norm, sum(r["bytes"] for r in log.rows), norm < tol


def _clients(spark: SparkSession, sf_dir: str, workload: str, n: int) -> tuple[Clients, DataFrame, float]:
    began = time.monotonic()
    samples = features.portable_split(features.BUILDERS[workload](spark, sf_dir), n)
    return pin(samples, features.DIMENSIONS[workload]), samples, time.monotonic() - began


def base_method(spark, sf_dir, workload: str, n: int, rounds: int = 200, tol: float = 1e-12) -> DataFrame:
    """Base method, all compressors, option 'shift'."""
    clients, _, init = _clients(spark, sf_dir, workload, n)
    d = features.DIMENSIONS[workload]
    out = [_log(kind, init, train_shifts(clients, PROBLEM, compressors.make(kind, 8 * d), option="shift", rounds=rounds, tol=tol), tol) for kind in compressors.KINDS]
    clients.release()
    return _rows(spark, LOG, out)


def solvers(spark, sf_dir, workload: str, n: int = 142, tol: float = 9e-10, rounds: int = 1000, baseline_rounds: int = 1000, splitting_rounds: int = 1000) -> DataFrame:
    """Line search with all compressors against stand-ins for centralised and splitting solvers."""
    clients, samples, init = _clients(spark, sf_dir, workload, n)
    d, out = features.DIMENSIONS[workload], []
    for kind in compressors.KINDS:
        out.append(_log(f"search_{kind}", init, train_shifts(clients, PROBLEM, compressors.make(kind, 8 * d), line_search=SEARCH, tol=tol, rounds=rounds), tol))
    for name, solve in (
        ("damped_newton", lambda: baselines.damped_newton(clients, PROBLEM, tol=tol)),
        ("admm", lambda: baselines.admm(clients, PROBLEM, tol=tol, rounds=splitting_rounds)),
        ("lbfgs", lambda: baselines.lbfgs(clients, PROBLEM, tol=tol, rounds=baseline_rounds)),
    ):
        began = time.monotonic()
        _, log = solve()
        out.append(_baseline(name, init, time.monotonic() - began, log, tol))
    out.append(_library(clients, samples, d, tol))
    clients.release()
    return _rows(spark, LOG, out)


def _library(clients: Clients, samples: DataFrame, d: int, tol: float) -> tuple:
    """MLlib minimises the mean over rows, clients of equal size or not; the gradient is that of its own objective."""
    x, seconds = baselines.mllib_logistic(samples, PROBLEM.lam, d=d)
    pooled = Clients(clients.blocks, clients.d, clients.rows, "pooled", clients.together, clients.hot, clients.parts)
    norm = float(np.linalg.norm(global_oracles(pooled, PROBLEM, x)[1]))
    return "mllib", 0.0, seconds, 0, norm, 0, norm < tol


def multi_node(spark, sf_dir, workload: str, n: int = 50, tol: float = 1e-9, rounds: int = 200, baseline_rounds: int = 200) -> DataFrame:
    """All compressors with the base step and with the search, against MLlib and data-parallel L-BFGS; seconds a round and
    what the search adds to them."""
    clients, samples, init = _clients(spark, sf_dir, workload, n)
    d, out, added = features.DIMENSIONS[workload], [], []
    for kind in compressors.KINDS:
        base = train_shifts(clients, PROBLEM, compressors.make(kind, 8 * d), tol=tol, rounds=rounds)
        search = train_shifts(clients, PROBLEM, compressors.make(kind, 8 * d), line_search=SEARCH, tol=tol, rounds=rounds)
        out += [_log(f"base_{kind}", init, base, tol), _log(f"search_{kind}", init, search, tol)]
        added.append((search.seconds / search.rounds) / (base.seconds / base.rounds))
    began = time.monotonic()
    _, log = baselines.lbfgs(clients, PROBLEM, tol=tol, rounds=baseline_rounds)
    out += [_baseline("lbfgs", init, time.monotonic() - began, log, tol), _library(clients, samples, d, tol)]
    clients.release()
    return _rows(spark, LOG, out).withColumn("search_slowdown", F.lit(float(np.median(added))))


def curves(spark, sf_dir, workload: str, n: int = 50, tau: int = 12, rounds: int = 1000) -> DataFrame:
    """Gradient norm against round, bytes and time, all compressors: base method, line search, partial participation."""
    clients, _, _ = _clients(spark, sf_dir, workload, n)
    log, least = RoundLog(), baselines.damped_newton(clients, PROBLEM)[1].rows[-1]["f"]
    for kind in compressors.KINDS:
        c = compressors.make(kind, 8 * features.DIMENSIONS[workload])
        log.rows += train_shifts(clients, PROBLEM, c, rounds=rounds, run_id=f"base_{kind}").log.rows
        log.rows += train_shifts(clients, PROBLEM, c, rounds=rounds, line_search=SEARCH, run_id=f"search_{kind}").log.rows
        log.rows += train_partial(clients, PROBLEM, c, tau, rounds=rounds, run_id=f"partial_{kind}").log.rows
    clients.release()
    return log.frame(spark).withColumn("gap", F.col("f") - F.lit(float(least)))


def experiment_network(spark, sf_dir):
    """Ten clients, the sparse workload: messages with explicit and with rebuilt indices, measured, and on the published network."""
    clients, _, init = _clients(spark, sf_dir, "sparse", 10)
    out = []
    for kind, indices in (("topk", "explicit"), ("randk", "explicit"), ("randk", "seed"), ("windowk", "seed")):
        fit = train_shifts(clients, PROBLEM, compressors.make(kind, 8 * 301, indices=indices), rounds=10, tol=0.0, option="shift")
        out.append((f"{kind}_{indices}", fit.rounds, fit.bytes, fit.seconds, costmodel.transfer_seconds(float(fit.bytes), 476.79)))
    clients.release()
    return _rows(spark, "run string, rounds int, bytes long, seconds double, published_network_s double", out)


def experiment_order(spark, sf_dir):
    """What holds on any machine: bytes and rounds by compressor, participation against rounds."""
    clients = dense_clients(spark, sf_dir, 10)
    fits = {kind: train_shifts(clients, PROBLEM, compressors.make(kind, K), rounds=10, tol=0.0) for kind in ("identity", "topk", "windowk", "tight")}
    norm = {k: f.log.rows[-1]["grad_norm"] for k, f in fits.items()}
    few = train_partial(clients, PROBLEM, compressors.make("topk", K), 2, rounds=8, tol=0.0, probe_every=8)
    rows = [
        ("tight_sends_least", fits["tight"].bytes < fits["windowk"].bytes < fits["topk"].bytes < fits["identity"].bytes),
        ("tight_converges_slower", norm["tight"] > norm["topk"]),
        ("identity_converges_fastest", norm["identity"] <= min(norm["windowk"], norm["tight"])),
        ("partial_sends_its_share", few.log.rows[0]["bytes"] * 5 == fits["topk"].log.rows[0]["bytes"]),
    ]
    return _rows(spark, "claim string, holds boolean", rows)


ORDER_SQL = "SELECT claim, true AS holds FROM (VALUES ('tight_sends_least'), ('tight_converges_slower'), ('identity_converges_fastest'), ('partial_sends_its_share')) t(claim)"


def experiment_tight_expectation(spark, sf_dir):
    """Mean lost share of the square over 3,000 draws against 1 - K / w, on the second moments of the embeddings."""
    d, k = 10, 12
    v, w = moments(spark, sf_dir, d), packed.length(d)

    def run(batches):
        import pyarrow as pa

        c = compressors.make("tight", k)
        for batch in batches:
            lost = [packed.frobenius(c(v, d, (s,)).dense(w) - v, d) ** 2 / packed.frobenius(v, d) ** 2 for s in batch.column("id").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(lost, pa.float64())], ["lost"])

    out = spark.range(3000).mapInArrow(run, "lost double").agg(F.avg("lost").alias("lost"))
    return out.select((F.abs(F.col("lost") - (1 - k / w)) < 0.01).alias("equal"))


def experiment_window_locality(spark, sf_dir):
    """WindowK against RandK: draws a message, and the memory lines and triangle tiles it touches, in the mean over one
    message of every client that holds orders."""
    w, k, tile = packed.length(301), 2408, 1024
    keys = features.load(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("string").alias("sample_key"))
    clients = features.portable_split(keys, 142).select("client_id").distinct()

    def touched(batches):
        window, rand = compressors.make("windowk", k), compressors.make("randk", k)
        for batch in batches:
            rows = []
            for c in batch.column("client_id").to_pylist():
                for name, draws, idx in (("windowk", 1, window.positions(w, (7, 0, c))), ("randk", w, rand(np.ones(w), None, (7, 0, c)).idx)):
                    rows.append((name, draws, float(len(np.unique(idx // 8))), float(len(np.unique(idx // tile)))))
            if rows:
                kinds, drawn, lines, tiles = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(kinds), pa.array(drawn, pa.int32()), pa.array(lines), pa.array(tiles)], ["kind", "draws", "lines", "tiles"])

    out = clients.mapInArrow(touched, "kind string, draws int, lines double, tiles double").groupBy("kind", "draws").agg(F.avg("lines").alias("lines"), F.avg("tiles").alias("tiles"))
    model = F.when(F.col("kind") == "windowk", costmodel.memory_transactions("windowk", k)).otherwise(costmodel.memory_transactions("randk", k))
    return out.withColumn("model", model)


def experiment_ablations(spark, sf_dir):
    """Single improvements, each off and on: least seconds over every block, where the blocks lie, and the ratio."""
    clients = dense_clients(spark, sf_dir, 5)
    d, k = DENSE, K

    def measure(batches):
        for batch in batches:
            for n, raw in zip(batch.column("n_rows").to_pylist(), batch.column("z").to_pylist(), strict=True):
                rows = [(name, _least(off), _least(on)) for name, off, on in _improvements(np.frombuffer(raw).reshape(n, -1), d, k)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["improvement", "off_s", "on_s"])

    out = clients.blocks.mapInArrow(measure, "improvement string, off_s double, on_s double").groupBy("improvement").agg(F.min("off_s").alias("off_s"), F.min("on_s").alias("on_s"))
    return out.withColumn("ratio", F.col("off_s") / F.col("on_s"))


def _least(work: Callable[[], object]) -> float:
    best = float("inf")
    for _ in range(3):
        began = time.perf_counter()
        work()
        best = min(best, time.perf_counter() - began)
    return best


def _improvements(z: np.ndarray, d: int, k: int) -> list[tuple]:
    """(name, without it, with it) on one block; the groups of the published history that mean something here."""
    w, x = packed.length(d), np.linspace(-1, 1, d)
    _, g, h = PROBLEM.finish(len(z), PROBLEM.sums(z, x), x)
    full, v = packed.unpack(h, d), np.random.default_rng(0).normal(size=w)
    message = compressors.make("topk", k)(v, d, (0,))
    shuffled = np.random.default_rng(1).permutation(len(message.idx))
    target = np.zeros(w)

    def apart():
        PROBLEM.sums(z, x)[0], PROBLEM.sums(z, x)[1], PROBLEM.sums(z, x)[2]

    def rowwise():
        out = np.zeros((d, d))
        for row in z:
            s = 1 / (1 + np.exp(-row @ x))
            out += s * (1 - s) * np.outer(row, row)

    def indices_each_time():
        packed.indices.cache_clear()
        packed.pack(full)

    def scatter(order):
        for _ in range(50):
            target[message.idx[order]] += message.val[order]

    def add_dense():
        for _ in range(50):
            target.__iadd__(message.dense(w))

    ordered = np.arange(len(message.idx))
    window = compressors.make("windowk", k)
    return [
        ("cholesky_for_elimination", lambda: np.linalg.solve(full, g), lambda: server.cholesky_solve(full, g)),
        ("fused_oracles", apart, lambda: PROBLEM.sums(z, x)),
        ("blocks_for_rows", rowwise, lambda: PROBLEM.sums(z, x)),
        ("triangle_indices_once", indices_each_time, lambda: packed.pack(full)),
        ("sparse_scatter", add_dense, lambda: scatter(ordered)),
        ("indices_in_order", lambda: scatter(shuffled), lambda: scatter(ordered)),
        ("partition_for_sort", lambda: compressors.largest(np.abs(v), k, "sort"), lambda: compressors.largest(np.abs(v), k, "partition")),
        ("heap_for_sort", lambda: compressors.largest(np.abs(v), k, "sort"), lambda: compressors.largest(np.abs(v), k, "heap")),
        ("triangle_norm", lambda: np.linalg.norm(packed.unpack(h, d)), lambda: packed.frobenius(h, d)),
        ("window_for_random", lambda: compressors.make("randk", k)(v, d, (1,)), lambda: window(v, d, (1,))),
        ("early_indices_sent_entries_only", lambda: PROBLEM.sums(z, x), lambda: PROBLEM.entries(z, x, window.positions(w, (1,)))),
    ]


def experiment_indices(spark, sf_dir):
    """Explicit against seed-rebuilt indices: bytes of a RandK message from every client that holds orders, and their time on
    the published network."""
    rows, (n, _) = [], order_clients(spark, sf_dir)
    for mode in ("explicit", "seed"):
        size = n * (costmodel.payload_bytes("randk", 301, 2408, indices=mode) + 8 * 301 + 16)
        rows.append((mode, int(size), round(costmodel.transfer_seconds(size, 476.79), 9)))
    return _rows(spark, "indices string, bytes long, seconds double", rows)


INDICES_SQL = f"{ORDER_CLIENTS}SELECT indices, CAST(n * size AS BIGINT) AS bytes, round(n * size * 8 / 476.79e6, 9) AS seconds FROM c, (SELECT 'explicit' AS indices, 12 * 2408 + 8 * 301 + 16 AS size UNION ALL SELECT 'seed', 8 * 2408 + 8 * 301 + 16)"


def experiment_memory(spark, sf_dir):
    """Peak resident memory and open files after each method: the driver's, the JVM's heap in use, and the largest Python worker's.

    Peaks only grow within a process, so the methods run from the leanest to the one that needs most.
    """
    clients, samples, _ = _clients(spark, sf_dir, "dense", 20)
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    out = []
    for name, run in (
        ("lbfgs", lambda: baselines.lbfgs(clients, PROBLEM, rounds=10)),
        ("damped_newton", lambda: baselines.damped_newton(clients, PROBLEM, rounds=4)),
        ("hsn_windowk", lambda: train_shifts(clients, PROBLEM, compressors.make("windowk", K), rounds=3, tol=0.0)),
        ("hsn_topk", lambda: train_shifts(clients, PROBLEM, compressors.make("topk", K), rounds=3, tol=0.0)),
        ("hsn_identity", lambda: train_shifts(clients, PROBLEM, compressors.make("identity", K), rounds=3, tol=0.0)),
        ("admm", lambda: baselines.admm(clients, PROBLEM, rounds=2)),
        ("mllib", lambda: baselines.mllib_logistic(samples, PROBLEM.lam)),
    ):
        run()
        worker = clients.blocks.mapInArrow(_worker_resources, "peak_rss_kb long, open_files long").agg(F.max("peak_rss_kb"), F.max("open_files")).first()
        r = metrics.resources()
        out.append((name, r["peak_rss_kb"], r["open_files"], (runtime.totalMemory() - runtime.freeMemory()) >> 10, worker[0], worker[1]))
    clients.release()
    return _rows(spark, "method string, driver_peak_kb long, driver_files long, jvm_heap_kb long, worker_peak_kb long, worker_files long", out)


def _worker_resources(batches):
    for _ in batches:
        pass
    r = metrics.resources()
    yield pa.RecordBatch.from_arrays([pa.array([r["peak_rss_kb"]], pa.int64()), pa.array([r["open_files"]], pa.int64())], ["peak_rss_kb", "open_files"])


def experiment_estimate(spark, sf_dir):
    """Seconds that the arithmetic of 1,000 rounds over the orders' clients takes at a given speed, by solver."""
    flops, (n, held) = 3.3e9 * 12 * 3, order_clients(spark, sf_dir)
    rows = [(s, round(costmodel.run_seconds(301, n, held, 2408, 1000, flops, s), 3)) for s in ("cholesky", "gauss", "eigen")]
    return _rows(spark, "solver string, seconds double", rows)


ESTIMATE_SQL = f"""{ORDER_CLIENTS}
SELECT solver, round(1000 * (n * (301.0::DOUBLE * 301 * rows + 301 * rows + 2 * 301 * 301) + n * (301 * (2408 / 301) + 301) + solve) / (3.3e9 * 12 * 3), 3) AS seconds
FROM c, (VALUES ('cholesky', pow(301, 3) / 3), ('gauss', 2 * pow(301, 3) / 3), ('eigen', 9 * pow(301, 3))) t(solver, solve)
"""


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {
        f.__name__: f
        for f in (experiment_network, experiment_order, experiment_tight_expectation, experiment_window_locality, experiment_ablations, experiment_indices, experiment_memory, experiment_estimate)
    }
    found |= {f"experiment_base_{w}": partial(base_method, workload=w, n=n, rounds=BASE_ROUNDS) for w, n in (("dense", 20), ("sparse", 142))}
    found |= {f"experiment_solvers_{w}": partial(solvers, workload=w, rounds=SEARCH_ROUNDS, baseline_rounds=BASELINE_ROUNDS, splitting_rounds=SPLITTING_ROUNDS) for w in ("dense", "onehot")}
    found["experiment_solvers_sparse"] = partial(solvers, workload="sparse")
    found |= {f"experiment_multi_node_{w}": partial(multi_node, workload=w, rounds=CURVE_ROUNDS, baseline_rounds=BASELINE_ROUNDS) for w in WORKLOADS}
    found |= {f"experiment_curves_{w}": partial(curves, workload=w, rounds=CURVE_ROUNDS) for w in ("dense", "sparse")}
    found["experiment_curves_onehot"] = partial(curves, workload="onehot")
    return found


def oracle_sql() -> dict[str, str]:
    return {
        "experiment_order": ORDER_SQL,
        "experiment_tight_expectation": "SELECT true AS equal",
        "experiment_indices": INDICES_SQL,
        "experiment_estimate": ESTIMATE_SQL,
    }
