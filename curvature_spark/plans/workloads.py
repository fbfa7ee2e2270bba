"""Queries of the reference's methods, variants, baselines and measures on the given tables."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import packed
from ..functions.vectors import dot, log1p_exp, norm, packed_frobenius, sigmoid
from ..operators import baselines, compressors, costmodel, features, metrics
from ..operators.methods import Fit, predict, shift_gap, train_partial, train_shifts
from ..operators.partition import Clients, pin, split_equal
from ..operators.problems import LogisticProblem, QuadraticProblem, curvature_bounds, difference_errors, difference_sums, lipschitz_ratios
from ..operators.rounds import global_oracles
from . import oracles

Query = Callable[[SparkSession, str], DataFrame]
LAM = 1e-3
DENSE = 69
#: The point at which single oracles are evaluated.
AT = (0.3, -0.2, 0.1)


def _rows(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([tuple(v.item() if hasattr(v, "item") else v for v in r) for r in rows], schema)


def r6(x: float) -> float:
    return round(float(x), 6) + 0.0


def tiny_clients(spark: SparkSession, sf_dir: str) -> Clients:
    return pin(features.portable_split(features.tiny(spark, sf_dir), 5), 3)


def dense_clients(spark: SparkSession, sf_dir: str, n: int = 20) -> Clients:
    return pin(split_equal(features.dense(spark, sf_dir), n), DENSE)


def order_clients(spark: SparkSession, sf_dir: str) -> tuple[int, int]:
    """Orders dealt to the 142 clients of the cost figures: clients that hold any, and rows a client (whole part)."""
    rows = features.load(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("string").alias("sample_key"))
    n, total = features.portable_split(rows, 142).groupBy("client_id").count().agg(F.count(F.lit(1)), F.sum("count")).first()
    return n, total // n


ORDER_CLIENTS = f"WITH c AS (SELECT n, total // n AS rows FROM (SELECT count(DISTINCT {oracles.draw_sql('7', 'CAST(o_orderkey AS VARCHAR)')} % 142) AS n, count(*) AS total FROM orders)) "


def moments(spark: SparkSession, sf_dir: str, d: int) -> np.ndarray:
    """Packed mean of the outer products of the first d components of all embeddings."""

    def sums(batches):
        import pyarrow as pa

        total, n = np.zeros((d, d)), 0
        for batch in batches:
            z = batch.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            total, n = total + z.T @ z, n + len(z)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([total.tobytes()], pa.binary())], ["n", "v"])

    rows = features.load(spark, sf_dir, "embeddings").where(F.col("embedding").isNotNull())
    parts = rows.select(F.slice("embedding", 1, d).cast("array<double>").alias("v")).mapInArrow(sums, "n long, v binary").collect()  # one row a task
    return packed.pack(sum(np.frombuffer(r.v) for r in parts).reshape(d, d) / sum(r.n for r in parts))


# -- oracles in expressions -------------------------------------------------------------------------------
def _terms(spark, sf_dir) -> DataFrame:
    """client, z1..z3, margin m and s = sigmoid(-m), computed once and shared by all oracles."""
    rows = features.portable_split(features.tiny(spark, sf_dir), 5)
    z = [(F.col("features")[i] * F.col("label")).alias(f"z{i + 1}") for i in range(3)]
    rows = rows.select(F.col("client_id").alias("client"), *z)
    rows = rows.withColumn("m", sum((F.col(f"z{i + 1}") * AT[i] for i in range(1, 3)), F.col("z1") * AT[0]))
    return rows.withColumn("s", sigmoid(-F.col("m")))


def logit_value_at_zero(spark, sf_dir):
    rows = features.tiny(spark, sf_dir).select((dot(F.col("features"), F.array(*[F.lit(0.0)] * 3)) * F.col("label")).alias("m"))
    return rows.agg(F.round(F.avg(log1p_exp(-F.col("m"))), 6).alias("f"))


def fused_oracle(spark, sf_dir):
    """Value, gradient and Hessian triangle of every client in one pass."""
    square = sum(a * a for a in AT)
    aggs = [(F.avg(log1p_exp(-F.col("m"))) + LAM / 2 * square).alias("f")]
    aggs += [(F.avg(-F.col("s") * F.col(f"z{i + 1}")) + LAM * AT[i]).alias(f"g{i + 1}") for i in range(3)]
    aggs += [(F.avg(F.col("s") * (1 - F.col("s")) * F.col(f"z{i + 1}") * F.col(f"z{j + 1}")) + (LAM if i == j else 0.0)).alias(f"h{p}") for p, (i, j) in enumerate(oracles.ENTRIES)]
    out = _terms(spark, sf_dir).groupBy("client").agg(*aggs)
    return out.select("client", *[(F.round(c, 6) + 0.0).alias(c) for c in out.columns[1:]])


def logit_gradient(spark, sf_dir):
    return fused_oracle(spark, sf_dir).select("client", "g1", "g2", "g3")


def logit_hessian(spark, sf_dir):
    rows = fused_oracle(spark, sf_dir)
    return rows.select("client", F.posexplode(F.array(*[F.col(f"h{p}") for p in range(6)])).alias("pos", "h"))


def engine_oracle(spark, sf_dir):
    """The same oracles of the whole objective from the matrix blocks."""
    f, g, h = global_oracles(tiny_clients(spark, sf_dir), LogisticProblem(LAM), np.array(AT))
    return _rows(spark, "f double, g1 double, g2 double, g3 double, h0 double, h1 double, h2 double, h3 double, h4 double, h5 double", [tuple(map(r6, [f, *g, *h]))])


def hessian_long_dense(spark, sf_dir):
    """Sum of outer products of the raw embeddings in long form: one row an entry of the triangle."""
    v = features.load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "a"))
    v = v.select("vec_id", "i", F.col("a").cast("double").alias("a"))
    w = v.select("vec_id", F.col("i").alias("j"), F.col("a").alias("b"))
    pairs = v.join(w, "vec_id").where("i <= j")
    return pairs.groupBy("i", "j").agg((F.round(F.sum(F.col("a") * F.col("b")), 4) + 0.0).alias("h"))


def oracle_fd_check(spark, sf_dir):
    """Gradient and Hessian against central differences on every client; blocks become sums where they lie."""
    import pyarrow as pa

    problem, x = LogisticProblem(LAM), np.array(AT)

    def sums(batches):
        for batch in batches:
            rows = batch.column("n_rows").to_pylist()
            made = [difference_sums(problem, np.frombuffer(r, dtype=np.float64).reshape(n, -1), x).tobytes() for n, r in zip(rows, batch.column("z").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("client_id"), batch.column("n_rows"), pa.array(made, pa.binary())], ["client_id", "n_rows", "v"])

    def check(key, table):
        total = np.sum([np.frombuffer(v, dtype=np.float64) for v in table.column("v").to_pylist()], axis=0)
        g, h = difference_errors(problem, sum(table.column("n_rows").to_pylist()), total, x)
        return pa.table({"client": [key[0].as_py()], "gradient_ok": [g < 1e-8], "hessian_ok": [h < 1e-7]})

    parts = tiny_clients(spark, sf_dir).blocks.mapInArrow(sums, "client_id long, n_rows int, v binary")
    return parts.groupBy("client_id").applyInArrow(check, "client long, gradient_ok boolean, hessian_ok boolean")


def quad_least_squares(spark, sf_dir):
    """Least squares through sufficient statistics; one exact Newton step from anywhere is the answer."""
    clients = pin(features.quad(spark, sf_dir).withColumn("client_id", F.lit(0).cast("long")), 4, label=None)
    problem, x = QuadraticProblem(), np.ones(3)
    _, g, h = global_oracles(clients, problem, x)
    x = x - np.linalg.solve(packed.unpack(h, 3), g)
    return _rows(spark, "b1 double, b2 double, b3 double", [tuple(map(r6, x))])


# -- compressors -------------------------------------------------------------------------------------------
def compressed(kind: str, k: int = 3) -> Query:
    def query(spark, sf_dir):
        """What each client sends of its Hessian at 0 in round 0, the shift being zero."""
        out = []
        clients = tiny_clients(spark, sf_dir)
        run = train_shifts(clients, LogisticProblem(LAM), compressors.make(kind, k), option="shift", init="zero", alpha=1.0, rounds=1, tol=0.0)
        for r in run.engine.shifts.select("client_id", "h").collect():
            for p, v in enumerate(np.frombuffer(r.h, dtype=np.float64)):
                if v:
                    out.append((r.client_id, p, r6(v)))
        return _rows(spark, "client long, pos int, sent double", out)

    return query


def compressed_sql(kind: str, k: int = 3) -> str:
    ctes = [oracles.TINY, "x0 AS (SELECT 0.0::DOUBLE AS x1, 0.0::DOUBLE AS x2, 0.0::DOUBLE AS x3)", "t0 AS MATERIALIZED (SELECT client, unnest(range(6)) AS pos, 0.0::DOUBLE AS h FROM (SELECT DISTINCT client FROM data))"]
    ctes += [*oracles.oracle_ctes(0), oracles.compress_cte(0, kind, k)]
    return "WITH " + ",\n".join(ctes) + "\nSELECT client, CAST(pos AS INTEGER) AS pos, round(sent, 6) + 0.0 AS sent FROM c0 WHERE sent <> 0"


def topk_impls_agree(spark, sf_dir):
    _, _, h = global_oracles(dense_clients(spark, sf_dir), LogisticProblem(LAM), np.zeros(DENSE))
    k = 8 * DENSE
    found = [np.sort(compressors.largest(compressors.scores(h, DENSE, "frobenius"), k, impl)).tolist() for impl in ("sort", "heap", "partition")]
    return _rows(spark, "agree boolean, k int", [(found[0] == found[1] == found[2], len(found[0]))])


def compressor_bias_variance(spark, sf_dir):
    """Over every possible window: the mean equals the input (mean quantities of the lines whose order key leaves
    0 to 14 by 15), the mean squared error is w/K - 1 of the square."""
    w, k = 15, 4
    v = features.load(spark, sf_dir, "lineitem").groupBy((F.col("l_orderkey") % w).alias("pos")).agg(F.avg("l_quantity").alias("v"))
    starts = spark.range(w).select(F.col("id").alias("s")).crossJoin(F.broadcast(v))
    sent = starts.withColumn("c", F.when(F.pmod(F.col("pos") - F.col("s"), F.lit(w)) < k, F.col("v") * (w / k)).otherwise(0.0))
    by = sent.groupBy("pos").agg(F.avg("c").alias("mean"), F.max("v").alias("v"), F.avg((F.col("c") - F.col("v")) ** 2).alias("mse"))
    return by.agg(F.round(F.max(F.abs(F.col("mean") - F.col("v"))), 6).alias("bias"), F.round(F.sum("mse") / F.sum(F.col("v") ** 2), 6).alias("variance_ratio"))


def compressor_diagnostics(spark, sf_dir):
    """Empirical bias, error ratio and items of every compressor over many seeds against its constants, on the second
    moments of the embeddings."""
    d, k, trials = 12, 30, 400
    v = moments(spark, sf_dir, d)
    w = packed.length(d)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            rows = []
            for seed in batch.column("id").to_pylist():
                for kind in compressors.KINDS:
                    message = compressors.make(kind, k)(v, d, (seed, 0, 0))
                    error = message.dense(w) - v
                    rows.append((kind, packed.frobenius(error, d) ** 2 / packed.frobenius(v, d) ** 2, float(error.mean()), len(message.idx)))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["kind", "error", "bias", "items"])

    out = spark.range(trials).mapInArrow(run, "kind string, error double, bias double, items long").groupBy("kind").agg(F.avg("error").alias("error"), F.avg("bias").alias("bias"), F.avg("items").alias("items"))
    theory = _rows(spark, "kind string, omega double, delta double", [(n, float(c(k).omega(w)), float(c(k).delta(w))) for n, c in compressors.KINDS.items()])
    return out.join(F.broadcast(theory), "kind")


# -- runs --------------------------------------------------------------------------------------------------
def traced(fit_rounds: list[tuple[int, np.ndarray, object]], spark: SparkSession) -> DataFrame:
    rows = [(k, *map(r6, x), r6(m.f), r6(np.linalg.norm(m.g))) for k, x, m in fit_rounds]
    return _rows(spark, "round int, x1 double, x2 double, x3 double, f double, grad_norm double", rows)


def tiny_run(kind: str, k: int = 3, rounds: int = 4, **options) -> Query:
    def query(spark, sf_dir):
        seen = []
        train_shifts(tiny_clients(spark, sf_dir), LogisticProblem(LAM), compressors.make(kind, k), rounds=rounds, tol=0.0, inspect=lambda i, x, m: seen.append((i, x.copy(), m)), **options)
        return traced(seen, spark)

    return query


def hsn_pp_rounds(spark, sf_dir):
    xs = []
    clients = tiny_clients(spark, sf_dir)
    for r in range(1, 4):
        fit = train_partial(clients, LogisticProblem(LAM), compressors.make("topk", 3), 2, rounds=r, tol=0.0, probe_every=0)
        xs.append((r - 1, *map(r6, fit.x)))
    return _rows(spark, "round int, x1 double, x2 double, x3 double", xs)


def hsn_pp_invariants(spark, sf_dir):
    """The server's running mean of the shifts equals the mean of the clients' shifts after partial rounds."""
    fit = train_partial(tiny_clients(spark, sf_dir), LogisticProblem(LAM), compressors.make("topk", 3), 2, rounds=6, tol=0.0, probe_every=0)
    return _rows(spark, "mean_kept boolean", [(shift_gap(fit) < 1e-12,)])


#: The converged parameters in three dimensions by exact Newton steps, to check every method that converges there.
CONVERGED_TINY = oracles.shifts_run("identity", 6, 8, option="project", init="hessian").rsplit("\nSELECT", 1)[0]


def converged(name: str, solve: Callable[[Clients], np.ndarray]) -> Query:
    def query(spark, sf_dir):
        x = solve(tiny_clients(spark, sf_dir))
        return _rows(spark, "method string, x1 double, x2 double, x3 double", [(name, *map(r6, x))])

    return query


def converged_sql(name: str) -> str:
    return f"{CONVERGED_TINY}\nSELECT '{name}' AS method, round(x1, 6) + 0.0 AS x1, round(x2, 6) + 0.0 AS x2, round(x3, 6) + 0.0 AS x3 FROM x8"


def method(kind: str, **options):
    return lambda c: train_shifts(c, LogisticProblem(LAM), compressors.make(kind, 3), rounds=60, tol=1e-11, **options).x


PROBLEM = LogisticProblem(LAM)
CONVERGING = {
    **{f"hsn_project_{kind}": method(kind) for kind in compressors.KINDS},
    **{f"hsn_shift_{kind}": method(kind, option="shift") for kind in compressors.KINDS},
    "hsn_ls_project": method("topk", line_search=(0.49, 0.5)),
    "hsn_ls_shift": method("topk", option="shift", line_search=(0.49, 0.5)),
    "hsn_cubic": method("topk", lipschitz=1.0),
    "hsn_windowk_lazy": method("windowk", lazy=True),
    "hsn_zero_start": method("topk", option="shift", init="zero"),
    "hsn_alpha_contractive": method("topk", alpha="contractive"),
    "hsn_pp_topk": lambda c: train_partial(c, PROBLEM, compressors.make("topk", 3), 2, rounds=60, tol=1e-11).x,
    "hsn_pp_all": lambda c: train_partial(c, PROBLEM, compressors.make("topk", 3), 5, rounds=60, tol=1e-11).x,
    "baseline_newton": lambda c: baselines.damped_newton(c, PROBLEM)[0],
    "baseline_newton_cg": lambda c: baselines.newton_cg(c, PROBLEM, tol=1e-11)[0],
    "baseline_lbfgs": lambda c: baselines.lbfgs(c, PROBLEM, tol=1e-10)[0],
    "baseline_accelerated_gradient": lambda c: baselines.gradient_descent(c, PROBLEM, momentum=True, rounds=300, tol=1e-10)[0],
    "baseline_admm": lambda c: baselines.admm(c, PROBLEM, tol=1e-9)[0],
    "baseline_compressed_differences": lambda c: baselines.compressed_gradient(c, PROBLEM, 2, 0.5, rounds=1000, tol=1e-10)[0],
}


def baseline_error_feedback(spark, sf_dir):
    """With a constant step this method stalls before the minimiser: how far it comes, and no SQL to hold it to."""
    x, log = baselines.compressed_gradient(tiny_clients(spark, sf_dir), PROBLEM, 2, 0.5, feedback="error")
    return _rows(spark, "method string, rounds int, grad_norm double, x1 double, x2 double, x3 double", [("baseline_error_feedback", len(log.rows), log.rows[-1]["grad_norm"], *map(r6, x))])


def hsn_vs_mllib(spark, sf_dir):
    """Coordinate by coordinate: the method on 20 equal clients, and the library on their rows."""
    samples = split_equal(features.dense(spark, sf_dir), 20)
    clients = pin(samples, DENSE)
    fit = train_shifts(clients, PROBLEM, compressors.make("topk", 8 * DENSE))
    x, _ = baselines.mllib_logistic(samples, LAM)
    clients.release()
    return _rows(spark, "pos int, engine double, library double", [(j + 1, r6(a), round(float(b), 4) + 0.0) for j, (a, b) in enumerate(zip(fit.x, x, strict=True))])


def hsn_vs_numpy(spark, sf_dir):
    """Engine and dense single-process prototype agree on the iterate, compressor by compressor."""
    clients = dense_clients(spark, sf_dir, 10)
    local = {r.client_id: np.frombuffer(r.z, dtype=np.float64).reshape(r.n_rows, -1) for r in clients.blocks.collect()}
    out = []
    for kind in ("topk", "windowk", "tight"):
        c = compressors.make(kind, 8 * DENSE)
        a = train_shifts(clients, PROBLEM, c, option="shift", rounds=5, tol=0.0)
        b, _ = baselines.numpy_reference(local, PROBLEM, c, option="shift", rounds=5, tol=0.0)
        out.append((kind, bool(np.abs(a.x - b).max() < 1e-8)))
    return _rows(spark, "kind string, close boolean", out)


def trained(spark: SparkSession, sf_dir: str, workload: str, kind: str, n: int, rounds: int = 150, **options) -> Fit:
    samples, d = features.BUILDERS[workload](spark, sf_dir), features.DIMENSIONS[workload]
    clients = pin(features.portable_split(samples, n), d)
    fit = train_shifts(clients, PROBLEM, compressors.make(kind, 8 * d), rounds=rounds, run_id=f"{workload}_{kind}", **options)
    clients.release()
    return fit


def full_run(workload: str, kind: str, n: int, **options) -> Query:
    """Train to the tolerance; the round log says how."""
    return lambda spark, sf_dir: trained(spark, sf_dir, workload, kind, n, **options).log.frame(spark)


def solution(workload: str, kind: str, n: int, **options) -> Query:
    """The coordinates that training ends at; a gradient of 1e-11 bounds their error by 1e-8 at the curvature of at least 1e-3."""

    def query(spark, sf_dir):
        fit = trained(spark, sf_dir, workload, kind, n, tol=1e-11, **options)
        return _rows(spark, "pos int, x double", [(j + 1, r6(v)) for j, v in enumerate(fit.x)])

    return query


def least_value(workload: str, kind: str, n: int, **options) -> Query:
    """Whether training gets below 1e-9, and the value it ends at."""

    def query(spark, sf_dir):
        fit = trained(spark, sf_dir, workload, kind, n, **options)
        return _rows(spark, "reached boolean, f double", [(fit.log.rows[-1]["grad_norm"] < 1e-9, r6(fit.log.rows[-1]["f"]))])

    return query


def users_partial(spark, sf_dir):
    """Unequal clients by user, pooled weights, a twelfth of them a round."""
    samples = features.users(spark, sf_dir).withColumn("client_id", F.col("user_id"))
    clients = pin(samples, 5, weights="pooled")
    fit = train_partial(clients, PROBLEM, compressors.make("topk", 5), max(1, clients.n // 4), rounds=40, tol=1e-9, run_id="users")
    return fit.log.frame(spark)


def spectrum(spark, sf_dir):
    """Curvature at 0 and Lipschitz ratios between two points, on every logistic workload."""
    out = []
    for name in ("tiny", "users", "dense", "onehot", "sparse"):
        d = features.DIMENSIONS[name]
        clients = pin(features.portable_split(features.BUILDERS[name](spark, sf_dir), 10), d)
        x, y = np.zeros(d), np.full(d, 0.1)
        _, _, hx = global_oracles(clients, PROBLEM, x)
        _, _, hy = global_oracles(clients, PROBLEM, y)
        out.append((name, *curvature_bounds(hx, d), *lipschitz_ratios(hx, hy, x, y)))
        clients.release()
    return _rows(spark, "workload string, least double, largest double, condition double, spectral double, frobenius double, entry double", out)


# -- measures ----------------------------------------------------------------------------------------------
KEPT = {"tight": 18.46}


def comm_bytes_model(spark, sf_dir):
    n, _ = order_clients(spark, sf_dir)
    rows = [(k, round(costmodel.total_megabytes(k, 301, n, 1000, 8 * 301, KEPT.get(k)), 1)) for k in compressors.KINDS]
    return _rows(spark, "kind string, megabytes double", rows)


COMM_SQL = f"""{ORDER_CLIENTS}
SELECT kind, round(n * 1000 * (8 * 301 + 16 + payload) / 1048576.0::DOUBLE, 1) AS megabytes FROM c, (VALUES
  ('identity', 8.0 * 45451), ('topk', 12.0 * 2408), ('randk', 8.0 * 2408), ('windowk', 8.0 * 2408), ('tight', 12.0 * 18.46 + 4), ('natural', ceil(1.5 * 45451))) t(kind, payload)
"""


def comm_bytes_measured(spark, sf_dir):
    """Bytes and items that a run logs, round by round."""
    clients = pin(features.portable_split(features.dense(spark, sf_dir), 10), DENSE)
    out = []
    for kind in ("topk", "randk", "windowk", "identity", "natural"):
        fit = train_shifts(clients, PROBLEM, compressors.make(kind, 8 * DENSE), rounds=2, tol=0.0)
        out += [(kind, r["round"], r["items"], r["bytes"]) for r in fit.log.rows]
    clients.release()
    return _rows(spark, "kind string, round int, items long, bytes long", out)


def cost_model(spark, sf_dir):
    d, k = 301, 2408
    n, rows = order_clients(spark, sf_dir)
    return _rows(
        spark,
        "client_flops double, server_cholesky double, server_gauss double, scattered double, contiguous double, transfer_s double",
        [(costmodel.client_flops(d, rows), round(costmodel.server_flops(d, n, k / d), 3), round(costmodel.server_flops(d, n, k / d, "gauss"), 3), costmodel.memory_transactions("randk", k), costmodel.memory_transactions("windowk", k), round(costmodel.transfer_seconds(8.0 * k, 476.79), 9))],
    )


COST_SQL = f"""{ORDER_CLIENTS}
SELECT 301.0::DOUBLE * 301 * rows + 301 * rows + 2.0::DOUBLE * 301 * 301 AS client_flops, round(n * (301 * (2408 / 301) + 301) + pow(301, 3) / 3, 3) AS server_cholesky,
  round(n * (301 * (2408 / 301) + 301) + 2 * pow(301, 3) / 3, 3) AS server_gauss, 2408.0::DOUBLE AS scattered, 2408 * 8 / 64.0::DOUBLE + 2 AS contiguous, round(2408.0::DOUBLE * 8 * 8 / 476.79e6, 9) AS transfer_s
FROM c
"""


def _scored(spark, sf_dir):
    w = F.array(*[F.lit(0.05 * ((i * 7) % 5 - 2)) for i in range(DENSE)])
    rows = features.dense(spark, sf_dir)
    out = rows.withColumn("margin", dot(F.col("features"), w))
    return out.withColumn("probability", F.round(sigmoid(F.col("margin")), 6)).withColumn("predicted", F.when(F.col("margin") >= 0, 1.0).otherwise(-1.0))


def predict_score(spark, sf_dir):
    return _scored(spark, sf_dir).select("sample_key", "probability", "label")


def auc(spark, sf_dir):
    return metrics.auc(_scored(spark, sf_dir)).select(F.round("auc", 6).alias("auc"))


def confusion(spark, sf_dir):
    return metrics.confusion(_scored(spark, sf_dir))


def trained_auc(spark, sf_dir):
    samples = split_equal(features.dense(spark, sf_dir), 20)
    fit = train_shifts(pin(samples, DENSE), PROBLEM, compressors.make("topk", 8 * DENSE))
    return metrics.auc(predict(samples, fit.x))


SCORED_SQL = """
WITH v AS (
  SELECT CAST(vec_id AS VARCHAR) AS sample_key, CASE WHEN label = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings
), f AS (
  SELECT sample_key, label, list_concat(e, [sqrt(list_sum(list_transform(e, lambda x: x * x))), list_max(e), list_min(e), list_sum(list_transform(e, lambda x: abs(x))) / 8, 1.0]) AS features FROM v
), s AS (
  SELECT *, list_inner_product(features, list_transform(range(69), lambda i: 0.05::DOUBLE * ((i * 7) % 5 - 2))) AS margin FROM f
), p AS (SELECT sample_key, label, round(1 / (1 + exp(-margin)), 6) AS probability, CASE WHEN margin >= 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS predicted FROM s)
"""


def feature_dense(spark, sf_dir):
    rows = features.dense(spark, sf_dir)
    return rows.select("sample_key", "label", *[F.round(F.col("features")[i], 6).alias(f"a{i}") for i in (0, 64, 65, 66, 67, 68)])


def feature_events_json(spark, sf_dir):
    rows = features.users(spark, sf_dir)
    return rows.select("sample_key", "user_id", "label", *[(F.round(F.col("features")[i], 6) + 0.0).alias(f"a{i}") for i in range(5)])


def feature_text_hash(spark, sf_dir):
    rows = features.sparse(spark, sf_dir)
    total = F.aggregate("hot", F.lit(0).cast("long"), lambda s, v: s + v) - features.BUCKETS
    return rows.select("sample_key", "label", (F.size("hot") - 1).alias("ones"), total.alias("total"))


def feature_star_onehot(spark, sf_dir):
    rows = features.onehot(spark, sf_dir).select("label", F.explode("hot").alias("pos")).where(F.col("pos") < features.DIMENSIONS["onehot"] - 1)
    return rows.groupBy("pos").agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("balance"))


STAR_SQL = """
WITH a AS (
  SELECT CASE WHEN l_returnflag = 'R' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, [
    l_linenumber - 1, 7 + CAST(round(l_discount * 100) AS INTEGER), 18 + CAST(round(l_tax * 100) AS INTEGER), 27 + CAST(floor((l_quantity - 1) / 5) AS INTEGER), 37 + CAST(l_linestatus = 'O' AS INTEGER),
    39 + month(l_shipdate) - 1, 51 + dayofweek(l_shipdate), 58 + CAST(substr(p_brand, 7, 2) AS INTEGER) - 1,
    83 + list_position(['ECONOMY', 'LARGE', 'MEDIUM', 'PROMO', 'SMALL', 'STANDARD'], p_type) - 1, 89 + CAST(substr(o_orderpriority, 1, 1) AS INTEGER) - 1,
    94 + list_position(['F', 'O', 'P'], o_orderstatus) - 1, 97 + list_position(['AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY'], c_mktsegment) - 1, 102 + n_regionkey,
    107 + least(10, CAST(floor(l_extendedprice / 1e4) AS INTEGER)), 118 + CAST(floor((p_size - 1) / 10) AS INTEGER)] AS hot
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey
    JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey
)
SELECT CAST(pos AS INTEGER) AS pos, count(*) AS n, sum(label) AS balance FROM (SELECT label, unnest(hot) AS pos FROM a) GROUP BY pos
"""


def client_split_equal(spark, sf_dir):
    rows = features.load(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("string").alias("sample_key"))
    return split_equal(rows, 7).select("sample_key", "client_id")


def client_split_natural(spark, sf_dir):
    """Clients are nations; their weights follow their rows."""
    rows = features.load(spark, sf_dir, "orders").select("o_custkey").join(features.load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    counts = rows.groupBy(F.col("c_nationkey").cast("long").alias("client_id")).agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("client_id", "n", F.round(F.col("n") / F.col("total"), 6).alias("weight"))


def client_stats(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("double")
    return features.load(spark, sf_dir, "events").groupBy("user_id").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.var_pop("value"), 4).alias("variance"),
        F.round(F.stddev_pop("value"), 6).alias("deviation"), F.round(F.covar_pop(F.col("value"), k), 4).alias("covariance"),
    )


def dataset_statistics(spark, sf_dir):
    out = features.statistics(features.tiny(spark, sf_dir))
    return out.select("n", "positives", "d", *[F.round(c, 6).alias(c) for c in ("density", "mean", "variance")])


def digest_table(spark, sf_dir):
    rows = features.load(spark, sf_dir, "orders")
    return metrics.digest(rows, F.col("o_orderkey"), F.col("o_custkey"), F.col("o_orderstatus"))


def vector_functions(spark, sf_dir):
    v = F.transform("embedding", lambda x: x.cast("double"))
    rows = features.load(spark, sf_dir, "embeddings").select("vec_id", v.alias("v"))
    # 64 components and two ones are the triangle of an 11 x 11 matrix.
    triangle = F.concat("v", F.array(F.lit(1.0), F.lit(1.0)))
    return rows.select("vec_id", F.round(dot(F.col("v"), F.col("v")), 5).alias("dot"), F.round(norm(F.col("v")), 5).alias("norm"), F.round(packed_frobenius(triangle, 11), 5).alias("frobenius"))


def queries() -> dict[str, Query]:
    named = (
        logit_value_at_zero, fused_oracle, logit_gradient, logit_hessian, engine_oracle, hessian_long_dense, oracle_fd_check, quad_least_squares,
        topk_impls_agree, compressor_bias_variance, compressor_diagnostics, hsn_pp_rounds, hsn_pp_invariants, hsn_vs_mllib, hsn_vs_numpy, baseline_error_feedback, users_partial,
        spectrum, comm_bytes_model, comm_bytes_measured, cost_model, predict_score, auc, confusion, trained_auc, feature_dense, feature_events_json, feature_text_hash,
        feature_star_onehot, client_split_equal, client_split_natural, client_stats, dataset_statistics, digest_table, vector_functions,
    )
    found: dict[str, Query] = {f.__name__: f for f in named}
    found |= {f"compress_{kind}": compressed(kind) for kind in compressors.KINDS}
    found |= {f"hsn_rounds_{kind}": tiny_run(kind, option="shift", init="zero", alpha=1.0 if kind in ("identity", "topk", "tight") else 0.5 if kind != "natural" else 8 / 9) for kind in compressors.KINDS}
    found["hsn_step_project"] = tiny_run("topk", rounds=2)
    found["hsn_step_shift"] = tiny_run("topk", rounds=2, option="shift")
    found["hsn_ls_rounds"] = tiny_run("topk", rounds=3, line_search=(0.49, 0.5))
    found["newton_exact"] = tiny_run("identity", rounds=5)
    found |= {name: converged(name, solve) for name, solve in CONVERGING.items()}
    # Full projected steps converge locally: where Hessians change by orders on the way (sparse), or a round corrects little of
    # them (tight), they can overshoot for good, and the search along the step is what makes the method converge.
    search = {"line_search": (0.49, 0.5)}
    found |= {f"dense_{kind}": solution("dense", kind, 20, **(search if kind == "tight" else {})) for kind in compressors.KINDS}
    found["dense_shift_tight"] = solution("dense", "tight", 20, option="shift")
    found["dense_ls_topk"] = solution("dense", "topk", 20, **search)
    found["onehot_topk"] = least_value("onehot", "topk", 50)
    found["sparse_topk"] = least_value("sparse", "topk", 20, **search)
    found["dense_log_topk"] = full_run("dense", "topk", 20)
    return found


def oracle_sql() -> dict[str, str]:
    q = oracles
    point = f"x0 AS (SELECT {AT[0]}::DOUBLE AS x1, {AT[1]}::DOUBLE AS x2, {AT[2]}::DOUBLE AS x3)"
    at = "WITH " + q.TINY + ", " + point + ", " + q.oracle_ctes(0)[0]
    r = lambda names: ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in names)
    g, h = ["g1", "g2", "g3"], [f"h{p}" for p in range(6)]
    found = {
        "logit_value_at_zero": "SELECT round(ln(2), 6) AS f FROM (SELECT count(*) AS n FROM lineitem) WHERE n > 0",
        "fused_oracle": f"{at} SELECT client, {r(['f', *g, *h])} FROM o0",
        "logit_gradient": f"{at} SELECT client, {r(g)} FROM o0",
        "logit_hessian": f"{at} SELECT client, CAST(e.p AS INTEGER) AS pos, round(e.v, 6) + 0.0 AS h FROM (SELECT client, unnest([{', '.join(f'{{p: {p}, v: h{p}}}' for p in range(6))}]) AS e FROM o0)",
        "engine_oracle": f"{at} SELECT " + ", ".join(f"round(avg({c}), 6) + 0.0 AS {c}" for c in ["f", *g, *h]) + " FROM o0",
        "hessian_long_dense": "WITH v AS (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding)::DOUBLE AS a FROM embeddings) SELECT CAST(v.i AS INTEGER) AS i, CAST(w.i AS INTEGER) AS j, round(sum(v.a * w.a), 4) + 0.0 AS h FROM v JOIN v w ON v.vec_id = w.vec_id AND v.i <= w.i GROUP BY v.i, w.i",
        "oracle_fd_check": f"WITH {q.TINY} SELECT DISTINCT client, true AS gradient_ok, true AS hessian_ok FROM data",
        "quad_least_squares": _quad_sql(),
        "topk_impls_agree": "SELECT true AS agree, CAST(552 AS INTEGER) AS k",
        "compressor_bias_variance": "SELECT 0.0::DOUBLE AS bias, round(w / 4.0 - 1, 6)::DOUBLE AS variance_ratio FROM (SELECT count(DISTINCT l_orderkey % 15) AS w FROM lineitem)",
        "hsn_pp_rounds": q.partial_run(3, 3, 2),
        "hsn_pp_invariants": "SELECT true AS mean_kept",
        "hsn_vs_mllib": q.minimiser(q.LONG["dense"], 20, DENSE, 1.0, 1000, equal=True) + "SELECT CAST(j AS INTEGER) AS pos, round(x, 6) + 0.0 AS engine, round(x, 4) + 0.0 AS library FROM least",
        "hsn_vs_numpy": "SELECT * FROM (VALUES ('topk', true), ('windowk', true), ('tight', true)) t(kind, close)",
        "comm_bytes_model": COMM_SQL,
        "comm_bytes_measured": f"WITH n AS (SELECT count(DISTINCT {q.draw_sql('7', 'CAST(vec_id AS VARCHAR)')} % 10) AS n FROM embeddings WHERE embedding IS NOT NULL) SELECT kind, CAST(r AS INTEGER) AS round, CAST(n * items AS BIGINT) AS items, CAST(n * (8 * 69 + 16 + payload) AS BIGINT) AS bytes FROM n, range(2) t(r), (VALUES ('topk', 552, 12 * 552), ('randk', 552, 8 * 552), ('windowk', 552, 8 * 552), ('identity', 2415, 8 * 2415), ('natural', 2415, 3623)) k(kind, items, payload)",
        "cost_model": COST_SQL,
        "predict_score": SCORED_SQL + "SELECT sample_key, probability, label FROM p",
        "auc": SCORED_SQL + ", r AS (SELECT label, avg(rn) OVER (PARTITION BY probability) AS rk FROM (SELECT *, row_number() OVER (ORDER BY probability) AS rn FROM p)), t AS (SELECT sum(CASE WHEN label > 0 THEN rk END) AS s, count(*) FILTER (label > 0) AS np, count(*) AS n FROM r) SELECT round((s - np * (np + 1) / 2) / (np * (n - np)), 6) AS auc FROM t",
        "confusion": SCORED_SQL + "SELECT label, predicted, count(*) AS n FROM p GROUP BY label, predicted",
        "feature_dense": SCORED_SQL + "SELECT sample_key, label, " + ", ".join(f"round(features[{i + 1}], 6) AS a{i}" for i in (0, 64, 65, 66, 67, 68)) + " FROM f",
        "feature_events_json": "SELECT CAST(event_id AS VARCHAR) AS sample_key, user_id, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, round(value / 500, 6) + 0.0 AS a0, round(CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100, 6) + 0.0 AS a1, round(hour(ts) / 24.0::DOUBLE, 6) + 0.0 AS a2, round(dayofweek(ts) / 7.0::DOUBLE, 6) + 0.0 AS a3, 1.0::DOUBLE AS a4 FROM events",
        "feature_text_hash": "WITH t AS (SELECT doc_id, lang, list_distinct(list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda x: x <> '')) AS w FROM documents), b AS (SELECT doc_id, lang, list_distinct(list_transform(w, lambda x: CAST('0x' || substr(md5(x), 1, 8) AS BIGINT) % 300)) AS p FROM t) SELECT CAST(doc_id AS VARCHAR) AS sample_key, CASE WHEN lang = 'en' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS label, CAST(len(p) AS INTEGER) AS ones, CAST(coalesce(list_sum(p), 0) AS BIGINT) AS total FROM b",
        "feature_star_onehot": STAR_SQL,
        "client_split_equal": f"WITH o AS (SELECT CAST(o_orderkey AS VARCHAR) AS sample_key FROM orders), r AS (SELECT sample_key, row_number() OVER (ORDER BY {q.draw_sql('7', 'sample_key')}, sample_key) - 1 AS n, (SELECT count(*) // 7 FROM o) AS per FROM o) SELECT sample_key, n // per AS client_id FROM r WHERE n < per * 7",
        "client_split_natural": "SELECT CAST(c_nationkey AS BIGINT) AS client_id, count(*) AS n, round(count(*) / CAST((SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) AS DOUBLE), 6) AS weight FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_nationkey",
        "client_stats": "SELECT user_id, count(*) AS n, round(avg(value), 6) AS mean, round(var_pop(value), 4) AS variance, round(stddev_pop(value), 6) AS deviation, round(covar_pop(value, CAST(json_extract_string(props, '$.k') AS DOUBLE)), 4) AS covariance FROM events GROUP BY user_id",
        "dataset_statistics": "WITH s AS (SELECT l_returnflag = 'R' AS y, unnest([l_discount * 10, l_tax * 12.5, 1.0::DOUBLE]) AS v FROM lineitem) SELECT count(*) // 3 AS n, CAST(sum(CAST(y AS INTEGER)) // 3 AS BIGINT) AS positives, CAST(3 AS INTEGER) AS d, round(count(*) FILTER (v <> 0) / CAST(count(*) AS DOUBLE), 6) AS density, round(avg(v), 6) AS mean, round(var_pop(v), 6) AS variance FROM s",
        "digest_table": "SELECT count(*) AS n, CAST(sum(CAST('0x' || substr(md5(concat_ws('|', CAST(o_orderkey AS VARCHAR), CAST(o_custkey AS VARCHAR), o_orderstatus)), 1, 8) AS BIGINT)) AS BIGINT) AS digest FROM orders",
        "vector_functions": "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings) SELECT vec_id, round(list_inner_product(e, e), 5) AS dot, round(sqrt(list_inner_product(e, e)), 5) AS norm, round(sqrt(2 * list_inner_product(e, e) + 3 - list_sum(list_transform([1, 3, 6, 10, 15, 21, 28, 36, 45, 55], lambda i: e[i] * e[i]))), 5) AS frobenius FROM v",
    }
    found |= {f"compress_{kind}": compressed_sql(kind) for kind in compressors.KINDS}
    found |= {f"hsn_rounds_{kind}": q.shifts_run(kind, 3, 4, alpha=1.0 if kind in ("identity", "topk", "tight") else 0.5 if kind != "natural" else 8 / 9) for kind in compressors.KINDS}
    found["hsn_step_project"] = q.shifts_run("topk", 3, 2, option="project", init="hessian")
    found["hsn_step_shift"] = q.shifts_run("topk", 3, 2, option="shift", init="hessian")
    found["hsn_ls_rounds"] = q.shifts_run("topk", 3, 3, option="project", init="hessian", line_search=(0.49, 0.5))
    found["newton_exact"] = q.shifts_run("identity", 6, 5, option="project", init="hessian")
    found |= {name: converged_sql(name) for name in CONVERGING}
    dense = q.minimiser(q.LONG["dense"], 20, DENSE, 1.0, 1000) + "SELECT CAST(j AS INTEGER) AS pos, round(x, 6) + 0.0 AS x FROM least"
    found |= {name: dense for name in (*(f"dense_{kind}" for kind in compressors.KINDS), "dense_shift_tight", "dense_ls_topk")}
    value = "SELECT true AS reached, round(max(f), 6) AS f FROM least"
    found["sparse_topk"] = q.minimiser(q.LONG["sparse"], 20, 301, 23.0, 1500) + value
    found["onehot_topk"] = q.minimiser(_star_cells(), 50, 124, 1.0, 300) + value
    return found


def _star_cells() -> str:
    """The one-hot workload in long form."""
    hot = STAR_SQL.strip().removeprefix("WITH a AS (").split("\n)\nSELECT")[0]
    keyed = hot.replace("SELECT CASE", f"SELECT {oracles.LINE_KEY} AS sample_key, CASE", 1)
    return f"a AS ({keyed}), cells AS (SELECT sample_key, label AS y, 1 + unnest(list_append(hot, 123)) AS j, 1.0::DOUBLE AS v FROM a)"


def _quad_sql() -> str:
    a = ["l_quantity / 50", "l_discount * 10", "1.0::DOUBLE"]
    h = ", ".join(f"avg(({a[i]}) * ({a[j]})) AS h{p}" for p, (i, j) in enumerate(oracles.ENTRIES))
    b = ", ".join(f"avg(({a[i]}) * l_extendedprice / 1e5) AS q{i}" for i in range(3))
    s = oracles.solve3([f"h{p}" for p in range(6)], ["q0", "q1", "q2"])
    return f"WITH m AS (SELECT {h}, {b} FROM lineitem) SELECT " + ", ".join(f"round({x}, 6) + 0.0 AS b{i + 1}" for i, x in enumerate(s)) + " FROM m"
