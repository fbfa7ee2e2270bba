"""What the methods are compared with; stand-ins for solvers that are not installed are named as such."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import packed
from . import server
from .compressors import Compressor, TopK
from .partition import Clients
from .problems import LogisticProblem, Problem
from .rounds import MOST_BYTES, RoundLog, _doubles, global_gradient, global_oracles, global_values, hessian_product, now
from .server import backtrack


def numpy_reference(blocks: dict[int, np.ndarray], problem: Problem, compressor: Compressor, *, option: str = "project", rounds: int = 50, tol: float = 1e-9, seed: int = 7, init: str = "hessian", alpha="default", line_search: tuple[float, float] | None = None) -> tuple[np.ndarray, RoundLog]:
    """The base method in one process with dense matrices: the prototype's way, and the engine's brute-force check."""
    ids = sorted(blocks)
    d = blocks[ids[0]].shape[1]
    w, x, log = packed.length(d), np.zeros(d), RoundLog()
    rate = compressor.alpha(w, alpha)
    oracle = lambda c, at: problem.finish(len(blocks[c]), problem.sums(blocks[c], at), at)
    shifts = {c: np.zeros(w) if init == "zero" else oracle(c, x)[2] for c in ids}
    h = np.mean([shifts[c] for c in ids], axis=0)
    for k in range(rounds):
        tick = now()
        f = l = 0.0
        g, s, items = np.zeros(d), np.zeros(w), 0
        for c in ids:
            fi, gi, hi = oracle(c, x)
            diff = hi - shifts[c]
            message = compressor(diff, d, (seed, k, c))
            sent = message.dense(w)
            shifts[c] = shifts[c] + rate * sent
            f, g, s, l, items = f + fi, g + gi, s + sent, l + packed.frobenius(diff, d), items + len(message.idx)
        n = len(ids)
        f, g, s, l = f / n, g / n, s / n, l / n
        norm = float(np.linalg.norm(g))
        p, halvings = server.newton_direction(h, l, g, option, getattr(problem, "lam", 0.0), "gauss"), 0
        if line_search and norm >= tol:
            value = lambda at: float(np.mean([problem.finish_values(len(blocks[c]), problem.values(blocks[c], at[None]), at[None])[0] for c in ids]))
            halvings = backtrack(lambda points: np.array([value(at) for at in points]), x, p, f, float(g @ p), *line_search)
            p = line_search[1] ** halvings * p
        log.add(run_id="numpy", round=k, f=f, grad_norm=norm, l=l, items=items, bytes=0, step_s=halvings, seconds=now() - tick)
        if norm < tol:
            break
        x = x + p
        h = h + rate * s
    return x, log


def mllib_logistic(samples: DataFrame, lam: float, tol: float = 1e-12, most: int = 200, d: int | None = None) -> tuple[np.ndarray, float]:
    """Spark MLlib's L-BFGS on the mean loss over all rows; binary samples (`hot`, needs d) go in as sparse vectors.

    Without an intercept of its own MLlib forces the weight of a constant column to 0, so the signs of half of
    the rows are flipped, (a, b) and (-a, -b) having the same loss: then no column is constant.
    """
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import CountVectorizerModel, Interaction
    from pyspark.ml.functions import array_to_vector

    sign = F.when(F.pmod(F.xxhash64("sample_key"), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    rows = samples.withColumn("_sign", sign).withColumn("_label", (F.col("label") * F.col("_sign") + 1) / 2)
    if "hot" in samples.columns:
        places = rows.select("_sign", "_label", F.col("hot").cast("array<string>").alias("_places"))
        ones = CountVectorizerModel.from_vocabulary([str(i) for i in range(d)], "_places", "_ones")
        rows = Interaction(inputCols=["_sign", "_ones"], outputCol="features").transform(ones.transform(places))
    else:
        rows = rows.withColumn("features", array_to_vector(F.transform("features", lambda v: v * F.col("_sign"))))
    rows = rows.select("features", F.col("_label").alias("label")).persist()
    rows.count()
    began = now()
    model = LogisticRegression(regParam=lam, elasticNetParam=0.0, standardization=False, fitIntercept=False, tol=tol, maxIter=most).fit(rows)
    seconds = now() - began
    rows.unpersist()
    return model.coefficients.toArray(), seconds


def lbfgs(clients: Clients, problem: Problem, memory: int = 10, rounds: int = 200, tol: float = 1e-9) -> tuple[np.ndarray, RoundLog]:
    """Data-parallel L-BFGS, one gradient job a step: stand-in for a task-parallel system with a library solver.

    The first step tried is judged by that job's value; only if it does not do, a job gives the values of the shorter ones.
    """
    x, log, pairs = np.zeros(clients.d), RoundLog(), []
    f, g = global_gradient(clients, problem, x)
    for k in range(rounds):
        tick = now()
        norm = float(np.linalg.norm(g))
        if norm < tol:
            log.add(run_id="lbfgs", round=k, f=f, grad_norm=norm, l=0.0, items=0, bytes=0, step_s=0, seconds=now() - tick)
            break
        q, coefficients = g.copy(), []
        for s, y in reversed(pairs):
            a = float(s @ q) / float(s @ y)
            coefficients.append(a)
            q -= a * y
        if pairs:
            s, y = pairs[-1]
            q *= float(s @ y) / float(y @ y)
        for (s, y), a in zip(pairs, reversed(coefficients), strict=True):
            q += (a - float(y @ q) / float(s @ y)) * s
        p, slope = -q, -float(g @ q)
        steps = 0.5 ** np.arange(20) if k else np.concatenate([[min(1.0, 1.0 / norm)], 0.5 ** np.arange(1, 20)])
        new, good = x + steps[0] * p, np.zeros(1, dtype=np.int64)
        f2, g2 = global_gradient(clients, problem, new)
        if not f2 <= f + 1e-4 * steps[0] * slope + 1e-15:
            good = 1 + np.nonzero(global_values(clients, problem, x + steps[1:, None] * p) <= f + 1e-4 * steps[1:] * slope + 1e-15)[0]
            new = x + (steps[good[0]] if len(good) else steps[-1]) * p
            f2, g2 = global_gradient(clients, problem, new)
        if float((new - x) @ (g2 - g)) > 1e-18:
            pairs = [*pairs, (new - x, g2 - g)][-memory:]
        log.add(run_id="lbfgs", round=k, f=f, grad_norm=norm, l=0.0, items=0, bytes=8 * clients.d * clients.n, step_s=int(good[0]) if len(good) else -1, seconds=now() - tick)
        x, f, g = new, f2, g2
    return x, log


def gradient_descent(clients: Clients, problem: Problem, smoothness: float | None = None, rounds: int = 300, tol: float = 1e-9, momentum: bool = False) -> tuple[np.ndarray, RoundLog]:
    """First-order baseline with step 1 / L, optionally accelerated."""
    x, log = np.zeros(clients.d), RoundLog()
    if smoothness is None:
        _, _, h = global_oracles(clients, problem, x)
        smoothness = float(np.linalg.eigvalsh(packed.unpack(h, clients.d))[-1])
    lam = max(getattr(problem, "lam", 0.0), 1e-12)
    beta = (np.sqrt(smoothness / lam) - 1) / (np.sqrt(smoothness / lam) + 1) if momentum else 0.0
    y = x
    for k in range(rounds):
        tick = now()
        f, g = global_gradient(clients, problem, y)
        norm = float(np.linalg.norm(g))
        log.add(run_id="gd", round=k, f=f, grad_norm=norm, l=0.0, items=clients.d * clients.n, bytes=8 * clients.d * clients.n, step_s=0, seconds=now() - tick)
        if norm < tol:
            break
        new = y - g / smoothness
        y, x = new + beta * (new - x), new
    return x, log


def folded(clients: Clients) -> dict[int, tuple[np.ndarray, np.ndarray]] | None:
    """Every client's distinct rows and how often each occurs, if rows repeat so much that all of them are few.

    Equal rows have equal gradients, so these stand for all rows of all clients. At most MOST_BYTES come to the driver, once;
    None says that there are more, and then every gradient is a job over the blocks.
    """
    import pyarrow as pa

    if clients.folded is not None:
        return clients.folded or None
    matrix = clients.reader()

    def fold(batches):
        for batch in batches:
            for i, (c, n) in enumerate(zip(batch.column("client_id").to_pylist(), batch.column("n_rows").to_pylist(), strict=True)):
                z = matrix(batch.column("z"), i, n)
                rows, counts = np.unique(z, axis=0, return_counts=True)
                kept = 4 * len(rows) <= n
                cells = (rows.tobytes(), counts.astype(np.int64).tobytes()) if kept else (None, None)
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.int64()), *[pa.array([v], pa.binary()) for v in cells]], ["c", "z", "n"])

    parts = clients.blocks.mapInArrow(fold, "c long, z binary, n binary").persist()
    size, missing = parts.agg(F.sum(F.length("z")), F.count_if(F.col("z").isNull())).first()
    clients.folded = {}
    if not missing and size and size <= MOST_BYTES:
        held: dict[int, list] = {}
        for r in parts.collect():  # at most MOST_BYTES
            held.setdefault(r.c, []).append((_doubles(r.z), np.frombuffer(r.n, dtype=np.int64)))
        for c, found in held.items():
            counts = np.concatenate([n for _, n in found])
            rows, place = np.unique(np.concatenate([z for z, _ in found]).reshape(len(counts), -1), axis=0, return_inverse=True)
            clients.folded[c] = rows, np.bincount(place.ravel(), weights=counts)
    parts.unpersist()
    return clients.folded or None


def client_gradients(clients: Clients, problem: LogisticProblem, x: np.ndarray) -> dict[int, np.ndarray]:
    """Every client's own gradient (n rows of d numbers)."""
    import pyarrow as pa

    few = folded(clients)
    if few is not None:
        found = {}
        for c, (z, counts) in few.items():
            e = np.exp(-np.abs(m := z @ x))
            found[c] = -(z.T @ (counts * np.where(m >= 0, e, 1.0) / (1.0 + e))) / clients.rows[c] + problem.lam * x
        return found
    matrix = clients.reader(multiplied=True)

    def work(batches):
        held = {}
        for batch in batches:
            for i, (c, n) in enumerate(zip(batch.column("client_id").to_pylist(), batch.column("n_rows").to_pylist(), strict=True)):
                z = matrix(batch.column("z"), i, n)
                e = np.exp(-np.abs(m := z @ x))
                held[c] = held.get(c, 0.0) - z.T @ (np.where(m >= 0, e, 1.0) / (1.0 + e))
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array([v.tobytes() for v in held.values()])], ["c", "g"])

    total: dict[int, np.ndarray] = {}
    for r in clients.blocks.mapInArrow(work, "c long, g binary").collect():
        total[r.c] = total.get(r.c, 0.0) + _doubles(r.g)
    return {c: v / clients.rows[c] + problem.lam * x for c, v in total.items()}


def compressed_gradient(clients: Clients, problem: LogisticProblem, k: int, smoothness: float, rounds: int = 300, tol: float = 1e-9, feedback: str = "difference") -> tuple[np.ndarray, RoundLog]:
    """First-order methods with compressed messages: gradient differences, or error feedback."""
    compressor = TopK(k)
    x, log = np.zeros(clients.d), RoundLog()
    memory = {c: np.zeros(clients.d) for c in clients.ids}
    mean = np.zeros(clients.d)
    for step in range(rounds):
        tick = now()
        grads = client_gradients(clients, problem, x)
        true = sum(clients.weight[c] * g for c, g in grads.items())
        norm = float(np.linalg.norm(true))
        sent = np.zeros(clients.d)
        for c, g in grads.items():
            target = g - memory[c] if feedback == "difference" else g / smoothness + memory[c]
            message = compressor(target, None, (0, step, c)).dense(clients.d)
            memory[c] = memory[c] + message if feedback == "difference" else target - message
            sent += clients.weight[c] * message
        log.add(run_id=feedback, round=step, f=0.0, grad_norm=norm, l=0.0, items=k * clients.n, bytes=12 * k * clients.n, step_s=0, seconds=now() - tick)
        if norm < tol:
            break
        mean = mean + sent
        x = x - (mean / smoothness if feedback == "difference" else sent)
    return x, log


def damped_newton(clients: Clients, problem: Problem, rounds: int = 50, tol: float = 1e-14) -> tuple[np.ndarray, RoundLog]:
    """Centralised second-order solver with backtracking: stand-in for interior-point solvers."""
    x, log = np.zeros(clients.d), RoundLog()
    for k in range(rounds):
        tick = now()
        f, g, h = global_oracles(clients, problem, x)
        norm = float(np.linalg.norm(g))
        log.add(run_id="newton", round=k, f=f, grad_norm=norm, l=0.0, items=0, bytes=8 * packed.length(clients.d) * clients.n, step_s=0, seconds=now() - tick)
        if norm < tol:
            break
        p = server.newton_direction(h, 0.0, g, "project", 1e-12)
        steps = 0.5 ** np.arange(30)
        good = np.nonzero(global_values(clients, problem, x + steps[:, None] * p) <= f + 1e-4 * steps * float(g @ p))[0]
        if norm > 1e-6 and len(good):
            p = steps[good[0]] * p
        x = x + p
    return x, log


def newton_cg(clients: Clients, problem: LogisticProblem, rounds: int = 30, tol: float = 1e-9) -> tuple[np.ndarray, RoundLog]:
    """Newton steps by conjugate gradients on distributed Hessian-vector products: no d x d matrix anywhere."""
    x, log = np.zeros(clients.d), RoundLog()
    for k in range(rounds):
        tick = now()
        f, g = global_gradient(clients, problem, x)
        norm = float(np.linalg.norm(g))
        log.add(run_id="newton_cg", round=k, f=f, grad_norm=norm, l=0.0, items=0, bytes=0, step_s=0, seconds=now() - tick)
        if norm < tol:
            break
        at = x
        x = x - server.conjugate_gradient(lambda v: hessian_product(clients, problem, at, v), g, tol=min(0.1, norm), most=4 * clients.d)  # noqa: B023
    return x, log


def admm(clients: Clients, problem: LogisticProblem, rho: float = 0.1, rounds: int = 200, tol: float = 1e-9) -> tuple[np.ndarray, RoundLog]:
    """Consensus by operator splitting, clients solving their proximal problem with Newton: stand-in for SCS.

    A client's rows must lie in one task here: its problem is solved whole.
    """
    import pyarrow as pa

    d, n, matrix = clients.d, clients.n, clients.reader(getattr(problem, "multiplies", False))
    z, log = np.zeros(d), RoundLog()
    dual = {c: np.zeros(d) for c in clients.ids}
    for k in range(rounds):
        tick = now()
        sent = clients.blocks.sparkSession.sparkContext.broadcast((z, dual))

        def local(key, table):
            c = key[0].as_py()
            centre = sent.value[0] - sent.value[1][c]
            blocks, x = table.column("z").combine_chunks(), sent.value[0].copy()
            rows = table.column("n_rows").to_pylist()
            for _ in range(30):
                # Block by block: a client's matrix is never there as a whole.
                parts = [problem.sums(matrix(blocks, i, m), x) for i, m in enumerate(rows)]
                _, g, h = problem.finish(sum(rows), tuple(sum(p[j] for p in parts) for j in range(3)), x)
                g = g + rho * (x - centre)
                if np.linalg.norm(g) < 1e-12:
                    break
                x = x - np.linalg.solve(packed.unpack(h, d) + rho * np.eye(d), g)
            return pa.table({"c": [c], "x": [x.tobytes()]})

        found = {r.c: _doubles(r.x) for r in clients.blocks.groupBy("client_id").applyInArrow(local, "c long, x binary").collect()}
        z = sum(found[c] + dual[c] for c in clients.ids) / n
        dual = {c: dual[c] + found[c] - z for c in clients.ids}
        f, g = global_gradient(clients, problem, z)
        norm = float(np.linalg.norm(g))
        log.add(run_id="admm", round=k, f=f, grad_norm=norm, l=0.0, items=0, bytes=16 * d * n, step_s=0, seconds=now() - tick)
        if norm < tol:
            break
    return z, log
