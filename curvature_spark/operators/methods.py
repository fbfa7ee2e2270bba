"""Second-order training over clients that send compressed corrections of their Hessian estimates.

    train_shifts       every client every round; option 'project' or 'shift'; optional backtracking or cubic model
    train_partial      tau of n clients a round
Exact Newton is train_shifts with the identity compressor, step constant 1 and option 'project'.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..functions import packed
from . import server
from .compressors import Compressor
from .partition import Clients
from .problems import Problem
from .rounds import Engine, Means, RoundLog, global_gradient, now


@dataclass
class Fit:
    x: np.ndarray
    log: RoundLog
    h: np.ndarray
    engine: Engine
    seconds: float

    @property
    def rounds(self) -> int:
        return len(self.log.rows)

    def rounds_to(self, tol: float) -> int | None:
        """Rounds of communication until the gradient norm is below `tol`."""
        return next((r["round"] for r in self.log.rows if r["grad_norm"] < tol), None)

    @property
    def bytes(self) -> int:
        return sum(r["bytes"] for r in self.log.rows)


def message_bytes(d: int, payload: int, clients: int) -> int:
    """What clients send in a round: gradient, two scalars and the compressed message each."""
    return clients * (8 * d + 16) + payload


def train_shifts(
    clients: Clients,
    problem: Problem,
    compressor: Compressor,
    *,
    option: str = "project",
    alpha: str | float = "default",
    mu: float | None = None,
    rounds: int = 100,
    tol: float = 1e-9,
    seed: int = 7,
    init: str = "hessian",
    x0: np.ndarray | None = None,
    line_search: tuple[float, float] | None = None,
    lipschitz: float | None = None,
    solver: str = "cholesky",
    commit_every: int = 10,
    lazy: bool = False,
    run_id: str = "shifts",
    inspect: Callable[[int, np.ndarray, Means], None] | None = None,
    owner: str = "session",
) -> Fit:
    """Train with every client in every round.

    The step uses the mean shift as it was before this round's corrections. line_search = (c, shrink) turns
    on backtracking; lipschitz gives the cubic model's constant. lazy computes, with WindowK and 'project', only the
    Hessian entries that are sent. Round k of the log has the value and gradient norm at x^k.
    """
    d = clients.d
    w = packed.length(d)
    rate = compressor.alpha(w, alpha)
    mu = getattr(problem, "lam", 0.0) if mu is None else mu
    engine = Engine(clients, problem, compressor, rate, seed, commit_every, lazy and option == "project", owner)
    began = now()
    x = np.zeros(d) if x0 is None else np.array(x0, dtype=float)
    h, _ = engine.start(x, init)
    log = RoundLog()
    for k in range(rounds):
        tick = now()
        m = engine.round(x, k)
        norm = float(np.linalg.norm(m.g))
        if inspect:
            inspect(k, x, m)
        row = {"run_id": run_id, "round": k, "f": m.f, "grad_norm": norm, "l": m.l, "items": m.items, "bytes": message_bytes(d, m.payload, m.clients), "step_s": 0}
        if norm >= tol:
            if lipschitz is not None:
                p = server.cubic_direction(h, m.l, m.g, lipschitz)
            else:
                p = server.newton_direction(h, m.l, m.g, option, mu, solver)
            if line_search:
                row["step_s"] = server.backtrack(engine.values, x, p, m.f, float(m.g @ p), *line_search)
                p = line_search[1] ** row["step_s"] * p
            x = x + p
            h = h + rate * m.s
        log.add(**row, seconds=now() - tick)
        if norm < tol:
            break
    engine.release()
    return Fit(x, log, h, engine, now() - began)


def train_partial(
    clients: Clients,
    problem: Problem,
    compressor: Compressor,
    tau: int,
    *,
    alpha: str | float = "default",
    rounds: int = 200,
    tol: float = 1e-9,
    seed: int = 7,
    init: str = "hessian",
    x0: np.ndarray | None = None,
    probe_every: int = 1,
    solver: str = "cholesky",
    commit_every: int = 5,
    run_id: str = "partial",
    owner: str = "session",
) -> Fit:
    """Train with tau clients a round.

    The server solves (H + l I) x = g from running means of the clients' shifts, error norms and corrected
    gradients, and adds the changes of those that took part. The gradient norm is a measurement: a pass of its own over
    all clients every `probe_every` rounds, not part of the method's cost.
    """
    d, n = clients.d, clients.n
    engine = Engine(clients, problem, compressor, compressor.alpha(packed.length(d), alpha), seed, commit_every, owner=owner)
    began = now()
    x = np.zeros(d) if x0 is None else np.array(x0, dtype=float)
    h, l, g = start_partial(engine, x, init)
    log = RoundLog()
    for k in range(rounds):
        tick = now()
        x = server.SOLVERS[solver](packed.unpack(h, d) + l * np.eye(d), g)
        chosen = [clients.ids[i] for i in server.participants(n, tau, seed, k)]
        m = engine.round(x, k, None if tau >= n else chosen, track=True)
        h, l, g = h + engine.alpha * m.s, l + m.l, g + m.g
        seconds = now() - tick
        f, grad = global_gradient(clients, problem, x) if probe_every and k % probe_every == 0 else (None, None)
        norm = float(np.linalg.norm(grad)) if grad is not None else float("nan")
        log.add(run_id=run_id, round=k, f=f, grad_norm=norm, l=l, items=m.items, bytes=message_bytes(d, m.payload, m.clients), step_s=0, seconds=seconds)
        if norm < tol:
            break
    engine.release()
    return Fit(x, log, h, engine, now() - began)


def start_partial(engine: Engine, x: np.ndarray, init: str) -> tuple[np.ndarray, float, np.ndarray]:
    """First shifts, error norms and corrected gradients of all clients, and their means.

    A round at x that moves no shift (step constant 0) makes the clients' error norms and corrected gradients.
    """
    h, _ = engine.start(x, init)
    kept, engine.alpha = engine.alpha, 0.0
    m = engine.round(x, -1, track=True)
    engine.alpha = kept
    return h, m.l, m.g


def shift_gap(fit: Fit) -> float:
    """Largest difference between the server's mean shift and the mean of the clients' shifts."""
    total = np.zeros_like(fit.h)
    for r in fit.engine.shifts.select("client_id", "h").toLocalIterator():
        total += fit.engine.clients.weight[r.client_id] * np.frombuffer(r.h, dtype=np.float64)
    return float(np.abs(total - fit.h).max())


def predict(samples: DataFrame, x: np.ndarray) -> DataFrame:
    """samples with margin, probability and predicted label (+1 or -1), in JVM expressions."""
    from pyspark.sql import functions as F

    from ..functions.vectors import dot, sigmoid

    weights = F.array(*[F.lit(float(v)) for v in x])
    out = samples.withColumn("margin", dot(F.col("features"), weights))
    return out.withColumn("probability", sigmoid(F.col("margin"))).withColumn("predicted", F.when(F.col("margin") >= 0, 1.0).otherwise(-1.0))
