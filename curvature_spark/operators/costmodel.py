"""Analytic measures: bytes, arithmetic, memory transactions and transfer time."""

from __future__ import annotations

from ..functions import packed

MB = float(1 << 20)


def payload_bytes(kind: str, d: int, k: int, kept: float | None = None, indices: str = "seed") -> float:
    """Bytes of one compressed message beyond gradient and scalars."""
    w = packed.length(d)
    return {
        "identity": 8.0 * w,
        "topk": 12.0 * k,
        "randk": (8.0 if indices == "seed" else 12.0) * k,
        "windowk": (8.0 if indices == "seed" else 12.0) * k,
        "tight": 12.0 * (k if kept is None else kept) + 4,
        "natural": float(-(-3 * w // 2)),
    }[kind]


def total_megabytes(kind: str, d: int, n: int, rounds: int, k: int, kept: float | None = None, indices: str = "seed") -> float:
    """What the server collects over a run: gradient, two scalars and the message of every client and round."""
    return n * rounds * (8 * d + 16 + payload_bytes(kind, d, k, kept, indices)) / MB


def client_flops(d: int, rows: int) -> float:
    """One client's oracles: triangle of the Hessian over its rows, gradient, difference and norm."""
    return d * d * rows + d * rows + 2.0 * d * d


def server_flops(d: int, n: int, sent: float, solver: str = "cholesky") -> float:
    """Adding n messages and one solve (Cholesky d^3 / 3, elimination 2 d^3 / 3, eigenvalues 9 d^3)."""
    return n * (d * sent + d) + {"cholesky": d**3 / 3, "gauss": 2 * d**3 / 3, "eigen": 9.0 * d**3}[solver]


def run_seconds(d: int, n: int, rows: int, k: int, rounds: int, flops: float, solver: str = "cholesky") -> float:
    """Seconds of a run at `flops` operations a second, clients and server one after the other."""
    return rounds * (n * client_flops(d, rows) + server_flops(d, n, k / d, solver)) / flops


def memory_transactions(kind: str, k: int, width: int = 8, line: int = 64) -> float:
    """Cache lines touched by k values: one each if scattered, side by side k * width / line + 2 at most."""
    return k * width / line + 2 if kind == "windowk" else float(k)


def transfer_seconds(size: float, rate_mbit: float, rtt: float = 0.0) -> float:
    return rtt + size * 8 / (rate_mbit * 1e6)
