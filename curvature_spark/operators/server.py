"""The driver's part of a round: small dense algebra on d x d matrices."""

from __future__ import annotations

import numpy as np

from ..functions import packed, prng


def projected(h: np.ndarray, mu: float) -> np.ndarray:
    """The nearest matrix with all eigenvalues at least mu: eigenvalues below are raised to mu."""
    values, vectors = np.linalg.eigh(h)
    return h if values[0] >= mu else (vectors * np.maximum(values, mu)) @ vectors.T


def cholesky_solve(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    lower = np.linalg.cholesky(a)
    return triangular(lower.T, triangular(lower, b, lower_part=True), lower_part=False)


def triangular(t: np.ndarray, b: np.ndarray, lower_part: bool, block: int = 64) -> np.ndarray:
    """Substitution by blocks."""
    n, x = len(b), np.array(b, dtype=float)
    edges = list(range(0, n, block))
    for a in edges if lower_part else reversed(edges):
        e = min(n, a + block)
        x[a:e] = np.linalg.solve(t[a:e, a:e], x[a:e])
        if lower_part:
            x[e:] -= t[e:, a:e] @ x[a:e]
        else:
            x[:a] -= t[:a, a:e] @ x[a:e]
    return x


def jacobi(a: np.ndarray, b: np.ndarray, tol: float = 1e-12, most: int = 10_000) -> np.ndarray:
    x, diag = np.zeros_like(b), np.diag(a)
    for _ in range(most):
        r = b - a @ x
        if np.linalg.norm(r) <= tol * np.linalg.norm(b):
            break
        x = x + r / diag
    return x


def gauss_seidel(a: np.ndarray, b: np.ndarray, tol: float = 1e-12, most: int = 10_000) -> np.ndarray:
    x, low, up = np.zeros_like(b), np.tril(a), np.triu(a, 1)
    for _ in range(most):
        if np.linalg.norm(b - a @ x) <= tol * np.linalg.norm(b):
            break
        x = triangular(low, b - up @ x, lower_part=True)
    return x


def conjugate_gradient(product, b: np.ndarray, tol: float = 1e-12, most: int = 1000) -> np.ndarray:
    """Solves A x = b from products with A, a matrix or a function (which may run a Spark job)."""
    product = product if callable(product) else product.__matmul__
    x, r = np.zeros_like(b), b.copy()
    p, rr = r.copy(), float(r @ r)
    for _ in range(most):
        if np.sqrt(rr) <= tol * np.linalg.norm(b):
            break
        q = product(p)
        step = rr / float(p @ q)
        x, r = x + step * p, r - step * q
        new = float(r @ r)
        p, rr = r + new / rr * p, new
    return x


def qr_solve(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    q, r = np.linalg.qr(a)
    return triangular(r, q.T @ b, lower_part=False)


SOLVERS = {"cholesky": cholesky_solve, "gauss": np.linalg.solve, "qr": qr_solve, "jacobi": jacobi, "gauss_seidel": gauss_seidel, "cg": conjugate_gradient}


def newton_direction(h: np.ndarray, l: float, g: np.ndarray, option: str, mu: float, solver: str = "cholesky") -> np.ndarray:
    """-[H]^-1 g with H projected ('project') or shifted by l ('shift'); h is packed."""
    full = packed.unpack(h, len(g))
    safe = projected(full, mu) if option == "project" else full + l * np.eye(len(g))
    return -SOLVERS[solver](safe, g)


def cubic_direction(h: np.ndarray, l: float, g: np.ndarray, lipschitz: float) -> np.ndarray:
    """Minimiser of <g, p> + p'(H + l I)p / 2 + (lipschitz / 6) |p|^3, by its one-dimensional dual."""
    values, vectors = np.linalg.eigh(packed.unpack(h, len(g)) + l * np.eye(len(g)))
    c = vectors.T @ g
    reach = lambda r: float(np.linalg.norm(c / np.maximum(values + lipschitz * r / 2, 1e-300)))
    low, high = max(0.0, -2 * values[0] / lipschitz) if lipschitz else 0.0, 1.0
    while reach(high) > high:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if reach(mid) > mid else (low, mid)
    return -(vectors @ (c / (values + lipschitz * high / 2)))


#: Shortest step tried by backtracking: the search direction times shrink to this power.
STEP_LIMIT = 30


def backtrack(values, x: np.ndarray, p: np.ndarray, f: float, slope: float, c: float, shrink: float) -> int:
    """Smallest s with f(x + shrink^s p) <= f + c shrink^s slope; `values` gives f at several points in one pass: at the full
    step, and only if that does not do, at all shorter ones.

    Near the optimum f stops moving at rounding: a full step whose promised decrease is below that is taken.
    """
    if abs(c * slope) < 1e-13 * max(1.0, abs(f)):
        return 0
    steps = shrink ** np.arange(STEP_LIMIT + 1)
    for tried in (slice(0, 1), slice(1, None)):
        good = np.nonzero(values(x + steps[tried, None] * p) <= f + c * steps[tried] * slope)[0]
        if len(good):
            return tried.start + int(good[0])
    raise RuntimeError("no step along the search direction decreases the objective")


def participants(n: int, tau: int, seed: int, step: int) -> np.ndarray:
    """tau of the clients numbered 0..n-1, uniformly: those of smallest keyed draw."""
    order = np.lexsort((np.arange(n), prng.draws(n, seed, step)))
    return np.sort(order[:tau])
