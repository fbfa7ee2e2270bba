"""Objectives: value, gradient and Hessian triangle of a client block, as sums over its rows.

A block is the matrix Z whose rows are label * features. Sums carry no regulariser and are not divided by
the number of rows, so blocks of one client, wherever they lie, add up; `finish` divides and adds the
regulariser to each client's own function.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np

from ..functions import packed

Sums = tuple[float, np.ndarray, np.ndarray]


class Problem(Protocol):
    """What a caller must provide to train an objective of their own."""

    def sums(self, z: np.ndarray, x: np.ndarray) -> Sums: ...

    def values(self, z: np.ndarray, points: np.ndarray) -> np.ndarray: ...

    def finish(self, n: float, sums: Sums, x: np.ndarray) -> Sums: ...

    def finish_values(self, n: float, values: np.ndarray, points: np.ndarray) -> np.ndarray: ...


class _L2:
    """Adds (lam / 2) |x|^2 to every client's mean; lam = 0 is no regulariser."""

    lam: float

    def finish(self, n: float, sums: Sums, x: np.ndarray) -> Sums:
        f, g, h = sums
        h = h / n
        h[packed.diagonal(len(x))] += self.lam
        return f / n + 0.5 * self.lam * float(x @ x), g / n + self.lam * x, h

    def finish_values(self, n: float, values: np.ndarray, points: np.ndarray) -> np.ndarray:
        return values / n + 0.5 * self.lam * (points * points).sum(axis=1)


class LogisticProblem(_L2):
    """Logistic loss of margins m = Z x; the sigmoid is computed once for value, gradient and Hessian."""

    #: Sums and values take blocks of positions (`partition.Ones`) as they take matrices.
    multiplies = True

    def __init__(self, lam: float = 1e-3):
        self.lam = lam

    def sums(self, z: np.ndarray, x: np.ndarray) -> Sums:
        m = z @ x
        e = np.exp(-np.abs(m))
        value = (np.maximum(-m, 0.0) + np.log1p(e)).sum()
        s = np.where(m >= 0, e, 1.0) / (1.0 + e)  # sigmoid(-m)
        root = np.sqrt(s * (1.0 - s))
        half = z.matrix(root) if hasattr(z, "matrix") else root[:, None] * z  # a matrix times its own transpose costs half of a product
        return float(value), -(z.T @ s), packed.pack(half.T @ half)

    def grouped(self, z: np.ndarray, x: np.ndarray, group: np.ndarray, count: int) -> tuple[np.ndarray, np.ndarray]:
        """Gradient and Hessian sums of many small groups at once: row i belongs to group[i] in 0..count-1."""
        m = z @ x
        e = np.exp(-np.abs(m))
        s = np.where(m >= 0, e, 1.0) / (1.0 + e)
        rows, cols = packed.indices(z.shape[1])
        by = lambda values: np.stack([np.bincount(group, weights=v, minlength=count) for v in values.T], axis=1)
        return by(-s[:, None] * z), by((s * (1.0 - s))[:, None] * z[:, rows] * z[:, cols])

    def values(self, z: np.ndarray, points: np.ndarray) -> np.ndarray:
        m = z @ points.T
        return (np.maximum(-m, 0.0) + np.log1p(np.exp(-np.abs(m)))).sum(axis=0)

    def entries(self, z: np.ndarray, x: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Hessian sums at the packed positions `at` only: rows(at) * n multiplications, not the whole triangle."""
        m = np.abs(z @ x)
        e = np.exp(-m)
        h = e / (1.0 + e) ** 2
        rows, cols = packed.indices(z.shape[1])
        return np.einsum("nk,nk->k", h[:, None] * z[:, rows[at]], z[:, cols[at]])


class QuadraticProblem(_L2):
    """Least squares: rows are (features, target), the value is half the squared residual."""

    def __init__(self, lam: float = 0.0):
        self.lam = lam

    def sums(self, z: np.ndarray, x: np.ndarray) -> Sums:
        a, b = z[:, :-1], z[:, -1]
        r = a @ x - b
        return 0.5 * float(r @ r), a.T @ r, packed.pack(a.T @ a)

    def values(self, z: np.ndarray, points: np.ndarray) -> np.ndarray:
        r = z[:, :-1] @ points.T - z[:, -1:]
        return 0.5 * (r * r).sum(axis=0)


#: Rows whose values are summed before central differences are taken.
PIECE = 1024


def difference_sums(problem: Problem, z: np.ndarray, x: np.ndarray, eps: float = 1e-5) -> np.ndarray:
    """Sums over the rows of a block: gradient, Hessian, and differences of values and of gradients around x.

    Differences are taken over PIECE rows at a time: those of sums over millions of rows would lose to rounding
    what they are meant to show. The vectors of a client's blocks add up.
    """
    d = len(x)
    steps = eps * np.eye(d)
    points = np.concatenate([x + steps, x - steps])
    total = np.zeros(d + packed.length(d) + d + d * d)
    for a in range(0, len(z), PIECE):
        piece = z[a : a + PIECE]
        _, g, h = problem.sums(piece, x)
        values = problem.values(piece, points)
        columns = [problem.sums(piece, x + s)[1] - problem.sums(piece, x - s)[1] for s in steps]
        total += np.concatenate([g, h, values[:d] - values[d:], *columns])
    return total


def difference_errors(problem: Problem, n: int, sums: np.ndarray, x: np.ndarray, eps: float = 1e-5) -> tuple[float, float]:
    """Largest absolute error of gradient and Hessian of n rows with these `difference_sums`."""
    d, w = len(x), packed.length(len(x))
    g, h, values, columns = np.split(np.array(sums), np.cumsum([d, w, d]))
    _, grad, hessian = problem.finish(n, (0.0, g, h), x)
    steps, none, blank = eps * np.eye(d), np.zeros(d), np.zeros(w)
    near = (problem.finish_values(n, values, x + steps) - problem.finish_values(n, none, x - steps)) / (2 * eps)
    sides = [problem.finish(n, (0.0, c, blank), x + s)[1] - problem.finish(n, (0.0, none, blank), x - s)[1] for c, s in zip(columns.reshape(d, d), steps, strict=True)]
    return float(np.abs(near - grad).max()), float(np.abs(np.array(sides) / (2 * eps) - packed.unpack(hessian, d)).max())


def check_oracles(problem: Problem, z: np.ndarray, x: np.ndarray, eps: float = 1e-5) -> tuple[float, float]:
    """Largest absolute error of gradient and Hessian against central differences."""
    return difference_errors(problem, len(z), difference_sums(problem, z, x, eps), x, eps)


def curvature_bounds(h: np.ndarray, d: int) -> tuple[float, float, float]:
    """Least and largest eigenvalue of a packed Hessian and their ratio."""
    values = np.linalg.eigvalsh(packed.unpack(h, d))
    return float(values[0]), float(values[-1]), float(values[-1] / values[0])


def lipschitz_ratios(hx: np.ndarray, hy: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
    """|H(x) - H(y)| / |x - y| in the spectral, Frobenius and largest-entry norms."""
    d, gap = len(x), float(np.linalg.norm(x - y))
    diff = packed.unpack(hx - hy, d)
    return float(np.abs(np.linalg.eigvalsh(diff)).max()) / gap, packed.frobenius(hx - hy, d) / gap, float(np.abs(diff).max()) / gap
