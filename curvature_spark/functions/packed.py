"""Symmetric d x d matrices as their upper triangle, column by column: entry (i, j), i <= j, at j(j+1)/2 + i."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


def length(d: int) -> int:
    return d * (d + 1) // 2


def position(i: int, j: int) -> int:
    i, j = min(i, j), max(i, j)
    return j * (j + 1) // 2 + i


@lru_cache(maxsize=64)
def indices(d: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of all positions, computed once per process."""
    cols = np.repeat(np.arange(d), np.arange(1, d + 1))
    rows = np.arange(length(d)) - cols * (cols + 1) // 2
    return rows, cols


@lru_cache(maxsize=64)
def multiplicity(d: int) -> np.ndarray:
    """How often each position stands in the full matrix: 1 on the diagonal, 2 off it."""
    rows, cols = indices(d)
    return np.where(rows == cols, 1.0, 2.0)


def diagonal(d: int) -> np.ndarray:
    j = np.arange(d)
    return j * (j + 1) // 2 + j


def pack(full: np.ndarray) -> np.ndarray:
    rows, cols = indices(full.shape[0])
    return full[rows, cols]


def unpack(packed: np.ndarray, d: int) -> np.ndarray:
    rows, cols = indices(d)
    full = np.empty((d, d))
    full[rows, cols] = packed
    full[cols, rows] = packed
    return full


def frobenius(packed: np.ndarray, d: int) -> float:
    """Norm of the full matrix from the triangle alone."""
    return float(np.sqrt((multiplicity(d) * packed * packed).sum()))


def dimension(w: int) -> int:
    return int((np.sqrt(8 * w + 1) - 1) / 2 + 0.5)


def layout(d: int) -> str:
    """How a client's shift is held: one packed array, or tiles of rows once an array passes 64 MB."""
    return "packed" if 8 * length(d) <= 64 << 20 else "tiled"
