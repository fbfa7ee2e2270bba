"""Compressors of packed symmetric matrices, and of plain vectors (d=None: every entry counts once).

Each call returns positions and values of what is sent. Random choices are keyed by (seed, round, client), so a
replayed task sends the same message.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np

from ..functions import packed, prng


@dataclass(frozen=True)
class Message:
    idx: np.ndarray
    val: np.ndarray
    payload: int  # bytes beyond gradient and scalars

    def dense(self, w: int) -> np.ndarray:
        out = np.zeros(w)
        np.add.at(out, self.idx, self.val)
        return out


def scores(v: np.ndarray, d: int | None, ranking: str) -> np.ndarray:
    """What selection ranks by: |v|, times sqrt 2 off the diagonal if the full matrix's norm is to be kept."""
    return np.abs(v) * np.sqrt(packed.multiplicity(d)) if d and ranking == "frobenius" else np.abs(v)


def largest(score: np.ndarray, k: int, impl: str = "partition") -> np.ndarray:
    """Positions of the k largest scores, ties to the smaller position, in falling order.

    Scores are compared after rounding to 12 decimals, which keeps the choice the same in other engines.
    """
    s = np.round(score, 12)
    k = min(k, len(s))
    if k == 0:
        return np.empty(0, dtype=np.int64)
    if impl == "sort":
        return np.lexsort((np.arange(len(s)), -s))[:k]
    if impl == "heap":
        held: list[tuple[float, int]] = []
        for p, x in enumerate(s.tolist()):
            item = (x, -p)
            if len(held) < k:
                heapq.heappush(held, item)
            elif item > held[0]:
                heapq.heapreplace(held, item)
        return np.array([-p for _, p in sorted(held, reverse=True)], dtype=np.int64)
    edge = np.partition(s, len(s) - k)[len(s) - k]
    over, ties = np.nonzero(s > edge)[0], np.nonzero(s == edge)[0]
    chosen = np.concatenate([over, ties[: k - len(over)]])
    return chosen[np.lexsort((chosen, -s[chosen]))]


class Compressor:
    """name; k of w entries; unbiased or contractive; theoretical step constant."""

    name = "identity"
    unbiased = False

    def __init__(self, k: int | None = None, ranking: str = "frobenius", impl: str = "partition", indices: str = "seed", scaled: bool = True):
        self.k, self.ranking, self.impl, self.indices, self.scaled = k, ranking, impl, indices, scaled

    def omega(self, w: int) -> float:
        """Variance constant of the unbiased form (0: exact)."""
        return 0.0

    def delta(self, w: int) -> float:
        """Contraction: the mean squared error is at most (1 - delta) of the square."""
        return 1.0

    def alpha(self, w: int, rule: str | float) -> float:
        """Step constant of the shift: a number, 1, 1 - sqrt(1 - delta), or 1 / (omega + 1)."""
        if not isinstance(rule, str):
            return float(rule)
        if rule == "default":
            rule = "unbiased" if self.unbiased and self.scaled else "unit"
        return {"unit": 1.0, "contractive": 1 - np.sqrt(max(0.0, 1 - self.delta(w))), "unbiased": 1 / (self.omega(w) + 1)}[rule]

    def budget(self, w: int) -> int:
        return min(self.k or w, w)

    def __call__(self, v: np.ndarray, d: int | None, key: tuple[int, ...]) -> Message:
        return Message(np.arange(len(v)), v, 8 * len(v))

    def _random_message(self, idx: np.ndarray, v: np.ndarray) -> Message:
        factor = len(v) / len(idx) if self.scaled and len(idx) else 1.0
        return Message(idx, v[idx] * factor, (8 if self.indices == "seed" else 12) * len(idx))


class Identity(Compressor):
    pass


class TopK(Compressor):
    name = "topk"

    def delta(self, w: int) -> float:
        return self.budget(w) / w

    def __call__(self, v, d, key):
        idx = np.sort(largest(scores(v, d, self.ranking), self.budget(len(v)), self.impl))
        return Message(idx, v[idx], 12 * len(idx))


class RandK(Compressor):
    """A uniform K-subset: the K smallest keyed draws, one per position."""

    name, unbiased = "randk", True

    def omega(self, w: int) -> float:
        return w / self.budget(w) - 1

    def delta(self, w: int) -> float:
        return self.budget(w) / w

    def __call__(self, v, d, key):
        order = np.lexsort((np.arange(len(v)), prng.draws(len(v), *key)))
        return self._random_message(np.sort(order[: self.budget(len(v))]), v)


class WindowK(Compressor):
    """K positions side by side from a uniform start, wrapping round: one draw, contiguous reads."""

    name, unbiased = "windowk", True
    omega, delta = RandK.omega, RandK.delta

    def positions(self, w: int, key: tuple[int, ...]) -> np.ndarray:
        return np.sort((prng.draw(*key) % w + np.arange(self.budget(w))) % w)

    def __call__(self, v, d, key):
        return self._random_message(self.positions(len(v), key), v)


class TightTopK(Compressor):
    """As few of the largest entries as keep the contraction delta = K / w with equality in expectation."""

    name = "tight"

    def delta(self, w: int) -> float:
        return self.budget(w) / w

    def split(self, v: np.ndarray, d: int | None) -> tuple[np.ndarray, int, float]:
        """Order of the entries, the smallest count whose share of the square reaches delta, and the chance of one less."""
        energy = v * v * (packed.multiplicity(d) if d else 1.0)
        order = largest(np.sqrt(energy), len(v), "sort")
        total = energy.sum()
        if not total > 0:
            return order, 0, 0.0
        share = np.concatenate([[0.0], np.cumsum(energy[order]) / total])
        delta = self.delta(len(v))
        k = min(int(np.searchsorted(share, delta - 1e-15)), int(np.count_nonzero(energy)))
        step = share[k] - share[k - 1] if k else 0.0
        return order, k, float(min(1.0, max(0.0, (share[k] - delta) / step))) if step > 0 else 0.0

    def __call__(self, v, d, key):
        order, k, less = self.split(v, d)
        if k and prng.uniform(*key) < less:
            k -= 1
        idx = np.sort(order[:k])
        return Message(idx, v[idx], 12 * k + 4)


class Natural(Compressor):
    """Every value to one of its two neighbouring powers of two, unbiased; 12 bits a value."""

    name, unbiased = "natural", True

    def omega(self, w: int) -> float:
        return 0.125

    def delta(self, w: int) -> float:
        return 1 / 1.125

    def __call__(self, v, d, key):
        mantissa, exponent = np.frexp(np.abs(v))  # |v| = mantissa * 2^exponent with mantissa in [1/2, 1)
        up = prng.draws(len(v), *key) / prng.SPAN < 2 * mantissa - 1
        out = np.sign(v) * np.where(v == 0, 0.0, np.ldexp(0.5, exponent + up))
        out[np.abs(v) < np.finfo(float).tiny] = 0.0
        return Message(np.arange(len(v)), out, -(-3 * len(v) // 2))


KINDS = {c.name: c for c in (Identity, TopK, RandK, WindowK, TightTopK, Natural)}


def make(name: str, k: int | None = None, **options) -> Compressor:
    return KINDS[name](k, **options)
