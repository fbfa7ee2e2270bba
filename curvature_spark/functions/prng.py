"""Portable keyed randomness: a pure function of integers, equal in Spark, Python and DuckDB.

The draw for keys (k1, k2, ...) is the number in the first 8 hex digits of md5("k1:k2:..."). A task that
runs again draws the same numbers, on any partitioning.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def draw(*keys: int) -> int:
    """An integer in 0..2^32-1."""
    return int(hashlib.md5(":".join(map(str, keys)).encode()).hexdigest()[:8], 16)


def draws(count: int, *keys: int) -> np.ndarray:
    """draw(*keys, i) for i in 0..count-1, all at once for those whose text fits one block of the digest."""
    head = (":".join(map(str, keys)) + ":").encode()
    out, low = np.empty(count, dtype=np.int64), 0
    while low < count:  # numbers with the same count of digits
        digits = len(str(low))
        high = min(count, 10**digits)
        if len(head) + digits <= 55:
            out[low:high] = _digests(head, np.arange(low, high), digits)
        else:
            out[low:high] = [int(hashlib.md5(head + str(i).encode()).hexdigest()[:8], 16) for i in range(low, high)]
        low = high
    return out


_SHIFTS = np.concatenate([np.tile(turns, 4) for turns in ([7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21])])
_SINES = np.floor(np.abs(np.sin(np.arange(1, 65))) * SPAN).astype(np.uint32)


def _digests(head: bytes, numbers: np.ndarray, digits: int) -> np.ndarray:
    """The first four bytes of the MD5 (RFC 1321) of head and number, big-endian, for numbers of so many digits."""
    size = len(head) + digits
    text = np.zeros((64, len(numbers)), dtype=np.uint8)
    text[: len(head)] = np.frombuffer(head, np.uint8)[:, None]
    for j in range(digits):
        text[len(head) + j] = 48 + numbers // 10 ** (digits - 1 - j) % 10
    text[size] = 128
    text[56:58] = np.array([size * 8 % 256, size * 8 // 256], np.uint8)[:, None]
    t = text.astype(np.uint32)
    words = t[0::4] | t[1::4] << np.uint32(8) | t[2::4] << np.uint32(16) | t[3::4] << np.uint32(24)
    a, b, c, d = (np.full(len(numbers), v, np.uint32) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    first = a
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f = f + a + words[g] + _SINES[i]
        turn = int(_SHIFTS[i])
        a, d, c, b = d, c, b, b + (f << np.uint32(turn) | f >> np.uint32(32 - turn))
    return (a + first).byteswap().astype(np.int64)


def uniform(*keys: int) -> float:
    """A number in [0, 1)."""
    return draw(*keys) / SPAN


def draw_column(*keys: Column | int | str) -> Column:
    """The same integer from columns and literals (integers, or strings standing for column names)."""
    parts = [F.lit(str(k)) if isinstance(k, int) else (F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("long")


def draw_sql(*keys: str) -> str:
    """The same integer as DuckDB SQL; keys are SQL expressions."""
    text = " || ':' || ".join(f"CAST({k} AS VARCHAR)" for k in keys)
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"
