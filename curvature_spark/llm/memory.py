"""Python workers that give memory back between tasks.

A worker lives on and serves the next stages; what it has freed stays with its allocators, so that the workers of an
executor would add up the peaks of all stages that ran on it.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa


def give_back() -> None:
    """Return freed memory to the system, where the allocators offer that."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def lean(work: Callable[[Iterable], Iterator]) -> Callable[[Iterable], Iterator]:
    """`work`, a function over batches, followed by giving memory back."""

    def run(batches):
        try:
            yield from work(batches)
        finally:
            give_back()

    return run
