"""One round as a Spark job: oracles at the iterate, compressed differences, new shifts, and their means.

    pinned blocks, clustered and sorted by client --+-- joined by client --> one Arrow pass:
    shifts of the last round, one row a client -----+      sums of a client's blocks, difference to its shift,
                                                           error norm, message, new shift; one row of means a task

Blocks never move after they are pinned; a round shuffles the shifts, one triangle a client. A client whose blocks are
spread by salts meets as sums: one triangle a client and task is shuffled instead of its blocks. The shifts are a distributed
table: kept for the next round, and written to shared storage every `commit_every` rounds, which bounds what a lost
executor costs.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import packed
from ..plans.cuts import written
from .compressors import Compressor, WindowK
from .partition import Clients
from .problems import Problem

STATE = "client_id long, l double, g binary, h binary"
MADE = "kind int, client_id long, f double, l double, items long, payload long, clients long, g binary, h binary"
SUMS = "client_id long, n_rows int, f double, sum_g binary, sum_h binary"
SHIFT, TOTAL = 0, 1
#: Bytes of partial sums that may meet in one place; more go through another level of summation first.
MOST_BYTES = 64 << 20


def _names(schema: str) -> list[str]:
    return [c.split()[0] for c in schema.split(", ")]


TYPES = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "binary": pa.binary()}


def _batch(schema: str, *rows: tuple) -> pa.RecordBatch:
    types = [TYPES[c.split()[1]] for c in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], _names(schema))


def _resting(batch: pa.RecordBatch) -> pa.RecordBatch:
    """Shifts as they were, of clients that take no part in a round."""
    none = dict.fromkeys(_names(MADE), pa.array(np.zeros(batch.num_rows, np.int64))) | {c: batch.column(c) for c in _names(STATE)}
    return pa.RecordBatch.from_arrays([none[c.split()[0]].cast(TYPES[c.split()[1]]) for c in MADE.split(", ")], _names(MADE))


def _doubles(raw) -> np.ndarray:
    return np.frombuffer(raw, dtype=np.float64)


def _cell(column: pa.Array, i: int) -> np.ndarray:
    """The doubles in a binary cell, without a copy."""
    return _doubles(column[i].as_buffer())


@contextmanager
def planned_once(spark: SparkSession, parts: int | None = None) -> Iterator[None]:
    """While a round's job runs: no plan changes between its stages, whose sizes are known beforehand, and shuffles deal to
    as many partitions as the blocks lie in."""
    wanted = {"spark.sql.adaptive.enabled": "false"} | ({"spark.sql.shuffle.partitions": str(parts)} if parts else {})
    before = {key: spark.conf.get(key) for key in wanted}
    for key, value in wanted.items():
        spark.conf.set(key, value)
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.set(key, value)


@dataclass
class Means:
    """Weighted means over the clients of a round."""

    f: float
    l: float
    g: np.ndarray
    s: np.ndarray
    items: int
    payload: int
    clients: int

    @staticmethod
    def none(d: int, w: int) -> Means:
        return Means(0.0, 0.0, np.zeros(d), np.zeros(w), 0, 0, 0)

    def add(self, f: float, l: float, g: np.ndarray, s: np.ndarray, items: int, payload: int, clients: int) -> None:
        self.f, self.l, self.items, self.payload, self.clients = self.f + f, self.l + l, self.items + items, self.payload + payload, self.clients + clients
        self.g += g
        self.s += s

    def batch(self) -> pa.RecordBatch:
        return _batch(MADE, (TOTAL, -1, self.f, self.l, self.items, self.payload, self.clients, self.g.tobytes(), self.s.tobytes()))


@dataclass
class RoundLog:
    rows: list[dict] = field(default_factory=list)

    def add(self, **row) -> None:
        self.rows.append(row)

    def frame(self, spark) -> DataFrame:
        schema = "run_id string, round int, f double, grad_norm double, l double, items long, bytes long, step_s int, seconds double"
        names = _names(schema)
        return spark.createDataFrame([tuple(r.get(c) for c in names) for r in self.rows], schema)


def merged(parts: DataFrame, schema: str, work, row_bytes: int) -> DataFrame:
    """Partial sums in as many levels as keep what one place receives below MOST_BYTES; `work` sums an iterator of batches."""
    count = int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    while count * row_bytes > MOST_BYTES and count > 4:
        count = max(4, int(count**0.5))
        parts = parts.repartition(count).mapInArrow(work, schema)
    return parts


class Engine:
    """Runs rounds for one problem over pinned clients."""

    def __init__(self, clients: Clients, problem: Problem, compressor: Compressor, alpha: float, seed: int = 7, commit_every: int = 10, lazy: bool = False, owner: str = "session"):
        self.clients, self.problem, self.compressor, self.alpha = clients, problem, compressor, alpha
        self.seed, self.commit_every, self.owner = seed, commit_every, owner
        self.lazy = lazy and isinstance(compressor, WindowK) and hasattr(problem, "entries")
        self.spark = clients.blocks.sparkSession
        self.shifts: DataFrame | None = None
        self._kept: list[DataFrame] = []
        self._rounds = 0

    # -- oracles -----------------------------------------------------------------------------------------
    def _multiplies(self, step: int) -> bool:
        return getattr(self.problem, "multiplies", False) and not (self.lazy and step >= 0)

    def _block_sums(self, x: np.ndarray, step: int):
        """Function of a client and a block: value, gradient and Hessian sums (with lazy, of the entries to be sent)."""
        problem, compressor, seed, w = self.problem, self.compressor, self.seed, packed.length(self.clients.d)
        if not self.lazy or step < 0:
            return lambda c, z: problem.sums(z, x)

        def entries(c, z):
            m = z @ x
            e = np.exp(-np.abs(m))
            s = np.where(m >= 0, e, 1.0) / (1.0 + e)
            return float((np.maximum(-m, 0) + np.log1p(e)).sum()), -(z.T @ s), problem.entries(z, x, compressor.positions(w, (seed, step, c)))

        return entries

    def _client_sums(self, x: np.ndarray, step: int, blocks: DataFrame) -> DataFrame:
        """Sums of the blocks a task holds of a client: what travels when clients are spread over tasks."""
        sums, matrix = self._block_sums(x, step), self.clients.reader(self._multiplies(step))

        def evaluate(batches):
            held: dict[int, list] = {}
            for batch in batches:
                for i, (c, n) in enumerate(zip(batch.column("client_id").to_pylist(), batch.column("n_rows").to_pylist(), strict=True)):
                    f, g, h = sums(c, matrix(batch.column("z"), i, n))
                    own = held.get(c)
                    held[c] = [n, f, g, h] if own is None else [own[0] + n, own[1] + f, own[2] + g, own[3] + h]
            for c, (n, f, g, h) in held.items():
                yield _batch(SUMS, (c, n, f, g.tobytes(), h.tobytes()))

        return blocks.mapInArrow(evaluate, SUMS)

    def start(self, x: np.ndarray, init: str) -> tuple[np.ndarray, float]:
        """First shifts, zero or the Hessians at x; their mean."""
        w = packed.length(self.clients.d)
        if init == "zero":

            def zeros(batches):
                for batch in batches:
                    yield _batch(STATE, *[(c, 0.0, None, np.zeros(w).tobytes()) for c in batch.column("client_id").to_pylist()])

            # Zero shifts are made where they are used: only the ids leave the driver.
            self._keep(self.spark.createDataFrame([(c,) for c in self.clients.ids], "client_id long").mapInArrow(zeros, STATE))
            return np.zeros(w), 0.0
        problem = self.problem
        shared = self.owner == "session"  # such tables stay as long as the process
        for known, point, shifts, mean in self.clients.starts if shared else ():
            if known is problem and np.array_equal(point, x):
                self.shifts = shifts
                return mean.copy(), 0.0

        def first(key, table):
            n, h = sum(table.column("n_rows").to_pylist()), sum(_doubles(r) for r in table.column("sum_h").to_pylist())
            _, _, h = problem.finish(n, (0.0, np.zeros_like(x), np.array(h)), x)
            return pa.table({"client_id": [key[0].as_py()], "l": [0.0], "g": pa.array([None], pa.binary()), "h": [h.tobytes()]})

        self._keep(self._client_sums(x, -1, self.clients.blocks).groupBy("client_id").applyInArrow(first, STATE))
        mean = global_oracles(self.clients, problem, x)[2]
        if shared:
            self.clients.starts.append((problem, x.copy(), self.shifts, mean.copy()))
        return mean, 0.0

    # -- a round -----------------------------------------------------------------------------------------
    def round(self, x: np.ndarray, step: int, only: list[int] | None = None, track: bool = False) -> Means:
        """Evaluate at x, compress the differences, move the shifts; the means over the clients taking part.

        track keeps each client's corrected gradient (H_i + l_i I) x - g_i and returns changes of it and of l_i
        instead of the values, as partial participation needs.
        """
        with planned_once(self.spark, self.clients.parts):
            return self._round(x, step, only, track)

    def _round(self, x: np.ndarray, step: int, only: list[int] | None, track: bool) -> Means:
        together = self.clients.together
        blocks, before = self.clients.blocks, self.shifts
        if only is not None:
            blocks = blocks.where(F.col("client_id").isin([int(c) for c in only]))
        pieces = blocks if together else self._client_sums(x, step, blocks)
        # Shifts of clients that sit a round out meet no block and pass through it.
        joined = pieces.join(before.hint("merge"), "client_id", "inner" if only is None else "right")
        made = joined.mapInArrow(self._sweep(x, step, track), MADE).persist(StorageLevel.MEMORY_AND_DISK)
        means = self._collect(made.where(F.col("kind") == TOTAL))
        state = made.where(F.col("kind") == SHIFT).select(*_names(STATE))
        self._rounds += 1
        self._kept.append(made)
        self.shifts = state
        if self.commit_every and self._rounds % self.commit_every == 0:
            self.shifts = written(state, "shifts", self.owner)
            while self._kept:
                self._kept.pop().unpersist()
        elif len(self._kept) > 2:
            self._kept.pop(0).unpersist()
        return means

    def _sweep(self, x: np.ndarray, step: int, track: bool):
        """Function of the joined rows of a task, those of a client side by side."""
        problem, compressor, alpha, seed, d = self.problem, self.compressor, self.alpha, self.seed, self.clients.d
        w, lazy, together = packed.length(d), self.lazy and step >= 0, self.clients.together
        sums, facts, matrix = self._block_sums(x, step), self.clients.facts(), self.clients.reader(self._multiplies(step))

        def finish(c, held, old, total):
            n, f, g, h = held
            rows, q = facts.value[c]
            if n != rows:
                raise RuntimeError(f"client {c}: {n} of {rows} rows met in a task")
            shift = old[2].copy()
            if lazy:
                where = compressor.positions(w, (seed, step, c))
                value = h / n + np.where(np.isin(where, packed.diagonal(d)), problem.lam, 0.0)
                idx, payload = where, 8 * len(where)
                val = (value - shift[where]) * (w / len(where) if compressor.scaled else 1.0)
                f, g, l = f / n + 0.5 * problem.lam * float(x @ x), g / n + problem.lam * x, 0.0
            else:
                f, g, h = problem.finish(n, (f, g, h), x)
                diff = h - shift
                l = packed.frobenius(diff, d)
                message = compressor(diff, d, (seed, step, c))
                idx, val, payload = message.idx, message.val, message.payload
            shift[idx] += alpha * val
            sent = np.zeros(w)
            sent[idx] = val
            out_l, out_g, keep_l, keep_g = l, g, l, None
            if track:
                keep_l = packed.frobenius(h - shift, d)
                corrected = packed.unpack(shift, d) @ x + keep_l * x - g
                out_l, out_g, keep_g = keep_l - old[0], corrected - (0.0 if old[1] is None else old[1]), corrected.tobytes()
            total.add(q * f, q * out_l, q * out_g, q * sent, len(val), payload, 1)
            return _batch(MADE, (SHIFT, c, f, keep_l, 0, 0, 0, keep_g, shift.tobytes()))

        def sweep(batches):
            total, client, held, old = Means.none(d, w), None, None, None
            for batch in batches:
                if batch.column("n_rows").null_count:
                    met = batch.column("n_rows").is_valid()
                    yield _resting(batch.filter(batch.column("n_rows").is_null()))
                    batch = batch.filter(met)
                column = batch.column
                for i, (c, n) in enumerate(zip(column("client_id").to_pylist(), column("n_rows").to_pylist(), strict=True)):
                    if c != client:
                        if client is not None:
                            yield finish(client, held, old, total)
                        client, held = c, None
                        old = column("l")[i].as_py(), _cell(column("g"), i).copy() if column("g")[i].is_valid else None, _cell(column("h"), i).copy()
                    f, g, h = sums(c, matrix(column("z"), i, n)) if together else (column("f")[i].as_py(), _cell(column("sum_g"), i), _cell(column("sum_h"), i))
                    held = [n, f, g, h] if held is None else [held[0] + n, held[1] + f, held[2] + g, held[3] + h]
            if client is not None:
                yield finish(client, held, old, total)
            if total.clients:
                yield total.batch()

        return sweep

    def _keep(self, df: DataFrame) -> DataFrame:
        self.shifts = written(df, "shifts", self.owner)
        return self.shifts

    def _collect(self, totals: DataFrame) -> Means:
        """The sum of the tasks' means: on the driver, or through levels of tasks first where they are large."""
        d, w = self.clients.d, packed.length(self.clients.d)

        def add(total, f, l, g, h, items, payload, clients):
            total.add(f, l, _doubles(g), _doubles(h), items, payload, clients)

        def merge(batches):
            total = Means.none(d, w)
            for batch in batches:
                for r in batch.to_pylist():
                    add(total, r["f"], r["l"], r["g"], r["h"], r["items"], r["payload"], r["clients"])
            if total.clients:
                yield total.batch()

        out = Means.none(d, w)
        for r in merged(totals, MADE, merge, 8 * (d + w)).collect():  # at most MOST_BYTES
            add(out, r.f, r.l, r.g, r.h, r["items"], r.payload, r.clients)
        return out

    # -- passes without state ----------------------------------------------------------------------------
    def oracles(self, x: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        return global_oracles(self.clients, self.problem, x)

    def values(self, points: np.ndarray) -> np.ndarray:
        return global_values(self.clients, self.problem, points)

    def release(self) -> None:
        while self._kept:
            self._kept.pop().unpersist()


def _summed(clients: Clients, function, size: int, multiplied: bool = True) -> np.ndarray:
    """Sum over all blocks of weight / rows * function(block), a vector of `size` doubles, partially per task; `multiplied` says
    that the function only multiplies the block."""
    facts, matrix = clients.facts(), clients.reader(multiplied)

    def work(batches):
        total, any_row = np.zeros(size), False
        for batch in batches:
            for i, (c, n) in enumerate(zip(batch.column("client_id").to_pylist(), batch.column("n_rows").to_pylist(), strict=True)):
                rows, weight = facts.value[c]
                total += weight / rows * function(matrix(batch.column("z"), i, n))
                any_row = True
        if any_row:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], ["v"])

    def merge(batches):
        total = None
        for batch in batches:
            for i in range(batch.num_rows):
                total = _cell(batch.column("v"), i) if total is None else total + _cell(batch.column("v"), i)
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], ["v"])

    with planned_once(clients.blocks.sparkSession, clients.parts):
        parts = merged(clients.blocks.mapInArrow(work, "v binary"), "v binary", merge, 8 * size)
        return np.sum([_doubles(r.v) for r in parts.collect()], axis=0)


def global_oracles(clients: Clients, problem: Problem, x: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Value, gradient and packed Hessian of the whole objective in one job."""
    d, w = len(x), packed.length(len(x))

    def function(z):
        f, g, h = problem.sums(z, x)
        return np.concatenate([[f], g, h])

    v = _summed(clients, function, 1 + d + w, getattr(problem, "multiplies", False))
    return problem.finish(1.0, (float(v[0]), v[1 : 1 + d], v[1 + d :].copy()), x)


def global_gradient(clients: Clients, problem: Problem, x: np.ndarray) -> tuple[float, np.ndarray]:
    d = len(x)

    def function(z):
        m = z @ x
        e = np.exp(-np.abs(m))
        return np.concatenate([[float((np.maximum(-m, 0) + np.log1p(e)).sum())], -(z.T @ (np.where(m >= 0, e, 1.0) / (1.0 + e)))])

    v = _summed(clients, function, 1 + d)
    lam = getattr(problem, "lam", 0.0)
    return float(v[0]) + 0.5 * lam * float(x @ x), v[1:] + lam * x


def global_values(clients: Clients, problem: Problem, points: np.ndarray) -> np.ndarray:
    """Values at several points in one job; along a line the blocks are read once for all steps."""
    return problem.finish_values(1.0, _summed(clients, lambda z: problem.values(z, points), len(points), getattr(problem, "multiplies", False)), points)


def hessian_product(clients: Clients, problem: Problem, x: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Hessian at x times v without forming the Hessian (logistic loss)."""

    def function(z):
        e = np.exp(-np.abs(z @ x))
        return z.T @ ((e / (1.0 + e) ** 2) * (z @ v))

    return _summed(clients, function, len(x)) + getattr(problem, "lam", 0.0) * v


def now() -> float:
    return time.monotonic()
