"""Dealing samples to clients and packing each client's rows into matrix blocks."""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import Broadcast, StorageLevel, TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.prng import SPAN, draw_column
from ..plans.cuts import written
from .features import scattered

BLOCK_ROWS = 4096
#: Equal ranges of the draw in which split_equal ranks rows.
SLICES = 4096
#: Tasks a core over pinned blocks at most: an empty one costs a pass as much as several blocks.
TASKS_A_CORE = 4
BLOCK_SCHEMA = "client_id long, block_id long, n_rows int, z binary"


def split_equal(samples: DataFrame, clients: int, seed: int = 7) -> DataFrame:
    """Shuffled equal split: floor(N / clients) rows each, the remainder dropped.

    A row's place is its rank by a portable draw. Ranks are counted within SLICES equal ranges of the draw, and
    each slice begins where the rows of those before it end, so no task sorts more than a slice.
    """
    drawn = samples.withColumn("_draw", draw_column(seed, F.col("sample_key")))
    drawn = drawn.withColumn("_slice", F.floor(F.col("_draw") / (SPAN // SLICES)).cast("int"))
    begins, total = [], 0
    for r in drawn.groupBy("_slice").count().orderBy("_slice").collect():  # SLICES rows at most
        begins.append((r["_slice"], total))
        total += r["count"]
    per = total // clients
    starts = samples.sparkSession.createDataFrame(begins, "_slice int, _begin long")
    rank = F.row_number().over(Window.partitionBy("_slice").orderBy("_draw", "sample_key")) - 1
    ranked = drawn.withColumn("_rank", rank).join(F.broadcast(starts), "_slice").withColumn("_n", F.col("_begin") + F.col("_rank"))
    dealt = ranked.where(F.col("_n") < per * clients).withColumn("client_id", F.floor(F.col("_n") / max(1, per)).cast("long"))
    return dealt.drop("_n", "_begin", "_rank", "_draw", "_slice")


def split_hashed(samples: DataFrame, clients: int, seed: int = 7) -> DataFrame:
    """Split by a hash of the key: no shuffle, no global order; clients differ slightly in size."""
    return samples.withColumn("client_id", F.pmod(F.xxhash64("sample_key", F.lit(seed)), F.lit(clients)).cast("long"))


def split_natural(samples: DataFrame, by: Column) -> DataFrame:
    """Clients as the data has them."""
    return samples.withColumn("client_id", by.cast("long"))


class Clients:
    """Pinned blocks of all clients: the table, the dimension, and what each client weighs.

    `weights` maps client to (rows, weight): 'equal' makes the objective the plain mean of the clients'
    functions, 'pooled' weighs them by rows, which is the mean over all rows. `together` says that the table is
    clustered and sorted by client (in `parts` partitions), `hot` that blocks hold the positions of ones in rows of that length. The driver holds
    two numbers a client, never rows or matrices of clients.
    """

    def __init__(self, blocks: DataFrame, d: int, rows: dict[int, int], weights: str = "equal", together: bool = False, hot: int | None = None, parts: int | None = None):
        self.blocks, self.d, self.rows, self.together, self.hot, self.parts = blocks, d, rows, together, hot, parts
        self._facts: Broadcast | None = None
        #: First shifts by problem and point: every run over these clients that begins there shares them.
        self.starts: list[tuple] = []
        #: Distinct rows and their counts by client; empty if they are too many, None before anyone asked.
        self.folded: dict | None = None
        self.ids = sorted(rows)
        total = sum(rows.values())
        self.weight = {c: 1.0 / len(rows) if weights == "equal" else n / total for c, n in rows.items()}

    @property
    def n(self) -> int:
        return len(self.ids)

    def facts(self) -> Broadcast:
        """Rows and weight of every client, sent to the executors once."""
        if self._facts is None:
            self._facts = self.blocks.sparkSession.sparkContext.broadcast({c: (self.rows[c], self.weight[c]) for c in self.ids})
        return self._facts

    def reader(self, multiplied: bool = False):
        """Function of a column of blocks, a place in it and the block's rows: the matrix there, or what multiplies like it."""
        return partial(block_factor if multiplied else block_matrix, d=self.hot)

    def release(self) -> None:
        self.blocks.unpersist()
        self.starts.clear()
        if self._facts is not None:
            self._facts.unpersist()
            self._facts = None


def positions_type(d: int) -> type:
    return np.uint16 if d <= 1 << 16 else np.uint32


def _once(rows: np.ndarray, at: np.ndarray, n: int, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and positions without repeated positions of a row; untouched where nothing repeats."""
    places = rows * d + at
    if n * d <= 1 << 24:
        seen = np.zeros(n * d, dtype=bool)
        seen[places] = True
        if np.count_nonzero(seen) == len(places):
            return rows, at
    kept = np.unique(places)
    return (rows, at) if len(kept) == len(places) else (kept // d, kept % d)


def hot_rows(hot: pa.Array, labels: np.ndarray, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Label, number of ones and positions of every row of a list column; a missing position or list is none."""
    lengths = np.nan_to_num(hot.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
    at = hot.flatten().to_numpy(zero_copy_only=False)
    rows = np.repeat(np.arange(len(hot)), lengths)
    if at.dtype.kind == "f":
        known = ~np.isnan(at)
        rows, at = rows[known], at[known]
    if len(at) and not 0 <= at.min() <= at.max() < d:
        raise IndexError(f"a position outside 0..{d - 1}")
    rows, at = _once(rows, at.astype(np.int64), len(hot), d)
    return labels, np.bincount(rows, minlength=len(hot)).astype(np.uint32), at.astype(positions_type(d))


def block_ones(column: pa.Array, i: int, n: int, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Labels, counts of ones and their positions in the n rows of a binary block."""
    raw = column[i].as_buffer()
    return np.frombuffer(raw, np.float64, n), np.frombuffer(raw, np.uint32, n, 8 * n), np.frombuffer(raw, positions_type(d), offset=12 * n)


class Ones:
    """A binary block that is only multiplied: margins and transposed products from its positions, no matrix."""

    def __init__(self, labels: np.ndarray, counts: np.ndarray, at: np.ndarray, d: int):
        self.labels, self.counts, self.at, self.d = labels, np.asarray(counts, np.int64), at, d
        self.transposed = False

    def __len__(self) -> int:
        return len(self.labels)

    @property
    def T(self) -> Ones:
        other = Ones(self.labels, self.counts, self.at, self.d)
        other.transposed = not self.transposed
        return other

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        if x.ndim > 1:
            if x.shape[1] <= 4 and not self.transposed:
                return np.stack([self @ v for v in x.T], axis=1)
            return (self.matrix().T if self.transposed else self.matrix()) @ x
        if self.transposed:
            return np.bincount(self.at, weights=np.repeat(self.labels * x, self.counts), minlength=self.d)
        k = len(self.at) // len(self)
        if k and (self.counts == k).all():
            return self.labels * x[self.at].reshape(-1, k).sum(axis=1)
        out, some = np.zeros(len(self)), self.counts > 0
        if some.any():
            out[some] = np.add.reduceat(x[self.at], (np.cumsum(self.counts) - self.counts)[some])
        return self.labels * out

    def matrix(self, scale: np.ndarray | float = 1.0) -> np.ndarray:
        """The rows, each times its number in `scale`."""
        z = np.zeros((len(self), self.d))
        z[np.repeat(np.arange(len(self)), self.counts), self.at] = np.repeat(self.labels * scale, self.counts)
        return z


def block_matrix(column: pa.Array, i: int, n: int, d: int | None = None) -> np.ndarray:
    """The n rows of a block: as they lie in the cell, or (d given) scattered from labels, counts and positions."""
    if d is None:
        return np.frombuffer(column[i].as_buffer(), dtype=np.float64).reshape(n, -1)
    return Ones(*block_ones(column, i, n, d), d).matrix()


def block_factor(column: pa.Array, i: int, n: int, d: int | None = None) -> np.ndarray | Ones:
    """The same rows for those that only multiply them."""
    return block_matrix(column, i, n) if d is None else Ones(*block_ones(column, i, n, d), d)


def pack_blocks(samples: DataFrame, d: int, rows_per_block: int = BLOCK_ROWS, salts: int = 1, label: str | None = "label", compact: bool = False) -> DataFrame:
    """Blocks of at most rows_per_block rows: row-major float64, label multiplied in; with `compact`, rows of ones (`hot`)
    stay positions (see `block_matrix`).

    Rows are dealt by (client, salt) and streamed in key order, so memory is one block whatever a client's
    size; salts > 1 spreads a client that holds a large share of all rows over several tasks.
    """
    salt = F.pmod(F.xxhash64("sample_key"), F.lit(salts))
    given = "hot" if "hot" in samples.columns else "features"
    packs = compact and given == "hot"
    columns = ["client_id", given] + ([label] if label else [])
    dealt = samples.select("sample_key", *columns).withColumn("_salt", salt).repartition("client_id", "_salt").sortWithinPartitions("client_id", "_salt", "sample_key").select(*columns)

    def pack(batches):
        base, made = TaskContext.get().partitionId() << 32, 0
        client, held, n = None, [], 0

        def emit():
            nonlocal held, n, made
            z = b"".join(np.concatenate(parts).tobytes() for parts in zip(*held, strict=True))
            made += 1
            out = pa.RecordBatch.from_arrays([pa.array([client], pa.int64()), pa.array([base + made], pa.int64()), pa.array([n], pa.int32()), pa.array([z], pa.binary())], ["client_id", "block_id", "n_rows", "z"])
            held, n = [], 0
            return out

        for batch in batches:
            ids = batch.column("client_id").to_numpy(zero_copy_only=False)
            labels = batch.column(label).to_numpy(zero_copy_only=False) if label else np.ones(len(ids))
            if packs:
                rows = hot_rows(batch.column(given), labels, d)
                ends = np.concatenate([[0], np.cumsum(rows[1], dtype=np.int64)])
            else:
                z = scattered(batch.column(given), d) if given == "hot" else batch.column(given).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
                z = z * labels[:, None] if label else z
            edges = np.concatenate([[0], np.nonzero(np.diff(ids))[0] + 1, [len(ids)]])
            for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                if a == b:
                    continue
                if n and ids[a] != client:
                    yield emit()
                client = int(ids[a])
                while a < b:
                    take = min(b - a, rows_per_block - n)
                    held.append((rows[0][a : a + take], rows[1][a : a + take], rows[2][ends[a] : ends[a + take]]) if packs else (z[a : a + take],))
                    n, a = n + take, a + take
                    if n == rows_per_block:
                        yield emit()
        if n:
            yield emit()

    return dealt.mapInArrow(pack, BLOCK_SCHEMA)


def pin(samples: DataFrame, d: int, weights: str = "equal", rows_per_block: int = BLOCK_ROWS, salts: int = 1, label: str | None = "label") -> Clients:
    """Pack and keep the blocks near the executors (memory, then disk; read again from shared storage if lost).

    The packed blocks are written once, so no plan of a round carries the plan of the samples. Without salts they are clustered
    by client once more, in a way that later plans know of: rounds then join shifts to them without moving a block.
    """
    blocks, together, parts = written(pack_blocks(samples, d, rows_per_block, salts, label, compact=True), "blocks"), salts == 1, None
    if together:
        spark = samples.sparkSession
        parts = min(int(spark.conf.get("spark.sql.shuffle.partitions")), max(4, TASKS_A_CORE * spark.sparkContext.defaultParallelism))
        blocks = blocks.repartition(parts, "client_id").sortWithinPartitions("client_id", "block_id")
    blocks = blocks.persist(StorageLevel.MEMORY_AND_DISK)
    rows = {r.client_id: r.n for r in blocks.groupBy("client_id").agg(F.sum("n_rows").alias("n")).collect()}  # one row a client
    return Clients(blocks, d - (0 if label else 1), rows, weights, together, d if "hot" in samples.columns else None, parts)


def write_split(samples: DataFrame, path: str) -> None:
    """One folder per client."""
    samples.write.partitionBy("client_id").parquet(path)
