"""Exact top-k by inner product, pruned by segment statistics from coarse to fine.

A vector cut into segments has a mean and a deviation norm per segment. The squared distance of two
vectors is at least the sum over segments of n (mean difference)^2 + (difference of deviation norms)^2; with the
exact norms that lower bound on the distance is an upper bound on the inner product. Candidates pass 1,
then 4, then 16 segments; those no query still wants are dropped, and exact integer products are taken
of the survivors only. A query wants a candidate whose bound reaches its k-th best score so far, and
ties survive, so the answer is exact.

Queries are a stated set; they go out in blocks of bounded size, one scan of all candidates a block.
Every task sends its k best per query, and a ranked aggregate keeps the k best of those.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cuts import written

LEVELS = (1, 4, 16)
#: Queries broadcast at once: 4096 vectors of 64 longs are 2 MB.
QUERY_BLOCK = 4096
#: Candidates scored on the driver to start each query's threshold: rows, not a share of the table.
SEED_ROWS = 512
BATCH = 1024
FREE, WORST = np.iinfo(np.int64).max, np.iinfo(np.int64).min
#: Doubles from here on are whole numbers; products of components below HUGE have exact sums over 2^9 components.
WHOLE, HUGE = float(2**53), float(2**22)


def integer_vector(vector: Column, scale: int = 1024) -> Column:
    """floor(scale * x) of each component as a double; null unless every component is finite.

    From 2^53 on a double is whole already, and its floor would not fit the long that `floor` gives.
    """
    ok = vector.isNotNull() & ~F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    scaled = F.transform(vector, lambda x: x.cast("double") * scale)
    ok = ok & ~F.exists(scaled, lambda y: F.abs(y) == float("inf"))
    return F.when(ok, F.transform(scaled, lambda y: F.when(F.abs(y) < WHOLE, F.floor(y).cast("double")).otherwise(y)))


def segment_features(x: np.ndarray, segments: int) -> np.ndarray:
    """Per segment: sqrt(n) * mean and the norm of the deviations; products of features bound inner products."""
    parts = []
    for piece in np.array_split(x, min(segments, max(1, x.shape[1])), axis=1):
        n = max(1, piece.shape[1])
        mean = piece.sum(axis=1) / n
        parts += [mean * np.sqrt(n), np.sqrt(np.maximum((piece * piece).sum(axis=1) - n * mean * mean, 0.0))]
    return np.stack(parts, axis=1)


def exact_scores(q: np.ndarray, c: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """Integer inner products of the pairs (rows, cols), in doubles where those hold every sum exactly.

    Products beyond the 64 bits of a score are its largest or smallest value; such scores tie.
    """
    top = float(np.abs(q).max(initial=0.0)) * float(np.abs(c).max(initial=0.0)) * max(1, q.shape[1])
    if top < 2**53:
        out = np.empty(len(rows), dtype=np.int64)
        for a in range(0, len(rows), 1 << 16):
            out[a : a + (1 << 16)] = np.einsum("ij,ij->i", q[rows[a : a + (1 << 16)]], c[cols[a : a + (1 << 16)]])
        return out
    whole_q, whole_c = ({i: [int(a) for a in m[i]] for i in np.unique(at).tolist()} for m, at in ((q, rows), (c, cols)))
    exact = (sum(a * b for a, b in zip(whole_q[i], whole_c[j], strict=True)) for i, j in zip(rows.tolist(), cols.tolist(), strict=True))
    return np.array([min(FREE, max(-FREE, s)) for s in exact], dtype=np.int64)


class Best:
    """The k best (score, smaller id) per query of one task."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int, floors: np.ndarray):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.features = [segment_features(vectors, s) for s in LEVELS]
        self.floors = floors.copy()
        self.found_id = np.full((len(ids), k), FREE)
        self.found = np.full((len(ids), k), WORST)

    def add(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        # Rounding of the bounds stays far below 1e-6 of the norms involved; scores are integers.
        slack = 1.0 + 1e-9 * (np.abs(self.vectors).sum(axis=1).max(initial=0.0) * np.abs(vectors).sum(axis=1).max(initial=0.0))
        cols = np.arange(len(ids))
        want = None
        for level, mine in enumerate(self.features):
            bound = mine @ segment_features(vectors[cols], LEVELS[level]).T
            want = ~(bound + slack < self.floors[:, None])  # a bound that overflows drops nothing
            alive = want.any(axis=0)
            cols, want = cols[alive], want[:, alive]
            if not len(cols):
                return
        want &= self.ids[:, None] != ids[cols][None, :]
        rows, at = np.nonzero(want)
        if not len(rows):
            return
        score = exact_scores(self.vectors, vectors, rows, cols[at])
        own = ids[cols[at]]
        touched = np.unique(rows)
        all_rows = np.concatenate([rows, np.repeat(touched, self.k)])
        all_score = np.concatenate([score, self.found[touched].ravel()])
        all_id = np.concatenate([own, self.found_id[touched].ravel()])
        order = np.lexsort((all_id, ~all_score, all_rows))
        all_rows, all_score, all_id = all_rows[order], all_score[order], all_id[order]
        # A repeated row of one candidate is one candidate; free places (the largest id) are not candidates.
        again = (all_rows[1:] == all_rows[:-1]) & (all_id[1:] == all_id[:-1]) & (all_score[1:] == all_score[:-1]) & (all_id[1:] != FREE)
        single = np.concatenate([[True], ~again])
        all_rows, all_score, all_id = all_rows[single], all_score[single], all_id[single]
        start = np.searchsorted(all_rows, touched)
        take = start[:, None] + np.arange(self.k)[None, :]
        self.found[touched], self.found_id[touched] = all_score[take], all_id[take]
        kth = self.found[touched, self.k - 1]
        self.floors[touched] = np.maximum(self.floors[touched], np.where(kth == WORST, -np.inf, kth.astype(np.float64)))

    def rows(self) -> pd.DataFrame:
        q, j = np.nonzero(self.found_id != FREE)
        return pd.DataFrame({"query_id": self.ids[q], "vec_id": self.found_id[q, j], "score": self.found[q, j]})


def _stacked(values) -> dict[tuple[int, bool], tuple[np.ndarray, np.ndarray]]:
    """ids and matrices of (id, vector) pairs by length and by whether a component is huge.

    Vectors of other lengths have no inner product; huge ones loosen bounds and need longer integers, which the
    others are spared.
    """
    by = defaultdict(lambda: ([], []))
    for i, v in values:
        v = np.asarray(v, dtype=np.float64)
        own = by[len(v), bool(np.abs(v).max(initial=0.0) >= HUGE)]
        own[0].append(i)
        own[1].append(v)
    return {k: (np.array(i, dtype=np.int64), np.stack(v).reshape(len(i), k[0])) for k, (i, v) in by.items()}


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, owner: str = "session", query_block: int = QUERY_BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: the k best candidates of every query, all if there are fewer.

    Both tables need vec_id (long) and vector (whole numbers as array<double>). Null ids and null vectors
    take no part, nor do candidates of another length than the query or with the query's own id; ties go to
    the smaller vec_id; repeated rows of a candidate are one candidate. Scores beyond 64 bits are the largest or smallest
    long and tie. Empty tables give no rows.

    Queries run block by block, each a scan of all candidates of its own whose broadcast is destroyed when its
    best are written.
    """
    spark = vectors.sparkSession
    clean = lambda df: df.where(F.col("vec_id").isNotNull() & F.col("vector").isNotNull()).select("vec_id", "vector")
    candidates = clean(vectors)
    asked = written(clean(queries).groupBy("vec_id").agg(F.min("vector").alias("vector")), "topk-queries", owner)
    # Query blocks by range of the id; the driver holds one block at a time.
    count = asked.count()
    schema = "query_id long, vec_id long, score long"
    if not count:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    blocks = -(-count // query_block)
    edges = [float("-inf"), *(asked.approxQuantile("vec_id", [i / blocks for i in range(1, blocks)], 1 / (8 * blocks)) if blocks > 1 else []), float("inf")]
    seeds = _stacked((r.vec_id, r.vector) for r in candidates.limit(SEED_ROWS).collect())
    partial = []
    for low, high in zip(edges, edges[1:], strict=False):
        if low >= high:
            continue
        part = asked if blocks == 1 else asked.where((F.col("vec_id") > low) & (F.col("vec_id") <= high))
        block = _stacked((r.vec_id, r.vector) for r in part.toLocalIterator())
        started = {}
        for (n, huge), (ids, mat) in block.items():
            first = Best(ids, mat, k, np.full(len(ids), -np.inf))
            if (n, False) in seeds:
                first.add(*seeds[n, False])
            started[n, huge] = (ids, mat, first.floors)
        sent = spark.sparkContext.broadcast(started)

        def scan(batches, sent=sent):
            best = {key: Best(ids, mat, k, floors) for key, (ids, mat, floors) in sent.value.items()}
            for pdf in batches:
                for (n, _), (ids, mat) in _stacked(zip(pdf["vec_id"], pdf["vector"], strict=True)).items():
                    for asked_for in (best[key] for key in ((n, False), (n, True)) if key in best):
                        for a in range(0, len(ids), BATCH):
                            asked_for.add(ids[a : a + BATCH], mat[a : a + BATCH])
            for x in best.values():
                yield x.rows()

        partial.append(written(candidates.mapInPandas(scan, schema), "topk-best", owner))
        sent.destroy()
    found = partial[0]
    for x in partial[1:]:
        found = found.unionByName(x)
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    ranked = found.distinct().withColumn("rank", F.row_number().over(order).cast("int")).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * CAST(x AS DOUBLE))) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 100 = 0
), r AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
