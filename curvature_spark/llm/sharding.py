"""Sharding by a keyed permutation of global row numbers, in DataFrame expressions only.

Rows are numbered 0..N-1 in the order of (doc_id, text_crc32, size). A Feistel network over
Z_a x Z_b, with a = ceil(sqrt N) and b = ceil(N / a), permutes 0..ab-1; a value outside 0..N-1 walks on
along its cycle until it falls inside, which keeps the map a permutation of 0..N-1. Place p of a row
gives shard p mod n and slot p div n, so where any row number lies can be computed without a table.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cuts import written

ROUNDS = 6
PRIME = 2147483629
#: More steps than any walk takes for N up to 10^3 (fewer than sqrt N places lie outside); beyond,
#: a longer walk has a chance below N * N^(-WALK/2), and ends the query with an error, never with a wrong place.
WALK = 32


def round_keys(seed: int) -> list[tuple[int, int]]:
    """Multiplier and offset of each round, derived from the seed by a linear congruence."""
    state, keys = seed % PRIME, []
    for _ in range(ROUNDS):
        pair = []
        for _ in range(2):
            state = (state * 48271 + 11) % PRIME
            pair.append(1 + state % (PRIME - 1))
        keys.append((pair[0], pair[1]))
    return keys


def _floor_div(x: Column, n: int) -> Column:
    return ((x - x % n) / n).cast("long")


def _pass(acc: Column, a: int, b: int, seed: int) -> Column:
    """The network with its halves bound once per round, as nested one-element folds (no repeated subtrees)."""
    state = F.struct(_floor_div(acc, b).alias("l"), (acc % b).alias("r"))
    keys = F.array(*[F.struct(F.lit(k).cast("long").alias("m"), F.lit(o).cast("long").alias("o"), F.lit(n % 2 == 0).alias("even")) for n, (k, o) in enumerate(round_keys(seed))])

    def turn(s: Column, k: Column) -> Column:
        x = F.when(k["even"], s["r"]).otherwise(s["l"])
        y = (x * k["m"] + k["o"]) % PRIME
        f = ((y * y) % PRIME) * k["m"] % PRIME
        return F.struct(
            F.when(k["even"], (s["l"] + f) % a).otherwise(s["l"]).alias("l"),
            F.when(k["even"], s["r"]).otherwise((s["r"] + f) % b).alias("r"),
        )

    return F.aggregate(keys, state, turn, lambda s: s["l"] * b + s["r"])


def place(x: Column, total: int, seed: int) -> Column:
    """The place of row number x (long) among `total` rows: network passes until the value is below `total`."""
    a = max(1, math.isqrt(max(0, total - 1)) + 1)
    b = max(1, -(-total // a))
    first = _pass(x, a, b, seed)
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), first, lambda acc, _: F.when(acc < total, acc).otherwise(_pass(acc, a, b, seed)))
    return F.aggregate(F.array(walked), F.lit(0).cast("long"), lambda _, p: F.when(p < total, p).otherwise(F.raise_error(F.lit("a walk is not over: raise WALK")).cast("long")))


def global_rows(rows: DataFrame, order: list[str], owner: str = "session") -> tuple[DataFrame, int]:
    """`rows` with column row_no, 0 to N-1 in the given order, and N.

    Rows are dealt into ranges of the order, which splits any number of rows evenly, and written once
    with their range; a row's number is its rank in the range plus the sizes of the ranges before,
    a table of one row per range. Equal rows may swap numbers among themselves.
    """
    ranged = rows.repartitionByRange(*order).withColumn("range_no", F.spark_partition_id())
    ranged = written(ranged, "ranges", owner)
    counts = ranged.groupBy("range_no").agg(F.count(F.lit(1)).alias("n"))
    counts = written(counts.withColumn("before", F.sum("n").over(Window.orderBy("range_no")) - F.col("n")), "range-counts", owner)
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    within = Window.partitionBy("range_no").orderBy(*order)
    numbered = ranged.withColumn("_rank", F.row_number().over(within)).join(counts.drop("n"), "range_no")
    return numbered.withColumn("row_no", (F.col("before") + F.col("_rank") - 1).cast("long")).drop("_rank", "before", "range_no"), total


def shard(docs: DataFrame, shards: int = 8, seed: int = 23, owner: str = "session") -> DataFrame:
    """One row per row of `docs`: doc_id, size, text_crc32, row_no, law, shard, slot, grown_shard.

    docs needs doc_id and text; other columns are ignored. The law is `rows`: shard counts differ by one
    at most and slots run from 0 without gaps; grown_shard, which only the key law has, is null. Null text
    has size 1 and the checksum 0 of no bytes. Null ids sort first; repeated rows take one number each.
    An empty table gives no rows.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    numbered, total = global_rows(rows, ["doc_id", "text_crc32", "size"], owner)
    placed = numbered.withColumn("place", place(F.col("row_no"), total, seed))
    return placed.select(
        "doc_id", "size", "text_crc32", "row_no",
        F.lit("rows").alias("law"),
        (F.col("place") % shards).cast("int").alias("shard"),
        _floor_div(F.col("place"), shards).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def place_in_python(x: int, total: int, seed: int) -> int:
    """The same law for one row number, for callers that look up single rows."""
    a = max(1, math.isqrt(max(0, total - 1)) + 1)
    b = max(1, -(-total // a))
    while True:
        left, right = divmod(x, b)
        for n, (m, o) in enumerate(round_keys(seed)):
            y = ((left if n % 2 else right) * m + o) % PRIME
            f = y * y % PRIME * m % PRIME
            left, right = (left, (right + f) % b) if n % 2 else ((left + f) % a, right)
        x = left * b + right
        if x < total:
            return x


def oracle(shards: int = 8, seed: int = 23) -> str:
    """DuckDB SQL of the same law: its own checksum from bit operations, and the walk as a recursion."""
    chain, left, right = ["x // b AS l0", "x % b AS r0"], "l0", "r0"
    for n, (m, o) in enumerate(round_keys(seed)):
        other = left if n % 2 else right
        chain.append(f"({other} * {m} + {o}) % {PRIME} AS y{n + 1}")
        chain.append(f"((y{n + 1} * y{n + 1}) % {PRIME}) * {m} % {PRIME} AS f{n + 1}")
        if n % 2:
            chain.append(f"({right} + f{n + 1}) % b AS r{n + 1}")
            right = f"r{n + 1}"
        else:
            chain.append(f"({left} + f{n + 1}) % a AS l{n + 1}")
            left = f"l{n + 1}"
    network = ", ".join(chain) + f", {left} * b + {right} AS p"
    return f"""
WITH RECURSIVE bits AS (
  SELECT list(list_reduce(range(8), lambda c, i: CASE WHEN c % 2 = 1 THEN xor(3988292384, c // 2) ELSE c // 2 END, n) ORDER BY n) AS t FROM range(256) r(n)
), d AS (
  SELECT doc_id, CAST(strlen(coalesce(text, '')) + 1 AS BIGINT) AS size, hex(encode(coalesce(text, ''))) AS h FROM documents
), c AS (
  SELECT doc_id, size, CAST(xor(4294967295, list_reduce(range(1, len(h), 2), lambda c, i: xor(c >> 8, t[1 + (xor(c, CAST('0x' || h[i:i+1] AS BIGINT)) & 255)]), 4294967295)) AS BIGINT) AS text_crc32 FROM d, bits
), n AS (
  SELECT *, CAST(row_number() OVER (ORDER BY doc_id NULLS FIRST, text_crc32, size) - 1 AS BIGINT) AS row_no FROM c
), s AS (
  SELECT total, a, (total + a - 1) // a AS b FROM (SELECT count(*) AS total, CAST(floor(sqrt(greatest(count(*) - 1, 0))) AS BIGINT) + 1 AS a FROM documents)
), w(row_no, p, total) AS (
  SELECT row_no, p, total FROM (SELECT row_no, row_no AS x, total, a, b, {network} FROM n, s)
  UNION ALL
  SELECT row_no, p, total FROM (SELECT w.row_no, w.p AS x, s.total, a, b, {network.replace(" AS p", " AS q")} FROM w, s WHERE w.p >= s.total) t(row_no, x, total, a, b, {", ".join(c.rsplit(" AS ", 1)[1] for c in chain)}, p)
)
SELECT n.doc_id, n.size, n.text_crc32, n.row_no, 'rows' AS law, CAST(w.p % {shards} AS INTEGER) AS shard, CAST(w.p // {shards} AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard
FROM n JOIN w ON n.row_no = w.row_no AND w.p < w.total
"""


ORACLE = oracle()
