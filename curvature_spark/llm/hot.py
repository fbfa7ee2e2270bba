"""Joins whose keys may be hot: a key can hold a third of all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.cuts import written

#: Keys handled apart: the broadcast holds this many rows at most, and any other key fewer than 1 / HOTTEST of the uses.
HOTTEST = 1000
#: Uses below which a key is like any other.
FEW_USES = 100


def hot_join(rows: DataFrame, table: DataFrame, on: str | list[str], uses: str | None = None, owner: str = "session") -> DataFrame:
    """Inner join of `rows` with `table`, one row a key.

    The HOTTEST keys with the most uses are broadcast, so their rows stay where they are; all others are dealt by
    key. `uses` names the column of `table` that counts what a key meets, which is left out of the result; without it the keys
    of `rows` are counted. Both tables are read twice: give written ones.
    """
    on = [on] if isinstance(on, str) else on
    if uses:
        counts, table = table.select(*on, F.col(uses).alias("uses_")), table.drop(uses)
    else:
        counts = rows.groupBy(*on).agg(F.count(F.lit(1)).alias("uses_"))
    top = counts.where(F.col("uses_") > FEW_USES).orderBy(F.desc("uses_"), *on).limit(HOTTEST).select(*on)
    hot = written(top, "hot-keys", owner)
    if hot.isEmpty():
        return rows.join(table, on)
    here = rows.join(F.broadcast(table.join(F.broadcast(hot), on)), on)
    dealt = rows.join(F.broadcast(hot), on, "left_anti").join(table, on)
    return here.unionByName(dealt)


def beside(docs: DataFrame, **columns) -> DataFrame:
    """The rows of `docs` as one struct column `row`, so that no name of theirs can meet those of `columns`."""
    return docs.select(F.struct("*").alias("row"), *[c.alias(name) for name, c in columns.items()])
