"""Exact dedup by deterministic block naming.

The normalised text of a document is cut into fixed-size blocks. Distinct blocks are sorted and get
integer names, equal names for equal contents and no others; then adjacent names of a document are
paired, distinct pairs sorted and named, until one name is left: the document's identity, free of
collisions because every name stands for one content.

Distinct contents are found with map-side combining, so a block shared by a third of all documents
leaves each map task once. Documents meet the names through a short key (length, two hashes); contents
whose short key is not theirs alone are joined by content instead, so no hash is trusted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cuts import written
from .hot import beside, hot_join
from .words import lower_ascii

BLOCK_CHARS = 32768


#: Equal ranges of a 64-bit hash in which names are counted.
SLICE_BITS = 12


def _names(distinct: DataFrame, hashed: Column, order: list[str]) -> DataFrame:
    """Integer names 0, 1, 2, ... for the rows of `distinct` (written) in the order of (hashed, *order).

    The order is that of the contents alone, so names do not depend on how a table is split. Ranks are counted
    within equal ranges of the hash, each beginning where those before it end: no task sorts more than a range, and no
    content goes to the driver to find ranges.
    """
    sliced = distinct.withColumn("hashed", hashed).withColumn("slice", F.shiftright("hashed", 64 - SLICE_BITS).cast("int"))
    counts = sliced.groupBy("slice").agg(F.count(F.lit(1)).alias("n"))
    begins = counts.select("slice", (F.sum("n").over(Window.orderBy("slice")) - F.col("n")).alias("begins"))  # 2^SLICE_BITS rows
    rank = F.row_number().over(Window.partitionBy("slice").orderBy("hashed", *order)) - 1
    return sliced.withColumn("rank", rank).join(F.broadcast(begins), "slice").withColumn("name", (F.col("begins") + F.col("rank")).cast("long")).drop("hashed", "slice", "rank", "begins")


def _short_key(block: Column) -> Column:
    return F.struct(F.length(block).alias("n"), F.xxhash64(block).alias("h"), F.crc32(block).alias("c"))


def identities(docs: DataFrame, block_chars: int = BLOCK_CHARS, owner: str = "session") -> DataFrame:
    """One row per row of `docs`, written: row_no (arbitrary, distinct), doc_id, text_sha256, identity."""
    text = lower_ascii(F.col("text"))
    base = docs.select("doc_id", text.alias("t"))
    blocks = base.select(
        "doc_id",
        F.sha2("t", 256).alias("text_sha256"),
        F.transform(
            F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("t") - 1) / block_chars).cast("int"))),
            lambda i: F.substring(F.col("t"), i * block_chars + 1, F.lit(block_chars)),
        ).alias("blocks"),
    )
    # One pass over the texts: the short keys of every document are written, contents are not.
    keyed = written(
        blocks.select("doc_id", "text_sha256", F.transform("blocks", _short_key).alias("keys")).withColumn("row_no", F.monotonically_increasing_id()),
        "naming-keys",
        owner,
    )
    content = base.select(
        F.explode(
            F.transform(
                F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("t") - 1) / block_chars).cast("int"))),
                lambda i: F.substring(F.col("t"), i * block_chars + 1, F.lit(block_chars)),
            )
        ).alias("block")
    )
    distinct = content.groupBy("block").agg(F.count(F.lit(1)).alias("uses"))
    short = written(distinct.select(_short_key(F.col("block")).alias("key"), "uses"), "naming-blocks", owner)
    shared = short.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    if not shared.isEmpty():
        return _by_content(docs, distinct, block_chars, owner)
    named = written(_names(short, F.xxhash64("key"), ["key"]), "naming-names", owner)
    return _folded(keyed.select("row_no", "doc_id", "text_sha256", F.posexplode("keys").alias("pos", "key")), named, owner)


def _by_content(docs: DataFrame, distinct: DataFrame, block_chars: int, owner: str) -> DataFrame:
    """The same identities when short keys collide: whole contents are the join key."""
    named = written(_names(written(distinct, "naming-distinct", owner), F.xxhash64("block"), ["block"]), "naming-contents", owner)
    text = lower_ascii(F.col("text"))
    base = docs.select("doc_id", text.alias("t")).withColumn("row_no", F.monotonically_increasing_id())
    pieces = base.select(
        "row_no", "doc_id", F.sha2("t", 256).alias("text_sha256"),
        F.posexplode(
            F.transform(
                F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("t") - 1) / block_chars).cast("int"))),
                lambda i: F.substring(F.col("t"), i * block_chars + 1, F.lit(block_chars)),
            )
        ).alias("pos", "key"),
    )
    return _folded(written(pieces, "naming-pieces", owner), named.withColumnRenamed("block", "key"), owner)


def _folded(pieces: DataFrame, names: DataFrame, owner: str) -> DataFrame:
    """Name adjacent pairs until each document has one name left. names: key, name, uses."""
    level = written(hot_join(pieces, names, "key", "uses", owner).select("row_no", "doc_id", "text_sha256", "pos", "name"), "naming-level", owner)
    ended = level.where("pos = 0")
    longest = level.agg(F.max("pos")).first()[0] or 0
    if longest == 0:
        return ended.select("row_no", "doc_id", "text_sha256", F.struct(F.lit(0).alias("level"), F.col("name").alias("name")).alias("identity"))
    long_rows = level.where("pos = 1").select("row_no")
    single = ended.join(long_rows, "row_no", "left_anti")
    done = [single.select("row_no", F.lit(0).alias("level"), "name")]
    rest = level.join(long_rows, "row_no", "left_semi").select("row_no", "pos", "name")
    step = 0
    while longest > 0:
        step += 1
        pairs = rest.groupBy("row_no", F.floor(F.col("pos") / 2).cast("int").alias("pos")).agg(
            F.min(F.when(F.col("pos") % 2 == 0, F.col("name"))).alias("a"),
            # An odd end is paired with -1, which names nothing.
            F.coalesce(F.min(F.when(F.col("pos") % 2 == 1, F.col("name"))), F.lit(-1)).alias("b"),
        )
        pairs = written(pairs, "naming-pairs", owner)
        distinct = written(pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("uses")), "naming-distinct-pairs", owner)
        named = written(_names(distinct, F.xxhash64("a", "b"), ["a", "b"]), "naming-pair-names", owner)
        rest = written(hot_join(pairs, named, ["a", "b"], "uses", owner).select("row_no", "pos", "name"), "naming-level", owner)
        longest = rest.agg(F.max("pos")).first()[0] or 0
        if longest == 0:
            done.append(rest.select("row_no", F.lit(step).alias("level"), "name"))
        else:
            more = rest.where("pos = 1").select("row_no")
            done.append(rest.where("pos = 0").join(more, "row_no", "left_anti").select("row_no", F.lit(step).alias("level"), "name"))
            rest = rest.join(more, "row_no", "left_semi")
    # A document leaves at the level that its number of blocks sets, so equal texts leave at one level.
    ids = done[0]
    for x in done[1:]:
        ids = ids.unionByName(x)
    about = ended.select("row_no", "doc_id", "text_sha256")
    return about.join(ids.select("row_no", F.struct("level", "name").alias("identity")), "row_no")


def exact_groups(docs: DataFrame, block_chars: int = BLOCK_CHARS, owner: str = "session") -> DataFrame:
    """One row per row of `docs`: doc_id, keep_id, group_size, kept, text_sha256.

    docs needs doc_id and text; other columns are ignored. Texts are equal when identical after
    lower-casing A to Z; null counts as empty, and empty texts are one group. The row with the largest
    doc_id stays; of repeated rows with that id one stays; null ids lose to any id. An empty table gives no rows.
    """
    rows = written(identities(docs, block_chars, owner), "naming-identities", owner)
    best = F.max(F.struct(F.col("doc_id"), F.col("row_no")))
    groups = rows.groupBy("identity").agg(best.alias("best"), F.count(F.lit(1)).alias("group_size"))
    groups = written(groups.withColumn("uses", F.col("group_size")), "naming-groups", owner)
    return hot_join(rows, groups, "identity", "uses", owner).select(
        "doc_id",
        F.col("best.doc_id").alias("keep_id"),
        "group_size",
        (F.col("row_no") == F.col("best.row_no")).alias("kept"),
        "text_sha256",
    )


def deduplicated(docs: DataFrame, block_chars: int = BLOCK_CHARS, owner: str = "session") -> DataFrame:
    """`docs` without all but one row of each group of equal texts; columns as they come, whatever their names."""
    same = F.struct(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id"), F.col("text_sha256"))
    kept = exact_groups(docs, block_chars, owner).where("kept").select(same.alias("same"))
    keyed = beside(docs, same=F.struct(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id"), F.sha2(lower_ascii(F.col("text")), 256).alias("text_sha256")))
    # Rows that repeat an id and a text are one document: any of them stands for all.
    return keyed.join(kept, "same", "left_semi").dropDuplicates(["same"]).select("row.*")


ORACLE = """
WITH d AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents
), g AS (
  SELECT t, max(doc_id) AS keep_id, CAST(count(*) AS BIGINT) AS group_size FROM d GROUP BY t
)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256 FROM d JOIN g ON d.t = g.t
"""
