"""Judging URLs against listed canonical rules: a blocked Bloom filter, then an exact hash join.

A canonical rule is host/path. Its key is its host and path themselves, or, of very long ones, their last
MOST_LABELS labels and first MOST_PATH bytes. The shape of a key is its number of labels and its length of path; a
URL has at most one key of every listed shape, so what it is probed with follows from the list, not from the URL's own
length. Keys are hashed from running polynomial sums, which cost a URL's length once. A blocked Bloom filter of the listed
keys (each sets its bits inside one 512-bit block) passes possible hits; only those are made into strings and
joined exactly with the list, which removes false positives and the rules whose cut part does not fit. The longest fitting
rule judges; URLs that no rule fits are allowed, a list-based filter having nothing against them.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.cuts import written

#: The rules of the contract: verdict, rule.
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
BLOCK_BITS, PROBES = 512, 8
BITS_PER_KEY = 16
#: The filter is broadcast, so its size is bounded: a list beyond it gets more false positives, never other verdicts.
MOST_FILTER_BYTES = 64 << 20
#: Labels and bytes of path that a key holds at most: what bounds the number of shapes. Whole rules are compared after the join.
MOST_LABELS, MOST_PATH = 64, 1024
#: Lists counted to be this short are broadcast to the exact join; longer ones are joined by key.
FEW_RULES = 50_000
#: Rows that share a URL are dealt to this many places when they meet its verdict.
SALTS = 64
U = np.uint64
#: Odd base of the running sums and one random 64-bit number a byte value.
BASE = 0x9E3779B97F4A7C15
BYTE_VALUES = np.random.default_rng(20240202).integers(0, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A to Z lower-cased) and path of a URL; both empty for null or without `://`."""
    url = F.coalesce(url, F.lit(""))
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(url)), r"^[^?#]*", 0)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def bloom_words(hashes: np.ndarray, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """Word numbers and masks, PROBES a key, of 64-bit hashes in a filter of `blocks` blocks."""
    h = hashes.astype(np.int64).view(np.uint64)
    block = (h >> np.uint64(32)) % np.uint64(blocks)
    with np.errstate(over="ignore"):
        mixed = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    bits = (mixed[:, None] >> (np.uint64(7) * np.arange(PROBES, dtype=np.uint64))[None, :]) & np.uint64(BLOCK_BITS - 1)
    return (block[:, None] * np.uint64(BLOCK_BITS // 64) + (bits >> np.uint64(6))).astype(np.int64), np.uint64(1) << (bits & np.uint64(63))


def _scrambled(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(31))) * U(BASE)
    return x ^ (x >> U(29))


def _powers(n: int) -> np.ndarray:
    steps = np.full(n + 1, BASE, dtype=U)
    steps[0] = 1
    return np.cumprod(steps, dtype=U)


def prefix_hashes(raw: bytes) -> np.ndarray:
    """Hash of raw[:n] for n = 0 .. len(raw)."""
    out = np.zeros(len(raw) + 1, dtype=U)
    np.cumsum(BYTE_VALUES[np.frombuffer(raw, dtype=np.uint8)] * _powers(len(raw))[:-1], out=out[1:])
    return out


def key_hashes(host: np.ndarray, path: np.ndarray) -> np.ndarray:
    """Hash of a key from the hashes of its reversed host and its path."""
    return _scrambled(_scrambled(host) + path)


def split_rule(rule: bytes) -> tuple[bytes, bytes]:
    """The host and path of a rule's key."""
    host, slash, path = rule.partition(b"/")
    return b".".join(host.split(b".")[-MOST_LABELS:]), (slash + path)[:MOST_PATH]


def hash_of_rule(rule: bytes) -> int:
    host, path = split_rule(rule)
    return int(key_hashes(prefix_hashes(host[::-1])[-1:], prefix_hashes(path)[-1:]).view(np.int64)[0])


class Shapes:
    """The listed shapes: for a number of labels, the lengths of path. At most MOST_LABELS * (MOST_PATH + 1) pairs."""

    def __init__(self, pairs: Sequence[tuple[int, int]]):
        self.lengths = {labels: np.sort([n for k, n in pairs if k == labels]) for labels in {k for k, _ in pairs}}

    def keys(self, host: bytes, path: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hash, host length and path length of every key of a URL that has a listed shape."""
        backwards = host[::-1]
        dots = np.nonzero(np.frombuffer(backwards, dtype=np.uint8) == 46)[0]
        ends = np.append(dots, len(host))  # where k labels from the right end, k = 1, 2, ...
        mine = [k for k in self.lengths if k <= len(ends)]
        if not host or not path or not mine:
            return np.empty(0, dtype=U), np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        longest = int(ends[max(mine) - 1])
        hosts, paths = prefix_hashes(backwards[:longest]), prefix_hashes(path[:MOST_PATH])
        hashes, at, cut = [], [], []
        for k in mine:
            lengths = self.lengths[k][: np.searchsorted(self.lengths[k], len(paths))]
            end = int(ends[k - 1])
            hashes.append(key_hashes(np.full(len(lengths), hosts[end]), paths[lengths]))
            at.append(np.full(len(lengths), end))
            cut.append(lengths)
        return np.concatenate(hashes), np.concatenate(at), np.concatenate(cut)


def build_filter(hashes: DataFrame, keys: int) -> np.ndarray:
    """The filter over the column `h` of `hashes`: words are or-ed on the executors, at most MOST_FILTER_BYTES come back."""
    blocks = max(1, min(MOST_FILTER_BYTES * 8, keys * BITS_PER_KEY) // BLOCK_BITS + 1)

    def parts(batches):
        for pdf in batches:
            at, mask = bloom_words(pdf["h"].to_numpy(), blocks)
            yield pd.DataFrame({"at": at.ravel(), "mask": mask.ravel().view(np.int64)})

    words = hashes.mapInPandas(parts, "at long, mask long").groupBy("at").agg(F.bit_or("mask").alias("mask"))
    table = np.zeros(blocks * BLOCK_BITS // 64, dtype=np.uint64)
    for at, mask in words.collect():
        table[at] = np.uint64(mask & 0xFFFFFFFFFFFFFFFF)
    return table


def rule_table(spark: SparkSession, rules: Sequence[tuple[str, str]] = RULES) -> DataFrame:
    return spark.createDataFrame([(v, r) for v, r in rules], "verdict string, rule string")


def judge(pages: DataFrame, rules: DataFrame, owner: str = "session") -> DataFrame:
    """One row per row of `pages`: page_id, host, path, rule, verdict.

    pages needs page_id and url, rules needs verdict and rule (host/path, host lower-case; repeated rules
    count once, the smaller verdict winning; rules without `/` or host fit nothing). Null urls and urls without `://` have
    empty host and path and fit nothing. Ties of length cannot fit one URL twice. Empty tables give no rows; an empty
    list allows all. Very long hosts, paths and rules are judged like others.
    """
    spark = pages.sparkSession
    sound = F.col("rule").isNotNull() & (F.instr("rule", "/") > 1)
    listed = rules.where(sound).groupBy("rule").agg(F.min("verdict").alias("listed_verdict"))

    def keyed_rules(batches):
        for batch in batches:
            raw = [r.encode() for r in batch.column("rule").to_pylist()]
            parts = [split_rule(r) for r in raw]
            yield pa.RecordBatch.from_arrays(
                [batch.column("rule"), batch.column("listed_verdict"), pa.array([h + p for h, p in parts], pa.binary()), pa.array([hash_of_rule(r) for r in raw], pa.int64()),
                 pa.array([h.count(b".") + 1 for h, _ in parts], pa.int32()), pa.array([len(p) for _, p in parts], pa.int32())],
                ["rule", "listed_verdict", "key", "h", "labels", "cut"],
            )

    listed = written(listed.mapInArrow(keyed_rules, "rule string, listed_verdict string, key binary, h long, labels int, cut int"), "url-rules", owner)
    host, path = host_and_path(F.col("url"))
    parsed = pages.select("page_id", host.alias("host"), path.alias("path"))
    count = listed.count()
    if not count:
        return parsed.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit("allow").alias("verdict"))
    shapes = Shapes([tuple(r) for r in listed.select("labels", "cut").distinct().collect()])
    sent = spark.sparkContext.broadcast((build_filter(listed.select("h"), count), shapes))
    kind = dict(pages.dtypes)["page_id"]

    def possible(batches):
        """The rows, with those keys of each that the filter passes."""
        words, known = sent.value
        for batch in batches:
            hosts, paths = ([t.encode() for t in batch.column(c).to_pylist()] for c in ("host", "path"))
            made = [known.keys(h, p) for h, p in zip(hosts, paths, strict=True)]
            sizes = [len(m[0]) for m in made]
            keys: list[list[bytes]] = [[] for _ in made]
            if sum(sizes):
                at, mask = bloom_words(np.concatenate([m[0] for m in made]).view(np.int64), len(words) * 64 // BLOCK_BITS)
                owner_of, begin = np.repeat(np.arange(len(made)), sizes), np.cumsum([0, *sizes])
                for j in np.nonzero(((words[at] & mask) == mask).all(axis=1))[0].tolist():
                    i = int(owner_of[j])
                    end, cut = int(made[i][1][j - begin[i]]), int(made[i][2][j - begin[i]])
                    keys[i].append(hosts[i][len(hosts[i]) - end :] + paths[i][:cut])
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in ("page_id", "host", "path")], pa.array(keys, pa.list_(pa.binary()))], ["page_id", "host", "path", "keys"])

    rows = written(parsed.mapInArrow(possible, f"page_id {kind}, host string, path string, keys array<binary>"), "url-keys", owner)
    hits = rows.where(F.size("keys") > 0)
    exact = hits.dropDuplicates(["host", "path"]).select("host", "path", F.explode("keys").alias("key")).join(F.broadcast(listed) if count <= FEW_RULES else listed, "key")
    at = F.instr("rule", "/")
    rule_host, rule_path = F.substring("rule", 1, at - 1), F.substring("rule", at, F.length("rule"))
    fits = F.startswith("path", rule_path) & ((F.col("host") == rule_host) | F.endswith("host", F.concat(F.lit("."), rule_host)))
    best = exact.where(fits).groupBy("host", "path").agg(F.max(F.struct(F.length("rule"), "rule", "listed_verdict")).alias("best"))
    # Rows of one URL may be a third of all: they meet its verdict in SALTS places.
    best = best.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salted = hits.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int"))
    judged = salted.join(best, ["host", "path", "salt"], "left").select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.listed_verdict", F.lit("allow")).alias("verdict"))
    clear = rows.where(F.size("keys") == 0).select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit("allow").alias("verdict"))
    return judged.unionByName(clear)


ORACLE = """
WITH u AS (
  SELECT page_id, CASE WHEN strpos(coalesce(url, ''), '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), h AS (
  SELECT page_id, rest, regexp_extract(rest, '^[^/?#]*') AS host0 FROM u
), p AS (
  SELECT page_id, translate(host0, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(substr(rest, length(host0) + 1), '^[^?#]*') AS path FROM h
), r(verdict, rhost, rpath) AS (
  VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')
), f AS (
  SELECT p.page_id, p.host, p.path, r.verdict, rhost || rpath AS rule,
    row_number() OVER (PARTITION BY p.page_id, p.host, p.path ORDER BY length(rhost || rpath) DESC NULLS LAST) AS n
  FROM p LEFT JOIN r ON (p.host = rhost OR ends_with(p.host, '.' || rhost)) AND starts_with(p.path, rpath)
)
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM f WHERE n = 1
"""
