"""Similarity join of documents on word n-grams: all links of Jaccard similarity at or above a bound.

1. Every text becomes its set of hashed n-grams. Equal sets are one class; classes, not copies, are compared.
2. Two sets of at least that similarity share one of their first s - ceil(t s) + 1 n-grams in any fixed
   order. The order is by the corpus count of an n-gram's rarest word, rare first (counts of all words in a table of
   fixed size; a collision there only changes the order). The n-grams a set shows this way are its tiles.
3. Tiles are banded by set size: only sizes within the bound of each other are compared.
   First every class meets the least class of its tile; found links are contracted. Then, twice, what is still apart meets
   one class drawn for each tile, which connects large groups by as many comparisons as they have rows.
   Last, classes of one tile that are still apart meet each other, large tiles as a grid of blocks: bands of set size,
   cut by a hash into blocks of about GRID rows, of which only those of the same and of neighbouring bands meet.
4. A pair must pass its 2048-bit signatures of odd counts: with d differing bits the overlap is at most (|A| + |B| - d) / 2.
   What passes is decided by intersecting the two sorted hash arrays.
5. Links are contracted to components.

N-grams are 64-bit hashes; everything else is exact, and no link between different sets is skipped
unless the two are connected already.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cuts import release, written
from .components import components
from .hot import hot_join
from .memory import lean

#: Slots of the table of word counts: at most 262,144 numbers on the driver.
SKETCH_BITS = 18
SIGNATURE_WORDS = 32
#: Rows of a tile that one task compares with each other, about.
GRID = 1024
#: A set that many others are compared with goes to several places, once for about so many of them.
PARTNERS = 64
#: Seeds of the turns in which each tile draws the class that the others meet.
DRAWN_TURNS = (1, 2)
#: Bits of the filter of documents whose sets are wanted (1 MB); fuller filters pass more, never less.
WANTED_BITS = 23
#: Bytes of text hashed at once; longer texts are hashed piece by piece, cut at white space.
PIECE = 1 << 17
U = np.uint64
#: One random 64-bit number a byte value, and an odd base: a word's hash is a polynomial over its bytes.
BYTE_VALUES = np.random.default_rng(20240101).integers(0, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)
IS_SPACE = np.isin(np.arange(256), list(b" \t\n\x0b\x0c\r"))

_powers: list[np.ndarray] = [np.ones(1, dtype=U), np.ones(1, dtype=U)]


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers (fixed values: the finaliser constants of a public generator)."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _power_tables(n: int) -> list[np.ndarray]:
    """Powers of the base and of its inverse, 0 to n - 1 at least."""
    if len(_powers[0]) < n:
        size = 1 << max(12, (n - 1).bit_length())
        for i, base in enumerate((BASE, INVERSE)):
            steps = np.full(size, base, dtype=U)
            steps[0] = 1
            _powers[i] = np.cumprod(steps, dtype=U)
    return _powers


def word_hashes(raw: bytes) -> np.ndarray:
    """A 64-bit hash of every word after lower-casing A to Z, in order."""
    if len(raw) > PIECE:
        parts, start = [], 0
        while start < len(raw):
            end = min(len(raw), start + PIECE)
            while end < len(raw) and not IS_SPACE[raw[end]]:
                end += 1
            parts.append(_hashes(raw[start:end]))
            start = end
        return np.concatenate(parts)
    return _hashes(raw)


def _hashes(raw: bytes) -> np.ndarray:
    b = np.frombuffer(raw.lower(), dtype=np.uint8)
    edge = np.ones(len(b) + 2, dtype=bool)
    edge[1:-1] = IS_SPACE[b]
    turns = np.nonzero(edge[1:] != edge[:-1])[0]
    starts, ends = turns[::2], turns[1::2]
    powers, inverse = _power_tables(len(b) + 1)
    running = np.zeros(len(b) + 1, dtype=U)
    np.cumsum(BYTE_VALUES[b] * powers[: len(b)], out=running[1:])
    return mixed((running[ends] - running[starts]) * inverse[starts] + (ends - starts).astype(U))


def _grams(h: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n-grams by position; one of the whole sequence if it is shorter."""
    width = min(n, len(h))
    x = np.full(len(h) - width + 1, width, dtype=U)
    for i in range(width):
        x = mixed(x * U(BASE) + h[i : len(h) - width + 1 + i])
    return x


def shingles(raw: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of the word n-grams; none without words."""
    h = word_hashes(raw) if raw else np.empty(0, dtype=U)
    return np.unique(_grams(h, n)) if len(h) else h


def ranked_shingles(raw: bytes, n: int, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same set, and for each n-gram the least rank of its words."""
    h = word_hashes(raw)
    if not len(h):
        return h, np.empty(0, dtype=ranks.dtype)
    word = ranks[(h & U((1 << SKETCH_BITS) - 1)).astype(np.int64)]
    width = min(n, len(h))
    least = word[: len(h) - width + 1].copy()
    for i in range(1, width):
        np.minimum(least, word[i : len(h) - width + 1 + i], out=least)
    s, at = np.unique(_grams(h, n), return_index=True)
    return s, least[at]


def prefix_length(size: int, num: int, den: int) -> int:
    """N-grams that a set of this size must show: size - ceil(size * num / den) + 1."""
    return size - -(-size * num // den) + 1


def shown(s: np.ndarray, rank: np.ndarray, num: int, den: int) -> np.ndarray:
    """The first n-grams of `s` by (rank, hash)."""
    return s[np.argsort(rank, kind="stable")[: prefix_length(len(s), num, den)]]


def signature(s: np.ndarray) -> np.ndarray:
    """64 * SIGNATURE_WORDS bits: for every cell, whether an odd number of n-grams falls into it.

    What two sets share cancels in the difference of their bits, so each differing bit needs an n-gram of its own that
    only one of them has: the number of differing bits is at most the size of the symmetric difference.
    """
    cells = ((s >> U(20)) % U(SIGNATURE_WORDS * 64)).astype(np.int64)
    odd = (np.bincount(cells, minlength=SIGNATURE_WORDS * 64) & 1).astype(np.uint8)
    return np.packbits(odd, bitorder="little").view(np.int64)


def _slices(batches, rows: int = 1000):
    """Arrow batches in slices: what Python holds of the texts at once stays small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def _raw(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("raw"))


def _base(docs: DataFrame, n: int, owner: str) -> DataFrame:
    """Per document its set size and set digest; per task the word counts of the sketch; one written table."""
    names = ["doc_id", "n", "digest", "slot", "hits"]
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.int32(), pa.int64()]

    def work(batches):
        counts = np.zeros(1 << SKETCH_BITS, dtype=np.int64)
        for batch in _slices(batches):
            size, digest = [], []
            for raw in batch.column("raw").to_pylist():
                h = word_hashes(raw) if raw else ()
                s = np.unique(_grams(h, n)) if len(h) else h
                size.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                if len(h):
                    np.add.at(counts, (h & U((1 << SKETCH_BITS) - 1)).astype(np.int64), 1)
            rows = len(size)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(v, k) for v, k in zip((size, digest, [-1] * rows, [0] * rows), kinds[1:], strict=True)]], names)
        at = np.nonzero(counts)[0]
        yield pa.RecordBatch.from_arrays([pa.nulls(len(at), kinds[0]), pa.array(np.full(len(at), -1), kinds[1]), pa.nulls(len(at), kinds[2]), pa.array(at, kinds[3]), pa.array(counts[at], kinds[4])], names)

    return written(_raw(docs).mapInArrow(lean(work), "doc_id long, n long, digest binary, slot int, hits long"), "jaccard-base", owner)


def _sketch_ranks(base: DataFrame) -> np.ndarray:
    """Counts of the sketch on a logarithmic scale of 8 bits."""
    ranks = np.zeros(1 << SKETCH_BITS, dtype=np.uint8)
    found = base.where("slot >= 0").groupBy("slot").agg(F.sum("hits").alias("hits")).toArrow()
    ranks[found["slot"].to_numpy()] = np.minimum(255, 4 * np.log2(1.0 + found["hits"].to_numpy())).astype(np.uint8)
    return ranks


def _wanted(ids: DataFrame) -> np.ndarray:
    """A filter of bounded size over the column `node`."""
    bit = F.pmod(F.xxhash64("node"), F.lit(1 << WANTED_BITS))
    words = ids.select(F.shiftright(bit, 6).alias("at"), F.expr(f"shiftleft(1L, cast(pmod(xxhash64(node), {1 << WANTED_BITS}) % 64 as int))").alias("mask"))
    table = np.zeros(1 << (WANTED_BITS - 6), dtype=np.uint64)
    for at, mask in words.groupBy("at").agg(F.bit_or("mask")).collect():
        table[at] = U(mask & 0xFFFFFFFFFFFFFFFF)
    return table


def _sets_of(docs: DataFrame, nodes: DataFrame, n: int) -> DataFrame:
    """node, set (sorted hashes as bytes) of the documents named in `nodes`, recomputed from their texts."""
    sent = docs.sparkSession.sparkContext.broadcast(_wanted(nodes))

    def work(batches):
        table = sent.value
        for batch in _slices(batches):
            bit = batch.column("bit").to_numpy()
            part = batch.filter(pa.array((table[bit >> 6] >> (bit & 63).astype(U)) & U(1) == 1))
            sets = [shingles(raw, n).tobytes() for raw in part.column("raw").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("node"), pa.array(sets, pa.binary()), pa.array([hashlib.blake2b(s, digest_size=16).digest() for s in sets], pa.binary())], ["node", "set", "digest"])

    rows = _raw(docs).where(F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("node"), "raw", F.pmod(F.xxhash64("doc_id"), F.lit(1 << WANTED_BITS)).alias("bit"))
    sets = rows.mapInArrow(lean(work), "node long, set binary, digest binary").join(nodes, "node", "left_semi")
    return sets.groupBy("node").agg(F.min(F.struct("digest", "set")).alias("s")).select("node", "s.set")


def _possible(num: int, den: int, na: Column, nb: Column, sig_a: Column, sig_b: Column) -> Column:
    """Sizes and signatures allow the similarity: with d differing bits, overlap <= (na + nb - d) / 2."""
    d = F.aggregate(F.zip_with(sig_a, sig_b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda acc, v: acc + v)
    # overlap / union >= num / den  <=>  (den + num) * overlap >= num * (na + nb)
    return (num * F.greatest(na, nb) <= den * F.least(na, nb)) & ((den + num) * (na + nb - d) >= 2 * num * (na + nb))


def _places(pairs: DataFrame, owner: str) -> DataFrame:
    """node, a, salt, b: the set of a (b null) once a place of about PARTNERS partners, the set of b once a pair."""
    counts = written(pairs.groupBy("a").agg(F.count(F.lit(1)).alias("partners")).withColumn("uses", F.col("partners")), "jaccard-partners", owner)
    salt = F.pmod(F.xxhash64("b"), F.ceil(F.col("partners") / PARTNERS)).cast("int")
    salted = hot_join(pairs, counts, "a", "uses", owner).select("a", "b", salt.alias("salt"))
    heads = salted.select("a", "salt").distinct().select(F.col("a").alias("node"), "a", "salt", F.lit(None).cast("long").alias("b"))
    return heads.unionByName(salted.select(F.col("b").alias("node"), "a", "salt", "b"))


def _verified(docs: DataFrame, pairs: DataFrame, n: int, num: int, den: int, owner: str, brief: str) -> DataFrame:
    """The pairs (a, b) whose sets reach the similarity, by intersecting sorted arrays; only sets of pairs are made.

    The sets are dealt by document as they are made and then to their places, and nowhere written. What stands under `brief`
    goes when the links are there, the table of `pairs` with it.
    """
    nodes = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    sets = _sets_of(docs, written(nodes, "jaccard-nodes", brief), n)
    # The set of a comes before those of its partners.
    met = _places(pairs, brief).join(sets, "node").select("a", "salt", "b", "set")
    dealt = met.repartition("a", "salt").sortWithinPartitions("a", "salt", F.col("b").asc_nulls_first())

    def work(batches):
        head, x = None, None
        for batch in _slices(batches, 500):
            a, ok = batch.column("a").to_pylist(), []
            for i, (b, raw) in enumerate(zip(batch.column("b"), batch.column("set"), strict=True)):
                y = np.frombuffer(raw.as_buffer(), dtype=U)
                if not b.is_valid:
                    head, x = a[i], y.copy()
                    ok.append(False)
                    continue
                if head != a[i]:
                    raise RuntimeError("a set came apart from its partners")
                overlap = len(np.intersect1d(x, y, assume_unique=True))
                ok.append(den * overlap >= num * (len(x) + len(y) - overlap))
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    links = written(dealt.mapInArrow(lean(work), "a long, b long"), "jaccard-links", owner)
    release(brief)
    return links


def similar_groups(docs: DataFrame, n: int = 5, num: int = 4, den: int = 5, owner: str = "session") -> DataFrame:
    """One row per row of `docs`: doc_id, n_shingles, component_id.

    docs needs doc_id (an integer) and text; other columns are ignored. Documents link when
    den * |A and B| >= num * |A or B| for their sets of word n-grams (A to Z lower-cased; fewer words than n: the whole
    sequence). Null, empty and blank texts have no n-grams and link with nothing. component_id is the smallest
    doc_id reachable by links, itself included. Repeated rows and rows sharing an id are one document in the
    links; null ids link with nothing and have a null component. An empty table gives no rows.
    """
    fresh = lambda: f"{owner}-{uuid.uuid4().hex}"  # noqa: E731  an owner of tables that go before the result is read
    base, early, held, lasting = _base(docs, n, owner), fresh(), fresh(), fresh()
    rows = base.where("slot < 0").select("doc_id", "n", "digest")
    classes = written(rows.where("n > 0 AND doc_id IS NOT NULL").groupBy("digest").agg(F.min("doc_id").alias("rep")), "jaccard-classes", owner)
    ranks = docs.sparkSession.sparkContext.broadcast(_sketch_ranks(base))

    def show(batches):
        for batch in _slices(batches):
            size, first, bits, digest = [], [], [], []
            for raw in batch.column("raw").to_pylist():
                s, rank = ranked_shingles(raw or b"", n, ranks.value)
                size.append(len(s))
                first.append(shown(s, rank, num, den).view(np.int64) if len(s) else [])
                bits.append(signature(s) if len(s) else [])
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
            longs = pa.list_(pa.int64())
            made = pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(size, pa.int64()), pa.array(first, longs), pa.array(bits, longs), pa.array(digest, pa.binary())], ["rep", "n", "shown", "sig", "digest"])
            yield made.filter(pa.array(np.array(size, dtype=np.int64) > 0))

    shown_rows = _raw(docs).where(F.col("doc_id").isNotNull()).mapInArrow(lean(show), "rep long, n long, shown array<bigint>, sig array<bigint>, digest binary")
    # Of a class only its representative is compared; of rows that share an id, the one with the least set.
    keep = classes.groupBy("rep").agg(F.min("digest").alias("digest"))
    # Joined by rep alone, rows stay where they are while duplicates are dropped.
    reps = shown_rows.join(keep.withColumnRenamed("digest", "kept"), "rep").where("digest = kept").dropDuplicates(["rep"])
    reps = written(reps.select("rep", "n", "shown", "sig"), "jaccard-reps", early)
    tiles = reps.select("rep", "n", F.explode("shown").alias("tile"))
    led = tiles.groupBy("tile").agg(F.count(F.lit(1)).alias("members"), F.min("rep").alias("leader")).where("members > 1")
    led = written(led.withColumn("uses", F.col("members")), "jaccard-led", early)
    tiles = written(hot_join(tiles, led, "tile", "uses", early).select("tile", "rep", "n", "members", "leader"), "jaccard-tiles", held)
    about = written(reps.select("rep", "n", "sig"), "jaccard-about", lasting)
    release(early)

    def filtered(pairs: DataFrame, brief: str) -> DataFrame:
        pairs = written(pairs, "jaccard-met", brief)
        a = about.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sig").alias("sa"))
        b = about.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sig").alias("sb"))
        met = hot_join(pairs, a, "a", owner=brief).join(b, "b").where(_possible(num, den, F.col("na"), F.col("nb"), F.col("sa"), F.col("sb")))
        return written(met.select("a", "b"), "jaccard-pairs", brief)

    brief = fresh()
    first = filtered(tiles.where("rep <> leader").select(F.col("leader").alias("a"), F.col("rep").alias("b")).distinct(), brief)
    links = _verified(docs, first, n, num, den, owner, brief)
    roots = components(links, owner)
    tiles = tiles.drop("members", "leader")
    turns = [*DRAWN_TURNS, None]
    while turns:
        turn, brief = turns.pop(0), fresh()
        # Tiles whose classes are still apart; two classes have met already.
        placed = tiles.join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").withColumn("root", F.coalesce("root", "rep"))
        placed = written(placed, "jaccard-placed", brief)
        release(held)  # the tiles of the turn before
        drawn = F.min_by(F.struct("rep", "root"), F.xxhash64("rep", "tile", F.lit(turn or 0)))
        apart = placed.groupBy("tile").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("members"), drawn.alias("leader")).where("lo < hi AND members > 2")
        apart = written(apart.drop("lo", "hi").withColumn("uses", F.col("members")), "jaccard-apart", brief)
        open_tiles = written(hot_join(placed, apart, "tile", "uses", brief), "jaccard-open", held)
        release(brief)
        if open_tiles.isEmpty():
            break
        if turn is None:
            pairs = _apart_pairs(open_tiles.drop("leader"), about, num, den, brief)
        else:
            pairs = open_tiles.where("root <> leader.root").select(F.col("leader.rep").alias("a"), F.col("rep").alias("b")).distinct()
        found = _verified(docs, filtered(pairs, brief), n, num, den, owner, brief)
        tiles = open_tiles.select("tile", "rep", "n")
        if found.isEmpty():
            turns = turns[-1:]  # drawn classes connect nothing more
            continue
        links = links.unionByName(found)
        roots = components(links, owner)

    release(held)
    release(lasting)
    by_class = classes.join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").select("digest", F.coalesce("root", "rep").alias("root"))
    return rows.join(by_class, "digest", "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("root", "doc_id")).alias("component_id")
    )


def _apart_pairs(tiles: DataFrame, about: DataFrame, num: int, den: int, owner: str) -> DataFrame:
    """Distinct pairs (a, b) of one tile with different roots whose sizes and signatures fit.

    Sizes within the bound of each other lie in one band or in neighbouring ones. A band of a large tile is cut by a
    hash into blocks of about GRID rows; every group of rows compared by a task is two blocks at most.
    """
    small = tiles.where(F.col("members") <= GRID).select("tile", "rep", "n", "root", F.lit(0).cast("long").alias("block"), F.array(F.lit(0).cast("long")).alias("others"))
    large = tiles.where(F.col("members") > GRID).withColumn("band", F.floor(F.log(F.col("n").cast("double")) / float(np.log(den / num) + 1e-12)).cast("long"))
    cut = large.groupBy("tile", "band").agg(F.count(F.lit(1)).alias("uses")).withColumn("parts", F.ceil(F.col("uses") / GRID).cast("long"))
    in_order = Window.partitionBy("tile").orderBy("band")  # one row a band
    beside = [F.when(step(F.col("band"), 1).over(in_order) == F.col("band") + way, step(F.col("parts"), 1).over(in_order)).otherwise(0) for step, way in ((F.lag, -1), (F.lead, 1))]
    cut = written(cut.withColumn("below", beside[0]).withColumn("above", beside[1]), "jaccard-bands", owner)
    number = lambda band, part: band * (1 << 32) + part
    blocks = lambda band, count: F.when(count > 0, F.transform(F.sequence(F.lit(0).cast("long"), count - 1), lambda p: number(band, p))).otherwise(F.array().cast("array<bigint>"))
    large = hot_join(large.drop("members"), cut, ["tile", "band"], "uses", owner).select(
        "tile", "rep", "n", "root", number(F.col("band"), F.pmod(F.xxhash64("rep"), F.col("parts"))).alias("block"),
        F.concat(blocks(F.col("band") - 1, F.col("below")), blocks(F.col("band"), F.col("parts")), blocks(F.col("band") + 1, F.col("above"))).alias("others"),
    )
    rows = small.unionByName(large).join(about.select("rep", "sig"), "rep").withColumn("other", F.explode("others"))
    rows = rows.select("tile", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "rep", "n", "root", "sig")

    dealt = rows.repartition("tile", "low", "high").sortWithinPartitions("tile", "low", "high", "n", "rep")

    def compare(batches):
        """Runs of equal (tile, low, high) in the sorted rows; a run that goes on in the next batch is carried over."""
        rest = None
        for batch in batches:
            table = pa.Table.from_batches([batch]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([batch])])
            key = [table.column(c).to_numpy() for c in ("tile", "low", "high")]
            edges = np.concatenate([[0], np.nonzero((key[0][1:] != key[0][:-1]) | (key[1][1:] != key[1][:-1]) | (key[2][1:] != key[2][:-1]))[0] + 1])
            last = int(edges[-1])
            yield pairs_of(table.slice(0, last), np.append(edges[:-1], last))
            rest = table.slice(last)
        if rest is not None:
            yield pairs_of(rest, np.array([0, rest.num_rows]))

    def pairs_of(table, edges):
        """Pairs of each run: rows of its low block against rows of its high block, the arrays taken out once."""
        low, high, block, n, rep, root = (table.column(c).to_numpy() for c in ("low", "high", "block", "n", "rep", "root"))
        sig = table.column("sig").combine_chunks().flatten().to_numpy().reshape(-1, SIGNATURE_WORDS) if table.num_rows else np.empty((0, SIGNATURE_WORDS), dtype=np.int64)
        a, b = [], []
        for x, y in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
            if y - x < 2:
                continue
            mine = np.arange(x, y)[block[x:y] == low[x]]
            same = low[x] == high[x]
            others = mine if same else np.arange(x, y)[block[x:y] == high[x]]
            for q, i in enumerate(mine.tolist()):
                # Rows are in order of set size, so only a stretch of them is in reach.
                near = others[q + 1 :] if same else others
                near = near[(root[near] != root[i]) & (num * np.maximum(n[i], n[near]) <= den * np.minimum(n[i], n[near]))]
                if len(near):
                    d = np.bitwise_count((sig[i] ^ sig[near]).view(np.uint64)).sum(axis=1, dtype=np.int64)
                    near = near[(den + num) * (n[i] + n[near] - d) >= 2 * num * (n[i] + n[near])]
                    a.append(np.minimum(rep[i], rep[near]))
                    b.append(np.maximum(rep[i], rep[near]))
        empty = np.empty(0, dtype=np.int64)
        found = np.unique(np.stack([np.concatenate([empty, *a]), np.concatenate([empty, *b])], axis=1), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(found[:, 0], pa.int64()), pa.array(found[:, 1], pa.int64())], ["a", "b"])

    return dealt.mapInArrow(lean(compare), "a long, b long").distinct()


def one_of_each_group(docs: DataFrame, n: int = 5, num: int = 4, den: int = 5, owner: str = "session") -> DataFrame:
    """`docs` with the document of smallest doc_id of each component; documents without links or ids stay."""
    gone = similar_groups(docs, n, num, den, owner).where("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(written(gone, "jaccard-gone", owner), "doc_id", "left_anti").select(*docs.columns)


def oracle(n: int, num: int, den: int) -> str:
    """DuckDB SQL by plain pair comparison over shared n-grams and a recursive closure."""
    return f"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {n} THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - {n} + 2), lambda i: array_to_string(w[i:i + {n - 1}], ' '))) END AS g FROM d
), c AS (SELECT g, min(doc_id) AS rep FROM (SELECT doc_id, list_sort(g) AS g FROM s WHERE len(g) > 0) GROUP BY g
), m AS (SELECT s.doc_id, c.rep FROM (SELECT doc_id, list_sort(g) AS g FROM s WHERE len(g) > 0) s JOIN c ON s.g = c.g
), u AS (SELECT rep, len(g) AS size, unnest(g) AS t FROM c
), o AS (SELECT a.rep AS a, b.rep AS b, any_value(a.size) AS na, any_value(b.size) AS nb, count(*) AS k FROM u a JOIN u b ON a.t = b.t AND a.rep <> b.rep GROUP BY a.rep, b.rep
), l AS (SELECT a, b FROM o WHERE {den} * k >= {num} * (na + nb - k)
), r(node, root) AS (
  SELECT rep, rep FROM c
  UNION
  SELECT l.b, r.root FROM r JOIN l ON r.node = l.a WHERE r.root < l.b
), f AS (SELECT node, min(root) AS root FROM r GROUP BY node)
SELECT s.doc_id, CAST(len(s.g) AS BIGINT) AS n_shingles, coalesce(f.root, s.doc_id) AS component_id
FROM s LEFT JOIN m ON s.doc_id = m.doc_id LEFT JOIN f ON m.rep = f.node
"""


ORACLE = oracle(3, 9, 10)
