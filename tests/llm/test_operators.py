"""The ten operators on hand-made tables, against plain Python."""

import hashlib
import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvature_spark.llm import hmm, jaccard, mixing, naming, packing, sharding, tokens, topk, toxicity, urls
from curvature_spark.llm.components import components
from curvature_spark.llm.queries import vocabulary
from curvature_spark.plans import cuts

SCHEMA = "doc_id long, text string, source string, lang string, size long, name string"
LONG = " ".join(f"word{i % 997}" for i in range(30_000))
BASE = " ".join(f"w{i}" for i in range(60))
TEXTS = [
    (1, "Alpha beta gamma delta", "b"), (2, "alpha BETA gamma delta", "a"), (3, None, "a"), (4, "", None), (5, " \t\n", None),
    (6, LONG, "a"), (7, LONG, "c"), (7, LONG, "c"), (8, BASE, "b"), (9, BASE + " x", "b"), (10, BASE + " x y", "b"),
    (None, BASE, "b"), (None, None, None), (11, "Ünï ÄÖ straße", "d"), (12, "ünï äö straße", "d"), (13, "one two", "d"), (14, "one two", "d"),
]


def words(text):
    return (text or "").encode().lower().split()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, s, "en", 3, "n") for i, t, s in TEXTS], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_every_operator_takes_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    vectors = spark.createDataFrame([], "vec_id long, vector array<double>")
    for found in (
        mixing.mix(empty), sharding.shard(empty), naming.exact_groups(empty), jaccard.similar_groups(empty), hmm.score(empty, rounds=1),
        toxicity.score(empty, toxicity.fit(empty, labels)), tokens.token_counts(empty, vocabulary("word_bpe_49k.json")),
        packing.packed(empty, vocabulary("byte_bpe_50k.json")), topk.top_k(vectors, vectors),
        urls.judge(spark.createDataFrame([], "page_id long, url string"), urls.rule_table(spark)),
        toxicity.clean_documents(empty, labels), naming.deduplicated(empty), jaccard.one_of_each_group(empty), mixing.mixed_documents(empty),
    ):
        assert found.count() == 0


def test_mix_meets_targets(docs):
    rows = mixing.mix(docs).collect()
    assert len(rows) == len(TEXTS)
    by = defaultdict(list)
    for r in rows:
        assert 0 <= r.taken <= 3 * r.size
        by[r.source].append(r)
    sizes = {s: sum(r.size for r in x) for s, x in by.items()}
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: 1 + n % 3 for n, s in enumerate(order)}
    target, free, left = {}, set(order), float(sum(sizes.values()))
    while free:  # share, stop, reshare
        level = left / sum(weight[s] for s in free)
        over = {s for s in free if level * weight[s] > 3 * sizes[s]}
        for s in over or free:
            target[s] = 3.0 * sizes[s] if over else level * weight[s]
        if not over:
            break
        left -= sum(target[s] for s in over)
        free -= over
    for s, x in by.items():
        assert x[0].target == pytest.approx(target[s])
        assert abs(sum(r.taken for r in x) - target[s]) <= 1
    assert sorted(map(str, mixing.mix(docs.repartition(5)).collect())) == sorted(map(str, rows))
    assert mixing.mixed_documents(docs).columns == docs.columns


def test_sharding_is_a_permutation(docs):
    rows = sharding.shard(docs, 4).collect()
    counts = Counter(r.shard for r in rows)
    assert len(rows) == len(TEXTS) and max(counts.values()) - min(counts.values()) <= 1
    for s in counts:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(counts[s]))
    for r in rows:
        place = sharding.place_in_python(r.row_no, len(rows), 23)
        assert (place % 4, place // 4) == (r.shard, r.slot)
    assert Counter(r.text_crc32 for r in rows) == Counter(zlib.crc32((t or "").encode()) for _, t, _ in TEXTS)


@pytest.mark.parametrize("total", [1, 2, 3, 7, 100, 1001])
def test_places_cover_every_total(spark, total):
    assert sorted(sharding.place_in_python(x, total, 9) for x in range(total)) == list(range(total))
    got = spark.range(total).select(sharding.place(F.col("id"), total, 9).alias("p")).collect()
    assert [r.p for r in got] == [sharding.place_in_python(x, total, 9) for x in range(total)]


@pytest.mark.parametrize("block", [7, 1000, naming.BLOCK_CHARS])
def test_exact_groups(docs, block):
    lower = lambda t: (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    groups = defaultdict(list)
    for i, t, _ in TEXTS:
        groups[lower(t)].append(i)
    rows = naming.exact_groups(docs.where("doc_id IS NULL OR doc_id < 6 OR doc_id > 7") if block == 7 else docs, block).collect()
    if block == 7:
        groups.pop(lower(LONG))
    by = defaultdict(list)
    for r in rows:
        by[r.text_sha256].append(r)
    assert len(by) == len(groups)
    for text, ids in groups.items():
        found = by[hashlib.sha256(text.encode()).hexdigest()]
        best = max((i for i in ids if i is not None), default=None)
        assert Counter(r.doc_id for r in found) == Counter(ids)
        assert {(r.keep_id, r.group_size) for r in found} == {(best, len(ids))}
        assert sum(r.kept for r in found) == 1 and [r.doc_id for r in found if r.kept] == [best]
    assert naming.deduplicated(docs, block if block > 7 else 100).count() == len({lower(t) for _, t, _ in TEXTS})


def test_exact_groups_by_content_when_short_keys_collide(spark, docs, monkeypatch):
    expected = sorted(map(str, naming.exact_groups(docs).collect()))
    monkeypatch.setattr(naming, "_short_key", lambda block: F.struct(F.lit(0).alias("n")))
    assert sorted(map(str, naming.exact_groups(docs).collect())) == expected


def brute_components(rows, n, num, den):
    def grams(t):
        w = words(t)
        return frozenset(tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))) if w else frozenset()

    sets = [(i, grams(t)) for i, t in rows]
    root = {i: i for i, _ in sets if i is not None}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for x, (i, a) in enumerate(sets):
        for j, b in sets[:x]:
            if i is not None and j is not None and a and b and den * len(a & b) >= num * len(a | b):
                p, q = sorted((find(i), find(j)))
                root[q] = p
    return sorted((str(i), len(s), str(find(i) if i is not None else None)) for i, s in sets)


@pytest.mark.parametrize("n,num,den", [(3, 9, 10), (5, 4, 5)])
def test_similar_groups(spark, docs, n, num, den):
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in jaccard.similar_groups(docs, n, num, den).collect())
    assert got == brute_components([(i, t) for i, t, _ in TEXTS], n, num, den)


def test_join_frees_tables_as_it_goes(spark):
    """Sets, tiles and their like are gone when the join returns; the set of a document with few partners goes to one place."""
    words = [f"w{i}" for i in range(40)]
    texts = [" ".join(words[:-1] + [f"x{i}"]) for i in range(12)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = jaccard.similar_groups(docs, 5, 4, 5, owner="frees")
    left = {path.rsplit("/", 1)[1].rsplit("-", 1)[0] for _, path in cuts._LIVE["frees"]}
    assert left == {"jaccard-base", "jaccard-classes", "jaccard-links", "links"}
    assert not [owner for owner in cuts._LIVE if owner.startswith("frees-")]
    assert {r.component_id for r in out.collect()} == {0}
    pairs = cuts.written(spark.range(1, 40).selectExpr("0L AS a", "id AS b"), "pairs", "frees")
    places = jaccard._places(pairs, "frees").collect()
    assert sum(r.b is None for r in places) == 1 and sorted(r.b for r in places if r.b is not None) == list(range(1, 40))
    cuts.release("frees")


def test_similar_groups_of_a_shared_passage(spark, monkeypatch):
    """Many texts share a passage and few are near copies; small grid blocks, so that tiles are cut."""
    monkeypatch.setattr(jaccard, "GRID", 4)
    rng = np.random.default_rng(3)
    shared = [f"s{i}" for i in range(40)]
    rows = []
    for i in range(40):
        own = [f"o{x}" for x in rng.integers(0, 50, rng.integers(1, 12))]
        rows.append((i, " ".join(shared + own if i % 2 else own + shared)))
    for i in range(40, 70):
        text = rows[int(rng.integers(0, 40))][1].split()
        text[int(rng.integers(0, len(text)))] = f"z{i % 5}"
        rows.append((i, " ".join(text)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for n, num, den in ((3, 9, 10), (5, 4, 5), (2, 1, 2)):
        got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in jaccard.similar_groups(df, n, num, den).collect())
        assert got == brute_components(rows, n, num, den)


def test_components_of_a_path_and_a_star(spark):
    links = [(i, i + 1) for i in range(20)] + [(100, 100 + i) for i in range(1, 30)] + [(5, 5), (200, 200)]
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(21)}, **{100 + i: 100 for i in range(30)}}


def test_top_k_against_all_products(spark):
    rng = np.random.default_rng(1)
    data = [(int(i), [float(x) for x in rng.normal(size=8)]) for i in range(300)]
    data += [(1000 + i, data[5][1]) for i in range(30)] + [(2000, None), (2001, [1.0, None] + [0.0] * 6), (2002, [float("nan")] * 8), (None, data[0][1]), (2003, [1.0, 2.0]), (7, data[7][1])]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>").select("vec_id", topk.integer_vector(F.col("embedding")).alias("vector")).repartition(3)
    got = [(r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(df, df.where("vec_id % 10 = 0"), 10, query_block=9).collect()]
    ok = {i: np.floor(1024 * np.array(v)).astype(int) for i, v in data if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)}
    want = []
    for q, v in ok.items():
        if q % 10 == 0:
            best = sorted((-int(v @ c), i) for i, c in ok.items() if i != q and len(c) == len(v))[:10]
            want += [(q, n + 1, i, -s) for n, (s, i) in enumerate(best)]
    assert sorted(got) == sorted(want)


def test_top_k_of_huge_components(spark):
    """Components whose floors or products pass 64 bits: scores at the ends of a long, the rest exact."""
    data = [(1, [3e38, 0.0]), (2, [1e20, 1.0]), (3, [-1e20, 2.0]), (4, [1.0, 1.0]), (5, [2.0**60, -3.0]), (6, [0.5, 0.25]), (7, [2.0, -1e30])]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>").select("vec_id", topk.integer_vector(F.col("embedding")).alias("vector")).repartition(3)
    whole = {i: [math.floor(1024 * x) for x in v] for i, v in data}
    assert {r.vec_id: [int(x) for x in r.vector] for r in df.collect()} == whole
    top = 2**63 - 1
    want = []
    for q, v in whole.items():
        best = sorted((-max(-top, min(top, sum(a * b for a, b in zip(v, c, strict=True)))), i) for i, c in whole.items() if i != q)[:4]
        want += [(q, n + 1, i, -s) for n, (s, i) in enumerate(best)]
    got = [(r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(df, df, 4, query_block=3).collect()]
    assert sorted(got) == sorted(want)


def test_top_k_of_large_components_is_exact():
    q, c = np.array([[2.0**40, 1.0]]), np.array([[2.0**20, 3.0]])
    assert topk.exact_scores(q, c, np.array([0]), np.array([0]))[0] == 2**60 + 3


def test_urls(spark):
    rows = [
        ("http://a.example.net/en/x", "a.example.net", "/en/x", "example.net/en/", "allow"), ("https://EXAMPLE.NET/de?x", "example.net", "/de", "net/", "block"),
        ("http://example.com/de/", "example.com", "/de/", "example.com/de/", "block"), ("http://myexample.com/de/", "myexample.com", "/de/", None, "allow"),
        ("x://org/fr/a#b", "org", "/fr/a", "org/fr/", "allow"), ("http://net", "net", "", None, "allow"), ("nothing", "", "", None, "allow"), (None, "", "", None, "allow"),
        ("http://a.net?q=/en/", "a.net", "", None, "allow"), ("http://.net/", ".net", "/", "net/", "block"),
    ]
    df = spark.createDataFrame([(n, r[0], "x") for n, r in enumerate(rows)] * 2, "page_id long, url string, rule string")
    got = sorted(urls.judge(df, urls.rule_table(spark)).collect(), key=lambda r: r.page_id)
    assert [(r.host, r.path, r.rule, r.verdict) for r in got] == [r[1:] for r in rows for _ in range(2)]


def test_urls_of_any_length_and_long_lists(spark):
    """Hosts of many labels, paths and rules of any length, against plain comparison."""
    rng = np.random.default_rng(3)
    part = lambda n: "".join(rng.choice(list("ab/"), n))
    rules = [("block", f"{h}/{part(int(n))}") for h in ("a", "b.a", "a.b", "x." * 70 + "a") for n in rng.integers(0, 12, 12)]
    rules += [("allow", "a/" + "p" * 5000), ("block", "a/" + "p" * 4000), ("block", "a/" + "p" * 1200 + "q"), ("block", "nopath"), ("block", "/nohost"), ("allow", None)]
    urls_of = [f"http://{h}/{part(int(n))}?x" for h in ("a", "b.a", "c.b.a", "a.b", "ba") for n in rng.integers(0, 14, 12)]
    urls_of += ["http://a/" + "p" * n for n in (10, 1200, 4000, 6000)] + ["http://a/" + "p" * 1200 + "qq", "http://" + "x." * 70 + "a/ab", "http://" + "y." * 80 + "b.a/b", "http://" + "z." * 20_000 + "a/b/", None, "http://ü.a/ä"]
    df = spark.createDataFrame([(n, u) for n, u in enumerate(urls_of)], "page_id long, url string").repartition(3)
    listed = {}
    for v, r in rules:
        if r and r.find("/") > 0:
            listed[r] = min(v, listed.get(r, v))
    for r in urls.judge(df, spark.createDataFrame(rules, "verdict string, rule string")).collect():
        fits = [x for x in listed if r.path.startswith(x[x.index("/") :]) and ("." + r.host).endswith("." + x[: x.index("/")])]
        best = max(fits, key=len, default=None)
        assert (r.rule, r.verdict) == (best, listed.get(best, "allow"))


def test_token_counts_and_splices(docs):
    path = vocabulary("word_bpe_49k.json")
    tok = tokens.tokenizer(path)[0]
    got = Counter((r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in tokens.token_counts(docs, path, chunk=5000).collect())
    n = lambda t: len(tok.encode(t or "", add_special_tokens=False).ids)
    assert got == Counter((i, len((t or "").encode()), n(t), n(t) > 2048) for i, t, _ in TEXTS)
    for text in (LONG[:20_000], "a" * 9000 + " b " + "c" * 9000, "Don't 12 'll x's" * 700, "日本語 テスト" * 900, "<|endoftext|> x " * 500, "\x1c\x85ſİ A" * 800, " " * 9000 + "x"):
        whole = tok.encode(text, add_special_tokens=False)
        assert [t[0] for t in tokens.spliced(tok, text, 1000, 16)] == whole.ids
        assert tokens.count(path, text, 10**9) == len(whole.ids)


def test_packing_round_trip(docs):
    import public_tokenizers

    path = vocabulary("byte_bpe_50k.json")
    tok = tokens.tokenizer(path)[0]
    want = Counter()
    for i, t, _ in TEXTS:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [1]
        want[(i, len(ids))] += 1
    frame = packing.packed(docs, path, vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, segments=4)
    rows = frame.collect()
    by = defaultdict(list)
    for r in rows:
        by[r.sequence_id].append(r)
    for pieces in by.values():
        pieces.sort(key=lambda r: r.offset)
        at = 0
        for r in pieces:
            assert r.offset == at
            at += r.length
        assert at == pieces[0].sequence_length <= 2048 and len(pieces) <= 4
    single = {i: tok.encode(t or "", add_special_tokens=False).ids + [1] for i, t, _ in TEXTS if i not in (None, 7)}
    for i, ids in single.items():
        pieces = sorted((r for r in rows if r.doc_id == i), key=lambda r: r.start)
        assert sum(r.length for r in pieces) == len(ids)
        for r in pieces:
            part = np.array(ids[r.start : r.start + r.length], dtype="<u4")
            assert zlib.crc32(part.tobytes()) == r.ids_crc32 and r.doc_tokens == len(ids)
    assert sum(r.length for r in rows) == sum(n * c for (_, n), c in want.items())


def test_packing_keeps_large_and_null_ids(spark):
    rows = [(2**53 + 1, "a b", 1), (None, "c", None), (2**62 + 3, None, 0), (-5, "d", 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, loss_from long").coalesce(1)
    got = packing.packed(df, vocabulary("byte_bpe_50k.json")).collect()
    assert Counter(r.doc_id for r in got) >= Counter(i for i, _, _ in rows)
    assert all(r.loss_tokens == r.length for r in got)  # a column that is not named plays no part
    masked = packing.packed(df, vocabulary("byte_bpe_50k.json"), loss_from="loss_from").collect()
    assert sum(r.length - r.loss_tokens for r in masked) == 3


def test_heuristic_step_finds_the_largest_product():
    rng = np.random.default_rng(5)
    for _ in range(200):
        packer = packing.Packer(2048, 8, 300, 64)
        pieces = []
        for d in range(12):
            n = int(rng.integers(1, 2048))
            loss = (np.arange(n) >= int(rng.integers(0, n + 1))).astype(np.int64)
            pieces.append(packing.Piece(d, 0, np.arange(n, dtype=np.uint32), n, loss))
            packer._hold(pieces[-1])
        last = {}
        for p in pieces:  # the newest of each kind is what a step looks at
            last[packer._kind(len(p.ids)), int(p.loss.sum()) * (packing.SHARES - 1) // len(p.ids)] = p
        left = np.array([int(rng.integers(1, 2048)), 4, int(rng.integers(1, 300))])
        share = left / np.array([2048, 8, 300])
        fits = [float(share @ (len(p.ids) / 2048, 1 / 8, p.loss.sum() / 300)) for p in last.values() if len(p.ids) <= left[0] and p.loss.sum() <= left[2]]
        found = packer._step(left)
        assert (found is None) == (not fits)
        if fits:
            assert share @ (len(found.ids) / 2048, 1 / 8, found.loss.sum() / 300) == pytest.approx(max(fits))


def test_rows_keep_columns_of_any_name(spark):
    """Extra columns named like the helpers of the operators come back with their values."""
    names = ["_id", "_none", "_sha", "_times", "_n", "row", "same", "key", "times", "turn", "name", "rep", "node", "component_id", "score", "held_out"]
    rows = [(n, t, "s", *[f"{c}{n}" for c in names]) for n, t in enumerate(["a b c", "A b c", "d", "one two three", None])]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, " + ", ".join(f"`{c}` string" for c in names))
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for found in (naming.deduplicated(df), jaccard.one_of_each_group(df), mixing.mixed_documents(df), toxicity.clean_documents(df, labels)):
        got = found.collect()
        assert found.columns == df.columns and got
        assert all(r[c] == f"{c}{r.doc_id}" for r in got for c in names)


def test_mixed_rows_that_share_an_id_are_apart(spark):
    rows = [(1, "a b c d", "x"), (1, "e", "y"), (2, "f g", "x"), (None, "h i", "y"), (None, "j", "y")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    want = Counter()
    for r in mixing._mix(df, 17, "session").collect():
        text = next(t for i, t, s in rows if i == r.doc_id and s == r.source and len(t.split()) == r.size)
        want[r.doc_id, text] += int(r.taken / r.size + 0.5)
    assert Counter((r.doc_id, r.text) for r in mixing.mixed_documents(df).collect()) == +want


def test_names_do_not_depend_on_partitions(docs):
    a, b = (sorted((str(r.doc_id), r.text_sha256, str(r.identity)) for r in naming.identities(docs.repartition(n), 100).collect()) for n in (2, 7))
    assert a == b


def test_rank_file_and_library_agree(spark, small):
    import public_tokenizers

    fast = packing.Ids(vocabulary("byte_bpe_50k.json"), vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    slow = packing.Ids(vocabulary("byte_bpe_50k.json"))
    texts = [r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()] + ["<|endoftext|> a", "\x00\x1c\x85  x\n\n y ", "日本語🙂 e\u0301", "a" * 3000]
    for t in texts:
        assert fast(t).tolist() == slow(t).tolist()


@pytest.mark.parametrize("segments,loss", [(3, None), (64, 700), (1, None)])
def test_packing_limits(segments, loss):
    rng = np.random.default_rng(0)
    pieces = []
    for d in range(300):
        n = int(rng.integers(1, 900) if d % 3 else rng.integers(2000, 7000))
        pieces.append(packing.Piece(d, 0, np.arange(n, dtype=np.uint32), n, (np.arange(n) >= n // 2).astype(np.int64)))
    seen, padding, total = defaultdict(int), 0, 0
    for sequence in packing.pack(iter(pieces), segments=segments, loss=loss, pool=64):
        size = sum(len(p.ids) for p in sequence)
        assert 0 < size <= 2048 and len(sequence) <= segments
        assert sum(int(p.loss.sum()) for p in sequence) <= (loss or 2048) or size & (size - 1) == 0
        for p in sequence:
            seen[p.doc] += len(p.ids)
        padding += 0 if size & (size - 1) == 0 else 2048 - size
        total += size
    assert all(seen[p.doc] == len(p.ids) for p in pieces)
    if segments == 64 and loss is None:  # a bound of few segments leaves padding by itself
        assert padding < 0.02 * total


def test_segments_are_maximal():
    rng = np.random.default_rng(2)
    for _ in range(200):
        s = np.round(rng.normal(-0.3, 1, int(rng.integers(0, 25))), 3)
        got = toxicity.segments(s)
        best = max((s[a:b].sum() for a in range(len(s)) for b in range(a + 1, len(s) + 1)), default=0)
        assert max((x[2] for x in got), default=0) == pytest.approx(max(best, 0))
        for b, e, v in got:
            assert v == pytest.approx(s[b:e].sum()) and v > 0
        assert all(a[1] <= b[0] for a, b in zip(got, got[1:], strict=False))


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    detector = toxicity.fit(docs, labels)
    out = toxicity.score(docs, detector).join(labels, "doc_id").where("held_out").toPandas()
    assert ((out["score"] >= 0.5) == (out["predicted"] == 1)).all() and out["score"].between(0, 1).all()
    hit = out[(out["toxic"] == 1)]["predicted"].mean()
    false = out[(out["toxic"] == 0)]["predicted"].mean()
    assert hit > 0.9 and false < 0.01
    odd = spark.createDataFrame([(1, None), (None, ""), (2, "idiot moron trash"), (3, "the of and")], "doc_id long, text string")
    got = {(r.doc_id): r.predicted for r in toxicity.score(odd, detector).collect()}
    assert got == {1: 0, None: 0, 2: 1, 3: 0}
    assert {r.doc_id for r in toxicity.passages(odd, detector).collect()} == {2}


def brute_toxicity(rows, folds, parts):
    """Scores of all texts by plain Python: rows of (doc_id, text, label or None)."""
    words_of = {i: toxicity.terms((t or "").encode()) for i, t, _ in rows}
    train = [(i, y) for i, _, y in rows if y is not None and not folds[i]]

    def weights(taught):
        n, held = Counter(y for _, y in taught), [Counter(), Counter()]
        for i, y in taught:
            held[y].update(set(words_of[i]))
        total, extra, out = n[0] + n[1], toxicity.PRIOR * (n[0] + n[1]), {}
        for w in held[0] | held[1]:
            a = [held[y][w] + extra * (held[0][w] + held[1][w]) / total for y in (0, 1)]
            odds = math.log(a[1] / (n[1] + extra - a[1] + 1e-9)) - math.log(a[0] / (n[0] + extra - a[0] + 1e-9))
            rest = abs(odds) - toxicity.SHRINK * math.sqrt(1 / a[0] + 1 / a[1])
            if rest > 0:
                out[w] = math.copysign(rest, odds)
        return out

    def segment_scores(weight, ws):
        """Repeatedly the best segment that crosses no earlier one, which gives all maximal ones."""
        x, out, todo = [weight.get(w, 0.0) - toxicity.GAP for w in ws], [], [(0, len(ws))]
        while todo:
            b, e = todo.pop()
            best, at, low, low_at, run = 0.0, None, 0.0, b, 0.0
            for j in range(b, e):
                run += x[j]
                if run - low > best:
                    best, at = run - low, (low_at, j + 1)
                if run < low:
                    low, low_at = run, j + 1
            if at:
                out.append(best)
                todo += [(b, at[0]), (at[1], e)]
        return out

    apart = {p: weights([(i, y) for i, y in train if parts[i] != p]) for p in range(toxicity.PARTS)}
    seen = {i: segment_scores(apart[parts[i]], words_of[i]) for i, _ in train}
    clean = [(max(seen[i], default=0.0), max(1, len(words_of[i]))) for i, y in train if not y]

    def likelihood(decay):
        k = sum(s > 0 for s, _ in clean) / sum(n * math.exp(-decay * s) for s, n in clean)
        return sum((math.log(decay * k * n) - decay * s if s > 0 else 0.0) - k * n * math.exp(-decay * s) for s, n in clean), k

    low, high = math.log(1e-3), math.log(64.0)
    for _ in range(200):  # golden section
        x, y = high - 0.618 * (high - low), low + 0.618 * (high - low)
        low, high = (low, y) if likelihood(math.exp(x))[0] > likelihood(math.exp(y))[0] else (x, high)
    decay = math.exp(low)
    k = likelihood(decay)[1]
    chance = lambda s, n: k * n * math.exp(-min(700.0, decay * s))
    evidence = lambda scores, n: math.log1p(sum(math.log(toxicity.LEVEL / max(1e-300, chance(s, n))) for s in scores if chance(s, n) < toxicity.LEVEL))
    slope, offset = toxicity._logistic(np.array([evidence(seen[i], len(words_of[i])) for i, _ in train]), np.array([float(y) for _, y in train]))
    final = weights(train)
    return {i: 1 / (1 + math.exp(-(offset + slope * evidence(segment_scores(final, ws), len(ws))))) for i, ws in words_of.items()}


def test_toxicity_query_against_brute_force(spark):
    from curvature_spark.llm.queries import op7_toxicity

    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    known = {r.doc_id: int(r.toxic) for r in labels.collect()}
    keyed = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(toxicity.PARTS)).alias("part")).collect()
    folds = {r.doc_id: zlib.crc32(str(r.doc_id).encode()) % 5 == 0 for r in keyed}
    want = brute_toxicity([(r.doc_id, r.text, known.get(r.doc_id)) for r in keyed], folds, {r.doc_id: r.part for r in keyed})
    got = op7_toxicity(spark, sf).collect()
    assert {r.doc_id: r.held_out for r in got} == folds and len(got) == len(keyed)
    assert {r.doc_id: r.score for r in got} == pytest.approx(want, abs=1e-4)
    assert sum(r.predicted for r in got) > 20


def test_extreme_value_law_is_recovered():
    rng = np.random.default_rng(6)
    n = rng.integers(50, 2000, 20_000).astype(float)
    decay, k = 1.7, 0.004
    best = np.maximum(0.0, np.log(-k * n / np.log(rng.random(len(n)))) / decay)  # inverse of exp(-k n exp(-decay s))
    assert toxicity.extreme_value_law(best, n) == pytest.approx((decay, k), rel=0.05)


def brute_forward(model, symbols):
    state, total = model.start * model.emit[symbols[0]], 0.0
    for s in symbols[1:]:
        total += math.log(state.sum())
        state = (state / state.sum()) @ model.step * model.emit[s]
    return total + math.log(state.sum())


def random_model(states=3, symbols=6, seed=0):
    rng = np.random.default_rng(seed)
    start, step, emit = rng.random(states), rng.random((states, states)), rng.random((symbols, states))
    return hmm.Model(start / start.sum(), step / step.sum(axis=1, keepdims=True), emit / emit.sum(axis=0))


def test_forward_is_exact(monkeypatch):
    model = random_model()
    rng = np.random.default_rng(4)
    seqs = [rng.integers(0, 6, int(n)) for n in (1, 2, 5, 40, 3, 200, 97)]
    want = [brute_forward(model, s) for s in seqs]
    assert hmm.forward(model, seqs) == pytest.approx(want)
    monkeypatch.setattr(hmm, "LONG", 10)
    monkeypatch.setattr(hmm, "SEGMENT", 8)
    assert hmm.forward(model, seqs) == pytest.approx(want)


def test_expected_counts_by_enumeration():
    import itertools

    model = random_model(2, 3, 1)
    windows = [np.array([0, 2, 1]), np.array([1]), np.array([2, 2])]
    start, step, emit, like = hmm.expected_counts(model, windows, np.array([True, True, False]))
    s2, t2, e2, total = np.zeros(2), np.zeros((2, 2)), np.zeros((3, 2)), 0.0
    for w, begins in zip(windows, (True, True, False), strict=True):
        paths = {}
        for path in itertools.product(range(2), repeat=len(w)):
            p = model.start[path[0]] * model.emit[w[0], path[0]]
            for a, b, o in zip(path, path[1:], w[1:], strict=False):
                p *= model.step[a, b] * model.emit[o, b]
            paths[path] = p
        z = sum(paths.values())
        total += math.log(z)
        for path, p in paths.items():
            s2[path[0]] += begins * p / z
            for a, b in zip(path, path[1:], strict=False):
                t2[a, b] += p / z
            for x, o in zip(path, w, strict=True):
                e2[o, x] += p / z
    assert start == pytest.approx(s2) and step == pytest.approx(t2) and emit == pytest.approx(e2) and like == pytest.approx(total)


def test_language_model_query(spark, docs, small, monkeypatch):
    monkeypatch.setattr(hmm, "HEAD", 200)  # most words then meet their counts in the join
    table = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang")
    table = table.unionByName(docs.select("doc_id", "text", "lang"))
    rows = hmm.score(table, rounds=3).collect()
    texts = table.collect()
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    counts = Counter()
    for r in texts:
        if not held(r.doc_id):
            counts.update([*words(r.text), None])
    total, types = sum(counts.values()), len(counts)
    want = Counter()
    for r in texts:
        seq = [*words(r.text), None]
        base = sum(math.log10((counts[w] + 1) / (total + types + 1)) for w in seq)
        want[(r.doc_id, held(r.doc_id), len(seq), sum(counts[w] > 0 for w in seq), total, round(base, 4))] += 1
    assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in rows) == want
    assert all(r.score < 0 for r in rows)


@pytest.mark.parametrize("head", [1, 4, 100])
def test_ends_of_few_long_texts_are_counted(spark, monkeypatch, head):
    """Words more frequent than texts: the end of a text is then in no bin that is broadcast."""
    monkeypatch.setattr(hmm, "HEAD", head)
    texts = [(0, "a b c " * 40 + "once"), (1, "a b c d " * 30), (2, "b a"), (4, "unseen a")]
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i, _ in texts}
    counts = Counter(w for i, t in texts if not held[i] for w in [*words(t), None])
    total, types = sum(counts.values()), len(counts)
    rows = {r.doc_id: r for r in hmm.score(spark.createDataFrame(texts, "doc_id long, text string"), rounds=1).collect()}
    assert 0 < counts[None] < counts[b"a"]
    for i, t in texts:
        seq = [*words(t), None]
        assert rows[i].n_known == sum(counts[w] > 0 for w in seq)
        assert rows[i].base_score == pytest.approx(sum(math.log10((counts[w] + 1) / (total + types + 1)) for w in seq))


def test_language_model_beats_its_base_on_held_out_texts(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = hmm.score(docs).where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert got[0] > got[1]


def test_word_probabilities_of_a_class_sum_to_one():
    types, sizes = np.zeros(hmm.CLASSES + 1), np.zeros(hmm.CLASSES + 1)
    k = hmm.class_of(b"a")
    types[k], sizes[k] = 1, 5
    r = hmm.Resolver({b"a": 5}, 6, 2, sizes, types)
    assert 10 ** r[b"a"][2] + 1 / (5 + 1 + 1) == pytest.approx(1.0)
