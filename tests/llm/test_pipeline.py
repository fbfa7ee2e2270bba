"""The pipeline, stage by stage on its own input, against plain Python."""

import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline as pipeline
from curvature_spark.llm import mixing, tokens, toxicity
from curvature_spark.llm.queries import vocabulary

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.fixture(scope="module")
def stages(spark, small, tmp_path_factory):
    """Input and output of every stage, written and read again as the contract has it."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    extra = spark.createDataFrame([(9001, None, "en", "src0", 0), (9002, "", "en", None, 0), (9003, "a b", None, "src1", None), (9003, "a b", None, "src1", None), (None, "A B", "en", "src1", 3)], docs.schema)
    docs, found = docs.unionByName(extra), []
    for name, stage in pipeline.STAGES:
        path = str(tmp_path_factory.mktemp("stage") / "out")
        stage(spark, docs, small).write.parquet(path)
        out = spark.read.parquet(path)
        found.append((name, docs, out))
        docs = out
    return found


def rows(df):
    return [tuple(r) for r in df.select("doc_id", "text", "source").collect()]


def test_columns_stay(stages):
    for _, docs, out in stages[:-1]:
        assert out.columns == docs.columns


def test_toxic_texts_go(spark, small, stages):
    _, docs, out = stages[0]
    detector = toxicity.fit(docs, spark.read.parquet(f"{small}/labels.parquet"))
    want = [r for r in rows(docs) if detector.probability(np.array([detector.evidence(None if r[1] is None else r[1].encode())]))[0] < 0.5]
    assert Counter(rows(out)) == Counter(want)


def test_toxic_texts_go_and_clean_ones_stay_where_labels_teach(spark):
    """The ten toxic texts among the smallest table's labels teach nothing that holds for others; those of the next do."""
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r.doc_id for r in pipeline.drop_toxic(spark, docs, sf).select("doc_id").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert all(i in kept for i, y in labels.items() if not y)
    assert sum(i not in kept for i, y in labels.items() if y) > 0.6 * sum(labels.values())


def test_one_of_each_exact_group_stays(stages):
    _, docs, out = stages[1]
    groups = defaultdict(list)
    for i, t, _ in rows(docs):
        groups[(t or "").translate(LOWER)].append(i)
    want = Counter(max((i for i in ids if i is not None), default=None) for ids in groups.values())
    assert Counter(r[0] for r in rows(out)) == want


def test_one_of_each_near_group_stays(stages):
    _, docs, out = stages[2]

    def grams(t):
        w = (t or "").encode().lower().split()
        return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()

    sets = [(i, grams(t)) for i, t, _ in rows(docs)]
    root = {i: i for i, _ in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for n, (i, a) in enumerate(sets):
        for j, b in sets[:n]:
            if i is not None and j is not None and a and b and 5 * len(a & b) >= 4 * len(a | b):
                p, q = sorted((find(i), find(j)))
                root[q] = p
    assert Counter(r[0] for r in rows(out)) == Counter(i for i, _ in sets if i is None or find(i) == i)


def test_documents_are_repeated_as_the_mix_takes_them(stages):
    _, docs, out = stages[3]
    want = Counter()
    for r in mixing.mix(docs).collect():
        if r.size:
            want[r.doc_id] += int(r.taken / r.size + 0.5)
    assert Counter(r[0] for r in rows(out)) == +want
    size, target = Counter(), {}
    for r in mixing.mix(docs).collect():
        size[r.source] += r.taken
        target[r.source] = r.target
    assert all(abs(size[s] - target[s]) <= 1 for s in target)


def test_pieces_cover_every_document(stages):
    _, docs, out = stages[4]
    tok = tokens.tokenizer(vocabulary("byte_bpe_50k.json"))[0]
    want, pieces = Counter(), Counter()
    whole = {}
    for i, t, _ in rows(docs):
        whole[i] = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], dtype="<u4")
        want[i] += len(whole[i])
    for r in out.collect():
        pieces[r.doc_id] += r.length
        assert zlib.crc32(whole[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32
    assert pieces == want


def test_run_is_the_stages_in_order(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    total = pipeline.run(spark, small).groupBy().sum("length").first()[0]
    for _, stage in pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, small).collect(), docs.schema)
    tok = tokens.tokenizer(vocabulary("byte_bpe_50k.json"))[0]
    assert total == sum(len(tok.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in docs.collect())
