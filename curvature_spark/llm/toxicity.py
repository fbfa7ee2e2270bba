"""Toxic passages by maximum-scoring segment search.

Terms get log-odds of occurring in toxic against clean training texts with an informative Dirichlet prior (the pooled
corpus), drawn towards zero by two standard errors and keeping their sign: a term that speaks for clean text costs its
log-odds. Every term, known or not, costs GAP besides, so that scores of clean text drift down. A linear scan finds all
maximal scoring segments of a text. Their scores on clean text follow an extreme-value law, expected number K n exp(-decay S) at
or above S in n terms; K and decay are fitted by maximum likelihood to the best segments of clean texts. Segments
below the significance level count; a text's evidence is the logarithm of one plus the sum of their excess, and a
one-dimensional logistic fit turns evidence into a probability.

The law and the logistic fit see every training text through terms learned from the other folds, never from the text itself;
the terms that score are then learned from all folds. A term counts once a text, which a long text cannot outvote.

Training reads at most SAMPLE labelled texts, those with the smallest hash of the id; scoring reads every whole text.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cuts import written
from .memory import lean

#: Labelled training texts at most: a broadcast of 20,000 pairs.
SAMPLE = 20_000
#: Texts the prior stands for, as a share of the training texts.
PRIOR = 0.1
#: Standard errors by which log-odds are drawn towards zero.
SHRINK = 2.0
#: What every term costs.
GAP = 0.4
LEVEL = 0.05
FOLDS = 5
#: Parts of the training texts of which one at a time is scored by the terms of the others.
PARTS = 4
#: Distinct terms a counting task holds before it sends their counts on.
FLUSH = 50_000
#: Bytes that separate terms: ASCII other than letters; A to Z become a to z.
LETTERS = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def terms(raw: bytes | None) -> list[bytes]:
    """Terms of a text: runs of letters and non-ASCII characters, lower-cased."""
    return raw.translate(LETTERS).split() if raw else []


def held_out(doc_id: Column) -> Column:
    """Whether crc32(doc_id as text) mod 5 is 0; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))), F.lit(FOLDS)) == 0


def segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (begin, end, score) of `scores`, in linear time.

    Works on runs: neighbouring positive scores are one run, what lies between two runs is one cost.
    """
    at = np.nonzero(scores > 0)[0]
    if not len(at):
        return []
    running = np.concatenate([[0.0], np.cumsum(scores)])
    breaks = np.nonzero(np.diff(at) > 1)[0]
    begins, ends = at[np.concatenate([[0], breaks + 1])], at[np.concatenate([breaks, [len(at) - 1]])] + 1
    # A candidate is (begin, end, sum before begin, sum at end, the nearest earlier one with a smaller sum before).
    held: list[tuple[int, int, float, float, int]] = []
    for b, e in zip(begins.tolist(), ends.tolist(), strict=True):
        low, high = float(running[b]), float(running[e])
        while True:
            j = len(held) - 1
            while j >= 0 and held[j][2] >= low:
                j = held[j][4]
            if j < 0 or held[j][3] >= high:
                held.append((b, e, low, high, j))
                break
            b, low = held[j][0], held[j][2]
            del held[j:]
    return [(b, e, high - low) for b, e, low, high, _ in held]


def evidence_of(found: list[tuple[int, int, float, float]]) -> float:
    """ln(1 + sum over significant segments of ln(LEVEL / chance)): long texts stay comparable without a bound."""
    return math.log1p(sum(math.log(LEVEL / max(chance, 1e-300)) for _, _, _, chance in found))


class Detector:
    """Term scores, the extreme-value law of clean text and the calibration."""

    def __init__(self, weights: dict[bytes, float], decay: float, scale: float, slope: float = 1.0, offset: float = 0.0):
        self.weights, self.decay, self.scale, self.slope, self.offset = weights, decay, scale, slope, offset

    def passages(self, raw: bytes | None) -> list[tuple[int, int, float, float]]:
        """(first term, end term, score, expected number by chance) of every significant segment."""
        words = terms(raw)
        get = self.weights.get
        scores = np.array([get(w, 0.0) for w in words]) - GAP
        found = []
        for b, e, s in segments(scores):
            chance = self.scale * len(words) * math.exp(-min(700.0, self.decay * s))
            if chance < LEVEL:
                found.append((b, e, s, chance))
        return found

    def evidence(self, raw: bytes | None) -> float:
        return evidence_of(self.passages(raw))

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.offset + self.slope * evidence, -30, 30)))


def extreme_value_law(best: np.ndarray, size: np.ndarray) -> tuple[float, float]:
    """Decay and K of the largest likelihood for best segment scores of clean texts of `size` terms, 0 where none is positive.

    A best score is at most S with probability exp(-K n exp(-decay S)). For a given decay the best K is the number of
    positive scores over the sum of n exp(-decay S), which leaves one equation for the decay.
    """
    n, seen = np.maximum(1.0, size), best > 0
    if not seen.any():
        return 1.0, 1.0 / max(1.0, float(n.sum()))

    def slope(decay: float) -> float:
        e = n * np.exp(-decay * best)
        return 1 / decay - float(best[seen].mean()) + float((best * e).sum() / e.sum())

    low, high = 1e-3, 64.0
    for _ in range(80):
        mid = math.sqrt(low * high)
        low, high = (mid, high) if slope(mid) > 0 else (low, mid)
    return low, float(seen.sum() / (n * np.exp(-low * best)).sum())


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset of a lightly penalised logistic fit."""
    a = np.stack([x, np.ones_like(x)], axis=1)
    theta = np.array([0.1, -2.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ theta, -30, 30)))
        g = a.T @ (p - y) + 1e-2 * theta
        h = (a * (p * (1 - p))[:, None]).T @ a + 1e-2 * np.eye(2)
        step = np.linalg.solve(h, g)
        theta = theta - step
        if np.abs(step).max() < 1e-9:
            break
    return float(max(theta[0], 1e-3)), float(theta[1])


def log_odds(toxic: Column, clean: Column, n1: float, n0: float) -> Column:
    """Shrunken log-odds of a term from the texts that hold it, `n1` toxic and `n0` clean ones in all."""
    weight = PRIOR * (n0 + n1)
    prior = weight * (toxic + clean) / F.lit(max(1.0, n0 + n1))
    a1, a0 = toxic + prior, clean + prior
    odds = F.log(a1 / (n1 + weight - a1 + 1e-9)) - F.log(a0 / (n0 + weight - a0 + 1e-9))
    rest = F.abs(odds) - SHRINK * F.sqrt(1 / a1 + 1 / a0)
    return F.when((rest > 0) & (toxic + clean > 0), F.signum(odds) * rest).otherwise(0.0)


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, owner: str = "session") -> Detector:
    """A detector from labelled rows of the training folds.

    labels needs doc_id and toxic; rows whose id is null or whose label is null teach nothing, of several labels of
    one id the larger holds, of several texts of one id the least. Without both classes every score is that of the one
    there is; without any, 0.
    """
    spark = docs.sparkSession
    taught = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    chosen = taught.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    texts = docs.select("doc_id", F.col("text").cast("binary").alias("raw")).join(F.broadcast(chosen), "doc_id")
    texts = written(texts.select("doc_id", "raw", "toxic", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(PARTS)).cast("int").alias("part")), "toxic-texts", owner)
    # Texts move only where an id has several.
    if not texts.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        texts = written(texts.groupBy("doc_id", "toxic", "part").agg(F.min("raw").alias("raw")), "toxic-texts", owner)
    texts = texts.select("raw", "toxic", "part")

    def count(batches):
        held: list[dict[bytes, int]] = [{} for _ in range(2 * PARTS)]  # by part and label; the empty term counts texts
        for batch in batches:
            for raw, y, part in zip(batch.column("raw"), batch.column("toxic").to_pylist(), batch.column("part").to_pylist(), strict=True):
                own = held[2 * part + (y > 0)]
                own[b""] = own.get(b"", 0) + 1
                for w in set(terms(raw.as_py())):
                    own[w] = own.get(w, 0) + 1
                if len(own) > FLUSH:
                    yield counted(part, y > 0, own)
                    own.clear()
        for n, own in enumerate(held):
            if own:
                yield counted(n // 2, n % 2 > 0, own)

    def counted(part, toxic, own):
        n, none = pa.array(list(own.values()), pa.int64()), pa.array(np.zeros(len(own), dtype=np.int64))
        return pa.RecordBatch.from_arrays([pa.array(list(own), pa.binary()), pa.array(np.full(len(own), part, dtype=np.int32)), none if toxic else n, n if toxic else none], ["term", "part", "clean", "toxic"])

    of_part = lambda c, p: F.sum(F.when(F.col("part") == p, F.col(c)).otherwise(0)).alias(f"{c}{p}")
    table = texts.mapInArrow(lean(count), "term binary, part int, clean long, toxic long").groupBy("term").agg(*[of_part(c, p) for c in ("clean", "toxic") for p in range(PARTS)])
    table = written(table, "toxic-terms", owner)
    got = table.where(F.length("term") == 0).first()
    n0, n1 = ([int(got[f"{c}{p}"]) for p in range(PARTS)] if got else [0] * PARTS for c in ("clean", "toxic"))
    if not sum(n0) or not sum(n1):
        return Detector({}, 1.0, 1.0, 1.0, 30.0 if sum(n1) else -30.0)

    def scored(without: int | None) -> Column:
        """Log-odds from all parts but one."""
        kept = [p for p in range(PARTS) if p != without]
        total = lambda c: sum((F.col(f"{c}{p}") for p in kept), F.lit(0))
        return log_odds(total("toxic"), total("clean"), float(sum(n1[p] for p in kept)), float(sum(n0[p] for p in kept)))

    # Terms whose log-odds pass their error: as many as the words of `sample` texts have, whatever the corpus.
    rated = table.where(F.length("term") > 0).select("term", scored(None).alias("all"), F.array(*[scored(p) for p in range(PARTS)]).alias("others"))
    kept = rated.where((F.col("all") != 0) | F.exists("others", lambda s: s != 0)).collect()
    apart = [Detector({bytes(r.term): r.others[p] for r in kept if r.others[p]}, 1.0, 1.0) for p in range(PARTS)]
    sent = spark.sparkContext.broadcast(apart)

    def rate(batches):
        for pdf in batches:
            best, size = [], []
            for raw, part in zip(pdf["raw"], pdf["part"], strict=True):
                words = terms(raw)
                get = sent.value[part].weights.get
                best.append(max((s for _, _, s in segments(np.array([get(w, 0.0) for w in words]) - GAP)), default=0.0))
                size.append(len(words))
            yield pd.DataFrame({"best": best, "size": size, "toxic": pdf["toxic"].astype("int64")})

    # At most `sample` rows of three numbers.
    tops = texts.mapInPandas(lean(rate), "best double, size long, toxic long").toPandas()
    clean = tops[tops["toxic"] == 0]
    decay, scale = extreme_value_law(clean["best"].to_numpy(), clean["size"].to_numpy(dtype=float))

    def weigh(batches):
        for pdf in batches:
            yield pd.DataFrame({"x": [Detector(sent.value[part].weights, decay, scale).evidence(raw) for raw, part in zip(pdf["raw"], pdf["part"], strict=True)], "toxic": pdf["toxic"].astype("double")})

    found = texts.mapInPandas(lean(weigh), "x double, toxic double").toPandas()
    slope, offset = _logistic(found["x"].to_numpy(), (found["toxic"] > 0).to_numpy(dtype=float))
    return Detector({bytes(r.term): r["all"] for r in kept if r["all"]}, decay, scale, slope, offset)


def score(docs: DataFrame, detector: Detector) -> DataFrame:
    """One row per row of `docs`: doc_id, held_out, score, predicted, n_passages.

    docs needs doc_id and text; nothing but the text enters the score. Null and empty texts have no passages
    and the score of that; repeated rows are scored each. An empty table gives no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(detector)

    def work(batches):
        d = sent.value
        for batch in batches:
            found = [d.passages(raw) for raw in batch.column("raw").to_pylist()]
            p = d.probability(np.array([evidence_of(f) for f in found]))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p, pa.float64()), pa.array([len(f) for f in found], pa.int64())], ["doc_id", "held_out", "score", "n_passages"])

    kind = dict(docs.dtypes)["doc_id"]
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("binary").alias("raw"))
    out = rows.mapInArrow(lean(work), f"doc_id {kind}, held_out boolean, score double, n_passages long")
    return out.select("doc_id", "held_out", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_passages")


def passages(docs: DataFrame, detector: Detector) -> DataFrame:
    """doc_id, first_term, end_term, passage_score, chance of every significant passage of every text."""
    sent = docs.sparkSession.sparkContext.broadcast(detector)

    def work(batches):
        for batch in batches:
            found = [sent.value.passages(raw) for raw in batch.column("raw").to_pylist()]
            owner = pa.array(np.repeat(np.arange(len(found)), [len(f) for f in found]), pa.int64())
            flat = list(zip(*[p for f in found for p in f], strict=True)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(owner), pa.array(flat[0], pa.int64()), pa.array(flat[1], pa.int64()), pa.array(flat[2], pa.float64()), pa.array(flat[3], pa.float64())],
                ["doc_id", "first_term", "end_term", "passage_score", "chance"],
            )

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", F.col("text").cast("binary").alias("raw")).mapInArrow(lean(work), f"doc_id {kind}, first_term long, end_term long, passage_score double, chance double")


def clean_documents(docs: DataFrame, labels: DataFrame, owner: str = "session") -> DataFrame:
    """`docs` without the texts predicted toxic; columns as they come, one pass over the texts after training."""
    detector = fit(docs, labels, owner=owner)
    sent = docs.sparkSession.sparkContext.broadcast(detector)

    def work(batches):
        d = sent.value
        for batch in batches:
            x = np.array([d.evidence(raw) for raw in batch.column("text").cast(pa.binary()).to_pylist()])
            yield batch.filter(pa.array(d.probability(x) < 0.5, pa.bool_()))

    return docs.mapInArrow(lean(work), docs.schema)
