"""A hidden Markov language model: Baum-Welch over partitions, exact likelihood by scaled forward recursion.

A latent state emits one of CLASSES word classes (a checksum of the word), the class emits the word:

    P(text) = sum over state paths of start * transitions * P(class | state)  *  product of P(word | class)

The second factor does not depend on the path, so it is a sum per document over exact word counts; the
first needs one table of STATES x CLASSES numbers, whose size does not grow with the corpus. The end of a
text is a token with a class of its own.

Word counts cover all training texts and stay a distributed table. The most frequent HEAD words go out
with their counts and are resolved where the texts are read; every other word of a document meets its count
in a join, so no word is left out. Class sequences are written once; every round of Baum-Welch
reads them, sums expected counts per task, and combines them per class before they reach the driver.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cuts import written
from .words import lowered_words

CLASSES, END = 1 << 14, 1 << 14
STATES, ROUNDS = 8, 6
#: Most frequent words that are broadcast with their counts.
HEAD = 100_000
#: Training texts are cut to windows of this many tokens; scoring takes whole texts.
WINDOW = 256
#: Tokens whose state probabilities are in memory at once.
TOGETHER = 1 << 18
#: Tokens from which on a text is scored by segments side by side.
LONG, SEGMENT = 1 << 15, 1 << 11
FLUSH = 300_000
#: Texts encoded at once.
SLICE = 500
HELD_OUT, FOLDS = 2, 7


def held_out(doc_id: Column) -> Column:
    """Whether crc32(doc_id as text) mod 7 is 2; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))), F.lit(FOLDS)) == HELD_OUT


def class_of(word: bytes) -> int:
    return zlib.crc32(word) & (CLASSES - 1)


class Model:
    """start (S), step (S x S) and emit (CLASSES + 1 x S) probabilities."""

    def __init__(self, start: np.ndarray, step: np.ndarray, emit: np.ndarray):
        self.start, self.step, self.emit = start, step, emit

    @classmethod
    def initial(cls, shares: np.ndarray, states: int, seed: int) -> Model:
        """Sticky states whose emissions are the class shares, each scaled by a random factor."""
        rng = np.random.default_rng(seed)
        emit = shares[:, None] * rng.gamma(1.0, size=(len(shares), states))
        step = np.full((states, states), 0.1 / max(1, states - 1))
        np.fill_diagonal(step, 0.9 if states > 1 else 1.0)
        return cls(np.full(states, 1 / states), step, emit / emit.sum(axis=0))


def time_major(sequences: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order by falling length; symbols by time, within a time by that order; sequences alive at each time."""
    lengths = np.array([len(s) for s in sequences])
    order = np.argsort(-lengths, kind="stable")
    flat = np.concatenate([sequences[i] for i in order]) if len(sequences) else np.empty(0, dtype=np.int64)
    lengths = lengths[order]
    starts = np.cumsum(lengths) - lengths
    alive = np.searchsorted(-lengths, -np.arange(lengths[0] if len(lengths) else 0), side="left")
    symbols = np.concatenate([flat[starts[:n] + t] for t, n in enumerate(alive)]) if len(alive) else flat
    return order, symbols.astype(np.int64), alive


def forward(model: Model, sequences: list[np.ndarray]) -> np.ndarray:
    """Natural log likelihood of each whole sequence."""
    out = np.zeros(len(sequences))
    short = [i for i, s in enumerate(sequences) if len(s) <= LONG]
    for i, s in enumerate(sequences):
        if len(s) > LONG:
            out[i] = _forward_long(model, s)
    step = model.step.T.copy()
    for part in _parts(sequences, short):
        order, symbols, alive = time_major([sequences[i] for i in part])
        logs, at, state = np.zeros(len(part)), 0, None
        for n in alive:
            # One column a sequence: sums over states are sums of long rows.
            seen = model.emit[symbols[at : at + n]].T
            state = (model.start[:, None] if state is None else step @ state[:, :n]) * seen
            scale = state.sum(axis=0)
            logs[:n] += np.log(scale)
            state /= scale
            at += n
        out[np.array(part)[order]] = logs
    return out


def _forward_long(model: Model, s: np.ndarray) -> float:
    """The same recursion for one very long text: the segments' transfer matrices side by side, then their product."""
    states = len(model.start)
    head = model.start * model.emit[s[0]]
    total = math.log(head.sum())
    head = head / head.sum()
    rest = s[1:]
    cut = len(rest) // SEGMENT * SEGMENT
    if cut:
        columns = rest[:cut].reshape(-1, SEGMENT)
        rows = np.tile(np.eye(states), (len(columns), 1))
        logs = np.zeros(len(rows))
        for t in range(SEGMENT):
            rows = (rows @ model.step) * np.repeat(model.emit[columns[:, t]], states, axis=0)
            scale = rows.sum(axis=1)
            logs += np.log(scale)
            rows /= scale[:, None]
        for matrix, scales in zip(rows.reshape(-1, states, states), logs.reshape(-1, states), strict=True):
            top = scales.max()
            head = (head * np.exp(scales - top)) @ matrix
            total += top + math.log(head.sum())
            head /= head.sum()
    for symbol in rest[cut:]:
        head = (head @ model.step) * model.emit[symbol]
        total += math.log(head.sum())
        head /= head.sum()
    return total


def _parts(sequences: list[np.ndarray], which: list[int]) -> Iterable[list[int]]:
    """Numbers of sequences, by falling length, TOGETHER tokens or one sequence at a time."""
    part, held = [], 0
    for i in sorted(which, key=lambda i: -len(sequences[i])):
        if part and held + len(sequences[i]) > TOGETHER:
            yield part
            part, held = [], 0
        part.append(i)
        held += len(sequences[i])
    if part:
        yield part


def expected_counts(model: Model, windows: list[np.ndarray], first: np.ndarray, dtype=None) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Expected start, step and emission counts of the windows, and their log likelihood.

    first tells windows that begin a text: only those count towards the start. dtype may ask for single
    precision, which the scaled recursions bear in training.
    """
    states = len(model.start)
    start, step, emit, like = np.zeros(states), np.zeros((states, states)), np.zeros_like(model.emit), 0.0
    exact = model.step.dtype if dtype is None else dtype
    forth, back, table, first_state = model.step.T.astype(exact), model.step.astype(exact), model.emit.astype(exact), model.start.astype(exact)[:, None]
    for part in _parts(windows, list(range(len(windows)))):
        order, symbols, alive = time_major([windows[i] for i in part])
        begins = first[np.array(part)[order]]
        seen = np.ascontiguousarray(table[symbols].T)
        ends = np.cumsum(alive)
        alpha, scales = np.empty_like(seen), np.empty(len(symbols), dtype=exact)
        state, at = None, 0
        for n in alive.tolist():
            state = (first_state if state is None else forth @ state[:, :n]) * seen[:, at : at + n]
            scale = state.sum(axis=0)
            state /= scale
            alpha[:, at : at + n], scales[at : at + n] = state, scale
            at += n
        like += float(np.log(scales.astype(np.float64)).sum())
        seen /= scales
        beta = np.ones((states, int(alive[-1])), dtype=exact)
        pairs = np.zeros((states, states), dtype=exact)
        for t in range(len(alive) - 1, -1, -1):
            n, at = int(alive[t]), int(ends[t]) - int(alive[t])
            if beta.shape[1] < n:
                beta = np.concatenate([beta, np.ones((states, n - beta.shape[1]), dtype=exact)], axis=1)
            if t:
                arriving = seen[:, at : at + n] * beta
                before = int(ends[t - 1]) - int(alive[t - 1])
                pairs += alpha[:, before : before + n] @ arriving.T
            alpha[:, at : at + n] *= beta  # the states' probabilities from here on
            if t:
                beta = back @ arriving
        step += pairs
        start += alpha[:, : len(part)][:, begins].sum(axis=1)
        for s in range(states):
            emit[:, s] += np.bincount(symbols, weights=alpha[s], minlength=len(emit))
    return start, step * model.step, emit, like


def _word_counts(train: DataFrame, owner: str) -> DataFrame:
    """word, c over all texts; the end of a text is the empty word. Counted per task before the shuffle."""

    def work(batches):
        held: Counter = Counter()
        for pdf in batches:
            for raw in pdf["raw"]:
                held.update(lowered_words(raw))
                held[b""] += 1
                if len(held) > FLUSH:
                    yield pd.DataFrame({"word": list(held.keys()), "c": list(held.values())})
                    held = Counter()
        yield pd.DataFrame({"word": list(held.keys()), "c": list(held.values())})

    parts = train.select("raw").mapInPandas(work, "word binary, c long")
    return written(parts.groupBy("word").agg(F.sum("c").alias("c")), "lm-words", owner)


def _frequent(counts: DataFrame) -> dict[bytes, int]:
    """Words and counts from some count on, HEAD of them at most.

    The count comes from a histogram on a logarithmic scale, so only words that are kept reach the driver.
    """
    size = F.floor(8 * F.log2("c")).cast("int")
    least, held = None, 0
    for k, n in sorted(((r.k, r.n) for r in counts.groupBy(size.alias("k")).agg(F.count(F.lit(1)).alias("n")).collect()), reverse=True):
        held += n
        if held > HEAD:
            break
        least = k
    return {} if least is None else {bytes(r.word): r.c for r in counts.where(size >= least).collect()}


class Resolver(dict):
    """word -> (class, log10 base probability, log10 P(word | class)); words outside the head have no logs."""

    def __init__(self, head: dict[bytes, int], tokens: int, types: int, class_tokens: np.ndarray, class_types: np.ndarray):
        super().__init__()
        self.head, self.total = head, tokens + types + 1
        self.class_total = class_tokens + class_types + 1

    def __missing__(self, word: bytes):
        if len(self) > FLUSH:
            self.clear()
        k = END if word == b"" else class_of(word)
        c = self.head.get(word)
        if c is None:
            found = (k, None, 0.0)
        else:
            found = (k, math.log10((c + 1) / self.total), 0.0 if k == END else math.log10((c + 1) / self.class_total[k]))
        self[word] = found
        return found


def score(docs: DataFrame, states: int = STATES, rounds: int = ROUNDS, seed: int = 5, owner: str = "session") -> DataFrame:
    """One row per row of `docs`: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    docs needs doc_id and text; other columns are ignored. Null and empty texts are the end token alone; repeated
    rows are scored, and counted in training, each. Without training texts every word is unknown and the states
    keep their initial emissions. An empty table gives no rows.
    """
    sc = docs.sparkSession.sparkContext
    raw = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("binary").alias("raw"))
    counts = _word_counts(raw.where(~F.col("held_out")), owner)
    texts_ended = F.sum(F.when(F.length("word") == 0, F.col("c")))
    n_tokens, n_types, ends = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1)), F.coalesce(texts_ended, F.lit(0))).first()
    class_column = F.crc32("word").bitwiseAND(F.lit(CLASSES - 1)).cast("int")
    class_tokens, class_types = np.zeros(CLASSES + 1), np.zeros(CLASSES + 1)
    for k, c, v in counts.where(F.length("word") > 0).groupBy(class_column.alias("k")).agg(F.sum("c"), F.count(F.lit(1))).collect():
        class_tokens[k], class_types[k] = c, v
    # The end of a text is resolved from the head alone, however rare it is among the words.
    head = _frequent(counts) | {b"": ends}
    sent = sc.broadcast((head, n_tokens, n_types, class_tokens, class_types))

    def encode(batches):
        words, base, row = Resolver(*sent.value), TaskContext.get().partitionId() << 33, 0
        for whole in batches:
            for at in range(0, whole.num_rows, SLICE):
                batch = whole.slice(at, SLICE)
                numbers, logs, symbols, tail_words, tail_counts, ends_at = [], [], [], [], [], [0]
                for text in batch.column("raw").to_pylist():
                    seen = [*lowered_words(text), b""]
                    found = list(map(words.__getitem__, seen))
                    base_logs = [x[1] for x in found if x[1] is not None]
                    if len(base_logs) < len(found):
                        for w, n in Counter(w for w, x in zip(seen, found, strict=True) if x[1] is None).items():
                            tail_words.append(w)
                            tail_counts.append(n)
                    ends_at.append(len(tail_words))
                    numbers.append((len(found), len(base_logs) - (0 if ends else 1)))
                    logs.append((sum(base_logs), sum(x[2] for x in found)))
                    symbols.append(np.array([x[0] for x in found], dtype="<u2").tobytes())
                tail = pa.ListArray.from_arrays(pa.array(ends_at, pa.int32()), pa.StructArray.from_arrays([pa.array(tail_words, pa.binary()), pa.array(tail_counts, pa.int64())], ["word", "n"]))
                made = [pa.array(np.arange(base + row, base + row + batch.num_rows), pa.int64()), batch.column("doc_id"), batch.column("held_out")]
                made += [pa.array([x[i] for x in numbers], pa.int64()) for i in (0, 1)] + [pa.array([x[i] for x in logs], pa.float64()) for i in (0, 1)]
                yield pa.RecordBatch.from_arrays([*made, pa.array(symbols, pa.binary()), tail], ["row_no", "doc_id", "held_out", "n_tokens", "known", "base_log", "class_log", "symbols", "tail"])
                row += batch.num_rows

    kind = dict(docs.dtypes)["doc_id"]
    encoded = written(
        raw.mapInArrow(encode, f"row_no long, doc_id {kind}, held_out boolean, n_tokens long, known long, base_log double, class_log double, symbols binary, tail array<struct<word: binary, n: long>>"),
        "lm-texts",
        owner,
    )

    # Words outside the head: each meets its count, then sums per document.
    total = float(n_tokens + n_types + 1)
    sizes = [float(x) for x in class_tokens + class_types + 1]
    tail = encoded.select("row_no", F.explode("tail").alias("t")).select("row_no", "t.word", "t.n")
    met = tail.join(counts, "word", "left")
    c = F.coalesce(F.col("c"), F.lit(0))
    class_sizes = docs.sparkSession.createDataFrame(pd.DataFrame({"k": range(CLASSES + 1), "size": sizes}))  # fixed number of rows
    tails = (
        met.withColumn("k", class_column)
        .join(F.broadcast(class_sizes), "k")
        .groupBy("row_no")
        .agg(
            F.sum(F.col("n") * F.log10((c + 1) / total)).alias("tail_base"),
            F.sum(F.col("n") * F.log10((c + 1) / F.col("size"))).alias("tail_class"),
            F.sum(F.when(c > 0, F.col("n")).otherwise(0)).alias("tail_known"),
        )
    )

    model = train(encoded.where(~F.col("held_out")).select("symbols"), class_tokens + class_types + 1, float(max(ends, 1)), states, rounds, seed)
    shared = sc.broadcast(model)

    def likelihood(batches):
        for batch in batches:
            logs = forward(shared.value, [np.frombuffer(s, dtype="<u2") for s in batch.column("symbols").to_pylist()])
            names = [n for n in batch.schema.names if n != "symbols"]
            yield pa.RecordBatch.from_arrays([*[batch.column(n) for n in names], pa.array(logs / math.log(10), pa.float64())], [*names, "path_log"])

    shown = f"row_no long, doc_id {kind}, held_out boolean, n_tokens long, known long, base_log double, class_log double, path_log double"
    paths = encoded.drop("tail").mapInArrow(likelihood, shown)
    zero = lambda name: F.coalesce(name, F.lit(0))
    return paths.join(tails, "row_no", "left").select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("known") + zero("tail_known")).cast("long").alias("n_known"),
        F.lit(int(n_tokens)).cast("long").alias("train_tokens"),
        (F.col("base_log") + zero("tail_base")).alias("base_score"),
        (F.col("path_log") + F.col("class_log") + zero("tail_class")).alias("score"),
    )


def train(texts: DataFrame, class_sizes: np.ndarray, ends: float, states: int = STATES, rounds: int = ROUNDS, seed: int = 5) -> Model:
    """Baum-Welch over the column `symbols`, all of it in every round."""
    sc = texts.sparkSession.sparkContext
    shares = class_sizes.astype(float).copy()
    shares[END] = ends
    shares /= shares.sum()
    model = Model.initial(shares, states, seed)
    for _ in range(rounds):
        sent = sc.broadcast(model)

        def collect_counts(batches, sent=sent):
            current = sent.value
            start, step, emit = np.zeros(states), np.zeros((states, states)), np.zeros_like(current.emit)
            for pdf in batches:
                windows, first = [], []
                for s in pdf["symbols"]:
                    symbols = np.frombuffer(s, dtype="<u2")
                    for a in range(0, len(symbols), WINDOW):
                        windows.append(symbols[a : a + WINDOW])
                        first.append(a == 0)
                for some in range(0, len(windows), 4096):
                    x = expected_counts(current, windows[some : some + 4096], np.array(first[some : some + 4096], dtype=bool), np.float32)
                    start, step, emit = start + x[0], step + x[1], emit + x[2]
            at = np.nonzero(emit.sum(axis=1))[0]
            rows = [(int(k), *emit[k]) for k in at] + [(-1, *start)] + [(-2 - i, *step[i]) for i in range(states)]
            yield pd.DataFrame(rows, columns=["k", *(f"s{i}" for i in range(states))])

        parts = texts.mapInPandas(collect_counts, "k int, " + ", ".join(f"s{i} double" for i in range(states)))
        emit, start, step = np.zeros_like(model.emit), np.zeros(states), np.zeros((states, states))
        for k, *values in parts.groupBy("k").agg(*[F.sum(f"s{i}") for i in range(states)]).collect():  # CLASSES + STATES + 2 rows at most
            if k >= 0:
                emit[k] = values
            elif k == -1:
                start[:] = values
            else:
                step[-2 - k] = values
        # Every state keeps a small share of the corpus-wide emissions, so no class is impossible anywhere.
        emit += 200.0 * shares[:, None]
        start, step = start + 0.1, step + 0.1
        model = Model(start / start.sum(), step / step.sum(axis=1, keepdims=True), emit / emit.sum(axis=0))
        sent.unpersist()
    return model
