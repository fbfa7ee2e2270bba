"""Packing token pieces into sequences by vector bin packing.

A document is its token ids and one end id. It is cut into full sequences and a rest; the rests are
vectors (tokens, segments, loss-bearing tokens) and go into open sequences by the dot-product heuristic:
among those that a sequence can still take, the piece whose demand points most along what the sequence has
left. What then is left of a sequence is filled by cutting one more piece, so padding is left only where
a limit on segments or loss-bearing tokens binds. The rows a task has left at its end are cut to powers of
two, which need no padding.

Every task packs its own rows: no shuffle, memory bounded by POOL pieces, and a task that runs again
gives the same sequences.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .memory import lean

LENGTH, END_ID = 2048, 1
SEGMENTS = 64
#: Rests held by a task before they are packed.
POOL = 4096
#: Kinds of rest by size, and of those by share of loss-bearing tokens; a heuristic step looks at one of each kind.
KINDS, SHARES = 128, 8

_loaded: dict[str, object] = {}


class Ids:
    """Ids as the library gives them. Texts go through the same vocabulary's rank file, which is several times
    faster; texts that hold a reserved string go to the library, as does everything when no rank file is given."""

    def __init__(self, path: str, ranks: str | None = None, pattern: str | None = None):
        self.path, self.fast = path, None
        self.library = None
        if ranks:
            import tiktoken

            with open(ranks, "rb") as f:
                table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding(ranks, pat_str=pattern, mergeable_ranks=table, special_tokens={})

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None and "<|" not in text:
            return np.array(self.fast.encode_ordinary(text), dtype=np.uint32)
        if self.library is None:
            from .tokens import tokenizer

            self.library = tokenizer(self.path)[0]
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype=np.uint32)


def ids_of(path: str, ranks: str | None, pattern: str | None) -> Ids:
    key = f"{path}|{ranks}"
    if key not in _loaded:
        _loaded[key] = Ids(path, ranks, pattern)
    return _loaded[key]


class Piece:
    """Ids start..start+n of one document; `loss` of them bear loss."""

    __slots__ = ("doc", "start", "ids", "total", "loss")

    def __init__(self, doc, start: int, ids: np.ndarray, total: int, loss: np.ndarray):
        self.doc, self.start, self.ids, self.total, self.loss = doc, start, ids, total, loss

    def cut(self, n: int) -> tuple[Piece, Piece]:
        return (
            Piece(self.doc, self.start, self.ids[:n], self.total, self.loss[:n]),
            Piece(self.doc, self.start + n, self.ids[n:], self.total, self.loss[n:]),
        )


def longest_fit(piece: Piece, tokens: int, loss: int) -> int:
    """Ids from the front of `piece` that fit the tokens and loss-bearing tokens left."""
    n = min(tokens, len(piece.ids))
    bearing = np.cumsum(piece.loss[:n], dtype=np.int64)
    return n if not n or bearing[-1] <= loss else int(np.searchsorted(bearing, loss, side="right"))


class Packer:
    """Sequences of one task."""

    def __init__(self, length: int, segments: int, loss: int, pool: int):
        self.length, self.segments, self.loss, self.pool = length, segments, loss, pool
        # By size, then by loss-bearing share; only shares that occur have a list.
        self.kinds: list[dict[int, list[Piece]]] = [{} for _ in range(KINDS + 1)]
        self.held = 0

    def _kind(self, n: int) -> int:
        return min(KINDS, n * KINDS // self.length)

    def _hold(self, piece: Piece) -> None:
        if len(piece.ids):
            share = int(piece.loss.sum()) * (SHARES - 1) // len(piece.ids)
            self.kinds[self._kind(len(piece.ids))].setdefault(share, []).append(piece)
            self.held += 1

    def _take(self, k: int, share: int) -> Piece:
        self.held -= 1
        own = self.kinds[k][share]
        piece = own.pop()
        if not own:
            del self.kinds[k][share]
        return piece

    def add(self, piece: Piece) -> Iterator[list[Piece]]:
        """Take a document; gives the sequences that are full."""
        while len(piece.ids) >= self.length:
            n = longest_fit(piece, self.length, self.loss)
            if n < self.length:
                break
            first, piece = piece.cut(n)
            yield [first]
        while len(piece.ids) >= self.length:  # loss-bearing tokens bind before the length does
            first, piece = piece.cut(max(1, longest_fit(piece, self.length, self.loss)))
            self._hold(first)
        self._hold(piece)
        if self.held >= self.pool:
            yield from self.drain(self.pool // 2)

    def _step(self, left: np.ndarray) -> Piece | None:
        """The piece of largest dot product with what is left, of those that fit."""
        share = left / np.array([self.length, self.segments, self.loss], dtype=float)
        best, chosen = -1.0, None
        for k in range(self._kind(int(left[0])), -1, -1):
            for kind, own in self.kinds[k].items():
                n, bearing = len(own[-1].ids), int(own[-1].loss.sum())
                if n > left[0] or bearing > left[2]:
                    continue
                score = float(share @ (n / self.length, 1 / self.segments, bearing / self.loss))
                if score > best:
                    best, chosen = score, (k, kind)
            # What smaller kinds can reach: fewer tokens than this kind begins with, all of them bearing loss.
            most = k * self.length / KINDS
            if best > share @ (most / self.length, 1 / self.segments, min(most, float(left[2])) / self.loss):
                break
        return None if chosen is None else self._take(*chosen)

    def _any(self) -> Piece | None:
        for k in range(KINDS, -1, -1):
            for kind in self.kinds[k]:
                return self._take(k, kind)
        return None

    def drain(self, keep: int) -> Iterator[list[Piece]]:
        """Pack until `keep` pieces are held or no full sequence can be made."""
        while self.held > keep:
            left, own = np.array([self.length, self.segments, self.loss]), []
            while left[0] and left[1] and self.held:
                # The last segment a sequence may have is better cut to fill it than small and whole.
                piece = self._step(left) if left[1] > 1 else None
                if piece is None:
                    piece = self._any()
                    n = longest_fit(piece, int(left[0]), int(left[2]))
                    if not n:
                        self._hold(piece)
                        break
                    piece, rest = piece.cut(n)
                    self._hold(rest)
                own.append(piece)
                left -= (len(piece.ids), 1, int(piece.loss.sum()))
            if left[0] and not self.held and not left[1] == 0:
                yield from self._last(own)
            else:
                yield own

    def _last(self, own: list[Piece]) -> Iterator[list[Piece]]:
        """The end of a task: what is left, cut to powers of two."""
        total = sum(len(p.ids) for p in own)
        while total:
            room = 1 << (total.bit_length() - 1)
            total -= room
            sequence = []
            while room:
                piece = own.pop(0)
                if len(piece.ids) > room:
                    piece, rest = piece.cut(room)
                    own.insert(0, rest)
                sequence.append(piece)
                room -= len(piece.ids)
            yield sequence


def pack(examples: Iterable[Piece], length: int = LENGTH, segments: int = SEGMENTS, loss: int | None = None, pool: int = POOL) -> Iterator[list[Piece]]:
    """Sequences of pieces within the limits on tokens, segments and loss-bearing tokens."""
    packer = Packer(length, segments, loss or length, pool)
    for piece in examples:
        yield from packer.add(piece)
    yield from packer.drain(0)


def packed(docs: DataFrame, path: str, ranks: str | None = None, pattern: str | None = None, length: int = LENGTH, segments: int = SEGMENTS, loss: int | None = None, loss_from: str | None = None) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, loss_tokens, sequence_id, offset, sequence_length.

    docs needs doc_id and text; loss_from names a column of whole numbers (null: 0): ids before it bear no loss, as
    prompts do. Other columns are ignored. Null and empty texts are the end id alone; repeated rows are packed each; ids of
    any size and null ids come back as they are. An empty table gives no rows. Sequences are padded to `length` unless
    sequence_length is a power of two. sequence_id is the task's number in the upper bits and the sequence's place in the
    task below.
    """
    kind = dict(docs.dtypes)["doc_id"]
    first = F.coalesce(F.col(loss_from).cast("long"), F.lit(0).cast("long")) if loss_from else F.lit(0).cast("long")
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), first.alias("first"))

    def work(batches):
        ids_for, base, types = ids_of(path, ranks, pattern), TaskContext.get().partitionId() << 40, []

        def examples():
            for batch in batches:
                types[:] = [batch.column("doc_id").type]
                for doc, text, bears in zip(batch.column("doc_id"), batch.column("text"), batch.column("first").to_pylist(), strict=True):
                    ids = np.append(ids_for(text.as_py()), np.uint32(END_ID))
                    yield Piece(doc.as_py(), 0, ids, len(ids), (np.arange(len(ids)) >= bears).astype(np.int8))

        made: list[tuple] = []
        for n, sequence in enumerate(pack(examples(), length, segments, loss)):
            at, total = 0, sum(len(p.ids) for p in sequence)
            for p in sequence:
                made.append((p.doc, p.start, len(p.ids), zlib.crc32(p.ids.astype("<u4").tobytes()), p.total, int(p.loss.sum()), base + n, at, total))
                at += len(p.ids)
            if len(made) >= 2_000:
                yield frame(made, types[0])
                made = []
        if made:
            yield frame(made, types[0])

    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "loss_tokens", "sequence_id", "offset", "sequence_length"]

    def frame(made, of):
        columns = list(zip(*made, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(columns[0], of), *[pa.array(c, pa.int64()) for c in columns[1:]]], names)

    return rows.mapInArrow(lean(work), f"doc_id {kind}, " + ", ".join(f"{c} long" for c in names[1:]))
