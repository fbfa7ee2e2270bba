"""Token counts of whole texts by a public tokenizer, huge texts by overlap resynchronisation.

Texts up to CHUNK characters are counted whole. A longer one is encoded in overlapping chunks with
offsets. Two neighbouring chunks are spliced at a stable common boundary: a place inside their overlap
where white space stands between two tokens and both encodings agree, id for id and offset for offset, on
the AGREE tokens before it and after it. The pattern of the pre-tokenizer drops white space, so no token and
no merge spans it: what lies behind such a place no longer depends on what lay before. If no such place
is found, the overlap doubles, in the end up to the whole text.

Most characters are in short, repeated words, and the vocabulary's merges never cross a word. In texts
made only of characters below U+0180 whose handling by normaliser and pattern is settled, words are
split here and each distinct word is counted once per worker by the library itself; every other text goes
to the library.
"""

from __future__ import annotations

import os
import re

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHUNK, OVERLAP, AGREE = 65536, 1024, 4
LIMIT = 2048
#: Words remembered per Python worker; at the bound the memory starts anew.
REMEMBERED = 400_000
#: The pre-tokenizer's pattern in the vocabulary file, and the strings it reserves.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
RESERVED = ("<|startoftext|>", "<|endoftext|>")
#: Characters outside these are left to the library: controls that libraries class differently, and all from U+0180 on.
UNSETTLED = re.compile("[^\t\n\r\x20-\x7e\xa0-ſ]")

_loaded: dict[str, tuple] = {}


class WordCounts(dict):
    """Tokens per word, asked of the library at first sight."""

    def __init__(self, tok):
        super().__init__()
        self.tok = tok

    def __missing__(self, word: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        n = self[word] = len(self.tok.encode(word, add_special_tokens=False).ids)
        return n


def tokenizer(path: str) -> tuple:
    """The library's tokenizer for `path`, without padding or truncation, and its word counts, one pair a worker."""
    if path not in _loaded:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        tok.no_padding()
        tok.no_truncation()
        _loaded[path] = tok, WordCounts(tok)
    return _loaded[path]


def _tokens(tok, text: str, start: int) -> list[tuple[int, int, int]]:
    """(id, begin, end) with offsets in the whole text, of the piece that starts there."""
    found = tok.encode(text, add_special_tokens=False)
    return [(i, a + start, b + start) for i, (a, b) in zip(found.ids, found.offsets, strict=True)]


def _boundary(text: str, left: list, right: list, least: int) -> tuple[int, int] | None:
    """Places (in left, in right) of a stable common boundary behind offset `least`, the last one there is."""
    seen = {t: n for n, t in enumerate(right)}
    for n in range(len(left) - AGREE, AGREE - 1, -1):
        begin = left[n][1]
        if begin <= least:
            return None
        m = seen.get(left[n])
        if m is None or m < AGREE or left[n - 1][2] >= begin or not text[left[n - 1][2] : begin].isspace():
            continue
        if left[n - AGREE : n + AGREE] == right[m - AGREE : m + AGREE]:
            return n, m
    return None


def spliced(tok, text: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[tuple[int, int, int]]:
    """(id, begin, end) of every token of `text`, equal to encoding it whole, from overlapping chunks."""
    done: list[tuple[int, int, int]] = []
    current, end = _tokens(tok, text[:chunk], 0), min(chunk, len(text))
    while end < len(text):
        width, cut = overlap, None
        least = current[0][1] if current else 0
        while cut is None:
            start = end - width
            if start <= least:
                return _tokens(tok, text, 0)
            following = _tokens(tok, text[start : start + width + chunk], start)
            cut = _boundary(text, current, following, start)
            width *= 2
        done += current[: cut[0]]
        current, end = following[cut[1] :], min(start + width // 2 + chunk, len(text))
    return done + current


def count(path: str, text: str | None, chunk: int = CHUNK) -> int:
    """Tokens of one text; null is empty."""
    if not text:
        return 0
    tok, words = tokenizer(path)
    if len(text) > chunk:
        return len(spliced(tok, text, chunk))
    if UNSETTLED.search(text) or any(r in text for r in RESERVED):
        return len(tok.encode(text, add_special_tokens=False).ids)
    return sum(map(words.__getitem__, _pattern().findall(text.lower())))


def _pattern():
    if "pattern" not in _loaded:
        _loaded["pattern"] = regex.compile(WORD_PATTERN)
    return _loaded["pattern"]


def token_counts(docs: DataFrame, path: str, limit: int = LIMIT, chunk: int = CHUNK) -> DataFrame:
    """One row per row of `docs`: doc_id, n_bytes, n_tokens, over_limit.

    docs needs doc_id and text; other columns are ignored. Null and empty texts have no bytes and no tokens;
    repeated rows are counted each. An empty table gives no rows. `path` names the vocabulary file, which every
    executor must have.
    """

    def counted(batches):
        for batch in batches:
            n = pa.array([count(path, t, chunk) for t in batch.column("text").to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), n], ["doc_id", "n_bytes", "n_tokens"])

    sized = docs.select("doc_id", "text", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))
    out = sized.mapInArrow(counted, f"doc_id {dict(docs.dtypes)['doc_id']}, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
