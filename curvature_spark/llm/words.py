"""What a word is, in both execution styles.

A word is a maximal run of characters other than space and U+0009 to U+000D. On bytes that is
``bytes.split()``: UTF-8 keeps those code points out of every multi-byte sequence.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPACE = " \t\n\x0b\f\r"
SPACES = r"[ \t-\r]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def word_array(text: Column) -> Column:
    """The words of `text` as an array; empty for null or blank text."""
    parts = F.split(F.coalesce(text, F.lit("")), SPACES)
    return F.filter(parts, lambda w: w != "")


def lower_ascii(text: Column) -> Column:
    """`text` with A to Z, and nothing else, lower-cased; null becomes the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def lowered_words(raw: bytes | None) -> list[bytes]:
    """The words of UTF-8 bytes after lower-casing A to Z (``bytes.lower`` touches ASCII only)."""
    return raw.lower().split() if raw else []
