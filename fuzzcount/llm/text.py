"""Normal forms of text that several operators share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What stands between words: every ASCII character but digits and letters (text is lower-cased before).
BETWEEN_WORDS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def lowered(text: Column) -> Column:
    """A-Z lower-cased and nothing else; null becomes empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def word_array(text: Column) -> Column:
    """The words of a text in order; a text without words has an empty array."""
    return F.filter(F.split(lowered(text), BETWEEN_WORDS), lambda w: w != "")


def trimmed_words(text: Column) -> Column:
    """The words of a text, each followed by one blank and the first preceded by one; no words: one blank."""
    return F.regexp_replace(F.concat(F.lit(" "), lowered(text), F.lit(" ")), BETWEEN_WORDS, " ")
