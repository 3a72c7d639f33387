"""Tokens of attributes: q-grams of strings, neighbours of numbers, categories.

A null or empty attribute has no token; a string shorter than q is its own token.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

FIELDS = ("given", "surname", "suburb", "postcode")


def normalise(text: Column) -> Column:
    return F.regexp_replace(F.trim(F.lower(text)), " +", " ")


def qgrams(text: Column, q: int = 2, pad: bool = False) -> Column:
    """Distinct q-grams of the normalised text in order of first appearance."""
    s = normalise(text)
    s = F.when(F.length(s) > 0, F.concat(F.lit("_" * (q - 1)), s, F.lit("_" * (q - 1)))) if pad else s
    none = F.array().cast("array<string>")
    whole = F.transform(F.sequence(F.lit(1), F.length(s) - (q - 1)), lambda i: F.substring(s, i, F.lit(q)))
    return F.when(F.coalesce(F.length(s), F.lit(0)) == 0, none).when(F.length(s) < q, F.array(s)).otherwise(F.array_distinct(whole))


def neighbours(value: Column, step: int, width: int) -> Column:
    """Grid values within `width` steps of a number's own grid value."""
    cell = F.floor(value / step) * step
    return F.when(value.isNull(), F.array().cast("array<bigint>")).otherwise(F.sequence(cell - width * step, cell + width * step, F.lit(step).cast("bigint")))


def category(value: Column) -> Column:
    v = normalise(value)
    return F.when(F.coalesce(F.length(v), F.lit(0)) == 0, F.array().cast("array<string>")).otherwise(F.array(v))


def record_tokens(fields: tuple[str, ...] = FIELDS, categories: tuple[str, ...] = ("gender",), q: int = 2, tagged: bool = True) -> Column:
    """All tokens of a record, each with its field's name so that equal grams of different fields stay apart."""
    def named(name: str, tokens: Column) -> Column:
        return F.transform(tokens, lambda t: F.concat(F.lit(f"{name}|"), t)) if tagged else tokens

    parts = [named(f, qgrams(F.col(f), q)) for f in fields] + [named(f, category(F.col(f))) for f in categories]
    return F.array_distinct(F.flatten(F.array(*parts)))
