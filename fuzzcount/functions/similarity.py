"""Similarities of two filters given as lane columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import LANES, popcount


def _pairs(a: str, b: str, lanes: tuple[str, ...]) -> list[tuple[Column, Column]]:
    return [(F.col(f"{a}.{w}"), F.col(f"{b}.{w}")) for w in lanes]


def common(a: str, b: str, lanes: tuple[str, ...] = LANES) -> Column:
    return popcount(*(x.bitwiseAND(y) for x, y in _pairs(a, b, lanes)))


def hamming(a: str, b: str, lanes: tuple[str, ...] = LANES) -> Column:
    return popcount(*(x.bitwiseXOR(y) for x, y in _pairs(a, b, lanes)))


def size(a: str, lanes: tuple[str, ...] = LANES) -> Column:
    return popcount(*(F.col(f"{a}.{w}") for w in lanes))


def dice(a: str, b: str) -> Column:
    total = size(a) + size(b)
    return F.when(total == 0, 0.0).otherwise(2 * common(a, b) / total)


def jaccard(a: str, b: str) -> Column:
    union = size(a) + size(b) - common(a, b)
    return F.when(union == 0, 0.0).otherwise(common(a, b) / union)


def euclid(a: str, b: str) -> Column:
    return F.sqrt(hamming(a, b).cast("double"))


def cosine(a: str, b: str) -> Column:
    product = size(a) * size(b)
    return F.when(product == 0, 0.0).otherwise(common(a, b) / F.sqrt(product.cast("double")))


def overlap(a: str, b: str) -> Column:
    least = F.least(size(a), size(b))
    return F.when(least == 0, 0.0).otherwise(common(a, b) / least)
