"""Bloom filters as lanes: four 50-bit integers hold the 200 bits of a record's filter.

Lanes are never negative, so engines agree on them; exclusive or and bit counts stay in generated code.
A record without tokens has an all-zero filter and is kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from fuzzcount.functions.digest import keyed, num
from fuzzcount.functions.md5 import draws

ELL, HASHES, LANE = 200, 20, 50
LANES = ("w0", "w1", "w2", "w3")
#: Which attributes each lane holds where every attribute has a filter of its own.
FIELDS = (("given",), ("surname",), ("suburb",), ("postcode", "gender"))


def lane_names(ell: int = ELL) -> tuple[str, ...]:
    return tuple(f"w{i}" for i in range(-(-ell // LANE)))


def positions(tokens: Column, ell: int = ELL, hashes: int = HASHES, key: str = "k", family: str = "independent") -> Column:
    """Distinct bit positions of all tokens; `family` is independent digests or the double-hash progression."""
    if family == "double":
        def of(token: Column) -> Column:
            digest = F.md5(F.concat(F.lit(f"{key}|"), token).cast("binary"))
            start = F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint")
            step = F.conv(F.substring(digest, 9, 8), 16, 10).cast("bigint")
            odd = F.pmod(step, F.lit(ell // 10)) * 10 + 1  # no factor in common with 200
            return F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda i: F.pmod(start + i * odd, F.lit(ell)))
    else:
        def of(token: Column) -> Column:
            return F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda i: F.pmod(num(F.concat_ws("|", F.lit(key), token, i.cast("string"))), F.lit(ell)))
    return F.array_sort(F.array_distinct(F.flatten(F.transform(tokens, of))))


def lane_of(bits: Column, lane: int) -> Column:
    """The integer of one lane from distinct positions."""
    own = F.filter(bits, lambda p: F.floor(p / LANE) == lane)
    return F.aggregate(own, F.lit(0).cast("bigint"), lambda total, p: total + F.pow(F.lit(2.0), F.pmod(p, F.lit(LANE))).cast("bigint"))


def with_lanes(df, bits: str, ell: int = ELL):
    """`df` with lane columns from a column of positions."""
    return df.withColumns({name: lane_of(F.col(bits), i) for i, name in enumerate(lane_names(ell))})


def token_lanes(tokens: pa.ListArray, ell: int = ELL, hashes: int = HASHES, key: str = "k") -> list[np.ndarray]:
    """The lanes of `positions` for a batch of token lists; a token that many rows share is hashed once."""
    words = tokens.flatten().dictionary_encode()
    heads = [f"{key}|{t}|".encode() for t in words.dictionary.to_pylist()]
    at = draws(heads, [str(i).encode() for i in range(hashes)]).astype(np.int64) % ell
    index, sizes = words.indices.to_numpy(zero_copy_only=False), pc.list_value_length(tokens).to_numpy(zero_copy_only=False)
    full = np.flatnonzero(sizes)
    starts = np.cumsum(sizes[full]) - sizes[full]
    lanes = []
    for lane in range(len(lane_names(ell))):
        own = np.bitwise_or.reduce(np.where(at // LANE == lane, np.int64(1) << at % LANE, 0), axis=1)
        out = np.zeros(len(tokens), np.int64)
        if len(full):
            out[full] = np.bitwise_or.reduceat(own[index], starts)
        lanes.append(out)
    return lanes


def encode_tokens(df: DataFrame, tokens: str = "tokens", ell: int = ELL, hashes: int = HASHES, key: str = "k") -> DataFrame:
    """`df` with lane columns in place of a column of tokens, none of which is null."""
    names, ids = list(lane_names(ell)), [c for c in df.columns if c != tokens]

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lanes = token_lanes(batch.column(len(ids)), ell, hashes, key)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(ids)], *map(pa.array, lanes)], names=[*ids, *names])

    rows = df.select(*ids, tokens)
    return rows.mapInArrow(encode, StructType([*rows.schema.fields[: len(ids)], *(StructField(n, LongType()) for n in names)]))


def encode_by_field(df, tokens: str = "tokens", hashes: int = 5, key: str = "k"):
    """`df` with lane columns: a filter of `LANE` bits for the tagged tokens of each group of attributes, side by side."""
    def own(fields: tuple[str, ...]) -> Column:
        mine = F.filter(tokens, lambda t: F.array_contains(F.array(*map(F.lit, fields)), F.substring_index(t, "|", 1)))
        return lane_of(positions(mine, LANE, hashes, key), 0)

    return df.withColumns({name: own(fields) for name, fields in zip(LANES, FIELDS, strict=True)})


def item_filters(items, words: int, least: int, hashes: int = 2, key: str = "k"):
    """(rec_id, lanes) of (id, text): the filter of the `least` smallest digests of the text's shingles of so many words."""
    w = F.filter(F.split(F.translate(F.coalesce("text", F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), " "), lambda x: x != "")
    split = items.select(F.col("id").alias("rec_id"), F.explode(F.array(w)).alias("w"))  # split once, not at each step of the lambda below
    width = F.least(F.lit(words), F.size("w"))
    grams = F.transform(F.sequence(F.lit(1), F.size("w") - width + 1), lambda i: num(F.array_join(F.slice("w", i, width), " ")))
    digests = F.when(F.size("w") > 0, F.slice(F.array_sort(F.array_distinct(grams)), 1, least)).otherwise(F.array().cast("array<bigint>"))
    bits = split.select("rec_id", positions(F.transform(digests, lambda d: d.cast("string")), ELL, hashes, key).alias("bits"))
    return with_lanes(bits, "bits").select("rec_id", *LANES)


def popcount(*lanes: Column) -> Column:
    return sum((F.bit_count(c) for c in lanes[1:]), F.bit_count(lanes[0]))


def has_bit(lanes: tuple[str, ...], p: Column) -> Column:
    return F.getbit(F.element_at(F.array(*lanes), (F.floor(p / LANE) + 1).cast("int")), F.pmod(p, F.lit(LANE)).cast("int")) == 1


def might_contain(lanes: tuple[str, ...], token: Column, ell: int = ELL, hashes: int = HASHES, key: str = "k") -> Column:
    """False: surely not in the filter; true: probably."""
    return F.forall(positions(F.array(token), ell, hashes, key), lambda p: has_bit(lanes, p))
