"""Randomised response on lanes.

Each bit is flipped with probability 1 / (1 + e^epsilon), by a draw keyed on owner, record and bit: a task
that runs again flips the same bits.  The guarantee is per bit; a record whose filter differs in d bits has d
times the budget.  `printed_branch` keeps the bits that the flip would change and changes the others: the
complement of the usual release.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import ELL, LANE, lane_names
from fuzzcount.functions.digest import below, num
from fuzzcount.functions.md5 import draws


def flip_rate(epsilon: float) -> float:
    return 1 / (1 + math.exp(epsilon))


def mask(prefix: Column, lane: int, share: float, ell: int = ELL) -> Column:
    """The bits of one lane whose draw falls under `share`, as an integer."""
    first, last = lane * LANE, min(ell, (lane + 1) * LANE) - 1
    drawn = F.filter(F.sequence(F.lit(first), F.lit(last)), lambda b: num(F.concat_ws("|", prefix, b.cast("string"))) < below(share))
    return F.aggregate(drawn, F.lit(0).cast("bigint"), lambda total, b: total + F.pow(F.lit(2.0), b - first).cast("bigint"))


def masks(prefixes: pa.Array, share: float, ell: int = ELL) -> list[np.ndarray]:
    """`mask` of every lane for a batch of prefixes."""
    heads, bound = [p.encode() + b"|" for p in prefixes.to_pylist()], below(share)
    out = []
    for lane in range(len(lane_names(ell))):
        bits = range(lane * LANE, min(ell, (lane + 1) * LANE))
        hit = draws(heads, [str(b).encode() for b in bits]) < bound
        out.append(hit @ (np.int64(1) << np.arange(len(bits), dtype=np.int64)))
    return out


def flipped(df: DataFrame, prefix: Column, share: float, ell: int = ELL) -> DataFrame:
    """`df` with every lane's bits flipped where the draw of (prefix, bit) falls under `share`."""
    names, columns = lane_names(ell), df.columns

    def flip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            drawn = dict(zip(names, masks(batch.column(len(columns)), share, ell), strict=True))
            lanes = {n: pc.bit_wise_xor(batch.column(columns.index(n)), pa.array(drawn[n])) for n in names}
            yield pa.RecordBatch.from_arrays([lanes.get(n, batch.column(i)) for i, n in enumerate(columns)], names=columns)

    return df.select("*", prefix.alias("prefix of draws")).mapInArrow(flip, df.schema)


def perturb(df: DataFrame, epsilon: float, key: str = "k", ell: int = ELL, printed_branch: bool = False) -> DataFrame:
    """Released filters of (owner, rec_id, lanes)."""
    out = flipped(df, F.concat_ws("|", F.lit(key), F.col("owner"), F.col("rec_id").cast("string")), flip_rate(epsilon), ell)
    if not printed_branch:
        return out
    full = [min(LANE, ell - i * LANE) for i in range(len(lane_names(ell)))]
    return out.withColumns({name: F.lit(2**n - 1).cast("bigint").bitwiseXOR(F.col(name)) for name, n in zip(lane_names(ell), full, strict=True)})


def _spread(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def gap_flips(seeds: np.ndarray, share: float, ell: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, bit) of the flips of rows with such seeds: the gaps between flips are geometric, so only flips are drawn."""
    at, alive, turn = np.full(len(seeds), -1.0), np.arange(len(seeds)), 0
    rows, bits = [], []
    while len(alive):
        turn += 1
        draw = _spread(seeds[alive] + np.uint64(0x9E3779B97F4A7C15 * turn % 2**64))
        u = ((draw >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53
        at[alive] += 1 + np.floor(np.log(u) / math.log1p(-share))
        alive = alive[at[alive] < ell]
        rows.append(alive)
        bits.append(at[alive].astype(np.int64))
    return (np.concatenate(rows), np.concatenate(bits)) if rows else (np.empty(0, np.int64), np.empty(0, np.int64))


def perturb_by_gaps(df: DataFrame, epsilon: float, key: str = "k", ell: int = ELL) -> DataFrame:
    """Released filters of (owner, rec_id, lanes) with the law of `perturb`, from about `ell` times the flip rate draws a record."""
    names, share = lane_names(ell), flip_rate(epsilon)

    def flip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lanes = [batch.column(3 + i).to_numpy(zero_copy_only=False).copy() for i in range(len(names))]
            rows, bits = gap_flips(batch.column(2).to_numpy(zero_copy_only=False).view(np.uint64), share, ell)
            for i, lane in enumerate(lanes):
                own = bits // LANE == i
                np.bitwise_xor.at(lane, rows[own], np.left_shift(np.int64(1), bits[own] % LANE))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *map(pa.array, lanes)], names=["owner", "rec_id", *names])

    seeded = df.select("owner", "rec_id", F.xxhash64(F.lit(key), "owner", "rec_id").alias("seed"), *names)
    return seeded.mapInArrow(flip, f"owner string, rec_id bigint, {', '.join(f'{n} bigint' for n in names)}")
