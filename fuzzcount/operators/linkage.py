"""Pairs of similar filters: all pairs of one cell, blocked pairs, components and cells."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import ELL, LANE, LANES, popcount
from fuzzcount.functions.similarity import common, dice, hamming


def with_class(rows: DataFrame, *block: str) -> DataFrame:
    """`rows` (rec_id, lanes, block) with `first`, the least rec_id of those with the same filter in the same block, written once."""
    from fuzzcount.sources.tables import cut

    by = [*LANES, *block]
    return cut(rows.select("rec_id", *by).join(rows.groupBy(*by).agg(F.min("rec_id").alias("first")), by))


def of_members(members: DataFrame, pairs: DataFrame, measure: str, same: float | int, alike: DataFrame | None = None) -> DataFrame:
    """(a, b, measure) of all records from pairs of classes; those within a class have the measure `same`, or no pair if not in `alike`."""
    x, y = members.select(F.col("rec_id").alias("x"), F.col("first").alias("a")), members.select(F.col("rec_id").alias("y"), F.col("first").alias("b"))
    between = pairs.join(x, "a").join(y, "b").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), measure)
    within = (members if alike is None else alike).select(F.col("rec_id").alias("x"), F.col("first").alias("a"), F.lit(same).alias(measure)).join(y.withColumnRenamed("b", "a"), "a").where("x < y")
    return between.unionByName(within.select(F.col("x").alias("a"), F.col("y").alias("b"), measure))


def match_pairs(rows: DataFrame, threshold: float, block: str) -> DataFrame:
    """(a, b, dice) of records of one block whose Dice reaches the threshold; bit counts prune first.

    Equal filters of a block are compared with the others once.
    """
    members = with_class(rows, block)
    firsts = members.where("rec_id = first").withColumn("bits", popcount(*map(F.col, LANES)))
    x, y = firsts.alias("x"), firsts.alias("y")
    #: Dice >= t needs a ratio of bit counts of at least t / (2 - t).
    bound = threshold / (2 - threshold)
    a, b = F.col("x.bits"), F.col("y.bits")
    close = (F.least(a, b) >= bound * F.greatest(a, b)) & (2 * common("x", "y") / (a + b) >= threshold)
    pairs = x.join(y, (F.col(f"x.{block}") == F.col(f"y.{block}")) & (F.col("x.rec_id") < F.col("y.rec_id")) & close).select(F.col("x.rec_id").alias("a"), F.col("y.rec_id").alias("b"), F.round(dice("x", "y"), 6).alias("dice"))
    return of_members(members, pairs, "dice", 1.0, members.where(popcount(*map(F.col, LANES)) > 0))  # an empty filter is like none


def bands(rows: DataFrame, ids: list[str], width: int = 10) -> DataFrame:
    """(ids, band, value): bit samples of each lane, so that filters within a small distance share some band."""
    per_lane = LANE // width
    parts = [F.struct(F.lit(i * per_lane + j).alias("band"), F.shiftright(F.col(w), j * width).bitwiseAND(F.lit(2**width - 1).cast("bigint")).alias("value")) for i, w in enumerate(LANES) for j in range(per_lane)]
    return rows.select(*ids, *LANES, F.inline(F.array(*parts)))


def blocked_pairs(rows: DataFrame, radius: int, width: int | None = None) -> DataFrame:
    """(a, b, d) within a Hamming radius that share a band: all such pairs if the radius is below the number of bands.

    By default bands are as wide as the radius allows.  A pair is formed in the first band that it shares, so
    none comes twice.  Dense filters share the band of ones alone, so large radii over many of them stay
    quadratic: give those a block (`match_pairs`).
    """
    width = width or LANE // -(-(radius + 1) // len(LANES))
    cut = bands(rows, ["rec_id"], width)
    x, y = cut.alias("x"), cut.alias("y")
    same = (F.col("x.band") == F.col("y.band")) & (F.col("x.value") == F.col("y.value")) & (F.col("x.rec_id") < F.col("y.rec_id"))
    per_lane, all_ones = LANE // width, 2**width - 1
    shared = [(i * per_lane + j, F.shiftright(F.col(f"x.{w}").bitwiseXOR(F.col(f"y.{w}")), j * width).bitwiseAND(F.lit(all_ones).cast("bigint")) == 0) for i, w in enumerate(LANES) for j in range(per_lane)]
    first = F.coalesce(*(F.when(equal, F.lit(band)) for band, equal in shared))
    return x.join(y, same & (hamming("x", "y") <= radius) & (first == F.col("x.band"))).select(F.col("x.rec_id").alias("a"), F.col("y.rec_id").alias("b"), hamming("x", "y").alias("d"))


def band_value(lanes: list[Column], first: int, last: int) -> Column:
    """The bits of a filter from `first` to before `last`, over the borders of lanes, as an integer."""
    parts = []
    for i, lane in enumerate(lanes):
        low, high = max(first, i * LANE), min(last, (i + 1) * LANE)
        if low < high:
            own = F.shiftright(lane, low - i * LANE).bitwiseAND(F.lit(2 ** (high - low) - 1).cast("bigint"))
            parts.append(F.shiftleft(own, low - first))
    return reduce(lambda a, b: a.bitwiseOR(b), parts)


def near_classes(rows: DataFrame, radius: int) -> DataFrame:
    """(a, b, d) of all pairs of different rows within a Hamming radius, for rows whose filters differ.

    Of `radius` + 2 bands at least two agree, so a pair is formed by the first two that do: dense filters share
    the ones of one band often, those of two seldom.
    """
    n = radius + 2
    edges = [ELL * i // n for i in range(n + 1)]
    at, wide = list(combinations(range(n), 2)), 2 * -(-ELL // n)
    if wide + len(at).bit_length() > 62:
        raise ValueError(f"two bands of a radius of {radius} do not fit a number")
    values = [band_value([F.col(w) for w in LANES], edges[i], edges[i + 1]) for i in range(n)]
    keys = [F.shiftleft(values[i], wide // 2).bitwiseOR(values[j]).bitwiseOR(F.lit(at.index((i, j)) << wide).cast("bigint")) for i, j in at]
    keyed = rows.select("rec_id", *LANES, F.posexplode(F.array(*keys)).alias("pair", "key"))
    lower = F.element_at(F.array(*(F.lit((1 << j) - 1) for _, j in at)), F.col("x.pair") + 1)
    own = F.element_at(F.array(*(F.lit(1 << i) for i, _ in at)), F.col("x.pair") + 1)
    x, y = keyed.alias("x"), keyed.alias("y")
    apart = [F.col(f"x.{w}").bitwiseXOR(F.col(f"y.{w}")) for w in LANES]
    agree = reduce(lambda a, b: a.bitwiseOR(b), (F.when(band_value(apart, edges[i], edges[i + 1]) == 0, 1 << i).otherwise(0) for i in range(n)))
    near = (F.col("x.key") == F.col("y.key")) & (F.col("x.rec_id") < F.col("y.rec_id")) & (hamming("x", "y") <= radius) & (agree.bitwiseAND(lower) == own)
    return x.join(y, near).select(F.col("x.rec_id").alias("a"), F.col("y.rec_id").alias("b"), hamming("x", "y").alias("d"))


def near_pairs(rows: DataFrame, radius: int) -> DataFrame:
    """(a, b, d) of all pairs of records within a Hamming radius; equal filters are compared with the others once."""
    members = with_class(rows)
    return of_members(members, near_classes(members.where("rec_id = first"), radius), "d", 0)


def near_components(rows: DataFrame, radius: int) -> DataFrame:
    """(node, component) of all records: single-link groups within a Hamming radius, of equal filters by the first of them."""
    members = with_class(rows)
    firsts = members.where("rec_id = first")
    groups = components(firsts, near_classes(firsts, radius)).withColumnRenamed("node", "first")
    return members.join(groups, "first").select(F.col("rec_id").alias("node"), "component")


def components(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """(node, component): single-link groups by least-label rounds, cut in the shared folder."""
    from fuzzcount.sources.tables import cut, drop

    both = cut(pairs.select(F.col("a").alias("u"), F.col("b").alias("v")).union(pairs.select("b", "a")))
    labels = cut(nodes.select(F.col("rec_id").alias("node"), F.col("rec_id").alias("component")))
    while True:
        old = labels
        seen = both.join(labels, both["v"] == labels["node"]).groupBy("u").agg(F.min("component").alias("m"))
        new = cut(labels.join(seen, labels["node"] == seen["u"], "left").select("node", F.least("component", F.coalesce("m", "component")).alias("component")))
        # Follow the label's own label, which halves the rounds.
        up = new.select(F.col("node").alias("component"), F.col("component").alias("root"))
        labels = cut(new.join(up, "component").select("node", F.col("root").alias("component")))
        drop(new)
        changed = labels.join(old.withColumnRenamed("component", "before"), "node").where("component <> before").limit(1).count()
        drop(old)
        if not changed:
            drop(both)
            return labels
