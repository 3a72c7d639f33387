"""Distinct counts without noise or typos: exact, HyperLogLog, theta, k minimum values, trailing zeros."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.functions.digest import num

#: Fixed value: the bias of the trailing-zero estimate.
FM_BIAS = 0.77351


def exact(df: DataFrame, item: Column, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count_distinct(item).alias("n"))


def hll(df: DataFrame, item: str, *by: str, lg_k: int = 12) -> DataFrame:
    return df.groupBy(*by).agg(F.hll_sketch_estimate(F.hll_sketch_agg(item, lg_k)).alias("estimate"))


def hll_union(df: DataFrame, item: str, by: str, lg_k: int = 12) -> DataFrame:
    """The estimate over all groups from the union of each group's sketch."""
    return df.groupBy(by).agg(F.hll_sketch_agg(item, lg_k).alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("estimate"))


def kmv(df: DataFrame, item: Column, by: str, k: int = 64) -> DataFrame:
    """(by, estimate): (k - 1) 2^32 over the k-th least distinct draw; the exact count below k."""
    drawn = df.select(by, num(item.cast("string")).alias("u")).distinct()
    ranked = drawn.withColumn("r", F.row_number().over(Window.partitionBy(by).orderBy("u"))).where(F.col("r") <= k)
    top = ranked.groupBy(by).agg(F.count("*").alias("n"), F.max("u").alias("u"))
    return top.select(by, F.when(F.col("n") < k, F.col("n").cast("double")).otherwise((k - 1) * 4294967296.0 / F.col("u")).alias("estimate"))


def fm(df: DataFrame, item: Column, maps: int = 64) -> DataFrame:
    """(estimate) from the lowest unset bit of `maps` bitmaps of trailing zeros."""
    digest = F.md5(item.cast("string").cast("binary"))
    first = F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint")
    second = F.conv(F.substring(digest, 9, 8), 16, 10).cast("bigint")
    zeros = F.when(second == 0, 32).otherwise(F.bit_count(second.bitwiseAND(-second) - 1))
    bitmaps = df.select(F.pmod(first, F.lit(maps)).alias("m"), F.pow(F.lit(2.0), zeros).cast("bigint").alias("bit")).groupBy("m").agg(F.bit_or("bit").alias("b"))
    lowest = F.bit_count((F.bitwise_not("b")).bitwiseAND(F.col("b") + 1) - 1)
    return bitmaps.agg(F.sum(lowest).alias("r")).select((maps * F.pow(F.lit(2.0), F.coalesce("r", F.lit(0)) / maps) / FM_BIAS).alias("estimate"))
