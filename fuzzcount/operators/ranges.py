"""Joins by range and by time, built from equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, left_value: str, right_value: str, width: float, *by: tuple[str, str]) -> DataFrame:
    """Pairs whose values differ by at most `width`: an equi-join on buckets of that width and their neighbours."""
    x = left.withColumn("__bucket", F.floor(F.col(left_value) / width)).alias("x")
    y = right.withColumn("__bucket", F.explode(F.array(*(F.floor(F.col(right_value) / width) + i for i in (-1, 0, 1))))).alias("y")
    same = F.col("x.__bucket") == F.col("y.__bucket")
    for a, b in by:
        same = same & (F.col(f"x.{a}") == F.col(f"y.{b}"))
    return x.join(y, same & (F.abs(F.col(f"x.{left_value}") - F.col(f"y.{right_value}")) <= width)).drop("__bucket")


def asof(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """`left` with the last `value` of `right` of the same key at or before its time: one shuffle, no pairs."""
    rows = left.withColumns({"__ts": F.col(left_ts), "__side": F.lit(1), "__value": F.lit(None).cast(right.schema[value].dataType)})
    marks = right.select(F.col(key), F.col(right_ts).alias("__ts"), F.lit(0).alias("__side"), F.col(value).alias("__value"))
    order = Window.partitionBy(key).orderBy("__ts", "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = rows.unionByName(marks, allowMissingColumns=True)
    return both.withColumn(value, F.last("__value", ignorenulls=True).over(order)).where("__side = 1").drop("__ts", "__side", "__value")


def hash_sample(df: DataFrame, draw: Column, share: float) -> DataFrame:
    """Rows whose keyed draw falls under the share: the same rows on every retry."""
    return df.where(draw < int(share * 2**32))
