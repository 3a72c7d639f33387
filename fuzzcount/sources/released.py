"""Release sink and reader: only filters cross from owners to the linkage side."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from fuzzcount.functions.bloom import LANES

ALLOWED = {"owner", "rec_id", "cell", "epsilon", *LANES}


def check_release(df: DataFrame) -> DataFrame:
    """Refuses a table with any column that is not part of a release."""
    extra = set(df.columns) - ALLOWED
    if extra:
        raise ValueError(f"a release holds filters only, not {sorted(extra)}")
    return df


def write_release(df: DataFrame, path: str) -> None:
    """Written once per owner: noise that is drawn anew for the same record could be averaged out."""
    check_release(df).write.partitionBy("owner").mode("errorifexists").parquet(path)


def read_release(spark: SparkSession, path: str) -> DataFrame:
    return check_release(spark.read.parquet(path))
