"""Labelled decoys: reference filters, noisy copies of them, and the pool they join.

Pool rows are (row_id, kind, ref_id, lanes) with kind real, ref or dum; ref_id is null for real rows.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import ELL, LANES
from fuzzcount.functions.digest import num
from fuzzcount.functions.noise import flipped
from fuzzcount.sources.tables import spread


def counts_for(n: int, pick_ratio: float = 0.1, dummy_ratio: float = 0.1, dummy_base: str = "references") -> tuple[int, int]:
    """(references, dummies of each) for a pool of n real records."""
    if dummy_base not in ("references", "records"):
        raise ValueError("dummy_base is 'references' or 'records'")
    refs = max(1, _rounded(pick_ratio * n))
    return refs, max(1, _rounded(dummy_ratio * (refs if dummy_base == "references" else n)))


def _rounded(x: float) -> int:
    """To the nearest whole number, halves up, as SQL does."""
    return math.floor(x + 0.5)


def invent(spark: SparkSession, n_ref: int, key: str = "k", density: float = 0.5, ell: int = ELL) -> DataFrame:
    """Method A: (ref_id, lanes) of filters whose bits are set by a coin."""
    blank = spark.range(n_ref).select(F.col("id").alias("ref_id"), *(F.lit(0).cast("bigint").alias(w) for w in LANES))
    prefix = F.concat_ws("|", F.lit(key), F.lit("refA"), F.col("ref_id").cast("string"))
    return flipped(blank, prefix, density, ell)


def sample(released: DataFrame, n_ref: int, key: str = "k") -> DataFrame:
    """Method B: (ref_id, owner, rec_id, lanes) of the records that a keyed draw ranks first, without replacement."""
    drawn = released.withColumn("draw", num(F.concat_ws("|", F.lit(key), F.lit("refB"), F.col("owner"), F.col("rec_id").cast("string"))))
    return ranked(drawn, n_ref, "draw", "owner", "rec_id").select(F.col("rank").alias("ref_id"), "owner", "rec_id", *LANES)


def ranked(rows: DataFrame, most: int, draw: str, *ties: str) -> DataFrame:
    """`rows` with their `rank` from 0 by a 32-bit draw, those below `most`.

    The draw's upper bits deal the rows into ranges; a range's first rank is the number of rows before it, so
    no task ranks more than one range and nothing but 65 536 counts meets in one place.
    """
    dealt = rows.withColumn("range", F.shiftright(draw, 16))
    counts = dealt.groupBy("range").agg(F.count("*").alias("n"))
    before = counts.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("before")).where(F.col("before") < most)
    own = dealt.join(before, "range").withColumn("rank", F.col("before") + F.row_number().over(Window.partitionBy("range").orderBy(draw, *ties)) - 1)
    return own.where(F.col("rank") < most).drop("range", "before")


def dummies(refs: DataFrame, n_dum: int, p_flip: float, key: str = "k") -> DataFrame:
    """(ref_id, dum_no, lanes): noisy copies of each reference."""
    if n_dum < 1:
        raise ValueError("at least one dummy of each reference")
    rows = spread(refs.select("ref_id", *LANES), "ref_id").select("ref_id", F.explode(F.sequence(F.lit(0), F.lit(n_dum - 1))).alias("dum_no"), *LANES)
    return flipped(rows, F.concat_ws("|", F.lit(key), F.lit("dum"), F.col("ref_id").cast("string"), F.col("dum_no").cast("string")), p_flip)


def pool(released: DataFrame, refs: DataFrame, dums: DataFrame, hold_out_source: bool = False) -> DataFrame:
    """Real rows, references and dummies in one table; `hold_out_source` drops the records that were sampled."""
    if hold_out_source and "rec_id" in refs.columns:
        released = released.join(refs.select("owner", "rec_id"), ["owner", "rec_id"], "left_anti")
    none = F.lit(None).cast("bigint")
    real = released.select(F.concat_ws("|", F.lit("real"), "owner", F.col("rec_id").cast("string")).alias("row_id"), F.lit("real").alias("kind"), none.alias("ref_id"), *LANES)
    ref = refs.select(F.concat_ws("|", F.lit("ref"), F.col("ref_id").cast("string")).alias("row_id"), F.lit("ref").alias("kind"), "ref_id", *LANES)
    dum = dums.select(F.concat_ws("|", F.lit("dum"), F.col("ref_id").cast("string"), F.col("dum_no").cast("string")).alias("row_id"), F.lit("dum").alias("kind"), "ref_id", *LANES)
    return real.unionByName(ref).unionByName(dum)
