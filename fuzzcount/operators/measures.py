"""Errors, grouping quality against the truth, distances under noise."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def count_error(k_star: Column, truth: Column) -> Column:
    return F.abs(k_star - truth)


def error_rate(k_star: Column, truth: Column) -> Column:
    return count_error(k_star, truth) / truth


def pairwise_quality(labels: DataFrame) -> DataFrame:
    """(precision, recall, f1) of pairs of (label, truth) rows, from the contingency table alone."""
    pairs = lambda c: (c * (c - 1) / 2).cast("double")
    cells = labels.groupBy("label", "truth").agg(F.count("*").alias("n"))
    both = cells.agg(F.sum(pairs(F.col("n"))).alias("tp"))
    found = cells.groupBy("label").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("found"))
    true = cells.groupBy("truth").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("true"))
    one = both.join(F.broadcast(found), F.lit(True)).join(F.broadcast(true), F.lit(True))  # one row each
    p, r = F.col("tp") / F.col("found"), F.col("tp") / F.col("true")
    return one.select(F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / (p + r), 6).alias("f1"))


def cluster_quality(labels: DataFrame) -> DataFrame:
    """(purity, completeness) of (label, truth) rows: shares of rows in their label's, and in their individual's, largest cell."""
    cells = labels.groupBy("label", "truth").agg(F.count("*").alias("n"))
    of = lambda by: cells.groupBy(by).agg(F.max("n").alias("most"), F.sum("n").alias("n")).agg((F.sum("most") / F.sum("n")).alias(by))
    return of("label").join(F.broadcast(of("truth")), F.lit(True)).select(F.round("label", 6).alias("purity"), F.round("truth", 6).alias("completeness"))  # one row each


def flip_audit(before: DataFrame, after: DataFrame, epsilon: float, ell: int = 200) -> DataFrame:
    """(owner, bits, flips, rate, low, high): the flip rate of each owner and the four-sigma band around the stated one."""
    from fuzzcount.functions.noise import flip_rate
    from fuzzcount.functions.similarity import hamming

    x, y = before.alias("x"), after.alias("y")
    joined = x.join(y, (F.col("x.owner") == F.col("y.owner")) & (F.col("x.rec_id") == F.col("y.rec_id")))
    found = joined.groupBy("x.owner").agg((F.count("*") * ell).alias("bits"), F.sum(hamming("x", "y")).alias("flips"))
    q = flip_rate(epsilon)
    band = 4 * F.sqrt(q * (1 - q) / F.col("bits"))
    return found.select("owner", "bits", "flips", F.round(F.col("flips") / F.col("bits"), 6).alias("rate"), F.round(q - band, 6).alias("low"), F.round(q + band, 6).alias("high"))


#: Measures of all pairs take the records of one cell.
MOST_PAIRED = 20_000


def _of_one_cell(rows: DataFrame) -> None:
    if rows.count() > MOST_PAIRED:
        raise ValueError(f"all pairs of more than {MOST_PAIRED} records: measure a cell")


def min_inter_distance(rows: DataFrame) -> DataFrame:
    """(d): least distance of records of different individuals, all pairs of one cell."""
    from fuzzcount.functions.similarity import hamming

    _of_one_cell(rows)
    x, y = rows.alias("x"), rows.alias("y")
    return x.join(y, (F.col("x.rec_id") < F.col("y.rec_id")) & (F.col("x.entity_id") != F.col("y.entity_id"))).agg(F.min(hamming("x", "y")).alias("d"))


def distance_histogram(rows: DataFrame) -> DataFrame:
    """(same, d, n): how many pairs of one cell lie so far apart, those of one individual and the others."""
    from fuzzcount.functions.similarity import hamming

    _of_one_cell(rows)
    x, y = rows.alias("x"), rows.alias("y")
    return x.join(y, F.col("x.rec_id") < F.col("y.rec_id")).groupBy((F.col("x.entity_id") == F.col("y.entity_id")).alias("same"), hamming("x", "y").alias("d")).agg(F.count("*").alias("n"))


def radius_constraints(rows: DataFrame, radius: int) -> DataFrame:
    """(same_within, different_beyond): shares of pairs that keep the two constraints of a good radius."""
    from fuzzcount.functions.similarity import hamming

    _of_one_cell(rows)
    x, y = rows.alias("x"), rows.alias("y")
    pairs = x.join(y, F.col("x.rec_id") < F.col("y.rec_id")).select((F.col("x.entity_id") == F.col("y.entity_id")).alias("same"), hamming("x", "y").alias("d"))
    return pairs.agg(
        F.round(F.avg(F.when(F.col("same"), (F.col("d") <= radius).cast("double"))), 6).alias("same_within"), F.round(F.avg(F.when(~F.col("same"), (F.col("d") > radius).cast("double"))), 6).alias("different_beyond")
    )
