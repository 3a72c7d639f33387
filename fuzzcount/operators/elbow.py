"""Baselines that choose k without decoys: silhouette, Calinski-Harabasz and the inertia knee."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: The exact silhouette compares all pairs of a cell; larger tables take the cluster-moment form.
MOST_COMPARED = 20_000
#: Rows whose distances to all others are held at a time: 160 MB at most.
COMPARED_AT_ONCE = 1_000


def silhouette(rows: DataFrame) -> DataFrame:
    """(silhouette) of (id, v array, label), exact, by Euclidean distance; a row alone counts 0, a single label gives null."""
    if rows.count() > MOST_COMPARED:
        raise ValueError(f"more than {MOST_COMPARED} rows: use silhouette_moments")
    found = rows.select("v", "label").toArrow()  # the rows of one cell, checked above
    labels, own = np.unique(found.column("label").to_numpy(), return_inverse=True)
    every = np.array(found.column("v").to_pylist(), np.float64).reshape(len(own), -1)
    shared = rows.sparkSession.sparkContext.broadcast((every, labels, np.eye(len(labels))[own]))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every, labels, member = shared.value
        squares, sizes = (every * every).sum(1), member.sum(0)
        for batch in batches:
            for at in range(0, batch.num_rows, COMPARED_AT_ONCE):
                part = batch.slice(at, COMPARED_AT_ONCE)
                x, own = np.array(part.column(0).to_pylist(), np.float64), np.searchsorted(labels, part.column(1).to_numpy(zero_copy_only=False))
                sums = np.sqrt(np.maximum((x * x).sum(1)[:, None] + squares - 2 * x @ every.T, 0)) @ member
                line = np.arange(len(x))
                a = sums[line, own] / np.maximum(sizes[own] - 1, 1)
                means = sums / sizes
                means[line, own] = np.inf
                b = means.min(1)
                score = np.where(sizes[own] > 1, (b - a) / np.maximum(np.maximum(a, b), 1e-300), 0.0)
                yield pa.RecordBatch.from_arrays([pa.array(score if len(labels) > 1 else [None] * len(x), pa.float64())], names=["score"])

    return rows.select("v", "label").mapInArrow(compare, "score double").agg(F.avg("score").alias("silhouette"))


def silhouette_moments(rows: DataFrame) -> float:
    """The same by squared distances and cluster moments (Spark ML): linear in the rows."""
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.functions import array_to_vector

    return ClusteringEvaluator(predictionCol="label").evaluate(rows.select(array_to_vector("v").alias("features"), F.col("label").cast("double").alias("label")))


def moments(rows: DataFrame) -> DataFrame:
    """(label, d, n, s, q): count, sum and sum of squares of each coordinate."""
    long = rows.select("label", F.posexplode("v").alias("d", "x"))
    return long.groupBy("label", "d").agg(F.count("*").alias("n"), F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("q"))


def inertia(rows: DataFrame) -> DataFrame:
    """(label, n, sse): squared distances to the label's mean."""
    return moments(rows).groupBy("label").agg(F.max("n").alias("n"), F.sum(F.col("q") - F.col("s") * F.col("s") / F.col("n")).alias("sse"))


def calinski_harabasz(rows: DataFrame) -> DataFrame:
    """(k, n, within, between, score)."""
    m = moments(rows)
    total = m.groupBy("d").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("q").alias("q"), F.sum(F.col("s") * F.col("s") / F.col("n")).alias("means"))
    parts = total.agg(F.max("n").alias("n"), F.sum(F.col("q") - F.col("means")).alias("within"), F.sum(F.col("means") - F.col("s") * F.col("s") / F.col("n")).alias("between"))
    k = m.agg(F.count_distinct("label").alias("k"))
    score = (F.col("between") / (F.col("k") - 1)) / (F.col("within") / (F.col("n") - F.col("k")))
    return parts.join(F.broadcast(k), F.col("k") > 1).select("k", "n", "within", "between", score.alias("score"))  # one row


def knee(curve: DataFrame) -> DataFrame:
    """(k, sse, bend): second difference of an inertia curve (k, sse)."""
    order = Window.orderBy("k")
    return curve.select("k", "sse", (F.lag("sse").over(order) - 2 * F.col("sse") + F.lead("sse").over(order)).alias("bend"))
