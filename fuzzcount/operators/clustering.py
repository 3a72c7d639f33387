"""Clustering of filters: nested seeds, Lloyd steps in SQL, NumPy inside one cell, and Spark ML.

The nested-seed sweep assigns every row to the nearest of the first k seeds for all k at once: one join
with the seeds and a running minimum, instead of a job for each k.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from fuzzcount.functions.bloom import ELL, LANE, LANES
from fuzzcount.functions.digest import num
from fuzzcount.functions.similarity import hamming
from fuzzcount.operators import decoys

#: A full sweep compares each row with each seed; larger pools go through cells or the coarse search.
MOST_SWEPT = 20_000
#: Distances at once: they stay in a core's cache.
COMPARED_AT_ONCE = 40_000


def seeds(pool: DataFrame, k_max: int, key: str = "k") -> DataFrame:
    """(rank, lanes) of the first `k_max` rows by a keyed draw."""
    drawn = pool.withColumn("draw", num(F.concat_ws("|", F.lit(key), F.lit("seed"), F.col("row_id"))))
    few = drawn.orderBy("draw", "row_id").limit(k_max).groupBy().agg(F.array_sort(F.collect_list(F.struct("draw", "row_id", *LANES))).alias("all"))
    return few.select(F.posexplode("all").alias("n", "s")).select((F.col("n") + 1).alias("rank"), *(f"s.{w}" for w in LANES))


def prefix_labels(pool: DataFrame, k_max: int, key: str = "k") -> DataFrame:
    """(k, row_id, kind, ref_id, label): for each k the nearest of the first k seeds, ties to the earlier seed."""
    if k_max > MOST_SWEPT:
        raise ValueError(f"a full sweep takes at most {MOST_SWEPT} seeds; use cells or the coarse search")
    x, s = pool.alias("x"), F.broadcast(seeds(pool, k_max, key)).alias("s")  # k_max rows, checked above
    near = x.join(s, F.col("s.rank") > 0).select("x.row_id", "x.kind", "x.ref_id", F.col("s.rank").alias("k"), F.struct(hamming("x", "s").alias("d"), F.col("s.rank").alias("r")).alias("seen"))
    to_here = Window.partitionBy("row_id").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    return near.select("k", "row_id", "kind", "ref_id", F.min("seen").over(to_here)["r"].alias("label"))


def dense_words(frame: pd.DataFrame) -> np.ndarray:
    """The lanes of a table as rows of 64-bit words without gaps: the first word tells most rows apart."""
    lanes = [frame[w].to_numpy(np.int64).astype(np.uint64) for w in LANES]
    out = np.zeros((-(-ELL // 64), len(frame)), np.uint64)
    for i, lane in enumerate(lanes):
        word, bit = divmod(i * LANE, 64)
        out[word] |= lane << np.uint64(bit)
        if bit + LANE > 64:
            out[word + 1] |= lane >> np.uint64(64 - bit)
    return out


def nearer_seeds(rows: np.ndarray, first: np.ndarray, centre: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(row, seed) in order of rows, then seeds, wherever a seed is nearer to a row than all seeds before it; all as `dense_words`.

    The words' distance bounds that of the filters from below.  With a `centre` that the rows are near to, so does its
    distance to the seed less that to the row: only seeds that can be nearer than the nearest so far are compared.
    """
    m, k_max = rows.shape[1], first.shape[1]
    least, found, start, size = np.full(m, ELL + 1, np.int16), [], 0, 64
    if centre is not None:
        near, own = (np.bitwise_count(x[0] ^ centre[0]).astype(np.int16) for x in (first, rows))
    while start < k_max:
        stop = min(k_max, start + size)
        parts = [(np.arange(m), np.arange(start, stop))]
        if centre is not None and start:
            bound = least + own
            parts = [(np.sort(part), start + np.flatnonzero(near[start:stop] < bound[part].max())) for part in np.array_split(np.argsort(bound), min(m, 8))]
        for part, seeds in parts:
            x, least_of, step = rows[:, part], least[part].astype(np.uint8), max(1, COMPARED_AT_ONCE // len(part))
            for at in range(0, len(seeds), step):
                s = first[:, seeds[at : at + step]]
                gaps = np.bitwise_count(s[0][:, None] ^ x[0])
                hit = np.flatnonzero(gaps < least_of)
                if len(hit) > gaps.size / 12:
                    for left, right in zip(s[1:], x[1:], strict=True):
                        gaps += np.bitwise_count(left[:, None] ^ right)
                    hit = np.flatnonzero(gaps < least_of)
                    seed, row = np.divmod(hit, len(part))
                    gap = gaps.ravel()[hit]
                else:
                    seed, row = np.divmod(hit, len(part))
                    gap = gaps.ravel()[hit]
                    for left, right in zip(s[1:], x[1:], strict=True):
                        gap += np.bitwise_count(left[seed] ^ right[row])
                    keep = gap < least_of[row]
                    seed, row, gap = seed[keep], row[keep], gap[keep]
                if not len(row):
                    continue
                order = np.argsort(row, kind="stable")
                row, seed = row[order], seed[order]
                falling = gap[order].astype(np.int64) - 256 * row  # below all of the rows before: their minima end there
                new = np.r_[True, falling[1:] < np.minimum.accumulate(falling)[:-1]]
                row, seed, gap = row[new], seed[new], gap[order][new]
                found.append((part[row], seeds[at + seed]))
                least_of[row] = gap  # the last one of each row counts
            least[part] = least_of
        start, size = stop, min(2 * size, 8192)
    row, seed = (np.concatenate([f[i] for f in found]) for i in (0, 1))
    order = np.argsort(row.astype(np.int64) * k_max + seed)
    return row[order], seed[order]


def prefix_changes(pool: DataFrame, k_max: int, key: str = "k") -> DataFrame:
    """The changes of `prefix_labels` from k - 1 to k, about ln k_max for each row, counted over the decoys of a reference or some real rows.

    One row (ref_id, dummies, moves, k, before, n) for each such group: at each `k`, `n` of its rows leave the label `before` (0:
    the first k) for the only new one, k; the reference itself does at the `moves`.
    """
    drawn = pool.withColumn("draw", num(F.concat_ws("|", F.lit(key), F.lit("seed"), F.col("row_id"))))
    first = decoys.ranked(drawn, k_max, "draw", "row_id").select("rank", *LANES).toPandas().sort_values("rank")
    shared = pool.sparkSession.sparkContext.broadcast(dense_words(first))

    def changes(group: pd.DataFrame) -> pd.DataFrame:
        rows, ref = dense_words(group), np.flatnonzero(group["kind"] == "ref")
        row, seed = nearer_seeds(rows, shared.value, rows[:, ref[0]] if len(ref) else None)
        before = np.where(np.r_[False, row[1:] == row[:-1]], np.r_[0, seed[:-1] + 1], 0)
        both, n = np.unique((seed.astype(np.int64) + 1) << 32 | before, return_counts=True)
        moves = seed[row == ref[0]] + 1 if len(ref) else seed[:0]
        out = {"ref_id": group["ref_id"].astype("Int64").iloc[:1].array, "dummies": [int((group["kind"] == "dum").sum())]}
        return pd.DataFrame(out | {c: [v.astype(np.int32)] for c, v in (("moves", moves), ("k", both >> 32), ("before", both & 0xFFFFFFFF), ("n", n))})

    some = -1 - F.pmod(F.xxhash64("row_id"), F.lit(1 + k_max // 1000))  # real rows by the thousand
    tasks = 16 * pool.sparkSession.sparkContext.defaultParallelism  # a group is a fraction of a second of work
    dealt = pool.select(F.coalesce("ref_id", some).alias("group"), "kind", "ref_id", *LANES).repartition(tasks, "group")
    return dealt.groupBy("group").applyInPandas(changes, "ref_id bigint, dummies bigint, moves array<int>, k array<int>, before array<int>, n array<int>")


def prefix_inertia(rows: DataFrame, first: DataFrame) -> DataFrame:
    """(k, sse): the rows' squared distances to the nearest of the first k seeds, summed, for every k."""
    x, s = rows.alias("x"), F.broadcast(first).alias("s")  # MOST_SWEPT rows at most
    near = x.join(s, F.col("s.rank") > 0).select("x.row_id", F.col("s.rank").alias("k"), hamming("x", "s").alias("d"))
    least = F.min("d").over(Window.partitionBy("row_id").orderBy("k").rowsBetween(Window.unboundedPreceding, 0))
    return near.select("k", least.alias("d")).groupBy("k").agg(F.sum("d").cast("bigint").alias("sse"))


def bits_long(rows: DataFrame, ids: list[str], ell: int = ELL) -> DataFrame:
    """(ids, bit, value) in long form."""
    lane = F.element_at(F.array(*LANES), (F.floor(F.col("bit") / LANE) + 1).cast("int"))
    return rows.select(*ids, *LANES, F.explode(F.sequence(F.lit(0), F.lit(ell - 1))).alias("bit")).select(*ids, "bit", F.getbit(lane, F.pmod("bit", F.lit(LANE)).cast("int")).cast("int").alias("value"))


def centroids(labelled: DataFrame) -> DataFrame:
    """(label, bit, mean): Lloyd's update of a labelled table (label, lanes)."""
    return bits_long(labelled, ["label"]).groupBy("label", "bit").agg(F.avg("value").alias("mean"))


def assign(rows: DataFrame, centres: DataFrame) -> DataFrame:
    """(row_id, label): nearest centre by squared distance to 9 places; ties to the smaller label.  Centres are broadcast: 200 numbers each."""
    packed = centres.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("bit", "mean"))), lambda b: b["mean"]).alias("centre")).toPandas().sort_values("label")
    shared = rows.sparkSession.sparkContext.broadcast((packed["label"].to_numpy(), np.stack(packed["centre"]).astype(np.float64)))

    def nearest(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        labels, centre = shared.value
        norms = (centre * centre).sum(1)
        for frame in frames:
            for first in range(0, len(frame), 1000):  # a matrix of 200 numbers each
                part = frame.iloc[first : first + 1000]
                x = unpack(part).astype(np.float64)
                gaps = (x.sum(1)[:, None] - 2 * x @ centre.T + norms).round(9)
                yield pd.DataFrame({"row_id": part["row_id"], "label": labels[gaps.argmin(1)]})

    out = StructType([rows.schema["row_id"], centres.schema["label"]])
    return rows.select("row_id", *LANES).mapInPandas(nearest, out)


def unpack(frame) -> np.ndarray:
    """The bits of a pandas table of lanes as a 0/1 matrix."""
    lanes = frame[list(LANES)].to_numpy(np.int64)
    return ((lanes[:, :, None] >> np.arange(LANE)) & 1).reshape(len(lanes), -1).astype(np.float32)


def lloyd(x: np.ndarray, centre: np.ndarray, rounds: int, labels: np.ndarray | None, norms: np.ndarray) -> np.ndarray:
    """Labels after some rounds from the centres, which move in place; `labels`, if given, are the first assignment."""
    for turn in range(rounds):
        if turn or labels is None:
            new = (norms[:, None] - 2 * x @ centre.T + (centre * centre).sum(1)).argmin(1)
            if labels is not None and (new == labels).all():
                return labels
            labels = new
        order = np.argsort(labels, kind="stable")
        present, starts = np.unique(labels[order], return_index=True)
        centre[present] = np.add.reduceat(x[order], starts, axis=0) / np.diff(np.r_[starts, len(x)])[:, None]
    return (norms[:, None] - 2 * x @ centre.T + (centre * centre).sum(1)).argmin(1)


class OneRound:
    """Labels after one Lloyd round for k = 1, 2, ... nested seeds, by what changes from one k to the next.

    A new seed takes rows from few clusters; only their centres move.  Rows nearest to one that moved are compared
    with all centres, the others with those that moved.  Equals `lloyd` up to the rounding of equal distances.
    """

    def __init__(self, x: np.ndarray, norms: np.ndarray, k_max: int):
        self.x, self.norms, self.k = x, norms, 0
        self.seeds, self.centre = (np.empty((k_max, x.shape[1]), x.dtype) for _ in range(2))
        self.first = self.near = np.zeros(len(x), np.int64)
        self.gap = np.empty(len(x), x.dtype)

    def _gaps(self, rows: np.ndarray | slice, centre: np.ndarray) -> np.ndarray:
        return self.norms[rows, None] - 2 * self.x[rows] @ centre.T + (centre * centre).sum(1)

    def _nearest(self, rows: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of the `rows` the nearest of the centres `labels` and its distance, in blocks of a few million numbers."""
        near, gap, step = np.empty(len(rows), np.int64), np.empty(len(rows), self.x.dtype), max(1, 4_000_000 // len(labels))
        for at in range(0, len(rows), step):
            gaps = self._gaps(rows[at : at + step], self.centre[labels])
            best = gaps.argmin(1)
            near[at : at + step], gap[at : at + step] = labels[best], gaps[np.arange(len(best)), best]
        return near, gap

    def after(self, labels: np.ndarray, seed: int) -> np.ndarray:
        """The labels after the round, from the first `labels` with one more seed."""
        k = self.k
        self.seeds[k] = self.x[seed]
        moved = np.zeros(k + 1, bool)
        moved[self.first[labels != self.first]] = moved[k] = True
        changed = np.flatnonzero(moved)
        self.centre[changed] = self.seeds[changed]  # kept where no row is left
        rows = np.flatnonzero(moved[labels])
        if len(rows):
            order = rows[np.argsort(labels[rows], kind="stable")]
            present, starts = np.unique(labels[order], return_index=True)
            self.centre[present] = np.add.reduceat(self.x[order], starts, axis=0) / np.diff(np.r_[starts, len(order)])[:, None]
        lost = moved[self.near] if k else np.ones(len(self.x), bool)
        near, anew, rest = self.near.copy(), np.flatnonzero(lost), np.flatnonzero(~lost)
        near[anew], self.gap[anew] = self._nearest(anew, np.arange(k + 1))
        other, gap = self._nearest(rest, changed)
        better = (gap < self.gap[rest]) | (gap == self.gap[rest]) & (other < near[rest])
        near[rest[better]], self.gap[rest[better]] = other[better], gap[better]
        self.first, self.near, self.k = labels.copy(), near, k + 1
        return near


def kmeans_labels(x: np.ndarray, k: int, rng: np.random.Generator, iters: int = 15, restarts: int = 1, init: str = "k-means++") -> np.ndarray:
    """Labels of the best of some runs; an empty cluster keeps its centre."""
    best, best_cost = None, np.inf
    norms = (x * x).sum(1)
    for _ in range(restarts):
        if init == "random":
            centre = x[rng.choice(len(x), k, replace=False)].copy()
        else:
            chosen = [int(rng.integers(len(x)))]
            gap = norms + norms[chosen[0]] - 2 * x @ x[chosen[0]]
            for _ in range(k - 1):
                weight = np.maximum(gap, 0)
                total = weight.sum()
                at = int(rng.choice(len(x), p=weight / total)) if total > 0 else int(rng.integers(len(x)))
                chosen.append(at)
                gap = np.minimum(gap, norms + norms[at] - 2 * x @ x[at])
            centre = x[chosen].copy()
        labels = lloyd(x, centre, iters, None, norms)
        cost = float(np.maximum((x - centre[labels]) ** 2, 0).sum())
        if cost < best_cost:
            best, best_cost = labels, cost
    return best


def ml_labels(pool: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """(row_id, label) by Spark ML's k-means on the unpacked bits: for pools beyond one cell."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    lane = lambda i: F.element_at(F.array(*LANES), (F.floor(i / LANE) + 1).cast("int"))
    flat = F.transform(F.sequence(F.lit(0), F.lit(ELL - 1)), lambda i: F.getbit(lane(i), F.pmod(i, F.lit(LANE)).cast("int")).cast("double"))
    rows = pool.select("row_id", array_to_vector(flat).alias("features"))
    return KMeans(k=k, seed=seed).fit(rows).transform(rows).select("row_id", F.col("prediction").alias("label"))
