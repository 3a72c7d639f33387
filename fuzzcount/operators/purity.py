"""How well decoys are grouped: the Jaccard index of a reference's dummies and its cluster."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut

#: Sums of purities are whole numbers of this part: they do not depend on the order, and 30 000 times 1 fits.
UNIT = float(1 << 48)
EVENT = ("label", "k", "until", "dummies", "own")


def per_reference(labels: DataFrame) -> DataFrame:
    """(k, ref_id, label, purity) from (k, row_id, kind, ref_id, label).

    Only counts are needed: of each cluster, and of each reference's own dummies in it.  A purity of
    nothing over nothing is 0.
    """
    sizes = labels.groupBy("k", "label").agg(F.count("*").alias("n_c"))
    refs = labels.where("kind = 'ref'").select("k", "ref_id", "label")
    dums = labels.where("kind = 'dum'").groupBy("k", "ref_id").agg(F.count("*").alias("n_dum"))
    own = labels.where("kind = 'dum'").groupBy("k", "ref_id", "label").agg(F.count("*").alias("x"))
    joined = refs.join(sizes, ["k", "label"]).join(dums, ["k", "ref_id"]).join(own, ["k", "ref_id", "label"], "left")
    x = F.coalesce("x", F.lit(0))
    below = F.col("n_dum") + F.col("n_c") - 1 - x
    return joined.select("k", "ref_id", "label", F.when(below == 0, 0.0).otherwise(x / below).alias("purity"))


def curve(labels: DataFrame) -> DataFrame:
    """(k, purity, mean_purity, n_ref)."""
    return per_reference(labels).groupBy("k").agg(F.sum("purity").alias("purity"), F.avg("purity").alias("mean_purity"), F.count("*").alias("n_ref"))


def curve_of_changes(changes: DataFrame, k_max: int) -> DataFrame:
    """`curve` from the rows of `clustering.prefix_changes`, by the changes of a reference's own cluster.

    Clusters are dealt over tasks by label: a task adds up how the sizes of its clusters change, only while a reference is
    in them, and from it and the dummies that stay with the reference how its purity changes from k to k + 1.
    """
    spark, changes = changes.sparkSession, cut(changes)  # read twice
    tasks = 16 * spark.sparkContext.defaultParallelism
    last, n_ref = np.zeros(k_max + 2, np.int64), 0
    for moves in changes.where("ref_id IS NOT NULL").select("moves").toPandas()["moves"]:
        last[moves] = np.maximum(last[moves], np.r_[moves[1:], k_max + 1])
        n_ref += 1
    shared = spark.sparkContext.broadcast(last)  # the k at which the last reference leaves a label

    def stays(p) -> tuple[np.ndarray, ...]:
        """(label, k, until, dummies, own) of a reference: so many of its dummies are its `own` cluster's from `k` on."""
        moves, k, before, n = (np.asarray(x, np.int64) for x in (p.moves, p.k, p.before, p.n))
        stay = np.searchsorted(moves, k, side="right") - 1
        fresh = moves[stay] == k  # it moves as well
        leave = ~fresh & (before == moves[stay])
        here = np.bincount(stay[fresh], n[fresh], len(moves)).astype(np.int64) - 1  # but for itself
        at, own = np.r_[moves, k[leave]], np.r_[here, -n[leave]]
        order = np.argsort(at, kind="stable")
        at, own, stay = at[order], own[order], np.r_[np.arange(len(moves)), stay[leave]][order]
        total, begins = own.cumsum(), np.searchsorted(stay, np.arange(len(moves)))
        return moves[stay], at, np.r_[at[1:], k_max + 1], np.full(len(at), p.dummies), total - (total[begins] - here)[stay]

    def dealt(parts: list[tuple[np.ndarray, ...]]) -> pd.DataFrame:
        """Columns as arrays, those of a label in one of the `tasks` rows."""
        columns = [np.concatenate(x).astype(np.int32) for x in zip(*parts, strict=True)]
        order = np.argsort(columns[0] % tasks, kind="stable")
        ends = np.searchsorted(columns[0][order] % tasks, np.arange(1, tasks))
        return pd.DataFrame({"task": np.arange(tasks)} | {c: np.split(x[order], ends) for c, x in zip(EVENT, columns, strict=True)})

    def events(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Stays, and the changes of size of clusters that hold a reference, summed up in the task (`until` is 0)."""
        last, held, waiting, found, many = shared.value, [], 0, [], 0

        def added() -> tuple[np.ndarray, np.ndarray]:
            keys, at = np.unique(np.concatenate([x for x, _ in held]), return_inverse=True)
            return keys, np.bincount(at, np.concatenate([n for _, n in held]), len(keys)).astype(np.int64)

        for frame in frames:
            for p in frame.itertuples():
                k, before, n = (np.asarray(x, np.int64) for x in (p.k, p.before, p.n))
                for label, sign in ((k, 1), (before, -1)):
                    needed = k < last[label]
                    held.append((label[needed] << 32 | k[needed], sign * n[needed]))
                    waiting += len(held[-1][0])
                if len(p.moves):
                    found.append(stays(p))
                    many += len(found[-1][0])
                if waiting > 2_000_000:
                    held, waiting = [added()], 0
                if many > 1_000_000:
                    yield dealt(found)
                    found, many = [], 0
        if held:
            keys, n = added()
            none = np.zeros(len(keys), np.int64)
            yield dealt([*found, (keys >> 32, keys & 0xFFFFFFFF, none, none, n)])

    def purities(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """(k, purity) where the sum of purities changes, in UNITs, by the clusters of the task."""
        parts, change = [*frames], np.zeros(k_max + 2, np.int64)
        if not parts:
            return
        label, k, until, dummies, own = (np.concatenate([x for f in parts for x in f[c]]).astype(np.int64) for c in EVENT)
        del parts
        size, stay, at = np.flatnonzero(until == 0), np.flatnonzero(until), label << 32 | k
        size = size[np.argsort(at[size])]
        keys, total = at[size], np.r_[0, own[size].cumsum()]
        opens = total[np.searchsorted(keys, label[stay] << 32)]  # before the label's first change
        begin, end = np.searchsorted(keys, at[stay], side="right"), np.searchsorted(keys, label[stay] << 32 | until[stay])
        times = 1 + end - begin  # a purity at its begin, and with every change of size
        cuts = np.unique(np.r_[0, np.searchsorted(times.cumsum(), np.arange(1_000_000, times.sum(), 1_000_000)), len(stay)])
        for low, high in zip(cuts[:-1], cuts[1:], strict=True):
            r = np.repeat(np.arange(low, high), times[low:high])
            turn = np.arange(len(r)) - np.repeat(times[low:high].cumsum() - times[low:high], times[low:high])
            place, row = begin[r] + turn, stay[r]
            below = dummies[row] + total[place] - opens[r] - 1 - own[row]
            value = np.rint(np.where(below > 0, own[row] / np.maximum(below, 1), 0.0) * UNIT).astype(np.int64)
            since = np.where(turn > 0, keys[place - 1] & 0xFFFFFFFF, k[row])
            to = np.where(turn + 1 < times[r], np.r_[since[1:], 0], until[row])
            np.add.at(change, since, value)
            np.subtract.at(change, to, value)
        at = np.flatnonzero(change)
        yield pd.DataFrame({"k": at, "purity": change[at]})

    def walk(frame: pd.DataFrame) -> pd.DataFrame:
        change = np.zeros(k_max + 2, np.int64)
        change[frame["k"]] = frame["purity"]
        purity = change[1 : k_max + 1].cumsum() / UNIT
        return pd.DataFrame({"k": np.arange(1, k_max + 1), "purity": purity, "mean_purity": purity / max(n_ref, 1), "n_ref": n_ref})

    found = changes.mapInPandas(events, "task int, " + ", ".join(f"{c} array<int>" for c in EVENT))
    sums = found.repartition(tasks, "task").mapInPandas(purities, "k bigint, purity bigint").groupBy("k").agg(F.sum("purity").alias("purity"))
    return sums.groupBy().applyInPandas(walk, "k bigint, purity double, mean_purity double, n_ref bigint")  # a row for each k


def occupied(labels: DataFrame) -> DataFrame:
    """(k, k_occupied, k_nonempty): clusters that hold a real record, and clusters that hold anything."""
    return labels.groupBy("k").agg(F.count_distinct(F.when(F.col("kind") == "real", F.col("label"))).alias("k_occupied"), F.count_distinct("label").alias("k_nonempty"))


def best_k(curve_rows: DataFrame, tie: str = "first") -> DataFrame:
    """(k_star, purity, k_lo, k_hi): the k of largest purity, and the ends of its plateau."""
    rounded = curve_rows.select("k", F.round("purity", 9).alias("p"))
    top = rounded.groupBy("p").agg(F.min("k").alias("k_lo"), F.max("k").alias("k_hi")).orderBy(F.desc("p")).limit(1)
    return top.select(F.col("k_lo" if tie == "first" else "k_hi").alias("k_star"), F.col("p").alias("purity"), "k_lo", "k_hi")
