"""The counter: released filters in, the number of individuals out.

Configurations (budget, method, flip probability, seed) are rows; each is searched in a task of its own over the
packed filters of one cell.  `private_count` is the exactly reproducible engine on nested seeds.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import LANES
from fuzzcount.functions.noise import perturb
from fuzzcount.operators import clustering, decoys, purity

#: Rows of one cell: its matrices have this squared numbers, 64 MB of each.
MOST_SEARCHED = 4_000
#: Decoys whose draws are held at a time: 16 MB.
DRAWN_AT_ONCE = 10_000


@dataclass(frozen=True)
class SearchSpec:
    method: str = "B"
    pick_ratio: float = 0.1
    dummy_ratio: float = 0.1
    dummy_base: str = "references"
    p_flip: float = 0.1
    tie: str = "first"
    hold_out_source: bool = False
    key: str = "k"
    density: float = 0.5


def build_pool(released: DataFrame, n: int, spec: SearchSpec) -> DataFrame:
    """The training pool of n released records."""
    n_ref, n_dum = decoys.counts_for(n, spec.pick_ratio, spec.dummy_ratio, spec.dummy_base)
    refs = decoys.invent(released.sparkSession, n_ref, spec.key, spec.density) if spec.method == "A" else decoys.sample(released, n_ref, spec.key)
    return decoys.pool(released, refs, decoys.dummies(refs, n_dum, spec.p_flip, spec.key), spec.hold_out_source)


def private_count(encoded: DataFrame, n: int, epsilon: float, spec: SearchSpec = SearchSpec(), k_max: int | None = None) -> DataFrame:
    """(k_star, purity, k_lo, k_hi, k_occupied, k_nonempty) by the nested-seed sweep."""
    released = perturb(encoded.select("owner", "rec_id", *LANES), epsilon, spec.key)
    labels = clustering.prefix_labels(build_pool(released, n, spec), k_max or n, spec.key)
    best = purity.best_k(purity.curve(labels), spec.tie)
    return best.join(purity.occupied(labels), best["k_star"] == F.col("k")).drop("k")


def purity_of(labels: np.ndarray, n_real: int, n_ref: int, n_dum: int) -> float:
    """Sum of purities when rows are real records, references, and the dummies of each reference in turn."""
    sizes = np.bincount(labels)
    refs = labels[n_real : n_real + n_ref]
    own = (labels[n_real + n_ref :].reshape(n_ref, n_dum) == refs[:, None]).sum(1)
    below = n_dum + sizes[refs] - 1 - own
    return float(np.where(below > 0, own / np.maximum(below, 1), 0.0).sum())


def silhouette_of(x: np.ndarray, labels: np.ndarray, distance: np.ndarray) -> float:
    """Mean silhouette by Euclidean distance; a row alone in its cluster counts 0."""
    _, labels = np.unique(labels, return_inverse=True)
    k = labels.max() + 1
    if k < 2 or k >= len(x):
        return 0.0
    order, sizes = np.argsort(labels, kind="stable"), np.bincount(labels)
    sums = np.add.reduceat(distance[:, order], np.r_[0, np.cumsum(sizes)[:-1]], axis=1)
    rows = np.arange(len(x))
    own = sizes[labels]
    a = sums[rows, labels] / np.maximum(own - 1, 1)
    other = sums / sizes
    other[rows, labels] = np.inf
    b = other.min(1)
    return float(np.where(own > 1, (b - a) / np.maximum(np.maximum(a, b), 1e-12), 0.0).mean())


RESULTS = "fixture string, eps double, method string, p_flip double, seed bigint, rounds bigint, n bigint, k_star bigint, k_occupied bigint, score double, truth bigint, err bigint, err_rate double, seconds double"
#: Choices of k without decoys.
BASELINES = ("silhouette", "calinski_harabasz", "knee")


@dataclass(frozen=True)
class Cell:
    """The released bits of one cell and, for methods A and B, the pool with decoys."""

    x: np.ndarray
    pool: np.ndarray
    n_ref: int
    n_dum: int

    @classmethod
    def drawn(cls, bits: np.ndarray, eps: float, method: str, p_flip: float, rng: np.random.Generator, pick_ratio: float = 0.1, dummy_ratio: float = 0.1, dummy_base: str = "references") -> Cell:
        x = np.abs(bits - (rng.random(bits.shape) < 1 / (1 + np.exp(eps)))).astype(np.float32)
        if method in BASELINES:
            return cls(x, x, 0, 0)
        n_ref, n_dum = decoys.counts_for(len(x), pick_ratio, dummy_ratio, dummy_base)
        refs = (rng.random((n_ref, x.shape[1])) < 0.5).astype(np.float32) if method == "A" else x[rng.choice(len(x), n_ref, replace=False)]
        pool = np.empty((len(x) + n_ref + n_ref * n_dum, x.shape[1]), np.float32)
        pool[: len(x)], pool[len(x) : len(x) + n_ref] = x, refs
        dums = pool[len(x) + n_ref :]
        for at in range(0, len(dums), DRAWN_AT_ONCE):
            own = refs[np.arange(at, min(at + DRAWN_AT_ONCE, len(dums))) // n_dum]
            dums[at : at + DRAWN_AT_ONCE] = np.abs(own - (rng.random(own.shape) < p_flip))
        return cls(x, pool, n_ref, n_dum)


def all_labels(pool: np.ndarray, k_max: int, rng: np.random.Generator, rounds: int) -> Iterator[np.ndarray]:
    """Labels for k = 1, 2, ..., k_max: seeds drawn once by squared distance, of which k takes the first k, then Lloyd rounds."""
    norms = (pool * pool).sum(1)
    at, gap = int(rng.integers(len(pool))), None
    chosen, labels = [], np.zeros(len(pool), np.int64)
    one = clustering.OneRound(pool, norms, k_max) if rounds == 1 else None
    for k in range(1, k_max + 1):
        if gap is not None:
            total = np.maximum(gap, 0).cumsum()
            at = int(np.searchsorted(total, rng.random() * total[-1], side="right")) if total[-1] > 0 else int(rng.integers(len(pool)))
        chosen.append(min(at, len(pool) - 1))
        distance = norms + norms[chosen[-1]] - 2 * pool @ pool[chosen[-1]]
        if gap is None:
            gap = distance
        else:
            nearer = distance < gap
            labels = np.where(nearer, k - 1, labels)
            gap = np.where(nearer, distance, gap)
        if one:
            yield one.after(labels, chosen[-1])
        else:
            yield clustering.lloyd(pool, pool[chosen].copy(), rounds, labels, norms) if rounds else labels


def scores_of(cell: Cell, method: str, rng: np.random.Generator, rounds: int) -> list[tuple[int, float, int]]:
    """(k, score, clusters with a real record) for every k; the largest score is the choice."""
    n = len(cell.x)
    last = n - 1 if method in BASELINES else n
    found = []
    if method not in BASELINES:
        for k, labels in enumerate(all_labels(cell.pool, last, rng, rounds), 1):
            found.append((k, purity_of(labels, n, cell.n_ref, cell.n_dum), len(np.unique(labels[:n]))))
        return found
    squares = (cell.x * cell.x).sum(1)
    distance = np.sqrt(np.maximum(squares[:, None] + squares - 2 * cell.x @ cell.x.T, 0)) if method == "silhouette" else None
    total, mean = float(squares.sum()), cell.x.mean(0)
    spread = []
    for k, labels in enumerate(all_labels(cell.x, last, rng, rounds), 1):
        sizes = np.bincount(labels)
        used = int((sizes > 0).sum())
        if method == "silhouette":
            found.append((k, silhouette_of(cell.x, labels, distance), used))
            continue
        order = np.argsort(labels, kind="stable")
        sums = np.add.reduceat(cell.x[order], np.r_[0, np.flatnonzero(np.diff(labels[order])) + 1], axis=0)
        within = total - float(((sums * sums).sum(1) / sizes[sizes > 0]).sum())
        spread.append(max(within, 0.0))
        between = total - n * float(mean @ mean) - spread[-1]
        found.append((k, between / (used - 1) / max(spread[-1] / max(n - used, 1), 1e-9) if used > 1 else 0.0, used))
    if method == "knee":  # the sharpest bend of the curve of inertia
        bends = np.r_[0.0, np.diff(spread, 2), 0.0] if len(spread) > 2 else np.zeros(len(spread))
        found = [(k, float(b), used) for (k, _, used), b in zip(found, bends, strict=True)]
    return found


def search_cell(bits: np.ndarray, eps: float, method: str, p_flip: float, seed: int, rounds: int = 0, **ratios) -> tuple[int, int, float]:
    """(k_star, k_occupied, score) of one configuration on the clean bits of one cell: every k from 1 (2 for baselines) to n."""
    rng = np.random.default_rng(seed)
    found = scores_of(Cell.drawn(bits, eps, method, p_flip, rng, **ratios), method, rng, rounds)
    k, score, occupied = max((f for f in found if f[0] > 1 or method not in BASELINES), key=lambda f: (round(f[1], 9), -f[0]))
    return k, occupied, round(score, 9)


def search_vectors(x: np.ndarray, method: str, sigma: float, seed: int, rounds: int = 1) -> tuple[int, int, float]:
    """(k_star, k_occupied, score) for real vectors: decoys are references with Gaussian noise of `sigma` deviations of each coordinate."""
    rng, n, spread = np.random.default_rng(seed), len(x), x.std(0)
    n_ref, n_dum = (0, 0) if method in BASELINES else decoys.counts_for(n)
    refs = x.mean(0) + rng.normal(size=(n_ref, x.shape[1])) * spread if method == "A" else x[rng.choice(n, n_ref, replace=False)]
    dums = np.repeat(refs, n_dum, axis=0) + rng.normal(size=(n_ref * n_dum, x.shape[1])) * sigma * spread
    cell = Cell(x.astype(np.float32), np.vstack([x, refs, dums]).astype(np.float32), n_ref, n_dum)
    k, score, occupied = max((f for f in scores_of(cell, method, rng, rounds) if f[0] > 1 or method not in BASELINES), key=lambda f: (round(f[1], 9), -f[0]))
    return k, occupied, round(score, 9)


def search_coarse(bits: np.ndarray, eps: float, method: str, p_flip: float, seed: int, ks: list[int], rounds: int = 8) -> tuple[int, int, float]:
    """The same from a grid of k and a second one around its best: a cheaper search, which can miss a narrow peak."""
    rng = np.random.default_rng(seed)
    cell, found = Cell.drawn(bits, eps, method, p_flip, rng), {}
    squares = (cell.x * cell.x).sum(1)
    distance = np.sqrt(np.maximum(squares[:, None] + squares - 2 * cell.x @ cell.x.T, 0)) if method in BASELINES else None

    def judge(grid: list[int]) -> int:
        for k in grid:
            if k not in found and 2 <= k <= len(cell.x) - (method in BASELINES):
                labels = clustering.kmeans_labels(cell.pool, k, rng, iters=rounds)
                value = silhouette_of(cell.x, labels, distance) if method in BASELINES else purity_of(labels, len(cell.x), cell.n_ref, cell.n_dum)
                found[k] = (round(value, 9), -k, len(np.unique(labels[: len(cell.x)])))
        return -max(found.values())[1]

    judge(refine_ks(judge(ks), ks, 8))
    score, k, occupied = max(found.values())
    return -k, occupied, score


def sweep(spark: SparkSession, fixtures: dict[str, DataFrame], configs: list[tuple], rounds: int = 0, **ratios) -> DataFrame:
    """One result row for each configuration (fixture, eps, method, p_flip, seed), over every k.

    `fixtures` are encoded panels (entity_id, lanes) of one cell each (`MOST_SEARCHED` rows at most, checked);
    every configuration is searched in a group of its own.
    """
    cells = {}
    for name, df in fixtures.items():
        rows = df.select("entity_id", *LANES).limit(MOST_SEARCHED + 1).toPandas()
        if len(rows) > MOST_SEARCHED:
            raise ValueError(f"{name}: split pools of more than {MOST_SEARCHED} rows into cells first")
        cells[name] = rows.sort_values(["entity_id", *LANES]).reset_index(drop=True)
    table = spark.createDataFrame([(i, *c) for i, c in enumerate(configs)], "id int, fixture string, eps double, method string, p_flip double, seed bigint")
    shared = spark.sparkContext.broadcast(cells)

    def one(group: pd.DataFrame) -> pd.DataFrame:
        out = []
        for c in group.itertuples():
            rows = shared.value[c.fixture]
            truth = rows["entity_id"].nunique()
            began = time.perf_counter()
            k, occupied, score = search_cell(clustering.unpack(rows), c.eps, c.method, c.p_flip, int(c.seed), rounds, **ratios)
            out.append((c.fixture, c.eps, c.method, c.p_flip, c.seed, rounds, len(rows), k, occupied, score, truth, abs(k - truth), abs(k - truth) / truth, time.perf_counter() - began))
        return pd.DataFrame(out, columns=[f.split(" ")[0] for f in RESULTS.split(", ")])

    tasks = min(len(configs), 16 * spark.sparkContext.defaultParallelism)
    return table.repartition(tasks, "id").groupBy("id").applyInPandas(one, RESULTS)


def sweep_vectors(rows: DataFrame, configs: list[tuple[str, float, int]], rounds: int = 1) -> DataFrame:
    """(method, sigma, seed, k_star, k_occupied, score) of (id, v array) for each configuration, each in a group of its own."""
    spark = rows.sparkSession
    vectors = rows.select("id", "v")
    found = (vectors if rounds <= 1 else vectors.limit(MOST_SEARCHED + 1)).toPandas().sort_values("id")
    if rounds > 1 and len(found) > MOST_SEARCHED:  # one round goes by changes, more are made anew for every k
        raise ValueError(f"more than {MOST_SEARCHED} vectors: split into cells first")
    shared = spark.sparkContext.broadcast(np.stack(found["v"]).astype(np.float64))
    table = spark.createDataFrame([(i, *c) for i, c in enumerate(configs)], "id int, method string, sigma double, seed bigint")

    def one(group: pd.DataFrame) -> pd.DataFrame:
        out = [(c.method, c.sigma, c.seed, *search_vectors(shared.value, c.method, c.sigma, int(c.seed), rounds)) for c in group.itertuples()]
        return pd.DataFrame(out, columns=["method", "sigma", "seed", "k_star", "k_occupied", "score"])

    return table.repartition(len(configs), "id").groupBy("id").applyInPandas(one, "method string, sigma double, seed bigint, k_star bigint, k_occupied bigint, score double")


def summary(results: DataFrame) -> DataFrame:
    """Per panel, budget, method and flip probability: the spread of K* and of its error over the seeds."""
    return results.groupBy("fixture", "eps", "method", "p_flip").agg(
        F.count("*").alias("runs"), F.percentile("k_star", 0.5).alias("median_k"), F.min("k_star").alias("least_k"), F.max("k_star").alias("most_k"), F.max("truth").alias("truth"),
        F.round(F.percentile("err_rate", 0.5), 6).alias("median_err_rate"), F.round(F.avg("err_rate"), 6).alias("mean_err_rate"),
    )


def best_flip(results: DataFrame) -> DataFrame:
    """Per panel, budget and method the flip probability of least median error, the smaller one of equals."""
    order = F.struct("median_err_rate", "p_flip")
    return summary(results).groupBy("fixture", "eps", "method").agg(F.min(order).alias("best"), F.count("*").alias("flips")).select("fixture", "eps", "method", "best.p_flip", "best.median_err_rate", "flips")


CELL_COUNTS = "cell string, n bigint, k_star bigint, k_occupied bigint, truth bigint"


def count_cells(encoded: DataFrame, cell: str, eps: float, method: str = "B", p_flip: float = 0.1, seed: int = 1, rounds: int = 0) -> DataFrame:
    """One row for each cell, an attribute whose values the owners agree on: the counts of cells add up.

    Every cell is searched in a group of its own and must fit it (`MOST_SEARCHED`, refused beyond): large
    ones need a finer attribute.  Individuals must not change cells, or they count in each.
    """

    def one(group: pd.DataFrame) -> pd.DataFrame:
        if len(group) > MOST_SEARCHED:
            raise ValueError(f"cell {group[cell].iloc[0]}: more than {MOST_SEARCHED} rows, take a finer attribute")
        group = group.sort_values(["entity_id", "rec_id"])
        k, occupied, _ = search_cell(clustering.unpack(group), eps, method, p_flip, seed, rounds) if len(group) > 2 else (len(group), len(group), 0.0)
        return pd.DataFrame([(str(group[cell].iloc[0]), len(group), k, occupied, group["entity_id"].nunique())], columns=["cell", "n", "k_star", "k_occupied", "truth"])

    return encoded.select(cell, "entity_id", "rec_id", *LANES).groupBy(cell).applyInPandas(one, CELL_COUNTS)


def split_cells(rows: DataFrame, cell: str, finer: list[str], most: int = MOST_SEARCHED) -> DataFrame:
    """`rows` with the cells of more than `most` rows split by the first of the `finer` attributes, what is still too large by the next.

    Owners must agree on these attributes too, and individuals must not change them.
    """
    for attribute in finer:
        large = rows.groupBy(cell).agg(F.count("*").alias("rows of a cell")).where(F.col("rows of a cell") > most)
        wide = rows.join(F.broadcast(large), cell, "left")  # cells, not rows
        parted = F.when(F.col("rows of a cell").isNotNull(), F.concat_ws("|", cell, attribute)).otherwise(F.col(cell))
        rows = wide.withColumn(cell, parted).drop("rows of a cell")
    return rows


def coarse_ks(low: int, high: int, points: int = 12) -> list[int]:
    """A geometric grid for the first round of a coarse-to-fine search."""
    return sorted({int(round(k)) for k in np.geomspace(max(low, 2), high, points)})


def refine_ks(best: int, grid: list[int], points: int = 12) -> list[int]:
    """The grid of the second round: between the neighbours of the first round's best."""
    at = grid.index(best)
    low, high = grid[max(0, at - 1)], grid[min(len(grid) - 1, at + 1)]
    return sorted({int(round(k)) for k in np.linspace(low, high, points)})
