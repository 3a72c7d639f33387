"""The search over every k, its summaries, the cells and the samplers."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from fuzzcount.functions import noise
from fuzzcount.functions.bloom import LANES
from fuzzcount.operators import clustering, decoys, elbow, measures, search
from fuzzcount.plans import core_queries
from fuzzcount.sources import fixtures

SF = "/root/testdata/sf0.001"


def people(n, copies, seed=5):
    return np.repeat((np.random.default_rng(seed).random((n, 200)) < 0.5).astype(np.float32), copies, axis=0)


def test_every_k_equals_a_search_of_its_own():
    """Labels of nested seeds for each k are the nearest of the first k seeds."""
    pool = people(12, 3)
    pool = np.abs(pool - (np.random.default_rng(1).random(pool.shape) < 0.1)).astype(np.float32)
    seeds = []
    for k, labels in enumerate(search.all_labels(pool, 20, np.random.default_rng(2), 0), 1):
        gap = ((pool[:, None] - pool[None]) ** 2).sum(2)
        new = np.flatnonzero((labels == k - 1) & (gap[np.arange(len(pool))].min(1) == 0))
        assert len(np.unique(labels)) <= k and labels.max() <= k - 1 and len(new)
        seeds.append(k)
    assert len(seeds) == 20


def test_methods_on_clean_cells():
    bits = people(30, 4)
    for method in ("B", *search.BASELINES):
        k, occupied, _ = search.search_cell(bits, 10.0, method, 0.05, 1)
        assert abs(k - 30) <= 12, (method, k)
        assert occupied <= k
    k, _, _ = search.search_cell(bits, 10.0, "B", 0.05, 1, rounds=3)
    assert abs(k - 30) <= 10


def test_summary_and_best_flip_equal_sql(spark):
    rows = fixtures.encoded(fixtures.panel_tiny(spark, SF))
    configs = [("tiny", e, m, p, r) for e in (1.0, 10.0) for m, p in (("A", 0.1), ("B", 0.1), ("B", 0.2), ("silhouette", 0.0)) for r in range(3)]
    results = search.sweep(spark, {"tiny": rows}, configs).cache()
    runs = results.toPandas()
    assert len(runs) == len(configs)
    want = duckdb.sql("""SELECT fixture, eps, method, p_flip, count(*) AS runs, quantile_cont(k_star, 0.5) AS median_k, min(k_star) AS least_k, max(k_star) AS most_k, max(truth) AS truth,
        round(quantile_cont(err_rate, 0.5), 6) AS median_err_rate, round(avg(err_rate), 6) AS mean_err_rate FROM runs GROUP BY ALL ORDER BY ALL""").df()
    got = search.summary(results).toPandas().sort_values(["fixture", "eps", "method", "p_flip"]).reset_index(drop=True)
    assert np.allclose(got.iloc[:, 4:].astype(float), want.iloc[:, 4:].astype(float)) and (got.iloc[:, 2] == want.iloc[:, 2]).all()
    best = duckdb.sql("SELECT fixture, eps, method, arg_min(p_flip, (median_err_rate, p_flip)) AS p_flip, min(median_err_rate) AS m FROM want GROUP BY ALL ORDER BY ALL").df()
    got = search.best_flip(results).toPandas().sort_values(["fixture", "eps", "method"]).reset_index(drop=True)
    assert np.allclose(got["p_flip"], best["p_flip"]) and np.allclose(got["median_err_rate"], best["m"])


def test_the_grid_has_every_configuration():
    found = core_queries.configurations(["c0", "c20", "c40"])
    assert len(found) == 3 * 6 * (2 * len(core_queries.FLIPS) + 3) * 5 and len(core_queries.FLIPS) == 24


def test_coarse_search_agrees_on_a_clear_peak():
    bits = people(30, 4)
    k, _, _ = search.search_coarse(bits, 10.0, "B", 0.05, 1, search.coarse_ks(2, 120))
    assert abs(k - 30) <= 12


def test_cells_add_up_and_large_ones_are_refused(spark, monkeypatch):
    rows = fixtures.encoded(fixtures.panel3(spark, SF)).withColumn("cell", F.pmod("entity_id", F.lit(5)).cast("string"))
    found = search.count_cells(rows, "cell", 10.0).toPandas()
    assert len(found) == 5 and found["n"].sum() == rows.count() and found["truth"].sum() == rows.select("entity_id").distinct().count()
    monkeypatch.setattr(search, "MOST_SEARCHED", 10)
    with pytest.raises(ValueError):
        search.sweep(spark, {"panel": rows}, [("panel", 1.0, "B", 0.1, 0)])


def test_gap_sampler_has_the_law_of_the_flips():
    seeds = np.random.default_rng(3).integers(0, 1 << 63, 20_000).astype(np.uint64)
    for share in (0.2689, 0.0474, 0.0000454):
        rows, bits = noise.gap_flips(seeds, share, 200)
        n = len(seeds) * 200
        assert abs(len(rows) / n - share) < 5 * np.sqrt(share * (1 - share) / n) + 1e-9
        assert bits.min(initial=0) >= 0 and bits.max(initial=0) < 200 and len({*zip(rows.tolist(), bits.tolist(), strict=True)}) == len(rows)
    each = np.bincount(noise.gap_flips(seeds, 0.2689, 200)[1], minlength=200) / len(seeds)
    assert abs(each - 0.2689).max() < 0.02
    assert len(noise.gap_flips(seeds[:0], 0.2, 200)[0]) == 0


def test_gap_sampler_is_stable_across_partitions(spark):
    rows = fixtures.encoded(fixtures.panel_tiny(spark, SF)).drop("entity_id")
    one, two = (sorted(map(tuple, noise.perturb_by_gaps(rows.repartition(n), 1.0).collect())) for n in (1, 5))
    assert one == two and len(one) == 12


def test_ranks_equal_a_sort(spark):
    rows = spark.range(3000).select("id", F.pmod(F.xxhash64("id"), F.lit(1 << 32)).alias("draw"))
    got = {r["id"]: r["rank"] for r in decoys.ranked(rows, 700, "draw", "id").collect()}
    want = {r["id"]: i for i, r in enumerate(sorted(rows.collect(), key=lambda r: (r["draw"], r["id"]))[:700])}
    assert got == want


def test_halves_round_up():
    assert decoys.counts_for(45) == (5, 1) and decoys.counts_for(450) == (45, 5)


def test_cluster_quality_by_hand(spark):
    rows = spark.createDataFrame([(1, 1), (1, 1), (1, 2), (2, 2), (2, 3)], "label int, truth int")
    assert tuple(measures.cluster_quality(rows).first()) == (0.6, 0.8)


def test_bends_equal_numpy(spark):
    pool = spark.createDataFrame([(f"r{i}", *(int(x) for x in np.random.default_rng(i).integers(0, 1 << 50, 4))) for i in range(15)], "row_id string, w0 bigint, w1 bigint, w2 bigint, w3 bigint")
    curve = {r["k"]: r["sse"] for r in clustering.prefix_inertia(pool, clustering.seeds(pool, 15)).collect()}
    seeds = {r["rank"]: [r[w] for w in LANES] for r in clustering.seeds(pool, 15).collect()}
    rows = [[r[w] for w in LANES] for r in pool.collect()]
    gap = lambda a, b: sum(bin(x ^ y).count("1") for x, y in zip(a, b, strict=True))
    assert curve == {k: sum(min(gap(x, seeds[s]) for s in range(1, k + 1)) for x in rows) for k in range(1, 16)}
    bends = elbow.knee(clustering.prefix_inertia(pool, clustering.seeds(pool, 15))).where("bend IS NOT NULL").count()
    assert bends == 13


def test_vectors_in_clear_groups():
    rng = np.random.default_rng(4)
    x = np.repeat(rng.normal(size=(12, 8)) * 10, 10, axis=0) + rng.normal(size=(120, 8)) * 0.1
    # Decoys spread wider than the groups themselves; invented references have clusters of their own.
    assert search.search_vectors(x, "B", 0.1, 1)[0] == search.search_vectors(x, "silhouette", 0.0, 1)[0] == 12
    k, occupied, _ = search.search_vectors(x, "A", 0.1, 1)
    assert k - 12 <= 13 and occupied == 12


def test_one_round_by_changes_equals_rounds_made_anew():
    """For every k, with rows that occur twice, each row gets a centre as near as in a Lloyd round of its own."""
    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 16)).astype(np.float32)
    x = np.vstack([x, x[:40]])
    norms, seeds = (x * x).sum(1), rng.permutation(340)
    gaps, one = ((x[:, None] - x[seeds][None]) ** 2).sum(2), clustering.OneRound(x, norms, 340)
    for k in range(1, 341):
        labels = gaps[:, :k].argmin(1)
        centre = x[seeds[:k]].copy()
        want, got = clustering.lloyd(x, centre, 1, labels, norms), one.after(labels, seeds[k - 1])
        far = ((x[:, None] - centre[None]) ** 2).sum(2)
        assert np.allclose(far[np.arange(340), got], far[np.arange(340), want], atol=1e-4), k


def test_more_vectors_than_a_cell_are_searched(spark, monkeypatch):
    monkeypatch.setattr(search, "MOST_SEARCHED", 50)
    rng = np.random.default_rng(4)
    x = np.repeat(rng.normal(size=(12, 8)) * 10, 10, axis=0) + rng.normal(size=(120, 8)) * 0.1
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id bigint, v array<double>")
    assert [r["k_star"] for r in search.sweep_vectors(rows, [("B", 0.1, 1)]).collect()] == [12]
