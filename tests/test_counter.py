import numpy as np
import pytest
from pyspark.sql import functions as F

from fuzzcount.functions.bloom import LANES
from fuzzcount.operators import clustering, decoys, linkage, purity, search
from fuzzcount.sources import corrupt, fixtures

SF = "/root/testdata/sf0.001"


def labels(spark, rows):
    return spark.createDataFrame(rows, "k int, row_id string, kind string, ref_id bigint, label int")


def test_purity_by_hand(spark):
    rows = [(1, "r", "ref", 0, 7)] + [(1, f"d{i}", "dum", 0, 7 if i < 4 else 8) for i in range(5)] + [(1, f"x{i}", "real", None, 7) for i in range(2)]
    assert purity.per_reference(labels(spark, rows)).first()["purity"] == pytest.approx(4 / 7)
    alone = [(1, "r", "ref", 0, 7), (1, "d", "dum", 0, 8)]
    assert purity.per_reference(labels(spark, alone)).first()["purity"] == 0.0


def test_ties(spark):
    curve = spark.createDataFrame([(1, 0.2), (2, 0.9), (3, 0.9), (4, 0.1)], "k int, purity double")
    assert purity.best_k(curve).first()["k_star"] == 2
    assert purity.best_k(curve, "last").first()["k_star"] == 3


def test_prefix_labels_equal_brute_force(spark):
    pool = spark.range(12).select(F.concat(F.lit("r"), F.col("id").cast("string")).alias("row_id"), F.lit("real").alias("kind"), F.lit(None).cast("bigint").alias("ref_id"), *(F.pmod(F.xxhash64("id", F.lit(i)), F.lit(1 << 50)).alias(w) for i, w in enumerate(LANES))).cache()
    found = {(r["k"], r["row_id"]): r["label"] for r in clustering.prefix_labels(pool, 12).collect()}
    seeds = {r["rank"]: tuple(r[w] for w in LANES) for r in clustering.seeds(pool, 12).collect()}
    for row in pool.collect():
        gaps = {rank: sum(bin(row[w] ^ s).count("1") for w, s in zip(LANES, seed, strict=True)) for rank, seed in seeds.items()}
        for k in range(1, 13):
            assert found[k, row["row_id"]] == min((gaps[r], r) for r in gaps if r <= k)[1]


def test_lloyd_step_agrees_with_numpy(spark):
    rows = fixtures.encoded(fixtures.panel_tiny(spark, SF)).withColumn("label", F.pmod("entity_id", F.lit(3))).withColumn("row_id", F.col("rec_id").cast("string")).cache()
    frame = rows.toPandas()
    x = clustering.unpack(frame)
    centres = np.array([x[frame["label"] == c].mean(0) for c in range(3)])
    gaps = ((x[:, None] - centres[None]) ** 2).sum(2).round(9)
    want = dict(zip(frame["row_id"], gaps.argmin(1), strict=True))
    assert {r["row_id"]: r["label"] for r in clustering.assign(rows, clustering.centroids(rows)).collect()} == want


def test_decoy_counts_and_guards(spark):
    assert decoys.counts_for(513) == (51, 5)
    assert decoys.counts_for(513, dummy_base="records") == (51, 51)
    with pytest.raises(ValueError):
        decoys.dummies(spark.createDataFrame([(0, 1, 1, 1, 1)], "ref_id bigint, w0 bigint, w1 bigint, w2 bigint, w3 bigint"), 0, 0.1)


def test_purity_of_matches_the_table_form():
    assert search.purity_of(np.array([0, 0, 0, 0, 0, 1]), 2, 1, 3) == pytest.approx(2 / (3 + 5 - 1 - 2))


def test_corruption_share_and_distance(spark):
    panel = fixtures.panel3(spark, SF)
    changed = corrupt.corrupted(panel, 20)
    n, hit = changed.agg(F.count("*"), F.count("op")).first()
    assert hit == round(0.2 * n)
    both = changed.alias("c").join(panel.alias("p"), "rec_id").where("c.op in ('insert', 'delete', 'substitute')")
    far = both.select(F.max(F.greatest(*(F.levenshtein(f"c.{a}", f"p.{a}") for a in ("given", "surname", "suburb"))))).first()[0]
    assert far <= 1


def test_blocked_pairs_cover_a_small_radius_and_no_cartesian(spark):
    rows = fixtures.encoded(fixtures.panel3(spark, SF)).select("owner", "rec_id", *LANES).cache()
    found = linkage.blocked_pairs(rows, 12)
    assert "CartesianProduct" not in found._jdf.queryExecution().executedPlan().toString()
    x, y = rows.alias("x"), rows.alias("y")
    from fuzzcount.functions.similarity import hamming

    want = x.join(y, (F.col("x.rec_id") < F.col("y.rec_id")) & (hamming("x", "y") <= 12)).count()
    assert found.count() == want


def test_encoding_does_not_shuffle(spark):
    people = spark.range(3).select(F.lit("o").alias("owner"), F.col("id").alias("rec_id"), F.col("id").alias("entity_id"), *(F.lit("ab").alias(c) for c in fixtures.PII))
    assert "Exchange" not in fixtures.encoded(people)._jdf.queryExecution().executedPlan().toString()


def test_guard_on_large_sweeps(spark):
    with pytest.raises(ValueError):
        clustering.prefix_labels(spark.range(0).select(F.lit("x").alias("row_id")), clustering.MOST_SWEPT + 1)
