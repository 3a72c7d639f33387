import math

import pytest
from pyspark.sql import functions as F

from fuzzcount.functions import bloom, digest, grams, noise, similarity, theory
from fuzzcount.functions.bloom import LANES


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first()["x"]


def test_digest_matches_a_hand_checked_value(spark):
    assert one(spark, digest.num(F.lit("given|sm"))) == 1449232340


def test_grams(spark):
    assert set(one(spark, grams.qgrams(F.lit("Smith")))) == {"sm", "mi", "it", "th"}
    assert one(spark, grams.qgrams(F.lit("a"))) == ["a"]
    assert one(spark, grams.qgrams(F.lit(""))) == []
    assert one(spark, grams.qgrams(F.lit(None).cast("string"))) == []
    assert one(spark, grams.qgrams(F.lit("ab"), pad=True)) == ["_a", "ab", "b_"]
    assert one(spark, grams.neighbours(F.lit(13), 5, 1)) == [5, 10, 15]


def test_closed_forms():
    assert noise.flip_rate(1.0) == pytest.approx(0.268941, abs=1e-6)
    assert noise.flip_rate(0.1) == pytest.approx(0.475021, abs=1e-6)
    assert theory.optimal_hashes(200, 10) == pytest.approx(13.86, abs=0.01)
    for fraction, eps, p in ((0.005, 5, 0.3845), (0.010, 4, 0.5848), (0.015, 3, 0.4359), (0.025, 2, 0.5999), (0.040, 1, 0.9483)):
        assert theory.same_cluster_prob_value(fraction * 200, eps, 200) == pytest.approx(p, abs=1e-4)
    assert theory.same_cluster_prob_exact(200, 1.0, 200) == pytest.approx(1.0)
    eps = theory.min_eps(5, 0.9, 200)
    assert theory.same_cluster_prob_value(5, eps, 200) == pytest.approx(0.9, abs=1e-6)


def test_rates_in_spark(spark):
    assert one(spark, theory.fpr(F.lit(20.0), F.lit(10.0), F.lit(200.0))) == pytest.approx(0.000103752, abs=1e-8)
    assert one(spark, theory.same_cluster_prob(F.lit(3.0), F.lit(3.0), 200)) == pytest.approx(0.4359, abs=1e-4)


@pytest.fixture(scope="module")
def filters(spark):
    rows = spark.createDataFrame([("o0", 1, ["a", "b", "c"]), ("o0", 2, ["a", "b"]), ("o1", 3, [])], "owner string, rec_id bigint, tokens array<string>")
    return bloom.with_lanes(rows.withColumn("bits", bloom.positions(F.col("tokens"))), "bits").cache()


def test_membership_and_blank(filters):
    found = {r["rec_id"]: r["m"] for r in filters.select("rec_id", bloom.might_contain(LANES, F.lit("b")).alias("m")).collect()}
    assert found == {1: True, 2: True, 3: False}
    assert filters.where("rec_id = 3").select(bloom.popcount(*map(F.col, LANES))).first()[0] == 0


def test_double_family_reaches_many_places(spark):
    assert len(one(spark, bloom.positions(F.array(F.lit("x")), family="double"))) == 20


def test_printed_branch_is_the_complement(filters):
    rows = filters.select("owner", "rec_id", *LANES)
    a, b = noise.perturb(rows, 2.0).alias("a"), noise.perturb(rows, 2.0, printed_branch=True).alias("b")
    joined = a.join(b, F.col("a.rec_id") == F.col("b.rec_id"))
    assert [r[0] for r in joined.select(similarity.hamming("a", "b")).collect()] == [200, 200, 200]


def test_large_budget_keeps_the_filter_and_partitioning_does_not_matter(filters):
    rows = filters.select("owner", "rec_id", *LANES)
    assert sorted(noise.perturb(rows, 30.0).collect()) == sorted(rows.collect())
    assert sorted(noise.perturb(rows.repartition(1), 1.0).collect()) == sorted(noise.perturb(rows.repartition(7), 1.0).collect())


def test_likelihood_ratio_is_bounded():
    q = noise.flip_rate(2.0)
    for out in (0, 1):
        p = lambda bit, out=out: 1 - q if bit == out else q
        assert math.exp(-2.0) - 1e-12 <= p(0) / p(1) <= math.exp(2.0) + 1e-12


def test_release_refuses_attributes(filters):
    from fuzzcount.sources.released import check_release

    with pytest.raises(ValueError):
        check_release(filters)
    check_release(filters.select("owner", "rec_id", *LANES))
