"""Batch forms of digests, and pairs in which equal filters are compared once: the same results as the plain forms."""

import hashlib

import pytest
from pyspark.sql import functions as F

from fuzzcount.functions import bloom, grams, noise
from fuzzcount.functions.bloom import LANES
from fuzzcount.functions.md5 import draws
from fuzzcount.operators import linkage
from fuzzcount.functions.similarity import dice, hamming
from fuzzcount.sources import fixtures

SF = "/root/testdata/sf0.001"


def test_draws_equal_the_library():
    heads, tails = [b"", b"k|", "k|ä€|".encode(), b"x" * 53, b"x" * 54, b"x" * 55, b"x" * 300], [b"", b"7", b"199"]
    want = [[int(hashlib.md5(h + t).hexdigest()[:8], 16) for t in tails] for h in heads]
    assert draws(heads, tails).tolist() == want


def test_batches_encode_and_flip_as_columns_do(spark):
    people = fixtures.panel3(spark, SF, 20).withColumn("surname", F.when(F.col("rec_id") % 5 == 0, None).when(F.col("rec_id") % 7 == 0, "Übergröße 東").otherwise(F.col("surname")))
    bits = people.select("owner", "rec_id", "entity_id", bloom.positions(grams.record_tokens()).alias("bits"))
    want = bloom.with_lanes(bits, "bits").drop("bits")
    assert sorted(map(tuple, fixtures.encoded(people).collect())) == sorted(map(tuple, want.collect()))
    prefix = F.concat_ws("|", F.lit("p"), "owner", "rec_id")
    masked = want.select("owner", "rec_id", "entity_id", *(F.col(w).bitwiseXOR(noise.mask(prefix, i, 0.3)).alias(w) for i, w in enumerate(LANES)))
    flipped = noise.flipped(want, prefix, 0.3)
    assert sorted(map(tuple, flipped.collect())) == sorted(map(tuple, masked.collect()))
    assert "MapInArrow" in flipped._jdf.queryExecution().executedPlan().toString()


def test_a_record_without_tokens_is_blank(spark):
    rows = spark.createDataFrame([(1, []), (2, ["a"]), (3, [])], "id bigint, tokens array<string>").coalesce(1)
    found = {r["id"]: [r[w] for w in LANES] for r in bloom.encode_tokens(rows).collect()}
    assert found[1] == found[3] == [0, 0, 0, 0] and any(found[2])


@pytest.fixture(scope="module")
def copies(spark):
    """Filters near each other, each of them several times, and blank ones."""
    base = fixtures.encoded(fixtures.panel3(spark, SF, 60)).select("owner", "rec_id", *LANES)
    some = noise.perturb(base, 4.0).where("rec_id % 2 = 0").union(base.where("rec_id % 2 = 1"))
    blank = spark.range(1000, 1003).select(F.lit("o").alias("owner"), F.col("id").alias("rec_id"), *(F.lit(0).cast("bigint").alias(w) for w in LANES))
    return some.union(blank).withColumn("block", F.col("rec_id") % 2).cache()


@pytest.mark.parametrize("radius", [6, 7, 12])
def test_near_pairs_equal_brute_force(copies, radius):
    x, y = copies.alias("x"), copies.alias("y")
    want = x.join(y, (F.col("x.rec_id") < F.col("y.rec_id")) & (hamming("x", "y") <= radius)).select("x.rec_id", "y.rec_id", hamming("x", "y"))
    found = sorted(map(tuple, linkage.near_pairs(copies, radius).select("a", "b", "d").collect()))
    assert found == sorted(map(tuple, want.collect())) and any(d for *_, d in found)
    plain = {r["node"]: r["component"] for r in linkage.components(copies, linkage.blocked_pairs(copies, radius)).collect()}
    assert {r["node"]: r["component"] for r in linkage.near_components(copies, radius).collect()} == plain


def test_match_pairs_equal_brute_force(copies):
    x, y = copies.alias("x"), copies.alias("y")
    close = (F.col("x.block") == F.col("y.block")) & (F.col("x.rec_id") < F.col("y.rec_id")) & (dice("x", "y") >= 0.9)
    want = x.join(y, close).select("x.rec_id", "y.rec_id", F.round(dice("x", "y"), 6))
    assert sorted(map(tuple, linkage.match_pairs(copies, 0.9, "block").collect())) == sorted(map(tuple, want.collect()))


def test_changes_of_labels_give_the_curve_of_all_labels(spark):
    from fuzzcount.operators import clustering, purity, search

    rows = fixtures.encoded(fixtures.panel3(spark, SF, 25)).select("owner", "rec_id", *LANES)
    released = noise.perturb(rows, 3.0)
    pool = search.build_pool(released, 75, search.SearchSpec()).cache()
    plain = [tuple(r) for r in purity.curve(clustering.prefix_labels(pool, 75)).orderBy("k").collect()]
    few = clustering.prefix_changes(pool, 75)
    found = [tuple(r) for r in purity.curve_of_changes(few, 75).orderBy("k").collect()]
    assert len(plain) == 75 and found == [pytest.approx(p, abs=1e-9) for p in plain]
    assert few.count() < 75 * pool.count() / 5


@pytest.mark.parametrize("name", ["bloom_fpr", "flip_budget", "flip_probability", "same_cluster_prob", "method_a_refs"])
def test_closed_forms_read_a_table(spark, name):
    import __spark_entry__ as entry
    from fuzzcount.plans import core_queries

    if name == "method_a_refs":  # counts on the keys themselves; the result holds no scan
        counted = core_queries.records(spark, SF).agg(F.count("rec_id"))
        assert "ReadSchema: struct<c_custkey" in counted._jdf.queryExecution().executedPlan().toString()
        assert len(counted.inputFiles()) == 1
    else:
        assert "FileScan parquet" in entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()


def test_large_cells_are_split_and_no_record_is_lost(spark):
    from fuzzcount.operators import search

    rows = spark.range(100).select("id", F.when(F.col("id") < 10, "a").otherwise("b").alias("cell"), (F.col("id") % 3).cast("string").alias("suburb"), (F.col("id") % 2).cast("string").alias("gender"))
    found = search.split_cells(rows, "cell", ["suburb", "gender"], 29)
    sizes = {r["cell"]: r["count"] for r in found.groupBy("cell").count().collect()}
    assert sum(sizes.values()) == 100 and sizes["a"] == 10 and max(sizes.values()) <= 29


def test_more_seeds_than_a_full_sweep_takes(spark, monkeypatch):
    """Every k of a pool beyond `MOST_SWEPT`, from rows of counts for each reference, equals the curve of all labels."""
    from fuzzcount.operators import clustering, purity, search

    rows = fixtures.encoded(fixtures.panel3(spark, SF, 40)).select("owner", "rec_id", *LANES)
    pool = search.build_pool(noise.perturb(rows, 4.0), 120, search.SearchSpec(p_flip=0.05, dummy_base="records")).cache()
    plain = [tuple(r) for r in purity.curve(clustering.prefix_labels(pool, 120)).orderBy("k").collect()]
    monkeypatch.setattr(clustering, "MOST_SWEPT", 50)
    few = clustering.prefix_changes(pool, 120)
    found = [tuple(r) for r in purity.curve_of_changes(few, 120).orderBy("k").collect()]
    assert len(plain) == 120 and found == [pytest.approx(p, abs=1e-9) for p in plain]
    assert few.count() <= 12 + 2


def test_nearer_seeds_equal_brute_force():
    import numpy as np
    import pandas as pd

    from fuzzcount.operators import clustering

    rng = np.random.default_rng(5)
    centre = rng.random(200) < 0.5
    rows, seeds = centre ^ (rng.random((90, 200)) < 0.05), rng.random((700, 200)) < 0.5
    rows[0], seeds[300:320] = centre, centre ^ (rng.random((20, 200)) < 0.05)
    packed = [clustering.dense_words(pd.DataFrame({w: x[:, 50 * i : 50 * i + 50] @ (np.int64(1) << np.arange(50)) for i, w in enumerate(LANES)})) for x in (rows, seeds)]
    apart = (rows[:, None] != seeds[None]).sum(2)
    want = [(i, j) for i in range(90) for j in range(700) if j == 0 or apart[i, j] < apart[i, :j].min()]
    for near in (None, packed[0][:, 0]):
        found = clustering.nearer_seeds(*packed, near)
        assert list(zip(*(x.tolist() for x in found), strict=True)) == want
