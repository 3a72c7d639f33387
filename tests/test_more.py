import numpy as np
import pytest

from fuzzcount.functions.register import register
from fuzzcount.operators import hierarchical


def test_sql_functions(spark):
    register(spark)
    row = spark.sql("SELECT fc_hamming(1, 0, 3, 0, 0, 0, 1, 0) AS h, fc_dice(1, 0, 3, 0, 0, 0, 1, 0) AS d, fc_eta(1D) AS e, fc_num('given|sm') AS n").first()
    assert row["h"] == 2 and row["d"] == pytest.approx(0.5) and row["e"] == pytest.approx(0.268941, abs=1e-6) and row["n"] == 1449232340


def test_linkages():
    rng = np.random.default_rng(1)
    people = (rng.random((4, 60)) < 0.5).astype(int)
    x = np.repeat(people, 5, axis=0)
    x = np.abs(x - (rng.random(x.shape) < 0.03))
    for link in ("single", "complete", "average"):
        found = hierarchical.labels(x, link, k=4)
        assert all(len(set(found[i * 5 : i * 5 + 5])) == 1 for i in range(4)) and len(set(found)) == 4
    assert len(set(hierarchical.labels(x, "single", cut=-1.0))) == 20
    assert len(hierarchical.labels(x[:0])) == 0


def test_embedding_best_k_sweeps_every_k(spark, tmp_path):
    import random

    from fuzzcount.plans.core_queries import embedding_best_k

    rng = random.Random(2)
    rows = [(i, [rng.uniform(-1, 1) for _ in range(64)], i) for i in range(120)]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert embedding_best_k(spark, str(tmp_path)).first()["k_star"] > 60


def test_python_functions_equal_the_plans(spark):
    from fuzzcount.functions import python_udfs
    from fuzzcount.functions.bloom import LANES
    from fuzzcount.operators import decoys, linkage

    python_udfs.register(spark)
    refs = decoys.invent(spark, 4)
    refs.createOrReplaceTempView("refs")
    got = spark.sql("SELECT r.ref_id, c.* FROM refs r, LATERAL fc_noisy_copies(r.w0, r.w1, r.w2, r.w3, 3, 0.2D, 'k', r.ref_id) c")
    want = decoys.dummies(refs, 3, 0.2).select("ref_id", "dum_no", *LANES)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    bands = spark.sql("SELECT r.ref_id, b.* FROM refs r, LATERAL fc_bands(r.w0, r.w1, r.w2, r.w3, 10) b")
    assert sorted(map(tuple, bands.collect())) == sorted(map(tuple, linkage.bands(refs, ["ref_id"]).select("ref_id", "band", "value").collect()))


def test_people_source_equals_the_fixture(spark):
    from fuzzcount.sources import fixtures, panel_source

    panel_source.register(spark)
    got = spark.read.format("fuzzcount_people").option("persons", 40).load()
    want = fixtures.of_owners(fixtures.people(spark, "/root/testdata/sf0.001").where("entity_id < 40")).select(*got.columns)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_a_cluster_without_a_shared_folder_is_refused():
    from types import SimpleNamespace

    from fuzzcount.sources.tables import shared_folder

    unset = SimpleNamespace(get=lambda *_: None)
    nowhere = SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: SimpleNamespace(isDefined=lambda: False)))
    context = SimpleNamespace(getConf=lambda: unset, _jsc=nowhere, master="spark://host:7077")
    with pytest.raises(ValueError):
        shared_folder(SimpleNamespace(sparkContext=context, conf=unset))


def test_steps_are_removed(spark):
    from pathlib import Path

    from fuzzcount.sources.tables import cut, drop, shared_folder

    kept = cut(spark.range(5))
    files = {p.name for p in Path(shared_folder(spark)).glob("step-*")}
    gone = cut(kept.where("id > 1"))
    assert gone.count() == 3
    drop(gone)
    assert {p.name for p in Path(shared_folder(spark)).glob("step-*")} == files and kept.count() == 5
