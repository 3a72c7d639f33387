import hashlib
import random

from fuzzcount.llm.cuckoo import CuckooFilter, LiveIndex, drop_exact_copies, exact_groups


def digest(i):
    return hashlib.sha256(str(i).encode()).digest()


def test_filter_inserts_and_deletes():
    f = CuckooFilter(256)
    assert all(f.insert(digest(i)) for i in range(500))
    assert all(digest(i) in f for i in range(500))
    for i in range(0, 500, 2):
        assert f.delete(digest(i))
    assert all(digest(i) in f for i in range(1, 500, 2))
    assert sum(digest(i) in f for i in range(0, 500, 2)) < 10


def test_index_resizes_and_equals_a_dictionary():
    index, want, rng = LiveIndex(4), {}, random.Random(3)
    for step in range(5000):
        i = rng.randrange(1500)
        if rng.random() < 0.1:
            assert index.remove(digest(i)) == (want.pop(digest(i), None) is not None)
        else:
            index.offer(digest(i), step)
            old = want.get(digest(i), (0, 0))
            want[digest(i)] = (max(old[0], step), old[1] + 1)
    assert {e[0]: (e[1], e[2]) for e in index.items()} == want and index.resizes > 3


def test_odd_rows(odd_docs, no_docs):
    found = exact_groups(odd_docs).toPandas()
    assert len(found) == 11
    by = found.dropna().groupby("doc_id").first()
    assert by.loc[1].keep_id == 2 and by.loc[4].keep_id == 5 and by.loc[6].keep_id == 7 and by.loc[6].group_size == 4
    assert exact_groups(no_docs).count() == 0
    kept = drop_exact_copies(odd_docs)
    assert kept.columns == odd_docs.columns and sorted(r["doc_id"] for r in kept.collect()) == [2, 3, 5, 7, 8, 9]
    assert drop_exact_copies(no_docs).count() == 0


def test_small_indexes_equal_brute_force(spark, monkeypatch):
    """Indexes that are passed on early, and more tasks than partitions, change nothing."""
    from fuzzcount.llm import cuckoo

    monkeypatch.setattr(cuckoo, "MOST_LIVE", 7)
    rng = random.Random(6)
    rows = [(i, rng.choice(["Same text", "sAME TEXT", "", None, f"own {i}", f"shared {i % 40}"])) for i in range(600)]
    found = {r["doc_id"]: r for r in exact_groups(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(5)).collect()}
    groups = {}
    for i, text in rows:
        groups.setdefault((text or "").lower(), []).append(i)
    for text, ids in groups.items():
        for i in ids:
            assert (found[i]["keep_id"], found[i]["group_size"], found[i]["kept"]) == (max(ids), len(ids), i == max(ids))
            assert found[i]["text_sha256"] == hashlib.sha256(text.encode()).hexdigest()
