import random

import pytest

from fuzzcount.llm.near_copies import drop_near_copies, near_groups


def sets_of(text, size):
    words = text.split()
    return {tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1))} if words else set()


def brute(texts, size, percent):
    sets, parent = {i: sets_of(t, size) for i, t in texts.items()}, {i: i for i in texts}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in texts:
        for j in texts:
            shared = len(sets[i] & sets[j])
            if i < j and sets[i] and 100 * shared >= percent * (len(sets[i]) + len(sets[j]) - shared):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return {i: root(i) for i in texts}


def test_families_equal_brute_force(spark):
    rng = random.Random(7)
    texts = {}
    for family in range(6):
        base = [f"{family}x{rng.randrange(400)}" for _ in range(150)]
        for _ in range(25):
            words = list(base)
            for _ in range(rng.choice([0, 1, 2, 3, 5, 8, 12])):
                words[rng.randrange(len(words))] = f"n{rng.randrange(10**6)}"
            if rng.random() < 0.3:
                words = words[: rng.randrange(100, 150)]
            texts[len(texts)] = " ".join(words)
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    found = {r["doc_id"]: r["component_id"] for r in near_groups(docs, 3, 85).collect()}
    assert found == brute(texts, 3, 85)


def test_odd_rows(odd_docs, no_docs):
    found = {(r["doc_id"], r["n_shingles"]): r for r in near_groups(odd_docs, 3, 85).collect()}
    assert found[1, 0]["component_id"] == 1 and found[2, 0]["component_id"] == 2 and found[5, 29998]["component_id"] == 4 and found[8, 1]["kept"]
    assert found[7, 2]["component_id"] == 6 and found[None, 2]["component_id"] == 6
    assert near_groups(no_docs, 3, 85).count() == 0
    kept = drop_near_copies(odd_docs)
    assert kept.columns == odd_docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 2, 3, 4, 6, 8, 9]


def families(rng, groups):
    """Texts that share a long passage, walk away from it step by step, and mix a few common lines."""
    texts, lines = {}, [" ".join(f"line{i}w{j}" for j in range(12)) for i in range(4)]
    for g in range(groups):
        base = [f"g{g}w{i}" for i in range(120)]
        walk = list(base)
        for n in range(40):
            own = [f"g{g}n{n}o{i}" for i in range(rng.choice([2, 6, 12, 18, 30]))]
            texts[len(texts)] = " ".join(base + own)
            walk[rng.randrange(120)] = f"g{g}s{n}"
            texts[len(texts)] = " ".join([*walk, *rng.choice(lines).split(" ")])
    return texts


@pytest.mark.parametrize(("few", "many"), [(1 << 20, 32), (0, 0)])
def test_large_groups_equal_brute_force(spark, monkeypatch, few, many):
    """With few = many = 0 groups are joined at a few of their nodes until that finds nothing more."""
    from fuzzcount.llm import near_copies

    monkeypatch.setattr(near_copies, "FEW", few)
    monkeypatch.setattr(near_copies, "MANY", many)
    texts = families(random.Random(4), 3)
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    for size, percent in ((3, 85), (5, 80)):
        assert {r["doc_id"]: r["component_id"] for r in near_groups(docs, size, percent).collect()} == brute(texts, size, percent)


def test_given_documents_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    az = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    texts = {r["doc_id"]: (r["text"] or "").translate(az) for r in docs.collect()}
    found = {r["doc_id"]: r["component_id"] for r in near_groups(docs, 3, 85).collect()}
    assert found == brute(texts, 3, 85)


def test_a_pair_is_formed_at_its_first_common_token(spark):
    """Near copies that share dozens of first shingles meet once, not once for each shingle; every allowed pair does."""
    from pyspark.sql import functions as F

    from fuzzcount.llm import near_copies

    rng, docs = random.Random(3), []
    for i in range(40):
        words = [f"w{j}" for j in range(150)]
        for _ in range(rng.randrange(1, 5)):
            words[rng.randrange(150)] = f"n{i}x{rng.randrange(10**6)}"
        docs.append((i, " ".join(words)))
    docs = spark.createDataFrame(docs, "doc_id bigint, text string")
    sets = near_copies.shingle_sets(docs, 5).withColumn("row", F.monotonically_increasing_id()).cache()
    sketches = near_copies.described(docs, 5, near_copies.halves_for(0.8)).select(F.col("doc_id").alias("id"), "sketch")
    rows = near_copies.first_shingles(docs.select(F.col("doc_id").alias("id")), sets, 80).withColumn("component", F.col("id")).join(sketches, "id").cache()
    formed = [tuple(r) for r in near_copies.meetings(rows, 80).collect()]
    plain = rows.alias("x").join(rows.alias("y"), "token").where(near_copies._allowed(80) & (F.col("x.id") > F.col("y.id"))).select("x.id", "y.id")
    assert len(formed) == len(set(formed)) and set(formed) == {tuple(r) for r in plain.distinct().collect()}
    assert plain.count() > 2 * len(formed) > 0


def test_a_large_group_is_joined_before_its_pairs_are_formed(spark, monkeypatch):
    """A group whose pairs are more than a turn looks at is joined at drawn nodes; the result is that of all pairs."""
    from fuzzcount.llm import near_copies

    seen, few = [], near_copies.from_few
    monkeypatch.setattr(near_copies, "FEW", 0)
    monkeypatch.setattr(near_copies, "DRAWN", 2)
    monkeypatch.setattr(near_copies, "from_few", lambda rows, percent, turn, drawn: seen.append(drawn) or few(rows, percent, turn, drawn))
    texts = families(random.Random(6), 2)
    docs = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    assert {r["doc_id"]: r["component_id"] for r in near_groups(docs, 5, 80).collect()} == brute(texts, 5, 80)
    assert seen and seen == [2 * near_copies.MORE**i for i in range(len(seen))]
