import numpy as np
from pyspark.sql import functions as F

from fuzzcount.llm.toxic_segments import GRID, SIGNIFICANT, cells_of, drop_toxic, fold, score, segments, train, words_of

SF = "/root/testdata/sf0.1"


def brute(scores):
    """Maximal scoring segments by definition, in quadratic time: best sub-interval, then left and right of it."""
    if not any(s > 0 for s in scores):
        return []
    total = np.r_[0.0, np.cumsum(scores)]
    best = max(((total[j] - total[i], i - j, i, j) for i in range(len(scores)) for j in range(i + 1, len(scores) + 1)), key=lambda x: (round(x[0], 9), x[1]))
    i, j = best[2], best[3]
    right = [(a + j, b + j, s) for a, b, s in brute(scores[j:])]
    return [*brute(scores[:i]), (i, j, best[0]), *right]


def test_segments_equal_brute_force():
    rng = np.random.default_rng(1)
    for _ in range(300):
        scores = rng.normal(-0.2, 1, rng.integers(1, 25)).round(3)
        got, want = segments(scores), brute(scores.tolist())
        assert [(a, b) for a, b, _ in got] == [(a, b) for a, b, _ in want]
        assert np.allclose([s for *_, s in got], [s for *_, s in want])


def test_held_out_accuracy(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    scored = score(docs, train(docs, labels)).where(fold("doc_id") == 0).join(labels, "doc_id").select("score", "toxic").toPandas()
    hit = scored.score >= 0.5
    assert (hit & (scored.toxic == 1)).sum() >= 0.8 * (scored.toxic == 1).sum()
    assert (hit & (scored.toxic == 0)).sum() <= 0.02 * (scored.toxic == 0).sum()


def test_the_setting_comes_from_training_folds_alone(spark):
    """Labels of held-out rows, whatever they say, change neither the setting nor the score."""
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    turned = labels.withColumn("toxic", F.when(fold("doc_id") == 0, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    one, two = train(docs, labels), train(docs, turned)
    assert one.setting == two.setting and one.setting in GRID and np.allclose(one.weights[1:], two.weights[1:])


def test_scores_equal_their_parts(spark):
    """The score put together by hand: weights of words, segments by brute force, chances, evidence, logistic."""
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = train(docs, labels)
    few = docs.where("length(text) < 900").orderBy("doc_id").limit(40)
    texts = {r["doc_id"]: r["text"] for r in few.collect()}
    for row in score(few, model).collect():
        seen, scores = {}, []
        for word in words_of(texts[row["doc_id"]]):
            cells = cells_of(word) if model.setting.stems else cells_of(word)[:1]
            value = max(float(model.weights[c]) for c in cells) - model.setting.drift
            if value > 0:
                seen[word] = seen.get(word, 0) + 1
                value /= seen[word] if model.setting.fading else 1
            scores.append(value)
        c, n = model.calibration, len(scores)
        logs = sorted((-np.log(max(-np.expm1(-c.scale * max(n, 1) * np.exp(-min(c.rate * s, 700.0))), 1e-300)) for *_, s in brute(np.array(scores))), reverse=True)
        evidence = np.log1p(logs[0] + sum(x for x in logs[1:] if x > -np.log(SIGNIFICANT))) if logs else 0.0
        assert abs(row["score"] - 1 / (1 + np.exp(-(c.slope * evidence + c.offset)))) < 1e-6


def test_odd_rows(spark, odd_docs, no_docs):
    labels = spark.createDataFrame([(6, 1), (8, 0), (None, 1), (7, None)], "doc_id bigint, toxic int")
    model = train(odd_docs, labels)
    assert score(odd_docs, model).count() == 11 and score(no_docs, model).count() == 0
    kept = drop_toxic(odd_docs, model)
    assert kept.columns == odd_docs.columns and kept.where("text IS NULL").count() == 1
    none = train(no_docs, labels.limit(0))
    assert {r["score"] for r in score(odd_docs, none).collect()} == {0.0}
