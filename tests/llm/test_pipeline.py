import corpus_pipeline
from fuzzcount.sources.tables import table

SF = "/root/testdata/sf0.001"


def test_stages_keep_columns_and_pass_on(spark):
    docs, sizes = table(spark, SF, "documents"), []
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == columns, name
        docs = out.cache()
        sizes.append(docs.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 100
    assert corpus_pipeline.run(spark, SF).select("doc_id").distinct().count() == sizes[-1]


def test_odd_rows_through_every_stage(spark, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        for name, stage in corpus_pipeline.STAGES:
            assert stage(spark, docs, SF).count() >= 0, name
