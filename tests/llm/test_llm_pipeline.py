import corpus_pipeline
from relmine.llm import common
from relmine.llm.queries import ORACLE_SQL, QUERIES


def test_stages_keep_the_columns_and_apply_decisions(spark):
    sf = "/root/testdata/sf0.001"
    docs = common.table(spark, sf, "documents")
    before = docs.count()
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = common.saved(stage(spark, docs, sf), "test")
        now = docs.count()
        assert 0 < now <= before
        if i < 4:
            assert docs.columns == corpus_pipeline.COLUMNS
        before = now
    assert {"doc_id", "n_tokens", "ids"} <= set(docs.columns)


def test_stages_take_empty_and_odd_rows(spark):
    sf = "/root/testdata/sf0.001"
    odd = spark.createDataFrame([(1, None, None, None, None, 1), (1, None, None, None, None, 2), (None, "", "en", None, 0, 3), (2, "some words of text", "xx", "s", 18, 4)],
                                "doc_id long, text string, lang string, source string, n_chars long, n_hit long")
    for frame, least in ((odd, 1), (odd.limit(0), 0)):
        docs = frame
        for name, stage in corpus_pipeline.STAGES:
            docs = common.saved(stage(spark, docs, sf), "test")
        assert docs.count() >= least


def test_all_operators_are_registered():
    assert {f"op{n}" for n in range(1, 11)} == {k.split("_")[0] for k in QUERIES}
    assert set(ORACLE_SQL) <= set(QUERIES)
