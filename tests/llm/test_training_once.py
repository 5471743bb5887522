"""The trusted texts are picked once; counting their n-grams moves no other text."""

from relmine.llm import quality


def test_counting_moves_no_texts_of_others(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"word{i % 7} of a line {i % 5} of text", "en") for i in range(60)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(0, 60, 2)], "doc_id long, quality int, toxic int")
    plans, plain = {}, quality.saved

    def saved(df, label, batch=None):
        plans.setdefault(label, []).append(df._jdf.queryExecution().optimizedPlan().toString())
        return plain(df, label, batch)

    monkeypatch.setattr(quality, "saved", saved)
    assert quality.quality(docs, labels).count() == 60
    assert len(plans["training"]) == 1 and "Join" in plans["training"][0]
    assert len(plans["grams"]) == 2 and not any("Join" in p for p in plans["grams"])
