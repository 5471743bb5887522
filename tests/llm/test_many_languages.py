from relmine.llm import language


def test_every_labelled_language_has_a_model(spark):
    """More than 32 languages, one of them in a single document among many."""
    rows = [(i, f"l{i % 39:02d}", f"word{i % 39} text of some length {i}") for i in range(5000)] + [(9999, "zz", "rara avis")]
    langs, table = language.fit(spark.createDataFrame(rows, "doc_id long, lang string, text string"), max_train=50)
    assert langs == [f"l{i:02d}" for i in range(39)] + ["zz"]
    assert len(table) == 40
