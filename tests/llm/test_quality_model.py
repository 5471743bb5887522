"""Perplexities against a plain model of dictionaries, and what they must not depend on."""

import math
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from relmine.llm import quality
from relmine.llm.common import table

SF = "/root/testdata/sf0.001"


class Plain:
    """Interpolated modified Kneser-Ney by dictionaries of word tuples."""

    def __init__(self, texts, order):
        self.order, self.tables, self.weights = order, {}, {}
        top = Counter(g for t in texts for g in self.grams(t))
        for k in range(order, 0, -1):
            self.tables[k] = top
            seen = Counter(min(n, 5) for n in top.values())
            self.weights[k] = self._weights(top, [self._discount(seen, i) for i in (1, 2, 3)])
            top = Counter(g[1:] for g in top)
        self.types = len(self.tables[1])

    @staticmethod
    def _discount(seen, i):
        if not seen[1] or not seen[2]:
            return 0.5
        d = i - (i + 1) * seen[1] / (seen[1] + 2 * seen[2]) * (seen[i + 1] / seen[i] if seen[i] else 0)
        return min(max(d, 0.05), (0.95, 1.9, 2.8)[i - 1])

    @staticmethod
    def _weights(counts, taken):
        out = defaultdict(lambda: [0, 0.0])
        for g, n in counts.items():
            out[g[:-1]][0] += n
            out[g[:-1]][1] += taken[min(n, 3) - 1]
        return dict(out), taken

    def grams(self, text):
        w = (text or "").split()
        w = [x if i == 0 or w[i - 1] != x else (x, "again") for i, x in enumerate(w)]
        w = ["<s>"] * (self.order - 1) + w + ["</s>"]
        return list(zip(*(w[i:] for i in range(self.order))))

    def probability(self, gram):
        if not gram:
            return 1 / (self.types + 1)
        k, low = len(gram), self.probability(gram[1:])
        contexts, taken = self.weights[k]
        if gram[:-1] not in contexts:
            return low
        total, off = contexts[gram[:-1]]
        n = self.tables[k].get(gram, 0)
        return (n - (taken[min(n, 3) - 1] if n else 0) + off * low) / total

    def score(self, text):
        grams = self.grams(text)
        return sum(math.log(self.probability(g)) for g in grams), len(grams)


@pytest.mark.parametrize("order", [2, 3])
def test_perplexities_by_dictionaries(spark, order):
    docs = table(spark, SF, "documents").where("lang in ('en', 'fr')").unionByName(
        spark.createDataFrame([(-3, None, "en", None, 0), (-6, "", "fr", None, 0), (-9, "of of of of the the of", "en", None, 0), (-12, "solo", None, None, 0)], table(spark, SF, "documents").schema))
    texts = quality.identified(docs)
    got = quality.perplexities(texts, texts.where("doc_id % 3 = 0"), order).join(texts.select("key", "doc_id", "lang", "text"), "key").collect()
    assert len(got) == docs.count() > 50
    models = {x: Plain([r["text"] for r in got if r["lang"] == x and r["doc_id"] % 3 == 0], order) for x in ("en", "fr", None)}
    for r in got:
        logp, tokens = models[r["lang"]].score(r["text"])
        assert r["tokens"] == tokens and r["logp"] == pytest.approx(logp, rel=1e-5, abs=1e-4)


def test_probabilities_of_all_words_sum_to_one():
    model = Plain(["a b a c", "b c a b", "a a b"], 3)
    words = [g[0] for g in model.tables[1]] + ["unseen"]
    for context in (("<s>", "<s>"), ("a", "b"), ("x", "y")):
        assert sum(model.probability((*context, w)) for w in words) == pytest.approx(1)


def test_results_do_not_depend_on_batches_and_partitions(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    size = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    got = []
    try:
        for rows, parts in (("3", 5), ("10000", 1)):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
            out = quality.quality(docs.repartition(parts), labels).select("doc_id", "n_words", F.round("perplexity", 4).alias("p"), "accepted")
            got.append(sorted(map(tuple, out.collect()), key=repr))
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
    assert got[0] == got[1]


def test_languages_have_their_own_models_and_thresholds(spark):
    docs, labels = table(spark, "/root/testdata/sf0.01", "documents"), table(spark, "/root/testdata/sf0.01", "labels")
    got = quality.quality(docs, labels)
    assert got.count() == docs.count()
    limits = got.select("lang", "threshold").distinct().collect()
    assert len(limits) == docs.select("lang").distinct().count() == len({r["threshold"] for r in limits}) and None not in {r["threshold"] for r in limits}
    both = got.join(labels, "doc_id").groupBy("lang", "quality").agg(F.avg(F.col("accepted").cast("int")).alias("a"))
    assert all(r["a"] > 0.95 if r["quality"] else r["a"] < 0.1 for r in both.collect())


def test_a_long_text_is_cut_over_blocks(spark):
    """A text of more words than a block, repeated rows, and lists for more shards than there are documents."""
    long_ = " ".join(f"w{i % 977}" for i in range(30_000))
    docs = spark.createDataFrame([(1, long_, "en"), (1, long_, "en"), (2, "w1 w2 w3", "en"), (3, None, None)], "doc_id long, text string, lang string")
    texts = quality.identified(docs)
    parts = quality.packed_documents(texts, 2, 40, 40, size=500)
    assert parts.where("shard = 0").count() >= 3 and parts.count() > 40
    got = {r["tokens"]: r for r in quality.perplexities(texts, texts.where("doc_id = 1"), 2).collect()}
    assert set(got) == {30_001, 4, 1} and math.exp(-got[30_001]["logp"] / 30_001) < 3 and got[1]["logp"] is None


def test_the_largest_tables_are_joined_piece_by_piece(spark):
    texts = quality.identified(table(spark, SF, "documents"))
    counts = [quality.saved(quality.gram_counts(texts, 2, i, 2), "grams", 50) for i in range(2)]
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000"
    whole = [c.count() for c in counts]
    entries, _ = quality.model_entries(counts, 2)
    pieces = [[r["w1"] for r in frame.select("w1").collect()] for k, frame in entries if k == 2]
    assert sum(map(len, pieces)) == sum(whole) and max(map(len, pieces)) < min(whole) / 2
    for i, a in enumerate(pieces):
        assert not any(set(a) & set(b) for b in pieces[:i])
