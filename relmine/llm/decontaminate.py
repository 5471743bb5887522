"""Benchmark decontamination: a prefix-filtered join of item windows with documents, DataFrame operations only.

A window (``size`` consecutive item words, or all words of a shorter item) is a
set of positioned words. Ordered by rarity in the documents, its rarest word is
the prefix that any document with the window must hold; only documents' words
that equal a prefix become candidates. The positional bound follows from the
prefix's place in the window, the length bound from the document's word count;
each candidate is then verified word for word. Explode, join, bounds and
verification stay in one generated stage over the scan, so the words of a
document are split once and never shuffled.

The windows are broadcast in pieces of at most ``piece`` rows, each of bounded
size; a larger benchmark takes several passes.

Defined cases: null or empty text has no words; items without words have no
windows; repeated items count once by item_id; repeated document rows are each
returned; null ids are kept; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmine.llm.common import saved, text_key

#: What separates words, and the letters that are lowered.
BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
RESULT = ("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words_of(text):
    """The words of a text column, in order; null and empty give none."""
    return F.array_remove(F.split(F.translate(F.coalesce(text.cast("string"), F.lit("")), UPPER, LOWER), BREAKS), "")


def item_windows(benchmark: DataFrame, size: int = 13) -> DataFrame:
    """(item_id, window): the distinct windows of each item."""
    items = benchmark.select(F.col("item_id"), words_of(F.col("text")).alias("w")).where("size(w) > 0")
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("w") - size + 1)))
    return items.select("item_id", "w", at.alias("i")).select("item_id", F.slice("w", F.col("i"), F.lit(size)).alias("window")).distinct()


def document_words(docs: DataFrame) -> DataFrame:
    """(doc_id, tid, words): tid tells apart texts under one id."""
    return docs.select(F.col("doc_id"), text_key().alias("tid"), words_of(F.col("text")).alias("words"))


def word_rarity(docs: DataFrame, vocabulary: DataFrame, piece: int) -> DataFrame:
    """(word, seen): how often the documents hold each word of ``vocabulary(word)``."""
    exploded = document_words(docs).select(F.explode("words").alias("word"))
    n = vocabulary.count()
    parts = max(1, -(-n // piece))
    share = lambda k: vocabulary.where(F.pmod(F.xxhash64("word"), F.lit(parts)) == k)
    counts = [exploded.join(F.broadcast(share(k)), "word").groupBy("word").agg(F.count("*").alias("seen")) for k in range(parts)]
    found = reduce(DataFrame.unionByName, counts)
    return vocabulary.join(found, "word", "left").select("word", F.coalesce("seen", F.lit(0)).alias("seen"))


def occurrences(docs: DataFrame, benchmark: DataFrame, size: int = 13, piece: int = 200_000) -> DataFrame:
    """(doc_id, tid, start, length, item_id): every place where an item's window stands, start from 1."""
    windows = saved(item_windows(benchmark, size), "windows")
    vocabulary = windows.select(F.explode("window").alias("word")).distinct()
    rarity = saved(word_rarity(docs, vocabulary, piece), "rarity")  # written, so that AQE can split a word of many windows
    # the rarest word of each distinct window; ties by the word, then by its first place
    distinct = windows.select("window").distinct()
    ranked = distinct.select("window", F.posexplode("window").alias("offset", "word")).join(rarity, "word")
    prefix = ranked.groupBy("window").agg(F.min(F.struct("seen", "word", "offset")).alias("p")).select(
        "window", F.col("p.word").alias("word"), F.col("p.offset").alias("offset"), F.size("window").alias("length"))
    prefix = saved(prefix, "prefixes")
    parts = max(1, -(-prefix.count() // piece))
    exploded = document_words(docs).select("doc_id", "tid", "words", F.posexplode("words").alias("pos", "word"))

    def matched(k: int) -> DataFrame:
        side = F.broadcast(prefix.where(F.pmod(F.xxhash64("window"), F.lit(parts)) == k))
        start = F.col("pos") - F.col("offset") + 1
        return exploded.join(side, "word").where((start >= 1) & (start + F.col("length") - 1 <= F.size("words"))).where(
            F.slice("words", F.greatest(start, F.lit(1)), F.col("length")) == F.col("window")).select("doc_id", "tid", start.alias("start"), "length", "window")

    found = reduce(DataFrame.unionByName, [matched(k) for k in range(parts)])
    return found.distinct().join(windows, "window").select("doc_id", "tid", "start", "length", "item_id")


def contamination(docs: DataFrame, benchmark: DataFrame, size: int = 13, share: int = 20, keep: list[str] | None = None) -> DataFrame:
    """A row per document: n_words, n_hit, n_items, items_sha256, contaminated (n_hit > 0 and share * n_hit >= n_words).

    ``keep`` names further columns of ``docs`` to return; those that bear a result's name are left out.
    """
    keep = [c for c in dict.fromkeys(keep or []) if c not in RESULT]
    found = saved(occurrences(docs, benchmark, size), "occurrences")
    # words under the union of the occurrences: what each adds beyond the furthest end before it
    spans = found.select("doc_id", "tid", F.col("start").cast("long").alias("start"), (F.col("start") + F.col("length")).alias("stop")).distinct()
    before = F.max("stop").over(Window.partitionBy("doc_id", "tid").orderBy("start", "stop").rowsBetween(Window.unboundedPreceding, -1))
    covered = spans.select("doc_id", "tid", F.greatest(F.lit(0), F.col("stop") - F.greatest("start", F.coalesce(before, F.lit(0)))).alias("adds"))
    hits = covered.groupBy("doc_id", "tid").agg(F.sum("adds").alias("n_hit"))
    items = found.groupBy("doc_id", "tid").agg(F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("items"))
    per_doc = hits.join(items, (hits.doc_id.eqNullSafe(items.doc_id)) & (hits.tid == items.tid)).select(
        hits.doc_id.alias("hit_id"), hits.tid.alias("hit_tid"), "n_hit", "items")
    kept = F.struct(*(F.col(c) for c in keep)) if keep else F.lit(None).cast("string")
    base = docs.select("doc_id", kept.alias("kept"), text_key().alias("tid"), F.size(words_of(F.col("text"))).cast("long").alias("n_words"))
    joined = base.join(per_doc, base.doc_id.eqNullSafe(per_doc.hit_id) & (base.tid == per_doc.hit_tid), "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    return joined.select(
        "doc_id", *(F.col(f"kept.`{c}`").alias(c) for c in keep), "n_words", n_hit.alias("n_hit"),
        F.coalesce(F.size("items"), F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.coalesce(F.array_join("items", ","), F.lit("")), 256).alias("items_sha256"),
        ((n_hit > 0) & (F.lit(share) * n_hit >= F.col("n_words"))).alias("contaminated"))
