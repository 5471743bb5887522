"""Language of web pages by Bayesian evidence fusion.

Four kinds of evidence: the text under hashed character-trigram models (fitted
on a bounded sample of documents with a known language), the language that the
markup declares, the suffix of the address, and the host's other pages. The
reliability of declarations is counted from the pages themselves: soft counts
of declared against text language. Host priors are soft counts summed by
grouped aggregation and smoothed hierarchically, host towards domain, domain
towards suffix, suffix towards all pages; a page's own share is taken out of
its host's counts before it is read.

Defined cases: null or empty html has no text evidence, and a page without any
evidence gets the prior; a null or odd url belongs to the empty host; declared
languages outside the models count as others; repeated rows are pages of their
own; very long pages are read whole; without documents of a known language there is one language, ``und``;
extra columns are ignored.
"""

from __future__ import annotations

import html as html_
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmine.llm.common import saved

BUCKETS = 1 << 16
_STRIP = re.compile(r"<!--.*?-->|<(script|style)\b.*?</\1\s*>|<[^>]*>", re.S | re.I)
_DECLARED = re.compile(r"<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z]{2,3})|<meta\b[^>]*?content-language[^>]*?content\s*=\s*[\"']?([A-Za-z]{2,3})", re.I | re.S)
#: Languages of country suffixes, by language.
SUFFIXES = {"en": "uk us au nz ie ca gb", "fr": "fr be ch lu mc", "de": "de at ch li", "es": "es mx ar cl co pe ve uy"}


def plain(page: str | None) -> str:
    return html_.unescape(_STRIP.sub(" ", page or ""))


def buckets(text: str) -> np.ndarray:
    """Bucket of each character trigram of the lower-cased words."""
    c = np.frombuffer((" " + " ".join(text.lower().split()) + " ").encode("utf-32-le", "replace"), np.uint32).astype(np.uint64)
    return (((c[:-2] * np.uint64(31) + c[1:-1]) * np.uint64(1009) + c[2:]) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(48)).astype(np.int64) if len(c) > 2 else np.zeros(0, np.int64)


def fit(docs: DataFrame, max_train: int = 4_000, smooth: float = 0.5) -> tuple[list[str], np.ndarray]:
    """Languages and their log probabilities of the buckets, from all documents of a language or, where
    it has more than ``max_train``, about so many by hash."""
    known = docs.where("lang is not null and lang <> '' and text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.lower(F.col("lang")).alias("lang"), F.col("text").cast("string").alias("text"))
    sizes = F.broadcast(known.groupBy("lang").agg(F.count("*").alias("of")))
    rows = known.join(sizes, "lang").where((F.col("of") <= max_train) | (F.pmod(F.xxhash64("doc_id"), "of") < max_train))

    def run(batches):
        for b in batches:
            by: dict[str, np.ndarray] = {}
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                by.setdefault(lang, np.zeros(BUCKETS, np.int64))
                by[lang] += np.bincount(buckets(text), minlength=BUCKETS)
            for lang, n in by.items():
                at = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(n[at])], names=["lang", "bucket", "n"])

    counts = rows.select("lang", "text").mapInArrow(run, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(counts.lang.unique()) or ["und"]
    table = np.full((len(langs), BUCKETS), smooth)
    for i, lang in enumerate(langs):
        own = counts[counts.lang == lang]
        table[i, own.bucket] += own.n
    return langs, np.log(table / table.sum(axis=1, keepdims=True)).astype(np.float32)


def evidence(pages: DataFrame, langs: list[str], table: np.ndarray, most: int = 200) -> DataFrame:
    """(page_id, url, host, domain, suffix, declared, text array<double>): log likelihoods of the whole text,
    scaled down to those of ``most`` trigrams, for trigrams of one text depend on each other."""
    shared = pages.sparkSession.sparkContext.broadcast(table)

    def run(batches):
        t = shared.value
        for b in batches:
            found, declared = [], []
            for page in b.column(2).to_pylist():
                at = buckets(plain(page))
                score = t[:, at].sum(axis=1, dtype=np.float64) * min(1.0, most / len(at)) if len(at) > 2 else np.zeros(len(langs))
                found.append((score - score.max()).tolist())
                m = _DECLARED.search(page or "")
                lang = ((m[1] or m[2]).lower()) if m else ""
                declared.append(lang if lang in langs else "other" if lang else "none")
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(declared, pa.string()), pa.array(found, pa.list_(pa.float64()))], names=["page_id", "url", "declared", "text"])

    read = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(
        run, "page_id long, url string, declared string, text array<double>")
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1))
    return read.withColumn("host", host).withColumn("domain", F.substring_index("host", ".", -2)).withColumn("suffix", F.substring_index("host", ".", -1))


def identify(pages: DataFrame, docs: DataFrame, max_train: int = 4_000, weight: float = 5.0, alpha: float = 1.0) -> DataFrame:
    """(page_id, url, lang, probability, text_lang, declared), a row for each row of ``pages``."""
    langs, table = fit(docs, max_train)
    n = len(langs)
    each = range(n)
    e = saved(evidence(pages, langs, table), "evidence")
    # the text's own posterior, soft counts of everything below
    power = F.transform("text", F.exp)
    e = e.withColumn("soft", F.transform(power, lambda x: x / F.aggregate(power, F.lit(0.0), lambda a, y: a + y)))
    sums = [F.sum(F.col("soft")[i]).alias(f"s{i}") for i in each]
    array = lambda prefix: F.array(*(F.coalesce(F.col(f"{prefix}{i}"), F.lit(0.0)) for i in each))
    total = e.agg(*sums).select(array("s").alias("all_n"))
    suffix = e.groupBy("suffix").agg(*sums).select("suffix", array("s").alias("suffix_n"))
    domain = e.groupBy("suffix", "domain").agg(*sums).select("suffix", "domain", array("s").alias("domain_n"))
    host = saved(e.groupBy("suffix", "domain", "host").agg(*sums).select("suffix", "domain", "host", array("s").alias("host_n")), "hosts")

    def smoothed(counts, above):
        size = F.aggregate(counts, F.lit(0.0), lambda a, y: a + y)
        return F.zip_with(counts, above, lambda c, p: (c + weight * p) / (size + weight))

    flat = F.array(*(F.lit(1.0 / n) for _ in each))
    country = F.array(*(F.when(F.col("suffix").isin(SUFFIXES.get(lang, "").split() or [""]) & (F.col("suffix") != ""), 3.0).otherwise(1.0) for lang in langs))
    levels = (host.join(domain, ["suffix", "domain"]).join(suffix, "suffix").join(F.broadcast(total), F.lit(True))
              .withColumn("p_all", smoothed(F.col("all_n"), flat))
              .withColumn("p_suffix", F.zip_with(smoothed(F.col("suffix_n"), F.col("p_all")), country, lambda p, c: p * c))
              .withColumn("p_domain", smoothed(F.col("domain_n"), F.transform("p_suffix", lambda p: p / F.aggregate("p_suffix", F.lit(0.0), lambda a, y: a + y)))))
    priors = levels.select("suffix", "domain", "host", "host_n", "p_domain")
    # P(declared | language), a row for each language, for others and for none
    said = e.groupBy("declared").agg(*sums).select("declared", array("s").alias("said_n"))
    rate = F.zip_with("said_n", "all_n", lambda s, a: (s + alpha) / (a + alpha * (n + 2)))
    spoken = said.join(F.broadcast(total), F.lit(True)).select("declared", rate.alias("said"))
    joined = e.join(F.broadcast(spoken), "declared").join(priors, ["suffix", "domain", "host"])
    rest = F.zip_with("host_n", "soft", lambda h, s: F.greatest(h - s, F.lit(0.0)))
    joined = joined.withColumn("prior", smoothed(rest, F.col("p_domain")))
    logs = F.zip_with(F.zip_with("text", "said", lambda t, s: t + F.log(s)), "prior", lambda t, p: t + F.log(p))
    joined = joined.withColumn("logs", logs).withColumn("odds", F.transform("logs", lambda x: F.exp(x - F.array_max("logs"))))
    names = F.array(*(F.lit(x) for x in langs))
    pick = lambda col: F.element_at(names, F.array_position(col, F.array_max(col)).cast("int"))
    return joined.select("page_id", "url", pick(F.col("odds")).alias("lang"), (F.array_max("odds") / F.aggregate("odds", F.lit(0.0), lambda a, y: a + y)).alias("probability"), pick(F.col("text")).alias("text_lang"), "declared")
