"""Substring deduplication: repeated runs of words found with an FM-index per shard.

Sharding. The least hash among the short word runs of a window is its anchor; it
depends on the window's words alone, so equal windows have equal anchors. The
windows of a document that share an anchor form a segment. Segments go to shards
by anchor, and equal segments are one with the smallest of their documents, so
copies never meet in a task; within a document they are one row with all its
places. Only anchors with differing segments of differing documents need a search.

Search. Each shard builds a compressed FM-index over its distinct segments and
streams them through backward search: the matching statistics restricted to
smaller documents report the windows that also start there. A segment that
another document with a smaller id holds whole needs no search.

Skew. An anchor with more than ``hot`` differing segments (a passage within many
different texts) is searched window by window on hashes instead, which needs no
group in one task.

Words are compared by 64-bit hashes. Defined cases: null or short texts have no
windows and lose nothing; equal doc_ids do not remove each other's words; a null
doc_id counts as larger than all others; repeated rows get equal results; extra
columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmine.llm.common import mark, release, saved, text_key
from relmine.llm.fmindex import FmIndex

#: Odd multipliers of the two rolling hashes, and of the mixer.
ROLL, DIGEST, MIX = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD
_MASK = (1 << 64) - 1


def word_hashes(text: str | None) -> tuple[list[bytes], np.ndarray]:
    words = (text or "").encode().split()
    digest = xxhash.xxh3_64_intdigest
    return words, np.array([digest(w) for w in words], np.uint64)


class Rolling:
    """Hashes of any run of words, from prefix sums of a polynomial with an odd base."""

    def __init__(self, hashes: np.ndarray, base: int):
        n = len(hashes)
        up, down = np.full(n, base, np.uint64), np.full(n, pow(base, -1, 1 << 64), np.uint64)
        if n:
            up[0] = down[0] = 1
        self.down = np.cumprod(down, dtype=np.uint64)
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(hashes * np.cumprod(up, dtype=np.uint64), dtype=np.uint64)])

    def runs(self, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
        """Mixed hashes of [start, stop); stop > start."""
        x = (self.sums[stops] - self.sums[starts]) * self.down[starts] + (stops - starts).astype(np.uint64)
        x ^= x >> np.uint64(33)
        x *= np.uint64(MIX)
        return x ^ (x >> np.uint64(29))


def segments(hashes: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, digest, first window, last window) of a document's segments."""
    n = len(hashes)
    if n < window:
        return (np.zeros(0, np.int64),) * 4
    starts = np.arange(n - gram + 1)
    grams, span = Rolling(hashes, ROLL).runs(starts, starts + gram), window - gram + 1
    views = np.lib.stride_tricks.sliding_window_view(grams, span)
    least = np.concatenate([views[a:a + 8192].argmin(axis=1) + np.arange(a, min(a + 8192, len(views))) for a in range(0, len(views), 8192)])
    edge = np.flatnonzero(np.diff(least)) + 1
    lo = np.concatenate([[0], edge])
    hi = np.concatenate([edge, [len(least)]]) - 1
    return grams[least[lo]].view(np.int64), Rolling(hashes, DIGEST).runs(lo, hi + window).view(np.int64), lo, hi


def _batch(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns.values()], names=list(columns))


def _identified(docs: DataFrame) -> DataFrame:
    """owner is the doc_id that counts in comparisons."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tid"), F.col("text").cast("string").alias("text")).withColumn(
        "owner", F.coalesce("doc_id", F.lit((1 << 63) - 1)))


def placed(hashes: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, digest, number of windows, number of places, places) of a document's different segments.

    A line that stands in a document many times makes the same segment each time; it is one row with many places.
    """
    g, d, lo, hi = segments(hashes, window, gram)
    order = np.lexsort((lo, d, g))
    g, d, lo, size = g[order], d[order], lo[order], (hi - lo + 1)[order]
    first = np.flatnonzero(np.concatenate([[True], (g[1:] != g[:-1]) | (d[1:] != d[:-1])])) if len(g) else np.zeros(0, np.int64)
    return g[first], d[first], size[first], np.diff(np.append(first, len(g))), lo


def anchored(docs: DataFrame, window: int, gram: int) -> DataFrame:
    """(owner, tid, g, digest, size, places): the different segments of all documents, where they begin."""
    def run(batches):
        for b in batches:
            if not len(b):
                continue
            owner, tid = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            parts = [placed(word_hashes(t)[1], window, gram) for t in b.column(2).to_pylist()]
            each = [len(p[0]) for p in parts]
            g, d, size, many, lo = (np.concatenate([p[i] for p in parts]) for i in range(5))
            places = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(many)]).astype(np.int32), pa.array(lo.astype(np.int32)))
            yield _batch(owner=np.repeat(owner, each), tid=np.repeat(tid, each), g=g, digest=d, size=size.astype(np.int32), places=places)

    return _identified(docs).select("owner", "tid", "text").mapInArrow(run, "owner long, tid long, g long, digest long, size int, places array<int>")


def _with_words(docs: DataFrame, heads: DataFrame, window: int) -> DataFrame:
    """(g, digest, owner, words): the word hashes of the segments in ``heads``."""
    wanted = heads.groupBy("owner", "tid").agg(F.collect_list(F.struct("g", "digest", "lo", "size")).alias("segments"))

    def run(batches):
        for b in batches:
            rows = []
            for owner, text, own in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                h = word_hashes(text)[1]
                rows += [(s["g"], s["digest"], owner, h[s["lo"]:s["lo"] + s["size"] + window - 1].tobytes()) for s in own]
            g, d, o, w = zip(*rows) if rows else ((),) * 4
            yield _batch(g=pa.array(g, pa.int64()), digest=pa.array(d, pa.int64()), owner=pa.array(o, pa.int64()), words=pa.array(w, pa.binary()))

    return _identified(docs).join(wanted, ["owner", "tid"]).select("owner", "text", "segments").mapInArrow(
        run, "g long, digest long, owner long, words binary")


def _search(segments_: DataFrame, window: int, shard_words: int) -> DataFrame:
    """(g, digest, a, b): word intervals, from the segment's start, that a smaller document also has."""
    def report(g, digest, owner, words):
        index = FmIndex(words, np.array(owner, np.int64))
        long_ = index.matching_statistics() >= window
        edge = np.flatnonzero(np.diff(np.concatenate([[0], long_.view(np.int8), [0]])))
        starts, stops = edge[::2], edge[1::2]  # marks never match, so a run stays within a segment
        which = np.searchsorted(index.ends, starts)
        begin = (index.ends - index.sizes)[which]
        return _batch(g=np.array(g, np.int64)[which], digest=np.array(digest, np.int64)[which], a=(starts - begin).astype(np.int32), b=(stops - 1 - begin + window).astype(np.int32))

    def run(batches):
        held, size = ([], [], [], []), 0
        for b in batches:
            for g, d, o, w in zip(*(b.column(i).to_pylist() for i in range(4))):
                if size >= shard_words and held[0][-1] != g:
                    yield report(*held)
                    held, size = ([], [], [], []), 0
                for part, x in zip(held, (g, d, o, np.frombuffer(w, np.uint64))):
                    part.append(x)
                size += len(held[3][-1])
        if held[0]:
            yield report(*held)

    return segments_.repartition("g").sortWithinPartitions("g", "digest").mapInArrow(run, "g long, digest long, a int, b int")


def _by_window(segments_: DataFrame, window: int) -> DataFrame:
    """What ``_search`` reports, from window hashes: for anchors with very many differing segments."""
    def run(batches):
        for b in batches:
            g, d, o = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            words = [np.frombuffer(w, np.uint64) for w in b.column(3).to_pylist()]
            n = np.array([len(w) - window + 1 for w in words], np.int64)
            hashes = [Rolling(w, DIGEST).runs(np.arange(k), np.arange(k) + window) for w, k in zip(words, n)]
            yield _batch(g=np.repeat(g, n), digest=np.repeat(d, n), owner=np.repeat(o, n), a=np.concatenate([np.arange(k, dtype=np.int32) for k in n] or [np.zeros(0, np.int32)]), h=np.concatenate(hashes or [np.zeros(0, np.uint64)]).view(np.int64))

    every = segments_.mapInArrow(run, "g long, digest long, owner long, a int, h long")
    least = every.groupBy("g", "h").agg(F.min("owner").alias("least"))
    return every.join(least, ["g", "h"]).where("least < owner").select("g", "digest", "a", (F.col("a") + window).cast("int").alias("b"))


def repeated_spans(docs: DataFrame, window: int = 50, gram: int = 8, hot: int = 4096, shard_words: int = 300_000) -> DataFrame:
    """(owner, tid, hits): for documents that lose words, segments' places and the word intervals [a, b) to remove
    from each place on."""
    since = mark()
    own = saved(anchored(docs, window, gram), "segments")
    head = F.min(F.struct("owner", "tid", F.element_at("places", 1).alias("lo"), "size")).alias("head")
    distinct = own.groupBy("g", "digest").agg(head, F.max("owner").alias("last"))
    distinct = saved(distinct.select("g", "digest", "last", "head.*"), "distinct")
    # both sides of the joins below are written before, so that AQE can split an anchor or a passage of many documents
    several = distinct.groupBy("g").agg(F.count("*").alias("n"), F.min("owner").alias("x"), F.max("owner").alias("y"))
    mixed = saved(several.where("n > 1 and x < y").select("g", "n"), "mixed")
    words = saved(_with_words(docs, distinct.join(mixed, "g"), window).join(mixed, "g"), "words")
    cold = _search(words.where(F.col("n") <= hot).select("g", "digest", "owner", "words"), window, shard_words)
    warm = _by_window(words.where(F.col("n") > hot).select("g", "digest", "owner", "words"), window)
    parts = saved(cold.unionByName(warm).groupBy("g", "digest").agg(F.collect_set(F.struct("a", "b")).alias("parts")), "parts")
    known = distinct.select("g", "digest", "last", F.col("owner").alias("first")).join(parts, ["g", "digest"], "left")
    known = saved(known.where("last > first or parts is not null"), "known")
    release(docs.sparkSession, since, own, known)
    hit = own.join(known, ["g", "digest"])
    whole = F.array(F.struct(F.lit(0).alias("a"), (F.col("size") + window - 1).alias("b")))
    part = F.when(F.col("owner") > F.col("first"), whole).otherwise(F.coalesce("parts", F.array().cast("array<struct<a:int,b:int>>")))
    spans = hit.select("owner", "tid", F.struct("places", part.alias("parts")).alias("hit"))
    spans = saved(spans.groupBy("owner", "tid").agg(F.collect_list("hit").alias("hits")), "spans")
    release(docs.sparkSession, since, spans)  # before the texts are moved
    return spans


def _covered(hits: list[dict], n: int) -> np.ndarray:
    """For each of ``n`` words whether a span of a hit holds it."""
    step = np.zeros(n + 1, np.int64)
    for hit in hits:
        at = np.array(hit["places"], np.int64)
        for p in hit["parts"]:
            np.add.at(step, at + p["a"], 1)
            np.add.at(step, at + p["b"], -1)
    return np.cumsum(step[:-1]) > 0


def deduplicated(docs: DataFrame, window: int = 50, gram: int = 8, keep: list[str] | None = None, with_text: bool = False) -> DataFrame:
    """A row per document: n_words, n_removed, kept_sha256 (kept words joined by one space), the ``keep`` columns,
    and with ``with_text`` the kept text; a text that loses nothing stays as it is."""
    keep = [c for c in dict.fromkeys(keep or []) if c not in ("doc_id", "text")]
    spans = repeated_spans(docs, window, gram)
    rest = F.struct(*(F.col(c) for c in keep)).alias("rest") if keep else F.lit(None).cast("string").alias("rest")
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tid"), F.col("text").cast("string").alias("text"), rest)
    base = base.withColumn("owner", F.coalesce("doc_id", F.lit((1 << 63) - 1)))
    joined = base.join(spans, ["owner", "tid"], "left").select("doc_id", "rest", "hits", "text")

    def run(batches):
        for b in batches:
            rows = []
            for hits, text in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
                words = (text or "").encode().split()
                kept, out = words, text
                if hits:
                    kept = [words[i] for i in np.flatnonzero(~_covered(hits, len(words))).tolist()]
                    if len(kept) < len(words):
                        out = b" ".join(kept).decode()
                rows.append((len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest(), out if with_text else None))
            n, removed, sha, out = zip(*rows) if rows else ((),) * 4
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(sha, pa.string()), pa.array(out, pa.string())],
                names=["doc_id", "rest", "n_words", "n_removed", "kept_sha256", "text"])

    kind = joined.schema["rest"].dataType.simpleString()
    out = joined.mapInArrow(run, f"doc_id long, rest {kind}, n_words long, n_removed long, kept_sha256 string, text string")
    return out.select("doc_id", *(F.col(f"rest.`{c}`").alias(c) for c in keep), *(["text"] if with_text else []), "n_words", "n_removed", "kept_sha256")
