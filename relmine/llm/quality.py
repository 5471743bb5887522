"""Quality by perplexity under an interpolated modified Kneser-Ney model of trusted text.

Model. Words are the runs between white space, as they are; a word that repeats
the one before it is another word than where it stands first, for repetition is
what junk has and prose has not. n-grams of words are counted per language over all
trusted text: tasks count their own, counts meet by n-gram, and continuation
counts, discounts and context totals are grouped joins of those counts. The
tables grow with the trusted text; none is gathered or broadcast.

Scoring. In backing-off form an interpolated model's log-probability of a text is
a sum over its n-grams: log p(w | u v) is the sum of the back-off weights of the
contexts and of what each seen n-gram has above backing off, so an n-gram that the
model lacks adds nothing. A document's score is then a join of its n-grams with
the model, summed by document. Both sides travel as sorted lists of hashes,
packed by shard of the hash; a shard holds its part of the model and streams the
documents' lists. To bound the disk that is used at once, n-grams are counted in
``parts``, each is joined with its contexts in ``SLICES`` and documents are scored
in ``passes`` by hash. The n-gram's hash has ``2 ** slack`` places for each n-gram of the corpus
at least, so a wrong match has a chance of 2 ** -slack.

Thresholds. One trusted document in ``folds`` is not trained on; a language's
threshold is a quantile of the perplexities of those, with a margin. A language
with fewer than ``enough`` of them has no threshold, and its documents stay.

Defined cases: null and empty texts have no words and hold the end mark only;
short texts are drawn to their language's average by ``prior`` tokens; documents
without label take no part in training; a language without trusted text has no
perplexity, and its documents stay; null lang is a language of its own; repeated
rows get equal results; very long texts are one document like others, cut over
several blocks; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmine.llm.common import dropped, mark, release, saved, text_key

#: Marks before a text and after it; what sets a repeated word apart.
BEFORE, AFTER, AGAIN = np.uint64(1), np.uint64(2), np.uint64(0xA0761D6478BD642F)
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: A part of the n-grams moves twice to become model entries: so many pieces of it one after the other.
SLICES = 4
#: Rows of a batch between Spark and Python: of texts, and of packed lists, which are far larger than a text.
TEXTS, LISTS = 2_000, 128


def word_hashes(texts: pa.Array) -> list[np.ndarray]:
    """Hashes of each text's words. The different words of all texts are hashed once; Arrow parts at the same characters as Python."""
    lists = pc.utf8_split_whitespace(texts.fill_null(""))
    words, ends = lists.flatten(), np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False), dtype=np.int64)])
    some = pc.binary_length(words).to_numpy(zero_copy_only=False) > 0  # none before or behind white space at an end
    ends = np.concatenate([[0], np.cumsum(some)])[ends]
    coded = words.filter(pa.array(some)).dictionary_encode()
    own = np.array([xxhash.xxh3_64_intdigest(w) for w in coded.dictionary.cast(pa.binary()).to_pylist()], np.uint64) | np.uint64(8)  # apart from the marks
    h = own[coded.indices.to_numpy(zero_copy_only=False)]
    again = np.concatenate([[False], h[1:] == h[:-1]])[:len(h)]
    again[ends[:-1][ends[:-1] < len(h)]] = False
    h[again] ^= AGAIN
    return [h[i:j] for i, j in zip(ends, ends[1:])]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


def gram_keys(salt: np.ndarray, words: list[np.ndarray]) -> np.ndarray:
    """64-bit hashes of n-grams given word by word; the salt is the language."""
    key = salt
    for w in words:
        key = _mixed(key * _ODD + w)
    return key


class Block:
    """The token sequences of several texts end to end."""

    def __init__(self, texts: list[np.ndarray], langs: list[int], order: int):
        head, tail = np.full(order - 1, BEFORE), np.array([AFTER])
        self.order, sizes = order, np.array([len(t) + order for t in texts], np.int64)
        self.tokens = np.concatenate([x for t in texts for x in (head, t, tail)])
        self.doc = np.repeat(np.arange(len(texts)), sizes)
        self.place = np.arange(len(self.tokens)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        self.lang = np.array(langs, np.int64)[self.doc]

    def grams(self, k: int) -> tuple[np.ndarray, list[np.ndarray]]:
        """Where the n-grams of k words start that predict a token or are the context of one, and their words."""
        n = len(self.tokens) - k + 1
        first = self.order - 1 if k == self.order else self.order - 2
        start = np.flatnonzero((self.doc[:n] == self.doc[k - 1:]) & (self.place[k - 1:] >= first)) if n > 0 else np.zeros(0, np.int64)
        return start, [self.tokens[start + i] for i in range(k)]


def blocks(batches: Iterator[pa.RecordBatch], order: int, size: int) -> Iterator[tuple[np.ndarray, Block]]:
    """(key of each text, its block) of rows (key, l, text); a text of more than ``size`` words is a block alone."""
    held, words = ([], [], []), 0
    for b in batches:
        for key, lang, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), word_hashes(b.column(2))):
            if words and words + len(t) > size:
                yield np.array(held[0], np.int64), Block(held[2], held[1], order)
                held, words = ([], [], []), 0
            for part, x in zip(held, (key, lang, t)):
                part.append(x)
            words += len(t) + order
    if held[0]:
        yield np.array(held[0], np.int64), Block(held[2], held[1], order)


def words_of(k: int) -> list[str]:
    return [f"w{i}" for i in range(1, k + 1)]


def gram_counts(texts: DataFrame, order: int, part: int = 0, parts: int = 1, size: int = 500_000) -> DataFrame:
    """(l, w1, ..., n): the n-grams of ``order`` words of rows (key, l, text), each language's own; of ``parts`` parts by
    the first word, one."""
    names = words_of(order)

    def run(batches):
        for _, block in blocks(batches, order, size):
            start, words = block.grams(order)
            if parts > 1:
                own = _mixed(words[0]) % np.uint64(parts) == part
                start, words = start[own], [w[own] for w in words]
            lang = block.lang[start]
            keys = gram_keys(lang.view(np.uint64), words)
            at = np.argsort(keys)  # which of equal n-grams comes first does not matter
            first = np.flatnonzero(np.concatenate([[True], np.diff(keys[at]) != 0])[:len(at)])
            at, n = at[first], np.diff(np.append(first, len(at)))
            yield pa.RecordBatch.from_arrays([pa.array(lang[at]), *(pa.array(w[at].view(np.int64)) for w in words), pa.array(n.astype(np.int64))], names=["l", *names, "n"])

    found = texts.select(F.lit(0).cast("long").alias("key"), "l", "text").mapInArrow(run, ", ".join(f"{c} long" for c in ["l", *names, "n"]))
    return found.groupBy("l", *names).agg(F.sum("n").alias("n"))


def _discounts(counts: DataFrame) -> DataFrame:
    """(l, d1, d2, d3): modified Kneser-Ney discounts of one order, from how many n-grams were seen once to four times."""
    some = counts.groupBy("l").agg(*(F.count_if(F.col("n") == k).cast("double").alias(f"n{k}") for k in (1, 2, 3, 4)))
    y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))
    kept = lambda d, top: F.when((F.col("n1") > 0) & (F.col("n2") > 0), F.least(F.greatest(F.coalesce(d, F.lit(3.0)), F.lit(0.05)), F.lit(top))).otherwise(F.lit(0.5))
    return some.select("l", kept(1 - 2 * y * F.try_divide("n2", "n1"), 0.95).alias("d1"), kept(2 - 3 * y * F.try_divide("n3", "n2"), 1.9).alias("d2"),
                       kept(3 - 4 * y * F.try_divide("n4", "n3"), 2.8).alias("d3"))


def _taken() -> F.Column:
    return F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3"))


def _united(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _slices(*frames: DataFrame) -> Iterator[list[DataFrame]]:
    """The rows of ``frames`` in pieces by the first word, which all of them have."""
    for i in range(SLICES):
        yield [f.where(F.pmod(F.xxhash64("w1"), F.lit(SLICES)) == i) for f in frames]


def model_entries(counts: list[DataFrame], order: int) -> tuple[Iterator[tuple[int, DataFrame]], DataFrame]:
    """Entries (k, rows (l, w1, ..., wk, value)) to be summed where an n-gram has two, and (l, unknown), the
    log-probability of a word that was never seen. ``counts`` are parts by the first word."""
    tables = {order: counts}
    for k in range(order - 1, 0, -1):  # how many different words stand before
        tables[k] = [saved(_united(tables[k + 1]).groupBy("l", *(F.col(f"w{i + 1}").alias(f"w{i}") for i in range(1, k + 1))).agg(F.count("*").alias("n")), f"grams{k}")]
    discounts = {k: saved(_discounts(_united(t)), "discounts") for k, t in tables.items()}
    sums = [F.sum("n").alias("all"), F.sum(_taken()).alias("off")]
    langs = tables[1][0].join(discounts[1], "l").groupBy("l").agg(*sums, F.count("*").alias("types")).join(discounts[1], "l")
    langs = saved(langs.withColumn("unknown", F.log(F.col("off") / F.col("all") / (F.col("types") + 1))), "languages")

    def entries():
        lower = tables[1][0].join(langs, "l").select("l", "w1", ((F.col("n") - _taken()) / F.col("all") + F.exp("unknown")).alias("p"), "unknown")
        lower = saved(lower, "unigrams")
        dropped(tables[1][0])
        yield 1, lower.select("l", "w1", (F.log("p") - F.col("unknown")).alias("value"))
        for k in range(2, order + 1):
            context, suffix = words_of(k - 1), [f"w{i}" for i in range(2, k + 1)]
            below = lower.select("l", *(F.col(f"w{i}").alias(f"w{i + 1}") for i in range(1, k)), F.col("p").alias("low"))
            full = []
            for table in tables[k]:
                own = table.join(discounts[k], "l")
                weights = saved(own.groupBy("l", *context).agg(*sums).select("l", *context, "all", (F.col("off") / F.col("all")).alias("rest")), "weights")
                yield k - 1, weights.select("l", *context, F.log("rest").alias("value"))
                for piece, of in _slices(own, weights):
                    # what is moved for the second join is as narrow as can be
                    above = piece.select("l", *words_of(k), (F.col("n") - _taken()).alias("n")).join(of, ["l", *context]).select("l", *words_of(k), (F.col("n") / F.col("all") / F.col("rest")).alias("x"), *(["rest"] if k < order else []))
                    met = above.join(below, ["l", *suffix])
                    if k < order:
                        met = saved(met.select("l", *words_of(k), (F.col("rest") * (F.col("low") + F.col("x"))).alias("p"), F.log1p(F.col("x") / F.col("low")).alias("value")), f"scores{k}")
                        full.append(met)
                        yield k, met.select("l", *words_of(k), "value")
                    else:
                        yield k, met.select("l", *words_of(k), F.log1p(F.col("x") / F.col("low")).alias("value"))
                if k == order:
                    dropped(table)
                dropped(weights)
            if k == order:
                dropped(lower)
            else:
                lower = _united(full)

    return entries(), langs.select("l", "unknown")


def _squeezed(values: np.ndarray) -> bytes:
    """Whole numbers byte by byte of their places, so that the upper ones, mostly alike, cost little."""
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(values.view(np.uint8).reshape(len(values), values.itemsize).T).tobytes())


def _spread(packed: bytes, kind: type) -> np.ndarray:
    flat = np.frombuffer(zstandard.ZstdDecompressor().decompress(packed), np.uint8)
    return np.ascontiguousarray(flat.reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel() if len(flat) else np.zeros(0, kind)


#: keys: differences of the sorted hashes. Of a model: values. Of documents: how many documents each hash has, which,
#: how often each, what documents these are, and in a block's first list how many tokens they have.
_PACKED = "shard int, kind int, keys binary, a binary, b binary, c binary, ids binary, tokens binary"


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32()] + [pa.binary()] * 6
    names = [f.split()[0] for f in _PACKED.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)


def _cuts(keys: np.ndarray, shards: int, bits: int) -> np.ndarray:
    """Where the shards of sorted hashes begin, and the end."""
    return np.searchsorted(keys, np.array([-(-(s << bits) // shards) for s in range(shards)], np.uint64)).tolist() + [len(keys)]


def packed_entries(frame: DataFrame, k: int, shards: int, bits: int, size: int = 1_000_000) -> DataFrame:
    """Entries of n-grams of k words by shard."""
    def flush(held):
        key, value = (np.concatenate(x) for x in zip(*held))
        order = np.argsort(key)
        key, value = key[order], value[order]
        cuts = _cuts(key, shards, bits)
        return _rows([(s, 0, _squeezed(np.diff(key[i:j], prepend=np.uint64(0))), _squeezed(value[i:j]), None, None, None, None) for s, (i, j) in enumerate(zip(cuts, cuts[1:])) if i < j])

    def run(batches):
        held, rows = [], 0
        for b in batches:
            if len(b):
                lang, *words = (c.to_numpy(zero_copy_only=False).view(np.uint64) for c in b.columns[:-1])
                held.append((gram_keys(lang, words) >> np.uint64(64 - bits), b.column(k + 1).to_numpy(zero_copy_only=False).astype(np.float32)))
                rows += len(b)
            if rows >= size:
                yield flush(held)
                held, rows = [], 0
        if held:
            yield flush(held)

    return frame.select("l", *words_of(k), "value").mapInArrow(run, _PACKED)


def packed_documents(texts: DataFrame, order: int, shards: int, bits: int, size: int = 300_000) -> DataFrame:
    """The n-grams of the rows (key, l, text) by shard."""
    def run(batches):
        for ids, block in blocks(batches, order, size):
            keys, docs = [], []
            for k in range(1, order + 1):
                start, words = block.grams(k)
                keys.append(gram_keys(block.lang[start].view(np.uint64), words) >> np.uint64(64 - bits))
                docs.append(block.doc[start])
            key, doc = np.concatenate(keys), np.concatenate(docs).astype(np.uint32)
            width = np.uint64(len(ids).bit_length())
            if bits + int(width) <= 64:  # one number to sort by
                both = np.sort((key << width) | doc)
                key, doc = both >> width, (both & ((np.uint64(1) << width) - np.uint64(1))).astype(np.uint32)
            else:
                at = np.lexsort((doc, key))
                key, doc = key[at], doc[at]
            pair = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])]))
            many = np.diff(np.append(pair, len(key))).astype(np.uint32)
            key, doc = key[pair], doc[pair]
            first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            each = np.diff(np.append(first, len(key))).astype(np.uint32)
            tokens = np.bincount(block.doc, minlength=len(ids)).astype(np.uint32) - np.uint32(order - 1)
            cuts, out = _cuts(key[first], shards, bits), []
            of = np.append(first, len(key))
            for s, (i, j) in enumerate(zip(cuts, cuts[1:])):
                if i < j or s == 0:
                    x, y = of[i], of[j]
                    out.append((s, 1, _squeezed(np.diff(key[first[i:j]], prepend=np.uint64(0))), _squeezed(each[i:j]), _squeezed(doc[x:y]), _squeezed(many[x:y]),
                                ids.tobytes(), _squeezed(tokens) if s == 0 else None))
            yield _rows(out)

    return texts.select("key", "l", "text").mapInArrow(run, _PACKED)


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, part, tokens) of each document and shard; a shard's model comes before its documents."""
    shard, held, keys, values = None, [], np.zeros(0, np.uint64), np.zeros(0)
    for b in batches:
        for i in range(len(b)):
            r = {name: c[i].as_py() for name, c in zip(b.schema.names, b.columns)}  # one list at a time
            if r["shard"] != shard:
                shard, held, keys, values = r["shard"], [], np.zeros(0, np.uint64), np.zeros(0)
            own = np.cumsum(_spread(r["keys"], np.uint64), dtype=np.uint64)
            if r["kind"] == 0:
                held.append((own, _spread(r["a"], np.float32)))
                continue
            if held:  # entries of one n-gram, as such and as a context, are summed
                k, v = (np.concatenate(x) for x in zip(*held))
                keys, at = np.unique(k, return_inverse=True)
                values, held = np.bincount(at, v, len(keys)), []
            value = np.zeros(len(own))
            if len(keys):
                at = np.minimum(np.searchsorted(keys, own), len(keys) - 1)
                value = np.where(keys[at] == own, values[at], 0.0)
            ids, each, doc, many = np.frombuffer(r["ids"], np.int64), _spread(r["a"], np.uint32), _spread(r["b"], np.uint32), _spread(r["c"], np.uint32)
            part = np.bincount(doc, np.repeat(value, each) * many, len(ids))
            tokens = np.zeros(len(ids), np.int64) if r["tokens"] is None else _spread(r["tokens"], np.uint32).astype(np.int64)
            some = np.flatnonzero((part != 0) | (tokens != 0))
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(part[some], pa.float64()), pa.array(tokens[some])], names=["key", "part", "tokens"])


def identified(docs: DataFrame) -> DataFrame:
    """(doc_id, tid, lang, l, key, text): l is the language, key the row's hash."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tid"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    l = F.xxhash64(F.coalesce("lang", F.lit("")), F.col("lang").isNull())  # noqa: E741
    return base.withColumn("l", l).withColumn("key", F.xxhash64("doc_id", "tid", "l"))


def trusted_ids(labels: DataFrame) -> DataFrame:
    return labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id")).distinct()


def log_probabilities(texts: DataFrame, training: DataFrame, order: int, slack: int = 12, shard_grams: int = 1 << 25, parts: int = 2, passes: int = 3) -> tuple[DataFrame, DataFrame]:
    """(key, logp, tokens) of the different rows of ``texts``, and the model's languages (l, unknown);
    logp lacks tokens times unknown."""
    spark = texts.sparkSession
    grams = order * (texts.agg(F.sum(F.length("text") + 1)).first()[0] or 0) // 6 + 1  # about six characters a word
    shards = max(2 * spark.sparkContext.defaultParallelism, -(-grams // shard_grams))
    bits = min(64, max(40, grams.bit_length() + slack))
    # picked once and written, so that the other texts do not lie in a shuffle while n-grams are counted
    training = saved(training.select("l", "text"), "training")
    counts = [saved(gram_counts(training, order, i, parts), "grams", TEXTS) for i in range(parts)]
    dropped(training)
    entries, langs = model_entries(counts, order)
    model = _united([saved(packed_entries(frame, k, shards, bits), "model") for k, frame in entries])
    scored = []
    for i in range(passes):
        both = model.unionByName(packed_documents(texts.where(F.pmod(F.xxhash64("doc_id"), F.lit(passes)) == i), order, shards, bits))
        sums = both.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", "kind").mapInArrow(_joined, "key long, part double, tokens long")
        scored.append(saved(sums.groupBy("key").agg(F.sum("part").alias("logp"), F.sum("tokens").alias("tokens")), "scored", LISTS))
    return _united(scored), langs


def perplexities(texts: DataFrame, training: DataFrame, order: int, ids: DataFrame | None = None) -> DataFrame:
    """(key, l, tokens, logp) of the different rows of ``texts``; logp is null without a model of the language. ``ids``
    has the rows' key and l, if they are at hand."""
    scored, langs = log_probabilities(texts, training, order)
    rows = (texts if ids is None else ids).groupBy("key", "l").agg(F.count("*").alias("rows"))  # equal rows were summed
    per = rows.join(scored, "key", "left").join(langs, "l", "left")
    tokens = F.col("tokens") / F.col("rows")
    return per.select("key", "l", tokens.cast("long").alias("tokens"), (F.col("logp") / F.col("rows") + tokens * F.col("unknown")).alias("logp"))


def quality(docs: DataFrame, labels: DataFrame, order: int = 2, quantile: float = 0.99, margin: float = 1.05, prior: float = 20.0, enough: int = 5, folds: int = 5) -> DataFrame:
    """(doc_id, tid, lang, n_words, perplexity, threshold, accepted), a row for each row of ``docs``."""
    texts, since = identified(docs), mark()
    ids = saved(texts.drop("text"), "ids")
    trusted = trusted_ids(labels).withColumn("fold", F.pmod(F.xxhash64("doc_id"), F.lit(folds)))
    scored = saved(perplexities(texts, texts.join(trusted.where("fold > 0"), "doc_id", "left_semi"), order, ids), "perplexities")
    unseen = ids.join(trusted.where("fold = 0"), "doc_id", "left_semi").select("key")
    unseen = saved(scored.join(unseen, "key").where("logp is not null"), "unseen")
    # a short text is drawn to its language's average
    drawn = F.coalesce(F.when(F.col("mean").isNotNull(), F.lit(prior)), F.lit(0.0))
    shrunk = F.exp(-(F.col("logp") + drawn * F.coalesce("mean", F.lit(0.0))) / (F.col("tokens") + drawn))
    means = saved(unseen.groupBy("l").agg((F.sum("logp") / F.sum("tokens")).alias("mean"), F.count("*").alias("seen")), "means")
    cut = F.percentile_approx("perplexity", quantile, 10_000) * margin
    limits = unseen.join(means, "l").withColumn("perplexity", shrunk).groupBy("l", "mean", "seen").agg(cut.alias("cut"))
    limits = saved(limits.select("l", "mean", F.when(F.col("seen") >= enough, F.col("cut")).alias("threshold")), "limits")
    release(docs.sparkSession, since, ids, scored, limits)
    judged = scored.join(limits, "l", "left").select("key", F.greatest(F.col("tokens") - 1, F.lit(0)).alias("n_words"), shrunk.alias("perplexity"), "threshold")
    out = ids.join(judged, "key", "left")
    return out.select("doc_id", "tid", "lang", "n_words", "perplexity", "threshold", F.coalesce(F.col("perplexity") <= F.col("threshold"), F.lit(True)).alias("accepted"))
