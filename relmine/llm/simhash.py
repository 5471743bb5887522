"""SimHash near-duplicates through Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into three segments of at most 23 bits. Each
segment is decoded with the perfect binary Golay code: its keys are the
codewords nearest to itself and to its one-bit neighbours, so two segments at
two or fewer differing bits always share a key (their midpoint decodes to it).
If two fingerprints differ in four bits or fewer, the two best of the three
segments together hold at most two of them, so each pair of segments gives
product keys that cannot miss a link. Candidates that share a key are verified
on the full fingerprint.

Distinct fingerprints only are keyed, so copies never meet. A bucket is linked
to a spanning forest inside its task; buckets above ``hot`` members are cut into
blocks and each pair of blocks is one bounded task.

Defined cases: null or empty text has fingerprint zero and links like any
other; fewer words than a shingle give one shingle of all words; repeated rows
are kept, one output row each; a null doc_id takes part, but is a component's
id only where no other is there; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmine.llm.common import components, saved, text_key

#: Generator polynomial of the (23, 12) Golay code, segment widths, hash seed.
GOLAY_POLY = 0b101011100011
WIDTHS = (23, 23, 18)
SEED = 42
PAIRS = ((0, 1), (0, 2), (1, 2))


def _remainders(words: np.ndarray) -> np.ndarray:
    """Syndrome of 23-bit words: remainder by the generator polynomial."""
    r = words.astype(np.uint32).copy()
    for bit in range(22, 10, -1):
        r ^= np.where((r >> np.uint32(bit)) & np.uint32(1), np.uint32(GOLAY_POLY << (bit - 11)), np.uint32(0))
    return r


def _error_table() -> np.ndarray:
    """The error of weight three or less for each syndrome; the code is perfect, so each has one."""
    one = (np.uint32(1) << np.arange(23, dtype=np.uint32)).astype(np.uint32)
    i, j = np.triu_indices(23, 1)
    two = one[i] | one[j]
    three = np.array([one[a] | one[b] | one[c] for a in range(23) for b in range(a + 1, 23) for c in range(b + 1, 23)], np.uint32)
    errors = np.concatenate([np.zeros(1, np.uint32), one, two, three])
    table = np.zeros(2048, np.uint32)
    table[_remainders(errors)] = errors
    return table


_ERRORS = _error_table()


def codeword(words: np.ndarray) -> np.ndarray:
    """Index of the nearest codeword: its 12 information bits."""
    return (words ^ _ERRORS[_remainders(words)]) >> np.uint32(11)


def segment_keys(words: np.ndarray, width: int) -> np.ndarray:
    """(n, 6) codeword indices near each segment, -1 where fewer."""
    flips = np.concatenate([np.zeros(1, np.uint32), np.uint32(1) << np.arange(width, dtype=np.uint32)]).astype(np.uint32)
    near = np.sort(codeword((words.astype(np.uint32)[:, None] ^ flips[None, :]).ravel()).reshape(len(words), -1).astype(np.int64), axis=1)
    first = np.ones(near.shape, bool)
    first[:, 1:] = near[:, 1:] != near[:, :-1]
    rank = np.cumsum(first, axis=1) - 1
    out = np.full((len(words), 6), -1, np.int64)
    rows, cols = np.nonzero(first)
    out[rows, rank[rows, cols]] = near[rows, cols]
    return out


def fuzzy_keys(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row number and key of every fuzzy key of the fingerprints (uint64)."""
    shifts = np.cumsum((0,) + WIDTHS[:-1])
    near = [segment_keys(((prints >> np.uint64(s)) & np.uint64((1 << w) - 1)).astype(np.uint32), w) for s, w in zip(shifts, WIDTHS)]
    rows, keys = [], []
    for n, (a, b) in enumerate(PAIRS):
        x, y = near[a][:, :, None], near[b][:, None, :]
        key = np.where((x >= 0) & (y >= 0), (n << 24) | (x << 12) | y, -1).reshape(len(prints), -1)
        r, c = np.nonzero(key >= 0)
        rows.append(r)
        keys.append(key[r, c])
    return np.concatenate(rows), np.concatenate(keys)


def fingerprint(text: str | None, shingle: int = 4) -> int:
    words = (text or "").encode().translate(_LOWER).split()
    if not words:
        return 0
    n = len(words)
    if n <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = (ends - [len(w) + 1 for w in words]).tolist()
    stops = (ends - 1).tolist()[shingle - 1:]
    digest = xxhash.xxh64_intdigest
    count, total = np.zeros(64, np.int64), len(stops)
    for at in range(0, total, 1 << 16):
        part = np.array([digest(joined[a:b], SEED) for a, b in zip(starts[at:at + (1 << 16)], stops[at:at + (1 << 16)])], np.uint64)
        count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * count > total, bitorder="little").view(np.uint64)[0])


_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """(doc_id, tid, fp): one row per row of ``docs``, the fingerprint as a signed long; tid tells apart texts under one id."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t, shingle) for t in b.column(2).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp)], names=["doc_id", "tid", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tid"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, tid long, fp long")


def _merge(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the classes of a[i] and b[i]; parent stays flat and points to the smallest."""
    while True:
        x, y = parent[a], parent[b]
        d = x != y
        if not d.any():
            return
        np.minimum.at(parent, np.maximum(x, y)[d], np.minimum(x, y)[d])
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent[:] = up


def _close(x: np.ndarray, y: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    return np.nonzero(np.bitwise_count(x[:, None] ^ y[None, :]) <= bits)


def bucket_forest(keys: np.ndarray, prints: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges (fp, smaller fp) of a spanning forest over the links inside the buckets; keys are sorted."""
    own, at = np.unique(prints, return_inverse=True)
    u, parent = prints.view(np.uint64), np.arange(len(own))
    edge = np.flatnonzero(np.diff(keys)) + 1
    starts, sizes = np.concatenate([[0], edge]), np.diff(np.concatenate([[0], edge, [len(keys)]]))
    small = np.repeat(sizes <= 48, sizes)
    ks, us, ats = keys[small], u[small], at[small]
    for d in range(1, int(min(48, sizes.max(initial=0)))):
        i = np.flatnonzero(ks[d:] == ks[:-d])
        if len(i) == 0:
            break
        i = i[np.bitwise_count(us[i] ^ us[i + d]) <= bits]
        _merge(parent, ats[i], ats[i + d])
    for s, n in zip(starts[sizes > 48], sizes[sizes > 48]):
        mine, ids = u[s:s + n], at[s:s + n]
        for j in range(0, n, 1024):
            x, y = _close(mine[j:j + 1024], mine[j:], bits)
            _merge(parent, ids[x + j], ids[y + j])
    linked = np.flatnonzero(parent != np.arange(len(own)))
    return own[linked], own[parent[linked]]


def fuzzy_links(prints: DataFrame, bits: int = 4, hot: int = 8192) -> DataFrame:
    """Edges (u, v) that connect all distinct fingerprints ``fp`` linked at ``bits`` or fewer bits."""
    if bits > 4:
        raise ValueError("the segment keys are complete up to four bits")

    def expand(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = b.column(0).to_numpy(zero_copy_only=False)
            for at in range(0, len(fp), 4096):
                part = fp[at:at + 4096]
                rows, keys = fuzzy_keys(part.view(np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(part[rows])], names=["key", "fp"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Buckets arrive sorted; a bucket over ``hot`` rows goes out as numbered rows instead."""
        out = lambda u, v, k, n: pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(k, pa.int64()), pa.array(n, pa.int64())], names=["u", "v", "key", "n"])
        keep_k, keep_f = np.zeros(0, np.int64), np.zeros(0, np.int64)
        running, sent = None, 0

        def flush(k, f):
            edge = np.flatnonzero(np.diff(k)) + 1
            sizes = np.diff(np.concatenate([[0], edge, [len(k)]]))
            heavy = np.repeat(sizes > hot, sizes)
            if heavy.any():
                within = np.arange(len(k)) - np.repeat(np.concatenate([[0], edge]), sizes)
                yield out(f[heavy], f[heavy], k[heavy], within[heavy])
                k, f = k[~heavy], f[~heavy]
            if len(k):
                a, b = bucket_forest(k, f, bits)
                if len(a):
                    yield out(a, b, np.full(len(a), -1), np.zeros(len(a)))

        for b in batches:
            k, f = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            if running is not None:  # the bucket that is being passed on goes on
                n = int(np.searchsorted(k, running, side="right"))
                if n:
                    yield out(f[:n], f[:n], k[:n], sent + np.arange(n))
                    sent += n
                k, f = k[n:], f[n:]
                if not len(k):
                    continue
                running = None
            keep_k, keep_f = np.concatenate([keep_k, k]), np.concatenate([keep_f, f])
            if len(keep_k) < 4 * hot:
                continue
            cut = int(np.searchsorted(keep_k, keep_k[-1], side="left"))
            yield from flush(keep_k[:cut], keep_f[:cut])
            keep_k, keep_f = keep_k[cut:], keep_f[cut:]
            if len(keep_k) > hot:
                running, sent = keep_k[0], len(keep_k)
                yield out(keep_f, keep_f, keep_k, np.arange(sent))
                keep_k, keep_f = keep_k[:0], keep_f[:0]
        yield from flush(keep_k, keep_f)

    keyed = prints.select("fp").distinct().mapInArrow(expand, "key long, fp long")
    found = saved(keyed.repartition("key").sortWithinPartitions("key", "fp").mapInArrow(link, "u long, v long, key long, n long"), "links")
    edges = found.where("key < 0").select("u", "v")
    heavy = found.where("key >= 0").select("key", F.col("u").alias("fp"), F.floor(F.col("n") / (hot // 2)).alias("block"))
    blocks = heavy.groupBy("key").agg(F.max("block").alias("last"))
    pairs = heavy.join(blocks, "key").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("last").cast("int")))).select(
        "key", "fp", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"))

    def block_pair(pdf):
        import pandas as pd

        f = pdf["fp"].to_numpy().astype(np.int64)
        a, b = bucket_forest(np.zeros(len(f), np.int64), f, bits)
        return pd.DataFrame({"u": a, "v": b})

    return edges.unionByName(pairs.groupBy("key", "lo", "hi").applyInPandas(block_pair, "u long, v long"))


def grouped(docs: DataFrame, shingle: int = 4, bits: int = 4) -> tuple[DataFrame, DataFrame]:
    """The fingerprints of ``docs``, and (fp, root) for each different fingerprint."""
    prints = saved(fingerprints(docs, shingle), "prints")
    groups = components(fuzzy_links(prints, bits))
    own = prints.select("fp").distinct()
    return prints, own.join(groups, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"))


def near_duplicates(docs: DataFrame, shingle: int = 4, bits: int = 4) -> DataFrame:
    """(doc_id, fingerprint, component_id): one row per row of ``docs``."""
    prints, rooted = grouped(docs, shingle, bits)
    # the smallest doc_id of each fingerprint first, then of each component: copies never meet unsummed
    least = prints.groupBy("fp").agg(F.min("doc_id").alias("least")).join(rooted, "fp")
    heads = saved(least.groupBy("root").agg(F.min("least").alias("component_id")), "heads")  # written, so that AQE can split a large component
    named = least.select("fp", "root").join(heads, "root").select("fp", "component_id")
    return prints.join(named, "fp", "left").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def representatives(docs: DataFrame, shingle: int = 4, bits: int = 4) -> DataFrame:
    """The rows of ``docs`` that stay when each component keeps the row with its smallest doc_id, nulls last."""
    prints, rooted = grouped(docs, shingle, bits)
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tid")
    least = prints.groupBy("fp").agg(F.min(order).alias("least"), F.count("*").alias("n")).join(rooted, "fp")
    heads = saved(least.groupBy("root").agg(F.min("least").alias("head")).select(F.col("head.doc_id").alias("own_id"), F.col("head.tid").alias("own_tid")), "heads")
    kept = docs.withColumn("tid", text_key()).join(heads, F.col("doc_id").eqNullSafe(F.col("own_id")) & (F.col("tid") == F.col("own_tid")), "left_semi")
    # the head itself may stand in the table more than once, as the same id with the same text
    again = prints.groupBy("doc_id", "tid").agg(F.count("*").alias("n")).where("n > 1").limit(1).count()
    return (kept.dropDuplicates(["doc_id", "tid"]) if again else kept).drop("tid")
