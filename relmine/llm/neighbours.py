"""Nearest neighbours by a block matrix join on int8 tiles with error bounds.

Queries and candidates are dealt into blocks of bounded size; each pair of
blocks is one task. Unit vectors are quantised to int8, a tile of integer
products gives approximate cosines, and the measured quantisation errors bound
each of them: |u.v - u'.v'| <= |v - v'| + |u - u'| |v'|. A candidate survives
where its upper bound reaches the k-th best lower bound seen so far; survivors
are recomputed from the original vectors in double precision and merged into
each query's heap of k. The heaps of the tiles are merged by rank at the end.
Nothing is lost to the approximation, so recall is 1.

Defined cases: vectors null, zero, empty, or with null or non-finite components,
and rows with a null vec_id, take no part; vectors of another length never meet;
rows with the query's own vec_id are left out; ties go to the smaller vec_id;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SCHEMA = "query_id long, vec_id long, score double"


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(id, dim, v): rows that take part."""
    v = F.col("v")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("v")).where(
        F.col("id").isNotNull() & v.isNotNull() & finite & F.exists(v, lambda x: x != 0)).select("id", F.size("v").alias("dim"), "v")


def _matrix(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids and rows in double precision, ordered by id."""
    ids = t.column("id").to_numpy()
    flat = t.column("v").combine_chunks()
    values = (flat.flatten() if not isinstance(flat, pa.ChunkedArray) else pa.concat_arrays(flat.chunks).flatten()).to_numpy(zero_copy_only=False)
    order = np.argsort(ids, kind="stable")
    return ids[order], values.astype(np.float64).reshape(len(ids), -1)[order]


def quantised(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(int8 codes, scale, error norm, norm of the quantised row) of unit vectors."""
    big = np.abs(rows).max(axis=1, keepdims=True)  # so that no square over- or underflows
    unit = rows / big
    unit /= np.sqrt((unit * unit).sum(axis=1, keepdims=True))
    scale = np.abs(unit).max(axis=1) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    back = codes * scale[:, None]
    return codes, scale, np.sqrt(((unit - back) ** 2).sum(axis=1)), np.sqrt((back**2).sum(axis=1))


def _tame(rows: np.ndarray) -> np.ndarray:
    """Rows whose squares could over- or underflow, scaled; all others as they are."""
    big = np.abs(rows).max(axis=1, keepdims=True, initial=0)
    return rows / np.where((big > 1e100) | (big < 1e-100), big, 1.0)


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, in double precision; equal rows give equal results."""
    a, b = _tame(a), _tame(b)
    return (a * b).sum(axis=1) / (np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1)))


def _best(q: np.ndarray, score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of each query's k best, ties to the smaller id."""
    order = np.lexsort((ids, -score, q))
    first = np.concatenate([[0], np.flatnonzero(np.diff(q[order])) + 1]) if len(q) else np.zeros(0, int)
    place = np.arange(len(q)) - np.repeat(first, np.diff(np.concatenate([first, [len(q)]])))
    return order[place < k]


def tile(queries: pa.Table, candidates: pa.Table, k: int, rows: int = 256, cols: int = 8192) -> pa.Table:
    """The k best candidates of each query in a pair of blocks."""
    out = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
    if queries.num_rows and candidates.num_rows:
        qid, q = _matrix(queries)
        cid, c = _matrix(candidates)
        qc, qs, qe, _ = quantised(q)
        cc, cs, ce, cn = quantised(c)
        heaps = []
        for a in range(0, len(q), rows):
            part = slice(a, a + rows)
            floor = np.full((len(qid[part]), k), -np.inf)  # the k best lower bounds so far
            heap = (np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64))
            for b in range(0, len(c), cols):
                some = slice(b, b + cols)
                # products of int8 codes are whole numbers that float32 holds exactly up to 1,040 dimensions
                kind = np.float32 if q.shape[1] <= 1000 else np.float64
                near = (qc[part].astype(kind) @ cc[some].astype(kind).T) * (qs[part][:, None] * cs[some][None, :])
                bound = ce[some][None, :] + qe[part][:, None] * cn[some][None, :] + 1e-6
                low = near - bound
                low[qid[part][:, None] == cid[some][None, :]] = -np.inf
                top = min(k, low.shape[1])
                floor = np.sort(np.concatenate([floor, np.partition(low, low.shape[1] - top, axis=1)[:, -top:]], axis=1), axis=1)[:, -k:]
                qi, ci = np.nonzero((near + bound >= floor[:, :1]) & (low > -np.inf))
                score = np.concatenate([cosine(q[part][qi[i:i + 65536]], c[some][ci[i:i + 65536]]) for i in range(0, len(qi), 65536)] or [np.zeros(0)])
                heap = tuple(np.concatenate(x) for x in zip(heap, (qi, score, cid[some][ci])))
                best = _best(*heap, k)
                heap = tuple(x[best] for x in heap)
            heaps.append((qid[part][heap[0]], heap[2], heap[1]))
        out = [np.concatenate(x) for x in zip(*heaps)]
    return pa.table({"query_id": pa.array(out[0], pa.int64()), "vec_id": pa.array(out[1], pa.int64()), "score": pa.array(out[2], pa.float64())})


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 5, query_block: int = 2048, block: int = 16384, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k nearest rows of ``vectors`` by cosine."""
    c, q = usable(vectors, id_col, vec_col), usable(queries, id_col, vec_col)
    nc, nq = max(1, -(-c.count() // block)), max(1, -(-q.count() // query_block))
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    deal = lambda n: F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")
    left = q.select("id", "dim", "v", deal(nq).alias("qb"), spread(nc).alias("cb"))
    right = c.select("id", "dim", "v", deal(nc).alias("cb"), spread(nq).alias("qb"))
    tiles = left.groupBy("dim", "qb", "cb").cogroup(right.groupBy("dim", "qb", "cb")).applyInArrow(lambda a, b: tile(a, b, k), SCHEMA)
    by = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return tiles.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
