"""Association and dependency measures, the baselines, from one table of joint counts.

Every measure is algebra over n_xy and its marginals. Entropies are in bits.
Larger means more reliable. Constant outputs count as fully determined; where
every input is different, the bias-corrected g3 and mu are 0. A candidate without
rows has no counts and no row; callers give it the lowest score.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MEASURES = ("chi", "mi", "fi", "smi", "rho", "g1", "g1s", "g1sp", "g2", "g3", "g3n", "pdep", "mu", "tau")


def pair_counts(df: DataFrame, pairs: Sequence[tuple[str, Sequence[str], str]], only: Sequence[Column | None] | None = None) -> DataFrame:
    """(cand, x, y, n) of (name, inputs, output) triples, a pass for 32 of them; several inputs are one array as text, so no
    delimiter inside a cell can make two keys equal. ``only`` has the rows that count for each triple."""
    key = lambda cols: F.to_json(F.array(*(F.coalesce(F.col(c).cast("string"), F.lit("\x00null")) for c in cols)))
    keep = lambda i: F.lit(True) if only is None or only[i] is None else F.coalesce(only[i], F.lit(False))
    rows = [F.struct(F.lit(name).alias("cand"), key(xs).alias("x"), F.coalesce(F.col(y).cast("string"), F.lit("\x00null")).alias("y"), keep(i).alias("k")) for i, (name, xs, y) in enumerate(pairs)]
    parts = [df.select(F.inline(F.array(*rows[at:at + 32]))) for at in range(0, len(rows), 32)]  # what a generated method can hold
    return reduce(DataFrame.unionByName, parts).where("k").groupBy("cand", "x", "y").agg(F.count("*").alias("n"))


def _xlog(n: Column) -> Column:
    return n * F.log2(n)


def summaries(counts: DataFrame) -> DataFrame:
    """One row per candidate with all sums that the measures need."""
    n = F.col("n").cast("double")
    by_x = counts.groupBy("cand", "x").agg(F.sum(n).alias("nx"), F.max(n).alias("best"), F.sum(n * n).alias("sq"), F.count("*").alias("ys"))
    by_y = counts.groupBy("cand", "y").agg(F.sum(n).alias("ny"))
    sx = by_x.groupBy("cand").agg(F.sum("nx").alias("N"), F.count("*").alias("Kx"), F.sum(_xlog(F.col("nx"))).alias("lx"), F.sum("best").alias("best"), F.sum(F.col("nx") * F.col("nx") - F.col("sq")).alias("viol"),
                                  F.sum(F.col("sq") / F.col("nx")).alias("dep"), F.sum(F.when(F.col("ys") == 1, F.col("nx")).otherwise(0.0)).alias("pure"))
    sy = by_y.groupBy("cand").agg(F.count("*").alias("Ky"), F.sum(_xlog(F.col("ny"))).alias("ly"), F.sum(F.col("ny") * F.col("ny")).alias("sqy"))
    joint = counts.join(by_x.select("cand", "x", "nx"), ["cand", "x"]).join(by_y, ["cand", "y"])
    sxy = joint.groupBy("cand").agg(F.count("*").alias("Kxy"), F.sum(_xlog(n)).alias("lxy"), F.sum(n * n / (F.col("nx") * F.col("ny"))).alias("phi"), F.sum(_xlog(n + 1)).alias("lxy1"))
    # smoothed marginals: every row and column of the grid gets one more in each of its cells
    ks = sx.select("cand", "Kx").join(sy.select("cand", "Ky"), "cand")
    lx1 = by_x.join(ks, "cand").groupBy("cand").agg(F.sum(_xlog(F.col("nx") + F.col("Ky"))).alias("lx1"))
    ly1 = by_y.join(ks, "cand").groupBy("cand").agg(F.sum(_xlog(F.col("ny") + F.col("Kx"))).alias("ly1"))
    out = sx
    for part in (sy, sxy, lx1, ly1):
        out = out.join(part, "cand")
    return out


def measures(counts: DataFrame) -> DataFrame:
    """(cand, one column per measure)."""
    s = summaries(counts)
    N, Kx, Ky, Kxy = (F.col(c) for c in ("N", "Kx", "Ky", "Kxy"))
    h = lambda sums, total: F.log2(total) - F.col(sums) / total
    hx, hy, hxy = h("lx", N), h("ly", N), h("lxy", N)
    mi, cond = hx + hy - hxy, hxy - hx
    size = N + Kx * Ky
    smi = h("lx1", size) + h("ly1", size) - h("lxy1", size)
    chi2 = N * (F.col("phi") - 1)
    low = F.least(Kx, Ky) - 1
    pdep, base = F.col("dep") / N, F.col("sqy") / (N * N)
    constant = Ky == 1
    one = F.lit(1.0)
    return s.select(
        "cand",
        F.when(low > 0, F.sqrt(F.greatest(chi2, F.lit(0.0)) / (N * low))).otherwise(one).alias("chi"),
        mi.alias("mi"), F.when(constant, one).otherwise(mi / hy).alias("fi"), smi.alias("smi"), (Kx / Kxy).alias("rho"),
        (1 - F.col("viol") / (N * N)).alias("g1"), (1 - cond).alias("g1s"), F.greatest(1 - cond, F.lit(0.0)).alias("g1sp"), (F.col("pure") / N).alias("g2"), (F.col("best") / N).alias("g3"),
        F.when(N > Kx, F.greatest((F.col("best") - Kx) / (N - Kx), F.lit(0.0))).otherwise(F.lit(0.0)).alias("g3n"), pdep.alias("pdep"),
        F.when(N <= Kx, F.lit(0.0)).when(constant, one).otherwise(F.greatest(1 - (1 - pdep) / (1 - base) * (N - 1) / (N - Kx), F.lit(0.0))).alias("mu"),
        F.when(constant, one).otherwise((pdep - base) / (1 - base)).alias("tau"))


def expected_information(xs: np.ndarray, ys: np.ndarray, cx: np.ndarray | None = None, cy: np.ndarray | None = None) -> float:
    """Expected mutual information of two groupings under permutation, in bits; ``cx`` and ``cy`` say how many groups
    have each size, one if not given.

    Groups of one size share their hypergeometric sum, so the work grows with
    different sizes, at most the square root of twice the rows on each side.
    """
    cx, cy = (np.ones(len(v), np.int64) if c is None else c for v, c in ((xs, cx), (ys, cy)))
    n = int((xs * cx).sum())
    lg = np.vectorize(math.lgamma, otypes=[float])
    fact = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, n + 1)))]) if n <= 5_000_000 else None
    f = (lambda k: fact[k]) if fact is not None else (lambda k: lg(np.asarray(k, float) + 1))
    total = 0.0
    (ux, ix), (uy, iy) = (np.unique(v, return_inverse=True) for v in (xs, ys))
    for a, ka in zip(ux.astype(int), np.bincount(ix, cx)):
        for b, kb in zip(uy.astype(int), np.bincount(iy, cy)):
            k = np.arange(max(1, a + b - n), min(a, b) + 1)
            if not len(k):
                continue
            p = np.exp(f(np.array(a)) + f(np.array(b)) + f(np.array(n - a)) + f(np.array(n - b)) - f(np.array(n)) - f(k) - f(a - k) - f(b - k) - f(n - a - b + k))
            total += ka * kb * float((k / n * np.log2(n * k / (a * b)) * p).sum())
    return total


def reliable_information(counts: DataFrame) -> DataFrame:
    """(cand, rfi, rfi_norm): the fraction of information above chance, plain and scaled, floored at 0.

    Sizes of groups are counted first; each candidate's task sees size histograms, not rows.
    """
    sizes = counts.groupBy("cand", "x").agg(F.sum("n").alias("k")).groupBy("cand", "k").agg(F.count("*").alias("c")).withColumn("side", F.lit("x")).unionByName(
        counts.groupBy("cand", "y").agg(F.sum("n").alias("k")).groupBy("cand", "k").agg(F.count("*").alias("c")).withColumn("side", F.lit("y")))
    base = measures(counts).select("cand", "mi", "fi")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y = (pdf[pdf.side == s] for s in "xy")
        xs, cx, ys, cy = x.k.to_numpy(), x.c.to_numpy(), y.k.to_numpy(), y.c.to_numpy()
        n = (ys * cy).sum()
        hy = math.log2(n) - float((cy * ys * np.log2(ys)).sum()) / n
        return pd.DataFrame({"cand": [pdf.cand.iloc[0]], "chance": [expected_information(xs, ys, cx, cy) / hy if hy > 0 else 1.0]})

    chance = sizes.groupBy("cand").applyInPandas(run, "cand string, chance double")
    e = F.col("chance")
    return base.join(chance, "cand").select("cand", F.greatest(F.col("fi") - e, F.lit(0.0)).alias("rfi"), F.when(e >= 1, F.lit(0.0)).otherwise(F.greatest((F.col("fi") - e) / (1 - e), F.lit(0.0))).alias("rfi_norm"))


def explanations(df: DataFrame, rels: Sequence, only_satisfied: bool = False) -> DataFrame:
    """(cand_id, conciseness, concentration, score) of rules in one pass: how short a rule is and how concentrated its
    residuals are. A value dependency's residual is whether y is the most frequent of its x."""
    from relmine.functions.expressions import evaluate, leaves, subtrees
    from relmine.operators.satisfy import dependency_counts, dependency_maps, exact_columns, holds

    spark, parts = df.sparkSession, []
    plain, fds = [r for r in rels if r.kind != "FD"], [r for r in rels if r.kind == "FD"]
    for at in range(0, len(plain), 32):
        rows = []
        for r in plain[at:at + 32]:
            made = evaluate(r.expr)
            residual = (made.cast("double") - F.col(r.output).cast("double")) if r.kind == "AR" else F.coalesce(made == F.col(r.output).cast("string"), F.lit(False)).cast("double")
            counts = F.coalesce(holds(r, exact=exact_columns(df, r)), F.lit(False)) if only_satisfied else F.lit(True)
            rows.append(F.struct(F.lit(r.cand_id).alias("cand_id"), F.round(residual, 6).alias("r"), counts.alias("counts")))
        parts.append(df.select(F.inline(F.array(*rows))).where("counts").groupBy("cand_id", "r").agg(F.count("*").alias("n")))
    if fds:
        maps = dependency_maps(dependency_counts(df, fds))
        of = F.array(F.struct(F.lit(0.0).alias("r"), F.col("n_y").alias("n")), F.struct(F.lit(1.0).alias("r"), (F.lit(0 if only_satisfied else 1) * (F.col("n") - F.col("n_y"))).alias("n")))
        parts.append(maps.select("cand_id", F.inline(of)).where("n > 0").groupBy("cand_id", "r").agg(F.sum("n").alias("n")))
    sizes = spark.createDataFrame([(r.cand_id, 1 / (1 + (2 if r.expr is None else len(leaves(r.expr)) + max(1, sum(1 for _ in subtrees(r.expr)))))) for r in rels], "cand_id string, conciseness double")
    by = reduce(DataFrame.unionByName, parts).groupBy("cand_id").agg(F.sum("n").alias("N"), F.sum(_xlog(F.col("n").cast("double"))).alias("l"), F.count("*").alias("k"))
    h = F.when(F.col("k") > 1, (F.log2("N") - F.col("l") / F.col("N")) / F.log2("k")).otherwise(F.lit(0.0))
    both = sizes.join(by, "cand_id", "left").withColumn("concentration", F.when(F.col("k").isNull(), F.lit(0.0)).otherwise(1 - h))
    return both.select("cand_id", "conciseness", "concentration", ((F.col("conciseness") + F.col("concentration")) / 2).alias("score"))


def judge_prompt(df: DataFrame, rel, rows: int = 5) -> str:
    """What a language-model judge would be asked; no model is called here."""
    sample = df.select(*rel.columns).limit(rows).collect()
    lines = [f"Columns: {', '.join(df.columns)}", f"Rule: {rel.text}", "Rows:", *(str(tuple(r)) for r in sample), "Is the rule meaningful rather than accidental? Answer with a number from 0 to 1."]
    return "\n".join(lines)


def external_scores(spark, path: str) -> DataFrame:
    """(cand_id, score) of a judge that ran elsewhere."""
    return spark.read.schema("cand_id string, score double").json(path)
