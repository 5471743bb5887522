"""The Independence Test: violations of a complete rule do not depend on a left-out column.

Totals of each value of each left-out column are counted once per table, and the
violating rows of sixteen arithmetic and string rules in each scan, so what is shuffled
per rule grows with violations. With p the share of violations, chi-squared is the
sum over values with violations of (k - n p)^2 / (n p (1 - p)) plus, for all the
other values together, their rows times p / (1 - p).

Defined cases: null is a value; a constant column, no violation and nothing but
violations pass; a table without rows passes; columns may bear any name.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from relmine.functions.statistics import chi2_tail
from relmine.model import Config, Relation
from relmine.operators.satisfy import exact_columns, holds, same_rows, violations

NULL = "\x00null"


def _cell(c: str) -> dict[str, Column]:
    return {"col": F.lit(c), "value": F.coalesce(F.col(c).cast("string"), F.lit(NULL))}


def _pairs(columns: Sequence[str]) -> Column:
    """(col, value) of each column as an array; null is a value of its own."""
    return F.array(*(F.struct(p["col"].alias("col"), p["value"].alias("value")) for p in map(_cell, columns)))


def _whole(df: DataFrame, columns: Sequence[str]) -> list[str]:
    """Those of ``columns`` that are counted as numbers, and are texts only once they are counted."""
    kinds = dict(df.dtypes)
    return [c for c in columns if kinds.get(c) in ("tinyint", "smallint", "int", "bigint")]


def _named(names: Sequence[str], at: str) -> Column:
    return F.get(F.array(*map(F.lit, names)), F.col(at))


def _text(number: str) -> Column:
    return F.coalesce(F.col(number).cast("string"), F.lit(NULL))


def totals(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    whole, parts = _whole(df, columns), []
    if whole:
        cells = F.array(*(F.struct(F.lit(i).alias("c"), F.col(c).cast("bigint").alias("v")) for i, c in enumerate(whole)))
        counts = df.select(F.inline(cells)).groupBy("c", "v").agg(F.count("*").alias("n"))
        parts.append(counts.select(_named(whole, "c").alias("col"), _text("v").alias("value"), "n"))
    if len(whole) < len(columns):
        parts.append(df.select(F.inline(_pairs([c for c in columns if c not in whole]))).groupBy("col", "value").agg(F.count("*").alias("n")))
    return reduce(DataFrame.unionByName, parts)


def violating(df: DataFrame, rels: Sequence[Relation], columns: dict[str, Sequence[str]], cfg: Config) -> DataFrame:
    """(cand_id, col, value, k): violating rows of each value of each rule's ``columns``."""
    parts = []
    plain = [r for r in rels if r.kind != "FD"]
    every = sorted({c for r in plain for c in columns[r.cand_id]})
    if plain and len(_whole(df, every)) == len(every):
        ids, counts = [r.cand_id for r in plain], []
        for at in range(0, len(plain), 16):
            tagged = lambda i, r: F.array(*(F.struct(F.lit(i).alias("r"), F.lit(every.index(c)).alias("c"), F.col(c).cast("bigint").alias("v")) for c in columns[r.cand_id]))
            bad = [F.when(~holds(r, exact=exact_columns(df, r), cfg=cfg), tagged(at + i, r)) for i, r in enumerate(plain[at:at + 16])]
            counts.append(df.select(F.inline(F.flatten(F.filter(F.array(*bad), lambda x: x.isNotNull())))))
        k = reduce(DataFrame.unionByName, counts).groupBy("r", "c", "v").agg(F.count("*").alias("k"))
        parts.append(k.select(_named(ids, "r").alias("cand_id"), _named(every, "c").alias("col"), _text("v").alias("value"), "k"))
        if len(plain) == len(rels):
            return parts[0]
        return parts[0].unionByName(violating(df, [r for r in rels if r.kind == "FD"], columns, cfg))
    for at in range(0, len(plain), 16):  # a scan for some rules: a row is taken apart for those that it violates
        tagged = lambda r: F.array(*(F.struct(F.lit(r.cand_id).alias("cand_id"), p["col"].alias("col"), p["value"].alias("value")) for p in map(_cell, columns[r.cand_id])))
        bad = [F.when(~holds(r, exact=exact_columns(df, r), cfg=cfg), tagged(r)) for r in plain[at:at + 16]]
        parts.append(df.select(F.inline(F.flatten(F.filter(F.array(*bad), lambda x: x.isNotNull())))))
    for r in (r for r in rels if r.kind == "FD"):
        parts.append(violations(df, r, cfg).select(F.lit(r.cand_id).alias("cand_id"), F.inline(_pairs(columns[r.cand_id]))))
    return reduce(DataFrame.unionByName, parts).groupBy("cand_id", "col", "value").agg(F.count("*").alias("k"))


def contingency(df: DataFrame, rel: Relation, columns: Sequence[str], cfg: Config | None = None) -> DataFrame:
    """(col, value, n, k): rows and violations of each value."""
    k = violating(df, [rel], {rel.cand_id: columns}, cfg or Config()).drop("cand_id")
    return totals(df, columns).join(k, ["col", "value"], "left").select("col", "value", "n", F.coalesce("k", F.lit(0)).alias("k"))


def chi2(df: DataFrame, rels: Sequence[Relation], cfg: Config, left_out: dict[str, Sequence[str]] | None = None, all_: DataFrame | None = None) -> DataFrame:
    """(cand_id, col, chi2, df, violations, n_rows, least) for each rule and left-out column; least is the smallest
    expected count of a cell."""
    columns = [c for c in df.columns if c not in cfg.exclude]
    own = {r.cand_id: (left_out or {}).get(r.cand_id) or [c for c in columns if c not in r.columns] for r in rels}
    all_ = totals(df, sorted({c for cs in own.values() for c in cs})) if all_ is None else all_
    sizes = all_.groupBy("col").agg(F.count("*").alias("values"), F.sum("n").alias("n_rows"), F.min("n").alias("fewest"))
    by = violating(df, rels, own, cfg).join(all_, ["col", "value"])
    # every left-out column shows all of a rule's violations
    each = by.withColumn("total", F.sum("k").over(Window.partitionBy("cand_id", "col"))).join(sizes, "col").withColumn("p", F.col("total") / F.col("n_rows"))
    spread = F.col("n") * F.col("p") * (1 - F.col("p"))
    gap = F.abs(F.col("k") - F.col("n") * F.col("p"))
    if cfg.yates:
        gap = F.greatest(gap - 0.5, F.lit(0.0))
    stat = each.groupBy("cand_id", "col", "values", "n_rows", "fewest").agg(F.sum(gap * gap / F.nullif(spread, F.lit(0.0))).alias("seen"), F.sum("n").alias("covered"), F.max("p").alias("p"), F.max("total").alias("violations"))
    value = F.col("seen") + (F.col("n_rows") - F.col("covered")) * F.col("p") / F.nullif(1 - F.col("p"), F.lit(0.0))
    least = F.col("fewest") * F.least("p", 1 - F.col("p"))
    return stat.select("cand_id", "col", F.when((F.col("values") > 1) & (F.col("p") < 1), value).alias("chi2"), (F.col("values") - 1).alias("df"), "violations", "n_rows", least.alias("least"))


@F.pandas_udf(DoubleType())
def tail(x: pd.Series, df: pd.Series) -> pd.Series:
    return pd.Series([chi2_tail(a, b) if a == a and a is not None else 1.0 for a, b in zip(x, df)])


def independent(df: DataFrame, rels: Sequence[Relation], cfg: Config) -> dict[str, tuple[bool, str | None, float | None, float]]:
    """By cand_id: passed, the column with the smallest p, its chi-squared and p. Rules without violations pass.

    With ``it_columns`` set, that many columns are tested at a time, and a rule that one of them rejects is not tested on
    the rest; the order is that of the table. The corrections for several tests need all columns, and test them at once.
    Rules that the same rows violate are tested once.
    """
    keys, firsts = same_rows(df, rels), {}
    for r in rels:
        firsts.setdefault(keys[r.cand_id], r)
    if len(firsts) < len(rels):
        got = independent(df, list(firsts.values()), cfg)
        return {r.cand_id: got[firsts[keys[r.cand_id]].cand_id] for r in rels}
    out = {r.cand_id: (True, None, None, 1.0) for r in rels}
    columns, left = [c for c in df.columns if c not in cfg.exclude], list(rels)
    step = cfg.it_columns if cfg.it_columns and cfg.multiplicity == "none" else max(1, len(columns))
    for at in range(0, len(columns), step):
        some = columns[at:at + step]
        own = {r.cand_id: mine for r in left if (mine := [c for c in some if c not in r.columns])}
        tried = [r for r in left if r.cand_id in own]
        if not tried:
            continue
        all_ = totals(df, some).persist()  # values of left-out columns, shared by the rules
        try:
            found = _tested(df, tried, cfg, own, all_)
        finally:
            all_.unpersist()
        for key, got in found.items():
            if got[3] < out[key][3] or out[key][1] is None:
                out[key] = (out[key][0] and got[0], *got[1:])
        left = [r for r in left if out[r.cand_id][0]]
    return out


def _tested(df: DataFrame, rels: Sequence[Relation], cfg: Config, own: dict[str, Sequence[str]], all_: DataFrame) -> dict[str, tuple]:
    tested = chi2(df, rels, cfg, own, all_).withColumn("p", tail("chi2", "df"))
    if cfg.min_expected > 0:
        tested = tested.withColumn("p", F.when(F.col("least") >= cfg.min_expected, F.col("p")).otherwise(F.lit(1.0)))
    if cfg.min_effect > 0:  # for two outcomes Cramer's V is sqrt(chi2 / n)
        tested = tested.withColumn("p", F.when(F.sqrt(F.col("chi2") / F.col("n_rows")) >= cfg.min_effect, F.col("p")).otherwise(F.lit(1.0)))
    rank = F.row_number().over(Window.partitionBy("cand_id").orderBy("p", "col"))  # as many rows as a rule has columns
    m = F.count("*").over(Window.partitionBy("cand_id"))
    limit = {"none": F.lit(cfg.alpha), "bonferroni": F.lit(cfg.alpha) / m, "benjamini_hochberg": F.lit(cfg.alpha) * rank / m}[cfg.multiplicity]
    judged = tested.withColumn("out", F.col("p") <= limit)
    worst = judged.groupBy("cand_id").agg(F.min(F.struct("p", "col", "chi2")).alias("w"), F.bool_or("out").alias("out")).collect()
    return {r["cand_id"]: (not r["out"], r["w"]["col"], r["w"]["chi2"], r["w"]["p"]) for r in worst}
