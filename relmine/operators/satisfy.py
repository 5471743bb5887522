"""Whether rows satisfy rules: satisfaction ratios, violations, expected values.

Defined cases: a table without rows has 0 hits in 0 rows; repeated rows count as
often as they stand; columns may bear any name, helper columns never stand beside
them (only ``with_holds`` adds a column, whose name must be free). Nulls, overflow
and division by zero: see ``holds``. In a value dependency null is a value like others.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relmine.functions.expressions import divides, evaluate, signed_sum
from relmine.model import Config, Relation

_EXACT = ("tinyint", "smallint", "int", "bigint", "string", "boolean", "date")


def holds(rel: Relation, column: Callable[[str], Column] = F.col, exact: bool = True, cfg: Config | None = None) -> Column:
    """True or false for each row, null where the row does not count.

    A row with one side null violates; one with all participating cells null is
    left out, violates or matches, as ``null_policy`` says. Division by zero and a
    result that its type cannot hold are null.
    """
    cfg = cfg or Config()
    if rel.kind == "FD":
        raise ValueError("a value dependency needs its map; see dependency_map")
    made, out = evaluate(rel.expr, column), column(rel.output)
    if rel.kind == "ST":
        same = made == out.cast("string")
    elif exact and not divides(rel.expr):
        same = made == out
    else:
        a, b = made.cast("double"), out.cast("double")
        same = F.abs(a - b) <= cfg.atol + cfg.rtol * F.abs(b)
    none = F.lit(True)
    for c in rel.columns:
        none = none & column(c).isNull()
    all_null = {"exclude_all_null": F.lit(None).cast("boolean"), "violate": F.lit(False), "match": F.lit(True)}[cfg.null_policy]
    return F.when(none, all_null).otherwise(F.coalesce(same, F.lit(False)))


def exact_columns(df: DataFrame, rel: Relation) -> bool:
    kinds = dict(df.dtypes)
    return all(kinds[c] in _EXACT or kinds[c].startswith("decimal") for c in rel.columns)


def sum_signs(df: DataFrame, rel: Relation) -> dict[str, int] | None:
    """Signs of a sum or difference of longs, brought to one side; None for other rules. On rows that satisfy it, all
    columns but one determine that one."""
    signs, kinds = signed_sum(rel.expr) if rel.kind == "AR" else None, dict(df.dtypes)
    if signs is None or len(signs) < rel.arity or any(kinds[c] != "bigint" for c in rel.columns):
        return None
    return signs | {rel.output: -1}


def same_rows(df: DataFrame, rels: Sequence[Relation]) -> dict[str, tuple | str]:
    """A key by cand_id: rules with one key are satisfied by the same rows, being one sum solved for different columns.

    Where a part of a longer sum might overflow, which depends on its order, a rule is alone.
    """
    signs = {r.cand_id: sum_signs(df, r) for r in rels}
    long = sorted({c for r in rels if r.arity > 2 and signs[r.cand_id] for c in r.columns})
    one = df.agg(*(f(c).alias(f"{n}{i}") for i, c in enumerate(long) for n, f in (("a", F.min), ("b", F.max)))).first() if long else None
    most = {c: max(abs(one[f"a{i}"] or 0), abs(one[f"b{i}"] or 0)) for i, c in enumerate(long)}
    out: dict[str, tuple | str] = {}
    for r in rels:
        by = signs[r.cand_id]
        if by is None or r.arity > 2 and sum(most[c] for c in r.columns) >= 2**63:
            out[r.cand_id] = r.cand_id
        else:
            out[r.cand_id] = tuple((c, by[c] * by[min(by)]) for c in sorted(by))
    return out


def cell_text(column: Column) -> Column:
    """A cell of a value dependency as text; null is a value of its own, and no text is taken for it."""
    return F.when(column.isNull(), "n").otherwise(F.concat(F.lit("v"), column.cast("string")))


def input_text(cells: Sequence[Column]) -> Column:
    """Several cells as one text that no delimiter inside a cell can make equal to another."""
    return cell_text(cells[0]) if len(cells) == 1 else F.to_json(F.array(*map(cell_text, cells)))


def dependency_counts(df: DataFrame, rels: Sequence[Relation]) -> DataFrame:
    """(cand_id, x, y, n) of value dependencies, inputs and output as text: one pass for all."""
    rows = F.array(*(F.struct(F.lit(r.cand_id).alias("cand_id"), input_text([F.col(c) for c in r.inputs]).alias("x"), cell_text(F.col(r.output)).alias("y")) for r in rels))
    return df.select(F.inline(rows)).groupBy("cand_id", "x", "y").agg(F.count("*").alias("n"))


def dependency_maps(counts: DataFrame) -> DataFrame:
    """(cand_id, x, y, n_y, n): each input's most frequent output, ties to the smallest text."""
    best = F.min(F.struct((-F.col("n")).alias("m"), "y")).alias("b")
    return counts.groupBy("cand_id", "x").agg(best, F.sum("n").alias("n")).select("cand_id", "x", F.col("b.y").alias("y"), (-F.col("b.m")).alias("n_y"), "n")


def dependency_map(df: DataFrame, rel: Relation) -> DataFrame:
    """(x, y, n_y, n) of one value dependency."""
    return dependency_maps(dependency_counts(df, [rel])).drop("cand_id")


def _flagged(df: DataFrame, rel: Relation) -> DataFrame:
    """(cells, ok): the rows as structs with a value dependency's verdict; it holds where y is the most frequent of its x."""
    best = dependency_map(df, rel).select("x", F.col("y").alias("usual"))
    own = df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("cells"), input_text([F.col(c) for c in rel.inputs]).alias("x"), cell_text(F.col(rel.output)).alias("y"))
    return own.join(best, "x").select("cells", (F.col("y") == F.col("usual")).alias("ok"))


def with_holds(df: DataFrame, rel: Relation, cfg: Config | None = None, name: str = "holds") -> DataFrame:
    """``df`` with the rule's verdict on each row as the column ``name``, which must be free."""
    if name in df.columns:
        raise ValueError(f"the table has a column {name}")
    if rel.kind != "FD":
        return df.withColumn(name, holds(rel, exact=exact_columns(df, rel), cfg=cfg))
    return _flagged(df, rel).select("cells.*", F.col("ok").alias(name))


def satisfaction(df: DataFrame, rels: Sequence[Relation], cfg: Config | None = None, maps: DataFrame | None = None) -> DataFrame:
    """(cand_id, kind, rule, hits, n_rows) of each rule: one scan for a batch of rules, one pass for all dependencies,
    for which ``maps`` may be given."""
    cfg = cfg or Config()
    spark, rows = df.sparkSession, []
    plain = [r for r in rels if r.kind != "FD"]
    for at in range(0, len(plain), cfg.batch_rules):
        part = plain[at:at + cfg.batch_rules]
        sums = []
        for i, r in enumerate(part):
            h = holds(r, exact=exact_columns(df, r), cfg=cfg)
            sums += [F.count_if(h).alias(f"h{i}"), F.count(h).alias(f"n{i}")]
        got = df.agg(*sums).first()
        rows += [(r.cand_id, r.kind, r.text, got[f"h{i}"], got[f"n{i}"]) for i, r in enumerate(part)]
    fds = [r for r in rels if r.kind == "FD"]
    if fds:
        maps = dependency_maps(dependency_counts(df, fds)) if maps is None else maps
        by = {r["cand_id"]: r for r in maps.groupBy("cand_id").agg(F.sum("n_y").alias("h"), F.sum("n").alias("n")).collect()}
        rows += [(r.cand_id, r.kind, r.text, *((by[r.cand_id]["h"], by[r.cand_id]["n"]) if r.cand_id in by else (0, 0))) for r in fds]
    return spark.createDataFrame(rows, "cand_id string, kind string, rule string, hits bigint, n_rows bigint")


def is_accurate(hits: int, rows: int, tau: float) -> bool:
    """hits / rows >= tau in whole numbers."""
    return hits >= math.ceil(Fraction(str(tau)) * rows)


def accurate(ratios: DataFrame, tau: float) -> DataFrame:
    """The rows of ``satisfaction`` with hits / n_rows >= tau, in whole numbers."""
    part = Fraction(str(tau))
    return ratios.where(F.col("hits").cast("decimal(38,0)") * part.denominator >= F.col("n_rows").cast("decimal(38,0)") * part.numerator)


def _rows(df: DataFrame, rel: Relation, cfg: Config | None, wanted: bool) -> DataFrame:
    if rel.kind == "FD":
        return _flagged(df, rel).where(F.col("ok") == wanted).select("cells.*")
    return df.where(holds(rel, exact=exact_columns(df, rel), cfg=cfg) == F.lit(wanted))


def violations(df: DataFrame, rel: Relation, cfg: Config | None = None) -> DataFrame:
    """The rows that violate the rule."""
    return _rows(df, rel, cfg, False)


def satisfied(df: DataFrame, rel: Relation, cfg: Config | None = None) -> DataFrame:
    return _rows(df, rel, cfg, True)


def expected_values(df: DataFrame, rel: Relation, keep: Sequence[str] = ()) -> DataFrame:
    """Repair aid: violating rows with what the rule expects of the output cell."""
    return violations(df, rel).select(*keep, *rel.columns, evaluate(rel.expr).alias("expected"))


def stable_exactly(df: DataFrame, rel: Relation) -> bool:
    """Whether some observed inputs and some observed output contradict the rule; two distincts, no cross join.

    A contradiction exists unless every observed output equals every computed one.
    """
    outputs = df.select(F.col(rel.output).alias("v")).distinct()
    if outputs.limit(2).count() > 1:
        return True
    made = df.select(evaluate(rel.expr).alias("v")).distinct()
    return made.join(outputs, made.v.eqNullSafe(outputs.v), "left_anti").limit(1).count() > 0


def ranked(rows: DataFrame, order: Sequence[Column], name: str = "rank") -> DataFrame:
    """Number the rows of a frame of bounded size."""
    return rows.withColumn(name, F.row_number().over(Window.orderBy(*order)))
