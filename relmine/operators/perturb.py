"""The Perturbation Test: how often a rule survives an exchange of observed cells.

A trial is two different rows and a set of the rule's columns whose cells the
rows exchange; the rule survives if both altered rows satisfy it. In the clean
setting one bank of row pairs, drawn in one scan, serves all rules; in the dirty
setting one scan draws a bank of each rule's satisfied rows. Rows are drawn by a
hash of their content, so the draw is the same on any number of executors; only
rows that repeat are told apart by where they were read.

Defined cases: a table, or satisfied rows, of fewer than two rows gives no trial;
rows that are equal in all cells are different rows; columns may bear any name, for
cells travel in structs; nulls as in ``satisfy``.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from statistics import NormalDist

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relmine.functions.statistics import hash_int, wilson_bounds
from relmine.model import Config, Relation
from relmine.operators.bounds import Known, core_checks
from relmine.operators.satisfy import cell_text, dependency_counts, dependency_maps, exact_columns, holds, input_text, satisfaction

OUTCOME = "cand_id string, trial bigint, mask bigint, survived int"


def _content(columns: Sequence[str]) -> Column:
    return F.concat_ws("|", *(F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in sorted(columns)))


def _drawn(df: DataFrame, columns: Sequence[str], n: int, seed: int, held: bool = False) -> tuple[DataFrame, int] | None:
    """(round, place, cells) of about 2n rows, and half of a round's rows; None of a table of fewer than two.

    ``held`` rows are persisted; then rows of small hashes are picked before a task puts rows in order, unless these are too few.
    """
    text = _content(df.columns)
    rows, different = df.agg(F.count("*"), F.approx_count_distinct(F.xxhash64(text), 0.02)).first()
    if rows < 2:
        return None
    cells = F.struct(*(F.col(c) for c in sorted(set(columns))))
    rounds, half = max(1, -(-2 * n // rows)), min(rows, 2 * n) // 2
    tie = F.monotonically_increasing_id().cast("string") if rows > 1.1 * different else F.lit("")
    many = df.select(cells.alias("cells"), text.alias("t"), tie.alias("i")).withColumn("round", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))) if rounds > 1 else F.lit(0))
    keyed = many.withColumn("k", F.md5(F.concat_ws("|", "t", "i", "round", F.lit(str(seed)))))
    place = F.row_number().over(Window.partitionBy("round").orderBy("k", "cells")) - 1  # at most 2n + rows in all
    placed = lambda some: some.select("round", place.alias("place"), "cells").where(F.col("place") < 2 * half)
    first = lambda some: some if rounds > 1 else some.orderBy("k", "cells").limit(2 * half)
    if not held:
        return placed(first(keyed)), half
    if (share := 2 * (2 * half + 200) / rows) < 0.5:
        near = placed(first(keyed.where(F.col("k") < f"{int(share * 16**12):012x}"))).persist()
        if near.count() == 2 * half:
            return near, half
        near.unpersist()
    return placed(first(keyed)).persist(), half


def _paired(placed: DataFrame, half, keys: Sequence[str], cell: str = "cells") -> DataFrame:
    """(keys, trial, a, b): the first half of each round's rows meets the second."""
    trial, second = (F.col("round") * half + F.col("place") % half).cast("bigint"), F.col("place") >= half
    side = lambda which: F.max(F.when(second == F.lit(which), F.col(cell)))
    return placed.groupBy(*keys, trial.alias("trial")).agg(side(False).alias("a"), side(True).alias("b"))


def trial_bank(df: DataFrame, columns: Sequence[str], n: int, seed: int = 42, known: Known | None = None) -> DataFrame:
    """(trial, a, b): about ``n`` pairs of different rows.

    The rows with the smallest hashes of all cells are drawn, a top-k per task
    without a global sort, and the first half meets the second. A table of fewer
    than 2n rows is drawn again with other hashes. Where many rows are equal in
    all cells, their hashes also take in where the row was read. ``known`` keeps the
    rows, which are the same for any columns, for the levels to come.
    """
    drawn = _drawn(df, columns, n, seed) if known is None else known.once(("drawn", n, seed), lambda: _drawn(df, df.columns, n, seed, True))
    if drawn is not None and known is not None:
        own = F.struct(*(F.col("cells")[c].alias(c) for c in sorted(set(columns))))
        drawn = drawn[0].select("round", "place", own.alias("cells")), drawn[1]
    if drawn is None:
        cells = F.struct(*(F.col(c) for c in sorted(set(columns))))
        return df.select(F.lit(0).cast("bigint").alias("trial"), cells.alias("a"), cells.alias("b")).limit(0)
    return _paired(*drawn, [])


def rule_banks(df: DataFrame, rels: Sequence[Relation], cfg: Config, hits: dict[str, int], spare: float = 1.3) -> DataFrame:
    """(cand_id, trial, a, b): about ``n_max`` pairs of each rule's satisfied rows, of which there are ``hits``.

    One scan for all rules. A row is drawn where its hash is below a share that makes a little more than 2n rows of the
    rule likely, and of those the smallest 2n are taken; rules of fewer rows are drawn in several rounds.
    """
    n, cells = cfg.n_max, F.struct(*(F.col(c) for c in sorted({c for r in rels for c in r.columns})))
    items, most = [], 0
    for r in rels:
        h = hits[r.cand_id]
        rounds = max(1, -(-2 * n // h)) if h > 1 else 0
        below = int(min(1.0, spare * (2 * n + 200) / h) * 2**60) if rounds == 1 else 2**60
        most = max(most, below if rounds else 0)
        items.append(F.struct(F.lit(r.cand_id).alias("cand_id"), F.lit(rounds).alias("rounds"), F.lit(max(1, min(h, 2 * n) // 2)).alias("half"), F.lit(below).alias("below"),
                              F.coalesce(holds(r, exact=exact_columns(df, r), cfg=cfg), F.lit(False)).alias("ok")))
    text = F.xxhash64(_content(df.columns), F.lit(cfg.seed))
    # what no rule draws goes before a row is taken apart by rules
    each = df.where(F.pmod(text, F.lit(2**60)) < most).select(cells.alias("cells"), text.alias("t"), F.monotonically_increasing_id().alias("i"), F.inline(F.array(*items)))
    many = each.where(F.col("ok") & (F.col("rounds") > 0) & (F.pmod("t", F.lit(2**60)) < F.col("below"))).select("cand_id", "half", "cells", "t", "i", F.explode(F.sequence(F.lit(0), F.col("rounds") - 1)).alias("round"))
    # rows that are equal in all cells are told apart by where they were read
    place = F.row_number().over(Window.partitionBy("cand_id", "round").orderBy(F.xxhash64("t", "round"), "cells", "i")) - 1
    placed = many.withColumn("place", place).where(F.col("place") < 2 * F.col("half"))
    return _paired(placed, F.col("half"), ["cand_id", "half"]).drop("half")


def mask_of(rel: Relation, trial: Column, space: str) -> Column:
    """A set of the rule's columns as bits, inputs first, from a hash of rule and trial."""
    size = (1 << len(rel.columns)) - (1 if space == "nonempty" else 2)
    return hash_int(F.lit(rel.cand_id), trial) % size + 1


def exchanged(rel: Relation, mask: Column, own: str, other: str):
    """Reads a cell of a row after the exchange."""
    place = {c: i for i, c in enumerate(rel.columns)}
    return lambda c: F.when(F.getbit(mask, F.lit(place[c])) == 1, F.col(f"{other}.{c}")).otherwise(F.col(f"{own}.{c}"))


def _outcome(rel: Relation, cfg: Config, exact: bool) -> tuple[Column, Column]:
    """(mask, survived) of an arithmetic or string rule on a row of a bank."""
    mask = mask_of(rel, F.col("trial"), cfg.subset_space)
    ok = holds(rel, exchanged(rel, mask, "a", "b"), exact, cfg) & holds(rel, exchanged(rel, mask, "b", "a"), exact, cfg)
    if cfg.use_core and rel.kind == "AR" and exact:
        known = F.lit(None).cast("boolean")  # what the core decides alone
        for m, (same, sure) in core_checks(rel, rel.columns, cfg.core_check == "guarded").items():
            known = F.when(mask == m, F.coalesce(same, F.lit(False)) if sure else F.when(same, F.lit(True))).otherwise(known)
        ok = F.coalesce(known, ok)
    return mask, F.coalesce(ok, F.lit(False)).cast("int")


def outcomes(bank: DataFrame, rel: Relation, cfg: Config, exact: bool = True, df: DataFrame | None = None) -> DataFrame:
    """(cand_id, trial, mask, survived) of one rule over the bank; ``df`` is needed for value dependencies."""
    if rel.kind == "FD":
        ok, base = _dependency(bank.withColumn("mask", mask_of(rel, F.col("trial"), cfg.subset_space)), rel, cfg, df)
        mask, survived = F.col("mask"), F.coalesce(ok, F.lit(False)).cast("int")
    else:
        base, (mask, survived) = bank, _outcome(rel, cfg, exact)
    return base.select(F.lit(rel.cand_id).alias("cand_id"), "trial", mask.alias("mask"), survived.alias("survived"))


def all_outcomes(bank: DataFrame, rels: Sequence[Relation], cfg: Config, exact: Sequence[bool], batch: int = 3) -> list[DataFrame]:
    """(cand_id, trial, mask, survived) of arithmetic and string rules over a shared bank, or over one with a cand_id."""
    parts, own = [], "cand_id" in bank.columns
    for at in range(0, len(rels), batch):
        rows = []
        for r, e in zip(rels[at:at + batch], exact[at:at + batch]):
            mask, survived = _outcome(r, cfg, e)
            row = F.struct(F.lit(r.cand_id).alias("cand_id"), "trial", mask.alias("mask"), survived.alias("survived"))
            rows.append(F.when(F.col("cand_id") == r.cand_id, row) if own else row)
        every = F.filter(F.array(*rows), lambda x: x.isNotNull()) if own else F.array(*rows)
        parts.append(bank.select(F.inline(every)))
    return parts


def _survives(mode: str, ax: str, ay: str, a_usual: str, a_n: str, bx: str, by: str, b_usual: str, b_n: str) -> Column:
    """Whether both rows go with the observed map after x or y was exchanged; exchanged whole, rows change places."""
    moved_a, moved_b = F.col(b_usual).eqNullSafe(F.col(ay)), F.col(a_usual).eqNullSafe(F.col(by))
    if mode == "recheck":  # an input that no other row holds contradicts nothing
        other = F.col(ax) != F.col(bx)
        moved_a, moved_b = moved_a | ((F.col(b_n) == 1) & other), moved_b | ((F.col(a_n) == 1) & other)
    return F.when(F.col("mask") == 3, F.lit(True)).otherwise(moved_a & moved_b)


def _dependency(base: DataFrame, rel: Relation, cfg: Config, df: DataFrame) -> tuple[Column, DataFrame]:
    """The observed map is joined to a bank of one value dependency."""
    if rel.arity != 1:
        raise ValueError("value dependencies have one input")
    x, y = rel.inputs[0], rel.output
    known = dependency_maps(dependency_counts(df, [rel]))
    for side in ("a", "b"):
        base = base.withColumns({f"{side}x": input_text([F.col(side)[x]]), f"{side}y": cell_text(F.col(side)[y])})
        base = base.join(known.select(F.col("x").alias(f"{side}x"), F.col("y").alias(f"{side}_usual"), F.col("n").alias(f"{side}_n")), f"{side}x", "left")
    return _survives(cfg.fd_mode, "ax", "ay", "a_usual", "a_n", "bx", "by", "b_usual", "b_n"), base


def dependency_outcomes(df: DataFrame, rels: Sequence[Relation], cfg: Config, maps: DataFrame, hits: dict[str, tuple[int, int]]) -> DataFrame | None:
    """(cand_id, trial, mask, survived) of all value dependencies over rows of one draw; in the dirty setting rows that
    violate a rule are left out of its trials, for which more rows are drawn."""
    only_ok = cfg.setting == "dirty" and cfg.row_pool == "satisfied"
    least = min((h / n for h, n in (hits[r.cand_id] for r in rels) if h), default=1.0) if only_ok else 1.0
    drawn = _drawn(df, sorted({c for r in rels for c in r.columns}), int(cfg.n_max / max(least, 0.01) * (1.1 if only_ok else 1)), cfg.seed)
    if drawn is None:
        return None
    rows, half = drawn
    cells = F.array(*(F.struct(F.lit(r.cand_id).alias("cand_id"), input_text([F.col("cells")[r.inputs[0]]]).alias("x"), cell_text(F.col("cells")[r.output]).alias("y")) for r in rels))
    each = rows.select("round", "place", F.inline(cells)).join(maps.select("cand_id", "x", F.col("y").alias("usual"), "n"), ["cand_id", "x"])
    each = each.withColumn("half", F.lit(half))
    if only_ok:
        by = Window.partitionBy("cand_id", "round")  # rows of one draw, a bounded number
        each = each.where("y = usual").withColumn("place", F.row_number().over(by.orderBy("place")) - 1).withColumn("half", F.floor(F.count("*").over(by) / 2).cast("int"))
        each = each.where(F.col("place") < 2 * F.col("half"))
    row, second = F.struct("x", "y", "usual", "n"), F.col("place") >= F.col("half")
    pairs = each.groupBy("cand_id", "round", (F.col("place") % F.col("half")).alias("at")).agg(F.max(F.when(~second, row)).alias("a"), F.max(F.when(second, row)).alias("b"))
    if only_ok:
        trial = F.row_number().over(Window.partitionBy("cand_id").orderBy("round", "at")) - 1
        pairs = pairs.withColumn("trial", trial.cast("bigint")).where(F.col("trial") < cfg.n_max)
    else:
        pairs = pairs.withColumn("trial", (F.col("round") * half + F.col("at")).cast("bigint")).where("a is not null and b is not null")
    size = 3 if cfg.subset_space == "nonempty" else 2
    pairs = pairs.withColumn("mask", hash_int(F.col("cand_id"), F.col("trial")) % size + 1)
    ok = _survives(cfg.fd_mode, "a.x", "a.y", "a.usual", "a.n", "b.x", "b.y", "b.usual", "b.n")
    return pairs.select("cand_id", "trial", "mask", F.coalesce(ok, F.lit(False)).cast("int").alias("survived"))


def stop_z(cfg: Config) -> float:
    """The quantile of each look at the interval: as published that of one look, or the error spread over all of them."""
    if cfg.looks == "single":
        return cfg.z
    normal = NormalDist()
    return normal.inv_cdf(1 - (1 - normal.cdf(cfg.z)) / max(1, -(-cfg.n_max // cfg.beta)))


def blocks(trials: DataFrame, cfg: Config) -> DataFrame:
    """(cand_id, block, n, s, low, high): trials and survivors up to and with each block, and their Wilson interval."""
    per = trials.groupBy("cand_id", F.floor(F.col("trial") / cfg.beta).alias("block")).agg(F.count("*").alias("k"), F.sum("survived").alias("t"))
    upto = Window.partitionBy("cand_id").orderBy("block").rowsBetween(Window.unboundedPreceding, 0)
    run = per.select("cand_id", "block", F.sum("k").over(upto).alias("n"), F.sum("t").over(upto).alias("s"))
    low, high = wilson_bounds(F.col("n"), F.col("s"), stop_z(cfg))
    return run.withColumn("low", low).withColumn("high", high)


def first_stop(trials: DataFrame, cfg: Config) -> DataFrame:
    """(cand_id, trials, survived, score, stop_reason): at the first block whose interval leaves eta, else at the last."""
    run = blocks(trials, cfg)
    off = (F.col("low") > cfg.eta) | (F.col("high") < cfg.eta)
    at = F.min(F.when(off, F.struct("block", "n", "s"))) if cfg.use_wilson else F.lit(None).cast("struct<block:bigint,n:bigint,s:bigint>")
    both = run.groupBy("cand_id").agg(at.alias("stop"), F.max(F.struct("block", "n", "s")).alias("last"))
    end = F.coalesce("stop", "last")
    return both.select("cand_id", end["n"].alias("trials"), end["s"].alias("survived"), (end["s"] / end["n"]).alias("score"), F.when(F.col("stop").isNotNull(), "wilson").otherwise("exhausted").alias("stop_reason"))


SCORE = "cand_id string, trials bigint, survived bigint, score double, stop_reason string"


def score(df: DataFrame, rels: Sequence[Relation], cfg: Config, hits: dict[str, tuple[int, int]] | None = None, maps: DataFrame | None = None, known: Known | None = None) -> DataFrame:
    """Sampled scores of rules, a row each; a rule without trials has none.

    Clean tables share one bank; in the dirty setting a rule's pool is its satisfied rows. The number of passes over the
    table does not depend on the number of rules. ``hits`` (hits and rows by cand_id), ``maps`` and ``known``
    (what other levels have read) may be given.
    """
    spark = df.sparkSession
    if not rels:
        return spark.createDataFrame([], SCORE)
    if hits is None:
        hits = {r["cand_id"]: (r["hits"], r["n_rows"]) for r in satisfaction(df, rels, cfg, maps).collect()}
    plain, fds = [r for r in rels if r.kind != "FD"], [r for r in rels if r.kind == "FD"]
    parts, held = [], []
    if plain:
        if cfg.setting == "clean" or cfg.row_pool == "all":
            bank = trial_bank(df, {c for r in plain for c in r.columns}, cfg.n_max, cfg.seed, known).persist()
        else:
            bank = rule_banks(df, plain, cfg, {k: h for k, (h, _) in hits.items()}).persist()
        held.append(bank)  # at most n_max rows, of each rule in the dirty setting
        parts += all_outcomes(bank, plain, cfg, [exact_columns(df, r) for r in plain])
    if fds:
        known = maps if maps is not None else dependency_maps(dependency_counts(df, fds))
        if (more := dependency_outcomes(df, fds, cfg, known, hits)) is not None:
            parts.append(more)
    if not parts:
        return spark.createDataFrame([], SCORE)
    tried = reduce(DataFrame.unionByName, parts).persist()
    held.append(tried)
    try:
        return spark.createDataFrame(_one_shot(tried, cfg) if cfg.mode == "one_shot" else _staged(tried, [r.cand_id for r in rels], cfg), SCORE)
    finally:
        for x in held:
            x.unpersist()


def _one_shot(tried: DataFrame, cfg: Config) -> list:
    return first_stop(tried, cfg).collect()


def _staged(tried: DataFrame, left: list[str], cfg: Config) -> list:
    """Rounds of beta * 4^k trials; decided rules leave between the rounds."""
    done, upto = [], cfg.beta
    while left:
        last = upto >= cfg.n_max
        got = first_stop(tried.where((F.col("trial") < upto) & F.col("cand_id").isin(left)), cfg).where("true" if last else "stop_reason = 'wilson'").collect()
        done += got
        left = [] if last else [k for k in left if k not in {r["cand_id"] for r in got}]
        upto *= 4
    return done


def exact_score(df: DataFrame, rel: Relation, cfg: Config, limit: int = 400) -> DataFrame:
    """(trials, survived, score) over all row pairs and column sets, the reference for small tables."""
    if df.count() > limit:
        raise ValueError(f"enumeration is for at most {limit} rows; use score()")
    rows = df.select(F.struct(*(F.col(c) for c in rel.columns)).alias("r")).withColumn("i", F.row_number().over(Window.orderBy("r")))
    pairs = rows.select(F.col("r").alias("a"), F.col("i").alias("ia")).join(rows.select(F.col("r").alias("b"), F.col("i").alias("ib")), F.col("ia") < F.col("ib"))
    last = (1 << len(rel.columns)) - (1 if cfg.subset_space == "nonempty" else 2)
    each = pairs.withColumn("mask", F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit(last).cast("bigint"))))
    if rel.kind == "FD":
        ok, each = _dependency(each, rel, cfg, df)
    else:
        exact = exact_columns(df, rel)
        ok = holds(rel, exchanged(rel, F.col("mask"), "a", "b"), exact, cfg) & holds(rel, exchanged(rel, F.col("mask"), "b", "a"), exact, cfg)
    return each.agg(F.count("*").alias("trials"), F.count_if(ok).alias("survived")).withColumn("score", F.col("survived") / F.col("trials"))
