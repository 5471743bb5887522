"""The whole loop: generate, prune, test independence and stability, level by level."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmine.model import VERDICT, Config, Relation
from relmine.operators import generate
from relmine.operators.bounds import Known, bounds
from relmine.operators.independence import independent
from relmine.operators.minimality import is_minimal
from relmine.operators.perturb import score
from relmine.operators.satisfy import dependency_counts, dependency_maps, satisfaction


def judge(df: DataFrame, rels: Sequence[Relation], cfg: Config, pruners: list[Relation], known: Known | None = None) -> list[tuple]:
    """Verdicts of one level's candidates; those that pass the first two tests join ``pruners`` before they are perturbed.

    The number of jobs does not depend on the number of candidates, but for batches of ``batch_rules`` and the value
    dependencies of the Independence Test. ``known`` carries over from level to level what bounds found of the table.
    """
    if not rels:
        return []
    fds = [r for r in rels if r.kind == "FD"]
    maps = dependency_maps(dependency_counts(df, fds)).persist() if fds else None
    try:
        hits = {r["cand_id"]: (r["hits"], r["n_rows"]) for r in satisfaction(df, rels, cfg, maps).collect()}
        minimal = {r.cand_id: not cfg.use_minimality or is_minimal(r, pruners) for r in rels}
        left = [r for r in rels if minimal[r.cand_id]]
        complete = {k for k, (h, n) in hits.items() if h == n}
        tested = {}
        if cfg.setting == "dirty" and cfg.use_independence and cfg.dirty_mode == "independence":  # a rule without violations passes
            open_ = [r for r in left if r.cand_id not in complete]
            tested = {r.cand_id: (True, None, None, 1.0) for r in left} | (independent(df, open_, cfg) if open_ else {})
        left = [r for r in left if tested.get(r.cand_id, (True,))[0]]
        pruners += left
        bound = bounds(df, left, cfg, maps, complete, known) if cfg.use_bound and left else {}
        open_ = [r for r in left if bound.get(r.cand_id, 0.0) <= cfg.eta]
        scored = {r["cand_id"]: r for r in score(df, open_, cfg, hits, maps, known).collect()} if open_ else {}
    finally:
        if maps is not None:
            maps.unpersist()
    return [_verdict(r, hits[r.cand_id], minimal[r.cand_id], tested.get(r.cand_id), bound.get(r.cand_id), scored.get(r.cand_id), cfg) for r in rels]


def _verdict(r: Relation, hits: tuple[int, int], minimal: bool, tested: tuple | None, bound: float | None, scored, cfg: Config) -> tuple:
    passed = minimal and (tested is None or tested[0])
    value, reason, trials, survived = None, "minimality" if not minimal else "independence", 0, 0
    if scored:
        value, reason, trials, survived = scored["score"], scored["stop_reason"], scored["trials"], scored["survived"]
    elif passed and bound is not None and bound > cfg.eta:
        value, reason = bound, "bound"
    elif passed:
        reason = "no rows"
    it = tested or (None, None, None, None)
    return (r.cand_id, r.kind, list(r.inputs), r.output, r.arity, r.text, *hits, minimal, *it, bound, trials, survived, value, reason, bool(scored is not None and value <= cfg.eta))


def candidates(df: DataFrame, level: int, cfg: Config, kinds: Sequence[str], pruners: Sequence[Relation], categories: Sequence[str], known: Known | None = None) -> list[Relation]:
    found: list[Relation] = []
    if "AR" in kinds and level == 1:
        found += generate.constants(df, cfg, pruners, known=known)
    if "AR" in kinds and level >= 2:
        found += generate.arithmetic(df, level, cfg, pruners, known=known)
    if "ST" in kinds and level == 1:
        found += generate.extractions(df, cfg, pruners)
    if "ST" in kinds and level == 2:
        found += generate.concatenations(df, cfg, pruners)
    if "ST" in kinds and level <= 3:
        known = {r.cand_id for r in found}
        found += [r for r in generate.programs(df, level, cfg, pruners) if r.cand_id not in known]
    if "FD" in kinds and level == 1 and len(categories) > 1:
        found += generate.dependencies(df, categories, cfg, pruners)
    return found


def discover(df: DataFrame, cfg: Config | None = None, kinds: Sequence[str] = ("AR", "ST", "FD"), categories: Sequence[str] | None = None) -> DataFrame:
    """Verdicts of all rules found in ``df``; a level without candidates is passed over.

    ``categories`` are the columns of value dependencies, by default text columns that are no keys.
    """
    cfg = cfg or Config()
    if categories is None:
        categories = [r["col"] for r in generate.profile(df, generate.text_columns(df, cfg)).where("not constant and not key_like").collect()] if "FD" in kinds else []
    pruners: list[Relation] = []
    rows: list[tuple] = []
    known = Known()
    try:
        for level in range(1, cfg.max_level + 1):
            rows += judge(df, candidates(df, level, cfg, kinds, pruners, categories, known), cfg, pruners, known)
    finally:
        known.close()
    return df.sparkSession.createDataFrame(rows, VERDICT)


def verify(df: DataFrame, pool: Sequence[Relation], cfg: Config | None = None) -> DataFrame:
    """Verdicts of a given pool, smaller rules first."""
    cfg = cfg or Config()
    pruners: list[Relation] = []
    rows: list[tuple] = []
    known = Known()
    try:
        for level in sorted({r.arity for r in pool}):
            rows += judge(df, [r for r in pool if r.arity == level], cfg, pruners, known)
    finally:
        known.close()
    return df.sparkSession.createDataFrame(rows, VERDICT)


def reliability(verdicts: DataFrame) -> DataFrame:
    """(cand_id, reliability): one minus the score; rules that another test rejects have 0."""
    passed = F.col("mt_pass") & F.coalesce("it_pass", F.lit(True))
    return verdicts.select("cand_id", F.when(passed, 1 - F.coalesce("score", F.lit(1.0))).otherwise(F.lit(0.0)).alias("reliability"))


def collapse_isomerous(verdicts: DataFrame) -> DataFrame:
    """One reliable rule for each set of columns: fewest divisions and subtractions, then the lowest score."""
    cost = F.length("rule") - F.length(F.translate("rule", "/-", ""))
    key = F.array_sort(F.array_append("inputs", F.col("output")))
    best = verdicts.where("reliable").withColumn("key", key).groupBy("key").agg(F.min(F.struct(cost.alias("c"), "score", "rule", "cand_id")).alias("b"))
    return best.select(F.col("key").alias("columns"), F.col("b.cand_id").alias("cand_id"), F.col("b.rule").alias("rule"), F.col("b.score").alias("score"))
