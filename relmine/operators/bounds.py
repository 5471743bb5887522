"""Collision probabilities and the bounds and closed scores made of them.

kappa(S) is the chance that two different rows agree on the columns S. The mean
of kappa over the exchanged column sets bounds the survival score from below.

Defined cases: null is a value; a table of one row has kappa 1, one without rows 0;
repeated rows are different rows that agree; columns may bear any name.
"""

from __future__ import annotations

from collections.abc import Callable, Collection, Iterable, Sequence
from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relmine.functions.expressions import absorbed_above, evaluate, leaves, subtrees
from relmine.model import Config, Relation


def column_sets(columns: Sequence[str]) -> list[frozenset[str]]:
    """All non-empty subsets."""
    return [frozenset(s) for n in range(1, len(columns) + 1) for s in combinations(columns, n)]


def kappas_of(df: DataFrame, items: Sequence[tuple[Sequence[str], Column | None]], batch: int = 64) -> list[float]:
    """kappa of each (columns, rows that count), a pass for each ``batch`` of them, counts combined before the shuffle.

    Rows that are equal in all columns that matter are one row with a count first. It gives a 64-bit hash for each item;
    two different cells have equal hashes with a chance of 2 ** -64, which is all that a hash can add to a kappa. Sums are
    decimals: a group of a third of 10^13 rows would overflow a long. A condition may read any column of ``df``.
    """
    out = [0.0] * len(items)
    if not items:
        return out
    columns = df.columns if any(only is not None for _, only in items) else sorted({c for own, _ in items for c in own})
    if len(items) > 1:
        df, rows = _counted(df, columns)
        if len(items) > batch:  # read once for each batch
            df = df.persist()
    else:
        rows = F.lit(1).cast("bigint")
    for at in range(0, len(items), batch):
        by: dict[int, list] = {}  # the sets of one rule share its condition
        for i, (columns, only) in enumerate(items[at:at + batch]):
            by.setdefault(id(only), [only]).append(F.struct(F.lit(i).alias("item"), _key(columns).alias("h"), rows.alias("k")))
        keyed = [F.array(*own) if only is None else F.when(only, F.array(*own)) for only, *own in by.values()]
        every = keyed[0] if len(keyed) == 1 else F.flatten(F.filter(F.array(*keyed), lambda x: x.isNotNull()))
        each = df.select(F.inline(every)).groupBy("item", "h").agg(F.sum("k").alias("n"))
        n = F.col("n").cast("decimal(19,0)")
        for r in each.groupBy("item").agg(F.sum(n * (n - 1)).alias("pairs"), F.sum(n).alias("rows")).collect():
            out[at + r["item"]] = _share(r["pairs"], r["rows"])
    if len(items) > batch:
        df.unpersist()
    return out


def _counted(df: DataFrame, columns: Sequence[str]) -> tuple[DataFrame, Column]:
    """The different rows of ``columns``, and how often each stands, under a name that no column bears."""
    taken, name = {c.lower() for c in columns}, "n"
    while name in taken:
        name += "_"
    return df.groupBy(*columns).agg(F.count("*").alias(name)), F.col(name)


def _key(columns: Sequence[str]) -> Column:
    """A hash in which null and the place of each cell count."""
    return F.xxhash64(*(x for c in columns for x in (F.col(c), F.col(c).isNull())))


def _share(pairs, rows) -> float:
    rows = int(rows)
    return float(pairs) / (rows * (rows - 1)) if rows > 1 else 1.0


def kappas(df: DataFrame, sets: Iterable[frozenset[str]]) -> dict[frozenset[str], float]:
    """kappa of each set of columns."""
    sets = sorted({frozenset(s) for s in sets}, key=sorted)
    return dict(zip(sets, kappas_of(df, [(sorted(s), None) for s in sets])))


def determined(df: DataFrame, rels: Sequence[Relation]) -> list[tuple[frozenset[str], str]]:
    """(columns, a column that they determine) by ``rels``, which hold on every row.

    In a sum or difference of whole numbers all columns but one determine that one, in other exact rules the inputs the
    output. A quotient is compared with a tolerance and determines nothing.
    """
    from relmine.functions.expressions import divides, signed_sum
    from relmine.operators.satisfy import exact_columns

    out: list[tuple[frozenset[str], str]] = []
    for r in rels:
        if r.kind == "AR" and exact_columns(df, r):
            full, signs = frozenset(r.columns), signed_sum(r.expr)
            if signs and len(signs) == r.arity:
                out += [(full - {c}, c) for c in r.columns]
            elif not divides(r.expr):
                out.append((frozenset(r.inputs), r.output))
    return out


@dataclass
class Known:
    """What is known of one table: which columns determine another, and kappas by all that a set of columns determines.

    Sets that determine the same columns group the rows alike, so one of them is counted for all. ``once`` keeps what is read
    from the table alike on every level: null patterns, probe rows and the draw of rows for trials.
    """

    steps: list[tuple[frozenset[str], str]] = field(default_factory=list)
    kappa: dict[frozenset[str], float] = field(default_factory=dict)
    seen: dict[tuple, Any] = field(default_factory=dict)

    def once(self, key: tuple, make: Callable[[], Any]) -> Any:
        if key not in self.seen:
            self.seen[key] = make()
        return self.seen[key]

    def close(self) -> None:
        """Rows drawn for trials are let go."""
        for key, value in self.seen.items():
            if key[0] == "drawn" and value is not None:
                value[0].unpersist()
        self.seen.clear()

    def closure(self, columns: Iterable[str]) -> frozenset[str]:
        out, before = set(columns), 0
        while before != len(out):
            before = len(out)
            out |= {c for given, c in self.steps if given <= out}
        return frozenset(out)

    def learn(self, df: DataFrame, rels: Sequence[Relation]) -> None:
        self.steps += [x for x in determined(df, rels) if x not in self.steps]
        self.kappa = {self.closure(s): v for s, v in self.kappa.items()}

    def kappas(self, df: DataFrame, sets: Iterable[frozenset[str]]) -> dict[frozenset[str], float]:
        """kappa of each set; a pass over ``df`` counts the smallest of those that group the rows alike, if none is known."""
        of = {s: self.closure(s) for s in set(sets)}
        open_: dict[frozenset[str], frozenset[str]] = {}
        for s in sorted(of, key=lambda s: (len(s), sorted(s))):
            if of[s] not in self.kappa:
                open_.setdefault(of[s], s)
        if open_:
            got = kappas(df, open_.values())
            self.kappa.update({whole: got[s] for whole, s in open_.items()})
        return {s: self.kappa[whole] for s, whole in of.items()}


def group_bound(kappa: dict[frozenset[str], float], rel: Relation, cfg: Config) -> float:
    """The published bound, or the tight one: a set survives if both rows agree on it or on all the others."""
    full = frozenset(rel.columns)
    total, n = 0.0, 0
    for s in column_sets(rel.columns):
        if cfg.subset_space == "proper" and s == full:
            continue
        n += 1
        if not cfg.tight:
            total += kappa[s]
        elif s == full:
            total += 1.0
        else:
            total += kappa[s] + kappa[full - s] - kappa[full]
    return total / n


def sampled(df: DataFrame, rows: int) -> DataFrame:
    """About ``rows`` rows, for bounds where exact grouping sets would expand the whole table."""
    n = df.count()
    return df if n <= rows else df.sample(fraction=rows / n, seed=42)


def bounds(df: DataFrame, rels: Sequence[Relation], cfg: Config, maps: DataFrame | None = None, complete: Collection[str] = (), known: Known | None = None) -> dict[str, float]:
    """Bound by cand_id, in one pass for all rules; in the dirty setting each rule sees its satisfied rows.

    ``maps`` are the value dependencies' maps (``dependency_maps``), if they are known; ``complete`` are the cand_ids of
    rules known to hold on every row, which need fewer sets. ``known`` carries over what earlier calls found of the same table.
    """
    from relmine.operators.satisfy import dependency_counts, dependency_maps, exact_columns, holds, same_rows, sum_signs

    base = sampled(df, cfg.bound_rows) if cfg.bound_mode == "sample" else df
    if cfg.setting == "clean":
        known = Known() if known is None else known
        known.learn(base, [r for r in rels if r.cand_id in complete])
        kappa = known.kappas(base, (s for r in rels for s in column_sets(r.columns)))
        return {r.cand_id: group_bound(kappa, r, cfg) for r in rels}
    plain, fds = [r for r in rels if r.kind != "FD"], [r for r in rels if r.kind == "FD"]
    keys = same_rows(base, plain)  # rules that are satisfied by the same rows share the kappas of their sets
    ok: dict = {}
    for r in plain:
        ok.setdefault(keys[r.cand_id], holds(r, exact=exact_columns(base, r), cfg=cfg))
    least = {r.cand_id: {s: frozenset(r.columns) if len(s) == r.arity and sum_signs(base, r) else s for s in column_sets(r.columns)} for r in plain}
    wanted = list(dict.fromkeys((keys[r.cand_id], s) for r in plain for s in least[r.cand_id].values()))
    narrow = base.select(*sorted({c for r in plain for c in r.columns})) if plain else base
    kappa = dict(zip(wanted, kappas_of(narrow, [(sorted(s), ok[k]) for k, s in wanted])))
    found: dict[str, dict] = {r.cand_id: {s: kappa[keys[r.cand_id], t] for s, t in least.get(r.cand_id, {}).items()} for r in rels}
    if fds:
        for r, by in zip(fds, _dependency_kappas(dependency_maps(dependency_counts(base, fds)) if maps is None or base is not df else maps, fds)):
            found[r.cand_id] = by
    return {r.cand_id: group_bound(found[r.cand_id], r, cfg) for r in rels}


def _dependency_kappas(maps: DataFrame, fds: Sequence[Relation]) -> list[dict[frozenset[str], float]]:
    """kappas of value dependencies' satisfied rows, whose input determines the output."""
    n = F.col("k").cast("decimal(19,0)")
    sums = lambda by: {r["cand_id"]: _share(r["pairs"], r["rows"]) for r in maps.groupBy("cand_id", by).agg(F.sum("n_y").alias("k")).groupBy("cand_id").agg(
        F.sum(n * (n - 1)).alias("pairs"), F.sum(n).alias("rows")).collect()}
    x, y = sums("x"), sums("y")
    out = []
    for r in fds:
        if r.arity > 1:
            raise ValueError("value dependencies have one input")
        a, b = frozenset(r.inputs), frozenset([r.output])
        out.append({a: x.get(r.cand_id, 0.0), b: y.get(r.cand_id, 0.0), a | b: x.get(r.cand_id, 0.0)})
    return out


def closed_sum_score(df: DataFrame, rel: Relation) -> float:
    """Exact survival score of a signed sum on its satisfied rows: every column set has a partial sum that decides."""
    from relmine.functions.expressions import signed_sum

    signs = signed_sum(rel.expr)
    if signs is None:
        raise ValueError("only rules of + and - have a core for every column set")
    full, sets = frozenset(rel.columns), column_sets(rel.columns)
    cores = {}
    for s in sets:
        part = full - s if rel.output in s else s
        if part:
            cores[s] = sorted(part)
    names = {s: f"core{i}" for i, s in enumerate(cores)}
    total = lambda part: reduce(F.try_add, (F.col(c) if signs[c] > 0 else F.negative(c) for c in part))
    frame = df.select(*(total(part).alias(names[s]) for s, part in cores.items()))
    kappa = kappas(frame, [frozenset([n]) for n in names.values()])
    return sum(kappa[frozenset([names[s]])] if s in names else 1.0 for s in sets) / len(sets)


def dependency_score(df: DataFrame, rel: Relation, mode: str) -> float:
    """Exact survival score of a value dependency: (1 + 2 kappa(y)) / 3 when the observed map is the rule,
    with the pairs of rows whose inputs occur once added when the table is asked again."""
    pairs = df.groupBy(*(F.col(c).alias(f"x{i}") for i, c in enumerate(rel.inputs))).agg(F.count("*").alias("n"), F.min(rel.output).alias("y"))
    n, k = df.count(), kappas(df, [frozenset([rel.output])])[frozenset([rel.output])]
    if n < 2:
        return 1.0
    if mode == "induced":
        return (1 + 2 * k) / 3
    once = pairs.where("n = 1").groupBy("y").agg(F.count("*").alias("s"))
    got = once.agg(F.sum("s").alias("a"), F.sum(F.col("s").cast("decimal(19,0)") * F.col("s")).alias("b")).first()
    s, same = int(got["a"] or 0), int(got["b"] or 0)
    return (1 + 2 * (k + (s * (s - 1) - (same - s)) / (n * (n - 1)))) / 3


def core_checks(rel: Relation, names: Sequence[str], guarded: bool) -> dict[int, tuple[Column, bool]]:
    """By mask: whether both rows agree on the inner node whose leaves are exchanged, and whether that decides alone.

    Where a zero above the node could hide a change, unequal nodes decide only without the guard.
    """
    out: dict[int, tuple[Column, bool]] = {}
    bit = {c: 1 << i for i, c in enumerate(names)}
    full = (1 << len(names)) - 1
    for node in subtrees(rel.expr):
        mask = sum(bit[c] for c in leaves(node))
        same = evaluate(node, lambda c: F.col(f"a.{c}")) == evaluate(node, lambda c: F.col(f"b.{c}"))
        sure = not guarded or not absorbed_above(rel.expr, node)
        for m in {mask, full ^ mask} - {0}:
            out.setdefault(m, (same, sure))
    return out
