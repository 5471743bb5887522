"""Labelled pools of generated rules on tables of the published average size, and runs of all methods over them.

Candidates are enumerated over a carrier's columns; the formulas that made the
columns say which of them are true. Negatives are all other candidates that hold
on some rows (clean) or on at least ``tau`` of them (dirty), drawn by hash to the
published base rate; among them are coincidences of sparse columns, rules that
leave a column out, and true rules with a column too many. Every candidate is
treated alike, whatever its label: in the clean setting each is judged on the rows
that satisfy it, in the dirty setting all are judged on one noisy table.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from contextlib import contextmanager
from dataclasses import dataclass
from functools import reduce
from hashlib import md5
from itertools import combinations, permutations, product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmine.bench import carriers
from relmine.functions.expressions import canonical, leaves, opt
from relmine.functions.measures import MEASURES, explanations, measures, pair_counts, reliable_information
from relmine.model import Config, Relation
from relmine.operators.satisfy import dependency_counts, dependency_maps, exact_columns, holds
from relmine.plans.framework import reliability, verify

#: Rows of a pool's table, and the share of true candidates: fixed values of the published pools.
ROWS = {"AR": 600, "ST": 400, "FD": 4000}
BASE_RATE = {"AR": 0.107, "ST": 0.0065, "FD": 0.386}
KEYS = {"AR": ("l_orderkey", "l_linenumber", "l_partkey", "ext_c"), "FD": ("l_orderkey", "l_linenumber", "l_partkey", "s_suppkey"), "ST": ("p_partkey",)}
#: What each summed column is made of.
SUMS = {"ext_c": {"ext": 1}, "disc_c": {"disc": 1}, "tax_c": {"tax": 1}, "ship_c": {"ship": 1}, "sur_c": {"sur": 1}, "net_c": {"ext": 1, "disc": -1}, "gross_c": {"ext": 1, "disc": -1, "tax": 1},
        "total_c": {"ext": 1, "disc": -1, "tax": 1, "ship": 1}, "due_c": {"ext": 1, "disc": -1, "tax": 1, "sur": 1}}
SPARSE = ("dp", "tp", "qty", "sur_c", "a_flag", "b_flag", "e_flag", "l_linenumber")
#: Columns that the schema says determine others.
DETERMINED = {"s_suppkey": ("n_name", "r_name"), "n_name": ("r_name",), "l_partkey": ("p_brand", "p_type"), "l_orderkey": ("o_orderstatus", "o_custkey", "c_mktsegment", "c_nationkey"), "o_custkey": ("c_mktsegment", "c_nationkey")}
FD_COLUMNS = ("s_suppkey", "n_name", "r_name", "l_partkey", "p_brand", "p_type", "l_orderkey", "o_custkey", "o_orderstatus", "c_mktsegment", "c_nationkey", "l_returnflag", "l_linestatus", "rare")


def ar(op: str, a, b, y: str) -> Relation:
    return Relation("AR", tuple(leaves((op, a, b))), y, (op, a, b))


@dataclass(frozen=True)
class Pool:
    """A table and its labelled candidates; ``keys`` are columns that no rule may use."""
    df: DataFrame
    items: list[tuple[Relation, bool]]
    keys: tuple[str, ...]

    @property
    def rels(self) -> list[Relation]:
        return [r for r, _ in self.items]


def carrier(spark: SparkSession, sf_dir: str, kind: str, rows: int | None = None) -> DataFrame:
    """The table of a pool: ``rows`` rows of the kind's carrier by hash order."""
    if kind == "AR":
        df = carriers.ar_lineitem(spark, sf_dir).drop("zero_c")
    elif kind == "FD":
        df = carriers.wide(spark, sf_dir).withColumn("rare", F.when(F.col("l_orderkey") % 25 == 0, "y").otherwise("n"))
    else:
        words = F.split("p_type", " ")
        foreign = lambda m, salt: F.pmod(F.xxhash64("p_partkey", F.lit(salt)), F.lit(m))
        df = carriers.st_part(spark, sf_dir).withColumns({
            "brand_no": F.split_part("p_brand", F.lit("#"), F.lit(2)), "type_1": words[0], "label": F.concat("w1", F.lit("-"), F.split_part("p_brand", F.lit("#"), F.lit(2))),
            # texts of another table put beside the rows, texts of one value, and nearly constant ones
            "other": F.concat(F.lit("Brand#"), foreign(30, 1)), "letter": F.substring(F.md5(foreign(9, 2).cast("string")), 1, 1), "flag": F.when(foreign(40, 3) == 0, "x").otherwise("B"), "same": F.lit("s"),
            "pair": F.concat(foreign(5, 4).cast("string"), F.lit(" "), foreign(4, 5).cast("string"))})
    return carriers.sized(df, rows or ROWS[kind], KEYS[kind])


def _numbers(frame: pd.DataFrame, tree) -> np.ndarray:
    if isinstance(tree, str):
        return frame[tree].to_numpy(float)
    a, b = (_numbers(frame, t) for t in tree[1:])
    with np.errstate(divide="ignore", invalid="ignore"):
        return a + b if tree[0] == "+" else a - b if tree[0] == "-" else a * b if tree[0] == "*" else np.where(b != 0, a / b, np.nan)


def _true_sum(tree, y: str) -> bool:
    total: dict[str, int] = {}
    todo = [(tree, 1), (y, -1)]
    while todo:
        t, sign = todo.pop()
        if isinstance(t, str):
            if t not in SUMS:
                return False
            for k, v in SUMS[t].items():
                total[k] = total.get(k, 0) + sign * v
        elif t[0] in "+-":
            todo += [(t[1], sign), (t[2], sign if t[0] == "+" else -sign)]
        else:
            return False
    return not any(total.values())


def _arithmetic(frame: pd.DataFrame) -> dict[Relation, tuple[float, bool]]:
    """Share of rows and truth of all rules of two inputs, of all sums of three, and of true rules with one column more."""
    columns = [*SUMS, "qty", "unit_c", "list_c", *(c for c in SPARSE if c not in (*SUMS, "qty"))]
    trees = {canonical((op, a, b)) for a, b in permutations(columns, 2) for op in "+-*/"}
    trees |= {canonical((o2, (o1, a, b), c)) for a, b, c in permutations(SUMS, 3) for o1, o2 in product("+-", repeat=2)}
    out: dict[Relation, tuple[float, bool]] = {}

    def add(tree, y, true):
        rel = Relation("AR", tuple(leaves(tree)), y, tree)
        out[rel] = (float(np.isclose(_numbers(frame, tree), frame[y].to_numpy(float), rtol=1e-9, atol=0).mean()), true)

    products = {("*", "qty", "unit_c"): "list_c", ("/", "list_c", "qty"): "unit_c", ("/", "list_c", "unit_c"): "qty"}
    for tree in sorted(trees, key=repr):
        used = set(leaves(tree))
        for y in columns:
            if y not in used:
                add(tree, y, products.get(tree) == y or _true_sum(tree, y))
    for rel in [r for r, (_, true) in out.items() if true and r.arity == 2]:
        for extra, op in product(("a_flag", "b_flag", "e_flag", "sur_c"), "+-"):
            if extra not in rel.columns:
                add(canonical((op, rel.expr, extra)), rel.output, False)
    return out


def _texts(frame: pd.DataFrame) -> dict[Relation, tuple[float, bool]]:
    """Share of rows and truth of all extractions of one input and all concatenations of two."""
    columns = [c for c in frame.columns if c != "p_partkey"]
    cells = {c: frame[c].astype(str).tolist() for c in columns}
    out: dict[Relation, tuple[float, bool]] = {}

    def add(inputs, y, tree, made):
        share = float(np.mean([a == b for a, b in zip(made, cells[y])]))
        if share:
            out[Relation("ST", inputs, y, tree)] = (share, tree in TRUE_TEXTS.get(y, ()))

    for x, y in permutations(columns, 2):
        for d, i in product((" ", "#", "-"), (1, 2)):
            add((x,), y, ("token", x, opt(d), opt(i)), [(v.split(d) + [None] * 2)[i - 1] for v in cells[x]])
        for start, size in product(range(1, 8), (1, 2, 3, 7)):
            add((x,), y, ("slice", x, opt(start), opt(size)), [v[start - 1:start - 1 + size] for v in cells[x]])
        for a in (c for c in columns if c not in (x, y)):
            for sep in ("", " ", "-"):
                add((x, a), y, ("concat", x, ("lit", sep), a) if sep else ("concat", x, a), [u + sep + v for u, v in zip(cells[x], cells[a])])
    return out


def _token(x: str, d: str, i: int) -> tuple:
    return ("token", x, opt(d), opt(i))


TRUE_TEXTS = {"w1": (_token("p_name", " ", 1), _token("label", "-", 1)), "w2": (_token("p_name", " ", 2),), "p_name": (("concat", "w1", ("lit", " "), "w2"),), "brand_no": (_token("p_brand", "#", 2), _token("label", "-", 2)),
              "type_1": (_token("p_type", " ", 1),), "label": (("concat", "w1", ("lit", "-"), "brand_no"),)}


def _dependencies(frame: pd.DataFrame) -> dict[Relation, tuple[float, bool]]:
    out = {}
    for x, y in permutations(FD_COLUMNS, 2):
        best = frame.groupby([x, y]).size().groupby(level=0).max().sum()
        out[Relation("FD", (x,), y)] = (float(best / max(1, len(frame))), y in DETERMINED.get(x, ()))
    return out


def _drawn(rels, count: int) -> list[Relation]:
    return sorted(rels, key=lambda r: md5(r.cand_id.encode()).hexdigest())[:count]


def pool(spark: SparkSession, sf_dir: str, kind: str, setting: str, rate: float = 0.1, rows: int | None = None, most: int = 134) -> Pool:
    """The labelled pool of a kind, at most sixteen true candidates and ``most`` others; in the dirty setting ``rate`` of
    the rows have one cell changed."""
    df = carrier(spark, sf_dir, kind, rows)
    frame = df.toPandas()  # as many rows as ``ROWS`` says
    found = {"AR": _arithmetic, "ST": _texts, "FD": _dependencies}[kind](frame)
    least = 0.05 if setting == "clean" else Config(setting="dirty").tau
    yes = _drawn([r for r, (_, true) in found.items() if true], 16)
    no = [r for r, (share, true) in found.items() if not true and share >= least and (kind != "FD" or frame[r.output].nunique() > 1)]
    wanted = min(most, round(len(yes) * (1 / BASE_RATE[kind] - 1)))
    items = [(r, True) for r in yes] + [(r, False) for r in _drawn(no, wanted)]
    used = sorted({c for r, _ in items for c in r.columns})
    if setting == "dirty":
        change = carriers.noisy if kind == "AR" else carriers.mixed_up
        noised = [c for c in used if kind != "AR" or c not in SPARSE]
        df = change(df, rate, noised, KEYS[kind])
    keys = tuple(c for c in KEYS[kind] if c not in used and c in df.columns)
    return Pool(df.select(*used, *keys), items, keys)


def settings(pool_: Pool, setting: str, **changes) -> Config:
    """The clean setting judges each candidate on the rows that satisfy it, which is what the dirty one does, without the
    test for independence of violations. 2,000 trials are the most: the interval leaves eta within a few hundred."""
    cfg = Config(setting="dirty", tau=0.0, use_independence=False) if setting == "clean" else Config(setting="dirty")
    return cfg.but(**({"exclude": pool_.keys, "n_max": 2000} | changes))


def _labels(pool_: Pool) -> DataFrame:
    return pool_.df.sparkSession.createDataFrame([(r.cand_id, r.arity, y) for r, y in pool_.items], "cand_id string, arity int, label boolean")


def framework_scores(pool_: Pool, cfg: Config, name: str = "framework") -> DataFrame:
    """(method, cand_id, arity, score, label): one minus the survival score; what was not judged has 0."""
    got = reliability(verify(pool_.df, pool_.rels, cfg))
    return _labels(pool_).join(got, "cand_id", "left").select(F.lit(name).alias("method"), "cand_id", "arity", F.coalesce("reliability", F.lit(0.0)).alias("score"), "label")


def _joint(pool_: Pool, setting: str) -> DataFrame:
    """(cand, x, y, n) on the rows that count."""
    rels, df = pool_.rels, pool_.df
    named = [(r.cand_id, r.inputs, r.output) for r in rels]
    if setting == "dirty":
        return pair_counts(df, named)
    if rels[0].kind == "FD":
        return dependency_maps(dependency_counts(df, rels)).select(F.col("cand_id").alias("cand"), "x", "y", F.col("n_y").alias("n"))
    return pair_counts(df, named, [holds(r, exact=exact_columns(df, r)) for r in rels])


def baseline_scores(pool_: Pool, setting: str, rfi: bool = True, explain: bool = True) -> DataFrame:
    """(method, cand_id, arity, score, label) of all measures on the same rows."""
    joint = _joint(pool_, setting).persist()
    long_ = lambda wide, names: wide.select(F.col("cand").alias("cand_id"), F.inline(F.array(*(F.struct(F.lit(m).alias("method"), F.col(m).cast("double").alias("score")) for m in names))))
    parts = [long_(measures(joint), MEASURES)]
    if rfi:
        parts.append(long_(reliable_information(joint), ("rfi", "rfi_norm")))
    if explain:
        parts.append(explanations(pool_.df, pool_.rels, only_satisfied=setting == "clean").select("cand_id", F.lit("explain").alias("method"), "score"))
    names = [*MEASURES, *(("rfi", "rfi_norm") if rfi else ()), *(("explain",) if explain else ())]
    every = _labels(pool_).withColumn("method", F.explode(F.array(*map(F.lit, names))))
    got = reduce(DataFrame.unionByName, parts)
    rows = every.join(got, ["cand_id", "method"], "left").select("method", "cand_id", "arity", F.coalesce("score", F.lit(0.0)).alias("score"), "label").collect()
    joint.unpersist()
    return pool_.df.sparkSession.createDataFrame(rows, "method string, cand_id string, arity int, score double, label boolean")


@contextmanager
def interpreted(spark: SparkSession):
    """Plans of hundreds of rules over hundreds of rows take far longer to compile than to run: they are interpreted."""
    wanted = {"spark.sql.codegen.wholeStage": "false", "spark.sql.codegen.factoryMode": "NO_CODEGEN"}
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def quality(spark: SparkSession, sf_dir: str, kind: str, setting: str) -> DataFrame:
    """(method, cand_id, arity, score, label) of the framework and of all measures."""
    p = pool(spark, sf_dir, kind, setting)
    p = Pool(p.df.persist(), p.items, p.keys)
    try:
        with interpreted(spark):
            ours = framework_scores(p, settings(p, setting)).collect()
            return spark.createDataFrame(ours, "method string, cand_id string, arity int, score double, label boolean").unionByName(baseline_scores(p, setting))
    finally:
        p.df.unpersist()


def timed(methods: dict[str, Callable[[], object]], candidates: int) -> list[tuple[str, float]]:
    """(method, ms per candidate) of running each over a whole pool, generation left out."""
    out = []
    for name, run in methods.items():
        began = time.perf_counter()
        run()
        out.append((name, 1000 * (time.perf_counter() - began) / max(1, candidates)))
    return out
