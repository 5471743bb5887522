"""Candidate generators: rules that hold on enough rows, level by level.

Arithmetic and token rules are found by signature joins: the values that an
expression takes on a few probe rows meet the values of an output column (or,
in the middle, of an output combined with one more input) in an equi-join, so
no combination of expression and output is ever spelled out. Probe rows come in
groups; a dirty rule need agree on one group only. All that is found is checked
again on the whole table.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from fractions import Fraction
from itertools import permutations
from math import gcd

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmine.functions.expressions import canonical, leaves, opt, render
from relmine.functions.statistics import wilson
from relmine.model import Config, Relation
from relmine.operators.bounds import Known
from relmine.operators.minimality import is_minimal
from relmine.operators.satisfy import is_accurate, satisfaction

NUMERIC = ("tinyint", "smallint", "int", "bigint", "float", "double")
DELIMITERS = ("-", "/", " ", "#", "_", ":")


def numeric_columns(df: DataFrame, cfg: Config) -> list[str]:
    return [c for c, t in df.dtypes if (t in NUMERIC or t.startswith("decimal")) and c not in cfg.exclude]


def text_columns(df: DataFrame, cfg: Config) -> list[str]:
    return [c for c, t in df.dtypes if t == "string" and c not in cfg.exclude]


def profile(df: DataFrame, columns: Sequence[str] | None = None) -> DataFrame:
    """(col, type, n_rows, nulls, distinct_values, constant, key_like): one aggregate for all columns."""
    columns = list(columns or df.columns)
    sums = [F.count("*").alias("n")]
    for i, c in enumerate(columns):
        sums += [F.count_if(F.col(c).isNull()).alias(f"z{i}"), F.approx_count_distinct(c, 0.02).alias(f"d{i}"), F.min(c).eqNullSafe(F.max(c)).alias(f"c{i}")]
    one = df.agg(*sums)
    kinds = dict(df.dtypes)
    rows = F.array(*(F.struct(F.lit(c).alias("col"), F.lit(kinds[c]).alias("type"), F.col("n").alias("n_rows"), F.col(f"z{i}").alias("nulls"), F.col(f"d{i}").alias("distinct_values"),
                              F.col(f"c{i}").alias("constant"), (F.col(f"d{i}") >= 0.97 * F.col("n")).alias("key_like")) for i, c in enumerate(columns)))
    return one.select(F.inline(rows))


def null_patterns(df: DataFrame, columns: Sequence[str]) -> list[list[str]]:
    """The columns, those together that are null in the same rows.

    A rule that holds on all rows has one pattern in all its columns, for a row
    with a part of them null violates it. Probes of an output's rules are rows
    where its pattern has values.
    """
    key = F.xxhash64(*(F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in columns)).cast("decimal(20,0)")
    one = df.agg(*(f for i, c in enumerate(columns) for f in (F.count_if(F.col(c).isNull()).alias(f"n{i}"), F.sum(F.when(F.col(c).isNull(), key)).alias(f"k{i}")))).first()
    by: dict[tuple, list[str]] = {}
    for i, c in enumerate(columns):
        by.setdefault((one[f"n{i}"], one[f"k{i}"]), []).append(c)
    return list(by.values())


def _once(known: Known | None, key: tuple, make: Callable):
    return make() if known is None else known.once(key, make)


def probe_rows(df: DataFrame, columns: Sequence[str], groups: int, size: int, seed: int = 7, known: Known | None = None, where: str | None = None) -> DataFrame:
    """(grp, row, cells): ``groups`` times ``size`` different rows with the smallest hashes.

    A top-k by hash, in which equal rows are neighbours; only where repeats leave too few of it are rows made different first.
    ``known`` keeps the rows for the levels to come; ``where`` names the column whose nulls ``df`` leaves out.
    """
    wanted, names = groups * size, sorted(set(columns))
    drawn, kind = _once(known, ("probes", where, *names, wanted, seed), lambda: _smallest(df, names, wanted, seed, None if known is None else df.count()))
    rows = [(i % groups, i, cells) for i, cells in enumerate(drawn)]
    schema = T.StructType([T.StructField("grp", T.IntegerType()), T.StructField("row", T.IntegerType()), T.StructField("cells", kind)])
    return df.sparkSession.createDataFrame(rows, schema)


def _smallest(df: DataFrame, names: Sequence[str], wanted: int, seed: int, rows: int | None) -> tuple[list, T.DataType]:
    """The cells of ``wanted`` different rows with the smallest hashes, and their type.

    Of a known number of rows those with small hashes are picked before a task puts rows in order; too few, and all are.
    """
    keyed = df.select(F.xxhash64(*(x for c in names for x in (F.col(c), F.col(c).isNull())), F.lit(seed)).alias("k"), F.struct(*(F.col(c) for c in names)).alias("cells"))
    some: list = []
    if rows and (share := 1024 * wanted / rows) < 0.5:
        some = keyed.where(F.col("k") < int(share * 2**64) - 2**63).orderBy("k").limit(16 * wanted).collect()
    if len(some) < 16 * wanted:
        some = keyed.orderBy("k").limit(16 * wanted).collect()
    drawn = {r["k"]: r["cells"] for r in some}
    if len(drawn) < wanted and len(some) == 16 * wanted:
        drawn = {r["k"]: r["cells"] for r in keyed.groupBy("k").agg(F.first("cells").alias("cells")).orderBy("k").limit(wanted).collect()}
    return [cells for _, cells in sorted(drawn.items(), key=lambda x: x[0])[:wanted]], keyed.schema["cells"].dataType


def cells(probes: DataFrame, columns: Sequence[str]) -> DataFrame:
    """(grp, row, col, v) in double precision."""
    pairs = F.array(*(F.struct(F.lit(c).alias("col"), F.col("cells")[c].cast("double").alias("v")) for c in columns))
    return probes.select("grp", "row", F.inline(pairs))


def texts_of(probes: DataFrame, columns: Sequence[str]) -> DataFrame:
    """(row, col, v) as text."""
    return probes.select("row", F.inline(F.array(*(F.struct(F.lit(c).alias("col"), F.col("cells")[c].cast("string").alias("v")) for c in columns))))


def pair_values(values: DataFrame) -> DataFrame:
    """(grp, row, l, op, r, v): the six combinations of two different columns."""
    a, b = values.select("grp", "row", F.col("col").alias("l"), F.col("v").alias("x")), values.select("grp", "row", F.col("col").alias("r"), F.col("v").alias("y"))
    both = a.join(b, ["grp", "row"]).where("l <> r")
    ops = F.array(F.struct(F.lit("+").alias("op"), (F.col("x") + F.col("y")).alias("v")), F.struct(F.lit("-").alias("op"), (F.col("x") - F.col("y")).alias("v")),
                  F.struct(F.lit("*").alias("op"), (F.col("x") * F.col("y")).alias("v")), F.struct(F.lit("/").alias("op"), F.try_divide("x", "y").alias("v")))
    return both.select("grp", "row", "l", "r", F.inline(ops)).where("l < r or op in ('-', '/')")


def signatures(values: DataFrame, keys: Sequence[str]) -> DataFrame:
    """(keys..., grp, sig): nine significant digits of the values on a group of probe rows; null where one is missing."""
    digits = F.format_string("%.8e", F.when(F.col("v") == 0, F.lit(0.0)).otherwise(F.col("v")))
    listed = values.groupBy(*keys, "grp").agg(F.sort_array(F.collect_list(F.struct("row", digits.alias("d")))).alias("s"), F.count("v").alias("n"), F.count("*").alias("m"))
    return listed.where("n = m").select(*keys, "grp", F.xxhash64("s").alias("sig"))


def arithmetic(df: DataFrame, level: int, cfg: Config, pruners: Sequence[Relation] = (), groups: int = 8, size: int = 3, known: Known | None = None) -> list[Relation]:
    """Rules with ``level`` inputs (2, 3 or 4) that hold on at least tau of the rows; ``known`` keeps what other levels read too."""
    columns, found = numeric_columns(df, cfg), []
    if len(columns) <= level:
        return []
    for outputs in _once(known, ("nulls", *columns), lambda: null_patterns(df, columns)):
        inputs = outputs if cfg.tau >= 1 else columns
        if len(inputs) > level:
            found += _arithmetic(df.where(F.col(outputs[0]).isNotNull()), level, cfg, inputs, outputs, groups, size, known)
    return checked(df, found, cfg, pruners)


def _arithmetic(df: DataFrame, level: int, cfg: Config, columns: Sequence[str], outputs: Sequence[str], groups: int, size: int, known: Known | None = None) -> list[Relation]:
    """Candidates with one of ``outputs``; a clean one agrees on every group that there is."""
    size = size if cfg.tau >= 1 else 2
    drawn = cells(probe_rows(df, columns, groups, size, known=known, where=outputs[0]), columns).collect()
    if not drawn:
        return []
    values = df.sparkSession.createDataFrame(drawn, "grp int, row int, col string, v double")
    need = len({r["grp"] for r in drawn}) if cfg.tau >= 1 else 1
    flat = signatures(values, ["col"])
    pairs = signatures(pair_values(values), ["l", "op", "r"])
    if level == 2:
        met = pairs.join(flat, ["grp", "sig"]).where("col <> l and col <> r").groupBy("l", "op", "r", "col").agg(F.count("*").alias("g")).where(F.col("g") >= need)
        found = [Relation("AR", tuple(leaves(t)), r["col"], t) for r in met.collect() for t in [canonical((r["op"], r["l"], r["r"]))]]
    else:
        left = pairs.select("grp", "sig", F.struct("l", "op", "r").alias("e")) if level == 3 else _triples(values)
        # e o c = y holds where e equals y with c undone: meet in the middle
        right = pairs.select("grp", "sig", F.col("l").alias("l2"), F.col("op").alias("op2"), F.col("r").alias("r2"))
        met = left.join(right, ["grp", "sig"]).groupBy("e", "l2", "op2", "r2").agg(F.count("*").alias("g")).where(F.col("g") >= need)
        found = []
        for r in met.collect():
            tree = _tree(r["e"])
            solved = _completed(tree, r["l2"], r["op2"], r["r2"])
            if level == 4:
                solved = solved + [_undone(r["e"], (r["op2"], r["l2"], r["r2"]))]
            for whole, y in solved:
                used = leaves(whole)
                if y not in used and len(set(used)) == level == len(used):
                    found.append(Relation("AR", tuple(leaves(canonical(whole))), y, canonical(whole)))
    return [r for r in found if r.output in outputs]


def _triples(values: DataFrame) -> DataFrame:
    two = pair_values(values).select("grp", "row", F.struct("l", "op", "r").alias("p"), F.col("v").alias("x"))
    one = values.select("grp", "row", F.col("col").alias("c"), F.col("v").alias("y"))
    both = two.join(one, ["grp", "row"]).where("c <> p.l and c <> p.r")
    ops = F.array(*(F.struct(F.lit(o).alias("op"), v.alias("v")) for o, v in (
        ("+", F.col("x") + F.col("y")), ("-", F.col("x") - F.col("y")), ("~", F.col("y") - F.col("x")), ("*", F.col("x") * F.col("y")), ("/", F.try_divide("x", "y")), ("\\", F.try_divide("y", "x")))))
    e = both.select("grp", "row", "p", "c", F.inline(ops)).select("grp", "row", F.struct("p", "op", "c").alias("e"), "v")
    return signatures(e, ["e"]).select("grp", "sig", "e")


def _tree(e):
    if "p" in e.__fields__:
        inner = (e["p"]["op"], e["p"]["l"], e["p"]["r"])
        return ({"~": "-", "\\": "/"}[e["op"]], e["c"], inner) if e["op"] in "~\\" else (e["op"], inner, e["c"])
    return (e["op"], e["l"], e["r"])


def _undone(e, pair):
    """The rule with two pairs that says that ``e``, a pair with a third column, equals ``pair``, solved for the column."""
    inner = (e["p"]["op"], e["p"]["l"], e["p"]["r"])
    return {"+": ("-", pair, inner), "-": ("-", inner, pair), "~": ("+", pair, inner),
            "*": ("/", pair, inner), "/": ("/", inner, pair), "\\": ("*", pair, inner)}[e["op"]], e["c"]


def _completed(tree, left: str, op: str, right: str):
    """Rules that say ``tree`` equals ``left op right``, solved for either column."""
    if op == "-":
        return [(("+", tree, right), left), (("-", left, tree), right)]
    if op == "+":
        return [(("-", tree, right), left), (("-", tree, left), right)]
    if op == "/":
        return [(("*", tree, right), left), (("/", left, tree), right)]
    return [(("/", tree, right), left), (("/", tree, left), right)]


def affine(df: DataFrame, cfg: Config) -> DataFrame:
    """(x, y, slope, intercept, r2): least squares of every ordered pair of numeric columns, one pass."""
    columns = numeric_columns(df, cfg)
    pairs = list(permutations(columns, 2))
    sums = [f.alias(f"{n}{i}") for i, (x, y) in enumerate(pairs) for n, f in (("s", F.regr_slope(y, x)), ("i", F.regr_intercept(y, x)), ("r", F.regr_r2(y, x)))]
    rows = F.array(*(F.struct(F.lit(x).alias("x"), F.lit(y).alias("y"), F.col(f"s{i}").alias("slope"), F.col(f"i{i}").alias("intercept"), F.col(f"r{i}").alias("r2")) for i, (x, y) in enumerate(pairs)))
    return df.agg(*sums).select(F.inline(rows))


def constants(df: DataFrame, cfg: Config, pruners: Sequence[Relation] = (), rows: int = 24, known: Known | None = None) -> list[Relation]:
    """Rules of whole numbers with one input and constants: y = a * x + b and y = x mod m, read from a few probe rows."""
    kinds = dict(df.dtypes)
    columns, found = [c for c in numeric_columns(df, cfg) if kinds[c] in ("tinyint", "smallint", "int", "bigint")], []
    for group in _once(known, ("nulls", *columns), lambda: null_patterns(df, columns)) if cfg.tau >= 1 else ():
        if len(group) < 2:
            continue
        probes = [r["cells"] for r in probe_rows(df.where(F.col(group[0]).isNotNull()), group, 1, rows, known=known, where=group[0]).collect()]
        for x, y in permutations(group, 2):
            points = sorted({(r[x], r[y]) for r in probes})
            if len({v for _, v in points}) < 2:
                continue
            (x0, y0), (x1, y1) = points[0], points[-1]
            a = Fraction(y1 - y0, x1 - x0) if x1 != x0 else Fraction(0)
            if a and a.denominator == 1 and all(v == a * (u - x0) + y0 for u, v in points):
                found.append(Relation("AR", (x,), y, ("affine", x, opt(int(a)), opt(int(y0 - a * x0)))))
            m = gcd(*(u - v for u, v in points))
            if min(v for _, v in points) >= 0 and max(v for _, v in points) < m < max(abs(u) for u, _ in points):
                found.append(Relation("AR", (x,), y, ("mod", x, opt(m))))
    return checked(df, found, cfg, pruners)


def _pieces(texts: Sequence[str], probes: list) -> list[tuple[str, tuple | str, list[str]]]:
    """(column, expression, values on the probe rows) of the columns and of their tokens, from the left and from the right."""
    out: list[tuple[str, tuple | str, list[str]]] = []
    for c in texts:
        values = [r[c] for r in probes]
        out.append((c, c, values))
        for d in DELIMITERS:
            cut = [v.split(d) for v in values]
            few = min(map(len, cut))
            if few > 1:
                same = few == max(map(len, cut))
                out += [(c, ("token", c, opt(d), opt(i + 1)), [t[i] for t in cut]) for i in range(few)]
                out += [] if same else [(c, ("token", c, opt(d), opt(-i - 1)), [t[-i - 1] for t in cut]) for i in range(few)]
    return [p for p in out if all(p[2])]


def programs(df: DataFrame, level: int, cfg: Config, pruners: Sequence[Relation] = (), rows: int = 24) -> list[Relation]:
    """String rules with ``level`` inputs (1 to 3) that hold on all rows: fixed places of a text, its token from the right,
    and columns or their tokens joined, with a constant text before, between and behind them."""
    texts, found = text_columns(df, cfg), []
    for group in null_patterns(df, texts) if cfg.tau >= 1 and texts else ():
        probes = [r["cells"] for r in probe_rows(df.where(F.col(group[0]).isNotNull()), group, 1, rows).collect()]
        if len(group) < 2 or not probes:
            continue
        pieces = _pieces(group, probes)
        for y in group:
            made = [r[y] for r in probes]
            if len(set(made)) < 2:
                continue
            others = [p for p in pieces if p[0] != y and len(set(p[2])) > 1]
            if level == 1:
                found += _places(y, made, others)
            found += _joins(y, made, others, level)
    return checked(df, found, cfg, pruners)


def _places(y: str, made: list[str], pieces: list) -> list[Relation]:
    out = []
    for c, expr, values in pieces:
        if expr == c and all(m and m in v and m != v for m, v in zip(made, values)):
            size, starts = {len(m) for m in made}, set.intersection(*({i for i in range(len(v)) if v.startswith(m, i)} for m, v in zip(made, values)))
            if len(size) == 1 and starts:
                out.append(Relation("ST", (c,), y, ("slice", c, opt(min(starts) + 1), opt(size.pop()))))
        elif expr != c and expr[3][1] < 0 and values == made:
            out.append(Relation("ST", (c,), y, expr))
    return out


def _joins(y: str, made: list[str], pieces: list, level: int) -> list[Relation]:
    """Pieces found one after the other in every value of y, from its start on, with constant texts around them."""
    out = []

    def grow(parts: list, rest: list[str], sources: list[str]) -> None:
        if parts and len(sources) == level and len(set(rest)) == 1 and (len(parts) > 1 or rest[0] and parts[0] != sources[0]):
            tree = ("concat", *parts, *([("lit", rest[0])] if rest[0] else []))
            out.append(Relation("ST", tuple(sources), y, tree))
        if len([p for p in parts if not (isinstance(p, tuple) and p[0] == "lit")]) == max(2, level):
            return
        for c, expr, values in pieces:
            if c not in sources and len(sources) == level or expr in parts:
                continue
            at = [r.find(v) for r, v in zip(rest, values)]
            if min(at) < 0 or len({r[:i] for r, i in zip(rest, at)}) > 1:
                continue
            lead = rest[0][:at[0]]
            grow([*parts, *([("lit", lead)] if lead else []), expr], [r[i + len(v):] for r, i, v in zip(rest, at, values)], sources if c in sources else [*sources, c])

    grow([], made, [])
    return out


def extractions(df: DataFrame, cfg: Config, pruners: Sequence[Relation] = (), rows: int = 24) -> list[Relation]:
    """String rules with one input: tokens by delimiter, letter case, and a literal before a (padded) value."""
    texts = text_columns(df, cfg)
    sources = texts + [c for c, t in df.dtypes if t in ("int", "bigint") and c not in cfg.exclude]
    found = []
    for outputs in null_patterns(df, sources) if texts else ():
        inputs = outputs if cfg.tau >= 1 else sources
        found += _extractions(df.where(F.col(outputs[0]).isNotNull()), cfg, [c for c in inputs if c in texts], inputs, rows)
    return checked(df, found, cfg, pruners)


def _extractions(df: DataFrame, cfg: Config, texts: Sequence[str], sources: Sequence[str], rows: int) -> list[Relation]:
    probes = probe_rows(df, list(dict.fromkeys(sources)), 1, rows)
    own = texts_of(probes, sources)
    out = own.select("row", F.col("col").alias("y"), F.col("v").alias("w"))
    total = probes.count()
    tokens = own.where(F.col("col").isin(texts)).select("row", "col", F.explode(F.array(*(F.lit(d) for d in DELIMITERS))).alias("d"), "v").select(
        "row", "col", "d", F.posexplode(F.expr(r"split(v, concat('\\Q', d, '\\E'))")).alias("i", "t"))
    least = F.lit(total if cfg.tau >= 1 else max(1, int(total * max(0.3, cfg.tau - 0.3))))
    hit = tokens.join(out, "row").where("col <> y and t = w").groupBy("col", "y", "d", "i").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    varied = out.groupBy("y").agg(F.count_distinct("w").alias("k"))
    hit = hit.join(varied.where("k > 1"), "y")
    found = [Relation("ST", (r["col"],), r["y"], ("token", r["col"], opt(r["d"]), opt(r["i"] + 1))) for r in hit.collect()]
    pairs = own.join(out, "row").where("col <> y")
    # y = literal + x, x perhaps padded with zeros to a fixed width
    bare = F.length("v") > 0
    ends = pairs.where(bare & F.expr("endswith(w, v)")).withColumn("lead", F.expr("regexp_replace(substr(w, 1, length(w) - length(v)), '0+$', '')")).groupBy("col", "y").agg(
        F.count("*").alias("n"), F.count_distinct("lead").alias("leads"), F.min("lead").alias("lead"), F.count_distinct(F.length("w")).alias("sizes"), F.max(F.length("w")).alias("size"),
        F.count_distinct(F.length("v")).alias("widths"), F.max(F.length("v")).alias("width")).where((F.col("n") >= least) & (F.col("leads") == 1))
    for r in ends.collect():
        width = r["size"] - len(r["lead"])
        body = ("padded", r["col"], opt(width)) if r["sizes"] == 1 and width > r["width"] else r["col"]
        if r["lead"] or body != r["col"]:
            found.append(Relation("ST", (r["col"],), r["y"], ("concat", ("lit", r["lead"]), body)))
    for op, made in (("lower", F.lower("v")), ("upper", F.upper("v")), ("trim", F.trim("v"))):
        same = pairs.where((made == F.col("w")) & F.col("col").isin(texts)).groupBy("col", "y").agg(F.count("*").alias("n")).where(F.col("n") >= least)
        found += [Relation("ST", (r["col"],), r["y"], (op, r["col"])) for r in same.collect()]
    return found


def concatenations(df: DataFrame, cfg: Config, pruners: Sequence[Relation] = (), rows: int = 24) -> list[Relation]:
    """String rules with two inputs: the output begins with one, ends with the other, with one separator between."""
    texts, found = text_columns(df, cfg), []
    if len(texts) < 3:
        return []
    for outputs in null_patterns(df, texts):
        inputs = outputs if cfg.tau >= 1 else texts
        if len(inputs) > 2:
            found += _concatenations(df.where(F.col(outputs[0]).isNotNull()), cfg, inputs, rows)
    return checked(df, found, cfg, pruners)


def _concatenations(df: DataFrame, cfg: Config, texts: Sequence[str], rows: int) -> list[Relation]:
    probes = probe_rows(df, texts, 1, rows)
    total = probes.count()
    cell = texts_of(probes, texts)
    as_ = lambda n: cell.select("row", F.col("col").alias(f"c{n}"), F.col("v").alias(f"v{n}"))
    heads = as_(0).join(as_(1), "row").where("c0 <> c1 and length(v1) > 0 and length(v0) > length(v1) and startswith(v0, v1)")
    met = heads.join(as_(2), "row").where("c2 <> c0 and c2 <> c1 and length(v2) > 0 and length(v0) >= length(v1) + length(v2) and endswith(v0, v2)")
    sep = met.withColumn("sep", F.expr("substr(v0, length(v1) + 1, length(v0) - length(v1) - length(v2))")).groupBy("c0", "c1", "c2", "sep").agg(F.count("*").alias("n"))
    least = total if cfg.tau >= 1 else max(1, int(total * max(0.3, cfg.tau - 0.3)))
    found = []
    for r in sep.where(F.col("n") >= least).collect():
        parts = (r["c1"], ("lit", r["sep"]), r["c2"]) if r["sep"] else (r["c1"], r["c2"])
        found.append(Relation("ST", (r["c1"], r["c2"]), r["c0"], ("concat", *parts)))
    return found


def dependency_ratios(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """(x, y, hits, n_rows, distinct_x): the share of rows with the most frequent output, for all ordered pairs in one pass."""
    pairs = F.array(*(F.struct(F.lit(x).alias("x"), F.lit(y).alias("y"), F.col(x).cast("string").alias("vx"), F.col(y).cast("string").alias("vy")) for x, y in permutations(columns, 2)))
    counts = df.select(F.inline(pairs)).groupBy("x", "y", "vx", "vy").agg(F.count("*").alias("n"))
    best = counts.groupBy("x", "y", "vx").agg(F.max("n").alias("m"), F.sum("n").alias("n"))
    return best.groupBy("x", "y").agg(F.sum("m").alias("hits"), F.sum("n").alias("n_rows"), F.count("*").alias("distinct_x"))


def dependencies(df: DataFrame, columns: Sequence[str], cfg: Config, pruners: Sequence[Relation] = ()) -> list[Relation]:
    """Value dependencies with one input; constant outputs are no rules."""
    constant = {r["col"] for r in profile(df, columns).where("constant").collect()}
    rows = dependency_ratios(df, columns).collect()
    return [Relation("FD", (r["x"],), r["y"]) for r in sorted(rows, key=lambda r: (r["x"], r["y"])) if r["y"] not in constant and is_accurate(r["hits"], r["n_rows"], cfg.tau)]


def screened(df: DataFrame, rels: Sequence[Relation], cfg: Config, rows: int = 1000, z: float = 4.0) -> list[Relation]:
    """Rules that some rows do not disprove: in the clean setting one violation does, in the dirty one the upper end of the
    share's interval below tau."""
    some = df.orderBy(F.xxhash64(*(F.col(f"`{c}`").cast("string") for c in df.columns))).limit(rows).persist()
    try:  # drawn once for all batches of rules
        got = {r["cand_id"]: (r["hits"], r["n_rows"]) for r in satisfaction(some, rels, cfg).collect()}
    finally:
        some.unpersist()
    open_ = lambda h, n: n == 0 or (h == n if cfg.tau >= 1 else wilson(n, h, z)[1] >= cfg.tau)
    return [r for r in rels if open_(*got[r.cand_id])]


def checked(df: DataFrame, found: Sequence[Relation], cfg: Config, pruners: Sequence[Relation] = ()) -> list[Relation]:
    """Different rules that hold on enough rows of the whole table and that no pruner covers; many are screened first."""
    unique = sorted({r.cand_id: r for r in found if not cfg.use_minimality or is_minimal(r, pruners)}.values(), key=lambda r: (r.output, render(r.expr)))
    if len(unique) > cfg.batch_rules:
        unique = screened(df, unique, cfg)
    if not unique:
        return []
    ok = {r["cand_id"] for r in satisfaction(df, unique, cfg).collect() if r["n_rows"] and is_accurate(r["hits"], r["n_rows"], cfg.tau)}
    return [r for r in unique if r.cand_id in ok]
