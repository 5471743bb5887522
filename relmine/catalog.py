"""Registered queries of the engine and, where SQL can express them, their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce
from itertools import permutations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relmine.bench import carriers, metrics, pools
from relmine.functions.expressions import canonical, leaves, opt, render
from relmine.functions.measures import MEASURES, explanations, measures, pair_counts, reliable_information
from relmine.functions.statistics import hash_int, wilson_bounds
from relmine.model import VERDICT, Config, Relation
from relmine.operators import bounds, generate, independence, minimality, perturb, satisfy
from relmine.plans import framework
from relmine.sources.tables import check_constraints, load, relations_view, satisfaction_template
from relmine.streaming import monitor

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
DIGITS = 6


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return add


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, DIGITS) for c in columns})


# ---- carriers in SQL -------------------------------------------------------------------------------------------------

AR = """ar as (
  select l_orderkey, l_linenumber, l_partkey, cast(round(l_quantity) as bigint) as qty, cast(round(l_extendedprice * 100) as bigint) as ext_c,
         cast(round(p_retailprice * 100) as bigint) as unit_c, cast(round(l_discount * 100) as bigint) as dp, cast(round(l_tax * 100) as bigint) as tp,
         (ext_c * dp + 50) // 100 as disc_c, ext_c - disc_c as net_c, (net_c * tp + 50) // 100 as tax_c, net_c + tax_c as gross_c, qty * unit_c as list_c,
         500 * qty as ship_c, net_c + tax_c + ship_c as total_c, case when l_partkey % 20 = 3 then 700 else 0 end as sur_c, gross_c + sur_c as due_c,
         case when qty = 50 then 1 else 0 end as a_flag, case when dp = 0 and tp = 0 then 1 else 0 end as b_flag,
         case when l_linenumber = 7 and l_partkey % 50 = 0 then 1 else 0 end as e_flag, 0 as zero_c
  from lineitem join part on l_partkey = p_partkey)"""
WIDE = """wide as (
  select l_orderkey, l_partkey, s_suppkey, o_custkey, n_name, r_name, p_brand, p_type, o_orderstatus, c_mktsegment, c_nationkey, l_returnflag, l_linestatus
  from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey
  join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey join customer on o_custkey = c_custkey)"""
ORD = """ord as (
  select o_orderkey, o_orderpriority, split_part(o_orderpriority, '-', 1) as prio_code, regexp_replace(o_orderpriority, '^[^-]*-', '') as prio_text,
         strftime(o_orderdate, '%Y-%m') as ym, strftime(o_orderdate, '%Y') as y, strftime(o_orderdate, '%m') as m from orders)"""
PART = "prt as (select p_partkey, p_name, split_part(p_name, ' ', 1) as w1, split_part(p_name, ' ', 2) as w2, p_brand, p_type from part)"


def sql_hash(*parts: str) -> str:
    return f"cast('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 15) as bigint)"


def ar(*args) -> Relation:
    return pools.ar(*args)


NET = ar("-", "ext_c", "disc_c", "net_c")
GROSS = ar("+", "net_c", "tax_c", "gross_c")
TOTAL = ar("+", ("+", "net_c", "tax_c"), "ship_c", "total_c")
LIST = ar("*", "qty", "unit_c", "list_c")
DUE = ar("+", "gross_c", "sur_c", "due_c")
SHORT = ar("+", "net_c", "tax_c", "due_c")
COINCIDENCE = ar("*", "a_flag", "b_flag", "e_flag")
CUSTOMER = Relation("ST", ("c_custkey",), "c_name", ("concat", ("lit", "Customer#"), ("padded", "c_custkey", opt(9))))
NATION = Relation("ST", ("n_nationkey",), "n_name", ("concat", ("lit", "NATION_"), "n_nationkey"))
URL_LANG = Relation("ST", ("url",), "page_lang", ("token", "url", opt("/"), opt(4)))
PART_NAME = Relation("ST", ("w1", "w2"), "p_name", ("concat", "w1", ("lit", " "), "w2"))
PRIORITY = Relation("ST", ("o_orderpriority",), "prio_code", ("token", "o_orderpriority", opt("-"), opt(1)))
REGION_MOD = Relation("AR", ("n_nationkey",), "n_regionkey", ("mod", "n_nationkey", opt(5)))


def _sql_sat(with_: str, source: str, conditions: Sequence[tuple[Relation, str]]) -> str:
    rows = " union all ".join(f"select '{r.text.replace(chr(39), chr(39) * 2)}' as rule, count(*) filter (where {c}) as hits, count(*) as n_rows from {source}" for r, c in conditions)
    return (f"with {with_} " if with_ else "") + rows


# ---- satisfaction ----------------------------------------------------------------------------------------------------

def _sat(name: str, frame: Callable, rels: Sequence[Relation], sql: str) -> None:
    query(name, sql)(lambda spark, d: satisfy.satisfaction(frame(spark, d), rels).select("rule", "hits", "n_rows"))


_sat("sat_ar_net", carriers.ar_lineitem, [NET], _sql_sat(AR, "ar", [(NET, "ext_c - disc_c = net_c")]))
_sat("sat_ar_gross", carriers.ar_lineitem, [GROSS, LIST], _sql_sat(AR, "ar", [(GROSS, "net_c + tax_c = gross_c"), (LIST, "qty * unit_c = list_c")]))
_sat("sat_ar_three_sum", carriers.ar_lineitem, [TOTAL], _sql_sat(AR, "ar", [(TOTAL, "net_c + tax_c + ship_c = total_c")]))
_sat("sat_ar_coincidence", carriers.ar_lineitem, [COINCIDENCE, SHORT], _sql_sat(AR, "ar", [(COINCIDENCE, "a_flag * b_flag = e_flag"), (SHORT, "net_c + tax_c = due_c")]))
_sat("sat_st_customer_name", lambda s, d: load(s, d, "customer"), [CUSTOMER], _sql_sat("", "customer", [(CUSTOMER, "c_name = 'Customer#' || lpad(cast(c_custkey as varchar), 9, '0')")]))
_sat("sat_st_nation_name", lambda s, d: load(s, d, "nation"), [NATION, REGION_MOD], _sql_sat("", "nation", [(NATION, "n_name = 'NATION_' || n_nationkey"), (REGION_MOD, "n_regionkey = n_nationkey % 5")]))
_sat("sat_st_url_lang", carriers.st_pages, [URL_LANG], _sql_sat("pg as (select url, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) as page_lang from pages)", "pg", [(URL_LANG, "split_part(url, '/', 4) = page_lang")]))
_sat("sat_st_part_name_concat", carriers.st_part, [PART_NAME], _sql_sat(PART, "prt", [(PART_NAME, "w1 || ' ' || w2 = p_name")]))
_sat("sat_st_priority_code", carriers.st_orders, [PRIORITY], _sql_sat(ORD, "ord", [(PRIORITY, "split_part(o_orderpriority, '-', 1) = prio_code")]))

FD_COLUMNS = ("n_name", "r_name", "p_brand", "o_orderstatus", "c_mktsegment", "l_returnflag")


def _sql_ratios(columns: Sequence[str]) -> str:
    parts = " union all ".join(
        f"select '{x}' as x, '{y}' as y, cast(sum(m) as bigint) as hits, cast(sum(n) as bigint) as n_rows, count(*) as distinct_x from (select {x}, max(n) as m, sum(n) as n from (select {x}, {y}, count(*) as n from wide group by 1, 2) group by 1)"
        for x, y in permutations(columns, 2))
    return f"with {WIDE} {parts}"


@query("sat_fd_all_pairs_wide", _sql_ratios(FD_COLUMNS))
def _(spark, d):
    return generate.dependency_ratios(carriers.wide(spark, d), FD_COLUMNS)


@query("gen_fd_clean", f"select x, y from ({_sql_ratios(FD_COLUMNS)}) where hits = n_rows")
def _(spark, d):
    rels = generate.dependencies(carriers.wide(spark, d), FD_COLUMNS, Config())
    return spark.createDataFrame([(r.inputs[0], r.output) for r in rels], "x string, y string")


@query("gen_fd_dirty", f"select x, y from ({_sql_ratios(('n_name', 'r_name', 'p_brand', 'l_returnflag'))}) where 5 * hits >= 4 * n_rows")
def _(spark, d):
    rels = generate.dependencies(carriers.wide(spark, d), ("n_name", "r_name", "p_brand", "l_returnflag"), Config(setting="dirty"))
    return spark.createDataFrame([(r.inputs[0], r.output) for r in rels], "x string, y string")


@query("tau_filter_dirty", f"select rule, hits, n_rows from ({_sql_sat(AR, 'ar', [(SHORT, 'net_c + tax_c = due_c'), (COINCIDENCE, 'a_flag * b_flag = e_flag'), (ar('+', 'net_c', 'sur_c', 'due_c'), 'net_c + sur_c = due_c')])}) where 5 * hits >= 4 * n_rows")
def _(spark, d):
    got = satisfy.satisfaction(carriers.ar_lineitem(spark, d), [SHORT, COINCIDENCE, ar("+", "net_c", "sur_c", "due_c")])
    return satisfy.accurate(got, Config(setting="dirty").tau).select("rule", "hits", "n_rows")


@query("violations_dirty_net", f"with {AR} select l_orderkey, l_linenumber, l_partkey, net_c, tax_c, due_c from ar where net_c + tax_c <> due_c")
def _(spark, d):
    return satisfy.violations(carriers.ar_lineitem(spark, d), SHORT).select("l_orderkey", "l_linenumber", "l_partkey", "net_c", "tax_c", "due_c")


@query("repair_expected_values", f"with {AR} select l_orderkey, l_linenumber, net_c, tax_c, due_c, net_c + tax_c as expected from ar where net_c + tax_c <> due_c")
def _(spark, d):
    return satisfy.expected_values(carriers.ar_lineitem(spark, d), SHORT, ["l_orderkey", "l_linenumber"])


_PROFILED = ("l_orderkey", "l_linenumber", "l_returnflag", "l_linestatus", "l_quantity")


@query("profile_lineitem", " union all ".join(f"select '{c}' as col, count(*) as n_rows, count(*) - count({c}) as nulls, min({c}) is not distinct from max({c}) as constant from lineitem" for c in _PROFILED))
def _(spark, d):
    return generate.profile(load(spark, d, "lineitem"), _PROFILED).select("col", "n_rows", "nulls", "constant")


@query("stable_exact_nation", "select 'name' as rule, count(distinct n_name) > 1 or not bool_and(n_name = 'NATION_' || n_nationkey) as stable from nation union all "
       "select 'region', count(distinct n_regionkey) > 1 or not bool_and(n_regionkey = n_nationkey % 5) from nation")
def _(spark, d):
    nation = load(spark, d, "nation")
    return spark.createDataFrame([("name", satisfy.stable_exactly(nation, NATION)), ("region", satisfy.stable_exactly(nation, REGION_MOD))], "rule string, stable boolean")


# ---- generation ------------------------------------------------------------------------------------------------------

GEN = ("ext_c", "disc_c", "net_c", "tax_c", "gross_c", "ship_c", "total_c")


def _sql_level2() -> str:
    tests = []
    for a, b in permutations(GEN, 2):
        for op in "+-*/":
            if op in "+*" and a > b:
                continue
            for y in GEN:
                if y not in (a, b):
                    cond = f"{a} {op} {b} = {y}" if op != "/" else f"({b} <> 0 and {a} = {y} * {b})"
                    tests.append((f"({a} {op} {b}) = {y}", cond))
    sums = ", ".join(f"coalesce(bool_and({c}), false) as t{i}" for i, (_, c) in enumerate(tests))
    rows = ", ".join(f"struct_pack(rule := '{t}', ok := t{i})" for i, (t, _) in enumerate(tests))
    return f"with {AR}, t as (select {sums} from ar), u as (select unnest([{rows}]) as s from t) select s.rule as rule from u where s.ok"


@query("gen_ar_level2", _sql_level2())
def _(spark, d):
    rels = generate.arithmetic(carriers.ar_lineitem(spark, d).select(*GEN), 2, Config())
    return spark.createDataFrame([(r.text,) for r in rels], "rule string")


def _sql_sums_of_three() -> str:
    # all sums and differences of three columns that hold on every row; products and quotients of cents make no other rule here
    trees = sorted({canonical((o2, (o1, a, b), c)) for a, b, c in permutations(GEN, 3) for o1 in "+-" for o2 in "+-"}, key=repr)
    tests = [f"{render(t)} = {y}" for t in trees for y in GEN if y not in leaves(t)]
    sums = ", ".join(f"coalesce(bool_and({t}), false) as t{i}" for i, t in enumerate(tests))
    rows = ", ".join(f"struct_pack(rule := '{t}', ok := t{i})" for i, t in enumerate(tests))
    return f"with {AR}, t as (select {sums} from ar), u as (select unnest([{rows}]) as s from t) select s.rule as rule from u where s.ok"


@query("gen_ar_level3", _sql_sums_of_three())
def _(spark, d):
    """Meet in the middle: pair expressions meet outputs combined with one more input."""
    rels = generate.arithmetic(carriers.ar_lineitem(spark, d).select(*GEN), 3, Config())
    return spark.createDataFrame([(r.text,) for r in rels], "rule string")


@query("gen_ar_signature", f"select 'gross_c' as output, count(*) as rules from ({_sql_level2()}) where rule like '%= gross_c' union all select 'net_c', count(*) from ({_sql_level2()}) where rule like '%= net_c'")
def _(spark, d):
    rels = generate.arithmetic(carriers.ar_lineitem(spark, d).select(*GEN), 2, Config())
    return spark.createDataFrame([(y, sum(r.output == y for r in rels)) for y in ("gross_c", "net_c")], "output string, rules bigint")


_NOISY_GEN = ("net_c", "tax_c", "gross_c", "sur_c", "due_c")


def _sql_level2_dirty() -> str:
    tests = []
    for a, b in permutations(_NOISY_GEN, 2):
        for op in "+-*/":
            for y in _NOISY_GEN:
                if y not in (a, b) and not (op in "+*" and a > b):
                    tests.append((f"({a} {op} {b}) = {y}", f"{a} {op} {b} = {y}" if op != "/" else f"({b} <> 0 and abs({a} / nullif({b}, 0) - {y}) <= 1e-9 * abs({y}))"))
    sums = ", ".join(f"count(*) filter (where {c}) as t{i}" for i, (_, c) in enumerate(tests))
    rows = ", ".join(f"struct_pack(rule := '{t}', hits := t{i})" for i, (t, _) in enumerate(tests))
    return f"with {AR}, t as (select count(*) as n, {sums} from ar), u as (select n, unnest([{rows}]) as s from t) select s.rule as rule, s.hits as hits, n as n_rows from u where 5 * s.hits >= 4 * n"


@query("gen_ar_dirty", _sql_level2_dirty())
def _(spark, d):
    rels = generate.arithmetic(carriers.ar_lineitem(spark, d).select("net_c", "tax_c", "gross_c", "sur_c", "due_c"), 2, Config(setting="dirty"))
    return satisfy.satisfaction(carriers.ar_lineitem(spark, d), rels).select("rule", "hits", "n_rows")


@query("gen_affine", f"with {AR} select 'qty' as x, 'ship_c' as y, round(regr_slope(ship_c, qty), {DIGITS}) as slope, round(regr_intercept(ship_c, qty), {DIGITS}) + 0.0 as intercept from ar")
def _(spark, d):
    got = generate.affine(carriers.ar_lineitem(spark, d).select("qty", "ship_c"), Config()).where("x = 'qty'")
    return rounded(got.select("x", "y", "slope", "intercept"), "slope", "intercept")


@query("gen_st_extract")
def _(spark, d):
    out = generate.extractions(carriers.st_part(spark, d), Config(exclude=("p_partkey",))) + generate.extractions(carriers.st_orders(spark, d), Config(exclude=("o_orderkey",))) + generate.extractions(load(spark, d, "customer"), Config())
    return spark.createDataFrame([(r.text,) for r in out], "rule string")


def _sql_concats(source: str, columns: Sequence[str]) -> str:
    parts = []
    for y, a, b in permutations(columns, 3):
        gap = f"substr({y}, length({a}) + 1, length({y}) - length({a}) - length({b}))"
        ok = f"bool_and(length({a}) > 0 and length({b}) > 0 and length({y}) >= length({a}) + length({b}) and starts_with({y}, {a}) and ends_with({y}, {b}))"
        parts.append(f"select '{a}' as a, '{b}' as b, '{y}' as y, {ok} as ok, min({gap}) as lo, max({gap}) as hi from {source}")
    return " union all ".join(parts)


_CONCAT_SQL = (f"with {PART}, {ORD}, c as ({_sql_concats('prt', ('p_name', 'w1', 'w2', 'p_brand', 'p_type'))} union all {_sql_concats('ord', ('o_orderpriority', 'prio_code', 'prio_text', 'ym', 'y', 'm'))}) "
               "select 'concat(' || a || case when lo = '' then '' else ', ' || chr(39) || lo || chr(39) end || ', ' || b || ') = ' || y as rule from c where ok and lo = hi")


@query("gen_st_concat", _CONCAT_SQL)
def _(spark, d):
    out = generate.concatenations(carriers.st_part(spark, d), Config()) + generate.concatenations(carriers.st_orders(spark, d), Config())
    return spark.createDataFrame([(r.text,) for r in out], "rule string")


# ---- minimality ------------------------------------------------------------------------------------------------------

_CANDS = (GROSS, TOTAL, ar("+", ("-", "ext_c", "disc_c"), "e_flag", "net_c"), NET, DUE, ar("+", ("+", "net_c", "tax_c"), "sur_c", "due_c"), ar("+", "net_c", "sur_c", "due_c"))
_PRUNERS = (NET, GROSS, DUE)
_POOL = tuple(dict.fromkeys((*_CANDS, *_PRUNERS)))


def _values(rels: Sequence[Relation], name: str) -> str:
    rows = ", ".join(f"('{r.text}', '{r.output}', [{', '.join(repr(c) for c in sorted(r.inputs))}])" for r in rels)
    return f"{name} as (select * from (values {rows}) v(rule, output, inputs))"


_MINIMAL_SQL = (f"with {AR}, {_values(_CANDS, 'c0')}, {_values(_PRUNERS, 'p0')}, sat as ({_sql_sat('', 'ar', [(r, r.text) for r in _POOL])}), "
                "c as (select c0.*, hits, n_rows from c0 join sat using (rule) where 5 * hits >= 4 * n_rows), p as (select p0.* from p0 join sat using (rule) where 5 * hits >= 4 * n_rows) "
                "select rule, output, len(inputs) as arity, hits, n_rows from c where not exists (select 1 from p where p.output = c.output and len(p.inputs) < len(c.inputs) and list_has_all(c.inputs, p.inputs))")


@query("minimality_prune", _MINIMAL_SQL)
def _(spark, d):
    """Of the rules that hold on enough rows, those that no smaller one of them makes needless."""
    hold = satisfy.accurate(satisfy.satisfaction(carriers.ar_lineitem(spark, d), _POOL), Config(setting="dirty").tau).select("cand_id", "hits", "n_rows")
    got = minimality.minimal(minimality.frame(spark, _CANDS).join(hold, "cand_id"), minimality.frame(spark, _PRUNERS).join(hold, "cand_id"))
    return got.select("rule", "output", F.col("arity").cast("bigint").alias("arity"), "hits", "n_rows")


# ---- perturbation ----------------------------------------------------------------------------------------------------

def _swap(rel: Relation, own: str, other: str) -> dict[str, str]:
    return {c: f"(case when (mask >> {i}) & 1 = 1 then {other}.{c} else {own}.{c} end)" for i, c in enumerate(rel.columns)}


def _sql_survives(rel: Relation, condition: str) -> str:
    """``condition`` has {column} places."""
    return f"({condition.format(**_swap(rel, 'a', 'b'))}) and ({condition.format(**_swap(rel, 'b', 'a'))})"


def _sql_bank(source: str, columns: Sequence[str], used: Sequence[str], n: int, where: str = "true", seed: int = 42) -> str:
    """Pairs (trial, a, b) as ``trial_bank`` draws them from a table of at least 2n rows."""
    text = "concat_ws('|', " + ", ".join(f"coalesce(cast({c} as varchar), '~')" for c in sorted(columns)) + ")"
    order = ", ".join(["k", *sorted(used)])
    return (f"keyed as (select {', '.join(sorted(used))}, md5(concat_ws('|', {text}, '', 0, '{seed}')) as k from {source} where {where}), "
            f"drawn as (select *, row_number() over (order by {order}) - 1 as r from keyed qualify r < {2 * n}), "
            f"bank as (select x.r as trial, x as a, y as b from drawn x join drawn y on y.r = x.r + {n} where x.r < {n})")


def _sql_outcomes(rels: Sequence[tuple[Relation, str]], space: str = "nonempty") -> str:
    parts = []
    for r, cond in rels:
        size = (1 << len(r.columns)) - (1 if space == "nonempty" else 2)
        key = f"'{r.cand_id}'"
        parts.append(f"select {key} as cand_id, trial, mask, case when {_sql_survives(r, cond)} then 1 else 0 end as survived from (select *, {sql_hash(key, 'trial')} % {size} + 1 as mask from bank)")
    return "outcomes as (" + " union all ".join(parts) + ")"


_AR_ALL = ("l_orderkey", "l_linenumber", "l_partkey", "qty", "ext_c", "unit_c", "dp", "tp", "disc_c", "net_c", "tax_c", "gross_c", "list_c", "ship_c", "total_c", "sur_c", "due_c", "a_flag", "b_flag", "e_flag", "zero_c")
_TRIED = ((NET, "{ext_c} - {disc_c} = {net_c}"), (GROSS, "{net_c} + {tax_c} = {gross_c}"), (LIST, "{qty} * {unit_c} = {list_c}"), (DUE, "{gross_c} + {sur_c} = {due_c}"))
_USED = sorted({c for r, _ in _TRIED for c in r.columns})
_N = 1000
_PLAIN = Config(n_max=_N, use_core=False)


def _tried(spark, d, cfg: Config = _PLAIN) -> DataFrame:
    df = carriers.ar_lineitem(spark, d)
    bank = perturb.trial_bank(df, _USED, _N)
    return reduce(DataFrame.unionByName, [perturb.outcomes(bank, r, cfg) for r, _ in _TRIED])


_TRIALS_SQL = f"{AR}, {_sql_bank('ar', _AR_ALL, _USED, _N)}, {_sql_outcomes(_TRIED)}"


@query("perturb_sampled_ar", f"with {_TRIALS_SQL} select cand_id, count(*) as trials, cast(sum(survived) as bigint) as survived from outcomes group by 1")
def _(spark, d):
    return _tried(spark, d).groupBy("cand_id").agg(F.count("*").alias("trials"), F.sum("survived").alias("survived"))


@query("perturb_core_trial", f"with {_TRIALS_SQL} select cand_id, mask, count(*) as trials, cast(sum(survived) as bigint) as survived from outcomes group by 1, 2")
def _(spark, d):
    """The core shortcut with its guard decides as the full check does."""
    return _tried(spark, d, Config(n_max=_N)).groupBy("cand_id", "mask").agg(F.count("*").alias("trials"), F.sum("survived").alias("survived"))


@query("perturb_proper_subsets", f"with {AR}, {_sql_bank('ar', _AR_ALL, _USED, _N)}, {_sql_outcomes(_TRIED, 'proper')} select cand_id, cast(sum(survived) as bigint) as survived from outcomes group by 1")
def _(spark, d):
    return _tried(spark, d, _PLAIN.but(subset_space="proper")).groupBy("cand_id").agg(F.sum("survived").alias("survived"))


_BLOCK_SQL = (f"{_TRIALS_SQL}, per as (select cand_id, trial // 100 as block, count(*) as k, sum(survived) as t from outcomes group by 1, 2), "
              "run as (select cand_id, block, sum(k) over w as n, sum(t) over w as s from per window w as (partition by cand_id order by block)), "
              "lim as (select *, (s + 1.96 * 1.96 / 2) / (n + 1.96 * 1.96) as mid, 1.96 * sqrt(s * (n - s) * 1.0 / n + 1.96 * 1.96 / 4) / (n + 1.96 * 1.96) as half from run)")


@query("wilson_stop_blocks", f"with {_BLOCK_SQL} select cand_id, cast(block as bigint) as block, cast(n as bigint) as n, cast(s as bigint) as s, round(mid - half, {DIGITS}) as low, round(mid + half, {DIGITS}) as high from lim")
def _(spark, d):
    return rounded(perturb.blocks(_tried(spark, d), _PLAIN), "low", "high")


@query("wilson_first_stop", f"with {_BLOCK_SQL}, off as (select cand_id, arg_min(n, block) as n, arg_min(s, block) as s, count(*) as c from lim where mid - half > 0.5 or mid + half < 0.5 group by 1), "
       "fin as (select cand_id, arg_max(n, block) as n, arg_max(s, block) as s from lim group by 1) "
       f"select fin.cand_id, cast(coalesce(off.n, fin.n) as bigint) as trials, cast(coalesce(off.s, fin.s) as bigint) as survived, round(coalesce(off.s, fin.s) * 1.0 / coalesce(off.n, fin.n), {DIGITS}) as score, case when off.n is null then 'exhausted' else 'wilson' end as stop_reason from fin left join off using (cand_id)")
def _(spark, d):
    return rounded(perturb.first_stop(_tried(spark, d), _PLAIN), "score")


@query("perturb_sampled_st", f"with {_sql_bank('customer', ('c_custkey', 'c_name', 'c_nationkey', 'c_acctbal', 'c_mktsegment'), CUSTOMER.columns, 400).replace('cast(c_acctbal as varchar)', 'cast(cast(round(c_acctbal * 100) as bigint) as varchar)')}, "
       + _sql_outcomes([(CUSTOMER, "{c_name} = 'Customer#' || lpad(cast({c_custkey} as varchar), 9, '0')")]) + " select cand_id, count(*) as trials, cast(sum(survived) as bigint) as survived from outcomes group by 1")
def _(spark, d):
    df = load(spark, d, "customer").withColumn("c_acctbal", F.round(F.col("c_acctbal") * 100).cast("bigint"))
    return perturb.outcomes(perturb.trial_bank(df, CUSTOMER.columns, 400), CUSTOMER, Config()).groupBy("cand_id").agg(F.count("*").alias("trials"), F.sum("survived").alias("survived"))


@query("perturb_dirty_satisfied", f"with {AR}, {_sql_bank('ar', _AR_ALL, SHORT.columns, _N, 'net_c + tax_c = due_c')}, {_sql_outcomes([(SHORT, '{net_c} + {tax_c} = {due_c}')])} select cand_id, count(*) as trials, cast(sum(survived) as bigint) as survived from outcomes group by 1")
def _(spark, d):
    df = satisfy.satisfied(carriers.ar_lineitem(spark, d), SHORT)
    return perturb.outcomes(perturb.trial_bank(df, SHORT.columns, _N), SHORT, _PLAIN).groupBy("cand_id").agg(F.count("*").alias("trials"), F.sum("survived").alias("survived"))


def _sql_exact(rel: Relation, condition: str) -> str:
    last = (1 << len(rel.columns)) - 1
    return (f"select '{rel.cand_id}' as cand_id, count(*) as trials, count(*) filter (where {_sql_survives(rel, condition)}) as survived from nation a join nation b on a.n_nationkey < b.n_nationkey, "
            f"(select unnest(range(1, {last + 1})) as mask) m")


@query("perturb_exact_nation", f"select *, round(survived / trials, {DIGITS}) as score from ({_sql_exact(NATION, chr(123) + 'n_name' + chr(125) + ' = ' + repr('NATION_') + ' || {n_nationkey}')} union all {_sql_exact(REGION_MOD, '{n_regionkey} = {n_nationkey} % 5')})")
def _(spark, d):
    nation = load(spark, d, "nation")
    each = [perturb.exact_score(nation, r, Config()).withColumn("cand_id", F.lit(r.cand_id)) for r in (NATION, REGION_MOD)]
    return rounded(reduce(DataFrame.unionByName, each), "score")


_FD = tuple(Relation("FD", (x,), y) for x, y in (("n_name", "r_name"), ("s_suppkey", "n_name"), ("l_partkey", "p_brand"), ("l_orderkey", "o_orderstatus"), ("o_custkey", "c_mktsegment")))


def _sql_fd(mode: str) -> str:
    parts = []
    for r in _FD:
        x, y = r.columns
        k = f"(select sum(n * (n - 1)) from (select count(*) as n from wide group by {y}))"
        once = f"(select coalesce(sum(s), 0) * (coalesce(sum(s), 0) - 1) - coalesce(sum(s * s) - sum(s), 0) from (select y, count(*) as s from (select min({y}) as y from wide group by {x} having count(*) = 1) group by 1))"
        parts.append(f"select '{r.text}' as rule, round((1 + 2.0 * ({k} + {once if mode == 'recheck' else '0'}) / (select count(*) * (count(*) - 1) from wide)) / 3, {DIGITS}) as score")
    return f"with {WIDE} " + " union all ".join(parts)


for _mode in ("recheck", "induced"):
    query(f"perturb_fd_{_mode}", _sql_fd(_mode))(lambda spark, d, mode=_mode: spark.createDataFrame(
        [(r.text, round(bounds.dependency_score(carriers.wide(spark, d), r, mode), DIGITS)) for r in _FD], "rule string, score double"))


@query("perturb_fd_sampled")
def _(spark, d):
    """Sampled scores of dependencies in both readings; compare perturb_fd_recheck and perturb_fd_induced."""
    run = lambda c: [perturb.score(c, _FD[:3], Config(n_max=2000, fd_mode=m, use_wilson=False)).withColumn("fd_mode", F.lit(m)) for m in ("recheck", "induced")]
    return reduce(DataFrame.unionByName, _cached(carriers.wide(spark, d), run))


def _sql_kappa(exprs: Sequence[str], source: str) -> str:
    return f"(select sum(cast(n as double) * (n - 1)) from (select count(*) as n from {source} group by {', '.join(exprs)})) / (select cast(count(*) as double) * (count(*) - 1) from {source})"


@query("perturb_closed_sum", f"with {AR} select '{GROSS.text}' as rule, round((2 * {_sql_kappa(['net_c'], 'ar')} + 2 * {_sql_kappa(['tax_c'], 'ar')} + 2 * {_sql_kappa(['net_c + tax_c'], 'ar')} + 1) / 7, {DIGITS}) as score")
def _(spark, d):
    return spark.createDataFrame([(GROSS.text, round(bounds.closed_sum_score(carriers.ar_lineitem(spark, d), GROSS), DIGITS))], "rule string, score double")


# ---- bounds ----------------------------------------------------------------------------------------------------------

def _sql_bound(rels: Sequence[Relation], source: str, tight: bool = False) -> str:
    parts = []
    for r in rels:
        sets = bounds.column_sets(r.columns)
        full = frozenset(r.columns)
        k = lambda s: _sql_kappa(sorted(s), source)
        terms = [k(s) if not tight else "1" if s == full else f"{k(s)} + {k(full - s)} - {k(full)}" for s in sets]
        parts.append(f"select '{r.text}' as rule, round(({' + '.join(terms)}) / {len(sets)}, {DIGITS}) as bound")
    return " union all ".join(parts)


def _bounds(df: DataFrame, rels: Sequence[Relation], cfg: Config) -> DataFrame:
    complete = {r["cand_id"] for r in satisfy.satisfaction(df, rels).where("hits = n_rows").collect()} if cfg.setting == "clean" else ()
    got = bounds.bounds(df, rels, cfg, complete=complete)
    return df.sparkSession.createDataFrame([(r.text, round(got[r.cand_id], DIGITS)) for r in rels], "rule string, bound double")


@query("bound_group_ar", f"with {AR} {_sql_bound([NET, GROSS, LIST, TOTAL, DUE], 'ar')}")
def _(spark, d):
    return _bounds(carriers.ar_lineitem(spark, d), [NET, GROSS, LIST, TOTAL, DUE], Config())


@query("bound_group_fd", f"with {WIDE} {_sql_bound(_FD, 'wide')}")
def _(spark, d):
    return _bounds(carriers.wide(spark, d), _FD, Config())


@query("bound_group_dirty", f"with {AR}, ok as (select * from ar where net_c + tax_c = due_c), co as (select * from ar where a_flag * b_flag = e_flag) {_sql_bound([SHORT], 'ok')} union all {_sql_bound([COINCIDENCE], 'co')}")
def _(spark, d):
    return _bounds(carriers.ar_lineitem(spark, d), [SHORT, COINCIDENCE], Config(setting="dirty"))


@query("bound_tight", f"with {AR} {_sql_bound([NET, GROSS, LIST, DUE], 'ar', True)}")
def _(spark, d):
    return _bounds(carriers.ar_lineitem(spark, d), [NET, GROSS, LIST, DUE], Config(tight=True))


_GRID = ("sur_c", "qty", "dp")
_WILSON_SQL = (f"with {AR}, g as (" + " union all ".join(f"select '{c}' as col, cast({c} as varchar) as value, cast(count(*) as double) as n, cast(count(*) filter (where net_c + tax_c = due_c) as double) as s from ar group by {c}" for c in _GRID) + ") "
               f"select col, value, cast(n as bigint) as n, cast(s as bigint) as s, round((s + 1.9208) / (n + 3.8416) - 1.96 * sqrt(s * (n - s) / n + 0.9604) / (n + 3.8416), {DIGITS}) as low, round((s + 1.9208) / (n + 3.8416) + 1.96 * sqrt(s * (n - s) / n + 0.9604) / (n + 3.8416), {DIGITS}) as high from g")


@query("wilson_grid", _WILSON_SQL)
def _(spark, d):
    """Wilson intervals of a rule's share of rows, for each value of other columns: from no row to all rows."""
    grid = independence.contingency(carriers.ar_lineitem(spark, d), SHORT, _GRID).select("col", "value", "n", (F.col("n") - F.col("k")).alias("s"))
    low, high = wilson_bounds(F.col("n"), F.col("s"))
    return rounded(grid.withColumn("low", low).withColumn("high", high), "low", "high")


# ---- independence ----------------------------------------------------------------------------------------------------

_LEFT = ("sur_c", "qty", "dp")


@query("chi2_contingency", f"with {AR} " + " union all ".join(f"select '{c}' as col, cast({c} as varchar) as value, count(*) as n, count(*) filter (where net_c + tax_c <> due_c) as k from ar group by {c}" for c in _LEFT))
def _(spark, d):
    return independence.contingency(carriers.ar_lineitem(spark, d), SHORT, _LEFT)


def _chi2(df: DataFrame, rel: Relation, columns: Sequence[str], cfg: Config) -> DataFrame:
    return independence.chi2(df.select(*rel.columns, *columns), [rel], cfg, {rel.cand_id: columns})


@query("chi2_statistic", f"with {AR}, t as (select count(*) as rows, count(*) filter (where net_c + tax_c <> due_c) * 1.0 / count(*) as p from ar) " + " union all ".join(
    f"select '{c}' as col, round(sum((k - n * p) * (k - n * p) / (n * p * (1 - p))), 4) as chi2, count(*) - 1 as df from (select {c}, count(*) as n, count(*) filter (where net_c + tax_c <> due_c) as k from ar group by {c}), t" for c in _LEFT))
def _(spark, d):
    return _chi2(carriers.ar_lineitem(spark, d), SHORT, _LEFT, Config(setting="dirty")).select("col", F.round("chi2", 4).alias("chi2"), "df")


@query("independence_decision")
def _(spark, d):
    df = carriers.ar_lineitem(spark, d).select(*DUE.columns, "net_c", "tax_c", "qty", "dp")
    got = independence.independent(df, [SHORT, DUE], Config(setting="dirty"))
    return spark.createDataFrame([(r.text, *got[r.cand_id]) for r in (SHORT, DUE)], "rule string, independent boolean, col string, chi2 double, p double")


_THIRDS = {"line": "l_linenumber % 3", "part": "l_partkey % 3", "size": "qty % 3"}


@query("independence_golden", f"with {AR}, t as (select count(*) filter (where net_c + tax_c <> due_c) * 1.0 / count(*) as p from ar), x as (" + " union all ".join(
    f"select '{c}' as col, sum((k - n * p) * (k - n * p) / (n * p * (1 - p))) as chi2, count(*) - 1 as df from (select {e}, count(*) as n, count(*) filter (where net_c + tax_c <> due_c) as k from ar group by {e}), t" for c, e in _THIRDS.items())
    + f") select col, round(chi2, 4) as chi2, df, round(exp(-chi2 / 2), {DIGITS}) as p from x")
def _(spark, d):
    """Columns of three values, for which the tail is known in closed form."""
    df = carriers.ar_lineitem(spark, d).select(*SHORT.columns, *(F.expr(e).alias(c) for c, e in _THIRDS.items()))
    got = _chi2(df, SHORT, list(_THIRDS), Config(setting="dirty"))
    return got.select("col", F.round("chi2", 4).alias("chi2"), "df", F.round(independence.tail("chi2", "df"), DIGITS).alias("p"))


# ---- measures --------------------------------------------------------------------------------------------------------

_PAIRS = (("n_name", "r_name"), ("p_brand", "p_type"), ("c_nationkey", "c_mktsegment"), ("l_returnflag", "l_linestatus"), ("l_partkey", "p_brand"))
_MEASURE_SQL = {
    "chi": "case when least(Kx, Ky) > 1 then sqrt(greatest(N * (phi - 1), 0) / (N * (least(Kx, Ky) - 1))) else 1 end",
    "mi": "hx + hy - hxy", "fi": "case when Ky = 1 then 1 else (hx + hy - hxy) / hy end",
    "smi": "log2(N + Kx * Ky) - lx1 / (N + Kx * Ky) + log2(N + Kx * Ky) - ly1 / (N + Kx * Ky) - log2(N + Kx * Ky) + lxy1 / (N + Kx * Ky)",
    "rho": "Kx / Kxy", "g1": "1 - viol / (N * N)", "g1s": "1 - (hxy - hx)", "g1sp": "greatest(1 - (hxy - hx), 0)", "g2": "pure / N", "g3": "best / N",
    "g3n": "case when N > Kx then greatest((best - Kx) / (N - Kx), 0) else 0 end", "pdep": "dep / N",
    "mu": "case when N <= Kx then 0 when Ky = 1 then 1 else greatest(1 - (1 - dep / N) / (1 - sqy / (N * N)) * (N - 1) / (N - Kx), 0) end",
    "tau": "case when Ky = 1 then 1 else (dep / N - sqy / (N * N)) / (1 - sqy / (N * N)) end",
}


def _sql_measure(name: str) -> str:
    parts = []
    for i, (x, y) in enumerate(_PAIRS):
        parts.append(
            f"select '{x}->{y}' as cand, s.*, (select sum(log2(nx + Ky) * (nx + Ky)) from x{i}) as lx1, (select sum(log2(ny + Kx) * (ny + Kx)) from y{i}) as ly1 from ("
            f"select (select cast(sum(n) as double) from c{i}) as N, (select cast(count(*) as double) from x{i}) as Kx, (select cast(count(*) as double) from y{i}) as Ky, (select cast(count(*) as double) from c{i}) as Kxy, "
            f"(select log2(sum(nx)) - sum(nx * log2(nx)) / sum(nx) from x{i}) as hx, (select log2(sum(ny)) - sum(ny * log2(ny)) / sum(ny) from y{i}) as hy, (select log2(sum(n)) - sum(n * log2(n)) / sum(n) from c{i}) as hxy, "
            f"(select cast(sum(best) as double) from x{i}) as best, (select cast(sum(nx * nx - sq) as double) from x{i}) as viol, (select sum(sq * 1.0 / nx) from x{i}) as dep, (select cast(sum(case when ys = 1 then nx else 0 end) as double) from x{i}) as pure, "
            f"(select cast(sum(ny * ny) as double) from y{i}) as sqy, (select sum(n * n * 1.0 / (cast(nx as double) * ny)) from c{i} join x{i} using (x) join y{i} using (y)) as phi, (select sum((n + 1) * log2(n + 1)) from c{i}) as lxy1) s")
    tables = ", ".join(f"c{i} as (select {x} as x, {y} as y, count(*) as n from wide group by 1, 2), x{i} as (select x, sum(n) as nx, max(n) as best, sum(n * n) as sq, count(*) as ys from c{i} group by 1), y{i} as (select y, sum(n) as ny from c{i} group by 1)" for i, (x, y) in enumerate(_PAIRS))
    return f"with {WIDE}, {tables} select cand, round(cast({_MEASURE_SQL[name]} as double), {DIGITS}) as {name} from ({' union all '.join(parts)})"


def _pair_counts(spark, d) -> DataFrame:
    return pair_counts(carriers.wide(spark, d), [(f"{x}->{y}", (x,), y) for x, y in _PAIRS])


for _name in MEASURES:
    query(f"measure_{_name}", _sql_measure(_name))(lambda spark, d, name=_name: rounded(measures(_pair_counts(spark, d)).select("cand", F.col(name).cast("double").alias(name)), name))
def _sql_reliable(name: str) -> str:
    parts, tables = [], []
    lg = lambda x: f"lgamma(cast({x} as double) + 1)"
    for i, (x, y) in enumerate(_PAIRS):
        tables.append(f"c{i} as (select {x} as x, {y} as y, count(*) as n from wide group by 1, 2), x{i} as (select sum(n) as a from c{i} group by x), y{i} as (select sum(n) as b from c{i} group by y), "
                      f"s{i} as (select cast(a as bigint) as a, ka, cast(b as bigint) as b, kb, (select cast(sum(n) as bigint) from c{i}) as n from (select a, count(*) as ka from x{i} group by 1), (select b, count(*) as kb from y{i} group by 1)), "
                      f"k{i} as (select *, unnest(range(greatest(1, a + b - n), least(a, b) + 1)) as k from s{i}), "
                      f"e{i} as (select sum(ka * kb * (k / n) * log2(cast(n as double) * k / (cast(a as double) * b)) * exp({lg('a')} + {lg('b')} + {lg('n - a')} + {lg('n - b')} - {lg('n')} - {lg('k')} - {lg('a - k')} - {lg('b - k')} - {lg('n - a - b + k')})) as e from k{i})")
        h = lambda t, c: f"(select log2(sum({c})) - sum({c} * log2({c})) / sum({c}) from {t})"
        parts.append(f"select '{x}->{y}' as cand, {h(f'x{i}', 'a')} as hx, {h(f'y{i}', 'b')} as hy, {h(f'c{i}', 'n')} as hxy, (select count(*) from y{i}) as ky, (select e from e{i}) as e")
    score = "greatest(fi - ch, 0)" if name == "rfi" else "case when ch >= 1 then 0 else greatest((fi - ch) / (1 - ch), 0) end"
    return (f"with {WIDE}, {', '.join(tables)}, m as ({' union all '.join(parts)}), f as (select cand, case when ky = 1 then 1 else (hx + hy - hxy) / hy end as fi, case when hy > 0 then e / hy else 1 end as ch from m) "
            f"select cand, round({score}, {DIGITS}) as {name} from f")


for _name in ("rfi", "rfi_norm"):
    query(f"measure_{_name}", _sql_reliable(_name))(lambda spark, d, name=_name: rounded(reliable_information(_pair_counts(spark, d)).select("cand", name), name))


@query("measure_explanation")
def _(spark, d):
    df = carriers.ar_lineitem(spark, d)
    return rounded(explanations(df, (NET, TOTAL, SHORT, COINCIDENCE)), "conciseness", "concentration", "score")


# ---- accuracy measures over a labelled pool of all pairs ------------------------------------------------------------

_GOLD = (("n_name", "r_name"),)


def _scores(spark, d) -> DataFrame:
    """Pairs of category columns, scored by g3 and by the number of inputs, labelled by the schema's dependency."""
    r = generate.dependency_ratios(carriers.wide(spark, d), FD_COLUMNS)
    label = reduce(lambda a, b: a | b, [(F.col("x") == x) & (F.col("y") == y) for x, y in _GOLD])
    g3 = F.round(F.col("hits") / F.col("n_rows"), 2)
    rows = F.array(F.struct(F.lit("g3").alias("method"), g3.alias("score")), F.struct(F.lit("inputs").alias("method"), (1 / F.col("distinct_x")).alias("score")))
    return r.select(label.alias("label"), F.inline(rows))


_SCORES_SQL = (f"scores as (select 'g3' as method, round(hits / n_rows, 2) as score, x = 'n_name' and y = 'r_name' as label from ({_sql_ratios(FD_COLUMNS)}) union all "
               f"select 'inputs', 1 / distinct_x, x = 'n_name' and y = 'r_name' from ({_sql_ratios(FD_COLUMNS)}))")
_CURVE_SQL = (f"{_SCORES_SQL}, pts as (select method, score, count(*) filter (where label) as p, count(*) filter (where not label) as q from scores group by 1, 2), "
              "cur as (select method, score, sum(p) over w as tp, sum(q) over w as fp, sum(p) over (partition by method) as pos from pts window w as (partition by method order by score desc)), "
              "pr as (select method, score, tp, fp, tp / (tp + fp) as prec, tp / pos as rec from cur), "
              "st as (select *, coalesce(lag(rec) over v, 0) as r0, coalesce(lag(prec) over v, prec) as p0 from pr window v as (partition by method order by score desc))")


@query("pr_curve", f"with {_CURVE_SQL} select method, round(score, {DIGITS}) as score, cast(tp as bigint) as tp, cast(fp as bigint) as fp, round(prec, {DIGITS}) as prec, round(rec, {DIGITS}) as rec from pr")
def _(spark, d):
    c = metrics.pr_curve(_scores(spark, d))
    return rounded(c.select("method", "score", "tp", "fp", F.col("precision").alias("prec"), F.col("recall").alias("rec")), "score", "prec", "rec")


for _rule, _height in (("step", "prec"), ("trapezoid", "(prec + p0) / 2")):
    query(f"pr_auc_{_rule}", f"with {_CURVE_SQL} select method, round(sum((rec - r0) * {_height}), {DIGITS}) as pr_auc from st group by 1")(
        lambda spark, d, rule=_rule: rounded(metrics.pr_auc(_scores(spark, d), rule), "pr_auc"))

_PRF_SQL = ("cast(count(*) filter (where yes and label) as bigint) as tp, count(*) filter (where yes and not label) as fp, count(*) filter (where not yes and label) as fn")


@query("prf_at_eta", f"with {_SCORES_SQL} select method, {_PRF_SQL} from (select *, score >= 0.5 as yes from scores) group by 1")
def _(spark, d):
    return metrics.prf(_scores(spark, d), 0.5).select("method", "tp", "fp", "fn")


@query("eta_sweep", f"with {_SCORES_SQL} select eta, method, {_PRF_SQL} from (select *, score >= 1 - eta as yes from scores, (select unnest([0.1, 0.3, 0.5, 0.7, 0.9]) as eta)) group by 1, 2")
def _(spark, d):
    s = _scores(spark, d).withColumn("eta", F.explode(F.array(*(F.lit(e) for e in (0.1, 0.3, 0.5, 0.7, 0.9)))))
    yes = F.col("score") >= (1 - F.col("eta"))
    return s.groupBy("eta", "method").agg(F.count_if(yes & F.col("label")).alias("tp"), F.count_if(yes & ~F.col("label")).alias("fp"), F.count_if(~yes & F.col("label")).alias("fn"))


@query("best_f1", f"with {_CURVE_SQL}, f as (select *, 2 * tp / (tp + fp + pos) as f1 from cur) select method, round(max(f1), {DIGITS}) as f1 from f group by 1")
def _(spark, d):
    return rounded(metrics.best_f1(_scores(spark, d)).select("method", "f1"), "f1")


# ---- experiment workloads --------------------------------------------------------------------------------------------

_NOISY = ("net_c", "tax_c", "gross_c")
_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "ext_c")


def _sql_noise(rate: int) -> str:
    key = ", ".join(f"cast({k} as varchar)" for k in _KEYS)
    cell = lambda i, c: f"{c} + case when pick and which = {i} then amount else 0 end"
    inner = f"select *, {sql_hash(key, repr('pick42'))} % 1000 < {rate} as pick, {sql_hash(key, repr('col42'))} % 3 as which, {sql_hash(key, repr('amt42'))} % 9973 + 1 as amount from ar"
    return f"select {rate} as rate, count(*) filter (where {cell(0, 'net_c')} + {cell(1, 'tax_c')} = {cell(2, 'gross_c')}) as hits, count(*) as n_rows from ({inner})"


@query("noise_sweep", f"with {AR} " + " union all ".join(_sql_noise(r) for r in (20, 40, 60, 80, 100)))
def _(spark, d):
    df, parts = carriers.ar_lineitem(spark, d), []
    for rate in (20, 40, 60, 80, 100):
        parts.append(satisfy.satisfaction(carriers.noisy(df, rate / 1000, _NOISY, _KEYS), [GROSS]).select(F.lit(rate).alias("rate"), "hits", "n_rows"))
    return reduce(DataFrame.unionByName, parts)


def _sql_size(n: int) -> str:
    cols = ("l_orderkey", "l_linenumber", "l_partkey", "ext_c")
    key = f"md5(concat_ws('|', {', '.join(f'cast({c} as varchar)' for c in cols)}))"
    return f"s{n} as (select * from ar order by {key}, {', '.join(cols)} limit {n})"


_SIZES = (2000, 4000, 6000, 8000, 10000)


@query("size_sweep", f"with {AR}, {', '.join(map(_sql_size, _SIZES))} " + " union all ".join(f"select {n} as size, rule, bound from ({_sql_bound([NET, DUE], f's{n}')})" for n in _SIZES))
def _(spark, d):
    df, parts = carriers.ar_lineitem(spark, d), []
    for n in _SIZES:
        view = carriers.sized(df, n, ("l_orderkey", "l_linenumber", "l_partkey", "ext_c"))
        parts.append(_bounds(view, [NET, DUE], Config()).withColumn("size", F.lit(n)))
    return reduce(DataFrame.unionByName, parts)


def _summed(scores: DataFrame) -> DataFrame:
    return rounded(metrics.summary(scores), "pr_auc", "precision", "recall", "f1", "gain")


for _kind in ("AR", "ST", "FD"):
    for _setting in ("clean", "dirty"):
        query(f"quality_{_kind.lower()}_{_setting}")(lambda spark, d, k=_kind, s=_setting: _summed(pools.quality(spark, d, k, s)))


@query("quality_curves")
def _(spark, d):
    """Points of the precision-recall curves of the framework and of the published best baselines, noisy arithmetic rules."""
    s = pools.quality(spark, d, "AR", "dirty").where("method in ('framework', 'mi', 'tau')")
    c = metrics.pr_curve(s)
    return rounded(c.select("method", "score", "tp", "fp", "precision", "recall"), "score", "precision", "recall")


@query("arity_split")
def _(spark, d):
    """PR-AUC by the number of columns: three and four of arithmetic rules, two and three of string rules, clean and noisy."""
    parts = []
    for kind, setting in (("AR", "clean"), ("AR", "dirty"), ("ST", "clean"), ("ST", "dirty")):
        s = pools.quality(spark, d, kind, setting).withColumn("method", F.concat_ws("/", F.lit(kind), F.lit(setting), (F.col("arity") + 1).cast("string"), "method"))
        parts.append(metrics.pr_auc(s))
    by = F.split("method", "/")
    return rounded(reduce(DataFrame.unionByName, parts).select(by[0].alias("kind"), by[1].alias("setting"), by[2].cast("int").alias("columns"), by[3].alias("method"), "pr_auc"), "pr_auc")


_SMALL = 30  # negatives of the pools that are run many times


def _runs(spark, d, kind: str, setting: str, runs: dict[str, dict], **pool_) -> DataFrame:
    """(method, cand_id, arity, score, label) of the framework with each run's settings on one pool."""
    p = pools.pool(spark, d, kind, setting, most=_SMALL, **pool_)
    p = pools.Pool(p.df.persist(), p.items, p.keys)
    with pools.interpreted(spark):
        rows = [r for name, change in runs.items() for r in pools.framework_scores(p, pools.settings(p, setting, **change), name).collect()]
    p.df.unpersist()
    return spark.createDataFrame(rows, "method string, cand_id string, arity int, score double, label boolean")


_WITHOUT = {"framework": {}, "without minimality": {"use_minimality": False}, "without independence": {"use_independence": False}, "violations dropped": {"dirty_mode": "drop_violations"},
            "Bonferroni": {"multiplicity": "bonferroni"}, "Benjamini-Hochberg": {"multiplicity": "benjamini_hochberg"}}


@query("ablation_minimality")
def _(spark, d):
    """Precision and recall of noisy arithmetic rules with and without the Minimality Test, at the default threshold."""
    s = _runs(spark, d, "AR", "dirty", {k: _WITHOUT[k] for k in ("framework", "without minimality")})
    return rounded(metrics.prf(s, 0.5).join(metrics.pr_auc(s), "method"), "precision", "recall", "f1", "pr_auc")


@query("ablation_independence")
def _(spark, d):
    """The same with and without the Independence Test, with violating rows dropped instead, and with corrections for several tests."""
    s = _runs(spark, d, "AR", "dirty", {k: v for k, v in _WITHOUT.items() if k != "without minimality"})
    return rounded(metrics.prf(s, 0.5).join(metrics.pr_auc(s), "method"), "precision", "recall", "f1", "pr_auc")


_OFF = {"all": {}, "no bound": {"use_bound": False}, "no core": {"use_core": False}, "no early stop": {"use_wilson": False}, "none": {"use_bound": False, "use_core": False, "use_wilson": False}}


@query("ablation_optimizations")
def _(spark, d):
    """Time per candidate, PR-AUC and shares of candidates with each optimization off, clean and noisy arithmetic rules."""
    parts = []
    for setting in ("clean", "dirty"):
        p = pools.pool(spark, d, "AR", setting, most=_SMALL)
        p = pools.Pool(p.df.persist(), p.items, p.keys)
        p.df.count()
        labels = spark.createDataFrame([(r.cand_id, y) for r, y in p.items], "cand_id string, label boolean")
        for name, change in _OFF.items():
            cfg, out = pools.settings(p, setting, **change), {}
            with pools.interpreted(spark):
                (_, ms), = pools.timed({name: lambda c=cfg, o=out: o.update(rows=framework.verify(p.df, p.rels, c).collect())}, len(p.items))
            v = spark.createDataFrame(out["rows"], VERDICT)
            auc = metrics.pr_auc(framework.reliability(v).join(labels, "cand_id").select(F.lit(name).alias("method"), F.col("reliability").alias("score"), "label"))
            parts.append(auc.join(metrics.optimization_counters(v), F.lit(True)).select(F.lit(setting).alias("setting"), "method", F.lit(ms).alias("ms"), "pr_auc", "candidates", "bound_rejected", "early_stopped"))
        p.df.unpersist()
    return rounded(reduce(DataFrame.unionByName, parts), "ms", "pr_auc", "bound_rejected", "early_stopped")


@query("core_applicability")
def _(spark, d):
    """Share of trials of the true arithmetic rules that the core shortcut decides, by arity."""
    p = pools.pool(spark, d, "AR", "clean", most=1)
    rows = []
    for r in p.rels:
        masks, checks = (1 << len(r.columns)) - 1, bounds.core_checks(r, r.columns, True)
        rows.append((r.arity, len(checks) / masks, sum(sure for _, sure in checks.values()) / masks))
    return rounded(spark.createDataFrame(rows, "arity int, met double, decided double").groupBy("arity").agg(F.avg("met").alias("met"), F.avg("decided").alias("decided"), F.count("*").alias("rules")), "met", "decided")


@query("quality_by_threshold")
def _(spark, d):
    """Precision, recall and F1 of noisy arithmetic rules for thresholds of the survival score."""
    s = _runs(spark, d, "AR", "dirty", {"framework": {"use_bound": False, "use_wilson": False}})
    parts = [metrics.prf(s, 1 - eta).select(F.lit(eta).alias("eta"), "precision", "recall", "f1") for eta in (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)]
    return rounded(reduce(DataFrame.unionByName, parts), "precision", "recall", "f1")


@query("quality_by_noise")
def _(spark, d):
    """Precision, recall and F1 of arithmetic rules for shares of noisy rows."""
    parts = []
    for rate in (0.02, 0.04, 0.06, 0.08, 0.1):
        s = _runs(spark, d, "AR", "dirty", {"framework": {}}, rate=rate)
        parts.append(metrics.prf(s, 0.5).select(F.lit(rate).alias("rate"), "precision", "recall", "f1"))
    return rounded(reduce(DataFrame.unionByName, parts), "precision", "recall", "f1")


_GOLD_TABLES = {
    "nation": ("n_nationkey", ("n_name", "n_regionkey")), "customer": ("c_custkey", ("c_name", "c_nationkey", "c_mktsegment")), "supplier": ("s_suppkey", ("s_name", "s_nationkey")),
    "part": ("p_partkey", ("p_name", "p_brand", "p_type", "p_size")), "orders": ("o_orderkey", ("o_custkey", "o_orderstatus", "o_orderpriority")), "region": ("r_regionkey", ("r_name",)),
    "pages": ("page_id", ("url",)), "labels": ("doc_id", ("quality", "toxic")), "events": ("event_id", ("user_id", "event_type"))}


def _gold(spark, d, mode: str) -> DataFrame:
    rows = []
    for name, (key, columns) in _GOLD_TABLES.items():
        df = load(spark, d, name).select(key, *columns)
        twice = {"region": 1, "nation": 1}.get(name, 1)
        rels = [Relation("FD", (x,), y) for x, y in permutations((key, *columns), 2)]
        cfg = Config(setting="dirty", tau=0.0, use_independence=False, use_minimality=False, n_max=1000 * twice, fd_mode=mode)
        got = {r["cand_id"]: r["reliability"] for r in framework.reliability(framework.verify(df, rels, cfg)).collect()}
        hits = {r["cand_id"]: r["hits"] / max(1, r["n_rows"]) for r in satisfy.satisfaction(df, rels).collect()}
        # names that stand for a key determine what the key does
        keys = {key, *(c for c in columns if c in ("n_name", "c_name", "s_name", "r_name", "url"))}
        for r in rels:
            true = r.inputs[0] in keys
            rows += [(f"framework, {mode}", got[r.cand_id], true), ("g3", hits[r.cand_id], true)]
    return spark.createDataFrame(rows, "method string, score double, label boolean")


for _mode in ("recheck", "induced"):
    query(f"labelled_dependencies_{_mode}")(lambda spark, d, mode=_mode: _summed(_gold(spark, d, mode)))


@query("rules_set_difference", f"with {AR} select '{SHORT.text}' as rule from ar having count(*) filter (where net_c + tax_c = due_c) * 5 >= 4 * count(*) and count(*) filter (where net_c + tax_c = due_c) < count(*)")
def _(spark, d):
    """Rules accurate enough in the dirty setting and not in the clean one."""
    sat = satisfy.satisfaction(carriers.ar_lineitem(spark, d), [SHORT, GROSS, DUE])
    return satisfy.accurate(sat, 0.8).select("rule").exceptAll(satisfy.accurate(sat, 1.0).select("rule"))


@query("topk_rules_per_output", f"select y as output, x as input, rank from (select *, row_number() over (partition by y order by hits desc, x) as rank from ({_sql_ratios(FD_COLUMNS)})) where rank <= 2")
def _(spark, d):
    r = generate.dependency_ratios(carriers.wide(spark, d), FD_COLUMNS)
    by = Window.partitionBy("y").orderBy(F.desc("hits"), "x")
    return r.withColumn("rank", F.row_number().over(by).cast("bigint")).where("rank <= 2").select(F.col("y").alias("output"), F.col("x").alias("input"), "rank")


def _timed_pool(spark, d, kind: str, setting: str, rows: int | None = None, only: Sequence[str] = ()) -> list[tuple[str, float]]:
    p = pools.pool(spark, d, kind, setting, most=_SMALL // 2, rows=rows)
    p = pools.Pool(p.df.persist(), p.items, p.keys)
    p.df.count()
    run = {"framework": lambda: framework.verify(p.df, p.rels, pools.settings(p, setting)).collect(), "measures": lambda: pools.baseline_scores(p, setting, rfi=False, explain=False).collect(),
           "reliable information": lambda: pools.baseline_scores(p, setting, explain=False).collect(), "explanation": lambda: explanations(p.df, p.rels, setting == "clean").collect()}
    with pools.interpreted(spark):
        out = pools.timed({k: f for k, f in run.items() if not only or k in only}, len(p.items))
    p.df.unpersist()
    return out


@query("timing_percentiles")
def _(spark, d):
    """Milliseconds per candidate by family and method over batches of candidates, generation left out."""
    rows = [(kind, setting, name, ms) for kind in ("AR", "ST", "FD") for setting in ("clean", "dirty") for name, ms in _timed_pool(spark, d, kind, setting)]
    return rounded(spark.createDataFrame(rows, "kind string, setting string, method string, ms double"), "ms")


@query("timing_by_size")
def _(spark, d):
    """Milliseconds per candidate of arithmetic rules on 2,000 to 10,000 rows."""
    rows = [(n, name, ms) for n in _SIZES for name, ms in _timed_pool(spark, d, "AR", "clean", n, ("framework", "measures"))]
    return rounded(spark.createDataFrame(rows, "rows int, method string, ms double"), "ms")


# ---- discovery -------------------------------------------------------------------------------------------------------

def _cached(df: DataFrame, run: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """A mining run reads its table many times; its verdicts are a table of their own."""
    held = df.persist()
    try:
        return run(held)
    finally:
        held.unpersist()


@query("discover_ar")
def _(spark, d):
    df = carriers.ar_lineitem(spark, d).select("ext_c", "disc_c", "net_c", "tax_c", "gross_c", "qty", "unit_c", "list_c", "sur_c", "due_c")
    return _cached(df, lambda c: framework.discover(c, Config(), kinds=("AR",)))


@query("discover_st")
def _(spark, d):
    return _cached(carriers.st_part(spark, d), lambda c: framework.discover(c, Config(exclude=("p_partkey",)), kinds=("ST",)))


@query("discover_fd")
def _(spark, d):
    df = carriers.wide(spark, d).select("n_name", "r_name", "p_brand", "c_mktsegment", "l_returnflag")
    return _cached(df, lambda c: framework.discover(c, Config(), kinds=("FD",), categories=c.columns))


@query("discover_dirty_ar")
def _(spark, d):
    df = carriers.ar_lineitem(spark, d).select("net_c", "tax_c", "gross_c", "sur_c", "due_c", "qty")
    return _cached(df, lambda c: framework.discover(c, Config(setting="dirty"), kinds=("AR",)))


@query("rules_as_constraints")
def _(spark, d):
    return check_constraints(QUERIES["discover_st"](spark, d))


@query("sql_surface", _sql_sat("", "nation", [(NATION, "n_name = 'NATION_' || n_nationkey"), (REGION_MOD, "n_regionkey = n_nationkey % 5")]) + " union all " + _sql_sat("", "customer", [(CUSTOMER, "c_name = 'Customer#' || lpad(cast(c_custkey as varchar), 9, '0')")]))
def _(spark, d):
    """Rules as a view and as SQL templates over views of the tables."""
    parts = []
    for name, rels in (("nation", (NATION, REGION_MOD)), ("customer", (CUSTOMER,))):
        relations_view(spark, rels)
        load(spark, d, name).createOrReplaceTempView(f"rules_{name}")
        parts.append(spark.sql(satisfaction_template(rels, f"rules_{name}")).join(spark.table("relations").select("rule"), "rule"))
    return reduce(DataFrame.unionByName, parts).select("rule", F.col("hits").cast("bigint").alias("hits"), "n_rows")


@query("independence_early_exit")
def _(spark, d):
    """One column at a time: a rule rejected by a column is not tested on the rest."""
    df = carriers.ar_lineitem(spark, d).select(*DUE.columns, "net_c", "tax_c", "qty", "dp")
    got = independence.independent(df, [SHORT, DUE], Config(setting="dirty", it_columns=1))
    return spark.createDataFrame([(r.text, got[r.cand_id][0], got[r.cand_id][1]) for r in (SHORT, DUE)], "rule string, independent boolean, col string")


# ---- streams ---------------------------------------------------------------------------------------------------------

_PROPS = Relation("ST", ("k",), "seen", ("concat", ("lit", '{"k": '), "k", ("lit", "}")))


def _events(spark, d) -> DataFrame:
    e = load(spark, d, "events").withColumn("k", F.get_json_object("props", "$.k"))
    return e.withColumn("seen", F.when(hash_int(F.col("event_id"), F.lit("drift")) % 20 == 0, F.lit("{}")).otherwise(F.col("props")))


_EV = (f"ev as (select event_id, user_id, ts, json_extract_string(props, '$.k') as k, case when {sql_hash('event_id', repr('drift'))} % 20 = 0 then '{{}}' else props end as seen from events), "
       "ok as (select *, seen = '{\"k\": ' || k || '}' as ok from ev)")
_RULE = _PROPS.text.replace("'", "''")


@query("rule_monitor_tumbling", f"with {_EV} select '{_RULE}' as rule, date_trunc('day', ts) as window_start, count(*) filter (where ok) as hits, count(*) as n_rows from ok group by 2")
def _(spark, d):
    w = monitor.windowed(_events(spark, d), [_PROPS], "1 day", late=None)
    return w.withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@query("rule_monitor_sliding", f"with {_EV} select '{_RULE}' as rule, s as window_start, count(*) filter (where ok) as hits, count(*) as n_rows from (select *, unnest([time_bucket(interval '12 hours', ts), time_bucket(interval '12 hours', ts) - interval '12 hours']) as s from ok) group by 2")
def _(spark, d):
    w = monitor.windowed(_events(spark, d), [_PROPS], "1 day", "12 hours", late=None)
    return w.withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@query("rule_monitor_session", f"with {_EV}, g as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval '6 hours' then 0 else 1 end as fresh from ok), "
       f"s as (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as sid from (select * from g)) select '{_RULE}' as rule, user_id, min(ts) as session_start, count(*) filter (where ok) as hits, count(*) as n_rows from s group by user_id, sid")
def _(spark, d):
    w = monitor.sessions(_events(spark, d), [_PROPS], "6 hours", "user_id", late=None)
    return w.withColumn("session_start", F.col("session_start").cast("timestamp_ntz"))


@query("asof_previous_event", "select event_id, lag(event_id) over (partition by user_id order by ts, event_id) as previous_id from events")
def _(spark, d):
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.lag("event_id").over(by).alias("previous_id"))
