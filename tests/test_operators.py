import pytest
from pyspark.sql import functions as F

from relmine.bench import carriers, metrics
from relmine.functions.measures import measures, pair_counts
from relmine.model import Config, Relation
from relmine.operators import bounds, generate, independence, minimality, perturb, satisfy
from relmine.plans import framework
from relmine.sources import tables

PRODUCT = Relation("AR", ("a", "b"), "c", ("*", "a", "b"))
SUM = Relation("AR", ("a", "b", "d"), "e", ("+", ("+", "a", "b"), "d"))


@pytest.fixture(scope="module")
def table(spark):
    rows = [(i % 5 + 1, i % 3, (i % 5 + 1) * (i % 3), i % 4, i % 5 + 1 + i % 3 + i % 4, f"k{i % 5 + 1}", f"k{i % 5 + 1}-{i % 3}") for i in range(20)]
    return spark.createDataFrame(rows, "a bigint, b bigint, c bigint, d bigint, e bigint, s string, t string").cache()


def test_satisfaction_nulls_and_division(spark):
    df = spark.createDataFrame([(6, 2, 3), (6, 0, 3), (None, None, None), (6, None, 3), (7, 2, 3)], "a bigint, b bigint, c bigint")
    rel = Relation("AR", ("a", "b"), "c", ("/", "a", "b"))
    got = satisfy.satisfaction(df, [rel]).first()
    assert (got["hits"], got["n_rows"]) == (1, 4)
    assert satisfy.satisfaction(df, [rel], Config(null_policy="violate")).first()["n_rows"] == 5
    assert satisfy.satisfaction(df, [rel], Config(null_policy="match")).first()["hits"] == 2
    assert satisfy.violations(df, rel).count() == 3


def test_accuracy_in_whole_numbers():
    assert satisfy.is_accurate(8, 10, 0.8) and not satisfy.is_accurate(7, 10, 0.8)
    assert satisfy.is_accurate(10, 10, 1.0) and not satisfy.is_accurate(9, 10, 1.0)


def test_bound_below_tight_below_exact(table):
    for rel in (PRODUCT, SUM):
        b = bounds.bounds(table, [rel], Config())[rel.cand_id]
        t = bounds.bounds(table, [rel], Config(tight=True))[rel.cand_id]
        s = perturb.exact_score(table, rel, Config()).first()["score"]
        k = len(rel.columns)
        assert b <= t + 1e-12 and t <= s + 1e-12 and s >= 1 / (2**k - 1)
    assert bounds.closed_sum_score(table, SUM) == pytest.approx(perturb.exact_score(table, SUM, Config()).first()["score"])
    b, t = (bounds.bounds(table, [PRODUCT], Config(tight=x))[PRODUCT.cand_id] for x in (False, True))
    assert t == pytest.approx(perturb.exact_score(table, PRODUCT, Config()).first()["score"])


def test_sampled_score_near_exact(table):
    exact = perturb.exact_score(table, SUM, Config()).first()["score"]
    got = perturb.score(table, [SUM], Config(n_max=2000, use_wilson=False)).first()
    assert got["trials"] >= 2000
    assert abs(got["score"] - exact) < 4 * (exact * (1 - exact) / got["trials"]) ** 0.5 + 0.02


def test_staged_and_one_shot_agree(table):
    cfg = Config(n_max=1600)
    one = {r["cand_id"]: tuple(r) for r in perturb.score(table, [PRODUCT, SUM], cfg).collect()}
    two = {r["cand_id"]: tuple(r) for r in perturb.score(table, [PRODUCT, SUM], cfg.but(mode="staged")).collect()}
    assert one == two


def test_core_guard_with_absorbing_zero(spark):
    df = spark.createDataFrame([(i % 4, i % 3, i % 2, (i % 4 + i % 3) * (i % 2)) for i in range(24)], "a bigint, b bigint, c bigint, y bigint")
    rel = Relation("AR", ("a", "b", "c"), "y", ("*", ("+", "a", "b"), "c"))
    bank = perturb.trial_bank(df, rel.columns, 400).cache()
    n = lambda **k: perturb.outcomes(bank, rel, Config(**k)).agg(F.sum("survived")).first()[0]
    assert n(use_core=True, core_check="guarded") == n(use_core=False)
    assert n(use_core=True, core_check="paper") < n(use_core=False)


def test_key_input_under_both_readings(spark):
    df = spark.createDataFrame([(i, "xyz"[i % 3]) for i in range(30)], "k bigint, v string")
    rel = Relation("FD", ("k",), "v")
    assert bounds.dependency_score(df, rel, "recheck") == pytest.approx(1.0)
    induced = bounds.dependency_score(df, rel, "induced")
    assert induced == pytest.approx(perturb.exact_score(df, rel, Config(fd_mode="induced")).first()["score"])
    assert perturb.exact_score(df, rel, Config(fd_mode="recheck")).first()["score"] == pytest.approx(1.0)


def test_dependency_score_by_enumeration(spark):
    df = spark.createDataFrame([(x, x % 2) for x in (0, 0, 1, 1, 2, 3, 4)], "x bigint, y bigint")
    rel = Relation("FD", ("x",), "y")
    for mode in ("recheck", "induced"):
        assert bounds.dependency_score(df, rel, mode) == pytest.approx(perturb.exact_score(df, rel, Config(fd_mode=mode)).first()["score"])


def test_minimality(spark):
    small, big = Relation("AR", ("a", "b"), "e", ("+", "a", "b")), SUM
    twin = Relation("AR", ("a", "d"), "e", ("-", "a", "d"))
    f = lambda *r: minimality.frame(spark, r)
    assert minimality.minimal(f(big, twin), f(small)).count() == 1
    assert minimality.minimal(f(small, twin), f(small, twin)).count() == 2
    assert not minimality.is_minimal(big, [small]) and minimality.is_minimal(small, [big])
    assert minimality.open_input_sets([frozenset("ab"), frozenset("abd")], "e", [small]) == [frozenset("ab")]


def test_independence(spark):
    rows = [(i, i + (5 if i % 4 == 0 else 0), i % 4 == 0, i % 2, 1) for i in range(200)]
    df = spark.createDataFrame(rows, "a bigint, b bigint, cause boolean, noise bigint, one bigint")
    from relmine.functions.expressions import opt

    rel = Relation("AR", ("a",), "b", ("affine", "a", opt(1), opt(0)))
    passed, col, chi, p = independence.independent(df, [rel], Config(setting="dirty", exclude=("noise",)))[rel.cand_id]
    assert not passed and col == "cause" and chi == pytest.approx(200)
    exact = Relation("AR", ("a",), "one", ("affine", "a", opt(0), opt(1)))
    assert independence.independent(df, [exact], Config(setting="dirty"))[exact.cand_id][0]


def test_generators_find_the_rules(table):
    two = {r.text for r in generate.arithmetic(table, 2, Config(exclude=("e",)))}
    assert "(a * b) = c" in two
    three = generate.arithmetic(table, 3, Config(exclude=("c",)))
    assert any(set(r.columns) == {"a", "b", "d", "e"} for r in three)
    st = {r.text for r in generate.extractions(table, Config())}
    assert "concat('k', a) = s" in st and "token(t, '-', 1) = s" in st
    fd = generate.dependencies(table, ["a", "s", "t"], Config())
    assert {(r.inputs[0], r.output) for r in fd} == {("a", "s"), ("s", "a"), ("t", "a"), ("t", "s")}


def test_discover_prunes_supersets(spark):
    rows = [(i * 7 % 23, i * 5 % 19, i * 7 % 23 + i * 5 % 19, i * 11 % 13) for i in range(60)]
    df = spark.createDataFrame(rows, "p bigint, q bigint, r bigint, z bigint")
    got = framework.discover(df, Config(max_level=3, n_max=400), kinds=("AR",)).collect()
    assert {r["rule"] for r in got if r["reliable"]} == {"(p + q) = r", "(r - p) = q", "(r - q) = p"}
    assert framework.collapse_isomerous(framework.discover(df, Config(max_level=2, n_max=400), kinds=("AR",))).count() == 1


def test_incomplete_rule_is_no_pruner(spark):
    rows = [(i * 7 % 23, 9 if i % 7 == 0 else 0, i * 7 % 23 + (9 if i % 7 == 0 else 0), i * 3 % 11) for i in range(210)]
    df = spark.createDataFrame(rows, "g bigint, s bigint, y bigint, w bigint")
    from relmine.functions.expressions import opt

    short, full = Relation("AR", ("g",), "y", ("affine", "g", opt(1), opt(0))), Relation("AR", ("g", "s"), "y", ("+", "g", "s"))
    got = {r["rule"]: r for r in framework.verify(df, [short, full], Config(setting="dirty", n_max=400)).collect()}
    assert got[short.text]["it_pass"] is False and got[full.text]["mt_pass"] is True
    without = {r["rule"]: r for r in framework.verify(df, [short, full], Config(setting="dirty", n_max=400, use_independence=False)).collect()}
    assert without[full.text]["mt_pass"] is False


def test_measures_by_hand(spark):
    df = spark.createDataFrame([("a", "1")] * 3 + [("a", "2")] + [("b", "2")] * 4, "x string, y string")
    m = measures(pair_counts(df, [("p", ("x",), "y")])).first()
    assert m["g3"] == pytest.approx(7 / 8) and m["rho"] == pytest.approx(2 / 3) and m["g2"] == pytest.approx(0.5)
    assert m["g1"] == pytest.approx(1 - 6 / 64) and m["pdep"] == pytest.approx((10 / 4 + 4) / 8)
    assert m["g3n"] == pytest.approx(5 / 6)
    clash = spark.createDataFrame([("a_b", "c", "1"), ("a", "b_c", "2")], "x string, z string, y string")
    assert pair_counts(clash, [("p", ("x", "z"), "y")]).select("x").distinct().count() == 2


def test_metrics(spark):
    s = spark.createDataFrame([("m", 0.9, True), ("m", 0.8, False), ("m", 0.7, True)], "method string, score double, label boolean")
    assert metrics.pr_auc(s).first()["pr_auc"] == pytest.approx(0.5 + 0.5 * 2 / 3)
    r = metrics.prf(s, 0.75).first()
    assert (r["tp"], r["fp"], r["fn"]) == (1, 1, 1)
    assert metrics.best_f1(s).first()["f1"] == pytest.approx(0.8)
    gain = spark.createDataFrame([("a", "us", 0.9), ("a", "x", 0.6), ("a", "y", 0.5)], "setting string, method string, pr_auc double")
    assert metrics.relative_gain(gain, "us").first()["gain"] == pytest.approx(0.5)


def test_noise_and_size(spark, small):
    df = carriers.ar_lineitem(spark, small)
    n = df.count()
    dirty = carriers.noisy(df, 0.1, ("net_c",), ("l_orderkey", "l_linenumber", "ext_c"))
    changed = dirty.where("net_c <> ext_c - disc_c").count()
    assert 0.05 * n < changed < 0.15 * n
    assert carriers.sized(df, 50, ("l_orderkey", "ext_c")).count() == 50
    assert carriers.sized(df.limit(30), 100, ("l_orderkey", "ext_c")).count() == 100


def test_pool_round_trip_and_corpus(spark, tmp_path):
    tables.write_pool([PRODUCT, Relation("FD", ("a",), "b")], spark, str(tmp_path / "pool"))
    assert {r.text for r in tables.read_pool(spark, str(tmp_path / "pool"))} == {PRODUCT.text, "a -> b"}
    for i in range(3):
        (tmp_path / f"t{i}.csv").write_text("x,y\n1,2\n3,4\n")
    spark.dataSource.register(tables.CorpusSource)
    got = spark.read.format("table_corpus").option("path", str(tmp_path)).option("batch", "2").load()
    assert got.count() == 6 and got.select("table_id").distinct().count() == 3


def test_scans_read_only_what_rules_need(spark, small):
    plan = carriers.ar_lineitem(spark, small).select("net_c")._jdf.queryExecution().executedPlan().toString()
    assert "l_shipdate" not in plan and "BatchEvalPython" not in plan


def test_mixed_up_changes_one_cell_of_some_rows(spark):
    from relmine.bench.carriers import mixed_up

    df = spark.createDataFrame([(i, f"t{i % 7}", i % 5, None, "only") for i in range(400)], "k long, a string, b int, c string, d string")
    after = {r["k"]: r for r in mixed_up(df, 0.1, ("a", "b", "c", "d"), ("k",)).collect()}
    changed = [sum(after[r["k"]][c] != r[c] for c in df.columns) for r in df.collect()]
    assert set(changed) == {0, 1} and 5 <= sum(changed) <= 60
    assert {r["a"] for r in after.values()} <= {f"t{i}" for i in range(7)} and {r["c"] for r in after.values()} == {None}
    assert mixed_up(df.limit(0), 0.1, ("a", "b"), ("k",)).count() == 0


def test_pools_hold_as_labelled(spark, small):
    """True candidates hold on every row of the clean table; the others are as many as the base rate says, or all there are."""
    from relmine.bench import pools
    from relmine.operators.satisfy import satisfaction

    for kind in ("AR", "ST", "FD"):
        p = pools.pool(spark, small, kind, "clean", most=80)
        got = {r["cand_id"]: (r["hits"], r["n_rows"]) for r in satisfaction(p.df, p.rels).collect()}
        yes = [r for r, y in p.items if y]
        assert yes and all(got[r.cand_id][0] == got[r.cand_id][1] > 0 for r in yes), kind
        no = [r for r, y in p.items if not y]
        assert no and all(got[r.cand_id][0] > 0 for r in no) and len(no) <= 80
        assert len({r.cand_id for r in p.rels}) == len(p.items) and not set(p.keys) & {c for r in p.rels for c in r.columns}


def test_methods_on_a_pool(spark, small):
    """The framework is ahead of every measure on arithmetic rules, and measures that see violations only are at the base rate."""
    from relmine.bench import pools

    p = pools.pool(spark, small, "AR", "clean", most=40)
    scores = pools.framework_scores(p, pools.settings(p, "clean", n_max=400)).unionByName(pools.baseline_scores(p, "clean", rfi=False))
    got = {r["method"]: r for r in metrics.summary(scores).collect()}
    base = sum(y for _, y in p.items) / len(p.items)
    assert got["g3"]["pr_auc"] == pytest.approx(base) and got["framework"]["pr_auc"] > 0.75 and got["framework"]["pr_auc"] > base
    assert set(got) >= {"framework", "chi", "mi", "explain"} and got["mi"]["gain"] is None


def test_helper_columns_meet_no_user_column(spark):
    """Rules over columns of any name: of helpers, with a slash, and with values whose product no long holds."""
    p = [(i * 7 % 23, i * 5 % 19, i * 7 % 23 + i * 5 % 19) for i in range(60)]
    for names in (("p", "q", "r"), ("row", "q", "r"), ("grp", "cells", "k"), ("_k", "_n", "_t"), ("n", "y", "x"), ("ok", "cand_id", "item"), ("a/b", "trial", "mask")):
        df = spark.createDataFrame(p, " bigint, ".join(f"`{c}`" for c in names) + " bigint")
        rel = Relation("AR", names[:2], names[2], ("+", *names[:2]))
        assert rel.isomerous(generate.arithmetic(df, 2, Config())[0]) and len(generate.arithmetic(df, 2, Config())) == 3
        got = framework.verify(df, [rel, Relation("FD", (names[0],), names[2])], Config(n_max=200, use_minimality=False)).collect()
        assert [r["n_rows"] for r in got] == [60, 60] or {r["n_rows"] for r in got} == {60}
        dirty = framework.verify(df, [rel, Relation("FD", (names[0],), names[1])], Config(setting="dirty", n_max=200)).collect()
        assert {r["rule"]: r["hits"] for r in dirty}[rel.text] == 60
        assert satisfy.violations(df, rel).count() == 0 and satisfy.satisfied(df, Relation("FD", (names[0],), names[1])).columns == list(names)
        assert independence.chi2(df, [Relation("FD", (names[0],), names[1])], Config(setting="dirty")).count() == 1
    with pytest.raises(ValueError):
        satisfy.with_holds(df, rel, name="mask")


def test_overflow_violates(spark):
    df = spark.createDataFrame([(2**40, 2**40, 1), (2, 3, 6), (2**62, 2**62, 0)], "a bigint, b bigint, c bigint")
    for op in "+-*":
        assert satisfy.satisfaction(df, [Relation("AR", ("a", "b"), "c", (op, "a", "b"))]).first()["n_rows"] == 3
    assert satisfy.satisfaction(df, [PRODUCT]).first()["hits"] == 1
    assert framework.verify(df, [PRODUCT, SUM_2], Config(setting="dirty", n_max=50)).count() == 2


SUM_2 = Relation("AR", ("a", "b"), "c", ("+", "a", "b"))


def test_empty_tables(spark):
    df = spark.createDataFrame([], "a bigint, b bigint, c bigint, s string, t string")
    rels = [PRODUCT, Relation("FD", ("s",), "t"), Relation("ST", ("s",), "t", ("upper", "s"))]
    for setting in ("clean", "dirty"):
        got = framework.verify(df, rels, Config(setting=setting)).collect()
        assert len(got) == 3 and not any(r["reliable"] for r in got) and {r["n_rows"] for r in got} == {0}
        assert framework.discover(df, Config(setting=setting)).where("reliable").count() == 0


def test_jobs_do_not_grow_with_the_pool(spark):
    rows = [(i * 7 % 23, i * 5 % 19, i * 7 % 23 + i * 5 % 19, i % 4, (i % 4) * 2, f"v{i % 6}", f"w{i % 3}") for i in range(400)]
    df = spark.createDataFrame(rows, "p bigint, q bigint, r bigint, z bigint, zz bigint, s string, t string")
    pool = [Relation("AR", ("p", "q"), "r", ("+", "p", "q")), Relation("AR", ("r", "p"), "q", ("-", "r", "p")), Relation("AR", ("r", "q"), "p", ("-", "r", "q")), Relation("AR", ("z", "p"), "zz", ("+", "z", "p")),
            Relation("FD", ("s",), "t"), Relation("FD", ("s",), "z"), Relation("FD", ("t",), "s")]

    def jobs(rels, cfg):
        group = f"jobs-{len(rels)}-{cfg.setting}"
        spark.sparkContext.setJobGroup(group, group)
        framework.verify(df, rels, cfg).collect()
        n = len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        return n

    for cfg in (Config(n_max=200, use_minimality=False), Config(setting="dirty", tau=0.2, n_max=200, use_minimality=False, use_independence=False)):
        level = [r for r in pool if r.arity == 2]
        copies = [Relation("AR", r.inputs, r.output, ("-" if r.expr[0] == "+" else "+", *r.expr[1:])) for r in level]
        more = [Relation("AR", r.inputs, r.output, ("*", *r.expr[1:])) for r in level]
        # a batch of rules is a job more, not a rule
        one, three = jobs(level, cfg), jobs(level + copies + more, cfg)
        assert three <= one + 4
        assert jobs([r for r in pool if r.kind == "FD"], cfg) <= jobs(pool[4:5], cfg) + 2
