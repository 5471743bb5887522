"""Column sets that group the rows alike are counted once for all levels, over rows that are made different first."""

from relmine.catalog import ar
from relmine.model import Config
from relmine.operators import bounds
from relmine.plans import framework

RULES = [ar("-", "a", "b", "c"), ar("+", "c", "d", "e"), ar("+", ("-", "a", "b"), "d", "e"), ar("*", "d", "n", "p")]


def test_sets_that_group_alike_are_counted_once(spark, monkeypatch):
    rows = [(a, b, a - b, d, a - b + d, n, d * n) for a, b, d, n in ((i * 37 % 11, i * 17 % 7, i * 5 % 4, i % 3) for i in range(120))]
    df = spark.createDataFrame(rows, "a bigint, b bigint, c bigint, d bigint, e bigint, n bigint, p bigint")
    df = df.unionByName(df.where("a < 6"))
    counted, plain = [], bounds.kappas_of
    monkeypatch.setattr(bounds, "kappas_of", lambda d, items, *a: counted.extend(frozenset(c) for c, _ in items) or plain(d, items, *a))
    cfg = Config(use_minimality=False)
    got = {r["cand_id"]: r["bound"] for r in framework.verify(df, RULES, cfg).collect()}
    known = bounds.Known()
    known.learn(df, RULES)
    assert len({known.closure(s) for s in counted}) == len(counted)
    assert frozenset("dn") in counted and frozenset("dnp") not in counted and frozenset("dp") in counted  # a zero hides n
    cells = [r.asDict() for r in df.collect()]  # the count's own name gives way to the column n
    for r in RULES:
        sets = bounds.column_sets(r.columns)
        share = lambda s: sum(all(x[c] == y[c] for c in s) for i, x in enumerate(cells) for j, y in enumerate(cells) if i != j) / (len(cells) * (len(cells) - 1))
        assert abs(got[r.cand_id] - sum(map(share, sets)) / len(sets)) < 1e-12


def test_quotients_and_doubles_determine_nothing(spark):
    df = spark.createDataFrame([(6, 2, 3, 1.0, 2.0, 3.0)], "a bigint, b bigint, c bigint, x double, y double, z double")
    assert bounds.determined(df, [ar("/", "a", "b", "c"), ar("+", "x", "y", "z")]) == []
    assert bounds.determined(df, [ar("*", "a", "b", "c")]) == [(frozenset("ab"), "c")]
