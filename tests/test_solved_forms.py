"""Rules that are one sum solved for different columns share scans; their verdicts stay what they are alone."""

from relmine.bench import carriers
from relmine.catalog import DUE, SHORT, ar
from relmine.model import Config
from relmine.operators import bounds, independence, satisfy

FORMS = (SHORT, ar("-", "due_c", "net_c", "tax_c"), ar("-", "due_c", "tax_c", "net_c"))


def test_solved_forms_are_counted_once(spark, small, monkeypatch):
    df = carriers.ar_lineitem(spark, small).select("net_c", "tax_c", "gross_c", "sur_c", "due_c", "qty").persist()
    cfg, sizes, tested = Config(setting="dirty"), [], []
    kappas_of, chi2 = bounds.kappas_of, independence.chi2
    monkeypatch.setattr(bounds, "kappas_of", lambda d, items, *a: sizes.append(len(items)) or kappas_of(d, items, *a))
    monkeypatch.setattr(independence, "chi2", lambda d, rels, *a: tested.append(len(rels)) or chi2(d, rels, *a))
    shared, judged = bounds.bounds(df, [*FORMS, DUE], cfg), independence.independent(df, FORMS, cfg)
    assert sizes == [8] and tested == [1]  # four sets for each of two sums, not seven for each of four rules
    for r in (*FORMS, DUE):
        ok = df.where(satisfy.holds(r))
        kappa = bounds.kappas(ok, bounds.column_sets(r.columns))
        assert abs(shared[r.cand_id] - bounds.group_bound(kappa, r, cfg)) < 1e-12
    assert len(set(judged.values())) == 1 and judged[SHORT.cand_id] == independence.independent(df, [SHORT], cfg)[SHORT.cand_id]
    df.unpersist()


def test_sums_that_may_overflow_are_alone(spark):
    rows = [(2**62, 2**62, -(2**62), 2**62), (1, 2, 3, 6), (2, 3, 4, 9)]
    df = spark.createDataFrame(rows, "a bigint, b bigint, c bigint, d bigint")
    forms = [ar("+", ("+", "a", "b"), "c", "d"), ar("+", ("+", "a", "c"), "b", "d")]
    assert len(set(satisfy.same_rows(df, forms).values())) == 2
    assert len(set(satisfy.same_rows(df.where("a < 9"), forms).values())) == 1
