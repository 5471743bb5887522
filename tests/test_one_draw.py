"""What all levels read alike is read once, and what is drawn stays the same."""

from relmine.catalog import ar
from relmine.model import Config
from relmine.operators import bounds, generate, perturb
from relmine.plans import framework


def numbers(spark, n):
    return spark.range(n).selectExpr("id * 7919 % 1009 as a", "id * 31 % 97 as b", "if(id % 50 = 0, null, id % 11) as d").selectExpr("*", "a + b as c", "a + b + coalesce(d, 0) as e").persist()


def test_levels_share_probes_and_trials(spark, monkeypatch):
    df, calls = numbers(spark, 3000).drop("d"), []
    for module, name in ((generate, "null_patterns"), (perturb, "_drawn"), (generate, "_smallest")):
        plain = getattr(module, name)
        monkeypatch.setattr(module, name, lambda *a, plain=plain, name=name: calls.append(name) or plain(*a))
    got = framework.discover(df, Config(n_max=200, max_level=3, use_minimality=False, use_bound=False), kinds=("AR",)).collect()
    assert {len(r["inputs"]) for r in got} >= {2} and any(r["trials"] for r in got)
    framework.verify(df, [ar("+", "a", "b", "c"), ar("+", ("+", "a", "b"), "e", "c")], Config(n_max=200, use_minimality=False, use_bound=False)).collect()
    assert calls.count("null_patterns") == calls.count("_smallest") == 1 and calls.count("_drawn") == 2  # one for each run


def test_draws_are_those_of_the_whole_order(spark):
    for df in (numbers(spark, 60_000), spark.range(60_000).selectExpr("id % 5 as a", "id % 3 as b")):
        known, names = bounds.Known(), sorted(df.columns)
        rows = lambda frame: sorted(map(str, frame.collect()))
        for _ in range(2):
            assert rows(generate.probe_rows(df, names, 8, 3, known=known)) == rows(generate.probe_rows(df, names, 8, 3))
            assert rows(perturb.trial_bank(df, ["b", "a"], 100, 42, known)) == rows(perturb.trial_bank(df, ["b", "a"], 100, 42))
        known.close()
