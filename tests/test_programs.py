from relmine.functions.expressions import opt
from relmine.model import Config
from relmine.operators import generate
from relmine.operators.satisfy import satisfaction


def test_constants(spark):
    df = spark.createDataFrame([(i, 3 * i - 7, i % 5, i * i, 4) for i in range(40)], "x bigint, y bigint, m bigint, q bigint, one bigint")
    got = {r.text for r in generate.constants(df, Config())}
    assert {"affine(x, 3, -7) = y", "mod(x, 5) = m"} <= got and not any("one" in t or "q" in t for t in got)


def test_string_programs(spark):
    rows = [(f"{a}-{b}", f"{c}", f"{b}.{c}", f"<{a}/{b}/{c}>", a, f"{a}{b[:2]}", b[:2], f"x {b} " * (1 + i % 3) + c) for i in range(40) for a, b, c in [("k%02d" % (i * 7 % 29), "word%d" % (i * 5 % 23), "z%d" % (i % 6))]]
    df = spark.createDataFrame(rows, "ab string, c string, bc string, all string, a string, short string, two string, tail string")
    found = [r for level in (1, 2, 3) for r in generate.programs(df, level, Config(use_minimality=False))]
    texts = {r.text for r in found}
    assert "concat(token(ab, '-', 2), '.', c) = bc" in texts  # split, then join
    assert any(r.output == "all" and r.arity == 3 and r.expr[1] == ("lit", "<") and r.expr[-1] == ("lit", ">") for r in found)
    assert "slice(short, 1, 3) = a" in texts
    assert any(r.output == "c" and r.expr == ("token", "tail", opt(" "), opt(-1)) for r in found)  # from the right
    got = satisfaction(df, found).collect()
    assert got and all(r["hits"] == r["n_rows"] == 40 for r in got)


def test_three_columns_joined(spark):
    rows = [(f"p{i * 7 % 31}", f"q{i * 5 % 17}", f"r{i % 7}") for i in range(40)]
    df = spark.createDataFrame([(a, b, c, f"{a}-{b}/{c}") for a, b, c in rows], "a string, b string, c string, y string")
    assert "concat(a, '-', b, '/', c) = y" in {r.text for r in generate.programs(df, 3, Config())}


def test_screening_keeps_what_holds(spark):
    from relmine.model import Relation

    df = spark.createDataFrame([(i, i + (1 if i % 9 == 0 else 0), i % 3) for i in range(3000)], "a bigint, b bigint, c bigint")
    near, wrong = (Relation("AR", ("a",), y, ("affine", "a", opt(1), opt(0))) for y in ("b", "c"))
    assert generate.screened(df, [near, wrong], Config(setting="dirty")) == [near]
    assert generate.screened(df, [near, wrong], Config()) == []


def test_early_exit_and_corrections(spark):
    from relmine.model import Relation
    from relmine.operators import independence, perturb

    rows = [(i, i + (5 if i % 4 == 0 else 0), i % 4 == 0, i % 2, i % 7) for i in range(280)]
    df = spark.createDataFrame(rows, "a bigint, b bigint, cause boolean, half bigint, seven bigint")
    rel = Relation("AR", ("a",), "b", ("affine", "a", opt(1), opt(0)))
    one = independence.independent(df, [rel], Config(setting="dirty", it_columns=1))[rel.cand_id]
    assert one[:2] == (False, "cause")
    for name in ("bonferroni", "benjamini_hochberg"):
        assert not independence.independent(df, [rel], Config(setting="dirty", multiplicity=name))[rel.cand_id][0]
    assert independence.independent(df, [rel], Config(setting="dirty", exclude=("cause", "half"), min_expected=50))[rel.cand_id][0]
    assert perturb.stop_z(Config(looks="spread")) > perturb.stop_z(Config()) == 1.96
