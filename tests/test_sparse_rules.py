from relmine.model import Config
from relmine.operators import generate

AR = "a bigint, b bigint, c bigint, d bigint"


def texts(rules):
    return {r.text for r in rules}


def test_rules_on_sparse_columns(spark):
    """Rows where all columns of a rule are null do not lose it, however many they are."""
    rows = [(i * 7 % 101, i * 5 % 97, i * 7 % 101 + i * 5 % 97, i) if i % 20 == 0 else (None, None, None, i) for i in range(2000)]
    df = spark.createDataFrame(rows, AR)
    assert "(a + b) = c" in texts(generate.arithmetic(df, 2, Config()))
    assert "(a + b) = c" in texts(generate.arithmetic(df, 2, Config(setting="dirty")))
    st = spark.createDataFrame([(f"{i}-{i * 3 % 11}", f"{i * 3 % 11}", f"k{i}", f"k{i}/{i * 3 % 11}", "x") if i % 20 == 0 else (None, None, None, None, "y") for i in range(2000)],
                               "t string, u string, k string, j string, z string")
    assert "token(t, '-', 2) = u" in texts(generate.extractions(st, Config()))
    assert "concat(k, '/', u) = j" in texts(generate.concatenations(st, Config()))


def test_rules_of_a_tiny_table(spark):
    df = spark.createDataFrame([(3, 4, 7, 12), (5, 9, 14, 45), (2, 8, 10, 16), (7, 1, 8, 7), (6, 11, 17, 66)], AR)
    assert {"(a + b) = c", "(a * b) = d"} <= texts(generate.arithmetic(df, 2, Config()))


def test_a_rule_with_a_part_of_its_cells_null_does_not_hold(spark):
    df = spark.createDataFrame([(i, i * 3 % 17, None if i == 7 else i + i * 3 % 17, i % 5) for i in range(60)], AR)
    assert "(a + b) = c" not in texts(generate.arithmetic(df, 2, Config()))
