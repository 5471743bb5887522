import random

import pytest

from relmine.functions.expressions import canonical
from relmine.model import Config
from relmine.operators import generate

RULES = {
    "sum of products": (("+", ("*", "a", "b"), ("*", "c", "d")), lambda a, b, c, d: a * b + c * d),
    "product of sums": (("*", ("+", "a", "b"), ("+", "c", "d")), lambda a, b, c, d: (a + b) * (c + d)),
    "quotient of sums": (("/", ("+", "a", "b"), ("+", "c", "d")), lambda a, b, c, d: (a + b) / (c + d)),
    "quotient by a sum, and one more": (("+", ("/", "c", ("+", "a", "b")), "d"), lambda a, b, c, d: c / (a + b) + d),
}


@pytest.mark.parametrize("name", list(RULES))
def test_bushy_rules_of_four_inputs(spark, name):
    tree, f = RULES[name]
    draw = random.Random(7)
    rows = [(*x, float(f(*x))) for x in ([draw.randrange(1, 1000) for _ in range(4)] for _ in range(60))]
    df = spark.createDataFrame(rows, "a bigint, b bigint, c bigint, d bigint, y double")
    got = generate.arithmetic(df, 4, Config())
    assert (canonical(tree), "y") in {(r.expr, r.output) for r in got}
