import math

import pytest

from relmine.functions.expressions import absorbed_above, canonical, leaves, render, signed_sum
from relmine.functions.measures import expected_information
from relmine.functions.statistics import chi2_tail, wilson
from relmine.model import Config, Relation


def test_wilson_goldens():
    for n, s, low, high in ((100, 50, 0.403830, 0.596170), (100, 14, 0.085263, 0.221374), (100, 90, 0.825633, 0.944771)):
        assert wilson(n, s) == pytest.approx((low, high), abs=1e-6)


def test_chi2_tail():
    assert chi2_tail(20, 2) == pytest.approx(math.exp(-10))
    assert chi2_tail(3.841459, 1) == pytest.approx(0.05, abs=1e-6)
    assert chi2_tail(60_000, 1) < 1e-300
    assert chi2_tail(0, 3) == 1.0
    assert chi2_tail(1000, 1000) == pytest.approx(0.494, abs=1e-3)


def test_trees():
    t = ("-", ("+", "c", "a"), "b")
    assert leaves(t) == ["c", "a", "b"]
    assert signed_sum(t) == {"a": 1, "c": 1, "b": -1}
    assert canonical(t) == canonical(("+", "a", ("-", "c", "b")))
    assert render(canonical(("*", "b", "a"))) == "(a * b)"
    inner = ("+", "a", "b")
    assert absorbed_above(("*", inner, "c"), inner)
    assert not absorbed_above(("-", inner, "c"), inner)


def test_relation_checks():
    with pytest.raises(ValueError):
        Relation("AR", ("a",), "a", "a")
    with pytest.raises(ValueError):
        Relation("FD", ("a",), "b", "a")
    with pytest.raises(ValueError):
        Config(setting="odd")
    assert Config(setting="dirty").tau == 0.8 and Config().tau == 1.0
    assert Relation("FD", ("a",), "b").isomerous(Relation("FD", ("b",), "a"))


def test_expected_information_by_enumeration():
    """All permutations of four rows in two groups on each side."""
    from itertools import permutations

    import numpy as np

    x, ys = (0, 0, 1, 1), (0, 0, 0, 1)
    total, n = 0.0, 0
    for p in set(permutations(ys)):
        n += 1
        for a in (0, 1):
            for b in (0, 1):
                k = sum(u == a and v == b for u, v in zip(x, p))
                if k:
                    total += k / 4 * math.log2(4 * k / (x.count(a) * p.count(b)))
    assert expected_information(np.array([2, 2]), np.array([3, 1])) == pytest.approx(total / n)
