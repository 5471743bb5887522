import numpy as np
import pytest

from relmine import catalog
from relmine.functions.measures import expected_information


def test_sizes_and_their_counts_say_the_same():
    xs, ys = np.array([1, 1, 1, 2, 2, 5]), np.array([4, 4, 4])
    assert expected_information(np.array([1, 2, 5]), np.array([4]), np.array([3, 2, 1]), np.array([3])) == pytest.approx(expected_information(xs, ys))


@pytest.mark.parametrize("name", ["rfi", "rfi_norm"])
def test_every_pair_is_measured(spark, small, name):
    got = {r["cand"]: r[name] for r in catalog.QUERIES[f"measure_{name}"](spark, small).collect()}
    assert set(got) == {f"{x}->{y}" for x, y in catalog._PAIRS}
    assert all(0 <= v <= 1 + 1e-9 for v in got.values())
