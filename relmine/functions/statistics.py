"""Wilson intervals, the chi-squared tail and deterministic integers from hashes."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash_int(*parts: Column) -> Column:
    """A 60-bit integer from the md5 of the parts, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *(p.cast("string") for p in parts))), 1, 15), 16, 10).cast("bigint")


def wilson(n: float, s: float, z: float = 1.96) -> tuple[float, float]:
    centre = (s + z * z / 2) / (n + z * z)
    half = z * math.sqrt(s * (n - s) / n + z * z / 4) / (n + z * z)
    return centre - half, centre + half


def wilson_bounds(n: Column, s: Column, z: float = 1.96) -> tuple[Column, Column]:
    n, s = n.cast("double"), s.cast("double")
    centre = (s + z * z / 2) / (n + z * z)
    half = F.lit(z) * F.sqrt(s * (n - s) / n + z * z / 4) / (n + z * z)
    return centre - half, centre + half


def chi2_tail(x: float, df: float) -> float:
    """Upper tail of the chi-squared law: the regularised incomplete gamma function, by series or continued fraction."""
    if x <= 0 or df <= 0:
        return 1.0
    a, x = df / 2, x / 2
    weight = math.exp(max(-745.0, -x + a * math.log(x) - math.lgamma(a)))
    if x < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-16:
            n += 1
            term *= x / n
            total += term
        return max(0.0, 1 - total * weight)
    tiny = 1e-300
    b = x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 100_000):
        k = -i * (i - a)
        b += 2
        d = 1 / ((k * d + b) or tiny)
        c = (b + k / c) or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return min(1.0, h * weight)
