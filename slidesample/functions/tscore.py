"""Quantiles of Student's t as column expressions.

Up to `EXACT` degrees of freedom they come from a short list computed here by inverting the distribution function; beyond it from
the Cornish–Fisher expansion with four correction terms.
"""

from __future__ import annotations

import math
from functools import lru_cache
from statistics import NormalDist

from pyspark.sql import Column
from pyspark.sql import functions as F

EXACT = 30


def _upper_tail(t: float, f: int) -> float:
    """P(T > t), by the closed sums for integer degrees of freedom."""
    theta = math.atan2(t, math.sqrt(f))
    c = math.cos(theta)
    if f == 1:
        inside = 2 * theta / math.pi
    elif f % 2:
        term, total = c, c
        for k in range(3, f - 1, 2):
            term *= c * c * (k - 1) / k
            total += term
        inside = 2 / math.pi * (theta + math.sin(theta) * total)
    else:
        term, total = 1.0, 1.0
        for k in range(2, f - 1, 2):
            term *= c * c * (k - 1) / k
            total += term
        inside = math.sin(theta) * total
    return (1 - inside) / 2


@lru_cache(maxsize=None)
def exact_quantile(f: int, p: float) -> float:
    lo, hi = 0.0, 1e6
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if _upper_tail(mid, f) > 1 - p else (lo, mid)
    return (lo + hi) / 2


def corrections(p: float) -> list[float]:
    """z and the coefficients of 1/f … 1/f^4."""
    z = NormalDist().inv_cdf(p)
    return [
        z,
        (z**3 + z) / 4,
        (5 * z**5 + 16 * z**3 + 3 * z) / 96,
        (3 * z**7 + 19 * z**5 + 17 * z**3 - 15 * z) / 384,
        (79 * z**9 + 776 * z**7 + 1482 * z**5 - 1920 * z**3 - 945 * z) / 92160,
    ]


def t_quantile(f: Column, p: float) -> Column:
    """Quantile `p` with `f` degrees of freedom; null where f <= 0."""
    series = sum((F.lit(c) / F.pow(f.cast("double"), F.lit(float(i))) for i, c in enumerate(corrections(p)) if i), F.lit(corrections(p)[0]))
    small = F.element_at(F.array(*[F.lit(exact_quantile(i, p)) for i in range(1, EXACT + 1)]), F.greatest(F.lit(1), F.least(f, F.lit(EXACT))).cast("int"))
    return F.when(f <= 0, F.lit(None)).when(f <= EXACT, small).otherwise(series)


def t_quantile_sql(f: str, p: float) -> str:
    """The same as SQL text (DuckDB and Spark's own SQL functions share it but for array access)."""
    listed = ", ".join(repr(exact_quantile(i, p)) for i in range(1, EXACT + 1))
    c = corrections(p)
    series = f"({c[0]!r} + " + " + ".join(f"({c[i]!r} / pow(CAST({f} AS DOUBLE), {i}))" for i in range(1, 5)) + ")"
    return f"CASE WHEN {f} <= 0 THEN NULL WHEN {f} <= {EXACT} THEN CAST(([{listed}])[CAST({f} AS INTEGER)] AS DOUBLE) ELSE {series} END"
