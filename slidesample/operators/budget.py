"""From a query budget to a sample size: tiny aggregates, one number to the driver.

`sample_size` is the one entry point that a run asks before every window; the functions below it answer for many windows at once.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slidesample.functions.tscore import corrections


@dataclass(frozen=True)
class Budget:
    """kind: 'fraction' (of the window), 'size' (items), 'tokens' (`per_item` for each item), 'latency' (seconds) or 'accuracy' (margin at `confidence`).

    `start` is the share of the window to sample while there is no history to predict from.
    """

    kind: str
    amount: float
    confidence: float = 0.95
    per_item: float = 1.0
    start: float = 0.1


@dataclass(frozen=True)
class Past:
    """What one window really cost: items sampled, seconds, whether it went over budget, and (for accuracy) the sum of B s^2 over strata."""

    n: int
    seconds: float
    over: bool = False
    spread: float | None = None


def sample_size(budget: Budget, history: list[Past], seen: int) -> int:
    """Items that the next window may sample out of `seen`; never more than those, never below one if there are any.

    Latency: seconds = a + b n fitted to the windows since the last violation, aiming at 95 %; right after a violation the size shrinks by what was over and a tenth more.
    Accuracy: the size whose margin is the amount, from the spread of the last window.
    """
    first = int(seen * budget.start)
    last = history[-1] if history else None
    if budget.kind == "fraction":
        size = int(seen * budget.amount + 1e-9)
    elif budget.kind == "size":
        size = int(budget.amount)
    elif budget.kind == "tokens":
        size = int(budget.amount / budget.per_item + 1e-9)
    elif budget.kind == "latency":
        if last is None:
            size = first
        elif last.over:
            size = int(last.n * 0.9 * budget.amount / last.seconds)
        else:
            since = max((i for i, h in enumerate(history) if h.over), default=0)  # before a violation an item cost something else
            size = _by_fit(history[since:][-20:], 0.95 * budget.amount, first)
    elif budget.kind == "accuracy":
        z = corrections(1 - (1 - budget.confidence) / 2)[0]
        q = None if last is None else last.spread
        size = first if q is None else math.ceil(seen * q / (q + (budget.amount / z) ** 2)) if q > 0 else 1
    else:
        raise ValueError(f"unknown kind of budget: {budget.kind}")
    return max(min(1, seen), min(seen, size))


def _by_fit(history: list[Past], seconds: float, first: int) -> int:
    n, t = [h.n for h in history], [h.seconds for h in history]
    mean_n, mean_t = sum(n) / len(n), sum(t) / len(t)
    spread = sum((x - mean_n) ** 2 for x in n)
    slope = sum((x - mean_n) * (y - mean_t) for x, y in zip(n, t, strict=True)) / spread if spread else 0.0
    if slope <= 0:  # no size has told yet what an item costs: try a little more while there is room
        return max(first, int(n[-1] * min(1.1, seconds / max(t[-1], 1e-9))))
    return int((seconds - (mean_t - slope * mean_n)) / slope)


def exceeded(budget: Budget, n: int, seconds: float, margin: float | None) -> bool:
    """Did a window go over its budget?"""
    if budget.kind == "latency":
        return seconds > budget.amount
    if budget.kind == "accuracy":
        return margin is None or margin > budget.amount
    return budget.kind == "tokens" and n * budget.per_item > budget.amount


def fraction_size(seen: Column, fraction: float) -> Column:
    return F.floor(seen * F.lit(fraction)).cast("long")


def token_size(resources: DataFrame) -> DataFrame:
    """resources(window_id, resource, tokens, per_item) -> the largest sample all resources can pay for."""
    return resources.groupBy("window_id").agg(F.min(F.floor(F.col("tokens") / F.col("per_item"))).cast("long").alias("sample_size"))


def latency_size(history: DataFrame, seconds: float | Column, factor: Column | None = None) -> DataFrame:
    """history(n, seconds): fit seconds = a + b n and solve for n; `factor` scales the prediction (time of day)."""
    fit = history.agg(F.regr_slope("seconds", "n").alias("b"), F.regr_intercept("seconds", "n").alias("a"))
    allowed = (F.lit(seconds) if not isinstance(seconds, Column) else seconds) / (F.lit(1.0) if factor is None else factor)
    return fit.withColumn("sample_size", F.greatest(F.lit(0), F.floor((allowed - F.col("a")) / F.col("b"))).cast("long"))


def accuracy_size(parts: DataFrame, epsilon: Column, confidence: float = 0.95, by: tuple[str, ...] = ("window_id",)) -> DataFrame:
    """The sample that keeps the margin within epsilon: k Q / (Q + (epsilon / z)^2) with Q the sum of B s^2 over strata."""
    z = corrections(1 - (1 - confidence) / 2)[0]
    s2 = (F.col("svv") - F.col("sv") * F.col("sv") / F.col("b")) / (F.col("b") - 1)
    sums = parts.groupBy(*by).agg(F.sum("n_all").alias("k"), F.sum(F.col("n_all") * s2).alias("q"), F.first(epsilon).alias("_eps"))
    need = F.col("k") * F.col("q") / (F.col("q") + F.pow(F.col("_eps") / z, 2))
    return sums.select(*by, F.least(F.col("k"), F.ceil(need)).cast("long").alias("sample_size"))


def feedback(costs: list[float], budget: float, start: int, cost_of) -> list[dict]:
    """Shrink after a violation, grow slowly otherwise; counts violations.  `cost_of(n, i)` is what window i really cost."""
    size, out, violations = start, [], 0
    for i, _ in enumerate(costs):
        actual = cost_of(size, i)
        over = actual > budget
        violations += over
        out.append({"window_id": i, "sample_size": size, "cost": round(actual, 4), "over": bool(over), "violations": violations})
        size = max(1, int(size * (0.9 * budget / actual if over else min(1.1, budget / actual))))
    return out
