"""Queries as users give them: a plain aggregate, from which the engine takes what it needs to run it on samples and on changes.

A specification names a function, a value and, if wanted, a condition.  It gives the partial columns of an item, how partials of neighbours
merge, whether an item can be taken out again (inverse), and how the estimate is finished.  Nothing in it knows of samples or windows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slidesample.operators import estimate

INVERTIBLE = ("sum", "count", "avg")
MERGEABLE = ("min", "max")


@dataclass(frozen=True)
class AggregateSpec:
    """`fn` of `value` (an SQL expression) over the items that satisfy `where`."""

    fn: str
    value: str = "value"
    where: str | None = None

    def __post_init__(self):
        if self.fn not in INVERTIBLE + MERGEABLE:
            raise ValueError(f"no bounds are known for {self.fn}")

    @property
    def invertible(self) -> bool:
        return self.fn in INVERTIBLE

    def item_value(self) -> Column:
        """What one item adds; items outside the condition add nothing."""
        v = F.lit(1).cast("decimal(18,2)") if self.fn == "count" else F.expr(self.value).cast("decimal(18,2)")
        if self.where is None:
            return v
        return F.when(F.expr(self.where), v).otherwise(None if self.fn in MERGEABLE else F.lit(0).cast("decimal(18,2)"))

    def partials(self, items: DataFrame, *by: str, sign: Column | int = 1) -> DataFrame:
        """b, sv, svv (signed counts and sums) and, without an inverse, the extreme, for each group."""
        v = self.item_value()
        sign = F.lit(sign) if isinstance(sign, int) else sign
        aggs = [F.sum(sign).cast("long").alias("b"), F.sum(sign * v).cast("decimal(38,2)").alias("sv"), F.sum(sign * v * v).cast("decimal(38,4)").alias("svv")]
        if not self.invertible:
            aggs.append((F.min(v) if self.fn == "min" else F.max(v)).alias("extreme"))
        return items.groupBy(*by).agg(*aggs)

    def merged(self, partials: DataFrame, *by: str) -> DataFrame:
        """Partials of several chunks or changes as one."""
        aggs = [F.sum("b").alias("b"), F.sum("sv").cast("decimal(38,2)").alias("sv"), F.sum("svv").cast("decimal(38,4)").alias("svv")]
        if not self.invertible:
            aggs.append((F.min("extreme") if self.fn == "min" else F.max("extreme")).alias("extreme"))
        return partials.groupBy(*by).agg(*aggs)

    def finish(self, parts: DataFrame, confidence: float = 0.95) -> DataFrame:
        """parts(window_id, stratum, n_all, b, sv, svv) -> window_id, estimate, margin, n_sampled, n_seen.  Extremes: that of the sample, without a margin."""
        if not self.invertible:
            best = F.min("extreme") if self.fn == "min" else F.max("extreme")
            return parts.groupBy("window_id").agg(
                best.cast("double").alias("estimate"), F.lit(None).cast("double").alias("margin"), F.sum("b").alias("n_sampled"), F.sum("n_all").alias("n_seen")
            )
        doubles = parts.withColumn("sv", F.col("sv").cast("double")).withColumn("svv", F.col("svv").cast("double"))
        terms = estimate.total_terms(doubles, ("window_id",))
        scale = F.col("n_seen").cast("double") if self.fn == "avg" else None
        return estimate.with_margin(terms, confidence, scale).select("window_id", "estimate", "margin", "n_sampled", "n_seen")
