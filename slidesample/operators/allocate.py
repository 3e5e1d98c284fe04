"""How many items each stratum may contribute."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def stratum_counts(assigned: DataFrame, *by: str) -> DataFrame:
    """Items seen per stratum (and window): partial sums before the shuffle."""
    return assigned.groupBy(*by, "stratum").agg(F.count("*").alias("n_seen"))


def proportional_quota(counts: DataFrame, size: int | Column, by: tuple[str, ...] = ("window_id",), least: int = 0) -> DataFrame:
    """Add `quota`: the sample size shared in proportion to n_seen, by largest remainder, ties by stratum name.

    Products are exact decimals.  A sample at least as large as the window takes everything.  With `least`, every stratum gets
    that many if the sample allows, taken back from the largest quotas.
    """
    group, size = Window.partitionBy(*by), size if isinstance(size, Column) else F.lit(size)
    product = size.cast("decimal(18,0)") * F.col("n_seen").cast("decimal(18,0)")
    out = (
        counts.withColumn("_k", F.sum("n_seen").over(group))
        .withColumn("_p", product)
        .withColumn("_base", F.call_function("div", F.col("_p"), F.col("_k").cast("decimal(18,0)")))
        .withColumn("_rest", (F.col("_p") - F.col("_base").cast("decimal(18,0)") * F.col("_k").cast("decimal(18,0)")))
        .withColumn("_rank", F.row_number().over(group.orderBy(F.col("_rest").desc(), F.col("stratum"))))
        .withColumn("_left", size - F.sum("_base").over(group))
    )
    quota = F.when(size >= F.col("_k"), F.col("n_seen")).otherwise(F.col("_base") + (F.col("_rank") <= F.col("_left")).cast("int"))
    out = out.withColumn("quota", quota.cast("long"))
    if least:
        lifted = F.least(F.greatest(F.col("quota"), F.lit(least)), F.col("n_seen"))
        out = out.withColumn("_lifted", lifted).withColumn("_over", F.sum("_lifted").over(group) - F.sum("quota").over(group))
        # the surplus comes back from the largest quotas, one after the other
        spare = F.greatest(F.col("_lifted") - least, F.lit(0))
        order = group.orderBy(F.col("_lifted").desc(), F.col("stratum"))
        before = F.coalesce(F.sum(spare).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        taken = F.greatest(F.lit(0), F.least(spare, F.col("_over") - before))
        out = out.withColumn("quota", (F.col("_lifted") - taken).cast("long"))
    return out.select(*by, "stratum", "n_seen", "quota")


def allocation_timeline(items: DataFrame, size: int, tick: int) -> DataFrame:
    """At the end of every tick: arrivals so far per stratum, its quota, and the change since the tick before.

    Sizes over time depend on counts alone, so they are known before any item is chosen.
    """
    per_tick = items.groupBy(F.floor(F.col("seq") / tick).cast("long").alias("tick"), "stratum").agg(F.count("*").alias("n"))
    dense = per_tick.select("tick").distinct().crossJoin(per_tick.select("stratum").distinct())  # ticks x strata, both few
    along = Window.partitionBy("stratum").orderBy("tick")
    seen = dense.join(per_tick, ["tick", "stratum"], "left").withColumn("n_seen", F.sum(F.coalesce("n", F.lit(0))).over(along)).where("n_seen > 0")
    quota = proportional_quota(seen.select("tick", "stratum", "n_seen"), size, by=("tick",))
    return quota.withColumn("change", F.col("quota") - F.coalesce(F.lag("quota").over(along), F.lit(0)))


def suggested_interval(timeline: DataFrame, least_shift: int = 1) -> DataFrame:
    """The smallest number of ticks after which some stratum's quota has moved by at least `least_shift`, averaged over the stream."""
    moved = timeline.where("tick > 0").groupBy("tick").agg(F.max(F.abs("change")).alias("shift"))
    return moved.agg(
        F.count("*").alias("ticks"),
        F.sum((F.col("shift") >= least_shift).cast("long")).alias("ticks_with_shift"),
        F.max("shift").alias("largest_shift"),
    ).withColumn("suggested_ticks", F.when(F.col("ticks_with_shift") > 0, F.greatest(F.lit(1).cast("long"), F.call_function("div", F.col("ticks"), F.col("ticks_with_shift")))).otherwise(F.col("ticks")))
