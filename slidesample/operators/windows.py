"""Window assignment, by count or by time, and panes.

A schedule is a DataFrame (window_id, lo, hi) of half-open ranges of `seq`.  Long windows are assembled from panes of width
gcd(length, slide), so a row is hashed once and not once per window it belongs to.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Slide:
    """Windows of `length` positions that move by `step`, all inside 0 … total-1."""

    length: int
    step: int
    total: int
    origin: int = 0

    @property
    def count(self) -> int:
        return max(0, (self.total - self.length) // self.step + 1) if self.step else 0

    @property
    def pane(self) -> int:
        return math.gcd(self.length, self.step)

    def schedule(self, spark: SparkSession) -> DataFrame:
        lo = F.col("id") * self.step + self.origin
        return spark.range(self.count).select(F.col("id").alias("window_id"), lo.alias("lo"), (lo + self.length).alias("hi"))


def assign(items: DataFrame, slide: Slide, seq: str = "seq") -> DataFrame:
    """One row per item and window that holds it (window_id, lo added).  Multiplies rows: use panes where that is too much."""
    at = F.col(seq) - slide.origin
    first = F.greatest(F.lit(0), F.ceil((at - slide.length + 1) / F.lit(slide.step))).cast("long")
    last = F.least(F.lit(slide.count - 1), F.floor(at / F.lit(slide.step))).cast("long")
    ids = F.when(first <= last, F.sequence(first, last)).otherwise(F.array().cast("array<bigint>"))
    return items.withColumn("window_id", F.explode(ids)).withColumn("lo", F.col("window_id") * slide.step + slide.origin)


def assign_schedule(items: DataFrame, schedule: DataFrame, cell: int, seq: str = "seq") -> DataFrame:
    """Any schedule: range join through cells of `cell` positions (equi-join) and a residual comparison."""
    cells = schedule.withColumn("_cell", F.explode(F.sequence(F.floor(F.col("lo") / cell), F.floor((F.col("hi") - 1) / cell))))
    return items.withColumn("_cell", F.floor(F.col(seq) / cell)).join(cells, "_cell").where((F.col(seq) >= F.col("lo")) & (F.col(seq) < F.col("hi"))).drop("_cell")


def pane_of(slide: Slide, seq: str = "seq") -> Column:
    return F.floor((F.col(seq) - slide.origin) / slide.pane).cast("long")


def panes_of_windows(spark: SparkSession, slide: Slide) -> DataFrame:
    """(window_id, pane) for every pane of every window: the edges along which pane results are merged."""
    per, step = slide.length // slide.pane, slide.step // slide.pane
    return spark.range(slide.count).select(F.col("id").alias("window_id"), F.explode(F.sequence(F.col("id") * step, F.col("id") * step + (per - 1))).alias("pane"))


def cell_of(slide: Slide, seq: str = "seq") -> Column:
    """Two cells a step, cut where windows begin and where they end: few even where length and step have no common divisor and panes are single positions."""
    at = F.col(seq) - slide.origin
    step = F.floor(at / slide.step).cast("long")
    return step * 2 + (at - step * slide.step >= slide.length % slide.step).cast("long")


def cells_of_windows(spark: SparkSession, slide: Slide) -> DataFrame:
    """(window_id, cell) for every cell of every window."""
    most = slide.length // slide.step * 2 + (1 if slide.length % slide.step else 0) - 1
    return spark.range(slide.count).select(F.col("id").alias("window_id"), F.explode(F.sequence(F.col("id") * 2, F.col("id") * 2 + most)).alias("cell"))


def window_schedule(base: int, deltas: list[int], slide_share: float, anchor: str = "start_moves", origin: int = 0) -> list[tuple[int, int, int]]:
    """Windows of changing size: the start (or the end) moves by a share of the previous size, the other side absorbs the change."""
    lo, hi, out = origin, origin + base, [(0, origin, origin + base)]
    for i, delta in enumerate(deltas, 1):
        move, size = round((hi - lo) * slide_share), hi - lo + delta
        if anchor == "start_moves":
            lo = lo + move
            hi = lo + size
        else:
            hi = hi + move
            lo = hi - size
        out.append((i, lo, hi))
    return out


def expire(rows: DataFrame, start: int | Column, seq: str = "seq") -> DataFrame:
    """Drop what lies before the window's start; with panes stored as partitions this prunes files."""
    return rows.where(F.col(seq) >= start)


def admit(window: DataFrame, arrivals: DataFrame) -> DataFrame:
    return window.unionByName(arrivals)
