"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

W5 runs the same query over line items by ship day (price of the items of urgent orders by customers of one region: a join with orders, customers and
nations; windows of 1000 days that move by 40, strata flag and status, samples of a tenth by key) in four ways: exact recompute (the query runs once on each
item, every window sums all its items), incremental only (pane sums and the inverse reduce), sample only (a fresh by-key sample in every window) and combined
(`by_key_windows` of the library: each item sampled once, the query on sampled items only, partials slide by the inverse reduce).
The others are experiments and measures over events, the chain of biased samples with accumulated changes among them.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from slidesample.operators import estimate, incremental, windows
from slidesample.plans import catalog
from slidesample.plans.q_loop import by_key_windows
from slidesample.sources import tables

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


class LineWindows:
    """The four ways over line items of urgent orders; each call gives one answer per window."""

    def __init__(self, spark):
        self.spark = spark
        li = tables.load(spark, SF_DIR, "lineitem")
        item = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
        day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
        items = li.select(item.alias("item_id"), day.alias("seq"), F.concat("l_returnflag", "l_linestatus").alias("stratum"), F.col("l_extendedprice").cast(tables.MONEY).alias("value"), "l_orderkey")
        lo, hi = items.agg(F.min("seq"), F.max("seq")).first()
        self.slide = windows.Slide(1000, 40, hi - lo + 1, lo)
        self.per, self.pace = self.slide.length // self.slide.pane, self.slide.step // self.slide.pane
        self.items = items
        orders = tables.load(spark, SF_DIR, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
        customers = tables.load(spark, SF_DIR, "customer").select("c_custkey", "c_nationkey")
        nations = tables.load(spark, SF_DIR, "nation").select("n_nationkey", "n_regionkey")
        where = orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).join(nations, F.col("c_nationkey") == F.col("n_nationkey"))
        self.counted = where.select("o_orderkey", (F.col("o_orderpriority").startswith("1") & (F.col("n_regionkey") == 1)).alias("counts"))
        self.kept = F.shiftrightunsigned("item_id", 1) < F.lit((1 << 63) // 10)

    def priced(self, items):
        """The query of one item: its order and customer decide whether the price counts."""
        joined = items.join(self.counted, F.col("l_orderkey") == F.col("o_orderkey"))
        return joined.withColumn("value", F.when(F.col("counts"), F.col("value")).otherwise(F.lit(0).cast(tables.MONEY)))

    def exact(self):
        return windows.assign(self.priced(self.items), self.slide).groupBy("window_id").agg(F.sum("value").alias("total"))

    def incremental(self):
        sums = self.priced(self.items).groupBy(windows.pane_of(self.slide).alias("pane")).agg(F.sum("value").alias("total"))
        full = incremental.every_pane(sums, -(-self.slide.total // self.slide.pane))
        return incremental.slide_invertible(full, self.per, self.pace, ["total"])

    def sampled(self):
        fresh = windows.assign(self.items, self.slide).where(F.shiftrightunsigned(F.xxhash64("item_id", "window_id"), 1) < F.lit((1 << 63) // 10))
        panes = self.items.groupBy(windows.pane_of(self.slide).alias("pane"), "stratum").agg(F.count("*").alias("n"))
        counts = windows.panes_of_windows(self.spark, self.slide).join(panes, "pane").groupBy("window_id", "stratum").agg(F.sum("n").alias("n_seen"))
        return estimate.estimate_total(self.priced(fresh), counts, F.col("value"))

    def combined(self):
        return by_key_windows(self.items, self.slide, self.kept, self.priced)


def timed(df) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    out: dict[str, float] = {}
    lines = LineWindows(spark)
    ways = ("exact", "incremental", "sampled", "combined")
    for way in ways:
        runs = [timed(getattr(lines, way)()) for _ in range(4)][1:]
        out[f"w5_{way}"] = round(sorted(runs)[1], 3)
    named = catalog.queries()
    for name in ("exact_sum_by_window", "incremental_sum_by_window", "combined_sum_by_window", "prototype_sum_by_window", "coordinated_sum_by_window", "sum_with_bound", "quota_by_window", "invertible_slide_var", "mergeable_slide_max", "stratum_counts", "weighted_rollup", "sampled_star_join"):
        timed(named[name](spark, SF_DIR))
        out[name] = round(timed(named[name](spark, SF_DIR)), 3)
    extra = {f"speedup_over_{w}": round(out[f"w5_{w}"] / out["w5_combined"], 3) for w in ways[:3]}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": SF_DIR.rsplit("sf", 1)[-1], **extra}), flush=True)
    os._exit(0)


if __name__ == "__main__":
    main()
