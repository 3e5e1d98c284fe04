"""Self-adjusting computation: chunks, fingerprints, reuse, change propagation, and reductions that slide.

A chunk is the sampled part of one (pane, stratum); its fingerprint is (count, sum of permanent item hashes), free of order.  Chunks whose
fingerprint is in the memo are reused, others computed.  Aggregates with an inverse instead follow item-level signed deltas, whose cost is
the number of changed items whatever the chunks look like.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slidesample.functions.hashing import priority
from slidesample.operators.memo import checkpointed


def fingerprints(sample: DataFrame, *by: str) -> DataFrame:
    h = priority("fp", F.col("item_id")).cast("decimal(38,0)")
    return sample.groupBy(*by).agg(F.count("*").alias("n"), F.sum(h).alias("hash_sum"))


def chunk_partials(sample: DataFrame, value: Column, *by: str) -> DataFrame:
    v = value.cast("decimal(18,2)")
    return sample.groupBy(*by).agg(F.count("*").alias("b"), F.sum(v).alias("sv"), F.sum(v * v).alias("svv"))


def split_reused(chunks: DataFrame, memo: DataFrame, keys: list[str]) -> DataFrame:
    """Adds `state`: reused (same fingerprint in the memo) or fresh; chunks only in the memo appear as removed."""
    old = memo.select(*keys, F.col("n").alias("_n"), F.col("hash_sum").alias("_h"))
    both = chunks.join(old, keys, "full_outer")
    same = (F.col("n") == F.col("_n")) & (F.col("hash_sum") == F.col("_h"))
    return both.withColumn("state", F.when(F.col("n").isNull(), "removed").when(same, "reused").otherwise("fresh")).drop("_n", "_h")


def dirty_reducers(edges: DataFrame, changed: DataFrame) -> DataFrame:
    """edges(src, dst), changed(node) -> all nodes downstream of a change, however many stages the graph has: goes on until a stage adds nothing."""
    down = lambda nodes: edges.join(nodes.select(F.col("node").alias("src")), "src", "left_semi").select(F.col("dst").alias("node")).distinct()
    dirty = frontier = down(changed)
    stage = 0
    while True:
        frontier = down(frontier).join(dirty, "node", "left_anti")
        stage += 1
        if stage % 8 == 0:  # plans of deep graphs are cut
            frontier, dirty = checkpointed(frontier), checkpointed(dirty)
        if frontier.isEmpty():
            return dirty
        dirty = dirty.unionByName(frontier)


def slide_invertible(panes: DataFrame, per_window: int, step: int, columns: list[str], by: tuple[str, ...] = ()) -> DataFrame:
    """Sliding sums over pane partials by un-reducing: running totals minus the running totals `per_window` panes before.

    panes(pane, columns…) must have every pane of the stream (for each group of `by`; see `every_pane`), empty ones with zeros.  A window ends at
    each pane with enough panes before it.  Rows are one per pane and group, whatever the number of items; without `by` one task walks the panes.
    """
    run = Window.partitionBy(*by).orderBy("pane").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    back = Window.partitionBy(*by).orderBy("pane")
    out = panes
    for c in columns:
        out = out.withColumn(f"_{c}", F.sum(c).over(run))
    for c in columns:
        out = out.withColumn(c, F.col(f"_{c}") - F.coalesce(F.lag(f"_{c}", per_window).over(back), F.lit(0)))
    first = F.col("pane") - (per_window - 1)
    return out.where((first >= 0) & (first % step == 0)).select(*by, F.call_function("div", first, F.lit(step).cast("long")).alias("window_id"), *columns)


def every_pane(panes: DataFrame, count: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Add the missing panes of 0 … count - 1 (for each group of `by`) with zeros."""
    grid = panes.sparkSession.range(count).select(F.col("id").alias("pane"))
    if by:
        grid = panes.select(*by).distinct().withColumn("pane", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(count - 1).cast("long"))))
    kinds = dict(panes.dtypes)
    rest = [c for c in panes.columns if c not in (*by, "pane")]
    return grid.join(panes, [*by, "pane"], "left").select(*by, "pane", *[F.coalesce(c, F.lit(0).cast(kinds[c])).alias(c) for c in rest])


def slide_mergeable(panes: DataFrame, per_window: int, step: int, aggregates: dict[str, Column], by: tuple[str, ...] = ()) -> DataFrame:
    """Sliding aggregates without an inverse (minimum, maximum): merge the panes of each window again."""
    frame = Window.partitionBy(*by).orderBy("pane").rowsBetween(-(per_window - 1), 0)
    out = panes
    for name, agg in aggregates.items():
        out = out.withColumn(name, agg.over(frame))
    first = F.col("pane") - (per_window - 1)
    return out.where((first >= 0) & (first % step == 0)).select(*by, F.call_function("div", first, F.lit(step).cast("long")).alias("window_id"), *aggregates)


def signed_delta(samples: DataFrame) -> DataFrame:
    """Items entering (+1) and leaving (-1) each window's sample against the window before, with the window they change."""
    now = samples.select("window_id", "stratum", "item_id", "value")
    before = now.withColumn("window_id", F.col("window_id") + 1)
    last = now.agg(F.max("window_id").alias("_last"))
    entering = now.join(before, ["window_id", "stratum", "item_id"], "left_anti").withColumn("sign", F.lit(1))
    leaving = before.join(now, ["window_id", "stratum", "item_id"], "left_anti").join(F.broadcast(last), F.col("window_id") <= F.col("_last")).drop("_last").withColumn("sign", F.lit(-1))
    return entering.unionByName(leaving)


def running_partials(changes: DataFrame, counts: DataFrame) -> DataFrame:
    """changes(window_id, stratum, signed b, sv, svv) + counts(window_id, stratum, n_seen) -> partials of every window, accumulated: nothing that stayed is read again."""
    run = Window.partitionBy("stratum").orderBy("window_id")
    both = counts.join(changes, ["window_id", "stratum"], "full_outer")
    summed = [F.sum(F.coalesce(c, F.lit(0).cast(t))).over(run).alias(c) for c, t in (("b", "long"), ("sv", "decimal(38,2)"), ("svv", "decimal(38,4)"))]
    return both.select("window_id", "stratum", F.col("n_seen").alias("n_all"), *summed).where("n_all IS NOT NULL")


def totals_from_deltas(deltas: DataFrame, windows: DataFrame, by: tuple[str, ...] = ("stratum",)) -> DataFrame:
    """Per-window partials (b, sv) accumulated from signed deltas alone."""
    step = deltas.groupBy("window_id", *by).agg(F.sum("sign").alias("b"), F.sum(F.col("sign") * F.col("value")).alias("sv"))
    grid = windows.join(deltas.select(*by).distinct())  # windows x strata
    run = Window.partitionBy(*by).orderBy("window_id")
    return grid.join(step, ["window_id", *by], "left").select("window_id", *by, F.sum(F.coalesce("b", F.lit(0))).over(run).alias("b"), F.sum(F.coalesce("sv", F.lit(0).cast("decimal(38,2)"))).over(run).alias("sv"))
