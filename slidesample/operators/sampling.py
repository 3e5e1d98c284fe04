"""Fixed-size samples as bottom-k by hashed priority, and the other designs they are compared with.

Keeping the items with the smallest hashed priorities has the law of a reservoir (every subset is equally likely), needs no arrival order,
and merges: the sample of a window is the bottom of the union of its panes' bottoms.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slidesample.functions.hashing import HEX, SPAN, priority, priority_of


def fixed_size_sample(assigned: DataFrame, quotas: DataFrame, most: int, by: tuple[str, ...] = ("window_id",)) -> DataFrame:
    """The quota's smallest priorities of each stratum; assigned has them as `u`, or as `digest`, which is cheaper.

    Priorities above their group's cut never leave the scan; what is left meets a constant bound `most`, then the exact quota.  Rows with the cuts
    (one a group) travel to the items, never the other way: Spark's size estimates do not know that an item is in many windows.
    """
    order = Window.partitionBy(*by, "stratum").orderBy("u", "item_id")
    digits = F.col("digest") if "digest" in assigned.columns else F.lpad(F.lower(F.hex("u")), HEX, "0")
    rows = assigned.withColumn("_head", F.substring(digits, 1, HEAD))
    low = rows.join(F.broadcast(quota_cuts(rows, quotas, by)), [*by, "stratum"]).where("_head <= _cut").drop("_head", "_cut")
    if "digest" in assigned.columns:
        low = low.withColumn("u", priority_of(F.col("digest"))).drop("digest")
    return low.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= most).where(F.col("rank") <= F.col("quota"))


#: Leading digits of a priority that items are counted by.
HEAD = 3


def reach(quota: Column, seen: Column) -> Column:
    """How far up first digits go that hold the quota, with much to spare (above eight standard deviations)."""
    return F.ceil(F.lit(16.0**HEAD) * (quota + 8 * F.sqrt(quota) + 40) / seen)


def quota_cuts(rows: DataFrame, quotas: DataFrame, by: tuple[str, ...] = ("window_id",)) -> DataFrame:
    """quotas with `_cut`, the first digits (`_head`) of priorities up to which a group holds its quota; groups without a quota are left out.

    Items are counted by their priority's first digits, partial sums before the shuffle, and only as far up as the quota should reach with much to spare.
    Exact all the same: a group that holds less than its quota there is not cut at all.
    """
    keys, top = [*by, "stratum"], 16**HEAD - 1
    wanted = F.broadcast(quotas.where("quota > 0"))
    near = wanted.select(*keys, "quota", F.lpad(F.lower(F.hex(F.least(F.lit(top), reach(F.col("quota"), F.col("n_seen"))).cast("long"))), HEAD, "0").alias("_reach"))
    held = rows.select(*keys, "_head").join(F.broadcast(near), keys).where("_head <= _reach").groupBy(*keys, "quota", "_head").agg(F.count("*").alias("_n"))
    upto = F.sum("_n").over(Window.partitionBy(*keys).orderBy("_head"))
    cut = held.withColumn("_upto", upto).where("_upto >= quota").groupBy(*keys).agg(F.min("_head").alias("_cut"))
    return wanted.join(cut, keys, "left").fillna("f" * HEAD, ["_cut"])


def pane_bottom_k(items: DataFrame, most: int) -> DataFrame:
    """Candidates of each (pane, stratum): at most `most` smallest permanent priorities."""
    order = Window.partitionBy("pane", "stratum").orderBy("u", "item_id")
    return items.withColumn("pane_rank", F.row_number().over(order)).where(F.col("pane_rank") <= most)


def merge_bottom_k(candidates: DataFrame, panes: DataFrame, quotas: DataFrame, most: int) -> DataFrame:
    """Window samples out of pane candidates."""
    return fixed_size_sample(candidates.join(panes, "pane"), quotas, most)


def priority_cuts(panes: DataFrame, edges: DataFrame, quotas: DataFrame, span: int = SPAN, levels: int = 4096) -> DataFrame:
    """pane, stratum, `cut`: no item of the pane with a permanent priority above the cut is in any window's sample.

    panes(pane, stratum, u).  Priorities are counted by level (partial sums before the shuffle, `levels` rows a cell at most); a window's cut is the
    first level at which its panes hold its quota together, a pane's cut the largest of its windows'.  Exact, no slack needed.
    """
    level = F.least(F.lit(levels - 1), F.floor(F.col("u") / F.lit(span / levels))).cast("int")
    counted = panes.groupBy("pane", "stratum", level.alias("level")).agg(F.count("*").alias("n"))
    merged = counted.join(edges, "pane").groupBy("window_id", "stratum", "level").agg(F.sum("n").alias("n"))
    upto = F.sum("n").over(Window.partitionBy("window_id", "stratum").orderBy("level"))
    held = merged.withColumn("_upto", upto).join(quotas.select("window_id", "stratum", "quota"), ["window_id", "stratum"]).where(F.col("_upto") - F.col("n") < F.col("quota"))
    last = held.groupBy("window_id", "stratum").agg(F.max("level").alias("level"))
    cut = F.when(F.max("level") == levels - 1, F.lit(float(span))).otherwise((F.max("level") + 1) * F.lit(span / levels))
    return last.join(edges, "window_id").groupBy("pane", "stratum").agg(cut.alias("cut"))


def bernoulli_by_stratum(items: DataFrame, fractions: DataFrame, seed: int | str) -> DataFrame:
    """Each item independently with its stratum's fraction; size varies, no shuffle but the small join."""
    u = priority(seed, F.col("item_id")).cast("double") / F.lit(float(SPAN))
    return items.join(F.broadcast(fractions), "stratum").where(u < F.col("fraction"))  # one row per stratum


def simple_random_sample(items: DataFrame, size: int, seed: int | str) -> DataFrame:
    """`size` items regardless of strata (top-k, no full sort)."""
    return items.withColumn("u", priority(seed, F.col("item_id"))).orderBy("u", "item_id").limit(size)


def global_sample(assigned: DataFrame, size: int, by: tuple[str, ...] = ("window_id",)) -> DataFrame:
    """One reservoir for all strata: `size` items per window."""
    order = Window.partitionBy(*by).orderBy("u", "item_id")
    return assigned.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= size)


def merge_reservoirs(a: DataFrame, seen_a: int, b: DataFrame, seen_b: int, size: int, seed: int) -> DataFrame:
    """One reservoir of two: the smallest of all priorities that the two populations would have had.

    A reservoir of m out of n stands for the m smallest of n uniform priorities; these are drawn for its items in a random order by their spacings
    (the j-th adds an exponential over n - j + 1).  So how many come from each side is hypergeometric, as it must be.
    """

    def drawn(df, seen, salt):
        order = Window.partitionBy("_side").orderBy(priority(f"{seed}{salt}", F.col("item_id")), "item_id")
        u = priority(f"{seed}{salt}gap", F.col("item_id")).cast("double") / F.lit(float(SPAN))
        rows = df.withColumn("_side", F.lit(salt)).withColumn("_j", F.row_number().over(order))
        return rows.withColumn("_at", F.sum(-F.log(1 - u) / (F.lit(seen) - F.col("_j") + 1)).over(order)).drop("_side", "_j")  # sample-sized

    return drawn(a, seen_a, "a").unionByName(drawn(b, seen_b, "b")).orderBy("_at", "item_id").limit(min(size, seen_a + seen_b)).drop("_at")
