"""Named queries of the window loop: answers that come out of the memo, its costs and budgets, the by-key prototype, the memo's replica."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from slidesample.functions.hashing import SPAN, priority, priority_sql
from slidesample.functions.tscore import corrections
from slidesample.operators import estimate, incremental, windows
from slidesample.operators.budget import Budget, Past, sample_size
from slidesample.operators.loop import WindowLoop, run_windows
from slidesample.operators.memo import shared_folder
from slidesample.operators.spec import AggregateSpec
from slidesample.plans.base import SEED, EventRun, chain_sql, events_sql, total_sql
from slidesample.sources import tables

QUERIES, ORACLE = {}, {}
#: The loop's windows are a third of the stream and move by half of that: five windows, each a few jobs.
LOOP = {"step_pct": 50, "parts": 3}


def query(sql=None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


def looped(spark, sf, spec=AggregateSpec("sum"), budget=None, replica=False, **options):
    run = EventRun(spark, sf, **LOOP)
    folder = f"{shared_folder(spark)}/memo/{uuid.uuid4().hex}"
    budget = budget or Budget("size", run.size)
    loop = WindowLoop(spark, folder, spec, budget, run.slide.length, run.slide.step, run.slide.pane, seed=SEED, replica=f"{folder}-replica" if replica else None)
    return run, loop, run_windows(run.items, loop, run.slide.count, **options)


_E50 = events_sql(**LOOP)
_SPECS = {
    "sum of values": (AggregateSpec("sum"), total_sql("chain")),
    "count above 50": (AggregateSpec("count", where="value > 50"), total_sql("chain", "CASE WHEN value > 50 THEN 1 ELSE 0 END")),
    "average": (AggregateSpec("avg"), total_sql("chain", scale="n_seen")),
}


@query(f"WITH RECURSIVE {_E50}, {chain_sql()} SELECT window_id, estimate, margin, n_sampled, n_seen FROM ({_SPECS['sum of values'][1]})")
def window_loop_sum(spark, sf):
    """The loop, window by window with its memo on disk; the SQL sums every biased sample from scratch."""
    return looped(spark, sf)[2][0]


@query(f"WITH RECURSIVE {_E50}, {chain_sql()} SELECT window_id, estimate, margin FROM ({_SPECS['count above 50'][1]})")
def window_loop_count(spark, sf):
    """Another user query through the same loop, unchanged otherwise."""
    return looped(spark, sf, _SPECS["count above 50"][0])[2][0].select("window_id", "estimate", "margin")


@query(f"WITH RECURSIVE {_E50}, {chain_sql()} SELECT window_id, CAST(max(value) AS DOUBLE) AS estimate, count(*) AS n_sampled FROM chain GROUP BY 1")
def window_loop_max(spark, sf):
    """An aggregate without an inverse: partials of unchanged chunks are read back."""
    return looped(spark, sf, AggregateSpec("max"))[2][0].select("window_id", "estimate", "n_sampled")


@query(f"""WITH RECURSIVE {_E50}, {chain_sql()}, i AS (SELECT window_id, count(*) AS n_sampled, count(*) FILTER (from_memo) AS n_known FROM chain GROUP BY 1),
s AS (SELECT window_id, CAST(sum(n_seen) AS BIGINT) AS n_seen FROM counts GROUP BY 1)
SELECT window_id, n_seen, n_sampled, n_known, n_sampled - n_known + coalesce(lag(n_sampled) OVER (ORDER BY window_id) - n_known, 0) AS values_read FROM i JOIN s USING (window_id)""")
def window_loop_work(spark, sf):
    """What the loop read: values of items that entered or left, and no others."""
    return looped(spark, sf)[2][1].select("window_id", "n_seen", "n_sampled", "n_known", "values_read")


@query()
def window_loop_latency(spark, sf):
    """Measured latency, throughput and violations under a latency budget, which the size follows."""
    return looped(spark, sf, budget=Budget("latency", 1.5))[2][1].select("window_id", "sample_size", "seconds", "items_per_second", "over", "violations")


@query(f"WITH RECURSIVE {events_sql(**LOOP, size='(SELECT CASE WHEN counts.window_id < 2 THEN ns WHEN counts.window_id < 4 THEN 2 * ns ELSE ns // 2 END FROM p)')}, {chain_sql()} SELECT window_id, count(*) AS n_sampled, count(*) FILTER (from_memo) AS n_known FROM chain GROUP BY 1")
def window_loop_budget_changes(spark, sf):
    """The budget doubles at window 2 and falls to a quarter of that at window 4, in the middle of the run."""
    size = EventRun(spark, sf, **LOOP).size
    out = looped(spark, sf, budgets={2: Budget("size", 2 * size), 4: Budget("size", size // 2)})[2][1]
    return out.select("window_id", "n_sampled", "n_known")


@query(f"WITH RECURSIVE {_E50}, {chain_sql()} SELECT stratum, count(*) AS n, sum(value) AS total FROM chain WHERE window_id = (SELECT max(window_id) FROM win) GROUP BY 1")
def memo_replica(spark, sf):
    """The memo's second copy, written in the background, after the first copy of the last window was lost."""
    _, loop, _ = looped(spark, sf, replica=True)
    last = loop.window_id - 1
    loop.store.lose("items", last)
    return loop.memo_items("bigint").groupBy("stratum").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


_PAST = [Past(100, 1.1), Past(200, 1.9), Past(400, 4.2), Past(800, 7.9)]
_KINDS = {
    "fraction": (Budget("fraction", 0.2), _PAST), "size": (Budget("size", 150), _PAST), "tokens": (Budget("tokens", 500.0, per_item=2.5), _PAST), "latency": (Budget("latency", 2.0), _PAST),
    "latency_over": (Budget("latency", 5.0), [*_PAST, Past(800, 8.0, True)]), "accuracy": (Budget("accuracy", 900.0), [Past(100, 1.0, False, 250000.0)]), "accuracy_first": (Budget("accuracy", 900.0), []),
}
_Z = corrections(0.975)[0]
_H = "(VALUES (100, 1.1::DOUBLE), (200, 1.9::DOUBLE), (400, 4.2::DOUBLE), (800, 7.9::DOUBLE)) h(n, s)"
_SIZES = {
    "fraction": "k // 5", "size": "150", "tokens": "200", "latency": f"(SELECT floor((0.95::DOUBLE * 2.0 - regr_intercept(s, n)) / regr_slope(s, n)) FROM {_H})", "latency_over": "450",
    "accuracy": f"ceil(k * 250000.0::DOUBLE / (250000.0::DOUBLE + pow(900.0 / {_Z!r}, 2)))", "accuracy_first": "k // 10",
}


@query("WITH w AS (SELECT count(*) // 10 AS k FROM events) " + " UNION ALL ".join(f"SELECT '{kind}' AS budget, CAST(least(k, {size}) AS BIGINT) AS sample_size FROM w" for kind, size in _SIZES.items()))
def budget_kinds(spark, sf):
    """Every kind of budget through the one entry point that the loop asks."""
    seen = tables.load(spark, sf, "events").count() // 10
    return spark.createDataFrame([(k, sample_size(b, past, seen)) for k, (b, past) in _KINDS.items()], "budget string, sample_size long")


_TENTH = SPAN // 10


def slid_partials(parts, strata, slide):
    """Partials of (pane, stratum), several rows each, -> partials of every window and stratum, by un-reducing.  Panes without items are added as zeros, not joined."""
    columns = ["n_all", "b", "sv", "svv"]
    kinds = dict(parts.dtypes)
    panes = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(-(-slide.total // slide.pane) - 1).cast("long")))
    zeros = strata.withColumn("pane", panes).select("pane", "stratum", *[F.lit(0).cast(kinds[c]).alias(c) for c in columns])
    full = parts.unionByName(zeros).groupBy("pane", "stratum").agg(*[F.sum(c).alias(c) for c in columns])
    return incremental.slide_invertible(full, slide.length // slide.pane, slide.step // slide.pane, columns, ("stratum",)).where("n_all > 0")


def by_key_windows(items, slide, kept, query=lambda sampled: sampled):
    """By-key sampling at a rate, once for each item, and sliding sums with an inverse: answers of all windows.

    `kept` says whether an item is in the sample; `query` turns sampled items into items with the `value` to sum (joins, conditions) and sees no others.
    Items that are not sampled are only counted.
    """
    pane = windows.pane_of(slide).alias("pane")
    v = F.coalesce(F.col("value").cast("decimal(18,2)"), F.lit(0).cast("decimal(18,2)"))
    none = F.lit(0).cast("long")
    seen = items.groupBy(pane, "stratum").agg(F.count("*").alias("n_all")).select("pane", "stratum", "n_all", none.alias("b"), none.cast("decimal(28,2)").alias("sv"), none.cast("decimal(38,4)").alias("svv"))
    sums = query(items.where(kept)).groupBy(pane, "stratum").agg(F.count("*").alias("b"), F.sum(v).cast("decimal(28,2)").alias("sv"), F.sum(v * v).cast("decimal(38,4)").alias("svv"))
    parts = seen.unionByName(sums.select("pane", "stratum", none.alias("n_all"), "b", "sv", "svv"))
    parts = slid_partials(parts, items.select("stratum").distinct(), slide)
    doubles = parts.withColumn("sv", F.col("sv").cast("double")).withColumn("svv", F.col("svv").cast("double"))
    return estimate.with_margin(estimate.total_terms(doubles, ("window_id",)))


@query(f"WITH {events_sql()}, kept AS (SELECT * FROM assigned WHERE u0 < {_TENTH}) SELECT window_id, n_sampled, n_seen, estimate, margin FROM ({total_sql('kept')})")
def prototype_sum_by_window(spark, sf):
    """By-key sampling at the budget's rate and a reversible reduce over panes; the SQL estimates every window from scratch."""
    run = EventRun(spark, sf)
    out = by_key_windows(run.items, run.slide, priority(SEED, F.col("item_id")) < _TENTH)
    return out.select("window_id", "n_sampled", "n_seen", "estimate", "margin")
