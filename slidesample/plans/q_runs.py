"""Named queries: the four ways to run a window query, measures, budgets, stratification, recovery, experiment workloads."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slidesample.functions.hashing import digest, priority, priority_sql
from slidesample.functions.tscore import corrections
from slidesample.operators import allocate, budget, carryover, estimate, incremental, memo, sampling, stratify, windows
from slidesample.plans.base import SEED, EventRun, chain_sql, events_sql, margin_sql, parts_sql, quota_sql, terms_sql, total_sql
from slidesample.plans.q_estimates import _CH, _ST, E_, chunks, states
from slidesample.plans.q_sampling import _V, DELTAS, varying_rows
from slidesample.sources import tables

QUERIES, ORACLE = {}, {}


def query(sql=None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# --- four ways to run ------------------------------------------------------------------------------------------------

_EXACT = f"WITH {E_} SELECT window_id, count(*) AS n, sum(value) AS total FROM assigned GROUP BY 1"


@query(_EXACT)
def exact_sum_by_window(spark, sf):
    """Recompute: every window reads all its items."""
    run = EventRun(spark, sf)
    return windows.assign(run.items, run.slide).groupBy("window_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


@query(_EXACT)
def incremental_sum_by_window(spark, sf):
    """Incremental only: pane partials and the inverse reduce."""
    from slidesample.plans.q_estimates import sliding

    return sliding(spark, sf).select("window_id", F.col("n").cast("long").alias("n"), F.col("sv").alias("total"))


@query(f"WITH {E_} SELECT window_id, n_sampled, estimate, margin FROM ({total_sql('sample')})")
def sampled_sum_by_window(spark, sf):
    """Approximate only: a fresh sample in every window."""
    run = EventRun(spark, sf)
    return estimate.estimate_total(run.sample, run.counts, F.col("value")).select("window_id", "n_sampled", "estimate", "margin")


@query(f"WITH RECURSIVE {E_}, {chain_sql('newest_first')} SELECT window_id, n_sampled, estimate, margin, n_known FROM ({total_sql('chain')}) JOIN (SELECT window_id, count(*) FILTER (from_memo) AS n_known FROM chain GROUP BY 1) USING (window_id)")
def combined_sum_by_window(spark, sf):
    """Approximate and incremental: samples biased towards known items; totals accumulate what enters and leaves, and no item that stays is read again."""
    run = EventRun(spark, sf)
    changes = run.changes("biased", "newest_first")
    v = F.col("value")
    delta = changes.groupBy("window_id", "stratum").agg(
        F.sum("sign").alias("b"), F.sum(F.col("sign") * v).cast("decimal(38,2)").alias("sv"), F.sum(F.col("sign") * v * v).cast("decimal(38,4)").alias("svv"), F.count_if(F.col("sign") == 1).alias("entering")
    )
    parts = incremental.running_partials(delta.drop("entering"), run.counts)
    doubles = parts.withColumn("sv", F.col("sv").cast("double")).withColumn("svv", F.col("svv").cast("double"))
    answers = estimate.with_margin(estimate.total_terms(doubles, ("window_id",)))
    entered = delta.groupBy("window_id").agg(F.sum("entering").alias("entering"))
    out = answers.join(entered, "window_id", "left")
    return out.select("window_id", "n_sampled", "estimate", "margin", (F.col("n_sampled") - F.coalesce("entering", F.lit(0))).alias("n_known"))


@query(f"WITH {E_} SELECT window_id, n_sampled, estimate, margin FROM ({total_sql('csample')})")
def coordinated_sum_by_window(spark, sf):
    """Permanent priorities: every item hashed once, all windows in one job, almost full reuse."""
    run = EventRun(spark, sf)
    return estimate.estimate_total(run.coordinated, run.counts, F.col("value")).select("window_id", "n_sampled", "estimate", "margin")


# --- measures --------------------------------------------------------------------------------------------------------


def memo_average(run, chain):
    alive = chain.withColumn("window_id", F.col("window_id") + 1).where((F.col("window_id") < run.slide.count) & (F.col("seq") >= F.col("window_id") * run.slide.step))
    per = alive.groupBy("window_id", "stratum").agg(F.count("*").alias("n"))
    return per.groupBy("stratum").agg(F.round(F.sum("n") / F.lit(run.slide.count - 1), 4).alias("memo_avg"))


def _memo_sql(chain="chain", label=""):
    return f"SELECT {label}stratum, round(CAST(count(*) AS DOUBLE) / (SELECT count(*) - 1 FROM win), 4) AS memo_avg FROM {chain} c JOIN win x ON x.window_id = c.window_id + 1 AND seq >= x.lo GROUP BY ALL"


@query(f"WITH RECURSIVE {events_sql(sub_streams=True)}, {chain_sql()} {_memo_sql()}")
def memo_avg_by_stratum(spark, sf):
    run = EventRun(spark, sf, sub_streams=True)
    return memo_average(run, run.chain())


def scheduled(spark, sf, plan, sample_share=10, sub_streams=True):
    """Fresh samples of a tenth of each window on a schedule of changing sizes, and their quotas."""
    items = tables.event_items(spark, sf)
    items = tables.thinned(items) if sub_streams else items
    sched = spark.createDataFrame(plan, "window_id long, lo long, hi long")
    assigned = windows.assign_schedule(items, sched, max(1, (plan[0][2] - plan[0][1]) // 50)).withColumn("u", priority(SEED, F.col("item_id"), F.col("window_id")))
    counts = assigned.groupBy("window_id", "stratum", "lo", "hi").agg(F.count("*").alias("n_seen"))
    size = F.call_function("div", F.col("hi") - F.col("lo"), F.lit(sample_share).cast("long"))
    quotas = allocate.proportional_quota(counts.withColumn("_size", size), F.col("_size"))
    return assigned, quotas, sampling.fixed_size_sample(assigned, quotas, max(h - lo for _, lo, h in plan) // sample_share)


def needed_and_memoized(chain, plan):
    """Per window: items needed, memoized items that are still inside it (however many are needed), and those reused."""
    bounds = chain.sparkSession.createDataFrame(plan, "window_id long, lo long, hi long").withColumnRenamed("window_id", "_w")
    alive = chain.join(F.broadcast(bounds), F.col("window_id") + 1 == F.col("_w")).where((F.col("seq") >= bounds["lo"]) & (F.col("seq") < F.col("hi")))  # one row per window of the plan
    held = alive.groupBy(F.col("_w").alias("window_id")).agg(F.count("*").alias("memoized"))
    needed = chain.groupBy("window_id").agg(F.count("*").alias("needed"), F.count_if("from_memo").alias("reused"))
    return needed.join(held, "window_id", "left").fillna(0, ["memoized"])


_VS = events_sql(sub_streams=True, win="SELECT * FROM v", size="(SELECT (hi - lo) // 10 FROM win z WHERE z.window_id = counts.window_id)")
_NM = """nm AS (SELECT window_id, count(*) AS needed, count(*) FILTER (from_memo) AS reused, any_value(memoized) AS memoized FROM chain JOIN (
  SELECT x.window_id, count(c.item_id) AS memoized FROM win x LEFT JOIN chain c ON c.window_id + 1 = x.window_id AND c.seq >= x.lo AND c.seq < x.hi GROUP BY 1) USING (window_id) GROUP BY 1)"""


@query(f"WITH RECURSIVE {_V}, {_VS}, {chain_sql()}, {_NM} SELECT window_id, needed, memoized, reused FROM nm")
def needed_vs_memoized(spark, sf):
    """Items that the sample needs beside those that the memo holds; more held than needed means full reuse."""
    plan = varying_rows(tables.load(spark, sf, "events").count())
    _, _, sample = scheduled(spark, sf, plan)
    return needed_and_memoized(carryover.carry_chain(sample, SEED), plan)


@query(f"WITH RECURSIVE {E_}, {_CH}, {_ST}, i AS (SELECT *, sampled - reused + coalesce(lag(sampled) OVER (ORDER BY window_id) - reused, 0) AS values_read FROM (SELECT window_id, count(*) AS sampled, count(*) FILTER (from_memo) AS reused FROM chain GROUP BY 1)), c AS (SELECT window_id, count(*) FILTER (state = 'fresh') AS fresh_chunks, count(*) FILTER (state = 'reused') AS reused_chunks FROM st GROUP BY 1), s AS (SELECT window_id, CAST(sum(n_seen) AS BIGINT) AS seen FROM counts GROUP BY 1) SELECT * FROM s JOIN i USING (window_id) JOIN c USING (window_id)")
def work_counters(spark, sf):
    run, chain, chunk = chunks(spark, sf)
    i = chain.groupBy("window_id").agg(F.count("*").alias("sampled"), F.count_if("from_memo").alias("reused"))
    read = run.changes("biased", "newest_first").groupBy("window_id").agg(F.count("*").alias("values_read"))
    i = i.join(read, "window_id", "left").fillna(0, ["values_read"])
    c = states(chunk).groupBy("window_id").agg(F.count_if(F.col("state") == "fresh").alias("fresh_chunks"), F.count_if(F.col("state") == "reused").alias("reused_chunks"))
    return run.counts.groupBy("window_id").agg(F.sum("n_seen").alias("seen")).join(i, "window_id").join(c, "window_id")


SEEDS = 40
_SEEDED = f"""e AS (SELECT event_id AS item_id, event_type AS stratum, CAST(value AS DECIMAL(18,2)) AS value, s * 1000 + event_id // (SELECT count(*) // 10 FROM events) AS window_id, {priority_sql('s', 'event_id')} AS u FROM events, (SELECT unnest(range(1, {SEEDS + 1})) AS s) WHERE event_id < (SELECT count(*) // 10 * 10 FROM events)),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM e GROUP BY ALL), q AS ({quota_sql('counts', 'SELECT count(*) // 100 FROM events')}),
sample AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u, item_id) AS rk FROM e) JOIN q USING (window_id, stratum) WHERE rk <= quota),
x AS (SELECT window_id, CAST(sum(value) AS DOUBLE) AS exact FROM e GROUP BY 1)"""


def seeded(spark, sf):
    """Independent samples of ten tumbling windows under many seeds, as windows seed * 1000 + window."""
    items = tables.event_items(spark, sf)
    total = items.count()
    w = total // 10
    e = items.where(F.col("seq") < w * 10).withColumn("s", F.explode(F.sequence(F.lit(1), F.lit(SEEDS))))
    e = e.withColumn("window_id", (F.col("s") * 1000 + F.call_function("div", F.col("seq"), F.lit(w).cast("long"))).cast("long")).withColumn("u", priority(F.col("s"), F.col("item_id")))
    counts = allocate.stratum_counts(e, "window_id")
    sample = sampling.fixed_size_sample(e, allocate.proportional_quota(counts, total // 100), total // 100)
    return e, counts, sample


@query(f"WITH {_SEEDED} " + " UNION ALL ".join(f"SELECT {c} AS confidence, count(*) AS intervals, count(*) FILTER (abs(estimate - exact) <= margin) AS covering FROM ({total_sql('sample', confidence=c)}) JOIN x USING (window_id)" for c in (0.9, 0.95, 0.99)))
def coverage_by_confidence(spark, sf):
    """How many intervals hold the exact sum."""
    e, counts, sample = seeded(spark, sf)
    exact = e.groupBy("window_id").agg(F.sum("value").cast("double").alias("exact"))
    terms = estimate.total_terms(estimate.stratum_parts(sample, counts, F.col("value")), ("window_id",))
    return union(
        [
            estimate.with_margin(terms, c).join(exact, "window_id").agg(F.lit(c).cast("decimal(3,2)").alias("confidence"), F.count("*").alias("intervals"), F.count_if(F.abs(F.col("estimate") - F.col("exact")) <= F.col("margin")).alias("covering"))
            for c in (0.9, 0.95, 0.99)
        ]
    )


_LI = f"""li AS (SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y-%m-%d')) AS item_id, 'p' || CAST(floor(l_extendedprice / 20000) AS BIGINT) AS stratum, CAST(l_extendedprice AS DECIMAL(18,2)) AS value FROM lineitem),
e AS (SELECT CAST(s AS BIGINT) AS window_id, li.*, {priority_sql('s', 'item_id')} AS u FROM li, (SELECT unnest(range(1, 21)) AS s)),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM e GROUP BY ALL), q AS ({quota_sql('counts', 'SELECT count(*) // 50 FROM lineitem')}),
st AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u, item_id) AS rk FROM e) JOIN q USING (window_id, stratum) WHERE rk <= quota),
gl AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id ORDER BY u, item_id) AS rk FROM e) WHERE rk <= (SELECT count(*) // 50 FROM lineitem)),
r AS (SELECT 'stratified' AS design, window_id, sum(CAST(n_seen AS DOUBLE) / quota * CAST(sv AS DOUBLE)) AS est FROM (SELECT window_id, stratum, any_value(n_seen) AS n_seen, any_value(quota) AS quota, sum(value) AS sv FROM st GROUP BY 1, 2) GROUP BY 2
UNION ALL SELECT 'unstratified', window_id, CAST(sum(value) AS DOUBLE) * (SELECT count(*) FROM lineitem) / (SELECT count(*) // 50 FROM lineitem) FROM gl GROUP BY 2)"""


def design_sums(items, quotas, total, size, runs=20, cut=True):
    """Of each run and stratum: n, q, sum of the stratified sample (sv) and of the stratum's part of the global one (sv_global), items held for either.

    Both designs read the same priorities, so an item is hashed once a run; with `cut`, rows that neither design can be expected to reach never leave the scan.
    Where that holds fewer items than a quota (held, held_global), the answer is not exact and the sums must be drawn without it.
    """
    top = 16**sampling.HEAD - 1
    reach = lambda q, n: F.least(F.lit(top), sampling.reach(q, n)) if cut else F.lit(top)
    plan = quotas.withColumn("_global", reach(F.lit(size), F.lit(total))).withColumn("_reach", F.greatest(reach(F.col("quota"), F.col("n_seen")), "_global"))
    for c in ("_global", "_reach"):
        plan = plan.withColumn(c, F.lpad(F.lower(F.hex(F.col(c).cast("long"))), sampling.HEAD, "0"))
    e = items.join(F.broadcast(plan), "stratum").withColumn("window_id", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(runs).cast("long"))))
    e = e.withColumn("digest", digest(F.col("window_id"), F.col("item_id"))).where(F.substring("digest", 1, sampling.HEAD) <= F.col("_reach"))
    e = e.withColumn("in_global", F.substring("digest", 1, sampling.HEAD) <= F.col("_global")).drop("_reach", "_global")
    ranks = {k: F.row_number().over(Window.partitionBy("window_id", *by).orderBy("digest", "item_id")) for k, by in (("rank_global", []), ("rank", ["stratum"]))}
    e = e.withColumns(ranks)
    within = lambda test: F.sum(F.when(test, F.col("value")))
    return e.groupBy("window_id", "stratum").agg(
        F.first("n_seen").alias("n"), F.first("quota").alias("q"), F.count("*").alias("held"), F.count_if("in_global").alias("held_global"),
        within(F.col("rank") <= F.col("quota")).cast("double").alias("sv"), within(F.col("rank_global") <= size).alias("sv_global"),
    )


@query(f"WITH {_LI} SELECT design, count(*) AS runs, round(stddev_samp(est) / 1e6, 4) AS spread_millions, round(avg(est) / (SELECT CAST(sum(value) AS DOUBLE) FROM li), 6) AS mean_ratio FROM r GROUP BY 1")
def variance_by_design(spark, sf):
    """Precision (spread of repeats) and accuracy (mean against the truth), stratified against one global reservoir; strata are price bands."""
    items = tables.lineitem_items(spark, sf, band=True).select("item_id", "stratum", "value")
    bands = allocate.stratum_counts(items.withColumn("window_id", F.lit(0).cast("long")), "window_id").localCheckpoint()  # one row a band
    total = bands.agg(F.sum("n_seen")).first()[0] or 0
    size = total // 50
    quotas = allocate.proportional_quota(bands, size).drop("window_id")  # the same in all runs
    sums = design_sums(items, quotas, total, size).localCheckpoint()  # one row a run and band
    short = sums.groupBy("window_id").agg(F.max(F.col("held") < F.col("q")).alias("s"), (F.sum("held_global") < size).alias("g")).where("s OR g")
    if not short.isEmpty():
        sums = design_sums(items, quotas, total, size, cut=False)
    a = sums.where("q > 0").groupBy("window_id").agg(F.sum(F.col("n") / F.col("q") * F.col("sv")).alias("est")).withColumn("design", F.lit("stratified"))
    b = sums.groupBy("window_id").agg((F.sum("sv_global").cast("double") * total / size).alias("est")).withColumn("design", F.lit("unstratified"))
    exact = items.agg(F.sum("value").cast("double").alias("exact"))
    out = a.unionByName(b).groupBy("design").agg(F.count("*").alias("runs"), F.stddev_samp("est").alias("sd"), F.avg("est").alias("mean"))
    return out.crossJoin(exact).select("design", "runs", F.round(F.col("sd") / 1e6, 4).alias("spread_millions"), F.round(F.col("mean") / F.col("exact"), 6).alias("mean_ratio"))  # one row


def _gap(sample, label):
    return f"SELECT '{label}' AS carry, window_id, round(max(abs(b / sb - n_seen / sn)), 6) AS gap FROM (SELECT *, CAST(sum(b) OVER (PARTITION BY window_id) AS DOUBLE) AS sb, CAST(sum(n_seen) OVER (PARTITION BY window_id) AS DOUBLE) AS sn FROM (SELECT c.window_id, c.stratum, c.n_seen, count(s.item_id) AS b FROM counts c LEFT JOIN {sample} s ON s.window_id = c.window_id AND s.stratum = c.stratum GROUP BY ALL)) GROUP BY 2"


@query(f"WITH RECURSIVE {events_sql(sub_streams=True)}, {chain_sql(name='ch1')}, {chain_sql(carry='all', name='ch2')} {_gap('ch1', 'biased')} UNION ALL {_gap('ch2', 'all')} UNION ALL {_gap('sample', 'none')}")
def proportionality_gap(spark, sf):
    """Largest difference between a stratum's share of the sample and of the window, for three ways to carry over."""
    run = EventRun(spark, sf, sub_streams=True)
    w = Window.partitionBy("window_id")
    out = []
    for carry in ("biased", "all", "none"):
        b = (run.sample if carry == "none" else run.chain(carry)).groupBy("window_id", "stratum").agg(F.count("*").alias("b"))
        both = run.counts.join(b, ["window_id", "stratum"], "left").fillna(0, ["b"])
        gap = F.abs(F.col("b") / F.sum("b").over(w) - F.col("n_seen") / F.sum("n_seen").over(w))
        out.append(both.withColumn("g", gap).groupBy("window_id").agg(F.round(F.max("g"), 6).alias("gap")).withColumn("carry", F.lit(carry)))
    return union(out)


_SAMPLES = {"hash": "ch_hash", "newest_first": "ch_new", "fresh": "sample", "coordinated": "csample"}
_CHAINS = f"{chain_sql(name='ch_hash')}, {chain_sql('newest_first', name='ch_new')}"


def four_samples(run):
    return {"hash": run.chain("biased", "hash"), "newest_first": run.chain("biased", "newest_first"), "fresh": run.sample, "coordinated": run.coordinated}


@query(f"WITH RECURSIVE {E_}, {_CHAINS} " + " UNION ALL ".join(f"SELECT '{k}' AS policy, round(avg((seq - lo) / CAST((SELECT w FROM p) AS DOUBLE)), 5) AS mean_position FROM {t} JOIN (SELECT window_id, lo FROM win) w2 USING (window_id) WHERE window_id >= 25".replace("(seq - lo)", "(seq - w2.lo)") for k, t in _SAMPLES.items()))
def sample_age_skew(spark, sf):
    """Mean relative position of sampled items after warm-up: .5 is uniform, less means old items linger."""
    run = EventRun(spark, sf)
    at = (F.col("seq") - F.col("window_id") * run.slide.step) / F.lit(float(run.slide.length))
    return union([s.where("window_id >= 25").agg(F.round(F.avg(at), 5).alias("mean_position")).withColumn("policy", F.lit(k)) for k, s in four_samples(run).items()])




@query(f"WITH RECURSIVE {E_}, {_CHAINS}, x AS (SELECT window_id, sum(CAST(value AS DOUBLE) + seq / 100.0) AS exact FROM assigned GROUP BY 1) " + " UNION ALL ".join(f"SELECT '{k}' AS policy, round(avg(estimate / exact - 1), 5) AS relative_bias FROM ({terms_sql(parts_sql(t, 'value + CAST(seq / 100.0 AS DECIMAL(18,2))'))}) JOIN x USING (window_id) WHERE window_id >= 25" for k, t in _SAMPLES.items()))
def trend_bias(spark, sf):
    """Values that drift: carry-over with hash refill lags behind, coordinated samples do not."""
    run = EventRun(spark, sf)
    value = F.col("value") + (F.col("seq") / 100).cast("decimal(18,2)")
    exact = run.assigned.groupBy("window_id").agg(F.sum(F.col("value").cast("double") + F.col("seq") / 100).alias("exact"))
    out = []
    for k, s in four_samples(run).items():
        terms = estimate.total_terms(estimate.stratum_parts(s, run.counts, value), ("window_id",)).join(exact, "window_id")
        out.append(terms.where("window_id >= 25").agg(F.round(F.avg(F.col("estimate") / F.col("exact") - 1), 5).alias("relative_bias")).withColumn("policy", F.lit(k)))
    return union(out)


# --- budgets ---------------------------------------------------------------------------------------------------------


@query("SELECT f AS fraction, CAST(floor(count(*) // 10 * f) AS BIGINT) AS sample_size FROM events, (SELECT unnest([0.1, 0.2, 0.4, 0.6, 0.8]) AS f) GROUP BY 1")
def budget_fraction(spark, sf):
    n = tables.load(spark, sf, "events").agg(F.call_function("div", F.count("*"), F.lit(10).cast("long")).alias("w"))
    return n.select(F.explode(F.array(*[F.lit(f).cast("decimal(2,1)") for f in (0.1, 0.2, 0.4, 0.6, 0.8)])).alias("fraction"), "w").select("fraction", budget.fraction_size(F.col("w"), 1.0).alias("w2"), F.floor(F.col("w") * F.col("fraction")).cast("long").alias("sample_size")).drop("w2")


@query("SELECT window_id, CAST(min(floor(tokens / per_item)) AS BIGINT) AS sample_size FROM (SELECT event_id % 10 AS window_id, CASE WHEN event_type = 'error' THEN 2.5::DOUBLE ELSE 1.0::DOUBLE END AS per_item, event_type, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS tokens FROM events GROUP BY ALL) GROUP BY 1")
def budget_tokens(spark, sf):
    """Event types are resources, the sums of their values what they may spend in a tenth of the events; an error costs 2.5 tokens, any other item one."""
    e = tables.event_items(spark, sf).withColumn("window_id", F.col("seq") % 10)
    resources = e.groupBy("window_id", F.col("stratum").alias("resource")).agg(F.sum("value").cast("double").alias("tokens"))
    return budget.token_size(resources.withColumn("per_item", F.when(F.col("resource") == "error", 2.5).otherwise(1.0)))


_HIST = [(100, 1.1), (200, 1.9), (400, 4.2), (800, 7.9)]
_HV = ", ".join(f"({n}, {s})" for n, s in _HIST)


@query("WITH h AS (SELECT event_type, hour(ts) AS hr, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) / 10000 AS seconds FROM events GROUP BY ALL) SELECT round(regr_slope(seconds, n), 6) AS per_item, round(regr_intercept(seconds, n), 6) AS fixed, CAST(greatest(0, floor((5.0 - regr_intercept(seconds, n)) / regr_slope(seconds, n))) AS BIGINT) AS sample_size FROM h")
def budget_latency(spark, sf):
    """History: of each type and hour of the day the number of events and their values, as ten-thousandths of a second."""
    history = tables.event_items(spark, sf).groupBy("stratum", F.hour("ts").alias("hr")).agg(F.count("*").alias("n"), (F.sum("value").cast("double") / 10000).alias("seconds"))
    out = budget.latency_size(history, 5.0)
    return out.select(F.round("b", 6).alias("per_item"), F.round("a", 6).alias("fixed"), "sample_size")


@query(f"WITH h(n, seconds) AS (VALUES {_HV}), f AS (SELECT regr_slope(seconds, n) AS b, regr_intercept(seconds, n) AS a FROM h), d AS (SELECT CAST(hour(ts) AS INTEGER) AS hr, count(*) AS c FROM events GROUP BY 1), m AS (SELECT avg(c) AS m FROM d) SELECT hr, round(c / m, 6) AS factor, CAST(greatest(0, floor((5.0 / (c / m) - a) / b)) AS BIGINT) AS sample_size FROM d, m, f")
def budget_diurnal(spark, sf):
    """Latency budget scaled by how busy each hour of the day is."""
    per = tables.event_items(spark, sf).groupBy(F.hour("ts").alias("hr")).agg(F.count("*").alias("c"))
    busy = per.withColumn("factor", F.col("c") / F.avg("c").over(Window.partitionBy()))
    fit = budget.latency_size(spark.createDataFrame(_HIST, "n int, seconds double"), 5.0).select("a", "b")
    out = busy.crossJoin(F.broadcast(fit))  # one row
    return out.select("hr", F.round("factor", 6).alias("factor"), F.greatest(F.lit(0), F.floor((F.lit(5.0) / F.col("factor") - F.col("a")) / F.col("b"))).cast("long").alias("sample_size"))


_Z = corrections(0.975)[0]


@query(f"WITH {E_}, t AS (SELECT *, bb * (svv - sv * sv / b) / (b - 1) AS qq FROM ({parts_sql('sample')})), x AS (SELECT window_id, CAST(sum(value) AS DOUBLE) AS exact FROM assigned GROUP BY 1), g AS (SELECT window_id, CAST(sum(bb) AS DOUBLE) AS k, sum(qq) AS q FROM t GROUP BY 1) SELECT window_id, CAST(least(k, ceil(k * q / (q + pow(0.05 * exact / {_Z!r}, 2)))) AS BIGINT) AS sample_size FROM g JOIN x USING (window_id)")
def budget_accuracy(spark, sf):
    """Sample for a margin of 5 % of the window's sum."""
    run = EventRun(spark, sf)
    exact = run.assigned.groupBy("window_id").agg(F.sum("value").cast("double").alias("exact"))
    return budget.accuracy_size(estimate.stratum_parts(run.sample, run.counts, F.col("value")).join(exact, "window_id"), F.col("exact") * 0.05)


@query(f"WITH {events_sql(size='(SELECT CASE WHEN counts.window_id % 8 < 4 THEN w // 10 ELSE w // 5 END FROM p)')} SELECT window_id, stratum, quota FROM quota")
def budget_changes(spark, sf):
    """Budgets per window: four windows with 10 %, four with 20 %, and so on."""
    run = EventRun(spark, sf)
    plan = run.counts.withColumn("_size", F.when(F.col("window_id") % 8 < 4, run.slide.length // 10).otherwise(run.slide.length // 5).cast("long"))
    return allocate.proportional_quota(plan, F.col("_size")).select("window_id", "stratum", "quota")


@query(f"""WITH RECURSIVE costs AS (SELECT hr, 0.001::DOUBLE * (k * 24) / (SELECT count(*) FROM events) AS c FROM (SELECT CAST(hour(ts) AS INTEGER) AS hr, count(*) AS k FROM events GROUP BY 1)),
r(window_id, n, violations) AS (SELECT 0, 1000, 0 UNION ALL
  SELECT window_id + 1, CAST(greatest(1, floor(n * CASE WHEN n * c > 1 THEN 0.9::DOUBLE / (n * c) ELSE least(1.1::DOUBLE, 1 / (n * c)) END)) AS INTEGER), violations + CASE WHEN n * c > 1 THEN 1 ELSE 0 END FROM r JOIN costs ON hr = window_id WHERE window_id < 23)
SELECT window_id, n AS sample_size, round(n * c, 4) AS cost, n * c > 1 AS "over", violations + CASE WHEN n * c > 1 THEN 1 ELSE 0 END AS violations FROM r JOIN costs ON hr = window_id""")
def budget_feedback(spark, sf):
    """Items cost more in the busy hours of the day: the sample shrinks once a violation is seen.  (`window_loop_latency` does the same on measured costs.)"""
    per = {r["hr"]: r["k"] for r in tables.event_items(spark, sf).groupBy(F.hour("ts").alias("hr")).agg(F.count("*").alias("k")).collect()}  # 24 rows
    total = sum(per.values())
    rows = budget.feedback([0.0] * 24, 1.0, 1000, lambda n, i: n * (0.001 * (per[i] * 24) / total))
    return spark.createDataFrame(rows, "window_id int, sample_size int, cost double, over boolean, violations int")


# --- stratification --------------------------------------------------------------------------------------------------


@query("""WITH RECURSIVE s AS (SELECT event_type AS stratum, count(*) AS n, avg(CAST(CAST(value AS DECIMAL(18,2)) AS DOUBLE)) AS m, var_samp(value) AS v FROM events GROUP BY 1),
e AS (SELECT a.stratum AS x, b.stratum AS y FROM s a JOIN s b ON abs(a.m - b.m) <= 1.5 * sqrt(a.v / a.n + b.v / b.n)),
r(x, y) AS (SELECT x, y FROM e UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x) SELECT x AS stratum, min(y) AS merged FROM r GROUP BY 1""")
def merge_similar_strata(spark, sf):
    return stratify.merge_similar(stratify.stratum_statistics(tables.event_items(spark, sf)), 1.5)


@query()
def bootstrap_strata(spark, sf):
    """Value classes learned from a first reservoir by bootstrap, applied to the whole stream."""
    items = tables.event_items(spark, sf)
    first = sampling.simple_random_sample(items, 500, "boot")
    return allocate.stratum_counts(stratify.assign_stratum(items, stratify.fit_bootstrap_strata(first)))


@query()
def semi_supervised_strata(spark, sf):
    out = stratify.self_train_strata(tables.load(spark, sf, "embeddings"))
    return out.where("NOT known").groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg((F.col("label") == F.col("predicted")).cast("double")), 4).alias("accuracy"))


@query("""WITH e AS (SELECT event_type AS stratum, CAST(CAST(value AS DECIMAL(18,2)) AS DOUBLE) AS x, lag(CAST(CAST(value AS DECIMAL(18,2)) AS DOUBLE)) OVER (PARTITION BY event_type ORDER BY event_id) AS y FROM events),
g AS (SELECT stratum, count(*) AS n, avg(x) AS mean, var_pop(x) AS within, corr(x, y) AS lag_1 FROM e GROUP BY 1), t AS (SELECT sum(n * mean) / sum(n) AS gm FROM g)
SELECT stratum, n, round(mean, 6) AS mean, round(within, 6) AS within, round((SELECT sum(n * pow(mean - gm, 2)) / sum(n) FROM g, t), 6) AS between, round(lag_1, 6) AS lag_1 FROM g""".replace("AS within,", 'AS "within",').replace("AS between", 'AS "between"').replace("round(within", 'round("within"'))
def stratum_homogeneity(spark, sf):
    return stratify.diagnostics(tables.event_items(spark, sf))


# --- losses of the memo ----------------------------------------------------------------------------------------------

_COLD = chain_sql("newest_first").replace("c.window_id + 1 AND c.seq >= x.lo", "c.window_id + 1 AND c.seq >= x.lo AND x.window_id <> 100")


@query(f"WITH RECURSIVE {E_}, {_COLD} SELECT window_id, count(*) AS n, count(*) FILTER (from_memo) AS n_known FROM chain GROUP BY 1")
def cold_window(spark, sf):
    """The memo is lost before window 100: that window reuses nothing, has its full sample, and the chain goes on from there."""
    run = EventRun(spark, sf)
    early = carryover.carry_chain(run.sample.where("window_id < 100"), SEED, "biased", "newest_first", run.slide.pane)
    late = carryover.carry_chain(run.sample.where("window_id >= 100"), SEED, "biased", "newest_first", run.slide.pane)
    return early.unionByName(late).groupBy("window_id").agg(F.count("*").alias("n"), F.count_if("from_memo").alias("n_known"))


@query(f"WITH {E_}, c AS (SELECT window_id, seq // (SELECT d FROM p) AS pane, stratum, count(*) AS n, sum(CAST({priority_sql(chr(39) + 'fp' + chr(39), 'item_id')} AS DECIMAL(38,0))) AS h FROM csample GROUP BY ALL) SELECT CASE WHEN pane % 3 = 0 THEN 'rebuilt' ELSE 'memo' END AS source, count(*) AS chunks, CAST(sum(n) AS BIGINT) AS items, sum(h) % 1000000007 AS hash_mod FROM c GROUP BY 1")
def memo_rebuild(spark, sf):
    """A third of the panes is lost from the memo: only those are computed again from the source."""
    run = EventRun(spark, sf)
    keys = ["window_id", "pane", "stratum"]
    sample = run.coordinated.withColumn("pane", F.call_function("div", F.col("seq"), F.lit(run.slide.step).cast("long")))
    stored = incremental.fingerprints(sample, *keys).where("pane % 3 <> 0")
    out = memo.rebuild(sample, stored, *keys)
    return out.groupBy("source").agg(F.count("*").alias("chunks"), F.sum("n").alias("items"), (F.sum("hash_sum") % F.lit(1000000007).cast("decimal(38,0)")).alias("hash_mod"))


@query(f"WITH RECURSIVE {E_}, {_CH}, {_ST} SELECT pane, stratum, CAST(sum(CASE WHEN state = 'reused' THEN 1 ELSE 0 END) AS BIGINT) AS hits FROM st GROUP BY ALL HAVING hits >= 20")
def hot_memo_entries(spark, sf):
    """Chunks that were reused at least 20 times."""
    hits = states(chunks(spark, sf)[2]).select("pane", "stratum", (F.col("state") == "reused").cast("long").alias("hit"))
    return memo.hot_entries(hits, 20)


# --- experiment workloads --------------------------------------------------------------------------------------------

_RATES = {"S1": 3.0, "S2": 4.0, "S3": 5.0}


def _poisson_sql():
    parts = []
    for name, rate in _RATES.items():
        cdf, p, total = [], math.exp(-rate), 0.0
        for k in range(int(rate + 12 * math.sqrt(rate) + 12)):
            total += p
            cdf.append(total)
            p *= rate / (k + 1)
        u = f"CAST({priority_sql(chr(39) + 'poisson1' + name + chr(39), 'id')} AS DOUBLE) / {float(16**15)!r}"
        parts.append(f"SELECT '{name}' AS stratum, len(list_filter([{', '.join(map(repr, cdf))}], lambda c: u > c)) AS n FROM (SELECT {u} AS u FROM (SELECT event_id AS id FROM events))")
    return " UNION ALL ".join(parts)


@query(f"SELECT stratum, CAST(sum(n) AS BIGINT) AS arrivals, round(avg(n), 5) AS mean, round(var_samp(n), 5) AS variance FROM ({_poisson_sql()}) GROUP BY 1")
def poisson_arrival_counts(spark, sf):
    """Simulated sub-streams of 3, 4 and 5 arrivals a tick; every event is a tick."""
    out = tables.poisson_arrivals(spark, tables.load(spark, sf, "events").select(F.col("event_id").alias("id")), _RATES)
    return out.groupBy("stratum").agg(F.sum("n").alias("arrivals"), F.round(F.avg("n"), 5).alias("mean"), F.round(F.var_samp("n"), 5).alias("variance"))


def memo_by_size(run, percents):
    """`memo_average` for several sample sizes: samples are drawn once, for the largest quotas, and a chain for each size goes over them."""
    most = [run.slide.length * p // 100 for p in percents]
    out = run.counts
    for k, size in enumerate(most):
        out = out.join(allocate.proportional_quota(run.counts, size).select("window_id", "stratum", F.col("quota").alias(f"q{k}")), ["window_id", "stratum"])
    quotas = {(r["window_id"], r["stratum"]): [r[f"q{k}"] for k in range(len(most))] for r in out.collect()}  # windows x strata, both few
    rows = [(w, s, q) for (w, s), each in quotas.items() if (q := max(each))]
    largest = run.counts.join(F.broadcast(run.spark.createDataFrame(rows, "window_id long, stratum string, quota long")), ["window_id", "stratum"])
    per = carryover.chain_counts(run.fresh(largest, max(most)), SEED, run.slide, quotas=quotas).where(F.col("window_id") + 1 < run.slide.count)
    label = F.element_at(F.array(*[F.lit(p) for p in percents]), F.col("size") + 1).alias("sample_pct")
    return per.groupBy(label, "stratum").agg(F.round(F.sum("alive") / F.lit(run.slide.count - 1), 4).alias("memo_avg"))


def sub_sql(label, ctes, body):
    """A sub-query with its own CTEs."""
    return f"SELECT * FROM (WITH RECURSIVE {ctes} {body})"


@query(" UNION ALL ".join(sub_sql(p, f"{events_sql(sample_pct=p, sub_streams=True)}, {chain_sql()}", _memo_sql(label=f"{p} AS sample_pct, ")) for p in (10, 20, 40, 60, 80)))
def exp_sample_size(spark, sf):
    """Memoized items of each sub-stream against the sample size: in proportion to it and to the arrival rate."""
    return memo_by_size(EventRun(spark, sf, sub_streams=True), (10, 20, 40, 60, 80))


def _poisson_events_sql():
    """CTE pev: the simulated arrivals in the shape of `events`, as many as there are events, at about."""
    parts = []
    for at, (name, rate) in enumerate(_RATES.items()):
        cdf, p, total = [], math.exp(-rate), 0.0
        for k in range(int(rate + 12 * math.sqrt(rate) + 12)):
            total += p
            cdf.append(total)
            p *= rate / (k + 1)
        u = f"CAST({priority_sql(chr(39) + 'poisson1' + name + chr(39), 'id')} AS DOUBLE) / {float(16**15)!r}"
        parts.append(f"SELECT '{name}' AS event_type, id * {len(_RATES)} + {at} AS cell, len(list_filter([{', '.join(map(repr, cdf))}], lambda c: u > c)) AS n FROM (SELECT id, {u} AS u FROM (SELECT unnest(range((SELECT count(*) // 12 FROM events))) AS id))")
    item = "SELECT event_type, cell * 1000 + k AS item FROM (SELECT *, unnest(range(n)) AS k FROM (" + " UNION ALL ".join(parts) + "))"
    value = f"({priority_sql(chr(39) + 'value' + chr(39), 'item')} % 10000) / 100.0"
    return f"pev AS (SELECT row_number() OVER (ORDER BY item) - 1 AS event_id, item, event_type, NULL AS ts, NULL AS user_id, NULL AS props, {value} AS value FROM ({item}))"


def poisson_sql(**options):
    """`events_sql` over the simulated arrivals."""
    over = events_sql(**options).replace("FROM events", "FROM pev").replace("SELECT event_id AS item_id, event_id AS seq", "SELECT item AS item_id, event_id AS seq")
    return f"{_poisson_events_sql()}, {over}"


def poisson_run(spark, sf, **options):
    run = EventRun(spark, sf, **options)
    run.items = tables.poisson_items(spark, tables.load(spark, sf, "events").count() // 12, _RATES)
    run.total = run.items.count()
    return run


@query(" UNION ALL ".join(sub_sql(p, f"{poisson_sql(sample_pct=p)}, {chain_sql()}", _memo_sql(label=f"{p} AS sample_pct, ")) for p in (10, 40, 80)))
def exp_poisson_sample_size(spark, sf):
    """Memoized items against the sample size over simulated Poisson sub-streams of rates 3, 4 and 5."""
    return memo_by_size(poisson_run(spark, sf), (10, 40, 80))


@query(" UNION ALL ".join(sub_sql(d, f"{poisson_sql(step_pct=d)}, {chain_sql('newest_first')}", f"SELECT {d} AS slide_pct, count(*) AS needed, count(*) FILTER (from_memo) AS known, round(count(*) FILTER (from_memo) / CAST(count(*) AS DOUBLE), 4) AS reuse FROM chain WHERE window_id >= {100 // d}") for d in (2, 4, 16)))
def exp_poisson_slide(spark, sf):
    """Reuse against the slide over simulated Poisson sub-streams."""
    out = []
    for d in (2, 4, 16):
        run = poisson_run(spark, sf, step_pct=d)
        out.append(reuse_by_refill(run, 100 // d, ("newest_first",)).withColumn("slide_pct", F.lit(d)).drop("refill"))
    return union(out)


def reuse_by_refill(run, skip, refills):
    """`reuse_after_warmup` of one chain for each refill, over the same samples."""
    per = carryover.chain_counts(run.sample, SEED, run.slide, refills).where(F.col("window_id") >= skip)
    return per.groupBy("refill").agg(F.sum("needed").alias("needed"), F.sum("known").alias("known")).withColumn("reuse", F.round(F.col("known") / F.col("needed"), 4))


def reuse_after_warmup(chain, skip):
    return chain.where(F.col("window_id") >= skip).agg(F.count("*").alias("needed"), F.count_if("from_memo").alias("known")).withColumn("reuse", F.round(F.col("known") / F.col("needed"), 4))


SLIDES = (1, 2, 4, 8, 16)


@query(" UNION ALL ".join(sub_sql(d, f"{events_sql(step_pct=d, sub_streams=True)}, {chain_sql(r)}", f"SELECT {d} AS slide_pct, '{r}' AS refill, count(*) AS needed, count(*) FILTER (from_memo) AS known, round(count(*) FILTER (from_memo) / CAST(count(*) AS DOUBLE), 4) AS reuse FROM chain WHERE window_id >= {100 // d}") for d in SLIDES for r in ("hash", "newest_first")))
def exp_slide(spark, sf):
    """Reuse against the slide, after one window length of warm-up: falls as windows move further."""
    out = []
    for d in SLIDES:
        run = EventRun(spark, sf, step_pct=d, sub_streams=True)
        out.append(reuse_by_refill(run, 100 // d, ("hash", "newest_first")).withColumn("slide_pct", F.lit(d)))
    return union(out)


def _time_sql(d):
    return f"""h AS (SELECT event_id AS item_id, CAST(floor(epoch(ts) / 3600) AS BIGINT) - (SELECT CAST(floor(epoch(min(ts)) / 3600) AS BIGINT) FROM events) AS seq, event_type AS stratum, CAST(value AS DECIMAL(18,2)) AS value FROM events),
p AS (SELECT max(seq) + 1 AS n, 100 AS w, {d} AS d, count(*) * 10 // (max(seq) + 1) AS ns FROM h),
win AS (SELECT window_id, window_id * d AS lo, window_id * d + w AS hi FROM (SELECT unnest(range((n - w) // d + 1)) AS window_id, d, w FROM p)),
assigned AS (SELECT window_id, lo, h.*, {priority_sql(chr(39) + SEED + chr(39), 'item_id', 'window_id')} AS u FROM win JOIN h ON seq >= lo AND seq < hi),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM assigned GROUP BY ALL), quota AS ({quota_sql('counts', 'SELECT ns FROM p')}),
sample AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u, item_id) AS rk FROM assigned) JOIN quota USING (window_id, stratum) WHERE rk <= quota)"""


@query(" UNION ALL ".join(sub_sql(d, f"{_time_sql(d)}, {chain_sql()}", f"SELECT {d} AS slide_hours, count(*) AS needed, count(*) FILTER (from_memo) AS known, round(count(*) FILTER (from_memo) / CAST(count(*) AS DOUBLE), 4) AS reuse FROM chain WHERE window_id >= {100 // d}") for d in SLIDES))
def exp_slide_time(spark, sf):
    """The same with windows of 100 hours."""
    items = tables.event_items(spark, sf)
    hour = F.floor(F.unix_seconds("ts") / 3600).cast("long")
    first, last, n = items.agg(F.min(hour), F.max(hour), F.count("*")).first()
    items = items.withColumn("seq", hour - first)
    out = []
    for d in SLIDES:
        slide = windows.Slide(100, d, last - first + 1)
        size = n * 10 // (last - first + 1)
        assigned = windows.assign(items, slide).withColumn("u", priority(SEED, F.col("item_id"), F.col("window_id")))
        sample = sampling.fixed_size_sample(assigned, allocate.proportional_quota(allocate.stratum_counts(assigned, "window_id"), size), size)
        out.append(reuse_after_warmup(carryover.carry_chain(sample, SEED), 100 // d).withColumn("slide_hours", F.lit(d)))
    return union(out)


_CHANGES = [0, 0, 0, 0, 0, 0] + [1, 1, 1, -1, -1, -1, 2, 2, 2, -2, -2, -2, 4, 4, 4, 0, 0, 0]


def changing_rows(total):
    base = total // 10
    return windows.window_schedule(base, [base * d // 100 for d in _CHANGES], 0.02)


_CV = f"""v AS (WITH RECURSIVE s(window_id, lo, hi) AS (SELECT 0, CAST(0 AS BIGINT), (SELECT count(*) // 10 FROM events)
  UNION ALL SELECT window_id + 1, lo + CAST(round_even((hi - lo) * 0.02, 0) AS BIGINT), lo + CAST(round_even((hi - lo) * 0.02, 0) AS BIGINT) + (hi - lo) + (SELECT count(*) // 10 FROM events) * ({_CHANGES}[window_id + 1]) // 100
  FROM s WHERE window_id < {len(_CHANGES)}) SELECT CAST(window_id AS BIGINT) AS window_id, lo, hi FROM s)"""


@query(f"WITH RECURSIVE {_CV}, {_VS}, {chain_sql('newest_first').replace('(SELECT gcd(w, d) FROM p)', '1')}, {_NM} SELECT ({[0, *_CHANGES]})[window_id + 1] AS change_pct, count(*) AS windows, CAST(sum(needed) AS BIGINT) AS needed, CAST(sum(memoized) AS BIGINT) AS memoized, CAST(sum(reused) AS BIGINT) AS reused, count(*) FILTER (memoized >= needed) AS windows_with_enough FROM nm WHERE window_id > 2 GROUP BY 1")
def exp_window_change(spark, sf):
    """Windows that grow or shrink by 1, 2, 4 %: shrinking helps reuse, growing hurts, more so the more it grows; the memo may hold more than is needed."""
    plan = changing_rows(tables.load(spark, sf, "events").count())
    _, _, sample = scheduled(spark, sf, plan)
    per = needed_and_memoized(carryover.carry_chain(sample, SEED, "biased", "newest_first", 1), plan).where("window_id > 2")
    label = F.element_at(F.array(*[F.lit(c) for c in [0, *_CHANGES]]), (F.col("window_id") + 1).cast("int"))
    sums = [F.sum(c).alias(c) for c in ("needed", "memoized", "reused")]
    return per.groupBy(label.alias("change_pct")).agg(F.count("*").alias("windows"), *sums, F.count_if(F.col("memoized") >= F.col("needed")).alias("windows_with_enough"))


_R1, _R2, _R3 = [1, 3, 3, 2, 2, 2], [4, 3, 5, 4, 3, 4], 4
_RS = f"CASE WHEN {priority_sql(chr(39) + 'rate' + chr(39), 'event_id')} % ({_R1}[e] + {_R2}[e] + {_R3}) < {_R1}[e] THEN 'S1' WHEN {priority_sql(chr(39) + 'rate' + chr(39), 'event_id')} % ({_R1}[e] + {_R2}[e] + {_R3}) < {_R1}[e] + {_R2}[e] THEN 'S2' ELSE 'S3' END".replace("[e]", "[event_id * 6 // (SELECT count(*) FROM events) + 1]")


@query(f"WITH RECURSIVE {events_sql(step_pct=2, stratum=_RS)}, {chain_sql('newest_first')} SELECT (window_id * (SELECT d FROM p) + (SELECT w FROM p)) * 6 // (SELECT n FROM p) AS epoch, stratum, count(*) AS needed, count(*) FILTER (from_memo) AS known, round(count(*) FILTER (from_memo) / CAST(count(*) AS DOUBLE), 4) AS reuse FROM chain WHERE window_id >= 25 GROUP BY ALL")
def exp_rate_change(spark, sf):
    """Fluctuating sub-streams: own reuse falls when the own rate rises and recovers when it falls; high overall."""
    run = EventRun(spark, sf, step_pct=2)
    epoch = F.call_function("div", F.col("seq") * 6, F.lit(run.total).cast("long")) + 1
    pick = lambda rates: F.element_at(F.array(*[F.lit(r) for r in rates]), epoch.cast("int"))
    at = F.pmod(priority("rate", F.col("item_id")), (pick(_R1) + pick(_R2) + _R3).cast("long"))
    run.items = run.items.withColumn("stratum", F.when(at < pick(_R1), "S1").when(at < pick(_R1) + pick(_R2), "S2").otherwise("S3"))
    e = F.call_function("div", (F.col("window_id") * run.slide.step + run.slide.length) * 6, F.lit(run.total).cast("long"))
    out = run.chain("biased", "newest_first").where("window_id >= 25").groupBy(e.alias("epoch"), "stratum")
    return out.agg(F.count("*").alias("needed"), F.count_if("from_memo").alias("known")).withColumn("reuse", F.round(F.col("known") / F.col("needed"), 4))


_G4 = f"""g AS (SELECT *, user_id % 4 AS grp FROM csample), b AS (SELECT window_id, stratum, count(*) AS b FROM g GROUP BY ALL),
sums AS (SELECT window_id, stratum, grp, CAST(sum(value) AS DOUBLE) AS sv, CAST(sum(value * value) AS DOUBLE) AS svv FROM g GROUP BY ALL),
gp AS (SELECT d.window_id * 1000 + d.grp AS wg, b.stratum, c.n_seen AS bb, b.b, coalesce(s.sv, 0) AS sv, coalesce(s.svv, 0) AS svv FROM (SELECT DISTINCT window_id, grp FROM g) d JOIN b ON b.window_id = d.window_id
  JOIN counts c ON c.window_id = b.window_id AND c.stratum = b.stratum LEFT JOIN sums s ON s.window_id = b.window_id AND s.stratum = b.stratum AND s.grp = d.grp),
x AS (SELECT window_id * 1000 + user_id % 4 AS wg, sum(value) AS exact FROM assigned GROUP BY 1)"""


@query(f"WITH {E_}, {_G4} SELECT wg // 1000 AS window_id, wg % 1000 AS grp, estimate, margin, exact, abs(estimate - CAST(exact AS DOUBLE)) <= margin AS covered FROM ({margin_sql(terms_sql('SELECT * FROM gp', 'wg'), 'wg')}) JOIN x USING (wg)")
def monitor_traffic(spark, sf):
    """Traffic per group of users in each window: estimate, margin, truth."""
    run = EventRun(spark, sf)
    grp = F.col("user_id") % 4
    est = estimate.estimate_by_group(run.coordinated.withColumn("grp", grp), run.counts, F.col("value"), "grp")
    exact = run.assigned.groupBy("window_id", grp.alias("grp")).agg(F.sum("value").alias("exact"))
    return est.join(exact, ["window_id", "grp"]).select("window_id", "grp", "estimate", "margin", "exact", (F.abs(F.col("estimate") - F.col("exact").cast("double")) <= F.col("margin")).alias("covered"))


_WHOLE = f"""i AS (SELECT 0 AS window_id, event_type AS stratum, event_id AS item_id, json_extract_string(props, '$.k') AS k, {priority_sql(chr(39) + SEED + chr(39), 'event_id')} AS u FROM events),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM i GROUP BY ALL), q AS ({quota_sql('counts', 'SELECT count(*) // 5 FROM events')}),
s AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY u, item_id) AS rk FROM i) JOIN q USING (window_id, stratum) WHERE rk <= quota)"""


def whole_sample(items, size):
    items = items.withColumn("window_id", F.lit(0).cast("long")).withColumn("u", priority(SEED, F.col("item_id")))
    return sampling.fixed_size_sample(items, allocate.proportional_quota(allocate.stratum_counts(items, "window_id"), size), size)


@query(f"WITH {_WHOLE} SELECT k, round(sum(CAST(n_seen AS DOUBLE) / quota), 4) AS estimated, (SELECT count(*) FROM i x WHERE x.k = s.k) AS exact FROM s GROUP BY k ORDER BY estimated DESC, k LIMIT 20")
def trending_keys(spark, sf):
    """The twenty most frequent keys, by a stratified fifth of the events."""
    items = tables.event_items(spark, sf, F.get_json_object("props", "$.k").alias("k"))
    top = whole_sample(items, items.count() // 5).groupBy("k").agg(F.round(F.sum(F.col("n_seen") / F.col("quota")), 4).alias("estimated")).orderBy(F.desc("estimated"), "k").limit(20)
    return top.join(items.groupBy("k").agg(F.count("*").alias("exact")), "k")


_DOCS = f"""i AS (SELECT 0 AS window_id, lang AS stratum, doc_id AS item_id, text, {priority_sql(chr(39) + SEED + chr(39), 'doc_id')} AS u FROM documents),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM i GROUP BY ALL), q AS ({quota_sql('counts', 'SELECT count(*) // 5 FROM documents')}),
s AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY u, item_id) AS rk FROM i) JOIN q USING (window_id, stratum) WHERE rk <= quota),
t AS (SELECT unnest(string_split(lower(text), ' ')) AS word, CAST(n_seen AS DOUBLE) / quota AS wt FROM s)"""


@query(f"WITH {_DOCS} SELECT word, round(sum(wt), 3) AS estimated FROM t WHERE word <> '' GROUP BY 1 ORDER BY round(sum(wt), 3) DESC, word LIMIT 20")
def trending_words(spark, sf):
    """The twenty most frequent words of the documents, by a fifth of each language."""
    docs = tables.load(spark, sf, "documents").select(F.col("doc_id").alias("item_id"), F.col("lang").alias("stratum"), "text")
    s = whole_sample(docs, docs.count() // 5).select(F.explode(F.split(F.lower("text"), " ", -1)).alias("word"), (F.col("n_seen") / F.col("quota")).alias("wt"))
    return s.where("word <> ''").groupBy("word").agg(F.round(F.sum("wt"), 3).alias("estimated")).orderBy(F.desc("estimated"), "word").limit(20)


_ER = events_sql(stratum="'u' || CAST(user_id % 5 AS VARCHAR)")


@query(f"WITH {_ER}, et AS (SELECT s.*, CASE WHEN event_type = 'error' THEN 1 ELSE 0 END AS err FROM csample s JOIN events ON event_id = item_id) SELECT window_id, estimate, margin FROM ({total_sql('et', 'err', scale='n_seen')})")
def error_rate_with_bound(spark, sf):
    """Share of error events per window, strata by user."""
    run = EventRun(spark, sf)
    kind = tables.event_items(spark, sf, "user_id", "props").withColumn("kind", F.col("stratum"))
    run.items = kind.withColumn("stratum", F.concat(F.lit("u"), (F.col("user_id") % 5).cast("string")))
    return estimate.estimate_mean(run.coordinated, run.counts, F.when(F.col("kind") == "error", 1).otherwise(0)).select("window_id", "estimate", "margin")
