"""Named queries: windows, allocation, sampling."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window

from slidesample.functions.hashing import priority, priority_sql
from slidesample.operators import allocate, reservoir, sampling, windows
from slidesample.plans.base import SEED, EventRun, events_sql, quota_sql
from slidesample.sources import tables

QUERIES, ORACLE = {}, {}


def query(sql=None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


E_ = events_sql()


# --- windows ---------------------------------------------------------------------------------------------------------


@query(f"WITH {E_} SELECT window_id, count(*) AS n_expired FROM win JOIN items ON seq >= lo - (SELECT d FROM p) AND seq < lo WHERE window_id > 0 GROUP BY ALL")
def expired_items(spark, sf):
    """Items that leave when a window moves on: one pane step, found by partition-like pruning on panes."""
    run = EventRun(spark, sf)
    step = run.slide.step
    gone = run.items.groupBy(F.floor(F.col("seq") / step).alias("s")).agg(F.count("*").alias("n_expired"))
    return gone.where(F.col("s") < run.slide.count - 1).select((F.col("s") + 1).alias("window_id"), "n_expired")


@query(f"WITH {E_} SELECT window_id, stratum, count(*) AS n_arrived FROM win JOIN items ON seq >= CASE WHEN window_id = 0 THEN 0 ELSE hi - (SELECT d FROM p) END AND seq < hi GROUP BY ALL")
def arrivals_per_window(spark, sf):
    run = EventRun(spark, sf)
    s = run.slide
    w = F.greatest(F.lit(0), F.ceil((F.col("seq") + 1 - s.length) / F.lit(s.step))).cast("long")
    return run.items.groupBy(w.alias("window_id"), "stratum").agg(F.count("*").alias("n_arrived")).where(F.col("window_id") < s.count)


@query("""WITH h AS (SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, event_type AS stratum FROM events),
b AS (SELECT min(hour) AS h0, max(hour) AS h1 FROM h), w AS (SELECT unnest(range((h1 - h0 + 1 - 100) // 4 + 1)) AS window_id, h0 FROM b)
SELECT window_id, stratum, count(*) AS n_seen FROM w JOIN h ON hour >= h0 + window_id * 4 AND hour < h0 + window_id * 4 + 100 GROUP BY ALL""")
def time_window_counts(spark, sf):
    """Windows of 100 hours that move by 4, assembled from four-hour panes."""
    hours = tables.event_items(spark, sf).select(F.floor(F.unix_seconds("ts") / 3600).cast("long").alias("seq"), "stratum")
    lo, hi = hours.agg(F.min("seq"), F.max("seq")).first()
    slide = windows.Slide(100, 4, hi - lo + 1, lo)
    panes = hours.groupBy(windows.pane_of(slide).alias("pane"), "stratum").agg(F.count("*").alias("n"))
    return windows.panes_of_windows(spark, slide).join(panes, "pane").groupBy("window_id", "stratum").agg(F.sum("n").alias("n_seen"))


@query(f"WITH {E_} SELECT window_id, lo, count(*) AS n_seen FROM assigned GROUP BY ALL")
def count_window_counts(spark, sf):
    run = EventRun(spark, sf)
    return windows.assign(run.items, run.slide).groupBy("window_id", "lo").agg(F.count("*").alias("n_seen"))


DELTAS = [2, -1, 2, -1, 1, -2, 4, -0.5]


def varying_rows(total):
    base = total // 10
    return windows.window_schedule(base, [round(base * d / 100) for d in DELTAS], 0.02)


_V = """v AS (WITH RECURSIVE s(window_id, lo, hi) AS (SELECT 0, CAST(0 AS BIGINT), (SELECT count(*) // 10 FROM events)
  UNION ALL SELECT window_id + 1, lo + CAST(round_even((hi - lo) * 0.02, 0) AS BIGINT), lo + CAST(round_even((hi - lo) * 0.02, 0) AS BIGINT) + (hi - lo) + CAST(round_even((SELECT count(*) // 10 FROM events) * [2, -1, 2, -1, 1, -2, 4, -0.5][window_id + 1] / 100, 0) AS BIGINT)
  FROM s WHERE window_id < 8) SELECT CAST(window_id AS BIGINT) AS window_id, lo, hi FROM s)"""


@query(f"WITH {_V} SELECT window_id, lo, hi, hi - lo AS length, count(*) AS n_seen FROM v JOIN events ON event_id >= lo AND event_id < hi GROUP BY ALL")
def varying_window_plan(spark, sf):
    items = tables.event_items(spark, sf)
    total = items.count()
    plan = spark.createDataFrame(varying_rows(total), "window_id long, lo long, hi long")
    cells = windows.assign_schedule(items, plan, max(1, total // 500))
    return cells.groupBy("window_id", "lo", "hi").agg(F.count("*").alias("n_seen")).withColumn("length", F.col("hi") - F.col("lo"))


# --- allocation ------------------------------------------------------------------------------------------------------


@query(f"WITH {E_} SELECT window_id, stratum, n_seen, quota FROM quota")
def quota_by_window(spark, sf):
    return EventRun(spark, sf).quotas


_TC = "counts AS (SELECT event_id % 10 AS window_id, event_type AS stratum, count(*) AS n_seen FROM events GROUP BY ALL)"


@query(f"WITH {_TC}, c AS (SELECT 0 AS window_id, stratum, CAST(sum(n_seen) AS BIGINT) AS n_seen FROM counts GROUP BY ALL) SELECT stratum, n_seen, quota FROM ({quota_sql('c', '300')})")
def quota_worked_example(spark, sf):
    """300 of all events, in proportion to their types."""
    counts = allocate.stratum_counts(tables.event_items(spark, sf).withColumn("window_id", F.lit(0).cast("long")), "window_id")
    return allocate.proportional_quota(counts, 300).drop("window_id")


@query(f"""WITH {_TC}, q AS ({quota_sql('counts', '7')}), l AS (SELECT *, least(greatest(quota, 1), n_seen) AS lifted FROM q),
o AS (SELECT *, greatest(lifted - 1, 0) AS spare, sum(lifted) OVER w - sum(quota) OVER w AS surplus FROM l WINDOW w AS (PARTITION BY window_id)),
b AS (SELECT *, coalesce(sum(spare) OVER (PARTITION BY window_id ORDER BY lifted DESC, stratum ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM o)
SELECT window_id, stratum, n_seen, CAST(lifted - greatest(0, least(spare, surplus - before)) AS BIGINT) AS quota FROM b""")
def quota_with_floor(spark, sf):
    """Seven of each tenth of the events, and no type left out."""
    counts = allocate.stratum_counts(tables.event_items(spark, sf).withColumn("window_id", F.col("seq") % 10), "window_id")
    return allocate.proportional_quota(counts, 7, least=1)


@query(f"WITH {E_} SELECT window_id, stratum, count(*) AS n_filled FROM assigned WHERE seq < lo + (SELECT ns FROM p) GROUP BY ALL")
def initial_fill_mix(spark, sf):
    """Strata of the arrivals that fill the reservoir before any choice is made."""
    run = EventRun(spark, sf)
    first = F.row_number().over(Window.partitionBy("window_id").orderBy("seq"))
    filled = windows.assign(run.items, run.slide).withColumn("_r", first).where(F.col("_r") <= run.size)
    return filled.groupBy("window_id", "stratum").agg(F.count("*").alias("n_filled"))


_TL = f"""t AS (SELECT event_id // 400 AS tick, event_type AS stratum, count(*) AS n FROM events GROUP BY ALL),
g AS (SELECT * FROM (SELECT DISTINCT tick FROM t) CROSS JOIN (SELECT DISTINCT stratum FROM t)),
seen AS (SELECT * FROM (SELECT tick, stratum, CAST(sum(coalesce(n, 0)) OVER (PARTITION BY stratum ORDER BY tick) AS BIGINT) AS n_seen FROM g LEFT JOIN t USING (tick, stratum)) WHERE n_seen > 0),
q AS ({quota_sql('seen', '(SELECT count(*) // 100 FROM events)', 'tick')}),
tl AS (SELECT *, quota - coalesce(lag(quota) OVER (PARTITION BY stratum ORDER BY tick), 0) AS change FROM q)"""


@query(f"WITH {_TL} SELECT tick, stratum, n_seen, quota, change FROM tl")
def allocation_timeline(spark, sf):
    items = tables.event_items(spark, sf)
    return allocate.allocation_timeline(items, items.count() // 100, 400)


@query(f"""WITH {_TL}, m AS (SELECT tick, max(abs(change)) AS shift FROM tl WHERE tick > 0 GROUP BY tick)
SELECT count(*) AS ticks, count(*) FILTER (shift >= 2) AS ticks_with_shift, max(shift) AS largest_shift,
CASE WHEN count(*) FILTER (shift >= 2) > 0 THEN greatest(1, count(*) // count(*) FILTER (shift >= 2)) ELSE count(*) END AS suggested_ticks FROM m""")
def suggested_interval(spark, sf):
    return allocate.suggested_interval(allocation_timeline(spark, sf), 2)


@query("SELECT event_type AS stratum, count(*) AS n_seen FROM events GROUP BY 1")
def stratum_counts(spark, sf):
    return allocate.stratum_counts(tables.event_items(spark, sf))


# --- samples ---------------------------------------------------------------------------------------------------------


@query(f"WITH {E_} SELECT window_id, stratum, item_id, u FROM sample")
def stratified_sample_items(spark, sf):
    return EventRun(spark, sf).sample.select("window_id", "stratum", "item_id", "u")


@query(f"WITH {E_} SELECT window_id, stratum, count(*) AS n_sampled, sum(value) AS sampled_sum FROM sample GROUP BY ALL")
def sample_mix_by_window(spark, sf):
    return EventRun(spark, sf).sample.groupBy("window_id", "stratum").agg(F.count("*").alias("n_sampled"), F.sum("value").alias("sampled_sum"))


@query(f"WITH {E_} SELECT window_id, stratum, item_id FROM csample")
def pane_merge_equals_direct(spark, sf):
    """Samples merged from pane candidates; the SQL draws them from the windows directly."""
    return EventRun(spark, sf).coordinated.select("window_id", "stratum", "item_id")


@query()
def reservoir_literal(spark, sf):
    """The item-by-item adaptive reservoir, replayed per window and stratum."""
    run = EventRun(spark, sf)
    return reservoir.literal_reservoir(windows.assign(run.items, run.slide), run.size, max(1, run.slide.length // 10), "next", 7)


@query()
def ars_grow_spread(spark, sf):
    run = EventRun(spark, sf)
    return reservoir.literal_reservoir(windows.assign(run.items, run.slide), run.size, max(1, run.slide.length // 10), "spread", 7)


@query(f"WITH {E_}, s AS (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u) AS k FROM sample) SELECT window_id, stratum, item_id FROM s WHERE k <= quota - quota // 10")
def ars_shrink(spark, sf):
    """A sub-reservoir that shrinks by a tenth evicts its largest priorities: a uniform choice of the survivors."""
    run = EventRun(spark, sf)
    return reservoir.shrink(run.sample, F.col("quota") - F.call_function("div", F.col("quota"), F.lit(10).cast("long"))).select("window_id", "stratum", "item_id")


def _side_sql(salt, seen, src):
    pr = lambda x: priority_sql(f"'{x}'", "item_id")
    return f"SELECT stratum, item_id, sum(-ln(1 - CAST({pr('3' + salt + 'gap')} AS DOUBLE) / {float(16**15)!r}) / ({seen} - j + 1)) OVER (ORDER BY j) AS place FROM (SELECT *, row_number() OVER (ORDER BY {pr('3' + salt)}, item_id) AS j FROM {src})"


_MR = f"""n AS (SELECT count(*) AS n FROM events), i AS (SELECT event_id AS item_id, event_type AS stratum FROM events),
ra AS (SELECT * FROM i WHERE item_id < (SELECT n // 3 FROM n) ORDER BY {priority_sql("'1'", 'item_id')}, item_id LIMIT (SELECT n // 50 FROM n)),
rb AS (SELECT * FROM i WHERE item_id >= (SELECT n // 3 FROM n) ORDER BY {priority_sql("'2'", 'item_id')}, item_id LIMIT (SELECT n // 50 FROM n))"""


@query(f"WITH {_MR} SELECT stratum, item_id FROM ({_side_sql('a', '(SELECT n // 3 FROM n)', 'ra')} UNION ALL {_side_sql('b', '(SELECT n - n // 3 FROM n)', 'rb')}) ORDER BY place, item_id LIMIT (SELECT n // 50 FROM n)")
def merged_reservoirs(spark, sf):
    """One fixed-size sample out of two reservoirs of unequal populations."""
    items = tables.event_items(spark, sf)
    n = items.count()
    first, rest = items.where(F.col("seq") < n // 3), items.where(F.col("seq") >= n // 3)
    a, b = sampling.simple_random_sample(first, n // 50, 1).drop("u"), sampling.simple_random_sample(rest, n // 50, 2).drop("u")
    return sampling.merge_reservoirs(a, n // 3, b, n - n // 3, n // 50, 3).select("stratum", "item_id")


_B = f"WITH c AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), f AS (SELECT event_type, least(1.0, 0.02 * (SELECT count(*) FROM events) / (5 * n)) AS fraction FROM c) SELECT event_type AS stratum, event_id AS item_id FROM events JOIN f USING (event_type) WHERE CAST({priority_sql(chr(39) + 'bern' + chr(39), 'event_id')} AS DOUBLE) / {float(16**15)!r} < fraction"


@query(_B)
def bernoulli_by_stratum(spark, sf):
    items = tables.event_items(spark, sf)
    counts = allocate.stratum_counts(items)
    total = items.count()
    fractions = counts.select("stratum", F.least(F.lit(1.0), F.lit(0.02) * F.lit(total) / (F.lit(5) * F.col("n_seen"))).alias("fraction"))
    return sampling.bernoulli_by_stratum(items, fractions, "bern").select("stratum", "item_id")


@query(f"SELECT event_type AS stratum, event_id AS item_id FROM events ORDER BY {priority_sql(chr(39) + 'srs' + chr(39), 'event_id')}, event_id LIMIT (SELECT count(*) // 100 FROM events)")
def simple_random_sample(spark, sf):
    items = tables.event_items(spark, sf)
    return sampling.simple_random_sample(items, items.count() // 100, "srs").select("stratum", "item_id")


@query("SELECT event_type AS stratum, sampler, count(*) AS n_all, TRUE AS near_a_tenth FROM events, (SELECT unnest(['sample', 'sample_by', 'tablesample']) AS sampler) GROUP BY ALL")
def engine_samplers(spark, sf):
    """Spark's own samplers side by side: Bernoulli rows, by-key fractions, TABLESAMPLE; is each stratum within six deviations of a tenth?"""
    items = tables.event_items(spark, sf)
    items.createOrReplaceTempView("slidesample_items")
    keys = [r[0] for r in items.select("stratum").distinct().collect()]  # strata, few
    one = lambda df, name: df.groupBy("stratum").agg(F.count("*").alias("n")).withColumn("sampler", F.lit(name))
    found = one(items.sample(0.1, seed=1), "sample").unionByName(one(items.stat.sampleBy("stratum", dict.fromkeys(keys, 0.1), 1), "sample_by")).unionByName(one(spark.sql("SELECT * FROM slidesample_items TABLESAMPLE (10 PERCENT) REPEATABLE (1)"), "tablesample"))
    n = F.col("n_all")
    near = F.abs(F.col("n") - n * 0.1) <= 6 * F.sqrt(n * 0.09)
    return found.join(items.groupBy("stratum").agg(F.count("*").alias("n_all")), "stratum").select("stratum", "sampler", "n_all", near.alias("near_a_tenth"))
