"""Named queries: the operators around the methods (scans, joins, aggregates, windows, sets, functions, SQL surface)."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from slidesample.functions import sqlfns
from slidesample.functions.hashing import priority_sql
from slidesample.operators import windows
from slidesample.plans.base import SEED, EventRun, events_sql, quota_sql
from slidesample.plans.q_runs import _DOCS, _WHOLE, union, whole_sample
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
_TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in _TABLES))
def scan_counts(spark, sf):
    return union([tables.load(spark, sf, t).agg(F.lit(t).alias("name"), F.count("*").alias("n")) for t in _TABLES])


@query("SELECT event_id, CASE WHEN value > 100 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band FROM events WHERE value BETWEEN 10 AND 200 AND event_type IN ('click', 'view', 'error') AND props LIKE '%1%' AND user_id IS NOT DISTINCT FROM user_id")
def filter_project(spark, sf):
    e = tables.load(spark, sf, "events").where(F.col("value").between(10, 200) & F.col("event_type").isin("click", "view", "error") & F.col("props").like("%1%") & F.col("user_id").eqNullSafe(F.col("user_id")))
    return e.select("event_id", F.when(F.col("value") > 100, "high").when(F.col("value") > 20, "mid").otherwise("low").alias("band"))


def line_sample(spark, sf):
    li = tables.lineitem_items(spark, sf)
    return whole_sample(li, li.count() // 10)


LS = f"""li AS (SELECT 0 AS window_id, l_returnflag || l_linestatus AS stratum, concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y-%m-%d')) AS item_id, CAST(l_extendedprice AS DECIMAL(18,2)) AS value, l_orderkey, l_returnflag FROM lineitem),
pr AS (SELECT *, {priority_sql(chr(39) + SEED + chr(39), 'item_id')} AS u FROM li),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM li GROUP BY ALL),
q AS ({quota_sql('counts', 'SELECT count(*) // 10 FROM lineitem')}),
s AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY u, item_id) AS rk FROM pr) JOIN q USING (window_id, stratum) WHERE rk <= quota)"""


@query(f"WITH {LS} SELECT r_name, round(sum(CAST(n_seen AS DOUBLE) / quota * CAST(value AS DOUBLE)), 2) AS revenue, count(*) AS n FROM s JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1")
def sampled_star_join(spark, sf):
    """Dimensions are joined after sampling the facts: N:1 joins commute with it."""
    s = line_sample(spark, sf)
    out = s.join(tables.load(spark, sf, "orders"), s.l_orderkey == F.col("o_orderkey")).join(tables.load(spark, sf, "customer"), F.col("c_custkey") == F.col("o_custkey"))
    out = out.join(F.broadcast(tables.load(spark, sf, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(tables.load(spark, sf, "region")), F.col("r_regionkey") == F.col("n_regionkey"))
    return out.groupBy("r_name").agg(F.round(F.sum(F.col("n_seen") / F.col("quota") * F.col("value").cast("double")), 2).alias("revenue"), F.count("*").alias("n"))


@query("SELECT s AS strategy, o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON o_orderkey = l_orderkey, (SELECT unnest(['broadcast', 'merge', 'shuffle_hash']) AS s) GROUP BY ALL")
def join_strategies(spark, sf):
    """The same join three ways.  A table that is too large to hold on the driver (`BROADCAST_ROWS`) is joined whole without the broadcast hint."""
    li, o = tables.load(spark, sf, "lineitem").select("l_orderkey"), tables.load(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    fits = o.count() <= BROADCAST_ROWS
    one = lambda h: li.join(o.hint(h) if fits or h != "broadcast" else o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")).withColumn("strategy", F.lit(h))
    return union([one(h) for h in ("broadcast", "merge", "shuffle_hash")])


BROADCAST_ROWS = 1_000_000


@query(f"WITH {E_} SELECT window_id, count(*) AS n, sum(item_id) AS id_sum FROM assigned GROUP BY 1")
def range_join_windows(spark, sf):
    """Items meet a schedule through cells (equi-join) and a residual range test."""
    run = EventRun(spark, sf)
    out = windows.assign_schedule(run.items, run.slide.schedule(spark), max(1, run.slide.length // 10))
    return out.groupBy("window_id").agg(F.count("*").alias("n"), F.sum("item_id").alias("id_sum"))


@query("""WITH r AS (SELECT unnest(range(0, 10)) AS d), b AS (SELECT TIMESTAMP '2024-01-01' + to_days(CAST(d * 3 AS INTEGER)) AS ts, d * 10 AS rate FROM r)
SELECT e.event_id, b.rate FROM events e ASOF JOIN b ON e.ts >= b.ts""")
def asof_rate(spark, sf):
    """Every event with the latest row of a rate table, however long ago: last known value along the day, or else that of the days before (carried by one row a day)."""
    rates = spark.range(10).select((F.lit("2024-01-01").cast("timestamp") + F.make_dt_interval((F.col("id") * 3).cast("int"))).alias("ts"), (F.col("id") * 10).alias("rate"))
    e = tables.event_items(spark, sf).select("ts", F.col("item_id").alias("event_id"))
    both = e.withColumn("rate", F.lit(None).cast("long")).unionByName(rates.withColumn("event_id", F.lit(None).cast("long")).select("ts", "event_id", "rate")).withColumn("day", F.to_date("ts"))
    latest = F.max(F.when(F.col("rate").isNotNull(), F.struct("ts", "rate")))["rate"]
    days = both.groupBy("day").agg(latest.alias("last"))
    before = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)
    days = days.select("day", F.last("last", ignorenulls=True).over(before).alias("carried"))  # one row a day
    along = Window.partitionBy("day").orderBy("ts", F.col("event_id").asc_nulls_first())
    out = both.withColumn("rate", F.last("rate", ignorenulls=True).over(along)).where("event_id IS NOT NULL").join(days, "day")
    return out.select("event_id", F.coalesce("rate", "carried").alias("rate"))


@query("WITH s AS (SELECT DISTINCT event_type AS stratum FROM events), t AS (SELECT DISTINCT event_id // 1000 AS tick FROM events) SELECT tick, stratum, count(event_id) AS n FROM s CROSS JOIN t LEFT JOIN events ON event_type = stratum AND event_id // 1000 = tick GROUP BY ALL")
def dense_ticks(spark, sf):
    """A row for every stratum and tick, also without arrivals (both sides few)."""
    e = tables.event_items(spark, sf).withColumn("tick", F.call_function("div", F.col("seq"), F.lit(1000).cast("long")))
    per = e.groupBy("tick", "stratum").agg(F.count("*").alias("n"))
    grid = per.select("stratum").distinct().crossJoin(per.select("tick").distinct())
    return grid.join(per, ["tick", "stratum"], "left").fillna(0, ["n"]).select("tick", "stratum", "n")


@query(f"WITH {E_}, c AS (SELECT window_id, stratum, count(*) AS n FROM csample GROUP BY ALL) SELECT coalesce(a.window_id, b.window_id + 1) AS window_id, coalesce(a.stratum, b.stratum) AS stratum, coalesce(a.n, 0) - coalesce(b.n, 0) AS change FROM c a FULL JOIN c b ON b.window_id + 1 = a.window_id AND a.stratum = b.stratum")
def fingerprint_diff(spark, sf):
    """Full outer join of this window's and the last window's counts."""
    now = EventRun(spark, sf).coordinated.groupBy("window_id", "stratum").agg(F.count("*").alias("n"))
    before = now.select((F.col("window_id") + 1).alias("window_id"), "stratum", F.col("n").alias("m"))
    return now.join(before, ["window_id", "stratum"], "full_outer").select("window_id", "stratum", (F.coalesce("n", F.lit(0)) - F.coalesce("m", F.lit(0))).alias("change"))


@query("SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users, count(*) FILTER (value > 50) AS above, max(value) AS mx, min(value) AS mn, sum(CAST(value AS DECIMAL(18,2))) AS total FROM events GROUP BY 1")
def agg_suite(spark, sf):
    e = tables.load(spark, sf, "events")
    return e.groupBy("event_type").agg(
        F.count("*").alias("n"), F.countDistinct("user_id").alias("users"), F.count_if(F.col("value") > 50).alias("above"), F.max("value").alias("mx"), F.min("value").alias("mn"), F.sum(F.col("value").cast("decimal(18,2)")).alias("total")
    )


@query("SELECT count(DISTINCT user_id) AS users, round(quantile_cont(value, 0.5), 6) AS median, TRUE AS users_close, TRUE AS hll_close, TRUE AS median_close, TRUE AS kll_close FROM events")
def sketch_suite(spark, sf):
    """Sketches of the engine beside exact answers: are they within a tenth (a twentieth of the ranks for medians)?"""
    e = tables.load(spark, sf, "events")
    out = e.agg(
        F.countDistinct("user_id").alias("users"), F.expr("percentile(value, 0.5)").alias("median"), F.expr("percentile(value, array(0.45, 0.55))").alias("_band"), F.approx_count_distinct("user_id").alias("_a"),
        F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("_h"), F.percentile_approx("value", 0.5, 10000).alias("_m"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)").alias("_k"),
    )
    close = lambda c: F.abs(F.col(c) - F.col("users")) <= 0.1 * F.col("users")
    inside = lambda c: F.col(c).between(F.col("_band")[0], F.col("_band")[1])
    return out.select("users", F.round("median", 6).alias("median"), close("_a").alias("users_close"), close("_h").alias("hll_close"), inside("_m").alias("median_close"), inside("_k").alias("kll_close"))


@query("SELECT event_type, median(value) AS median, count(*) * 4 AS copies FROM events GROUP BY 1")
def udf_suite(spark, sf):
    """A grouped aggregate in pandas (Arrow batches) and a table function, for what built-in functions lack."""

    def middle(v):
        return float(v.median())

    middle.__annotations__ = {"v": pd.Series, "return": float}
    middle = F.pandas_udf(middle, "double")

    @F.udtf(returnType="copy int")
    class Copies:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    spark.udtf.register("slidesample_copies", Copies)
    e = tables.load(spark, sf, "events")
    e.createOrReplaceTempView("slidesample_udf_events")
    copies = spark.sql("SELECT event_type, count(*) AS copies FROM slidesample_udf_events, LATERAL slidesample_copies(4) GROUP BY event_type")
    return e.groupBy("event_type").agg(middle("value").alias("median")).join(copies, "event_type")


_W = "sum(CAST(n_seen AS DOUBLE) / quota * CAST(value AS DOUBLE))"


@query(f"WITH {LS} SELECT l_returnflag, stratum, round({_W}, 2) AS weighted, count(*) AS n FROM s GROUP BY ROLLUP (l_returnflag, stratum)")
def weighted_rollup(spark, sf):
    """Scaled-up totals at every level."""
    w = F.col("n_seen") / F.col("quota") * F.col("value").cast("double")
    return line_sample(spark, sf).rollup("l_returnflag", "stratum").agg(F.round(F.sum(w), 2).alias("weighted"), F.count("*").alias("n"))


@query(f"WITH {LS} SELECT l_returnflag, l_orderkey % 3 AS part, round({_W}, 2) AS weighted, count(*) AS n FROM s GROUP BY CUBE (l_returnflag, l_orderkey % 3)")
def weighted_cube(spark, sf):
    w = F.col("n_seen") / F.col("quota") * F.col("value").cast("double")
    return line_sample(spark, sf).withColumn("part", F.col("l_orderkey") % 3).cube("l_returnflag", "part").agg(F.round(F.sum(w), 2).alias("weighted"), F.count("*").alias("n"))


_WS = "PARTITION BY event_type ORDER BY value, event_id"


@query(f"SELECT event_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quart, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS lowest, round(percent_rank() OVER v, 6) AS pr, round(sum(value) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3 FROM events WINDOW w AS ({_WS}), v AS (PARTITION BY event_type ORDER BY value)")
def window_suite(spark, sf):
    e = tables.load(spark, sf, "events")
    w, v = Window.partitionBy("event_type").orderBy("value", "event_id"), Window.partitionBy("event_type").orderBy("value")
    r = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(-2, 0)
    return e.select(
        "event_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quart"), F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"),
        F.first("value").over(w).alias("lowest"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.sum("value").over(r), 4).alias("last3"),
    )


@query(f"WITH {_WHOLE}, t AS (SELECT user_id, round(sum(CAST(n_seen AS DOUBLE) / quota), 4) AS estimated FROM s JOIN events ON event_id = item_id GROUP BY 1) SELECT * FROM t ORDER BY estimated DESC, user_id LIMIT 10")
def top_users_sampled(spark, sf):
    """Ten busiest users by a stratified fifth (a top-k report)."""
    items = tables.event_items(spark, sf, "user_id")
    return whole_sample(items, items.count() // 5).groupBy("user_id").agg(F.round(F.sum(F.col("n_seen") / F.col("quota")), 4).alias("estimated")).orderBy(F.desc("estimated"), "user_id").limit(10)


@query(f"""WITH {E_}, a AS (SELECT window_id + 1 AS window_id, item_id FROM csample WHERE window_id < (SELECT max(window_id) FROM win)), b AS (SELECT window_id, item_id FROM csample WHERE window_id > 0)
SELECT window_id, part, count(*) AS n FROM (SELECT *, 'both' AS part FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT *, 'new' FROM (SELECT * FROM b EXCEPT SELECT * FROM a)
  UNION ALL SELECT *, 'gone' FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT *, 'all' FROM (SELECT * FROM a UNION ALL SELECT * FROM b)) GROUP BY ALL""")
def set_ops_overlap(spark, sf):
    """Known, new and expired items of every two neighbouring samples, by set operations on (window, item)."""
    run = EventRun(spark, sf)
    s = run.coordinated.select("window_id", "item_id")
    a, b = s.withColumn("window_id", F.col("window_id") + 1).where(F.col("window_id") < run.slide.count), s.where("window_id > 0")
    one = lambda df, name: df.groupBy("window_id").agg(F.count("*").alias("n")).withColumn("part", F.lit(name))
    return union([one(a.intersect(b), "both"), one(b.exceptAll(a), "new"), one(a.subtract(b), "gone"), one(a.unionByName(b), "all")])


@query("""SELECT event_id, lower(event_type) AS kind, regexp_extract(props, '([0-9]+)', 1) AS digits, substr(md5(concat_ws('|', event_id, event_type)), 1, 8) AS tag, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, CAST(hour(ts) AS INTEGER) AS hr,
epoch_us(ts) AS micros, CAST(floor(value) AS BIGINT) AS whole, round(sqrt(value), 6) AS root, round(ln(value + 1), 6) AS logv, event_id % 7 AS m FROM events""")
def scalar_suite(spark, sf):
    e = tables.load(spark, sf, "events").withColumn("t", F.col("ts").cast("timestamp"))
    return e.select(
        "event_id", F.lower("event_type").alias("kind"), F.regexp_extract("props", "([0-9]+)", 1).alias("digits"), F.substring(F.md5(F.concat_ws("|", "event_id", "event_type")), 1, 8).alias("tag"), F.date_format(F.date_trunc("day", "t"), "yyyy-MM-dd").alias("day"),
        F.hour("t").alias("hr"), F.unix_micros("t").alias("micros"), F.floor("value").cast("long").alias("whole"), F.round(F.sqrt("value"), 6).alias("root"), F.round(F.log(F.col("value") + 1), 6).alias("logv"), F.pmod("event_id", F.lit(7)).alias("m"),
    )


@query(f"WITH {_WHOLE} SELECT CAST(k AS INTEGER) % 10 AS bucket, count(*) AS n FROM s GROUP BY 1")
def json_keys_sampled(spark, sf):
    items = tables.event_items(spark, sf, F.from_json("props", "map<string,int>").alias("m"))
    return whole_sample(items, items.count() // 5).groupBy((F.element_at("m", "k") % 10).alias("bucket")).agg(F.count("*").alias("n"))


@query("SELECT label, round(avg(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))))), 5) AS mean_norm, count(*) AS n FROM embeddings GROUP BY 1")
def embedding_norm_mean(spark, sf):
    v = F.transform("embedding", lambda x: x.cast("double") * x.cast("double"))
    norm = F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, b: a + b))
    return tables.load(spark, sf, "embeddings").groupBy("label").agg(F.round(F.avg(norm), 5).alias("mean_norm"), F.count("*").alias("n"))


@query("SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def tumbling_counts(spark, sf):
    e = tables.event_items(spark, sf)
    return e.groupBy(F.window("ts", "1 hour"), F.col("stratum").alias("event_type")).agg(F.count("*").alias("n")).select(F.unix_seconds("window.start").alias("start"), "event_type", "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS b FROM events),
s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts) AS sid FROM g) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, sid""")
def session_counts(spark, sf):
    e = tables.event_items(spark, sf, "user_id")
    return e.groupBy("user_id", F.session_window("ts", "2 hours")).agg(F.count("*").alias("n")).select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")


@query(f"SELECT event_type, count(*) AS n, avg(CAST(CAST(value AS DECIMAL(18,2)) AS DOUBLE)) * 0 + 1.962346 AS t_score, min({priority_sql(chr(39) + 'sql' + chr(39), 'event_id')}) AS least FROM events GROUP BY 1")
def sql_surface(spark, sf):
    """The same through SQL, with the registered functions."""
    sqlfns.register(spark)
    tables.load(spark, sf, "events").createOrReplaceTempView("slidesample_events")
    out = spark.sql("SELECT event_type, count(*) AS n, max(t_quantile_975(997D)) AS t_score, min(item_priority('sql', CAST(event_id AS STRING))) AS least FROM slidesample_events GROUP BY event_type")
    return out.withColumn("t_score", F.round("t_score", 6))


@query(f"WITH {_DOCS} SELECT stratum, count(*) AS n, max(length(text)) AS longest FROM s GROUP BY 1")
def document_sample(spark, sf):
    docs = tables.load(spark, sf, "documents").select(F.col("doc_id").alias("item_id"), F.col("lang").alias("stratum"), "text")
    return whole_sample(docs, docs.count() // 5).groupBy("stratum").agg(F.count("*").alias("n"), F.max(F.length("text")).cast("long").alias("longest"))


@query(f"SELECT role AS stratum, count(*) AS n, sum(length(text)) AS chars FROM conversations GROUP BY 1")
def conversation_strata(spark, sf):
    t = tables.load(spark, sf, "conversations")
    return t.groupBy(F.col("role").alias("stratum")).agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"))
