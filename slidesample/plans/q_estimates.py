"""Named queries: estimates and margins, carry-over, incremental execution."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window

from slidesample.functions.hashing import priority_sql
from slidesample.functions.tscore import t_quantile, t_quantile_sql
from slidesample.operators import carryover, estimate, incremental, windows
from slidesample.plans.base import SEED, EventRun, chain_sql, events_sql, margin_sql, parts_sql, terms_sql, total_sql
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
FIELDS = ["window_id", "df", "n_sampled", "n_seen", "pooled", "refused", "estimate", "margin", "lower", "upper", "small_sample"]
_F = 'window_id, df, n_sampled, n_seen, pooled, refused, estimate, margin, "lower", "upper", small_sample'


# --- estimates -------------------------------------------------------------------------------------------------------


@query(f"WITH {E_} SELECT {_F} FROM ({total_sql('sample')})")
def sum_with_bound(spark, sf):
    run = EventRun(spark, sf)
    return estimate.estimate_total(run.sample, run.counts, F.col("value")).select(*FIELDS)


@query(f"WITH {E_} SELECT {_F} FROM ({total_sql('sample', scale='n_seen')})")
def mean_with_bound(spark, sf):
    run = EventRun(spark, sf)
    return estimate.estimate_mean(run.sample, run.counts, F.col("value")).select(*FIELDS)


@query(f"WITH {E_} SELECT {_F} FROM ({total_sql('sample', 'CASE WHEN value > 50 THEN 1 ELSE 0 END')})")
def count_with_bound(spark, sf):
    run = EventRun(spark, sf)
    return estimate.estimate_count(run.sample, run.counts, F.col("value") > 50).select(*FIELDS)


_G = f"""g AS (SELECT *, user_id % 8 AS grp FROM sample),
b AS (SELECT window_id, stratum, count(*) AS b FROM g GROUP BY ALL),
sums AS (SELECT window_id, stratum, grp, CAST(sum(value) AS DOUBLE) AS sv, CAST(sum(value * value) AS DOUBLE) AS svv FROM g GROUP BY ALL),
gp AS (SELECT d.window_id * 1000 + d.grp AS wg, b.stratum, c.n_seen AS bb, b.b, coalesce(s.sv, 0) AS sv, coalesce(s.svv, 0) AS svv
  FROM (SELECT DISTINCT window_id, grp FROM g) d JOIN b ON b.window_id = d.window_id JOIN counts c ON c.window_id = b.window_id AND c.stratum = b.stratum
  LEFT JOIN sums s ON s.window_id = b.window_id AND s.stratum = b.stratum AND s.grp = d.grp)"""


@query(f"""WITH {E_}, {_G}
SELECT wg // 1000 AS window_id, wg % 1000 AS grp, df, n_sampled, n_seen, pooled, refused, estimate, margin, "lower", "upper", small_sample FROM ({margin_sql(terms_sql('SELECT * FROM gp', 'wg'), 'wg')})""")
def group_sum_with_bound(spark, sf):
    run = EventRun(spark, sf)
    sample = run.sample.withColumn("grp", F.col("user_id") % 8)
    return estimate.estimate_by_group(sample, run.counts, F.col("value"), "grp").select("grp", *FIELDS)


@query(f"""WITH {E_}, s AS (SELECT window_id, stratum, count(*) AS b, sum(num) AS sn, sum(den) AS sd, sum(num*num) AS snn, sum(num*den) AS snd, sum(den*den) AS sdd FROM
  (SELECT window_id, stratum, CASE WHEN value > 50 THEN CAST(value AS DOUBLE) ELSE 0.0 END AS num, CASE WHEN value > 50 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS den FROM sample) GROUP BY ALL),
r AS (SELECT s.*, c.n_seen AS bb, sum(c.n_seen::DOUBLE / b * sn) OVER (PARTITION BY s.window_id) / sum(c.n_seen::DOUBLE / b * sd) OVER (PARTITION BY s.window_id) AS r, sum(c.n_seen::DOUBLE / b * sd) OVER (PARTITION BY s.window_id) AS den FROM s JOIN counts c ON c.window_id = s.window_id AND c.stratum = s.stratum),
res AS (SELECT window_id, stratum, bb, b, sn - r * sd AS sv, snn - 2 * r * snd + r * r * sdd AS svv FROM r),
t AS (SELECT x.* EXCLUDE (estimate), k.r * k.den AS estimate, k.den FROM ({terms_sql('SELECT * FROM res')}) x JOIN (SELECT window_id, any_value(r) AS r, any_value(den) AS den FROM r GROUP BY 1) k USING (window_id))
SELECT {_F} FROM ({margin_sql('SELECT * FROM t', scale='den')})""")
def ratio_with_bound(spark, sf):
    """Average of the values above 50: filtered total over filtered count."""
    run = EventRun(spark, sf)
    num, den = F.when(F.col("value") > 50, F.col("value").cast("double")).otherwise(0.0), F.when(F.col("value") > 50, 1.0).otherwise(0.0)
    return estimate.estimate_ratio(run.sample, run.counts, num, den).select(*FIELDS)


@query(f"""WITH {E_}, pop AS (SELECT window_id, stratum, var_samp(CAST(value AS DOUBLE)) AS s2p FROM assigned GROUP BY ALL),
pp AS (SELECT x.*, s2p FROM ({parts_sql('sample')}) x JOIN pop USING (window_id, stratum))
SELECT a.window_id, a.estimate, a.margin AS margin_sample, b.margin AS margin_population FROM ({total_sql('sample')}) a JOIN ({margin_sql(terms_sql('SELECT * FROM pp', s2='s2p'))}) b USING (window_id)""")
def variance_basis_ablation(spark, sf):
    """Margins with the sample variance and with the true variance of each stratum."""
    run = EventRun(spark, sf)
    parts = estimate.stratum_parts(run.sample, run.counts, F.col("value"))
    true = run.assigned.groupBy("window_id", "stratum").agg(F.var_samp(F.col("value").cast("double")).alias("s2p"))
    a = estimate.with_margin(estimate.total_terms(parts, ("window_id",)))
    b = estimate.with_margin(estimate.total_terms(parts.join(true, ["window_id", "stratum"]), ("window_id",), F.col("s2p")))
    return a.select("window_id", "estimate", F.col("margin").alias("margin_sample")).join(b.select("window_id", F.col("margin").alias("margin_population")), "window_id")


_T = ", ".join(f"round({t_quantile_sql('f', p)}, 6) AS p{int(p * 10000)}" for p in (0.95, 0.975, 0.995))


@query(f"SELECT f, {_T} FROM (SELECT DISTINCT event_id % 1000 + 1 AS f FROM events)")
def t_scores(spark, sf):
    """Degrees of freedom 1 to 1000, as far as events have them: both sides of the exact list's end."""
    df = tables.load(spark, sf, "events").select((F.col("event_id") % 1000 + 1).alias("f")).distinct()
    return df.select("f", *[F.round(t_quantile(F.col("f"), p), 6).alias(f"p{int(p * 10000)}") for p in (0.95, 0.975, 0.995)])


@query(f"WITH {events_sql(sample_pct=2)} SELECT window_id, n_sampled, small_sample FROM ({total_sql('sample')})")
def small_sample_flag(spark, sf):
    run = EventRun(spark, sf, sample_pct=2)
    return estimate.estimate_total(run.sample, run.counts, F.col("value")).select("window_id", "n_sampled", "small_sample")


_LEVELS = (0.9, 0.95, 0.99)


@query(f"WITH {E_} " + " UNION ALL ".join(f"SELECT {c} AS confidence, window_id, estimate, margin FROM ({total_sql('sample', confidence=c)})" for c in _LEVELS))
def bounds_by_confidence(spark, sf):
    run = EventRun(spark, sf)
    terms = estimate.total_terms(estimate.stratum_parts(run.sample, run.counts, F.col("value")), ("window_id",))
    out = None
    for c in _LEVELS:
        part = estimate.with_margin(terms, c).select(F.lit(c).cast("decimal(3,2)").alias("confidence"), "window_id", "estimate", "margin")
        out = part if out is None else out.unionByName(part)
    return out


_X = priority_sql("'block'", "item_id")


@query(f"""WITH {E_}, m AS (SELECT window_id, {_X} % 10 AS block, max(CAST(value AS DOUBLE)) AS m FROM sample GROUP BY ALL),
g AS (SELECT window_id, max(m) AS mx, count(*) AS blocks, avg(m) AS mean, stddev_samp(m) * {6**0.5 / 3.141592653589793!r} AS beta FROM m GROUP BY 1)
SELECT window_id, round(mx, 4) AS sample_max, blocks, round(greatest(mean - 0.5772156649015329 * beta + beta * (ln(CAST(blocks AS DOUBLE)) - ln(-ln(0.95))), mx), 4) AS upper_95 FROM g""")
def max_extreme_value(spark, sf):
    return estimate.estimate_extreme(EventRun(spark, sf).sample, F.col("value"), 10)


_EDGE_KEPT = """CASE window_id WHEN 0 THEN TRUE WHEN 1 THEN CASE WHEN stratum = 'click' THEN item_id = first ELSE item_id % 10 = 0 END
  WHEN 2 THEN stratum <> 'error' AND item_id % 10 = 0 ELSE item_id = first END"""


@query(f"""WITH i AS (SELECT w AS window_id, event_type AS stratum, event_id AS item_id, CAST(value AS DECIMAL(18,2)) AS value, min(event_id) OVER (PARTITION BY event_type) AS first FROM events, (SELECT unnest(range(4)) AS w) WHERE w < 3 OR event_type = 'click'),
k AS (SELECT *, {_EDGE_KEPT} AS kept FROM i),
e AS (SELECT window_id, stratum, count(*) AS bb, count(*) FILTER (kept) AS b, coalesce(CAST(sum(value) FILTER (kept) AS DOUBLE), 0) AS sv, coalesce(CAST(sum(value * value) FILTER (kept) AS DOUBLE), 0) AS svv FROM k GROUP BY ALL)
SELECT {_F} FROM ({margin_sql(terms_sql('SELECT * FROM e'))})""")
def bound_edge_cases(spark, sf):
    """All events sampled; one of a stratum (pooled); none of a stratum (refused); one of one stratum, no degrees of freedom (no margin)."""
    items = tables.event_items(spark, sf)
    firsts = items.groupBy("stratum").agg(F.min("item_id").alias("first"))
    i = items.withColumn("window_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(3).cast("long")))).where("window_id < 3 OR stratum = 'click'")
    kept = F.expr(_EDGE_KEPT)
    sums = {"sv": F.col("value"), "svv": F.col("value") * F.col("value")}
    parts = i.join(F.broadcast(firsts), "stratum").groupBy("window_id", "stratum").agg(  # one row a stratum
        F.count("*").alias("n_all"), F.count_if(kept).alias("b"), *[F.coalesce(F.sum(F.when(kept, v)).cast("double"), F.lit(0.0)).alias(k) for k, v in sums.items()]
    )
    return estimate.with_margin(estimate.total_terms(parts, ("window_id",))).select(*FIELDS)


@query(f"WITH {E_} SELECT window_id, TRUE AS centred, TRUE AS as_wide FROM win")
def bootstrap_total(spark, sf):
    """Percentile intervals by resampling beside the margins: same centre (within half a margin) and like width (within a half of it)."""
    run = EventRun(spark, sf)
    boot = estimate.bootstrap_total(run.sample, run.counts)
    margins = estimate.estimate_total(run.sample, run.counts, F.col("value")).select("window_id", "estimate", "margin")
    half = (F.col("upper") - F.col("lower")) / 2
    return boot.join(margins, "window_id").select("window_id", (F.abs(F.col("mean") - F.col("estimate")) <= 0.5 * F.col("margin")).alias("centred"), half.between(0.5 * F.col("margin"), 1.5 * F.col("margin")).alias("as_wide"))


# --- carry-over ------------------------------------------------------------------------------------------------------

_MEMO = """memo AS (SELECT a.window_id, s.stratum, s.item_id, s.seq, s.value, a.u FROM sample s JOIN assigned a ON a.item_id = s.item_id AND a.window_id = s.window_id + 1)"""


def one_step(spark, sf, **options):
    """Each window's fresh sample biased towards the fresh sample of the window before."""
    run = EventRun(spark, sf)
    return run, carryover.prefer_known(carryover.beside_previous(run.sample, run.slide, SEED), run.quotas, **options)


def step_sql(order_memo="0", order_fresh="0", cut="rk <= quota"):
    return f"""step AS (SELECT window_id, stratum, item_id, seq, value, u, fm AS from_memo FROM (
  SELECT x.*, quota, row_number() OVER (PARTITION BY x.window_id, x.stratum ORDER BY fm DESC, CASE WHEN fm THEN {order_memo} ELSE {order_fresh} END, u, item_id) AS rk FROM (
    SELECT window_id, stratum, item_id, any_value(seq) AS seq, any_value(value) AS value, any_value(u) AS u, bool_or(fm) AS fm FROM (
      SELECT *, TRUE AS fm FROM memo UNION ALL SELECT window_id, stratum, item_id, seq, value, u, FALSE FROM sample) GROUP BY ALL) x JOIN quota q ON q.window_id = x.window_id AND q.stratum = x.stratum AND quota > 0) WHERE {cut})""".replace("GROUP BY ALL) x", "GROUP BY window_id, stratum, item_id) x")


@query(f"WITH {E_}, {_MEMO}, {step_sql()} SELECT window_id, stratum, item_id, from_memo FROM step")
def carryover_items(spark, sf):
    return one_step(spark, sf)[1].select("window_id", "stratum", "item_id", "from_memo")


@query(f"WITH {E_}, {_MEMO}, {step_sql()} SELECT window_id, count(*) AS n, count(DISTINCT item_id) AS n_distinct FROM step GROUP BY 1")
def carryover_no_dup(spark, sf):
    return one_step(spark, sf)[1].groupBy("window_id").agg(F.count("*").alias("n"), F.countDistinct("item_id").alias("n_distinct"))


@query(f"WITH {E_}, {_MEMO}, {step_sql()} SELECT window_id, stratum, count(*) AS n FROM step WHERE stratum <> 'error' OR window_id % 2 = 0 GROUP BY ALL")
def carryover_vanished_stratum(spark, sf):
    """In odd windows stratum `error` is gone from the sample; its memo items must not come back."""
    run = EventRun(spark, sf)
    gone = (F.col("stratum") == "error") & (F.col("window_id") % 2 == 1)
    both = carryover.beside_previous(run.sample, run.slide, SEED).where(F.col("from_memo") | ~gone)
    out = carryover.prefer_known(both, run.quotas.where(~gone))
    return out.groupBy("window_id", "stratum").agg(F.count("*").alias("n"))


@query(f"WITH {E_}, {_MEMO}, {step_sql('-seq', '0')} SELECT window_id, stratum, count(*) AS n, sum(seq) AS seq_sum FROM step GROUP BY ALL")
def carryover_surplus_policy(spark, sf):
    out = one_step(spark, sf, surplus="newest")[1]
    return out.groupBy("window_id", "stratum").agg(F.count("*").alias("n"), F.sum("seq").alias("seq_sum"))


@query(f"WITH {E_}, {_MEMO}, {step_sql('0', '-seq')} SELECT window_id, stratum, count(*) FILTER (from_memo) AS n_known, sum(seq) AS seq_sum FROM step GROUP BY ALL")
def carryover_refill_policy(spark, sf):
    out = one_step(spark, sf, refill="newest_first")[1]
    return out.groupBy("window_id", "stratum").agg(F.count_if("from_memo").alias("n_known"), F.sum("seq").alias("seq_sum"))


@query(f"WITH {E_}, {_MEMO}, {step_sql(cut='TRUE')} SELECT window_id, stratum, count(*) AS n_all, any_value(quota) AS quota FROM step JOIN quota USING (window_id, stratum) GROUP BY ALL".replace("GROUP BY ALL", "GROUP BY window_id, stratum"))
def carry_all_disproportion(spark, sf):
    """Keeping the whole memo: sizes leave their quotas."""
    run, out = one_step(spark, sf, carry="all")
    return out.groupBy("window_id", "stratum").agg(F.count("*").alias("n_all")).join(run.quotas.select("window_id", "stratum", "quota"), ["window_id", "stratum"])


@query(f"WITH {E_} SELECT s.window_id, count(*) AS n, count(b.item_id) AS n_known FROM sample s LEFT JOIN sample b ON b.window_id = s.window_id - 1 AND b.item_id = s.item_id GROUP BY 1")
def chance_overlap(spark, sf):
    out = carryover.overlap_with_previous(EventRun(spark, sf).sample, 1)
    return out.groupBy("window_id").agg(F.count("*").alias("n"), F.count_if("known").alias("n_known"))


@query(f"WITH {E_} SELECT s.window_id, count(*) AS n, count(b.item_id) AS n_known FROM csample s LEFT JOIN csample b ON b.window_id = s.window_id - 1 AND b.item_id = s.item_id GROUP BY 1")
def coordinated_overlap(spark, sf):
    out = carryover.overlap_with_previous(EventRun(spark, sf).coordinated, 1)
    return out.groupBy("window_id").agg(F.count("*").alias("n"), F.count_if("known").alias("n_known"))


@query(f"WITH RECURSIVE {E_}, {chain_sql()} SELECT window_id, count(*) AS n, count(*) FILTER (from_memo) AS n_known, sum(value) AS sampled_sum FROM chain GROUP BY 1")
def reuse_by_window(spark, sf):
    out = EventRun(spark, sf).chain()
    return out.groupBy("window_id").agg(F.count("*").alias("n"), F.count_if("from_memo").alias("n_known"), F.sum("value").alias("sampled_sum"))


_PANE = f"""panes AS (SELECT *, seq // (SELECT d FROM p) AS pane, {priority_sql(chr(39) + SEED + chr(39), 'item_id')} AS u0 FROM items),
ps AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY pane, stratum ORDER BY u0, item_id) AS rk, count(*) OVER (PARTITION BY pane, stratum) AS bb FROM panes) WHERE rk <= greatest(1, bb // 10)),
cells AS (SELECT w.window_id, ps.pane, ps.stratum, pane * 100 + dense_rank() OVER (ORDER BY ps.stratum) AS cell, any_value(bb) AS bb, count(*) AS b, CAST(sum(value) AS DOUBLE) AS sv, CAST(sum(value * value) AS DOUBLE) AS svv
  FROM win w JOIN ps ON pane >= w.lo // (SELECT d FROM p) AND pane < w.hi // (SELECT d FROM p) GROUP BY w.window_id, ps.pane, ps.stratum)"""


@query(f"WITH {E_}, {_PANE} SELECT {_F} FROM ({margin_sql(terms_sql('SELECT window_id, cell AS stratum, bb, b, sv, svv FROM cells'))})")
def pane_sampled_sum(spark, sf):
    """Each pane is sampled once and its partials slide: every (pane, stratum) cell is a stratum of the estimate."""
    run = EventRun(spark, sf)
    step = run.slide.step
    panes = run.items.withColumn("pane", F.call_function("div", F.col("seq"), F.lit(step).cast("long")))
    from slidesample.functions.hashing import priority

    cell = Window.partitionBy("pane", "stratum")
    ranked = panes.withColumn("u", priority(SEED, F.col("item_id"))).withColumn("rk", F.row_number().over(cell.orderBy("u", "item_id"))).withColumn("n_all", F.count("*").over(cell))
    kept = ranked.where(F.col("rk") <= F.greatest(F.lit(1), F.floor(F.col("n_all") / 10)))
    parts = kept.groupBy("pane", "stratum").agg(F.first("n_all").alias("n_all"), F.count("*").alias("b"), F.sum("value").cast("double").alias("sv"), F.sum(F.col("value") * F.col("value")).cast("double").alias("svv"))
    edges = windows.panes_of_windows(spark, windows.Slide(run.slide.length // step * step, step, run.total))
    edges = edges.where(F.col("window_id") < run.slide.count)
    joined = edges.join(parts, "pane").withColumn("stratum", F.concat_ws("/", "pane", "stratum"))
    return estimate.with_margin(estimate.total_terms(joined, ("window_id",))).select(*FIELDS)


# --- incremental -----------------------------------------------------------------------------------------------------

_CH = f"""{chain_sql('newest_first')}, ch AS (SELECT window_id, seq // (SELECT d FROM p) AS pane, stratum, count(*) AS n, CAST(sum(CAST({priority_sql("'fp'", 'item_id')} AS DECIMAL(38,0))) AS DECIMAL(38,0)) AS hash_sum, CAST(sum(value) AS DOUBLE) AS sv FROM chain GROUP BY ALL)"""


def chunks(spark, sf, refill="newest_first"):
    run = EventRun(spark, sf)
    c = run.chain("biased", refill).withColumn("pane", F.call_function("div", F.col("seq"), F.lit(run.slide.step).cast("long")))
    return run, c, incremental.fingerprints(c, "window_id", "pane", "stratum")


def states(chunk):
    memo = chunk.withColumn("window_id", F.col("window_id") + 1)
    last = chunk.agg(F.max("window_id").alias("_last"))
    both = incremental.split_reused(chunk, memo, ["window_id", "pane", "stratum"])
    return both.join(F.broadcast(last), F.col("window_id") <= F.col("_last")).drop("_last")


_ST = """st AS (SELECT coalesce(a.window_id, b.window_id + 1) AS window_id, coalesce(a.pane, b.pane) AS pane, coalesce(a.stratum, b.stratum) AS stratum,
  CASE WHEN a.n IS NULL THEN 'removed' WHEN a.n = b.n AND a.hash_sum = b.hash_sum THEN 'reused' ELSE 'fresh' END AS state, a.n
  FROM ch a FULL JOIN ch b ON b.window_id + 1 = a.window_id AND a.pane = b.pane AND a.stratum = b.stratum WHERE coalesce(a.window_id, b.window_id + 1) <= (SELECT max(window_id) FROM ch))"""


@query(f"WITH RECURSIVE {E_}, {_CH} SELECT window_id, pane, stratum, n, hash_sum % 1000000007 AS hash_mod FROM ch")
def chunk_fingerprints(spark, sf):
    return chunks(spark, sf)[2].select("window_id", "pane", "stratum", "n", (F.col("hash_sum") % F.lit(1000000007).cast("decimal(38,0)")).alias("hash_mod"))


@query(f"WITH RECURSIVE {E_}, {_CH}, {_ST} SELECT window_id, state, count(*) AS chunks FROM st GROUP BY ALL")
def reused_vs_fresh_chunks(spark, sf):
    return states(chunks(spark, sf)[2]).groupBy("window_id", "state").agg(F.count("*").alias("chunks"))


@query(f"WITH RECURSIVE {E_}, {_CH}, {_ST} SELECT DISTINCT window_id, stratum AS reducer FROM st WHERE state <> 'reused'")
def dirty_reducers(spark, sf):
    """Reducers (one per stratum and window) that some changed chunk feeds."""
    changed = states(chunks(spark, sf)[2]).where("state <> 'reused'")
    node = F.concat_ws(":", "window_id", "pane", "stratum")
    edges = changed.select(node.alias("src"), F.concat_ws(":", "window_id", F.lit("R"), "stratum").alias("dst"))
    dirty = incremental.dirty_reducers(edges, changed.select(node.alias("node")))
    part = F.split("node", ":")
    return dirty.select(F.element_at(part, 1).cast("long").alias("window_id"), F.element_at(part, 3).alias("reducer"))


@query("SELECT 'R' || CAST(event_id % 997 AS VARCHAR) AS reducer, CASE WHEN bool_or(user_id < 3) THEN 'redone' ELSE 'reused' END AS state FROM events GROUP BY 1")
def propagation_example(spark, sf):
    """Each user's events are a map task that feeds some of 997 reducers; the first three users change: what they feed runs again, the others keep their results."""
    e = tables.event_items(spark, sf, "user_id")
    node = lambda kind, c: F.concat(F.lit(kind), c.cast("string"))
    edges = e.select(node("M", F.col("user_id")).alias("src"), node("R", F.col("item_id") % 997).alias("dst")).distinct()
    changed = e.where("user_id < 3").select(node("M", F.col("user_id")).alias("node")).distinct()
    dirty = incremental.dirty_reducers(edges, changed)
    everyone = edges.select(F.col("dst").alias("reducer")).distinct()
    hit = dirty.select(F.col("node").alias("reducer"), F.lit("redone").alias("state"))
    return everyone.join(hit, "reducer", "left").select("reducer", F.coalesce("state", F.lit("reused")).alias("state"))


def pane_partials(run):
    pane = F.call_function("div", F.col("seq"), F.lit(run.slide.pane).cast("long"))
    v = F.col("value")
    return run.items.groupBy(pane.alias("pane")).agg(F.count("*").alias("n"), F.sum(v).alias("sv"), F.sum(v * v).alias("svv"), F.max(v).alias("mx"), F.min(v).alias("mn"))


def sliding(spark, sf):
    run = EventRun(spark, sf)
    s = run.slide
    return incremental.slide_invertible(pane_partials(run), s.length // s.pane, s.step // s.pane, ["n", "sv", "svv"])


@query(f"WITH {E_} SELECT window_id, sum(value) AS total FROM assigned GROUP BY 1")
def invertible_slide_sum(spark, sf):
    return sliding(spark, sf).select("window_id", F.col("sv").alias("total"))


@query(f"WITH {E_} SELECT window_id, count(*) AS n FROM assigned GROUP BY 1")
def invertible_slide_count(spark, sf):
    return sliding(spark, sf).select("window_id", F.col("n").cast("long").alias("n"))


@query(f"WITH {E_} SELECT window_id, round(CAST(sum(value) AS DOUBLE) / count(*), 6) AS mean FROM assigned GROUP BY 1")
def invertible_slide_avg(spark, sf):
    return sliding(spark, sf).select("window_id", F.round(F.col("sv").cast("double") / F.col("n"), 6).alias("mean"))


@query(f"WITH {E_} SELECT window_id, round((CAST(sum(value * value) AS DOUBLE) - CAST(sum(value) AS DOUBLE) * CAST(sum(value) AS DOUBLE) / count(*)) / (count(*) - 1), 6) AS variance FROM assigned GROUP BY 1")
def invertible_slide_var(spark, sf):
    sv, n = F.col("sv").cast("double"), F.col("n")
    return sliding(spark, sf).select("window_id", F.round((F.col("svv").cast("double") - sv * sv / n) / (n - 1), 6).alias("variance"))


@query(f"WITH {E_} SELECT window_id, max(value) AS largest, min(value) AS smallest FROM assigned GROUP BY 1")
def mergeable_slide_max(spark, sf):
    run = EventRun(spark, sf)
    s = run.slide
    return incremental.slide_mergeable(pane_partials(run), s.length // s.pane, s.step // s.pane, {"largest": F.max("mx"), "smallest": F.min("mn")})


@query(f"WITH RECURSIVE {E_}, {chain_sql()} SELECT c.window_id + 1 AS window_id, stratum, count(*) AS n_memo, sum(value) AS memo_sum FROM chain c JOIN win x ON x.window_id = c.window_id + 1 AND seq >= x.lo GROUP BY ALL")
def memo_contents(spark, sf):
    """What the memo holds when a window opens: the last biased sample without expired items."""
    run = EventRun(spark, sf)
    c = run.chain().withColumn("window_id", F.col("window_id") + 1).where(F.col("window_id") < run.slide.count)
    alive = windows.expire(c, F.col("window_id") * run.slide.step)
    return alive.groupBy("window_id", "stratum").agg(F.count("*").alias("n_memo"), F.sum("value").alias("memo_sum"))


@query(f"WITH RECURSIVE {E_}, {chain_sql()} SELECT window_id, stratum, count(*) AS b, sum(value) AS sv FROM chain GROUP BY ALL")
def signed_delta_sum(spark, sf):
    """Partials accumulated from entering and leaving items only; the SQL sums every sample from scratch."""
    run = EventRun(spark, sf)
    ids = spark.range(run.slide.count).select(F.col("id").alias("window_id"))
    out = incremental.totals_from_deltas(incremental.signed_delta(run.chain()), ids)
    return out.where("b > 0").select("window_id", "stratum", F.col("b").cast("long").alias("b"), "sv")


_GR = " UNION ALL ".join(
    f"""SELECT '{r}' AS refill, round(i.known, 4) AS items, round(c.known, 4) AS chunks FROM
 (SELECT avg(CASE WHEN from_memo THEN 1.0 ELSE 0 END) AS known FROM chain_{r} WHERE window_id > 0) i, (SELECT avg(CASE WHEN a.n = b.n AND a.h = b.h THEN 1.0 ELSE 0 END) AS known FROM ch_{r} a LEFT JOIN ch_{r} b ON b.window_id + 1 = a.window_id AND b.pane = a.pane AND b.stratum = a.stratum WHERE a.window_id > 0) c"""
    for r in ("hash", "newest_first")
)
_GC = ", ".join(f"{chain_sql(r, name=f'chain_{r}')}, ch_{r} AS (SELECT window_id, seq // (SELECT d FROM p) AS pane, stratum, count(*) AS n, sum(CAST({priority_sql(chr(39) + 'fp' + chr(39), 'item_id')} AS DECIMAL(38,0))) AS h FROM chain_{r} GROUP BY ALL)" for r in ("hash", "newest_first"))


@query(f"WITH RECURSIVE {E_}, {_GC} {_GR}")
def reuse_by_grain(spark, sf):
    """Reused share of items and of chunks: hash refill dirties almost every chunk, newest-first refill few."""
    out = None
    for refill in ("hash", "newest_first"):
        _, c, f = chunks(spark, sf, refill)
        items = c.where("window_id > 0").agg(F.round(F.avg(F.col("from_memo").cast("double")), 4).alias("items"))
        reused = states(f).where("window_id > 0 and state <> 'removed'").agg(F.round(F.avg((F.col("state") == "reused").cast("double")), 4).alias("chunks"))
        part = items.crossJoin(reused).withColumn("refill", F.lit(refill))  # one row each
        out = part if out is None else out.unionByName(part)
    return out
