"""What the named queries share: the standard windows over events, and the same steps as SQL text for the comparison."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slidesample.functions.hashing import digest, priority, priority_sql
from slidesample.functions.tscore import t_quantile_sql
from slidesample.operators import allocate, carryover, sampling, windows
from slidesample.sources import tables

SEED = "s1"


@dataclass
class EventRun:
    """Count windows over `events`: length one of `parts` of the stream, step 4 % of it, sample 10 % of it (all adjustable)."""

    spark: SparkSession
    sf_dir: str
    step_pct: int = 4
    sample_pct: int = 10
    sub_streams: bool = False
    parts: int = 10

    @cached_property
    def total(self) -> int:
        return tables.load(self.spark, self.sf_dir, "events").count()

    @cached_property
    def slide(self) -> windows.Slide:
        length = self.total // self.parts
        return windows.Slide(length, max(1, length * self.step_pct // 100), self.total)

    @property
    def size(self) -> int:
        return self.slide.length * self.sample_pct // 100

    @cached_property
    def items(self) -> DataFrame:
        items = tables.event_items(self.spark, self.sf_dir, "user_id", "props")
        return tables.thinned(items) if self.sub_streams else items

    @cached_property
    def assigned(self) -> DataFrame:
        return windows.assign(self.items, self.slide).withColumn("u", priority(SEED, F.col("item_id"), F.col("window_id")))

    @cached_property
    def permanent(self) -> DataFrame:
        return windows.assign(self.items, self.slide).withColumn("u", priority(SEED, F.col("item_id")))

    @cached_property
    def counts(self) -> DataFrame:
        """Counts per window from cell counts: each item is counted once."""
        cells = self.items.groupBy(windows.cell_of(self.slide).alias("cell"), "stratum").agg(F.count("*").alias("n"))
        edges = windows.cells_of_windows(self.spark, self.slide)
        return edges.join(cells, "cell").groupBy("window_id", "stratum").agg(F.sum("n").alias("n_seen"))

    @cached_property
    def quotas(self) -> DataFrame:
        return allocate.proportional_quota(self.counts, self.size)

    @cached_property
    def sample(self) -> DataFrame:
        """A fresh sample in every window."""
        return self.fresh(self.quotas, self.size)

    def fresh(self, quotas: DataFrame, most: int) -> DataFrame:
        rows = windows.assign(self.items, self.slide).withColumn("digest", digest(SEED, F.col("item_id"), F.col("window_id")))
        return sampling.fixed_size_sample(rows, quotas, most)

    @cached_property
    def coordinated(self) -> DataFrame:
        """Samples by permanent priorities: items above their pane's cut never leave the scan, the others meet their windows."""
        panes = self.items.withColumn("u", priority(SEED, F.col("item_id"))).withColumn("pane", windows.pane_of(self.slide))
        edges = windows.panes_of_windows(self.spark, self.slide)
        cuts = sampling.priority_cuts(panes.select("pane", "stratum", "u"), edges, self.quotas)
        candidates = panes.join(cuts, ["pane", "stratum"]).where("u <= cut").drop("cut")
        return sampling.merge_bottom_k(candidates, edges, self.quotas, self.size).withColumn("lo", F.col("window_id") * self.slide.step)

    def chain(self, carry: str = "biased", refill: str = "hash") -> DataFrame:
        return carryover.carry_chain(self.sample, SEED, carry, refill, self.slide.pane)

    def changes(self, carry: str = "biased", refill: str = "hash") -> DataFrame:
        """Items that enter and leave the chain's samples; nothing that stays."""
        return carryover.carry_chain(self.sample, SEED, carry, refill, self.slide.pane, changes=True)


# --- the same as SQL text --------------------------------------------------------------------------------------------


def quota_sql(counts: str, size: str, by: str = "window_id") -> str:
    return f"""SELECT {by}, stratum, n_seen, CAST(CASE WHEN sz >= k THEN n_seen ELSE base + CASE WHEN rnk <= sz - sum(base) OVER (PARTITION BY {by}) THEN 1 ELSE 0 END END AS BIGINT) AS quota
FROM (SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY rest DESC, stratum) AS rnk FROM (
  SELECT *, (sz * n_seen) // k AS base, (sz * n_seen) % k AS rest FROM (
    SELECT {by}, stratum, n_seen, ({size}) AS sz, sum(n_seen) OVER (PARTITION BY {by}) AS k FROM {counts})))"""


def events_sql(step_pct: int = 4, sample_pct: int = 10, sub_streams: bool = False, seed: str = SEED, stratum: str | None = None, win: str | None = None, size: str = "SELECT ns FROM p", parts: int = 10) -> str:
    """CTEs p, items, win, assigned, counts, quota, sample (fresh) and csample (permanent priorities)."""
    stratum = stratum or "event_type"
    if sub_streams:
        at = f"{priority_sql(chr(39) + 'sub' + chr(39), 'event_id')} % 12"
        stratum = f"CASE WHEN {at} < 3 THEN 'S1' WHEN {at} < 7 THEN 'S2' ELSE 'S3' END"
    s = f"'{seed}'"
    return f"""p AS (SELECT count(*) AS n, count(*) // {parts} AS w, greatest(1, (count(*) // {parts}) * {step_pct} // 100) AS d, (count(*) // {parts}) * {sample_pct} // 100 AS ns FROM events),
items AS (SELECT event_id AS item_id, event_id AS seq, ts, {stratum} AS stratum, CAST(value AS DECIMAL(18,2)) AS value, user_id, props FROM events),
win AS ({win or "SELECT window_id, window_id * d AS lo, window_id * d + w AS hi FROM (SELECT unnest(range((n - w) // d + 1)) AS window_id, d, w FROM p)"}),
assigned AS (SELECT window_id, lo, items.*, {priority_sql(s, 'item_id', 'window_id')} AS u, {priority_sql(s, 'item_id')} AS u0 FROM win JOIN items ON seq >= lo AND seq < hi),
counts AS (SELECT window_id, stratum, count(*) AS n_seen FROM assigned GROUP BY ALL),
quota AS ({quota_sql('counts', size)}),
sample AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u, item_id) AS rk FROM assigned) JOIN quota USING (window_id, stratum) WHERE rk <= quota),
csample AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, stratum ORDER BY u0, item_id) AS rk FROM assigned) JOIN quota USING (window_id, stratum) WHERE rk <= quota)"""


def chain_sql(refill: str = "hash", carry: str = "biased", name: str = "chain", seed: str = SEED) -> str:
    """Recursive CTE of the carry-over chain over `sample` (use after events_sql, under WITH RECURSIVE)."""
    order = {"hash": "0", "newest_first": "CASE WHEN fm THEN 0 ELSE -(seq // (SELECT gcd(w, d) FROM p)) END", "sample_order": "CASE WHEN fm THEN 0 ELSE seq END"}[refill]
    cut = "TRUE" if carry == "all" else "rk <= quota"
    prio = priority_sql(f"'{seed}'", "c.item_id", "x.window_id")
    return f"""{name}(window_id, stratum, item_id, seq, value, u, from_memo) AS (
  SELECT window_id, stratum, item_id, seq, value, u, FALSE FROM sample WHERE window_id = 0
  UNION ALL
  SELECT window_id, stratum, item_id, seq, value, u, fm FROM (
    SELECT m.*, q.quota, row_number() OVER (PARTITION BY m.window_id, m.stratum ORDER BY fm DESC, {order}, u, item_id) AS rk FROM (
      SELECT window_id, stratum, item_id, any_value(seq) AS seq, any_value(value) AS value, any_value(u) AS u, bool_or(fm) AS fm FROM (
        SELECT x.window_id, c.stratum, c.item_id, c.seq, c.value, {prio} AS u, TRUE AS fm FROM {name} c JOIN win x ON x.window_id = c.window_id + 1 AND c.seq >= x.lo
        UNION ALL
        SELECT s.window_id, s.stratum, s.item_id, s.seq, s.value, s.u, FALSE FROM sample s WHERE s.window_id = (SELECT max(window_id) + 1 FROM {name})
      ) GROUP BY window_id, stratum, item_id) m JOIN quota q ON q.window_id = m.window_id AND q.stratum = m.stratum AND q.quota > 0
  ) WHERE {cut})"""


def parts_sql(sample: str, value: str = "value", counts: str = "counts", by: str = "window_id") -> str:
    v = f"CAST({value} AS DECIMAL(18,2))"
    return f"""SELECT c.{by}, c.stratum, c.n_seen AS bb, coalesce(b, 0) AS b, coalesce(sv, 0) AS sv, coalesce(svv, 0) AS svv FROM {counts} c LEFT JOIN (
  SELECT {by}, stratum, count(*) AS b, CAST(sum({v}) AS DOUBLE) AS sv, CAST(sum({v} * {v}) AS DOUBLE) AS svv FROM {sample} GROUP BY ALL) s ON s.{by} = c.{by} AND s.stratum = c.stratum"""


def terms_sql(parts: str, by: str = "window_id", s2: str = "CASE WHEN b > 1 THEN greatest(0.0, (svv - sv * sv / b) / (b - 1)) END") -> str:
    return f"""SELECT {by}, sum(CASE WHEN b > 0 THEN CAST(bb AS DOUBLE) / b * sv ELSE 0 END) AS estimate,
  sum(CASE WHEN b = 0 OR b = bb THEN 0.0 ELSE CAST(bb AS DOUBLE) * (bb - b) * coalesce(s2, pooled) / b END) AS variance,
  CAST(sum(b) - count(CASE WHEN b > 0 THEN 1 END) AS BIGINT) AS df, CAST(sum(b) AS BIGINT) AS n_sampled, CAST(sum(bb) AS BIGINT) AS n_seen,
  max(CASE WHEN b = 1 AND bb > 1 THEN 1 ELSE 0 END) AS pooled, max(CASE WHEN b = 0 AND bb > 0 THEN 1 ELSE 0 END) AS refused
FROM (SELECT *, sum(s2 * (b - 1)) OVER (PARTITION BY {by}) / sum(CASE WHEN b > 1 THEN b - 1 END) OVER (PARTITION BY {by}) AS pooled FROM (SELECT *, {s2} AS s2 FROM ({parts}))) GROUP BY {by}"""


def margin_sql(terms: str, by: str = "window_id", confidence: float = 0.95, scale: str = "1.0") -> str:
    t = t_quantile_sql("df", 1 - (1 - confidence) / 2)
    return f"""SELECT {by}, df, n_sampled, n_seen, pooled, refused, round(e, 6) AS estimate, round(m, 6) AS margin, round(e - m, 6) AS "lower", round(e + m, 6) AS "upper", n_sampled < 30 AS small_sample
FROM (SELECT *, CASE WHEN refused = 0 THEN estimate / ({scale}) END AS e, CASE WHEN refused = 0 THEN CASE WHEN n_sampled = n_seen THEN 0.0 ELSE ({t}) * sqrt(variance) / ({scale}) END END AS m FROM ({terms}))"""


def total_sql(sample: str, value: str = "value", confidence: float = 0.95, scale: str = "1.0") -> str:
    return margin_sql(terms_sql(parts_sql(sample, value)), confidence=confidence, scale=scale)
