"""What large tables need: no row of an item is broadcast, cuts are exact, and the chain's summary is that of its rows."""

import pytest
from pyspark.sql import functions as F

from slidesample.functions.hashing import SPAN
from slidesample.operators import carryover, sampling, windows
from slidesample.plans import catalog
from slidesample.plans.base import SEED, EventRun
from slidesample.plans.q_runs import memo_average, poisson_run
from slidesample.sources import tables

SMALL, MID = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def broadcast_columns(df):
    """Names of the columns of every side of a join that Spark broadcasts."""
    out, todo = set(), [df._jdf.queryExecution().sparkPlan()]
    while todo:
        node = todo.pop()
        if node.nodeName().startswith("BroadcastHashJoin"):
            side = node.left() if "Left" in node.buildSide().toString() else node.right()
            out |= {side.output().apply(i).name() for i in range(side.output().size())}
        todo += [node.children().apply(i) for i in range(node.children().size())]
    return out


@pytest.mark.parametrize("name", ["carry_all_disproportion", "carryover_no_dup", "carryover_refill_policy", "carryover_surplus_policy", "carryover_vanished_stratum", "carryover_items"])
def test_no_items_are_broadcast(spark, name):
    """An item is in many windows, which Spark's size estimates don't know: it took samples and windows for small sides of joins."""
    assert "item_id" not in broadcast_columns(catalog.queries()[name](spark, SMALL))


def test_cuts_are_exact_for_priorities_that_are_not_uniform(spark):
    """Group a is crowded at the top (its quota lies above what n_seen leads one to expect), b has equal first digits, c takes all, d nothing."""
    rows = [(0, "a", i, SPAN - 1 - i) for i in range(300)] + [(0, "b", i, 5) for i in range(200)] + [(0, "c", i, i * (SPAN // 50)) for i in range(50)] + [(0, "d", 1, 1)]
    items = spark.createDataFrame(rows, "window_id long, stratum string, item_id long, u long")
    quotas = spark.createDataFrame([(0, "a", 300, 7), (0, "b", 200, 20), (0, "c", 50, 50), (0, "d", 1, 0)], "window_id long, stratum string, n_seen long, quota long")
    got = {}
    for r in sampling.fixed_size_sample(items, quotas, 1000).collect():
        got.setdefault(r["stratum"], set()).add(r["item_id"])
    assert got == {"a": set(range(293, 300)), "b": set(range(20)), "c": set(range(50))}
    cuts = {r["stratum"]: r["_cut"] for r in sampling.quota_cuts(items.withColumn("_head", F.substring(F.lpad(F.lower(F.hex("u")), 15, "0"), 1, 3)), quotas).collect()}
    assert cuts["a"] == "fff" and cuts["b"] == "000" and "d" not in cuts


def test_windows_have_few_cells_whatever_length_and_step(spark):
    for length, step in ((60013, 1200), (25, 25), (7, 3), (10, 4), (3, 5)):
        slide = windows.Slide(length, step, 5 * length + 11)
        edges = windows.cells_of_windows(spark, slide)
        assert edges.count() <= slide.count * (2 * (length // step) + 1)
        if slide.total < 1000:
            items = spark.range(slide.total).select(F.col("id").alias("seq"))
            got = items.withColumn("cell", windows.cell_of(slide)).join(edges, "cell").groupBy("window_id").agg(F.min("seq").alias("a"), F.max("seq").alias("b"), F.count("*").alias("n")).collect()
            assert {(r["window_id"], r["a"], r["b"], r["n"]) for r in got} == {(w, w * step, w * step + length - 1, length) for w in range(slide.count)}


@pytest.mark.parametrize("step", [2, 4, 16])
def test_exp_poisson_slide_has_few_edges(spark, step):
    """Simulated arrivals have no round number: panes of the common divisor were single positions, and the list of each window's panes was broadcast."""
    run = poisson_run(spark, MID, step_pct=step)
    assert windows.cells_of_windows(spark, run.slide).count() <= run.slide.count * (2 * (run.slide.length // run.slide.step) + 1)
    plan = run.counts._jdf.queryExecution().executedPlan().toString()
    assert "pane" not in plan


def test_exp_poisson_sample_size_numbers_arrivals_in_parallel(spark):
    """The numbers are those of one running sum, and items are not made in one task."""
    items = tables.poisson_items(spark, 3500, {"S1": 3.0, "S2": 4.0})
    seqs = [r["seq"] for r in items.orderBy("item_id").collect()]
    assert seqs == list(range(len(seqs)))
    plan = items._jdf.queryExecution().executedPlan().toString().split("\n")
    depth = lambda line: len(line) - len(line.lstrip(" :+-"))
    explode = next(depth(x) for x in plan if "Generate explode" in x)
    single = [x for x in plan if "Exchange SinglePartition" in x]
    assert single and all(depth(x) > explode + 6 for x in single)
    assert not [x for x in plan if "Window" in x and "block" not in x]


@pytest.mark.parametrize("name", ["exp_sample_size", "exp_slide"])
def test_chain_counts_are_those_of_the_chain(spark, name):
    """No row of a sample goes through Python one by one; the summary is that of all rows."""
    assert "MapInPandas" not in catalog.queries()[name](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    run = EventRun(spark, SMALL, sub_streams=True)
    for refill in ("hash", "newest_first", "sample_order"):
        got = {(r["window_id"], r["stratum"]): (r["needed"], r["known"]) for r in carryover.chain_counts(run.sample, SEED, run.slide, (refill,)).collect()}
        rows = run.chain("biased", refill).groupBy("window_id", "stratum").agg(F.count("*").alias("n"), F.count_if("from_memo").alias("k")).collect()
        assert got == {(r["window_id"], r["stratum"]): (r["n"], r["k"]) for r in rows}
    alive = carryover.chain_counts(run.sample, SEED, run.slide).where(F.col("window_id") + 1 < run.slide.count).groupBy("stratum").agg(F.sum("alive").alias("a"))
    want = {r["stratum"]: r["memo_avg"] for r in memo_average(run, run.chain()).collect()}
    assert {r["stratum"]: round(r["a"] / (run.slide.count - 1), 4) for r in alive.collect()} == pytest.approx(want)


def test_join_strategies_broadcast_only_what_fits(spark, monkeypatch):
    from slidesample.plans import q_surface

    want = sorted(map(tuple, q_surface.join_strategies(spark, SMALL).collect()))
    monkeypatch.setattr(q_surface, "BROADCAST_ROWS", 10)
    df = q_surface.join_strategies(spark, SMALL)
    assert "o_orderpriority" not in broadcast_columns(df.where("strategy = 'broadcast'")) and sorted(map(tuple, df.collect())) == want


@pytest.mark.parametrize("name", ["bound_edge_cases", "budget_latency", "budget_tokens", "poisson_arrival_counts", "propagation_example", "quota_with_floor", "quota_worked_example", "t_scores"])
def test_query_reads_a_table(spark, name):
    df = catalog.queries()[name](spark, SMALL)
    assert any("events.parquet" in f for f in df.inputFiles()) and not df.isEmpty()


def test_budget_feedback_follows_the_table(spark):
    """Costs are those of the table's hours: shares of hours as counted, not a fixed step."""
    rows = {r["window_id"]: r for r in catalog.queries()["budget_feedback"](spark, MID).collect()}
    per = {r["h"]: r["n"] for r in tables.event_items(spark, MID).groupBy(F.hour("ts").alias("h")).agg(F.count("*").alias("n")).collect()}
    assert set(rows) == set(range(24))
    for hour, r in rows.items():
        assert r["cost"] == pytest.approx(r["sample_size"] * 0.024 * per[hour] / sum(per.values()), abs=1e-4)


def test_bound_edge_cases_has_all_four(spark):
    r = {x["window_id"]: x for x in catalog.queries()["bound_edge_cases"](spark, MID).collect()}
    assert r[0]["margin"] == 0 and r[1]["pooled"] == 1 and r[1]["margin"] > 0 and r[2]["refused"] == 1 and r[2]["estimate"] is None and r[3]["df"] == 0 and r[3]["margin"] is None


def test_variance_by_design_is_exact_without_luck(spark):
    """With and without the cut the sums are the same, and far fewer rows are ranked with it."""
    from slidesample.operators import allocate
    from slidesample.plans.q_runs import design_sums

    items = tables.lineitem_items(spark, SMALL, band=True).select("item_id", "stratum", "value")
    bands = allocate.stratum_counts(items.withColumn("window_id", F.lit(0).cast("long")), "window_id")
    total = items.count()
    quotas = allocate.proportional_quota(bands, total // 50).drop("window_id")
    got = [{(r["window_id"], r["stratum"]): (r["sv"], r["sv_global"], r["held"]) for r in design_sums(items, quotas, total, total // 50, 3, cut).collect()} for cut in (True, False)]
    for k, (sv, sv_global, held) in got[1].items():
        assert got[0].get(k, (None, None, 0))[:2] == (sv, sv_global)
    assert sum(x[2] for x in got[0].values()) < sum(x[2] for x in got[1].values())
