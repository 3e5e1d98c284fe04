import random

import pytest
from pyspark.sql import functions as F

from slidesample.functions import tscore
from slidesample.functions.hashing import priority, priority_value
from slidesample.operators import allocate, budget, carryover, estimate, incremental, memo, reservoir, sampling, stratify, windows
from slidesample.operators.loop import WindowLoop, run_windows
from slidesample.operators.spec import AggregateSpec
from slidesample.plans import catalog
from slidesample.plans.base import SEED, EventRun

SMALL, MID = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def test_priority_is_the_same_everywhere(spark):
    got = spark.range(5).select(priority("a", F.col("id"), F.lit(3)).alias("x"), priority("a", F.col("id")).alias("y")).collect()
    assert [(r["x"], r["y"]) for r in got] == [(priority_value("a", i, 3), priority_value("a", i)) for i in range(5)]


def test_t_scores():
    golden = {1: 12.706205, 2: 4.302653, 5: 2.570582, 29: 2.045230}
    for f, t in golden.items():
        assert tscore.exact_quantile(f, 0.975) == pytest.approx(t, abs=1e-6)
    for f in (31, 97, 997):
        c = tscore.corrections(0.975)
        series = sum(x / f**i for i, x in enumerate(c))
        assert series == pytest.approx(tscore.exact_quantile(f, 0.975), abs=1e-6)


def test_worked_examples(spark):
    counts = spark.createDataFrame([(0, "A", 500), (0, "B", 1000)], "window_id long, stratum string, n_seen long")
    assert {(r["stratum"], r["quota"]) for r in allocate.proportional_quota(counts, 300).collect()} == {("A", 100), ("B", 200)}
    floor = spark.createDataFrame([(0, "A", 997), (0, "B", 2), (0, "C", 1)], "window_id long, stratum string, n_seen long")
    assert {(r["stratum"], r["quota"]) for r in allocate.proportional_quota(floor, 10, least=1).collect()} == {("A", 8), ("B", 1), ("C", 1)}
    feeds = {"M0": ["R3"], "M1": ["R1"], "M2": ["R2", "R3"], "M3": ["R4", "R5"], "M4": ["R1", "R2"], "M5": ["R3", "R5"], "M6": ["R3", "R5"]}
    edges = spark.createDataFrame([(m, r) for m, rs in feeds.items() for r in rs], "src string, dst string")
    changed = spark.createDataFrame([("M0",), ("M5",), ("M6",)], "node string")
    assert {r["node"] for r in incremental.dirty_reducers(edges, changed).collect()} == {"R3", "R5"}


def test_quotas(spark):
    rnd = random.Random(1)
    rows = [(w, f"s{i}", rnd.randrange(1, 5000)) for w in range(60) for i in range(rnd.randrange(1, 9))]
    sizes = {w: rnd.randrange(0, 3000) for w in range(60)}
    df = spark.createDataFrame([(w, s, n, sizes[w]) for w, s, n in rows], "window_id long, stratum string, n_seen long, size long")
    out = {}
    for r in allocate.proportional_quota(df, F.col("size")).collect():
        out.setdefault(r["window_id"], []).append((r["n_seen"], r["quota"]))
    for w, parts in out.items():
        k, n = sum(p[0] for p in parts), sizes[w]
        assert sum(p[1] for p in parts) == min(n, k)
        if n < k:
            assert all(abs(q - n * b / k) < 1 for b, q in parts)
    lifted = allocate.proportional_quota(df.where("size >= 20"), F.col("size"), least=1).groupBy("window_id").agg(F.sum("quota").alias("q"), F.min("quota").alias("m"), F.sum("n_seen").alias("k")).collect()
    assert all(r["m"] >= 1 and r["q"] == min(sizes[r["window_id"]], r["k"]) for r in lifted)


def test_everything_sampled_is_exact(spark):
    run = EventRun(spark, SMALL, sample_pct=100)
    got = estimate.estimate_total(run.sample, run.counts, F.col("value"))
    exact = run.assigned.groupBy("window_id").agg(F.sum("value").cast("double").alias("exact"))
    assert all(abs(r["estimate"] - r["exact"]) < 1e-6 and r["margin"] == 0 for r in got.join(exact, "window_id").collect())


def test_chain_keeps_quotas_and_carries_all_it_can(spark):
    run = EventRun(spark, SMALL, sub_streams=True)
    fresh = {(r["window_id"], r["stratum"]): r["n"] for r in run.sample.groupBy("window_id", "stratum").agg(F.count("*").alias("n")).collect()}
    for refill in ("hash", "sample_order", "newest_first"):
        rows = run.chain("biased", refill).collect()
        sets, known = {}, {}
        for r in rows:
            sets.setdefault((r["window_id"], r["stratum"]), {})[r["item_id"]] = r["seq"]
            known[(r["window_id"], r["stratum"])] = known.get((r["window_id"], r["stratum"]), 0) + r["from_memo"]
        assert {k: len(v) for k, v in sets.items()} == fresh and len(rows) == sum(fresh.values())
        for (w, s), items in sets.items():
            lo = w * run.slide.step
            assert all(lo <= q < lo + run.slide.length for q in items.values())
            alive = sum(q >= lo for q in sets.get((w - 1, s), {}).values())
            assert known[(w, s)] == min(alive, fresh[(w, s)])


def test_carry_over_cases(spark):
    cols = "window_id long, stratum string, item_id long, seq long, value decimal(18,2), u long"
    from decimal import Decimal

    row = lambda s, i: (0, s, i, i, Decimal(1), i)
    memo_rows = spark.createDataFrame([row("a", i) for i in range(7)] + [row("b", 100 + i) for i in range(3)] + [row("gone", 200)], cols)
    fresh = spark.createDataFrame([row("a", 10 + i) for i in range(5)] + [row("b", i) for i in (100, 101, 110, 111, 112)], cols)
    quotas = spark.createDataFrame([(0, "a", 5), (0, "b", 5)], "window_id long, stratum string, quota long")
    out = carryover.carry_over(fresh, memo_rows, quotas).collect()
    a, b = [r for r in out if r["stratum"] == "a"], [r for r in out if r["stratum"] == "b"]
    assert len(a) == 5 and all(r["from_memo"] for r in a)
    assert len({r["item_id"] for r in b}) == 5 and sum(r["from_memo"] for r in b) == 3
    assert not [r for r in out if r["stratum"] == "gone"]


def test_coordinated_reuse_and_refill_bands(spark):
    run = EventRun(spark, MID, step_pct=4, sub_streams=True)
    m = 25

    def reuse(chain):
        r = chain.where("window_id >= 25").agg(F.avg(F.col("from_memo").cast("double"))).first()
        return r[0]

    assert reuse(run.chain("biased", "hash")) == pytest.approx(1 - 2 / (m + 1), abs=0.02)
    assert reuse(run.chain("biased", "newest_first")) == pytest.approx(1 - 1 / m, abs=0.02)
    known = carryover.overlap_with_previous(run.coordinated, 1).where("window_id >= 1").agg(F.avg(F.col("known").cast("double"))).first()[0]
    assert known == pytest.approx(1 - 1 / m, abs=0.02)


def test_experiments_move_as_described(spark):
    q = catalog.queries()
    slide = {(r["slide_pct"], r["refill"]): r["reuse"] for r in q["exp_slide"](spark, MID).collect()}
    for refill in ("hash", "newest_first"):
        values = [slide[(d, refill)] for d in (1, 2, 4, 8, 16)]
        assert values == sorted(values, reverse=True)
    size = {(r["sample_pct"], r["stratum"]): r["memo_avg"] for r in q["exp_sample_size"](spark, MID).collect()}
    assert all(size[(p, "S1")] < size[(p, "S2")] < size[(p, "S3")] for p in (10, 20, 40, 60, 80))
    assert size[(80, "S3")] / size[(10, "S3")] == pytest.approx(8, rel=0.05)
    rows = q["exp_window_change"](spark, MID).collect()
    change = {r["change_pct"]: r["reused"] / r["needed"] for r in rows}
    assert change[-2] > change[1] > change[4] and change[-1] > change[2]
    assert any(r["memoized"] > r["needed"] for r in rows if r["change_pct"] < 0) and all(r["memoized"] < r["needed"] for r in rows if r["change_pct"] > 0)
    designs = {r["design"]: r["spread_millions"] for r in q["variance_by_design"](spark, MID).collect()}
    assert designs["stratified"] < designs["unstratified"]
    bias = {r["policy"]: r["relative_bias"] for r in q["trend_bias"](spark, MID).collect()}
    assert bias["hash"] < -abs(bias["coordinated"]) and abs(bias["coordinated"]) < 0.02
    cover = {float(r["confidence"]): r["covering"] / r["intervals"] for r in q["coverage_by_confidence"](spark, MID).collect()}
    assert 0.9 <= cover[0.95] <= 0.99


def test_inclusion_is_uniform(spark):
    """Over many seeds every item of a stratum is sampled about equally often."""
    items = spark.range(40).select(F.col("id").alias("item_id"), F.lit(0).cast("long").alias("w0"), F.lit("s").alias("stratum"))
    many = items.withColumn("window_id", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(400).cast("long"))))
    many = many.withColumn("u", priority(F.col("window_id"), F.col("item_id")))
    quotas = allocate.proportional_quota(allocate.stratum_counts(many, "window_id"), 10)
    n = [r["n"] for r in sampling.fixed_size_sample(many, quotas, 10).groupBy("item_id").agg(F.count("*").alias("n")).collect()]
    chi = sum((x - 100) ** 2 / 75 for x in n)
    assert len(n) == 40 and chi < 75


def test_literal_reservoir_has_the_quota_sizes(spark):
    run = EventRun(spark, SMALL, sub_streams=True)
    items = windows.assign(run.items, run.slide)
    for grow in ("next", "spread"):
        rows = reservoir.literal_reservoir(items, run.size, 20, grow).groupBy("window_id").agg(F.count("*").alias("n"), F.countDistinct("item_id").alias("d")).collect()
        assert all(r["n"] == r["d"] and abs(r["n"] - run.size) <= 2 for r in rows)


def test_new_stratum_in_mid_window(spark):
    from decimal import Decimal

    rows = [(i, i, "old" if i < 60 or i % 2 else "new", Decimal(1), 0, 0) for i in range(100)]
    items = spark.createDataFrame(rows, "item_id long, seq long, stratum string, value decimal(18,2), window_id long, lo long")
    got = {r["stratum"]: r["n"] for r in reservoir.literal_reservoir(items, 20, 10).groupBy("stratum").agg(F.count("*").alias("n")).collect()}
    assert got["new"] >= 1 and sum(got.values()) <= 20


def test_multi_stage_propagation(spark):
    edges = spark.createDataFrame([("a", "x"), ("b", "y"), ("x", "z"), ("z", "end"), ("y", "q")], "src string, dst string")
    got = {r["node"] for r in incremental.dirty_reducers(edges, spark.createDataFrame([("a",)], "node string")).collect()}
    assert got == {"x", "z", "end"}


def test_memo_store_survives_losses(spark, tmp_path):
    store = memo.MemoStore(spark, f"{tmp_path}/a", f"{tmp_path}/b")
    rows = spark.createDataFrame([(1, "x")], "item_id long, stratum string")
    store.write("items", 3, rows)
    store.replicate("items", 3)
    assert store.read("items", 3, rows.schema).count() == 1
    store.lose("items", 3)
    assert store.read("items", 3, rows.schema).count() == 1  # from the replica
    store.replicate_later("items", 4)
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        store.settle()
    store.pending.clear()
    store.forget("items", 3)
    assert store.read("items", 3, rows.schema).count() == 0
    assert store.read("items", 4, rows.schema).count() == 0  # cold
    with pytest.raises(FileNotFoundError):
        store.read("items", 4, rows.schema, on_loss="fail")


def test_budgets(spark):
    rows = budget.feedback([0.0] * 30, 1.0, 1000, lambda n, i: n * (0.001 if i < 10 else 0.002))
    assert rows[10]["over"] and not rows[11]["over"] and rows[-1]["violations"] <= 4
    run = EventRun(spark, MID)
    parts = estimate.stratum_parts(run.sample, run.counts, F.col("value"))
    need = budget.accuracy_size(parts.withColumn("eps", F.lit(5000.0)), F.col("eps")).collect()
    assert all(0 < r["sample_size"] <= run.slide.length for r in need)


def test_learned_strata(spark):
    rnd = random.Random(2)
    vectors = [(i, [float(i % 3) + rnd.gauss(0, 0.3), float(i % 3 == 1) + rnd.gauss(0, 0.3)], i % 3) for i in range(600)]
    out = stratify.self_train_strata(spark.createDataFrame(vectors, "vec_id long, embedding array<double>, label int")).where("NOT known").collect()
    assert len(out) > 400 and sum(r["label"] == r["predicted"] for r in out) / len(out) > 0.9
    items = EventRun(spark, MID).items
    intervals = stratify.fit_bootstrap_strata(sampling.simple_random_sample(items, 500, "b"))
    n = [r["n_seen"] for r in allocate.stratum_counts(stratify.assign_stratum(items, intervals)).collect()]
    assert len(n) == 4 and max(n) < 1.6 * min(n)


def test_merged_reservoirs(spark):
    """How many come from each side follows the hypergeometric law; no item twice."""
    a = spark.range(20).select(F.col("id").alias("item_id"))
    b = spark.range(100, 120).select(F.col("id").alias("item_id"))
    takes = []
    for seed in range(40):
        got = [r["item_id"] for r in sampling.merge_reservoirs(a, 100, b, 300, 20, seed).collect()]
        assert len(got) == len(set(got)) == 20
        takes.append(sum(i < 100 for i in got))
    sd = (20 * 0.25 * 0.75 * (400 - 20) / 399) ** 0.5
    assert abs(sum(takes) / 40 - 5) < 4 * sd / 40**0.5 and 0.5 * sd < (sum((t - 5) ** 2 for t in takes) / 40) ** 0.5 < 1.6 * sd


def test_literal_reservoir_includes_uniformly(spark):
    """Conventional steps alone (one stratum, no growth): every arrival is kept equally often; spread growth is less biased by arrival than next."""
    import numpy as np

    seqs, hits = np.arange(60), np.zeros(60)
    for seed in range(1500):
        for p in reservoir.replay(seqs, seqs < 10, 0, 1000, [], "next", np.random.default_rng(seed)):
            hits[p] += 1
    assert ((hits - 250) ** 2 / (250 * 50 / 60)).sum() < 110
    late = {}
    for grow in ("next", "spread"):
        after = np.zeros(60)
        for seed in range(600):
            for p in reservoir.replay(seqs, seqs < 10, 0, 20, [(0, 20)], grow, np.random.default_rng(seed)):
                after[p] += 1
        late[grow] = after[20:30].sum() / after[20:].sum()
    assert late["next"] > late["spread"] > 0.2


def test_window_loop(spark, tmp_path):
    """The loop's answers are those of the batch replay, also after a restart, from a replica, and without a memo."""
    run = EventRun(spark, SMALL, step_pct=50, parts=3)
    chain = run.chain("biased", "hash")
    want = {r["window_id"]: (r["estimate"], r["margin"]) for r in estimate.estimate_total(chain, run.counts, F.col("value")).collect()}

    def loop(folder, **more):
        return WindowLoop(spark, f"{tmp_path}/{folder}", AggregateSpec("sum"), budget.Budget("size", run.size), run.slide.length, run.slide.step, run.slide.pane, seed=SEED, **more)

    first = loop("a", replica=f"{tmp_path}/b")
    run_windows(run.items, first, 2)
    first.store.lose("items", 1)
    first.store.lose("partials", 1)
    again = loop("a", replica=f"{tmp_path}/b").resumed()
    assert again.window_id == 2
    answers, work = run_windows(run.items, again, run.slide.count - 2)
    assert {r["window_id"]: (r["estimate"], r["margin"]) for r in answers.collect()} == want
    assert all(r["values_read"] == 2 * (r["n_sampled"] - r["n_known"]) and 0 < r["n_known"] for r in work.collect())  # what entered and what left, nothing else
    cold = loop("c")
    run_windows(run.items, cold, 1)
    cold.store.lose("items", 0)
    cold.store.lose("partials", 0)
    row = cold.answer(run.items)
    assert row[6] == 0 and row[7] == row[5] == run.size  # nothing known, everything read, the answer is there
    assert spark.read.parquet(cold.store.path("answers", 1)).first()["n_sampled"] == run.size


def test_budgets_of_the_loop():
    b, past = budget.Budget, budget.Past
    assert budget.sample_size(b("fraction", 0.25), [], 1000) == 250
    assert budget.sample_size(b("size", 5000), [], 1000) == 1000 and budget.sample_size(b("size", 0), [], 1000) == 1
    history, cost, size = [], 0.01, 0
    for w in range(30):
        size = budget.sample_size(b("latency", 2.0), history, 1000)
        seconds = 0.5 + cost * size * (2 if w >= 15 else 1)
        history.append(past(size, seconds, budget.exceeded(b("latency", 2.0), size, seconds, None)))
    assert sum(h.over for h in history) <= 6 and not history[-1].over and size > 50
    assert budget.exceeded(b("accuracy", 1.0), 10, 0.1, 2.0) and not budget.exceeded(b("accuracy", 1.0), 10, 0.1, 0.5)
    assert budget.exceeded(b("tokens", 10, per_item=2.0), 6, 0.1, None)


def test_similar_strata_merge_through_long_chains(spark):
    stats = spark.createDataFrame([(f"s{i:02d}", 100, float(i), 50.0) for i in range(40)] + [("far", 100, 900.0, 50.0)], "stratum string, n long, mean double, variance double")
    got = {r["stratum"]: r["merged"] for r in stratify.merge_similar(stats, 1.1).collect()}
    assert got["far"] == "far" and {v for k, v in got.items() if k != "far"} == {"s00"}


def test_deep_propagation(spark):
    edges = spark.createDataFrame([(f"n{i}", f"n{i + 1}") for i in range(20)], "src string, dst string")
    assert incremental.dirty_reducers(edges, spark.createDataFrame([("n0",)], "node string")).count() == 20


def test_cuts_drop_items_before_windows(spark):
    run = EventRun(spark, MID)
    panes = run.items.withColumn("u", priority(SEED, F.col("item_id"))).withColumn("pane", windows.pane_of(run.slide))
    cuts = sampling.priority_cuts(panes.select("pane", "stratum", "u"), windows.panes_of_windows(spark, run.slide), run.quotas)
    left = panes.join(cuts, ["pane", "stratum"]).where("u <= cut").count()
    assert left < 0.2 * run.total
    direct = sampling.fixed_size_sample(run.permanent, run.quotas, run.size).select("window_id", "item_id")
    assert direct.exceptAll(run.coordinated.select("window_id", "item_id")).count() == 0


def test_plans(spark):
    run = EventRun(spark, SMALL)
    plan = run.sample._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "Python" not in plan
    assert "Python" not in run.coordinated._jdf.queryExecution().executedPlan().toString()
    total = estimate.estimate_total(run.coordinated, run.counts, F.col("value"))._jdf.queryExecution().executedPlan().toString()
    assert "user_id" not in total.split("ReadSchema")[1].split("\n")[0] and SEED in total


def test_empty_window_and_single_items(spark):
    from decimal import Decimal

    empty = spark.createDataFrame([], "window_id long, stratum string, n_seen long")
    assert allocate.proportional_quota(empty, 5).count() == 0
    sample = spark.createDataFrame([(0, "a", 1, Decimal(2))], "window_id long, stratum string, item_id long, value decimal(18,2)")
    counts = spark.createDataFrame([(0, "a", 1)], "window_id long, stratum string, n_seen long")
    r = estimate.estimate_total(sample, counts, F.col("value")).first()
    assert r["estimate"] == 2.0 and r["margin"] == 0.0 and r["df"] == 0
