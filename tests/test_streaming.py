from pyspark.sql import functions as F

from slidesample.operators import allocate, estimate, sampling, windows
from slidesample.functions.hashing import priority
from slidesample.sources import tables
from slidesample.streaming import live

SMALL = "/root/testdata/sf0.001"


def write_days(spark, folder, days=None):
    e = tables.load(spark, SMALL, "events").withColumn("d", F.to_date("ts"))
    for i, r in enumerate(e.select("d").distinct().orderBy("d").collect()):
        if days is None or i in days:
            e.where(F.col("d") == r["d"]).drop("d").coalesce(1).write.mode("append").parquet(folder)


def engine(spark, folder):
    origin = tables.event_items(spark, SMALL).agg(F.min(F.floor(F.unix_seconds("ts") / 3600))).first()[0]
    return live.LiveWindows(spark, folder, 120, 24, 40, int(origin), delay_hours=24)


def expected(spark, live_windows, last):
    items = tables.event_items(spark, SMALL).withColumn("seq", F.floor(F.unix_seconds("ts") / 3600).cast("long"))
    slide = windows.Slide(120, 24, 120 + 24 * last, live_windows.origin)
    assigned = windows.assign(items, slide).withColumn("u", priority("live", F.col("item_id")))
    counts = allocate.stratum_counts(assigned, "window_id")
    sample = sampling.fixed_size_sample(assigned, allocate.proportional_quota(counts, 40), 40)
    return {r["window_id"]: (r["estimate"], r["margin"]) for r in estimate.estimate_total(sample, counts, F.col("value")).collect()}


def test_stream_equals_batch_also_after_a_restart(spark, tmp_path):
    data, state, checkpoint = f"{tmp_path}/in", f"{tmp_path}/state", f"{tmp_path}/cp"
    write_days(spark, data, set(range(12)))
    first = engine(spark, state)
    first.start(tables.event_stream(spark, data, 6), checkpoint).awaitTermination()
    write_days(spark, data, set(range(12, 30)))
    second = engine(spark, state)  # a new process: nothing but the folders
    second.start(tables.event_stream(spark, data, 9), checkpoint).awaitTermination()
    got = {r["window_id"]: (r["estimate"], r["margin"]) for r in spark.read.parquet(f"{state}/answers").collect()}
    want = expected(spark, second, max(got))
    assert len(got) > 15 and got == {w: want[w] for w in got}
    # a replayed batch changes nothing
    batches = second.listed("counts")
    assert len(batches) < 5  # those that open windows need; the others are gone
    kept = spark.read.parquet(f"{state}/counts").agg(F.sum("n"), F.max("batch")).first()
    assert 0 < kept[0] < 1000 and second.dropped == 0


def test_late_rows_are_counted_and_dropped(spark, tmp_path):
    run = engine(spark, f"{tmp_path}/s")
    items = tables.event_items(spark, SMALL)
    cut = items.agg(F.expr("percentile_approx(ts, 0.5)")).first()[0]
    late = items.where(F.col("ts") < cut).orderBy("ts").limit(5)
    run.on_batch(items.join(late.select("item_id"), "item_id", "left_anti"), 0)
    run.on_batch(late, 1)
    assert run.dropped == 5
    run.on_batch(late, 1)  # a replay is not counted twice, nor lost on a restart
    assert run.dropped == 5 and engine(spark, f"{tmp_path}/s").dropped == 5


def test_engine_windows_over_a_stream(spark, tmp_path):
    data = f"{tmp_path}/in"
    write_days(spark, data, {0, 1, 2})
    stream = live.windowed_counts(tables.event_stream(spark, data, 3), "1 day", "1 day", "2 days")
    q = stream.writeStream.outputMode("complete").format("memory").queryName("slidesample_days").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.sql("SELECT sum(n) FROM slidesample_days").first()[0] == spark.read.parquet(data).count()


def test_running_totals_survive_a_restart(spark, tmp_path):
    from slidesample.streaming import stateful

    data = f"{tmp_path}/in"
    seen = {}

    def remember(batch, _):
        for r in batch.collect():
            seen[r["stratum"]] = (r["n"], round(r["total"], 2))

    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    stateful.use_rocksdb(spark)
    try:
        for days in ({0, 1, 2, 3}, {4, 5}):
            write_days(spark, data, days)
            totals = stateful.running_totals(tables.event_stream(spark, data, 2))
            totals.writeStream.outputMode("update").foreachBatch(remember).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)
    rows = spark.read.parquet(data).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total")).collect()
    assert seen == {r["event_type"]: (r["n"], r["total"]) for r in rows}


def test_rate_stream_gives_items(spark, tmp_path):
    q = tables.rate_stream(spark, 50).writeStream.format("memory").queryName("slidesample_rate").trigger(processingTime="1 second").start()
    try:
        for _ in range(30):
            if q.lastProgress and spark.sql("SELECT count(*) FROM slidesample_rate").first()[0]:
                break
            __import__("time").sleep(1)
    finally:
        q.stop()
    assert {r[0] for r in spark.sql("SELECT DISTINCT stratum FROM slidesample_rate").collect()} <= {"S1", "S2", "S3"} and spark.sql("SELECT count(*) FROM slidesample_rate").first()[0] > 0
