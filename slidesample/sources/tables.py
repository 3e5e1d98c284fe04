"""Sources: every table becomes the canonical item view (item_id, seq, ts, stratum, value, …).

Files are read with pruned columns; timestamps without a zone are cast under a UTC session.  `event_stream` reads the same files as a
stream with a declared schema; `kafka_items` maps topics to strata and needs the connector on the class path.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slidesample.functions.hashing import priority

MONEY = "decimal(18,2)"
EVENT_SCHEMA = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampNTZType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def event_items(spark: SparkSession, sf_dir: str, *extra: str) -> DataFrame:
    """Events: arrival order is the event id, sub-stream is the event type."""
    e = load(spark, sf_dir, "events")
    return e.select(
        F.col("event_id").alias("item_id"), F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("stratum"), F.col("value").cast(MONEY).alias("value"), *extra
    )


def thinned(items: DataFrame, weights: tuple[int, ...] = (3, 4, 5), salt: str = "sub") -> DataFrame:
    """Replace the stratum by sub-streams S1, S2, … with the given rates, by hashed thinning."""
    at = F.pmod(priority(salt, F.col("item_id")), F.lit(sum(weights)))
    label, total = F.lit(f"S{len(weights)}"), sum(weights)
    for i in range(len(weights) - 1, 0, -1):
        total -= weights[i]
        label = F.when(at < total, F.lit(f"S{i}")).otherwise(label)
    return items.withColumn("stratum", label)


def lineitem_items(spark: SparkSession, sf_dir: str, band: bool = False) -> DataFrame:
    """Line items by ship day; strata are flag and status, or bands of the price (strata that really differ)."""
    li = load(spark, sf_dir, "lineitem")
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.date_format("l_shipdate", "yyyy-MM-dd"))
    stratum = F.concat(F.lit("p"), F.floor(F.col("l_extendedprice") / 20000).cast("string")) if band else F.concat("l_returnflag", "l_linestatus")
    return li.select(
        key.alias("item_id"),
        F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long").alias("seq"),
        stratum.alias("stratum"),
        F.col("l_extendedprice").cast(MONEY).alias("value"),
        "l_orderkey",
        "l_returnflag",
    )


def poisson_arrivals(spark: SparkSession, ticks: int | DataFrame, rates: dict[str, float], seed: int = 1) -> DataFrame:
    """Arrivals of simulated Poisson sub-streams in `ticks` (how many, or rows with an id): tick, stratum, n; counts come from the inverse distribution of a hashed uniform."""
    import math

    parts = []
    for name, rate in rates.items():
        cdf, p, total = [], math.exp(-rate), 0.0
        for k in range(int(rate + 12 * math.sqrt(rate) + 12)):
            total += p
            cdf.append(total)
            p *= rate / (k + 1)
        u = priority(f"poisson{seed}{name}", F.col("id")).cast("double") / F.lit(float(16**15))
        n = sum((F.when(u > F.lit(c), 1).otherwise(0) for c in cdf), F.lit(0))
        parts.append((spark.range(ticks) if isinstance(ticks, int) else ticks).select(F.col("id").alias("tick"), F.lit(name).alias("stratum"), n.cast("long").alias("n")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def poisson_items(spark: SparkSession, ticks: int, rates: dict[str, float], seed: int = 1) -> DataFrame:
    """The same arrivals as items in order of tick, sub-stream and number within it; values are hashed, 0 to 99.99."""
    per = poisson_arrivals(spark, ticks, rates, seed).withColumn("at", F.array_position(F.array(*[F.lit(r) for r in rates]), F.col("stratum")) - 1)
    per = per.withColumn("block", F.floor(F.col("tick") / 1000))  # ticks are numbered block by block, so that no task gets them all
    blocks = per.groupBy("block").agg(F.sum("n").alias("_n")).withColumn("_first", F.coalesce(F.sum("_n").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    before = Window.partitionBy("block").orderBy("tick", "at").rowsBetween(Window.unboundedPreceding, -1)
    per = per.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0)))
    per = per.join(F.broadcast(blocks.select("block", "_first")), "block").withColumn("first", F.col("first") + F.col("_first"))  # one row a thousand ticks
    one = per.where("n > 0").withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)))
    item = (F.col("tick") * len(rates) + F.col("at")) * 1000 + F.col("k")
    value = F.pmod(priority("value", F.col("item_id")), F.lit(10000)) / 100
    return one.select(item.alias("item_id"), (F.col("first") + F.col("k")).alias("seq"), "stratum").withColumn("value", value.cast(MONEY))


def rate_stream(spark: SparkSession, rows_per_second: int, strata: int = 3) -> DataFrame:
    """The engine's own generator as a stream of items, for load tests."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return raw.select(
        F.col("value").alias("item_id"), F.col("value").alias("seq"), F.col("timestamp").alias("ts"), F.concat(F.lit("S"), F.pmod("value", F.lit(strata)) + 1).alias("stratum"), (F.pmod(F.xxhash64("value"), F.lit(10000)) / 100).cast(MONEY).alias("value")
    )


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Files of a folder as a stream of items (time zone aware, so that watermarks accept them)."""
    raw = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return raw.select(F.col("event_id").alias("item_id"), F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("stratum"), F.col("value").cast(MONEY).alias("value"))


def kafka_items(spark: SparkSession, servers: str, topics: list[str], value: str = "CAST(value AS STRING)") -> DataFrame:
    """Topics as strata.  Untested here: the connector is not installed."""
    raw = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", ",".join(topics)).load()
    return raw.select(
        F.concat_ws("-", "topic", "partition", "offset").alias("item_id"), F.col("offset").alias("seq"), F.col("timestamp").alias("ts"), F.col("topic").alias("stratum"), F.expr(value).cast(MONEY).alias("value")
    )
