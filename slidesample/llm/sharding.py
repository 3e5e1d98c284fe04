"""Sharding by a Feistel permutation with cycle walking over global row numbers.  Native.

Every row gets a global row number; a keyed Feistel permutation of 0 … n-1 turns it into a position; shard and
slot are position modulo and divided by the number of shards, so both can be computed from the row number alone,
shard sizes differ by one row at most, and slots have no gaps.  The network works on pairs (left, right) of a mixed
radix a * b with a = ceil(sqrt n), b = ceil(n / a), adding the round function modulo a and b in turn.  The domain holds
fewer than a values beyond n - 1; a value that lands there walks on until it is inside, which takes at most as many
steps as there are such values, so the walk always ends.

Global row numbers: rows are dealt to buckets by a hash of id, size and checksum, numbered inside their bucket, and
shifted by the counts of the buckets before it.  Buckets grow in number with the input, so no task holds more than a bucket.

Defined cases: a null text has size 1 and checksum 0; rows equal in id, size and checksum get neighbouring numbers in
any order (they are interchangeable); an empty table gives an empty result; shard counts above the row count leave shards
empty; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import let, shuffled, staged, table

ROUNDS = 6
ROWS_PER_BUCKET = 20_000


def feistel(x: Column, n: int, seed: int) -> Column:
    """One pass of the network over 0 … a*b-1 (LONG columns)."""
    a = max(1, math.isqrt(max(n - 1, 0)) + 1)
    b = max(1, -(-n // a))
    state = F.struct(F.call_function("div", x, F.lit(b).cast("long")).alias("l"), F.pmod(x, F.lit(b).cast("long")).alias("r"))

    def step(s: Column, k: Column) -> Column:
        even = k % 2 == 0
        left = F.when(even, F.pmod(s["l"] + F.pmod(F.xxhash64(s["r"], k, F.lit(seed)), F.lit(a)), F.lit(a))).otherwise(s["l"])
        right = F.when(even, s["r"]).otherwise(F.pmod(s["r"] + F.pmod(F.xxhash64(s["l"], k, F.lit(seed)), F.lit(b)), F.lit(b)))
        return F.struct(left.cast("long").alias("l"), right.cast("long").alias("r"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), state, step, lambda s: s["l"] * F.lit(b).cast("long") + s["r"])


def permuted(x: Column, n: int, seed: int) -> Column:
    """Position of row number `x` in a keyed permutation of 0 … n-1."""
    a = max(1, math.isqrt(max(n - 1, 0)) + 1)
    outside = a * max(1, -(-n // a)) - n

    def walk(start: Column, steps: int) -> Column:
        if steps <= 0:
            return start
        return F.aggregate(
            F.sequence(F.lit(1), F.lit(steps)), start, lambda p, _: F.when(p < F.lit(n), p).otherwise(feistel(p, n, seed))
        )

    short = min(outside, 16)

    def bounded(first: Column) -> Column:
        near = let(walk(first, short), lambda p: F.when(p < F.lit(n), p).otherwise(walk(p, outside - short)))
        return F.when(first < F.lit(n), first).otherwise(near)

    return let(feistel(x, n, seed), bounded)


def numbered(rows: DataFrame, key: list[str], n: int) -> DataFrame:
    """Add `row_no`, 0 … n-1, reproducible: hash buckets, ranks inside, offsets of the buckets before."""
    buckets = max(64, -(-n // ROWS_PER_BUCKET))
    dealt = rows.withColumn("_bucket", F.pmod(F.xxhash64(*key), F.lit(buckets)))
    counts = dealt.groupBy("_bucket").agg(F.count("*").alias("_n"))
    offsets = counts.select("_bucket", (F.sum("_n").over(Window.orderBy("_bucket")) - F.col("_n")).alias("_offset"))
    rank = F.row_number().over(Window.partitionBy("_bucket").orderBy(*key)) - 1
    return (
        dealt.withColumn("_rank", rank)
        .join(shuffled(offsets), "_bucket")  # rows are dealt by bucket already, so only the offsets move
        .withColumn("row_no", (F.col("_rank") + F.col("_offset")).cast("long"))
        .drop("_bucket", "_rank", "_offset")
    )


def shard_rows(docs: DataFrame, shards: int = 8, seed: int = 11, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: id, `keep` columns, size, text_crc32, shard, slot, row_no."""
    sized = docs.select(
        F.col(id_col),
        *keep,
        (F.coalesce(F.octet_length(text_col), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(F.encode(F.col(text_col), "UTF-8")), F.lit(0)).cast("long").alias("text_crc32"),
    )
    sized = staged(sized, "shard-sizes")
    n = sized.count()
    position = permuted(F.col("row_no"), n, seed)
    return (
        numbered(sized, [id_col, "size", "text_crc32"], n)
        .withColumn("_pos", position)
        .withColumn("shard", F.pmod("_pos", F.lit(shards)).cast("int"))
        .withColumn("slot", F.call_function("div", F.col("_pos"), F.lit(shards).cast("long")))
        .drop("_pos")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shard_rows(table(spark, sf_dir, "documents"))
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "row_no"
    )


QUERIES = {"op5_sharding": query}
ORACLE_SQL: dict[str, str] = {}
