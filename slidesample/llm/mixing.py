"""Mixing sources to target weights by entropy balancing.  Native.

Words of a source are the constraint: the mix shall take `target` words of it.  Among all document rates w in [0, cap] that meet the
constraints, entropy balancing takes those with the least sum of w log w - w + 1, the ones closest to taking every document once.
They are min(cap, exp(m * size)) with one multiplier m per source, tilted towards long documents where a source must
grow and towards short ones where it must shrink.  The multipliers solve the convex dual, whose gradient is the words that the tilted
rates take less the target.  Newton steps run on all sources at once, each an aggregation over the histogram of (source, size, documents), into
which all documents were counted before; a step that leaves its bracket is replaced by the middle of it, so the iteration always ends.

Rates become whole copies: documents of a source are dealt by hash into chunks of about `CHUNK`, walked from the longest to
the shortest, and each gets the whole number next to its rate that keeps the words taken nearest to the words due so far.
What is left at the end of a chunk is at most half of its shortest text, and copies follow each document's own rate in the mean.
A hot source has many chunks.  Repeated rows (equal id, source and text) are counted once with their number, so they never meet in one list.

Targets: the corpus size is shared by weight; a target stops at `cap` times its source's size and the rest goes to the
others by weight (solved exactly by one sweep over sources in order of cap / weight).

Defined cases: null text counts no words; a null source is a source, last in order; sources without words get target 0;
no words at all gives targets of 0; documents without words take 0; repeated rows share the copies of all of them evenly; ids may be null;
no rows, no result; extra columns are ignored (`mix`) or kept (`mixed_documents`).
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, dropped, keyed_rows, row_keys, shuffled, staged, table

CHUNK = 512
#: The dual is solved when the words taken are this near to the target, relatively.
TOLERANCE = 1e-10
MOST_STEPS = 200


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: float = 3.0) -> DataFrame:
    """sizes(source, size, n documents) -> one row per source: docs, source_size, weight, target."""
    sums = sizes.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"), F.sum("n").alias("docs"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(place, F.lit(len(weights))) + 1).cast("int"))
    limit = F.col("source_size") * F.lit(cap)
    everyone = Window.partitionBy()
    order = Window.orderBy(limit / F.col("weight"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    after = order.rowsBetween(0, Window.unboundedFollowing)
    level = (F.col("total") - F.coalesce(F.sum("limit").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    swept = (
        sums.withColumn("weight", weight)
        .withColumn("limit", limit.cast("double"))
        .withColumn("total", F.sum("source_size").over(everyone).cast("double"))
        .withColumn("_level", level)
        .withColumn("_free", F.col("limit") >= F.col("_level") * F.col("weight"))
    )
    # the first source whose limit is not reached fixes the level of all after it
    final = F.first(F.when(F.col("_free"), F.col("_level")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    level_all = F.coalesce(final, F.col("_level"))
    target = F.least(F.col("limit"), level_all * F.col("weight"))
    swept = swept.withColumn("target", F.when(F.col("total") > 0, target).otherwise(F.lit(0.0)))
    return swept.select("source", "docs", "source_size", "weight", "target")


def multipliers(sizes: DataFrame, targets: DataFrame, cap: float) -> DataFrame:
    """sizes(source, size, n) + targets -> source, `mean` (words of a document), `m`: rates are min(cap, exp(m * size / mean)); null where all rates are 0 or the cap."""
    spark = sizes.sparkSession
    mean = F.col("source_size") / F.col("docs")
    # at the ends of the bracket even the shortest text (1 word) is beyond the target
    low, high = F.least(F.log(F.col("target") / F.col("source_size")), F.lit(0.0)) * mean, F.lit(math.log(cap)) * mean
    solvable = (F.col("target") > 0) & (F.col("target") < F.col("source_size") * (cap - 1e-9))
    state = targets.where(solvable).select("source", "target", mean.alias("mean"), F.lit(0.0).alias("m"), low.alias("low"), high.alias("high"), F.lit(1e300).alias("off"))
    state = staged(state, "mix-multipliers")
    x = F.col("size") / F.col("mean")
    tilt = F.exp(F.least(F.col("m") * x, F.lit(math.log(cap))))
    words = F.col("n") * F.col("size") * tilt
    for _ in range(MOST_STEPS):
        here = sizes.where("size > 0").withColumnRenamed("source", "_s").join(state, F.col("_s").eqNullSafe(F.col("source")))
        sums = here.groupBy("source", "target", "mean", "m", "low", "high", "off").agg(
            F.sum(words).alias("taken"), F.sum(F.when(F.col("m") * x < math.log(cap), words * x).otherwise(0.0)).alias("slope")
        )
        gap = F.log(F.col("taken") / F.col("target"))
        low, high = F.when(gap < 0, F.col("m")).otherwise(F.col("low")), F.when(gap > 0, F.col("m")).otherwise(F.col("high"))
        newton = F.col("m") - gap * F.col("taken") / F.col("slope")
        use = (F.col("slope") > 0) & (newton > low) & (newton < high) & (F.abs(gap) <= 0.7 * F.col("off"))
        moved = F.when(F.abs(gap) <= TOLERANCE, F.col("m")).when(use, newton).otherwise((low + high) / 2)
        after = staged(sums.select("source", "target", "mean", moved.alias("m"), low.alias("low"), high.alias("high"), F.abs(gap).alias("off")), "mix-multipliers")
        dropped(spark, state._staged_path)
        state = after
        worst = state.agg(F.max(F.least("off", (F.col("high") - F.col("low")) / F.greatest(F.abs("m"), F.lit(1e-6))))).first()[0]
        if worst is None or worst <= TOLERANCE:
            return state.select("source", F.col("mean"), F.round("m", 9).alias("m"))
    raise RuntimeError("the dual of the mix was not solved")


def planned(docs: DataFrame, weights: tuple[int, ...], cap: float, seed: int, id_col: str) -> DataFrame:
    """One row per distinct document: `_k1`, `_k2`, id, source, size, rows (how often it is there), source_size, target, rate, copies (of all its rows)."""
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    sized = docs.select(F.col(id_col).alias("id"), "source", size.alias("size"), *row_keys(id_col, "source", "text"))
    sized = staged(sized.groupBy("_k1", "_k2").agg(*[F.first(c).alias(c) for c in ("id", "source", "size")], F.count("*").alias("rows")), "mix-sizes")
    sizes = staged(sized.groupBy("source", "size").agg(F.sum("rows").alias("n"), F.count("*").alias("distinct")), "mix-histogram")
    targets = staged(source_targets(sizes, weights, cap), "mix-targets")
    solved = multipliers(sizes, targets, cap).withColumnRenamed("source", "_m_source")
    chunks = sizes.groupBy(F.col("source").alias("_c_source")).agg(F.ceil(F.sum("distinct") / CHUNK).alias("_chunks"))
    targets = targets.join(solved, F.col("source").eqNullSafe(F.col("_m_source")), "left").join(chunks, F.col("source").eqNullSafe(F.col("_c_source")))
    targets = staged(targets.select(F.col("source").alias("_s"), "source_size", "target", "mean", "m", "_chunks"), "mix-rates")
    tilted = F.round(F.least(F.lit(float(cap)), F.exp(F.col("m") * F.col("size") / F.col("mean"))), 9)
    flat = F.when(F.col("target") > 0, F.lit(float(cap))).otherwise(F.lit(0.0))
    dealt = (
        sized.join(targets, F.col("source").eqNullSafe(F.col("_s")))
        .withColumn("rate", F.when(F.col("size") == 0, F.lit(0.0)).when(F.col("m").isNull(), flat).otherwise(tilted))
        .withColumn("_chunk", F.pmod(F.xxhash64("_k1", F.lit(seed)), "_chunks"))
    )
    order = F.struct(F.col("size"), F.xxhash64("_k1", F.lit(seed + 1)).alias("h"), *[F.col(c) for c in ("_k1", "_k2", "id", "rows", "rate")])
    lists = dealt.groupBy("source", "source_size", "target", "_chunk").agg(F.sort_array(F.collect_list(order.alias("d")), asc=False).alias("_docs"))

    def step(acc, d):
        size = F.greatest(d["size"], F.lit(1)).cast("double")
        due = acc["due"] + d["rows"] * d["rate"] * size
        most = F.least(d["rows"] * F.ceil(d["rate"]), F.greatest(d["rows"] * F.floor(d["rate"]), F.round(due / size).cast("long"))).cast("long")
        return F.struct((due - most * size).alias("due"), F.concat(acc["copies"], F.array(most)).alias("copies"))

    start = F.struct(F.lit(0.0).alias("due"), F.array().cast("array<bigint>").alias("copies"))
    walked = lists.withColumn("_copies", F.aggregate("_docs", start, step, lambda acc: acc["copies"]))
    one = walked.select("source", "source_size", "target", F.explode(F.arrays_zip("_docs", "_copies")).alias("_d"))
    fields = [F.col(f"_d._docs.{c}").alias(c) for c in ("_k1", "_k2", "id", "size", "rows", "rate")]
    return one.select("source", "source_size", "target", *fields, F.col("_d._copies").alias("copies"))


def of_row(nth):
    """Copies of the nth (from 0) of the rows of a distinct document."""
    return (F.floor(F.col("copies") / F.col("rows")) + (nth < F.col("copies") % F.col("rows")).cast("int")).cast("int")


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 5, id_col: str = "doc_id") -> DataFrame:
    """One row per document: id, source, size, source_size, target, rate, copies, taken."""
    each = planned(docs, weights, cap, seed, id_col).withColumn("_nth", F.explode(F.sequence(F.lit(0).cast("long"), F.col("rows") - 1)))
    out = each.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", "rate", of_row(F.col("_nth")).alias("copies"))
    return out.withColumn("taken", (F.col("copies") * F.col("size")).cast("long"))


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 5, id_col: str = "doc_id") -> DataFrame:
    """Each row of `docs`, with all its columns, as often as the mix takes it.  Texts are shuffled once, to meet their number of copies."""
    plan = planned(docs, weights, cap, seed, id_col).where("copies > 0").select("_k1", "_k2", "rows", "copies")
    met = keyed_rows(docs, id_col, "source", "text").join(shuffled(plan), ["_k1", "_k2"])
    nth = F.row_number().over(Window.partitionBy("_k1", "_k2").orderBy("_k1")) - 1
    met = met.withColumn("_times", of_row(nth)).where("_times > 0")
    return met.withColumn("_time", F.explode(F.sequence(F.lit(1), F.col("_times")))).select("_row.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies", "rate")


QUERIES = {"op4_mixing": query}
ORACLE_SQL: dict[str, str] = {}
