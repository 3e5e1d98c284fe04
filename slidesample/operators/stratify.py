"""Strata when sub-streams are not what they seem: merging, learning, diagnosing."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slidesample.functions.hashing import priority
from slidesample.operators.memo import checkpointed


def stratify_by(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumn("stratum", F.concat_ws("/", *columns))


def stratum_statistics(items: DataFrame) -> DataFrame:
    v = F.col("value").cast("double")
    return items.groupBy("stratum").agg(F.count("*").alias("n"), F.avg(v).alias("mean"), F.var_samp(v).alias("variance"))


def merge_similar(stats: DataFrame, tolerance: float) -> DataFrame:
    """Join strata whose means differ by less than `tolerance` standard errors: label = smallest name reachable, through chains of any length."""
    a, b = stats.alias("a"), stats.alias("b")
    error = F.sqrt(F.col("a.variance") / F.col("a.n") + F.col("b.variance") / F.col("b.n"))
    close = a.join(b, F.abs(F.col("a.mean") - F.col("b.mean")) <= tolerance * error).select(F.col("a.stratum").alias("x"), F.col("b.stratum").alias("y"))
    label = stats.select("stratum", F.col("stratum").alias("merged"))
    close, label = checkpointed(close), checkpointed(label)
    while True:
        step = close.join(label, close.y == label.stratum).groupBy("x").agg(F.min("merged").alias("merged")).select(F.col("x").alias("stratum"), "merged")
        step = checkpointed(step)
        if step.join(label.withColumnRenamed("merged", "was"), "stratum").where("merged <> was").isEmpty():
            return step
        label = step


def fit_bootstrap_strata(sample: DataFrame, classes: int = 4, reps: int = 100, seed: int = 3) -> DataFrame:
    """Intervals of value for each class: replicate quantiles of an initial sample, averaged (Poisson bootstrap; sample-sized input)."""
    one = sample.select("item_id", F.col("value").cast("double").alias("value")).withColumn("_g", F.lit(1))

    def run(pdf):
        pdf = pdf.sort_values("item_id")
        rng, v = np.random.default_rng(seed), pdf["value"].to_numpy()
        cuts = [np.quantile(v[rng.integers(0, len(v), len(v))], np.linspace(0, 1, classes + 1)[1:-1]) for _ in range(reps)]
        edges = [-np.inf, *np.mean(cuts, axis=0), np.inf]
        return pd.DataFrame({"stratum": [f"c{i}" for i in range(classes)], "low": edges[:-1], "high": edges[1:]})

    return one.groupBy("_g").applyInPandas(run, "stratum string, low double, high double")


def assign_stratum(items: DataFrame, intervals: DataFrame) -> DataFrame:
    """Range join with a handful of intervals."""
    v = F.col("value").cast("double")
    return items.drop("stratum").join(F.broadcast(intervals), (v >= F.col("low")) & (v < F.col("high"))).drop("low", "high")


def self_train_strata(vectors: DataFrame, share: float = 0.1, rounds: int = 4) -> DataFrame:
    """Few labelled, many unlabelled vectors: centroids of the labelled ones, then of all by their current label, round after round.

    vectors(vec_id, embedding, label) -> vec_id, label (true), known, predicted.
    """
    known = priority("semi", F.col("vec_id")).cast("double") / F.lit(float(16**15)) < F.lit(share)
    rows = vectors.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"), known.alias("known"))
    current = rows.where("known").select("vec_id", F.col("label").alias("predicted"), "v")
    for _ in range(rounds):
        centre = current.select("predicted", F.posexplode("v").alias("i", "x")).groupBy("predicted", "i").agg(F.avg("x").alias("x"))
        centre = centre.groupBy("predicted").agg(F.sort_array(F.collect_list(F.struct("i", "x"))).alias("_c")).select("predicted", F.transform("_c", lambda e: e["x"]).alias("c"))
        centres = centre.agg(F.collect_list(F.struct("predicted", "c")).alias("cs"))  # one row: classes x dimensions
        distance = lambda c: F.aggregate(F.zip_with("v", c["c"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, d: s + d)
        scored = rows.crossJoin(F.broadcast(centres)).withColumn("_b", F.array_min(F.transform("cs", lambda c: F.struct(distance(c).alias("d"), c["predicted"].alias("p")))))
        labelled = scored.select("vec_id", "label", "known", "v", F.when(F.col("known"), F.col("label")).otherwise(F.col("_b.p")).alias("predicted"))
        current = labelled.select("vec_id", "predicted", "v")
    return labelled.select("vec_id", "label", "known", "predicted")


def diagnostics(items: DataFrame) -> DataFrame:
    """Within and between variance, and lag-1 correlation of each stratum: is it homogeneous and independent?"""
    v = F.col("value").cast("double")
    lagged = items.withColumn("x", v).withColumn("y", F.lag(v).over(Window.partitionBy("stratum").orderBy("seq")))
    whole = Window.partitionBy()
    out = lagged.groupBy("stratum").agg(F.count("*").alias("n"), F.avg("x").alias("mean"), F.var_pop("x").alias("within"), F.corr("x", "y").alias("lag_1"))
    grand = F.sum(F.col("n") * F.col("mean")).over(whole) / F.sum("n").over(whole)
    return out.withColumn("between", F.sum(F.col("n") * F.pow(F.col("mean") - grand, 2)).over(whole) / F.sum("n").over(whole)).select(
        "stratum", "n", F.round("mean", 6).alias("mean"), F.round("within", 6).alias("within"), F.round("between", 6).alias("between"), F.round("lag_1", 6).alias("lag_1")
    )
