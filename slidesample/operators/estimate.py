"""Estimates with margins from stratified samples.

Everything starts from per-stratum partials (items seen `n_all`, sampled `b`, Σv, Σv²), which merge; margins are t-scores times the square root
of the estimated variance of the statistic.  Degenerate strata: all items sampled contribute no variance; one sampled item
of several borrows the pooled variance and raises a flag; a seen but unsampled stratum voids the estimate; without degrees of freedom there
is no margin.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slidesample.functions.hashing import priority
from slidesample.functions.tscore import t_quantile

CONFIDENCE = 0.95


def stratum_parts(sample: DataFrame, counts: DataFrame, value: Column, by: tuple[str, ...] = ("window_id",)) -> DataFrame:
    """Partials per stratum; strata without sampled items keep their counts."""
    v = value.cast("decimal(18,2)")
    sums = sample.groupBy(*by, "stratum").agg(F.count("*").alias("b"), F.sum(v).alias("sv"), F.sum(v * v).alias("svv"))
    return counts.select(*by, "stratum", F.col("n_seen").alias("n_all")).join(sums, [*by, "stratum"], "left").select(
        *by, "stratum", "n_all", F.coalesce("b", F.lit(0).cast("long")).alias("b"), F.coalesce(F.col("sv").cast("double"), F.lit(0.0)).alias("sv"), F.coalesce(F.col("svv").cast("double"), F.lit(0.0)).alias("svv")
    )


def sample_variance() -> Column:
    return F.when(F.col("b") > 1, F.greatest(F.lit(0.0), (F.col("svv") - F.col("sv") * F.col("sv") / F.col("b")) / (F.col("b") - 1)))


def total_terms(parts: DataFrame, by: tuple[str, ...], s2: Column | None = None) -> DataFrame:
    """One row per group: estimate, variance, df, n_sampled, n_seen, strata, flags."""
    s2 = sample_variance() if s2 is None else s2
    with_s2 = parts.withColumn("s2", s2)
    pooled = F.sum(F.col("s2") * (F.col("b") - 1)).over(_group(by)) / F.sum(F.when(F.col("b") > 1, F.col("b") - 1)).over(_group(by))
    with_s2 = with_s2.withColumn("_s2", F.coalesce("s2", pooled))
    term = F.when(F.col("b") == 0, F.lit(0.0)).when(F.col("n_all") == F.col("b"), F.lit(0.0)).otherwise(F.col("n_all") * (F.col("n_all") - F.col("b")) * F.col("_s2") / F.col("b"))
    return with_s2.groupBy(*by).agg(
        F.sum(F.when(F.col("b") > 0, F.col("n_all") / F.col("b") * F.col("sv")).otherwise(0.0)).alias("estimate"),
        F.sum(term).alias("variance"),
        (F.sum("b") - F.count(F.when(F.col("b") > 0, 1))).alias("df"),
        F.sum("b").alias("n_sampled"),
        F.sum("n_all").alias("n_seen"),
        F.max(F.when((F.col("b") == 1) & (F.col("n_all") > 1), 1).otherwise(0)).alias("pooled"),
        F.max(F.when((F.col("b") == 0) & (F.col("n_all") > 0), 1).otherwise(0)).alias("refused"),
    )


def _group(by):
    from pyspark.sql import Window

    return Window.partitionBy(*by)


def with_margin(terms: DataFrame, confidence: float = CONFIDENCE, scale: Column | None = None) -> DataFrame:
    """estimate ± margin, as columns; `scale` divides both (for means)."""
    scale = F.lit(1.0) if scale is None else scale
    t = t_quantile(F.col("df"), 1 - (1 - confidence) / 2)
    exact = F.col("n_sampled") == F.col("n_seen")
    margin = F.when(exact, F.lit(0.0)).otherwise(t * F.sqrt("variance")) / scale
    estimate = F.when(F.col("refused") == 0, F.col("estimate") / scale)
    return (
        terms.withColumn("_e", estimate)
        .withColumn("_m", F.when(F.col("refused") == 0, margin))
        .drop("estimate")
        .withColumn("estimate", F.round("_e", 6))
        .withColumn("margin", F.round("_m", 6))
        .withColumn("lower", F.round(F.col("_e") - F.col("_m"), 6))
        .withColumn("upper", F.round(F.col("_e") + F.col("_m"), 6))
        .withColumn("small_sample", F.col("n_sampled") < 30)
        .drop("_e", "_m", "variance")
    )


def estimate_total(sample, counts, value, by=("window_id",), confidence=CONFIDENCE):
    return with_margin(total_terms(stratum_parts(sample, counts, value, by), by), confidence)


def estimate_mean(sample, counts, value, by=("window_id",), confidence=CONFIDENCE):
    return with_margin(total_terms(stratum_parts(sample, counts, value, by), by), confidence, F.col("n_seen").cast("double"))


def estimate_count(sample, counts, predicate: Column, by=("window_id",), confidence=CONFIDENCE):
    return estimate_total(sample, counts, F.when(predicate, 1).otherwise(0), by, confidence)


def estimate_by_group(sample: DataFrame, counts: DataFrame, value: Column, group: str, by=("window_id",), confidence=CONFIDENCE) -> DataFrame:
    """Totals of each value of `group`; an item of another group counts as zero in its stratum's variance."""
    v = value.cast("decimal(18,2)")
    sizes = sample.groupBy(*by, "stratum").agg(F.count("*").alias("b")).join(counts.select(*by, "stratum", F.col("n_seen").alias("n_all")), [*by, "stratum"])
    sums = sample.groupBy(*by, "stratum", group).agg(F.sum(v).cast("double").alias("sv"), F.sum(v * v).cast("double").alias("svv"))
    groups = sums.select(*by, group).distinct()
    parts = groups.join(sizes, list(by)).join(sums, [*by, "stratum", group], "left").fillna(0.0, ["sv", "svv"])
    return with_margin(total_terms(parts, (*by, group)), confidence)


def estimate_ratio(sample: DataFrame, counts: DataFrame, num: Column, den: Column, by=("window_id",), confidence=CONFIDENCE) -> DataFrame:
    """Ratio of two totals; variance of the linearised residuals from the sums Σn, Σd, Σnn, Σnd, Σdd of one pass."""
    sums = sample.groupBy(*by, "stratum").agg(
        F.count("*").alias("b"), *[F.sum(x).cast("double").alias(n) for n, x in (("sn", num), ("sd", den), ("snn", num * num), ("snd", num * den), ("sdd", den * den))]
    )
    parts = counts.select(*by, "stratum", F.col("n_seen").alias("n_all")).join(sums, [*by, "stratum"])
    weight = F.col("n_all") / F.col("b")
    ratio = parts.withColumn("r", F.sum(weight * F.col("sn")).over(_group(by)) / F.sum(weight * F.col("sd")).over(_group(by))).withColumn("den", F.sum(weight * F.col("sd")).over(_group(by)))
    r = F.col("r")
    residual = ratio.select(*by, "stratum", "n_all", "b", "r", "den", (F.col("sn") - r * F.col("sd")).alias("sv"), (F.col("snn") - 2 * r * F.col("snd") + r * r * F.col("sdd")).alias("svv"))
    terms = total_terms(residual, by)
    keep = residual.groupBy(*by).agg(F.first("r").alias("_r"), F.first("den").alias("_d"))
    joined = terms.join(keep, list(by)).withColumn("estimate", F.col("_r") * F.col("_d"))
    return with_margin(joined, confidence, F.col("_d")).drop("_r", "_d")


def estimate_extreme(sample: DataFrame, value: Column, blocks: int, by=("window_id",)) -> DataFrame:
    """Sample maximum with an experimental Gumbel bound fitted to block maxima by moments."""
    euler = 0.5772156649015329
    block = F.pmod(priority("block", F.col("item_id")), F.lit(blocks))
    per = sample.groupBy(*by, block.alias("block")).agg(F.max(value).cast("double").alias("m"))
    beta = F.stddev_samp("m") * F.lit(6**0.5 / 3.141592653589793)
    out = per.groupBy(*by).agg(F.max("m").alias("sample_max"), F.count("*").alias("blocks"), F.avg("m").alias("_mean"), beta.alias("_beta"))
    # 95 % quantile of the largest of all blocks
    bound = F.col("_mean") - euler * F.col("_beta") + F.col("_beta") * (F.log(F.col("blocks").cast("double")) - F.log(F.lit(-np.log(0.95))))
    return out.select(*by, F.round("sample_max", 4).alias("sample_max"), "blocks", F.round(F.greatest(bound, F.col("sample_max")), 4).alias("upper_95"))


def bootstrap_total(sample: DataFrame, counts: DataFrame, reps: int = 200, seed: int = 9) -> DataFrame:
    """Percentile interval of the total from Poisson bootstrap replicates, per window."""
    sized = sample.join(counts.select("window_id", "stratum", F.col("n_seen").alias("n_all")), ["window_id", "stratum"]).select("window_id", "stratum", "item_id", F.col("value").cast("double").alias("value"), "n_all")

    def run(key, pdf):
        pdf = pdf.sort_values(["stratum", "item_id"])
        rng = np.random.default_rng([seed, int(key[0])])
        totals = np.zeros(reps)
        for _, part in pdf.groupby("stratum"):
            w = rng.poisson(1.0, size=(len(part), reps))
            n = np.maximum(w.sum(axis=0), 1)
            totals += part["n_all"].iloc[0] * (part["value"].to_numpy() @ w) / n
        return pd.DataFrame({"window_id": [key[0]], "mean": [totals.mean()], "lower": [np.quantile(totals, 0.025)], "upper": [np.quantile(totals, 0.975)]})

    return sized.groupBy("window_id").applyInPandas(run, "window_id long, mean double, lower double, upper double")
