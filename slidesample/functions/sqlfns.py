"""SQL names for users who write SQL: expressions only, so they stay inside generated code."""

from __future__ import annotations

from pyspark.sql import SparkSession

from slidesample.functions.hashing import HEX
from slidesample.functions.tscore import corrections


def register(spark: SparkSession) -> None:
    """`item_priority(seed, id)` and `t_quantile_975(df)` (expansion; for more than 30 degrees of freedom) as temporary functions."""
    c = corrections(0.975)
    series = " + ".join(f"{x!r} / pow(df, {i})" if i else repr(x) for i, x in enumerate(c))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION item_priority(seed STRING, id STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(concat_ws('|', seed, id)), 1, {HEX}), 16, 10) AS BIGINT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION t_quantile_975(df DOUBLE) RETURNS DOUBLE RETURN {series}")
