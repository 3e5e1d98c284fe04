"""Running partials of each sub-stream as arbitrary state: counts and sums that survive restarts, without panes or windows.

The state is three numbers a stratum in the engine's state store (RocksDB).  It answers what the whole stream so far amounts to, while `live` answers windows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

OUT = "stratum string, n long, total double, squares double"


class StratumTotals(StatefulProcessor):
    """Adds each batch's items to the totals of their stratum and emits them."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.totals = handle.getValueState("totals", "n long, total double, squares double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n, total, squares = self.totals.get() if self.totals.exists() else (0, 0.0, 0.0)
        for pdf in rows:
            v = pdf["value"].astype(float)
            n, total, squares = n + len(v), total + float(v.sum()), squares + float((v * v).sum())
        self.totals.update((n, total, squares))
        yield pd.DataFrame({"stratum": [key[0]], "n": [n], "total": [total], "squares": [squares]})

    def close(self) -> None:
        pass


def running_totals(stream: DataFrame) -> DataFrame:
    """items(stratum, value) as a stream -> totals of the strata that a batch touched."""
    return stream.select("stratum", "value").groupBy("stratum").transformWithStateInPandas(statefulProcessor=StratumTotals(), outputStructType=OUT, outputMode="Update", timeMode="None")


def use_rocksdb(spark: SparkSession) -> None:
    """The state store that arbitrary state needs (a setting of running sessions)."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
