"""The adaptive stratified reservoir, item by item.

Sub-reservoir sizes over time depend on counts only (`allocation_timeline`), so once they are known each (window, stratum) is independent
and is replayed in arrival order on its own.  The first arrivals of a window fill the reservoir; at each tick sizes are set anew;
a stratum that grew takes arrivals (the next ones, or a random choice among those its share is expected to bring), one that shrank
evicts at random; otherwise an arrival replaces a random resident with probability size / seen.  Items consumed by a
change of size are not offered again.  This is the fidelity path; bottom-k sampling is the one for scale.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slidesample.operators.allocate import proportional_quota


def tick_quotas(assigned: DataFrame, size: int, tick: int) -> DataFrame:
    """Quota of each stratum after each tick of each window: window_id, stratum, quotas (list by tick)."""
    per = assigned.groupBy("window_id", F.floor((F.col("seq") - F.col("lo")) / tick).cast("long").alias("tick"), "stratum").agg(F.count("*").alias("n"))
    ticks = per.select("window_id", "tick").distinct().join(per.select("window_id", "stratum").distinct(), "window_id")
    along = Window.partitionBy("window_id", "stratum").orderBy("tick")
    seen = ticks.join(per, ["window_id", "tick", "stratum"], "left").withColumn("n_seen", F.sum(F.coalesce("n", F.lit(0))).over(along))
    quota = proportional_quota(seen.where("n_seen > 0").select("window_id", "tick", "stratum", "n_seen"), size, by=("window_id", "tick"))
    return quota.groupBy("window_id", "stratum").agg(F.sort_array(F.collect_list(F.struct("tick", "quota"))).alias("quotas"))


def shrink(sample: DataFrame, size: Column) -> DataFrame:
    """Keep the `size` smallest priorities of each sub-reservoir."""
    order = Window.partitionBy("window_id", "stratum").orderBy("u", "item_id")
    return sample.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= size).drop("_k")


def replay(seqs: np.ndarray, filled: np.ndarray, lo: int, tick: int, quotas: list[tuple[int, int]], grow: str, rng: np.random.Generator) -> list[int]:
    """Positions (in `seqs`) of the residents at the end of the window."""
    residents = np.flatnonzero(filled).tolist()
    sizes, at, due = dict(quotas), int(filled.sum()), []
    seen, current = at, -1
    skip: set[int] = set()
    for pos in range(at, len(seqs)):
        now = int((seqs[pos] - lo) // tick)
        while current < now - 1:  # ticks that ended before this arrival
            current += 1
            target = sizes.get(current)
            if target is None:
                continue
            change = target - len(residents) - len(due)
            if change < 0:
                for _ in range(min(-change, len(residents))):
                    residents.pop(int(rng.integers(len(residents))))
            elif change > 0:
                span = change if grow == "next" else max(change, round(change * max(1, seen) / max(1, len(residents))))
                ahead = np.arange(pos, min(len(seqs), pos + span))
                chosen = ahead[:change] if grow == "next" else rng.choice(ahead, min(change, len(ahead)), replace=False)
                due = sorted({*due, *map(int, chosen)})
        seen += 1
        if due and pos == due[0]:
            residents.append(pos)
            due.pop(0)
            skip.add(pos)
        elif residents and rng.random() < len(residents) / seen:
            residents[int(rng.integers(len(residents)))] = pos
    return residents


def literal_reservoir(assigned: DataFrame, size: int, tick: int, grow: str = "next", seed: int = 7) -> DataFrame:
    """window_id, stratum, item_id, seq, value of the reservoirs at the end of each window."""
    first = F.row_number().over(Window.partitionBy("window_id").orderBy("seq")) <= size
    rows = assigned.withColumn("filled", first).join(tick_quotas(assigned, size, tick), ["window_id", "stratum"])

    def run(key, pdf):
        pdf = pdf.sort_values("seq").reset_index(drop=True)
        quotas = [(int(q["tick"]), int(q["quota"])) for q in pdf["quotas"].iloc[0]]
        rng = np.random.default_rng([seed, int(key[0]), *str(key[1]).encode()])
        kept = replay(pdf["seq"].to_numpy(), pdf["filled"].to_numpy(), int(pdf["lo"].iloc[0]), tick, quotas, grow, rng)
        return pdf.loc[sorted(kept), ["window_id", "stratum", "item_id", "seq", "value"]]

    kind = dict(assigned.dtypes)["item_id"]
    needed = rows.select("window_id", "stratum", "lo", "item_id", "seq", "value", "filled", "quotas")
    return needed.groupBy("window_id", "stratum").applyInPandas(run, f"window_id long, stratum string, item_id {kind}, seq long, value decimal(18,2)")
