"""The window loop: one window after the other, sampled within a budget, biased towards what is known, computed from what changed.

Every window: items before its start expire and new ones are admitted (arrivals alone are counted, by pane); the budget and the history of measured
costs give a sample size; strata get proportional quotas; a fresh sample is drawn and biased towards the memo; the aggregate is brought up to date;
sample, partials and answer are written; the window advances.

The aggregate: with an inverse, items that enter or leave the sample are added to or taken from the stored partials, and no value of an item that stays is
read.  Without one, the sample is cut into chunks of pane and stratum; partials of chunks whose fingerprint is in the memo are read back, the others computed, and all merged.

The memo is a set of tables in a folder (`MemoStore`).  After a restart `resumed` goes on behind the last window that was answered; one that was interrupted overwrites its own
tables.  Lost tables come from the replica, or the loop goes on without them: a full sample, nothing reused, and a correct answer.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slidesample.functions.hashing import priority
from slidesample.operators import allocate, carryover, estimate, incremental, sampling
from slidesample.operators.budget import Budget, Past, exceeded, sample_size
from slidesample.operators.memo import MemoStore
from slidesample.operators.spec import AggregateSpec

PARTIALS = "stratum string, b long, sv decimal(38,2), svv decimal(38,4)"
CHUNKS = "pane long, stratum string, n long, hash_sum decimal(38,0), b long, sv decimal(38,2), svv decimal(38,4), extreme decimal(18,2)"
COUNTS = "pane long, stratum string, n long"
MEASURES = "window_id long, lo long, hi long, sample_size long, n_seen long, n_sampled long, n_known long, values_read long, seconds double, items_per_second double, over boolean, violations long"


@dataclass
class WindowLoop:
    """State of a run: where the next window lies, its budget and what the past ones cost.  All of it may be changed between windows."""

    spark: SparkSession
    folder: str
    spec: AggregateSpec
    budget: Budget
    length: int
    step: int
    pane: int
    lo: int = 0
    window_id: int = 0
    seed: str = "loop"
    refill: str = "hash"
    confidence: float = 0.95
    replica: str | None = None
    history: list[Past] = field(default_factory=list)
    violations: int = 0

    def __post_init__(self):
        self.store = MemoStore(self.spark, self.folder, self.replica)

    def resumed(self) -> WindowLoop:
        """Go on behind the windows that the folder has answers of (with this object's step)."""
        while self.store.exists(self.store.path("answers", self.window_id)):
            self.window_id, self.lo = self.window_id + 1, self.lo + self.step
        return self

    # --- one window ---

    def answer(self, items: DataFrame) -> tuple:
        """Answer the window at `lo`, then advance by `step`; items(item_id, seq, stratum, value, …).  Returns one row of MEASURES."""
        began, w, hi = time.perf_counter(), self.window_id, self.lo + self.length
        counts = self.admitted(items, hi)
        seen = counts.agg(F.sum("n_seen")).first()[0] or 0
        size = sample_size(self.budget, self.history, seen)
        quotas = allocate.proportional_quota(counts, size)
        biased = self.biased(items, quotas, size, hi)
        self.store.write("items", w, biased)
        kind = items.select("item_id").schema["item_id"].dataType.simpleString()
        biased = self.store.read("items", w, f"window_id long, stratum string, item_id {kind}, seq long, value decimal(18,2), u long, from_memo boolean")
        previous = self.memo_items(kind) if w else biased.limit(0)
        parts, read = (self.by_changes if self.spec.invertible else self.by_chunks)(biased, previous)
        complete = counts.select("window_id", "stratum", F.col("n_seen").alias("n_all")).join(parts, "stratum", "left").fillna(0, ["b", "sv", "svv"])
        self.store.write("answers", w, self.spec.finish(complete, self.confidence))
        out = self.spark.read.parquet(self.store.path("answers", w)).first()
        known, sampled = biased.agg(F.count_if("from_memo"), F.count("*")).first()
        for table in ("items", "partials" if self.spec.invertible else "chunks"):
            self.store.replicate_later(table, w)
        return self.advance(w, hi, size, seen, sampled, known, read, time.perf_counter() - began, out, parts, counts)

    def advance(self, w, hi, size, seen, sampled, known, read, seconds, out, parts, counts) -> tuple:
        over = exceeded(self.budget, sampled, seconds, out["margin"] if out else None)
        self.violations += over
        spread = None
        if self.budget.kind == "accuracy":
            s2 = estimate.sample_variance()
            spread = parts.join(counts.select("stratum", "n_seen"), "stratum").agg(F.sum(F.col("n_seen") * s2.cast("double"))).first()[0]
        self.history.append(Past(sampled, seconds, over, spread))
        for table in ("items", "partials", "chunks", "counts"):
            if w >= 1 and table != "counts":
                self.store.forget_later(table, w - 1)
        row = (w, self.lo, hi, size, seen, sampled, known, read, round(seconds, 4), round(seen / seconds, 1), over, self.violations)
        self.window_id, self.lo = w + 1, self.lo + self.step
        return row

    def admitted(self, items: DataFrame, hi: int) -> DataFrame:
        """Counts by stratum; only panes that arrived since the last window are counted, the others are read from the memo."""
        w, pane = self.window_id, F.floor(F.col("seq") / self.pane).cast("long")
        stored = self.store.read("counts", w - 1, COUNTS) if w else self.spark.createDataFrame([], COUNTS)
        known = w and self.store.exists(self.store.path("counts", w - 1))
        begin = max(self.lo, hi - self.step) if known else self.lo
        begin = min(begin, self.counted_to) if known and hasattr(self, "counted_to") else begin
        arrivals = items.where((F.col("seq") >= begin) & (F.col("seq") < hi)).groupBy(pane.alias("pane"), "stratum").agg(F.count("*").alias("n"))
        kept = stored.where((F.col("pane") >= self.lo // self.pane) & (F.col("pane") < begin // self.pane))
        self.store.write("counts", w, kept.unionByName(arrivals))
        self.counted_to = hi
        if w:
            self.store.forget("counts", w - 1)
        now = self.spark.read.schema(COUNTS).parquet(self.store.path("counts", w))
        return now.groupBy("stratum").agg(F.sum("n").alias("n_seen")).withColumn("window_id", F.lit(w).cast("long"))

    def memo_items(self, kind: str) -> DataFrame:
        return self.store.read("items", self.window_id - 1, f"window_id long, stratum string, item_id {kind}, seq long, value decimal(18,2), u long, from_memo boolean")

    def biased(self, items: DataFrame, quotas: DataFrame, size: int, hi: int) -> DataFrame:
        """Fresh stratified sample of the window, then memo items first up to each quota."""
        w = self.window_id
        draw = lambda df: df.withColumn("window_id", F.lit(w).cast("long")).withColumn("u", priority(self.seed, F.col("item_id"), F.col("window_id")))
        inside = items.where((F.col("seq") >= self.lo) & (F.col("seq") < hi)).select("item_id", "seq", "stratum", self.spec.item_value().alias("value"))
        fresh = sampling.fixed_size_sample(draw(inside), quotas, max(1, size))
        columns = ["window_id", "stratum", "item_id", "seq", "value", "u"]
        if not w:
            return fresh.select(*columns).withColumn("from_memo", F.lit(False))
        kind = items.select("item_id").schema["item_id"].dataType.simpleString()
        memo = draw(self.memo_items(kind).where((F.col("seq") >= self.lo) & (F.col("seq") < hi)).select("stratum", "item_id", "seq", "value"))
        return carryover.carry_over(fresh, memo, quotas, "biased", "hash", self.refill)

    # --- bringing the aggregate up to date; the stored samples hold the value of the query of each item ---

    def by_changes(self, biased: DataFrame, previous: DataFrame) -> tuple[DataFrame, int]:
        """Stored partials, plus what entered, less what left: (partials by stratum, values read)."""
        w, plain = self.window_id, AggregateSpec("sum")
        stored = self.store.read("partials", w - 1, PARTIALS) if w else self.spark.createDataFrame([], PARTIALS)
        if w and not self.recalled("partials"):
            previous = biased.limit(0)  # cold: all of the sample enters
        entering = biased if not w or not self.recalled("partials") else biased.where("NOT from_memo")
        leaving = previous.join(biased.select("stratum", "item_id"), ["stratum", "item_id"], "left_anti")
        changed = entering.select("stratum", "value").withColumn("sign", F.lit(1)).unionByName(leaving.select("stratum", "value").withColumn("sign", F.lit(-1)))
        changed = changed.persist()
        try:
            merged = plain.merged(stored.unionByName(plain.partials(changed, "stratum", sign=F.col("sign"))), "stratum")
            self.store.write("partials", w, merged)
            read = changed.count()
        finally:
            changed.unpersist()
        return self.spark.read.schema(PARTIALS).parquet(self.store.path("partials", w)), read

    def by_chunks(self, biased: DataFrame, previous: DataFrame) -> tuple[DataFrame, int]:
        """Chunks with known fingerprints are read back, the others computed: (merged partials by stratum, values read)."""
        w, plain = self.window_id, AggregateSpec(self.spec.fn)
        stored = self.store.read("chunks", w - 1, CHUNKS) if w else self.spark.createDataFrame([], CHUNKS)
        rows = biased.withColumn("pane", F.floor(F.col("seq") / self.pane).cast("long"))
        keys = ["pane", "stratum", "n", "hash_sum"]
        prints = incremental.fingerprints(rows, "pane", "stratum")
        reused = stored.join(prints, keys, "left_semi")
        dirty = prints.join(stored, keys, "left_anti")
        fresh_rows = rows.join(dirty.select("pane", "stratum"), ["pane", "stratum"], "left_semi")
        fresh = dirty.join(plain.partials(fresh_rows, "pane", "stratum"), ["pane", "stratum"])
        columns = [c.split()[0] for c in CHUNKS.split(", ")]
        self.store.write("chunks", w, reused.select(*columns).withColumn("fresh", F.lit(False)).unionByName(fresh.select(*columns).withColumn("fresh", F.lit(True))))
        now = self.spark.read.parquet(self.store.path("chunks", w))
        read = now.where("fresh").agg(F.sum("n")).first()[0] or 0
        return plain.merged(now, "stratum"), read

    def recalled(self, table: str) -> bool:
        """Is the last window's table there, in either copy?"""
        roots = [self.folder, *([self.replica] if self.replica else [])]
        both = [table, "items"]
        return all(any(self.store.exists(self.store.path(t, self.window_id - 1, r)) for r in roots) for t in both)


def run_windows(items: DataFrame, loop: WindowLoop, count: int, budgets: dict[int, Budget] | None = None) -> tuple[DataFrame, DataFrame]:
    """Answer `count` windows: (window_id, estimate, margin, n_sampled, n_seen), and what each cost (MEASURES).  `budgets` changes the budget from a window on."""
    rows = []
    for _ in range(count):
        loop.budget = (budgets or {}).get(loop.window_id, loop.budget)
        rows.append(loop.answer(items))
    loop.store.settle()
    answers = loop.spark.read.parquet(f"{loop.folder}/answers")
    return answers.select(F.col("window_id").cast("long").alias("window_id"), "estimate", "margin", "n_sampled", "n_seen"), loop.spark.createDataFrame(rows, MEASURES)
