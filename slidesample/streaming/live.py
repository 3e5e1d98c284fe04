"""The live form: micro-batches fill pane summaries, and every window that the watermark has passed is answered once.

State is two tables in a folder: per pane and stratum the count, and the bottom-k candidates by permanent priority; raw windows are never kept,
and batches whose panes lie before all open windows are deleted.  Tables are keyed by batch, and a batch is judged by the batches before it, so a
replayed batch overwrites its own part and changes nothing.  Late rows within the watermark change their
pane like any others; later ones are counted (by batch) and dropped.  Answers are written together, and the next ones start behind the last.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from slidesample.functions.hashing import priority
from slidesample.operators import allocate, estimate, sampling, windows


@dataclass
class LiveWindows:
    """Sliding sums by event time, in whole hours: windows of `length` hours that move by `step`, `size` items sampled each."""

    spark: SparkSession
    folder: str
    length: int
    step: int
    size: int
    origin: int  # first hour (since the epoch)
    delay_hours: int = 1
    seed: str = "live"

    @property
    def slide(self) -> windows.Slide:
        return windows.Slide(self.length, self.step, 10**9, self.origin)

    def on_batch(self, batch: DataFrame, batch_id: int) -> None:
        """Pane summaries of one micro-batch, then the windows that are complete."""
        hour = F.floor(F.unix_seconds("ts") / 3600).cast("long")
        rows = batch.withColumn("seq", hour).withColumn("pane", windows.pane_of(self.slide, "seq")).withColumn("u", priority(self.seed, F.col("item_id")))
        mark = self.watermark(batch_id)
        if mark is not None:
            late = rows.where(F.col("seq") < mark).agg(F.count("*").alias("n"))
            late.write.mode("overwrite").parquet(f"{self.folder}/late/batch={batch_id}")
            rows = rows.where(F.col("seq") >= mark)
        rows = rows.persist()
        try:
            counts = rows.groupBy("pane", "stratum").agg(F.count("*").alias("n"), F.max("seq").alias("latest"))
            counts.write.mode("overwrite").parquet(f"{self.folder}/counts/batch={batch_id}")
            kept = sampling.pane_bottom_k(rows.select("pane", "stratum", "item_id", "value", "u"), self.size)
            kept.write.mode("overwrite").parquet(f"{self.folder}/candidates/batch={batch_id}")
        finally:
            rows.unpersist()
        self.answer_complete()

    def tables(self) -> tuple[DataFrame, DataFrame] | None:
        try:
            return self.spark.read.parquet(f"{self.folder}/counts"), self.spark.read.parquet(f"{self.folder}/candidates")
        except Exception as e:
            if "PATH_NOT_FOUND" in str(e) or "UNABLE_TO_INFER_SCHEMA" in str(e):
                return None
            raise

    def watermark(self, before_batch: int | None = None) -> int | None:
        """Hours before this one are closed (by the batches before `before_batch`)."""
        found = self.tables()
        if not found:
            return None
        counts = found[0] if before_batch is None else found[0].where(F.col("batch") < before_batch)
        latest = counts.agg(F.max("latest")).first()[0]
        return None if latest is None else latest - self.delay_hours

    @property
    def dropped(self) -> int:
        """Rows that came too late."""
        return sum(self.spark.read.parquet(f"{self.folder}/late/{name}").first()[0] for name in self.listed("late"))

    def listed(self, kind: str) -> list[str]:
        """Complete sub-folders of a table, by one listing."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{kind}")
        files = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        return [f.getPath().getName() for f in files.listStatus(path) if f.isDirectory()] if files.exists(path) else []

    def answers(self, first: int, last: int) -> DataFrame:
        """Estimates of windows first … last from pane summaries."""
        counts, candidates = self.tables()
        per = self.length // self.slide.pane
        move = self.step // self.slide.pane
        edges = self.spark.range(first, last + 1).select(F.col("id").alias("window_id"), F.explode(F.sequence(F.col("id") * move, F.col("id") * move + per - 1)).alias("pane"))
        seen = edges.join(counts.groupBy("pane", "stratum").agg(F.sum("n").alias("n")), "pane").groupBy("window_id", "stratum").agg(F.sum("n").alias("n_seen"))
        quotas = allocate.proportional_quota(seen, self.size)
        sample = sampling.merge_bottom_k(candidates.drop("pane_rank", "batch"), edges, quotas, self.size)
        return estimate.estimate_total(sample, seen, F.col("value")).select("window_id", "estimate", "margin", "n_sampled", "n_seen")

    def answer_complete(self) -> None:
        """Answer all windows between the last answered one and the watermark in one job, then drop batches that no open window needs."""
        mark = self.watermark()
        if mark is None:
            return
        done = [int(name.split("-")[1]) for name in self.listed("answers") if name.startswith("w=")]
        first, last = max(done, default=-1) + 1, (mark - self.origin - self.length) // self.step
        if first > last:
            return
        self.answers(first, last).coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/answers/w={first}-{last}")
        need = (last + 1) * (self.step // self.slide.pane)
        for row in self.tables()[0].groupBy("batch").agg(F.max("pane").alias("pane")).where(F.col("pane") < need).collect():  # one row per kept batch
            for kind in ("counts", "candidates"):
                path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{kind}/batch={row['batch']}")
                path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def start(self, stream: DataFrame, checkpoint: str) -> StreamingQuery:
        return stream.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(stream: DataFrame, length: str, slide: str, delay: str) -> DataFrame:
    """The engine's own sliding windows over a stream, with a watermark (reference for tests)."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", length, slide), "stratum").agg(F.count("*").alias("n"))


def deduplicated(stream: DataFrame, delay: str) -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["item_id"])
