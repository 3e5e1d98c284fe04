"""The memo as durable tables: one folder per window, a pointer written last, and ways to go on when it is lost."""

from __future__ import annotations

import tempfile
import uuid
from concurrent.futures import Future, ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F



def shared_folder(spark: SparkSession) -> str:
    """`spark.checkpoint.dir`; where it is unset, a temporary folder for a local master only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not getattr(spark, "_slidesample_memo", None):
        spark._slidesample_memo = tempfile.mkdtemp(prefix="slidesample-memo-")
    return spark._slidesample_memo


def checkpointed(df: DataFrame) -> DataFrame:
    """`df` written below the shared folder and read back: cuts a plan that grew in a loop."""
    path = f"{shared_folder(df.sparkSession)}/loop/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class MemoStore:
    """Samples and partial results of the last windows under `folder`; a replica folder is optional.

    A write is complete once its success marker exists (Spark's committer), so a replayed batch overwrites the same
    folder and changes nothing.
    """

    def __init__(self, spark: SparkSession, folder: str, replica: str | None = None):
        self.spark, self.folder, self.replica = spark, folder, replica
        self.background = ThreadPoolExecutor(1) if replica else None
        self.pending: list[Future] = []

    def path(self, kind: str, window_id: int, root: str | None = None) -> str:
        return f"{root or self.folder}/{kind}/window_id={window_id}"

    def write(self, kind: str, window_id: int, rows: DataFrame) -> None:
        rows.write.mode("overwrite").parquet(self.path(kind, window_id))

    def replicate_later(self, kind: str, window_id: int) -> None:
        """Copy in the background: the next window does not wait for it."""
        if self.background:
            self.pending.append(self.background.submit(self.replicate, kind, window_id))

    def settle(self) -> None:
        """Wait for the copies; raises what went wrong in one of them."""
        for f in self.pending:
            f.result()
        self.pending.clear()

    def replicate(self, kind: str, window_id: int) -> None:
        if self.replica:
            self.spark.read.parquet(self.path(kind, window_id)).write.mode("overwrite").parquet(self.path(kind, window_id, self.replica))

    def read(self, kind: str, window_id: int, schema, on_loss: str = "cold") -> DataFrame:
        """The rows, or after a loss those of the replica, or none (`on_loss='cold'`)."""
        for root in [self.folder, *([self.replica] if self.replica else [])]:
            if self.exists(self.path(kind, window_id, root)):
                return self.spark.read.schema(schema).parquet(self.path(kind, window_id, root))
        if on_loss == "fail":
            raise FileNotFoundError(self.path(kind, window_id))
        return self.spark.createDataFrame([], schema)

    def exists(self, path: str) -> bool:
        jvm = self.spark._jvm
        hadoop = jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
        return hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(hadoop)

    def forget_later(self, kind: str, window_id: int) -> None:
        """Forget once the copies that were asked for before are made."""
        if self.background:
            self.pending.append(self.background.submit(self.forget, kind, window_id))
        else:
            self.forget(kind, window_id)

    def forget(self, kind: str, window_id: int) -> None:
        """Delete both copies."""
        jvm = self.spark._jvm
        for root in [self.folder, *([self.replica] if self.replica else [])]:
            hadoop = jvm.org.apache.hadoop.fs.Path(self.path(kind, window_id, root))
            hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(hadoop, True)

    def lose(self, kind: str, window_id: int) -> None:
        """Delete the first copy only (what a failed disk does; for tests and drills)."""
        hadoop = self.spark._jvm.org.apache.hadoop.fs.Path(self.path(kind, window_id))
        hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def rebuild(sample: DataFrame, stored: DataFrame, *keys: str) -> DataFrame:
    """Chunk fingerprints of a sample where `stored` has lost some: the missing ones are computed, the others read."""
    from slidesample.operators.incremental import fingerprints

    missing = sample.join(stored.select(*keys), list(keys), "left_anti")
    return stored.withColumn("source", F.lit("memo")).unionByName(fingerprints(missing, *keys).withColumn("source", F.lit("rebuilt")))


def hot_entries(hits: DataFrame, least: int) -> DataFrame:
    """Entries that were reused at least `least` times: the ones worth a replica."""
    return hits.groupBy("stratum", "pane").agg(F.sum("hit").alias("hits")).where(F.col("hits") >= least)
