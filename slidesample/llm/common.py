"""What several training-data operators share: word patterns, staging, table access."""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a maximal run of characters other than ASCII white space (fixed value).
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: `spark.checkpoint.dir`.  Where it is unset, a local master gets a temporary one; a cluster raises."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not getattr(spark, "_slidesample_shared", None):
        spark._slidesample_shared = tempfile.mkdtemp(prefix="slidesample-")
    return spark._slidesample_shared


_MADE: list[str] = []


def staged(df: DataFrame, tag: str) -> DataFrame:
    """Write `df` as Parquet below the shared folder and read it back: cuts lineage, survives lost executors.

    Whoever wrote the results that read these files deletes them with `dropped`, or makes them inside `scratch`.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    _MADE.append(path)
    return out


def dropped(spark: SparkSession, *paths: str) -> None:
    """Delete staged tables."""
    for path in paths:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        if path in _MADE:
            _MADE.remove(path)


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """Tables staged inside are deleted at the end; `keep(df)` exempts one."""
    before, kept = set(_MADE), set()

    def keep(df: DataFrame) -> DataFrame:
        kept.add(df._staged_path)
        return df

    yield keep
    dropped(spark, *[p for p in list(_MADE) if p not in before and p not in kept])


def shuffled(df: DataFrame) -> DataFrame:
    """`df` as a side of a join whose sides both grow: sorted and merged at every size, skewed keys split at run time."""
    return df.hint("merge")


#: A hot key of such a join is dealt to so many tasks (run-time splitting of skewed partitions goes on from there).
SALTS = 64


def salt(*cols: str) -> Column:
    return F.pmod(F.xxhash64(*cols), F.lit(SALTS)).cast("int")


def salts_seen(*cols: str) -> Column:
    """Aggregate: a bit for every salt that occurs, so that the aggregate's row is repeated for these only."""
    return F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), salt(*cols)))


def per_salt(df: DataFrame, seen: str) -> DataFrame:
    """A row for every salt in the column `seen`, as `_salt`."""
    there = lambda i: F.call_function("shiftright", F.col(seen), i).bitwiseAND(1) == 1
    return df.withColumn("_salt", F.explode(F.filter(F.sequence(F.lit(0), F.lit(SALTS - 1)), there))).drop(seen)


def row_keys(*cols: str) -> list[Column]:
    """Two 64-bit hashes of these columns (nulls count), `_k1` and `_k2`: an identity for rows whose ids may be null or repeated."""
    flagged = [x for c in cols for x in (F.col(c).isNull(), F.col(c))]
    return [F.xxhash64(*flagged).alias("_k1"), F.xxhash64(F.lit(7), *flagged[::-1]).alias("_k2")]


def keyed_rows(docs: DataFrame, *cols: str) -> DataFrame:
    """`_row` (all columns of `docs` in one struct, so that no name can clash) and its keys over `cols`."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), *row_keys(*cols))


def lower_ascii(c: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def let(value: Column, body) -> Column:
    """Evaluate `value` once and hand it to `body` as a variable (keeps lambdas from re-evaluating it)."""
    return F.element_at(F.transform(F.array(value), body), 1)
