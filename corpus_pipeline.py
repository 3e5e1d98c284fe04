"""Corpus preparation in five stages, each on all that its predecessor kept.

quality rules -> one document of each group of near copies -> benchmark decontamination -> mixing sources -> sharding.
Every stage takes (spark, docs, sf_dir); all but the last return the columns of `docs`.  A stage shuffles whole texts only to meet a narrow
result by the row's identity (a hash of its id and text), so ids may be null or repeated and extra columns may have any name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slidesample.llm import jaccard, mixing, quality_rules, sharding, tiling
from slidesample.llm.common import keyed_rows, scratch, shuffled, staged, table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the risk-controlled cutoffs.

    Null or empty texts fail the base rules and go; a null language is a stratum; repeated rows share their verdict; no rows, no result.
    """
    return quality_rules.kept_documents(docs, table(spark, sf_dir, "labels"))


def near_copy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each component of near copies (five-word shingles, similarity 0.8), one row of it.

    Of rows with equal id and text one stays.  Rows of one id and unlike texts stay or go together.  Null or empty texts are near nothing and stay;
    so do rows without an id, of which none is known to be the smallest.
    """
    found = jaccard.jaccard_components(docs, words=5, percent=80)
    gone = staged(found.where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct(), "pipeline-copies")
    rows = keyed_rows(docs, "text").withColumn("_id", F.col("_row.doc_id"))
    left = rows.where("_id IS NOT NULL").join(shuffled(gone), F.col("_id") == F.col("_gone"), "left_anti")
    first = F.row_number().over(Window.partitionBy("_id", "_k1", "_k2").orderBy("_id"))
    left = left.withColumn("_nth", first).where("_nth = 1").select("_row")
    return left.unionByName(rows.where("_id IS NULL").select("_row")).select("_row.*")


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain no benchmark item.  Null or empty texts contain none and stay; repeated rows are judged alike; an empty benchmark keeps all."""
    return tiling.without_leaks(docs, table(spark, sf_dir, "benchmark"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many copies of each row as the mix takes (none to three).  Texts without words are not taken; a null source is a source; repeated rows share the copies of all of them."""
    return mixing.mixed_documents(docs)


def sharding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row with its shard and slot.  Null texts have size 1; rows equal in id, size and checksum are interchangeable; extra columns end here."""
    return sharding.shard_rows(docs, keep=("lang", "source", "n_chars", "text")).select("doc_id", "text", "lang", "source", "n_chars", "size", "text_crc32", "shard", "slot")


STAGES = [
    ("quality_rules", quality_stage),
    ("ngram_jaccard_join", near_copy_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
    ("sharding", sharding_stage),
]

#: Labels, tilings, tilts and permutations have no SQL; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage.  What the stages staged for themselves, and all but the last output, is deleted on the way."""
    docs = table(spark, sf_dir, "documents")
    with scratch(spark) as keep_last:
        for name, stage in STAGES:
            with scratch(spark) as keep:
                docs = keep(staged(stage(spark, docs, sf_dir), f"pipeline-{name}"))
        return keep_last(docs)
