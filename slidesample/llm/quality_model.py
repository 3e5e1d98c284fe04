"""Quality classifier: histogram gradient-boosted trees over statistics of whole texts.

The model learns from labelled documents outside the held-out fold, at most `SAMPLE` of them (those with the smallest hash of
their id, so reruns agree); statistics and scores then cover every document in one pass without a shuffle.  Identity, language,
source and labels are never inputs of a score.

Defined cases: null text counts as empty; empty texts get the score that the trees give to all-zero statistics; labels that are null
or have no document are ignored; without usable labels every score is 0.5; repeated rows are scored one by one; extra columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import boosting
from .common import table

#: Labelled documents learnt from, at most.
SAMPLE = 20_000
ACCEPT = 0.3

_CLASSES = {
    "upper": bytes(range(65, 91)),
    "lower": bytes(range(97, 123)),
    "digit": bytes(range(48, 58)),
    "symbol": b"#*$%&|<>",
    "stop": b".!?",
    "bang": b"!",
    "pause": b",;:",
    "other_ascii": b"\"'()-/=@[]^_`{}~+\\",
    "high": bytes(range(128, 256)),
    "newline": b"\n",
}
_MASKS = np.stack([np.isin(np.arange(256), list(v)) for v in _CLASSES.values()]).astype(np.float64)
NAMES = ["log_words", "word_length", *_CLASSES, "distinct_words", "top_word", "distinct_pairs", "repeated_lines", "long_words", "short_words", "words_per_stop", "log_lines"]


def statistics(text: str | None) -> list[float]:
    """The inputs of the trees for one whole text."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    chars = _MASKS @ np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    visible = sum(map(len, words))
    distinct = set(words)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    lengths = np.fromiter(map(len, words), np.int64, n)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return [
        float(np.log1p(n)),
        visible / n,
        *(chars / visible),
        len(distinct) / n,
        max(counts.values()) / n,
        len(set(zip(words, words[1:], strict=False))) / max(1, n - 1),
        1 - len(set(lines)) / max(1, len(lines)),
        float((lengths > 12).mean()),
        float((lengths < 3).mean()),
        float(np.log1p(n / (1 + chars[4]))),
        float(np.log1p(len(lines))),
    ]


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.encode(doc_id.cast("string"), "UTF-8")) % 5 == 0


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> boosting.Trees:
    """Fit trees to a bounded, reproducible sample of labelled documents outside the held-out fold."""
    usable = labels.where(F.col("quality").isin(0, 1) & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    chosen = usable.select(F.col(id_col).alias("_id"), F.col("quality").cast("int").alias("_label")).orderBy(F.xxhash64("_id"), "_id", "_label").limit(sample)
    rows = docs.select(F.col(id_col), F.col(text_col).alias("text")).join(F.broadcast(chosen), F.col(id_col) == F.col("_id"))

    def measure(batches):
        for pdf in batches:
            yield pd.DataFrame({"doc_id": pdf["_id"], "label": pdf["_label"], "x": [statistics(t if isinstance(t, str) else None) for t in pdf["text"]]})

    # repeated rows of a document count once, so that no more than `sample` rows come to the driver
    got = rows.select("_id", "_label", "text").mapInPandas(measure, "doc_id long, label int, x array<double>").groupBy("doc_id", "label").agg(F.min("x").alias("x")).toPandas()
    got = got.sort_values(["doc_id", "label"], kind="stable")  # so that reruns see the same order
    x = np.array(got["x"].tolist()).reshape(-1, len(NAMES))
    return boosting.fit(x, got["label"].to_numpy(np.float64))


def score(docs: DataFrame, model: boosting.Trees, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, score for every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a fixed number of nodes

    def scored(batches):
        for pdf in batches:
            x = np.array([statistics(t if isinstance(t, str) else None) for t in pdf["text"]]).reshape(-1, len(NAMES))
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "score": shared.value.scores(x)})

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInPandas(scored, "doc_id long, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scores = score(docs, learn(docs, table(spark, sf_dir, "labels")))
    return scores.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= ACCEPT).cast("int").alias("predicted"))


def fold_of(doc_id: int) -> int:
    """The fold that `held_out` computes, in Python (tests)."""
    return zlib.crc32(str(doc_id).encode()) % 5


QUERIES = {"op1_quality_classifier": query}
ORACLE_SQL: dict[str, str] = {}
