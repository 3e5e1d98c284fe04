"""Removal of repeated passages by seed and extend.

Seeds: every document's word k-grams are hashed and winnowed, so each window of `length` words holds exactly one chosen
anchor (the smallest hash, rightmost of equals), and equal windows choose equal anchors at equal offsets.  Documents meet on anchors that
occur in more than one document.  Join and extension: around a shared anchor every way to extend it to `length` words, so many to the left and
the rest to the right, is one window; each is joined to the smallest document with the same anchor and the same window.  Joined
windows that follow each other on one diagonal of the two documents extend to a maximal repeat (`maximal_repeats`: begin, end, partner and
the partner's begin).  The words of all maximal repeats are removed.

No pairs of documents are written out: thousands of copies of a passage are each joined to its first one only, which is all
that the removal needs, so frequent anchors cost as much as others.  Documents of equal words collapse first: all but
the first are repeats as a whole, and only the first goes on.

Whole texts are shuffled once, by document, to meet their shared anchors; those with any are kept in the shared folder and meet their ranges
there.  What the other documents need is known from the first scan.  All joins shuffle at every size.

Defined cases: null text has no words; documents under `length` words keep everything; of repeated rows (equal doc_id and text) each is
judged alike, since only a strictly smaller doc_id counts; rows of equal doc_id and unlike texts are judged each; a null doc_id is
neither smaller nor larger than any, such rows keep everything and repeat nobody; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import per_salt, salt, salts_seen, shuffled, staged, table

LENGTH = 50
GRAM = 20


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def mixed(h: np.ndarray) -> np.ndarray:
    """Spread 64-bit values (finaliser of a public generator)."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def gram_hashes(h: np.ndarray, n: int, salt: int) -> np.ndarray:
    """Hash of every run of `n` values: a position-weighted sum, by doubling."""
    with np.errstate(over="ignore"):
        base = np.uint64(0x9E3779B97F4A7C15 + 2 * salt)
        out, have = np.zeros(len(h) - n + 1, np.uint64), 0
        block, size, power = mixed(h + np.uint64(salt)), 1, base
        rest = n
        while rest:
            if rest & 1:
                at = n - have - size
                out = out * power + block[at : at + len(out)] if have else block[at : at + len(out)].copy()
                have += size
            rest >>= 1
            if rest:
                block = block[:-size] * power + block[size:]
                power, size = power * power, size * 2
    return mixed(out)


def sliding_choice(g: np.ndarray, width: int) -> np.ndarray:
    """For each run of `width` values the position of its smallest value, the rightmost of equals (by doubling)."""
    pos = np.arange(len(g))
    size = 1
    best = pos
    def better(a, b):  # b lies to the right of a
        return np.where(g[b] <= g[a], b, a)
    while size * 2 <= width:
        best = better(best[:-size], best[size:])
        size *= 2
    if size < width:
        shift = width - size
        best = better(best[: len(best) - shift], best[shift:])
    return best


def windows_of(text: str | None, length: int, gram: int):
    """Words, then per window of `length` words: anchor hash, offset of the anchor, window hash."""
    words = (text or "").encode("utf-8", "surrogatepass").split()
    if len(words) < length:
        return words, None
    h = word_hashes(words)
    g = gram_hashes(h, gram, 1)
    chosen = sliding_choice(g, length - gram + 1)
    return words, (g[chosen], chosen, h)


def profiles(batches, length: int, gram: int):
    """doc_id, key, text -> doc_id, key, n_words, sha256 of the words, anchors (each chosen hash once; null under `length` words)."""
    for batch in batches:
        counts, shas, found = [], [], []
        for text in batch.column(2).to_pylist():
            words, windows = windows_of(text, length, gram)
            counts.append(len(words))
            shas.append(hashlib.sha256(b" ".join(words)).digest())
            found.append(None if windows is None else np.unique(windows[0]).view(np.int64))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array(counts, pa.int64()), pa.array(shas, pa.binary()), pa.array(found, pa.list_(pa.int64()))],
            ["doc_id", "key", "n_words", "sha", "anchors"],
        )


def shared_windows(batches, length: int, gram: int):
    """doc_id, key, text, shared (list of shared anchors) -> doc_id, key, start, window, anchor of the windows on shared anchors."""
    for batch in batches:
        cols = [[], [], [], [], []]
        for doc, key, text, shared in zip(*(batch.column(i).to_pylist() for i in range(3)), batch.column(3), strict=True):
            _, found = windows_of(text, length, gram)
            if found is None:
                continue
            a, _, h = found
            keep = np.flatnonzero(np.isin(a, np.asarray(shared.values, np.int64).view(np.uint64)))
            if len(keep):
                cols[0].append(np.full(len(keep), doc, np.int64))
                cols[1].append(np.full(len(keep), key, np.int64))
                cols[2].append(keep.astype(np.int32))
                cols[3].append(gram_hashes(h, length, 2)[keep].view(np.int64))
                cols[4].append(a[keep].view(np.int64))
        if cols[0]:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], ["doc_id", "key", "start", "window", "anchor"])


def cut(text: str | None, ranges, length: int):
    """Words of `text`, and those outside the ranges (begin, end), which are sorted by begin.  A text under `length` words keeps all."""
    words = (text or "").encode("utf-8", "surrogatepass").split()
    kept, at = [], 0
    for begin, end in ranges if len(words) >= length else ():
        kept += words[at:begin]
        at = max(at, end)
    return words, kept + words[at:]


def keyed_texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, key (a hash of id and text: tells rows of one id apart), text."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(id_col).cast("long"), text_col).alias("key"), F.col(text_col).alias("text"))


def repeats_of(texts: DataFrame, length: int, gram: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(profiles, copies doc_id key, texts of documents that share anchors, maximal repeats doc_id key begin end partner partner_begin)."""
    schema = "doc_id long, key long, n_words long, sha binary, anchors array<bigint>"
    first_scan = staged(texts.mapInArrow(lambda it: profiles(it, length, gram), schema), "repeat-profiles")
    # Copies: the smallest id of each sequence of words.
    long = first_scan.where((F.col("n_words") >= length) & F.col("doc_id").isNotNull())
    first = long.groupBy("sha").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), salts_seen("key").alias("seen")).where("lo < hi")
    first = per_salt(first.drop("hi"), "seen")
    marked = long.withColumn("_salt", salt("key")).join(shuffled(first), ["sha", "_salt"], "left").withColumn("copy", F.coalesce(F.col("doc_id") > F.col("lo"), F.lit(False)))
    marked = staged(marked.select("doc_id", "key", "copy", F.when(~F.col("copy"), F.col("anchors")).alias("anchors")), "repeat-marked")
    copies = marked.where("copy").select("doc_id", "key").distinct()
    # Seeds: anchors of several documents, and the texts that have any.
    seeds = marked.where("NOT copy").select("doc_id", "key", F.explode("anchors").alias("anchor"))
    common = seeds.groupBy("anchor").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), salts_seen("key").alias("seen")).where("lo < hi")
    common = per_salt(common.select("anchor", "seen"), "seen")
    wanted = seeds.select("key", "anchor", salt("key").alias("_salt")).join(shuffled(common), ["anchor", "_salt"]).groupBy("key").agg(F.collect_set("anchor").alias("shared"))
    met = staged(texts.join(shuffled(wanted), "key").select("doc_id", "key", "text", "shared").where("doc_id IS NOT NULL"), "repeat-texts")
    # Extension: every window on a shared anchor finds its smallest document, and runs on a diagonal join.
    windows = met.mapInArrow(lambda it: shared_windows(it, length, gram), "doc_id long, key long, start int, window long, anchor long")
    windows = staged(windows, "repeat-windows")
    least = windows.groupBy("window", "anchor").agg(F.min(F.struct("doc_id", "start")).alias("source"), F.max("doc_id").alias("hi"), salts_seen("key").alias("seen"))
    least = least.where("source.doc_id < hi").select("window", "anchor", F.col("source.doc_id").alias("partner"), F.col("source.start").alias("there"), "seen")
    hits = windows.withColumn("_salt", salt("key")).join(shuffled(per_salt(least, "seen")), ["window", "anchor", "_salt"]).where("doc_id > partner").select("doc_id", "key", "start", "partner", "there").distinct()
    diagonal = Window.partitionBy("doc_id", "key", "partner", F.col("start") - F.col("there")).orderBy("start")
    runs = hits.withColumn("run", F.col("start") - F.row_number().over(diagonal))
    extended = runs.groupBy("doc_id", "key", "partner", (F.col("start") - F.col("there")).alias("shift"), "run").agg(
        F.min("start").alias("begin"), (F.max("start") + length).alias("end"), F.min("there").alias("partner_begin")
    )
    return first_scan, copies, met, staged(extended.drop("shift", "run"), "repeat-maximal")


def maximal_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per maximal repeat: doc_id, begin, end (words), partner (the smallest document that has it), partner_begin.  Whole copies are not listed."""
    return repeats_of(keyed_texts(docs, id_col, text_col), length, gram)[3].select("doc_id", "begin", "end", "partner", "partner_begin").distinct()


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_sha256 (and kept_text if asked, for which all texts are shuffled once more)."""
    texts = keyed_texts(docs, id_col, text_col)
    first_scan, copies, met, maximal = repeats_of(texts, length, gram)
    ranges = maximal.groupBy("doc_id", "key").agg(F.sort_array(F.collect_set(F.struct("begin", "end"))).alias("ranges"))
    whole = copies.withColumn("ranges", F.array(F.struct(F.lit(0).alias("begin"), F.lit(2**31 - 1).alias("end"))))
    schema = "doc_id long, key long, n_words long, n_removed long, kept_sha256 string" + (", kept_text string" if with_text else "")

    def finish(batches):
        for pdf in batches:
            rows = []
            for doc, key, text, ranges in zip(pdf["doc_id"], pdf["key"], pdf["text"], pdf["ranges"], strict=True):
                words, kept = cut(text if isinstance(text, str) else None, () if ranges is None else [(r["begin"], r["end"]) for r in ranges], length)
                body = b" ".join(kept)
                row = (None if pd.isna(doc) else int(doc), key, len(words), len(words) - len(kept), hashlib.sha256(body).hexdigest())
                rows.append((*row, body.decode("utf-8", "surrogatepass")) if with_text else row)
            yield pd.DataFrame(rows, columns=["doc_id", "key", "n_words", "n_removed", "kept_sha256"] + ["kept_text"] * with_text).astype({"doc_id": "Int64"})

    if with_text:
        judged = texts.join(shuffled(ranges.unionByName(whole)), ["doc_id", "key"], "left")
        return judged.select("doc_id", "key", "text", "ranges").mapInPandas(finish, schema).drop("key")
    cuts = met.join(shuffled(ranges), ["doc_id", "key"]).select("doc_id", "key", "text", "ranges").mapInPandas(finish, schema)
    cuts = cuts.select("doc_id", "key", F.col("n_removed").alias("gone"), F.col("kept_sha256").alias("sha_left"))
    emptied = copies.select("doc_id", "key", F.lit(None).cast("long").alias("gone"), F.lit(hashlib.sha256(b"").hexdigest()).alias("sha_left"))
    changes = staged(cuts.unionByName(emptied).distinct(), "repeat-changes")
    gone = F.when(F.col("sha_left").isNull(), F.lit(0).cast("long")).otherwise(F.coalesce("gone", "n_words"))
    return first_scan.join(shuffled(changes), ["doc_id", "key"], "left").select(
        "doc_id", "n_words", gone.alias("n_removed"), F.coalesce("sha_left", F.lower(F.hex("sha"))).alias("kept_sha256")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
s AS (SELECT doc_id, words, unnest(range(1, greatest(len(words) - 48, 1))) AS i FROM w),
g AS (SELECT doc_id, i, array_to_string(words[i:i + 49], ' ') AS win FROM s),
m AS (SELECT win, min(doc_id) AS lo FROM g GROUP BY win HAVING min(doc_id) < max(doc_id)),
hit AS (SELECT doc_id, list(DISTINCT i) AS starts FROM g JOIN m USING (win) WHERE doc_id > lo GROUP BY doc_id),
gone AS (SELECT doc_id, list_distinct(flatten(list_transform(starts, lambda x: range(x, x + 50)))) AS pos FROM hit),
k AS (SELECT doc_id, words, list_filter(range(1, len(words) + 1), lambda p: NOT list_contains(coalesce(pos, []), p)) AS keep FROM w LEFT JOIN gone USING (doc_id))
SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(len(words) - len(keep) AS BIGINT) AS n_removed,
       sha256(array_to_string(list_transform(keep, lambda p: words[p]), ' ')) AS kept_sha256
FROM k
"""

QUERIES = {"op9_substring_dedup": query}
ORACLE_SQL = {"op9_substring_dedup": SQL}
