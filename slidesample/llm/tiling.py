"""Benchmark decontamination by greedy string tiling.

Words are lower-cased runs of letters and digits, compared by 64-bit hashes.  Documents and test items meet on shared seeds (hashes of `seed`
words in a row, rolled in the manner of Karp and Rabin).  Greedy tiling then marks the longest match that overlaps no marked word of
either side, again and again, so reordered passages still add up.  A document is contaminated by an item when tiles cover at least
`coverage` of the item's words.

One scan of the documents keeps the stretches of text whose seeds pass a filter of the test set's seeds; the filter has a fixed size
(`FILTER_BITS`), whatever the test set's.  Seeds of these stretches are joined to the seeds of the items, pairs that share too few to reach the coverage leave,
and the rest is tiled: stretches hold every match of a seed's length, so tiling them is tiling the whole text.  Nothing of the test set passes
through the driver but the filter, and whole texts are never shuffled by the search.

Tiling (`tile`) looks for the greatest length at which any unmarked windows of both sides have equal rolling hashes (a match of some length contains matches
of all lesser ones, so halving finds it), confirms word by word, marks all matches of that length from the first on and goes on
below it.  Lengths of tiles differ and add up to no more than the item, so there are few rounds, and no list of
position pairs is made: texts of one repeated word need memory in proportion to their length.

Defined cases: null or empty texts match nothing; items of fewer than `seed` words must occur whole; items without words are ignored;
equal items are judged each; repeated rows are judged one by one; ids may be null; extra columns pass through; an empty test set finds nothing.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import keyed_rows, row_keys, shuffled, staged, table
from .repeats import gram_hashes, word_hashes

SEED = 5
COVERAGE = 0.5
#: Bits of the seed filter (16 MB): the bound of what is broadcast.  A test set of 10 million seeds passes 2 % of all others; a larger one passes more.
FILTER_BITS = 27

#: ASCII letters in lower case, digits and all other bytes above ASCII as they are; the rest separates.
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def tokens(text: str | None) -> np.ndarray:
    return word_hashes((text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split())


def free_starts(used: np.ndarray, length: int) -> np.ndarray:
    """Starts of the windows of `length` that hold no marked word."""
    total = np.concatenate([[0], np.cumsum(used)])
    return np.flatnonzero(total[length:] == total[:-length])


def equal_windows(doc, doc_used, item, item_used, length: int):
    """(item starts, their hashes, document starts, their hashes) of unmarked windows that occur on both sides, or None."""
    if length > min(len(doc), len(item)):
        return None
    d, i = free_starts(doc_used, length), free_starts(item_used, length)
    if not len(d) or not len(i):
        return None
    gd, gi = gram_hashes(doc, length, 3)[d], gram_hashes(item, length, 3)[i]
    on_i = np.isin(gi, gd)
    if not on_i.any():
        return None
    on_d = np.isin(gd, gi[on_i])
    return i[on_i], gi[on_i], d[on_d], gd[on_d]


def tile(doc: np.ndarray, item: np.ndarray, least: int, stretches: list[int] | None = None) -> list[tuple[int, int, int]]:
    """Greedy tiles (length, document start, item start): longest first, of equals the first in the item, then in the document.

    `stretches`: lengths of the parts of `doc` that no match may cross.
    """
    if stretches is not None and len(stretches) > 1:  # a marked word after each part
        ends = np.cumsum(stretches)
        doc = np.insert(doc, ends, 0)
        barriers = ends + np.arange(len(ends))
    else:
        barriers = np.zeros(0, np.int64)
    doc_used, item_used = np.zeros(len(doc), bool), np.zeros(len(item), bool)
    doc_used[barriers] = True
    tiles, top = [], min(len(doc), len(item))
    while top >= least:
        found = equal_windows(doc, doc_used, item, item_used, least)
        if found is None:
            break
        low, high = least, top
        while low < high:
            mid = (low + high + 1) // 2
            longer = equal_windows(doc, doc_used, item, item_used, mid)
            if longer is None:
                high = mid - 1
            else:
                low, found = mid, longer
        starts, hashes, d, gd = found
        order = np.argsort(gd, kind="stable")
        d, gd = d[order], gd[order]
        at = {}
        for i, g in zip(starts.tolist(), hashes, strict=True):
            if item_used[i : i + low].any():
                continue
            k = at.get(g)
            k, end = (np.searchsorted(gd, g), np.searchsorted(gd, g, "right")) if k is None else k
            while k < end:
                x = int(d[k])
                k += 1
                if not doc_used[x : x + low].any() and np.array_equal(doc[x : x + low], item[i : i + low]):
                    doc_used[x : x + low] = item_used[i : i + low] = True
                    tiles.append((low, x, i))
                    break
            at[g] = (k, end)
        top = low - 1
    return tiles


# --- the search ------------------------------------------------------------------------------------------------------


def indexed_items(benchmark: DataFrame, seed: int, coverage: float) -> DataFrame:
    """One row per item with words: item (row number), item_id, words, n (seed length), need (seed positions to share at least), seeds, times."""

    def run(batches):
        for batch in batches:
            out = []
            for item, item_id, text in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                h = tokens(text)
                if len(h):
                    n = min(seed, len(h))
                    g, times = np.unique(gram_hashes(h, n, 3), return_counts=True)
                    out.append((item, item_id, h.view(np.int64), n, max(1, int(np.ceil(coverage * len(h) / n - 1e-9))), g.view(np.int64), times))
            kinds = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())]
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in out], k) for c, k in enumerate(kinds)], ["item", "item_id", "words", "n", "need", "seeds", "times"])

    rows = benchmark.select(F.monotonically_increasing_id().alias("item"), F.col("item_id").cast("long").alias("item_id"), "text")
    return staged(rows.mapInArrow(run, "item long, item_id long, words array<bigint>, n int, need long, seeds array<bigint>, times array<bigint>"), "tiling-items")


def seed_filter(items: DataFrame) -> np.ndarray:
    """Bits at two places for each seed of the test set; at most 2 ** (FILTER_BITS - 6) rows come to the driver."""
    mask = (1 << FILTER_BITS) - 1
    seeds = items.select(F.explode("seeds").alias("g"))
    places = F.array(F.col("g").bitwiseAND(mask), F.shiftrightunsigned("g", FILTER_BITS).bitwiseAND(mask))
    at = seeds.select(F.explode(places).alias("p"))
    words = at.groupBy(F.shiftright("p", 6).alias("word")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("p").bitwiseAND(63).cast("int"))).alias("bits"))
    rows = words.toArrow()
    bits = np.zeros(1 << (FILTER_BITS - 6), np.uint64)
    bits[rows["word"].to_numpy()] = rows["bits"].to_numpy().view(np.uint64)
    return bits


def passes(g: np.ndarray, bits: np.ndarray) -> np.ndarray:
    mask, ok = np.uint64((1 << FILTER_BITS) - 1), np.ones(len(g), bool)
    for place in (g & mask, (g >> np.uint64(FILTER_BITS)) & mask):
        ok &= ((bits[(place >> np.uint64(6)).astype(np.int64)] >> (place & np.uint64(63))) & np.uint64(1)).astype(bool)
    return ok


def stretches_of(h: np.ndarray, lengths: list[int], bits: np.ndarray):
    """(distinct seeds that pass, words of the stretches they cover, lengths of the stretches)."""
    edge, found = np.zeros(len(h) + 1, np.int64), []
    for n in lengths:
        if len(h) >= n:
            g = gram_hashes(h, n, 3)
            at = np.flatnonzero(passes(g, bits))
            found.append(np.unique(g[at]))
            np.add.at(edge, at, 1)
            np.add.at(edge, at + n, -1)
    covered = np.cumsum(edge[:-1]) > 0
    turns = np.flatnonzero(np.diff(np.concatenate([[0], covered.astype(np.int8), [0]])))
    return np.unique(np.concatenate(found)) if found else np.zeros(0, np.uint64), h[covered], turns[1::2] - turns[::2]


def found_pairs(docs: DataFrame, benchmark: DataFrame, seed: int, coverage: float, id_col: str, text_col: str) -> DataFrame:
    """One row per contaminated document and item: `_k1`, `_k2` (of id and text), doc_id, item_id, covered, tiled_words, tiles."""
    spark = docs.sparkSession
    items = indexed_items(benchmark, seed, coverage)
    lengths = sorted(r[0] for r in items.select("n").distinct().collect())  # `seed` rows at most
    bits = spark.sparkContext.broadcast(seed_filter(items))

    def run(batches):
        for batch in batches:
            kept, seeds, words, lens = [], [], [], []
            for k, text in enumerate(batch.column(4).to_pylist()):
                h = tokens(text)
                s, w, n = stretches_of(h, lengths, bits.value)
                if len(s):
                    kept.append(k)
                    seeds.append(s.view(np.int64))
                    words.append(w.view(np.int64))
                    lens.append(n)
            if kept:
                ids = [batch.column(c).take(pa.array(kept)) for c in range(4)]
                lists = [pa.array(x, pa.list_(pa.int64())) for x in (seeds, words, lens)]
                yield pa.RecordBatch.from_arrays(ids + lists, ["row", "_k1", "_k2", "doc_id", "seeds", "stretch", "lens"])

    rows = docs.select(F.monotonically_increasing_id().alias("row"), *row_keys(id_col, text_col), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    schema = "row long, _k1 long, _k2 long, doc_id long, seeds array<bigint>, stretch array<bigint>, lens array<bigint>"
    hits = staged(rows.mapInArrow(run, schema), "tiling-stretches")
    known = items.select("item", "need", F.explode(F.arrays_zip("seeds", "times")).alias("s")).select("item", "need", F.col("s.seeds").alias("seed"), F.col("s.times").alias("times"))
    shared = hits.select("row", F.explode("seeds").alias("seed")).join(shuffled(known), "seed")
    pairs = shared.groupBy("row", "item").agg(F.sum("times").alias("shared"), F.first("need").alias("need")).where("shared >= need").select("row", "item")
    both = pairs.join(shuffled(hits.drop("seeds")), "row").join(shuffled(items.select("item", "item_id", "words", "n")), "item")

    def tiled(batches):
        for pdf in batches:
            out = []
            for r in pdf.itertuples(index=False):
                item = np.asarray(r.words, np.int64).view(np.uint64)
                tiles = tile(np.asarray(r.stretch, np.int64).view(np.uint64), item, r.n, np.asarray(r.lens).tolist())
                n = sum(t[0] for t in tiles)
                if n >= coverage * len(item):
                    out.append((r.k1, r.k2, r.doc_id, r.item_id, n / len(item), n, len(tiles)))
            yield pd.DataFrame(out, columns=["_k1", "_k2", "doc_id", "item_id", "covered", "tiled_words", "tiles"]).astype({"doc_id": "Int64", "item_id": "Int64"})

    both = both.select(F.col("_k1").alias("k1"), F.col("_k2").alias("k2"), "doc_id", "stretch", "lens", "item_id", "words", "n")
    return both.mapInPandas(tiled, "_k1 long, _k2 long, doc_id long, item_id long, covered double, tiled_words long, tiles int")


def find_leaks(docs: DataFrame, benchmark: DataFrame, seed: int = SEED, coverage: float = COVERAGE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per contaminated document and item: doc_id, item_id, covered, tiled_words, tiles."""
    return found_pairs(docs, benchmark, seed, coverage, id_col, text_col).drop("_k1", "_k2")


def without_leaks(docs: DataFrame, benchmark: DataFrame, seed: int = SEED, coverage: float = COVERAGE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs` that no test item contaminates, with all their columns.  Texts are shuffled once, to meet the search's result."""
    gone = staged(found_pairs(docs, benchmark, seed, coverage, id_col, text_col).select("_k1", "_k2").distinct(), "tiling-gone")
    return keyed_rows(docs, id_col, text_col).join(shuffled(gone), ["_k1", "_k2"], "left_anti").select("_row.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {"op3_decontamination": query}
ORACLE_SQL: dict[str, str] = {}
