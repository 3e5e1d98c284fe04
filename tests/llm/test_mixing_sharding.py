import math
from collections import Counter, defaultdict

import pytest

from slidesample.llm import mixing, sharding

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, source string, size string, _bucket int"


def brute_targets(sizes, weights=(1, 2, 3), cap=3.0):
    names = sorted([s for s in sizes if s is not None]) + ([None] if None in sizes else [])
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    total, fixed = float(sum(sizes.values())), {}
    while True:
        free = [s for s in names if s not in fixed]
        rest = total - sum(fixed.values())
        share = sum(w[s] for s in free)
        trial = {s: rest * w[s] / share for s in free}
        above = [s for s in free if trial[s] > cap * sizes[s]]
        if not above:
            return fixed | trial
        fixed |= {s: cap * sizes[s] for s in above}


def test_mixing_meets_targets(spark):
    rows = mixing.query(spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source"), "doc_id").collect()
    sizes = defaultdict(int)
    for r in rows:
        sizes[r["source"]] += r["size"]
    want = brute_targets(sizes)
    taken = defaultdict(int)
    for r in rows:
        assert r["source_size"] == sizes[r["source"]]
        assert r["target"] == pytest.approx(want[r["source"]], rel=1e-9)
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[r["source"]] += r["taken"]
    for s in sizes:
        shortest = min(r["size"] for r in rows if r["source"] == s and r["size"])
        assert abs(taken[s] - want[s]) <= max(shortest, 0.05 * want[s])


def test_mixing_edge_cases(spark):
    df = spark.createDataFrame(
        [(1, "a b c", "x", "q", 1), (1, "a b c", "x", "q", 1), (2, None, None, None, None), (3, "", "y", None, 2), (4, "w " * 5000, None, "z", 3)], DOCS
    )
    out = mixing.mix(df.drop("size")).collect()
    assert len(out) == 5
    assert {r["doc_id"]: r["target"] for r in out}[3] == 0
    assert mixing.mix(df.drop("size").limit(0)).count() == 0


def brute_multiplier(sizes, target, cap=3.0):
    """m with sum(size * min(cap, exp(m * size))) = target, by bisection."""
    words = lambda m: sum(x * min(cap, math.exp(min(m * x, 5))) for x in sizes)
    low, high = -50.0, 50.0
    for _ in range(300):
        mid = (low + high) / 2
        low, high = (mid, high) if words(mid) < target else (low, mid)
    return low


def test_rates_are_tilted_by_document_and_copies_follow_them(spark):
    """Rates solve the dual found by bisection, differ between documents of a source, and are met in the mean by texts of each size."""
    docs = spark.range(24000).selectExpr("id AS doc_id", "repeat('w ', CAST(IF(id % 50 = 7, 90, 10 + id % 3) AS INT)) AS text", "CAST(1000 + id % 4 AS STRING) AS source")
    rows = mixing.mix(docs, weights=(1, 2, 4, 9)).groupBy("source", "target", "rate", "size", "copies").count().collect()
    assert sum(r["count"] for r in rows) == 24000
    for source in {r["source"] for r in rows}:
        these = [r for r in rows if r["source"] == source]
        sizes = [r["size"] for r in these for _ in range(r["count"])]
        m = brute_multiplier(sizes, these[0]["target"])
        assert sum(r["size"] * r["copies"] * r["count"] for r in these) == pytest.approx(these[0]["target"], rel=0.002)
        assert len({r["rate"] for r in these}) > 1 or these[0]["rate"] in (0.0, 3.0)
        for size in set(sizes):
            mine = [r for r in these if r["size"] == size]
            n, rate = sum(r["count"] for r in mine), mine[0]["rate"]
            assert rate == pytest.approx(min(3.0, math.exp(m * size)), abs=1e-6) or these[0]["target"] >= 3 * sum(sizes) * (1 - 1e-9)
            assert abs(sum(r["copies"] * r["count"] for r in mine) / n - rate) < 0.03


def test_mixing_shares_copies_among_repeated_rows(spark):
    docs = spark.createDataFrame([(1, "a b c", "x")] * 300 + [(2, "d e", "x")] * 100 + [(None, "f g h i", "y")] * 50 + [(None, None, None)], "doc_id long, text string, source string")
    rows = mixing.mix(docs).collect()
    assert len(rows) == 451
    out = mixing.mixed_documents(docs.selectExpr("*", "1 AS _copies", "2 AS _id", "3 AS _k1", "4 AS size", "5 AS _row"))
    assert out.columns == ["doc_id", "text", "source", "_copies", "_id", "_k1", "size", "_row"]
    got = Counter(r["text"] for r in out.collect())
    want = Counter()
    for r in rows:
        want[{3: "a b c", 2: "d e", 4: "f g h i", 0: None}[r["size"]]] += r["copies"]
    assert got == +want
    for r in rows:
        assert r["copies"] in (math.floor(r["rate"]), math.ceil(r["rate"]))


def test_mixing_of_many_chunks_meets_targets(spark):
    docs = spark.range(6000).selectExpr("id AS doc_id", "repeat('w ', CAST(IF(id < 2, 5000, 5 + id % 50) AS INT)) AS text", "IF(id % 2 = 0, 'a', NULL) AS source")
    rows = mixing.mix(docs, weights=(1, 9)).collect()
    assert len(rows) == 6000
    for source in ("a", None):
        these = [r for r in rows if r["source"] == source]
        assert abs(sum(r["taken"] for r in these) - these[0]["target"]) <= 0.01 * these[0]["target"]


def test_sharding_is_a_permutation(spark):
    for n in (0, 1, 2, 7, 100, 1000):
        got = [r[0] for r in spark.range(n).select(sharding.permuted(__import__("pyspark").sql.functions.col("id"), n, 3)).collect()]
        assert sorted(got) == list(range(n))


def test_sharding_slots(spark):
    import zlib

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = sharding.query(spark, SF).collect()
    again = {r["doc_id"]: (r["shard"], r["slot"]) for r in sharding.query(spark, SF).collect()}
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
        body = (text[r["doc_id"]] or "").encode()
        assert r["size"] == len(body) + 1 and r["text_crc32"] == zlib.crc32(body)
        assert again[r["doc_id"]] == (r["shard"], r["slot"])
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())


def test_sharding_edge_cases(spark):
    df = spark.createDataFrame([(1, None, "x", "q", 1), (1, None, "x", "q", 1), (2, "", None, None, None), (None, "z" * 100000, None, None, 0)], DOCS)
    assert sharding.shard_rows(df).count() == 4
    assert sharding.shard_rows(df.limit(0)).count() == 0
