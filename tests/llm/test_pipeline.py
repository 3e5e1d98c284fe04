import math
from collections import Counter, defaultdict

import corpus_pipeline
import pytest
from slidesample.llm import jaccard, quality_rules, tiling
from test_mixing_sharding import brute_multiplier, brute_targets
from test_native_text import brute_quality
from tests_llm_helpers import brute_components

SF = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, SF)
        out.write.parquet(f"{tmp_path}/{k}")
        seen[name] = (docs, spark.read.parquet(f"{tmp_path}/{k}"))
        docs = seen[name][1]
        if k < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == columns
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "ngram_jaccard_join", "decontamination", "mixing", "sharding"]

    before, after = seen["quality_rules"]
    good = spark.read.parquet(f"{SF}/labels.parquet").where("quality = 1").count()
    assert good < quality_rules.least_labels(1)  # too few for any cutoff here: base rules act alone (cutoffs: test_native_text)
    want = set()
    for r in before.collect():
        words, _, _, _, repeated = brute_quality(r["text"])
        if words >= 50 and 100 * repeated <= 50 * words:
            want.add(r["doc_id"])
    assert want and {r["doc_id"] for r in after.collect()} == want

    before, after = seen["ngram_jaccard_join"]
    groups = brute_components([(r["doc_id"], r["text"]) for r in before.collect()], 5, 80)
    assert {r["doc_id"] for r in after.collect()} == {c for _, _, c in groups}

    before, after = seen["decontamination"]
    items = [(r["item_id"], set(zip(*[r["text"].lower().split()[i:] for i in range(8)], strict=False))) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    leaks = set()
    for r in before.collect():
        w = r["text"].lower().split()
        grams = set(zip(*[w[i:] for i in range(8)], strict=False))
        if any(len(g & grams) >= 0.8 * len(g) for _, g in items if g):
            leaks.add(r["doc_id"])
    assert leaks and {r["doc_id"] for r in after.collect()} == {r["doc_id"] for r in before.collect()} - leaks

    before, after = seen["mixing"]
    copies = Counter(r["doc_id"] for r in after.collect())
    docs_of = defaultdict(list)
    for r in before.collect():
        docs_of[r["source"]].append((r["doc_id"], len((r["text"] or "").split())))
    targets = brute_targets({s: sum(n for _, n in d) for s, d in docs_of.items()})
    for source, d in docs_of.items():
        total = sum(n for _, n in d)
        m = brute_multiplier([n for _, n in d], targets[source]) if targets[source] < 3 * total * (1 - 1e-9) else 5.0
        for i, n in d:
            rate = min(3.0, math.exp(min(5.0, m * n))) if n else 0.0
            assert math.floor(rate + 1e-6) <= copies[i] <= math.ceil(rate - 1e-6) or abs(copies[i] - rate) < 1e-6
        assert abs(sum(copies[i] * n for i, n in d) - targets[source]) <= max(n for _, n in d) / 2 + 1

    before, after = seen["sharding"]
    rows = after.collect()
    assert Counter((r["doc_id"], r["text"]) for r in rows) == Counter((r["doc_id"], r["text"]) for r in before.collect())
    per = Counter(r["shard"] for r in rows)
    assert max(per.values()) - min(per.values()) <= 1
    assert {(r["shard"], r["slot"]) for r in rows} == {(s, i) for s, n in per.items() for i in range(n)}


def test_stages_on_odd_rows(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (2, "", "en", "s", 0), (3, "some words " * 3, None, None, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0
        stage(spark, docs, SF).collect()
    assert corpus_pipeline.near_copy_stage(spark, docs, SF).count() == 3  # one of the repeated rows goes
    assert tiling.without_leaks(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).count() == 4
    assert jaccard.jaccard_components(docs).where("n_shingles = 0 AND component_id = doc_id").count() == 3


def test_stages_keep_columns_of_any_name_and_rows_without_ids(spark):
    text = " ".join(f"w{i}" for i in range(80))
    rows = [(None, text, "en", "s", 1), (None, text, "en", "s", 1), (7, text, "en", "s", 1), (7, text, "en", "s", 1), (7, text + " more words here", "de", None, 2), (9, text, "en", "t", 1)]
    names = ["_gone", "_id", "_copies", "_row", "_k1", "_nth", "_times", "_time", "size", "copies", "rows", "key", "_stratum", "kept", "h", "seq"]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").selectExpr("*", *[f"'{n}' AS {n}" for n in names])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        got = out.collect()
        assert all(r[n] == n for r in got for n in names)
        if name in ("quality_rules", "decontamination"):
            assert len(got) == 6
        if name == "ngram_jaccard_join":  # rows without an id stay, 9 is a copy of 7, one of the repeated rows stays
            assert sorted((r["doc_id"] or 0, len(r["text"])) for r in got) == sorted([(0, len(text)), (0, len(text)), (7, len(text)), (7, len(text) + 16)])
    assert corpus_pipeline.sharding_stage(spark, docs, SF).count() == 6


def test_run_leaves_only_its_result(spark, tmp_path, monkeypatch):
    import os

    from slidesample.llm import common

    monkeypatch.setattr(common, "shared_dir", lambda _: str(tmp_path))
    out = corpus_pipeline.run(spark, SF)
    assert out.count() > 50
    assert [n.rsplit("-", 1)[0] for n in os.listdir(f"{tmp_path}/staged")] == ["pipeline-sharding"]


def test_a_cluster_without_a_shared_folder_is_refused():
    from slidesample.llm import common

    class Session:
        conf = type("C", (), {"get": staticmethod(lambda key, default: default)})
        sparkContext = type("S", (), {"master": "spark://host:7077"})

    with pytest.raises(RuntimeError):
        common.shared_dir(Session())
