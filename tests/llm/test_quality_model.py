import numpy as np

from slidesample.llm import boosting, quality_model

SF = "/root/testdata/sf0.01"


def walk(model, row):
    total = model.prior
    for node in model.roots:
        while model.left[node] != node:
            node = model.right[node] if row[model.feature[node]] > model.threshold[node] else model.left[node]
        total += model.value[node]
    return 1 / (1 + np.exp(-total))


def test_flat_traversal_equals_walking_each_tree():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(400, 3))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    model = boosting.fit(x, y, trees=30)
    got = model.scores(x)
    assert np.allclose(got, [walk(model, r) for r in x])
    assert ((got > 0.5) == y).mean() > 0.97
    assert np.allclose(boosting.fit(x[:0], y[:0]).scores(x), 0.5)
    assert len(set(boosting.fit(x, np.ones(400)).scores(x))) == 1


def test_held_out_accuracy(spark):
    rows = quality_model.query(spark, SF).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert all(r["held_out"] == (quality_model.fold_of(r["doc_id"]) == 0) for r in rows)
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3) for r in rows)
    good, bad = [r["score"] for r in held if r["quality"] == 1], [r["score"] for r in held if r["quality"] == 0]
    auc = np.mean([(a > b) + 0.5 * (a == b) for a in good for b in bad])
    assert auc > 0.9, auc


def test_edge_cases(spark):
    docs = spark.createDataFrame([(1, None, "x"), (1, "", "x"), (2, "word " * 50000, "x"), (None, "a", "x")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(2, None), (7, 1), (None, 0)], "doc_id long, quality int")
    out = quality_model.score(docs, quality_model.learn(docs, labels)).collect()
    assert len(out) == 4 and all(abs(r["score"] - 0.5) < 1e-9 for r in out)
    assert quality_model.score(docs.limit(0), quality_model.learn(docs, labels)).count() == 0
