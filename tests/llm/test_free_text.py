import hashlib
import random
import re

import pytest

from slidesample.llm import html_text, jaccard, repeats, tiling
from tests_llm_helpers import brute_components

SF = "/root/testdata/sf0.001"


# --- repeats ---------------------------------------------------------------------------------------------------------


def brute_repeats(rows, length=50):
    words = [(i, (t or "").encode().split()) for i, t in rows]
    least = {}
    for i, w in words:
        for s in range(len(w) - length + 1):
            k = tuple(w[s : s + length])
            least[k] = min(i, least.get(k, i))
    out = []
    for i, w in words:
        gone = set()
        for s in range(len(w) - length + 1):
            if least[tuple(w[s : s + length])] < i:
                gone |= set(range(s, s + length))
        kept = [x for p, x in enumerate(w) if p not in gone]
        out.append((i, len(w), len(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    return sorted(out)


def passages():
    rnd = random.Random(3)
    word = lambda: f"w{rnd.randrange(5000)}é"
    shared = [" ".join(word() for _ in range(n)) for n in (49, 50, 51, 90, 130)]
    rows = [(1, None), (2, ""), (3, "few words"), (4, "x " * 400), (5, "x " * 120), (6, "x " * 49)]
    for i in range(10, 60):
        parts = [" ".join(word() for _ in range(rnd.randrange(0, 40))), rnd.choice(shared), " ".join(word() for _ in range(rnd.randrange(0, 40))), rnd.choice(shared)]
        rows.append((i, "\n".join(parts)))
    rows += [(70, rows[20][1]), (71, rows[20][1]), (71, rows[20][1])]
    return rows


def test_repeats_against_brute_force(spark):
    rows = passages()
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, anchor string").repartition(5)
    got = sorted(tuple(r) for r in repeats.remove_repeats(df).collect())
    assert got == brute_repeats(rows)
    assert repeats.remove_repeats(df.limit(0)).count() == 0
    kept = {r["doc_id"]: r["kept_text"] for r in repeats.remove_repeats(df, with_text=True).collect()}
    assert kept[71] == "" and kept[3] == "few words"


def test_repeats_with_odd_ids(spark):
    """A null id repeats nobody; rows of one id and unlike texts are judged each."""
    rows = passages()
    a, b = rows[20][1], rows[21][1]
    df = spark.createDataFrame([(None, a), (None, b), (20, a), (20, b), (19, b), (None, None), (3, None)], "doc_id long, text string")
    got = sorted(((-1 if r[0] is None else r[0]), r[1], r[2]) for r in repeats.remove_repeats(df).collect())
    n, m = len(a.split()), len(b.split())
    gone = dict((x[0], x[2]) for x in brute_repeats([(19, b), (20, a)]))[20]
    assert got == sorted([(-1, n, 0), (-1, m, 0), (20, n, gone), (20, m, m), (19, m, 0), (-1, 0, 0), (3, 0, 0)])


def test_maximal_repeats_extend_both_ways(spark):
    own = lambda i: " ".join(f"d{i}x{j}" for j in range(30))
    shared = [f"s{j}" for j in range(140)]
    rows = [(1, own(1) + " " + " ".join(shared)), (2, " ".join(shared[10:]) + " " + own(2)), (3, own(3) + " " + " ".join(shared[40:100]) + " " + own(4)), (4, " ".join(shared[:49]))]
    got = sorted(tuple(r) for r in repeats.maximal_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(2, 0, 130, 1, 40), (3, 30, 90, 1, 70)]


# --- Jaccard ---------------------------------------------------------------------------------------------------------


def near_copies(copies=60, seed=5):
    rnd = random.Random(seed)
    word = lambda: f"T{rnd.randrange(3000)}"
    passage = [word() for _ in range(120)]
    rows = [(1, None), (2, ""), (3, "one two"), (4, "ONE two"), (5, "one two three"), (6, " \n ")]
    nxt = 10
    for size in (30, 80, 200, 700):
        base = [word() for _ in range(size)]
        for _ in range(copies):
            w = list(base)
            for _ in range(rnd.randrange(0, max(2, size // 12))):
                w[rnd.randrange(len(w))] = word()
            rows.append((nxt, " ".join(w[: rnd.choice([len(w), len(w) - 2])])))
            nxt += 1
    for _ in range(copies):
        rows.append((nxt, " ".join([word() for _ in range(150)] + passage)))
        nxt += 1
    rows += [(nxt, rows[30][1]), (nxt + 1, rows[30][1].lower()), (nxt + 1, rows[30][1].lower())]
    return rows


@pytest.mark.parametrize("n,percent", [(4, 85), (5, 80)])
def test_jaccard_against_brute_force(spark, n, percent, monkeypatch):
    rows = near_copies()
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, token string, n int").repartition(6)
    want = brute_components(rows, n, percent)
    assert sorted(tuple(r) for r in jaccard.jaccard_components(df, n, percent).collect()) == want
    assert jaccard.jaccard_components(df.limit(0), n, percent).count() == 0


def test_jaccard_in_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "BUCKET_BLOCK", 7)
    monkeypatch.setattr(jaccard, "FAMILY_BLOCK", 9)
    rows = near_copies(30, 8)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    assert sorted(tuple(r) for r in jaccard.jaccard_components(df, 4, 85).collect()) == brute_components(rows, 4, 85)


def test_packed_counts_come_back():
    import numpy as np
    import pandas as pd

    low = np.array([0, 3, 65534, 65535, 200000, 200001, 9_000_000, 9_000_000 + 65536, 2**24 - 1])
    cnt = np.arange(1, 10).astype(np.uint16)
    tokens, counts = jaccard.stepped(low, cnt)
    got = jaccard.merged((5,), pd.DataFrame({"tokens": [tokens, tokens], "counts": [counts, counts]}), 1)
    assert got["token"].tolist() == [(5 << 24) + x for x in low] and got["df"].tolist() == [2 * x for x in range(1, 10)]


def test_jaccard_keeps_links_of_unlike_sets_with_equal_prefixes(spark):
    """Short sets that share their prefix and size but little else are one group; each still finds its own near copy."""
    rnd = random.Random(11)
    word = lambda: f"w{rnd.randrange(10**6)}"
    rows = []
    for _ in range(80):
        common = [word() for _ in range(4)]
        for _ in range(5):
            text = common + [word() for _ in range(5)]
            rows += [(len(rows), " ".join(text)), (len(rows) + 1, " ".join([*text, word()]))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute_components(rows, 4, 85)
    assert sum(c < d for d, _, c in want) == 400
    assert sorted(tuple(r) for r in jaccard.jaccard_components(df, 4, 85).collect()) == want


def test_jaccard_of_a_family_that_first_blocks_do_not_join(spark, monkeypatch):
    """A long chain of similar sets: few rows of a block are linked, so rows must travel; frequent members are spread."""
    monkeypatch.setattr(jaccard, "BUCKET_BLOCK", 5)
    monkeypatch.setattr(jaccard, "FAMILY_BLOCK", 4)
    monkeypatch.setattr(jaccard, "FREQUENT", 3)
    words = [f"w{i}" for i in range(400)]
    rows = [(k, " ".join(words[3 * k : 3 * k + 60])) for k in range(100)] + [(None, " ".join(words[:60])), (None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = [tuple(r) for r in jaccard.jaccard_components(df, 4, 85).collect()]
    assert sorted(r for r in got if r[0] is not None) == brute_components(rows[:100], 4, 85)
    assert sorted(r[1:] for r in got if r[0] is None) == [(0, None), (57, None)]


def test_jaccard_rows_of_a_large_family_grow_in_proportion(spark, monkeypatch):
    """Texts sent to blocks: about one for each member, not one for each member and block."""
    rnd = random.Random(1)
    base = [f"b{i}" for i in range(60)]
    rows = [(k, " ".join([*base[: rnd.randrange(55, 60)], f"own{k}"])) for k in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    monkeypatch.setattr(jaccard, "FAMILY_BLOCK", 50)
    seen = spark.sparkContext.accumulator(0)
    original = jaccard.verified

    def counting(batches, n, percent):
        def counted():
            for b in batches:
                seen.add(len(b))
                yield b

        return original(counted(), n, percent)

    monkeypatch.setattr(jaccard, "verified", counting)
    out = jaccard.jaccard_components(df, 4, 85).collect()
    assert {r["component_id"] for r in out} == {0}
    assert seen.value <= 4 * 3000


# --- tiling ----------------------------------------------------------------------------------------------------------


def brute_tiling(doc, item, least):
    """Textbook greedy string tiling by trying all positions."""
    used_d, used_i, total = [False] * len(doc), [False] * len(item), 0
    while True:
        best = None
        for i in range(len(item)):
            for d in range(len(doc)):
                k = 0
                while i + k < len(item) and d + k < len(doc) and doc[d + k] == item[i + k] and not used_d[d + k] and not used_i[i + k]:
                    k += 1
                if k >= least and (best is None or (-k, i, d) < best):
                    best = (-k, i, d)
        if best is None:
            return total
        k, i, d = -best[0], best[1], best[2]
        for x in range(k):
            used_d[d + x] = used_i[i + x] = True
        total += k


def test_tiling_against_brute_force():
    rnd = random.Random(2)
    for _ in range(150):
        item = [str(rnd.randrange(6)) for _ in range(rnd.randrange(3, 30))]
        doc = [str(rnd.randrange(6)) for _ in range(rnd.randrange(0, 40))] + item[rnd.randrange(3) :] + item[: rnd.randrange(8)]
        tiles = tiling.tile(tiling.tokens(" ".join(doc)), tiling.tokens(" ".join(item)), min(3, len(item)))
        assert sum(t[0] for t in tiles) == brute_tiling(doc, item, min(3, len(item)))
        parts = [x for x in (doc[:9], doc[9:12], doc[12:]) if x]  # no tile crosses from one part to the next
        tiles = tiling.tile(tiling.tokens(" ".join(doc)), tiling.tokens(" ".join(item)), min(3, len(item)), [len(x) for x in parts])
        barred = [w for x in parts for w in [*x, object()]]
        assert sum(t[0] for t in tiles) == brute_tiling(barred, item, min(3, len(item)))


def test_tiling_of_one_repeated_word_needs_no_pairs():
    import time
    import tracemalloc

    doc, item = tiling.tokens("word " * 60000), tiling.tokens("word " * 1000)
    tracemalloc.start()
    begin = time.time()
    assert tiling.tile(doc, item, 5) == [(1000, 0, 0)]
    assert time.time() - begin < 10 and tracemalloc.get_traced_memory()[1] < 50 << 20
    tracemalloc.stop()


def test_decontamination(spark):
    item = "The quick brown fox jumps over the lazy dog while seven wizards brew a strong potion tonight"
    w = item.split()
    rows = [
        (1, item.upper()), (2, "before " + " ".join(w[8:]) + " and then " + " ".join(w[:8])), (3, " ".join(w[:5]) + " nothing else of it"),
        (4, None), (5, ""), (6, "word " * 30000), (7, "x " * 9000 + item), (7, "clean text"), (8, "two words"),
    ]
    rows += [(None, "so " + item), (None, None)]
    docs = spark.createDataFrame([(i, t, 0.5, 1, 2) for i, t in rows], "doc_id long, text string, covered double, _k1 int, row int").repartition(3)
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, item), (5, "two words")], "item_id long, text string")
    found = {(r["doc_id"], r["item_id"]) for r in tiling.find_leaks(docs, bench).collect()}
    assert found == {(d, i) for d in (1, 2, 7, None) for i in (1, 4)} | {(8, 5)}
    kept = tiling.without_leaks(docs, bench)
    assert kept.columns == docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 3, 4, 5, 6, 7]
    assert tiling.find_leaks(docs, bench.limit(0)).count() == 0 and tiling.without_leaks(docs.limit(0), bench).count() == 0


# --- pages -----------------------------------------------------------------------------------------------------------


def brute_cut(scores, edges):
    best = None
    for m in range(1 << len(scores)):
        side = [bool(m >> i & 1) for i in range(len(scores))]
        cost = sum(max(0, -s) if k else max(0, s) for s, k in zip(scores, side, strict=True)) + sum(w for (a, b), w in edges.items() if side[a] != side[b])
        best = cost if best is None else min(best, cost)
    return best


def test_min_cut_is_minimal():
    rnd = random.Random(4)
    for _ in range(300):
        n = rnd.randrange(1, 9)
        scores = [rnd.uniform(-2, 2) for _ in range(n)]
        edges = {(a, b): rnd.uniform(0, 1.5) for a in range(n) for b in range(a + 1, n) if rnd.random() < 0.5}
        side = html_text.min_cut(scores, edges)
        cost = sum(max(0, -s) if k else max(0, s) for s, k in zip(scores, side, strict=True)) + sum(w for (a, b), w in edges.items() if side[a] != side[b])
        assert cost == pytest.approx(brute_cut(scores, edges))


def test_extraction_of_the_given_pages(spark):
    import html

    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}
    rows = html_text.query(spark, SF).collect()
    assert len(rows) == len(pages)
    for r in rows:
        body = re.search(r"<article>(.*?)</article>", pages[r["page_id"]], re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"<[^>]*>", " ", x)).split()) for x in re.split(r"</?p>|</?h1>", body)]
        assert r["text"] == "\n\n".join(p for p in parts if p) and r["n_chars"] == len(r["text"])


def test_extraction_edge_cases(spark):
    cases = {
        None: "",
        "": "",
        "<p": "",
        "<article><p>One &amp; two<br>three<p>Four.": "One & two three\n\nFour.",
        "<nav><p>Long menu text that is certainly not part of it.</p></nav><main><h1>Head</h1><p>Body text is here.</p></main><div class='comments'><p>I like this page very much, thanks.</p></div>": "Head\n\nBody text is here.",
        "<article><p>Kept text stays.</p><aside>Side note with many words in it.</aside><form><p>Sign up now for our letters.</p></form></article><footer>End</footer>": "Kept text stays.",
        "<script>var x = '<p>no</p>'</script><!-- <p>no</p> --><article><p>Yes, this one.</p></article><style>p{}": "Yes, this one.",
    }
    df = spark.createDataFrame([(i, "u", h, 5) for i, h in enumerate(cases)], "page_id long, url string, html string, n_chars int")
    got = {r["page_id"]: r["text"] for r in html_text.extract_pages(df).collect()}
    assert [got[i] for i in range(len(cases))] == list(cases.values())
    assert html_text.extract_pages(df.limit(0)).count() == 0
    assert len(html_text.extract("<article>" + "<p>some words here.</p>" * 20000 + "</article>")) > 300000


def test_names_inside_text_are_outvoted_and_comments_are_not():
    long = "This paragraph tells a long story about the town, its market and the people who lived there in those years."
    page = "<article><h1>Markets</h1><p>%s</p><div class='share-price'><p>The share price fell by a third in the first week of trading.</p></div><p>%s</p></article>" % (long, long)
    assert "The share price fell" in html_text.extract(page)
    page = "<div><h2>A dispute</h2><p>%s</p><p id='legal'>The legal dispute started in 1990 and lasted for seven years.</p></div>" % long
    assert "The legal dispute started" in html_text.extract(page)
    for wrap in ("<article><p>%s</p><section class='comments'>%s</section></article>", "<article><p>%s</p></article><div id='comment-list'>%s</div>", "<main><p>%s</p><div class='ad'>%s</div></main>"):
        text = html_text.extract(wrap % (long, "<p>" + "I have read this and I think that it is wrong. " * 8 + "</p>"))
        assert text == long


def test_long_and_deep_pages_cost_in_proportion():
    import time

    begin = time.time()
    html_text.extract("<div>" * 20000 + "<b>x</b>" * 20000)
    html_text.extract("".join(f"<div><p>Some words here{'.' * (i % 2)}</p></div><li><a href=x>w{i}</a></li>" for i in range(20000)))
    assert time.time() - begin < 20


def test_weights_are_fitted_to_examples(spark):
    import pandas as pd

    shapes = [(2 ** (k / 2), 0.0, 1, 4, 1, 50) for k in range(8, 14)] + [(2 ** (k / 2), 0.0, 1, 4, 0, 50) for k in range(1, 6)]
    w = html_text.fitted(pd.DataFrame(shapes, columns=["words", "share", "ends", "kind", "label", "n"]))
    assert w[1] > html_text.PRIOR[1] and html_text.log_odds(w, 40, 0.0, 1, 4) > 0 > html_text.log_odds(w, 1, 0.0, 1, 4)
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    assert abs(html_text.fit_weights(pages) - html_text.fit_weights(pages.repartition(7))).max() == 0
    assert (html_text.fit_weights(pages.limit(0)) == html_text.PRIOR).all()
