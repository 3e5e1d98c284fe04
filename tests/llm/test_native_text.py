import math
import re
from collections import Counter

from slidesample.llm import license_scan, quality_rules, url_filter

SF = "/root/testdata/sf0.001"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def brute_quality(text):
    text = text or ""
    w = WORDS.findall(text)
    seen, hit = {}, set()
    for i in range(len(w) - 2):
        seen.setdefault(tuple(w[i : i + 3]), []).append(i)
    for at in seen.values():
        if len(at) > 1:
            for i in at:
                hit |= {i, i + 1, i + 2}
    lines = [x for x in text.split("\n") if WORDS.search(x)]
    return (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(hit))


def test_quality_counts_and_verdicts(spark):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = quality_rules.query(spark, SF).collect()
    assert len(rows) == len(texts)
    for r in rows:
        want = brute_quality(texts[r["doc_id"]])
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (want[0] < 50 or 100 * want[4] > 50 * want[0])
        assert not (r["kept"] and r["base_failed"])


def test_quality_edge_cases(spark):
    crowd = "a b c " * 3000 + "a b"
    rows = [(1, None, None, "q"), (2, "", "en", "q"), (3, "\n\n \t", "en", "q"), (4, crowd, "en", "q"), (4, crowd, "en", "q"), (5, "a a a a", "de", None), (6, "a a a", "de", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, stratum string")
    labels = spark.createDataFrame([(1, None), (4, 1), (4, 1), (99, 1), (None, 0)], "doc_id long, quality int")
    got = {r["doc_id"]: r for r in quality_rules.judge(docs.drop("stratum"), labels).collect()}
    for i, text, *_ in rows:
        q = got[i]["_q"]
        assert (q["n_words"], q["word_chars"], q["n_symbols"], q["n_dup_lines"], q["n_repeat_words"]) == brute_quality(text)
    assert quality_rules.kept_documents(docs, labels).columns == docs.columns
    assert quality_rules.judge(docs.limit(0).drop("stratum"), labels.limit(0)).count() == 0


def test_binomial_tail(spark):
    from pyspark.sql import functions as F

    cases = [(0, 100), (3, 1000), (1, 2000), (40, 10000), (5, 900)]
    df = spark.createDataFrame(cases, "k long, n long")
    for r in df.select("k", "n", quality_rules.lower_tail(F.col("k"), F.col("n"), 0.005).alias("p")).collect():
        exact = sum(math.exp(math.lgamma(r["n"] + 1) - math.lgamma(i + 1) - math.lgamma(r["n"] - i + 1) + i * math.log(0.005) + (r["n"] - i) * math.log(0.995)) for i in range(r["k"] + 1))
        assert r["p"] == 1.0 if r["k"] >= r["n"] * 0.005 else abs(r["p"] - exact) < 1e-9


def test_binomial_tail_is_exact_at_every_size(spark):
    from pyspark.sql import functions as F

    cases = [(0, 5_000_000), (1, 1200), (20, 6000), (21, 6000), (4850, 1_000_000), (4850, 1_000_001), (9780, 2_000_000)]
    df = spark.createDataFrame(cases, "k long, n long")
    for r in df.select("k", "n", quality_rules.lower_tail(F.col("k"), F.col("n"), 0.005).alias("p")).collect():
        term, exact = r["n"] * math.log1p(-0.005), 0.0
        for i in range(r["k"] + 1):
            exact += math.exp(term)
            term += math.log((r["n"] - i) / (i + 1) * 0.005 / 0.995)
        assert abs(r["p"] - exact) <= 1e-7 * exact


def test_certified_cut_separates_junk(spark):
    good = [(i, "word number %d of this text is %d " % (i, i) + " ".join(f"w{i}x{j}" for j in range(60)), "en") for i in range(3000)]
    junk = [(10000 + i, " ".join(f"w{i}x{j}***" for j in range(60)), "en") for i in range(50)]
    docs = spark.createDataFrame(good + junk, "doc_id long, text string, lang string").repartition(4)
    labels = spark.createDataFrame([(i, 1) for i, *_ in good], "doc_id long, quality int")
    out = quality_rules.judge(docs, labels)
    assert out.where("kept").count() == 3000 and out.where("kept and doc_id >= 10000").count() == 0


def test_small_strata_share_certified_cuts(spark):
    def good(i):
        return " ".join(f"w{i}x{j}" for j in range(60)) + ("*" * 100 if i in (7001, 7002) else "")

    langs = {"en": (0, 2000), "de": (3000, 600), "fr": (5000, 600), "xx": (7000, 100), None: (8000, 30)}
    rows = [(a + i, good(a + i), lang) for lang, (a, n) in langs.items() for i in range(n)]
    junk = [(10000 + i, " ".join(f"w{i}x{j}***" for j in range(60)), lang) for i, lang in enumerate(["en", "de", "fr", None, "new", "xx"])]
    docs = spark.createDataFrame(rows + junk, "doc_id long, text string, lang string").repartition(4)
    labels = spark.createDataFrame([(i, 1) for i, *_ in rows], "doc_id long, quality int")
    no_rest = [(i, 1) for i, _, lang in rows if lang in ("en", "fr")]
    for given in (labels, spark.createDataFrame(no_rest, "doc_id long, quality int")):
        out = quality_rules.judge(docs, given)
        kept = {r["doc_id"] for r in out.where("kept").collect()}
        assert kept & set(range(10000, 10005)) == set()
        assert {r["doc_id"] for r in quality_rules.kept_documents(docs, given).collect()} == kept
        assert all(i in kept for i, _, lang in rows if lang in ("en", "de", "fr"))
    too_few = spark.createDataFrame([(i, 1) for i in range(quality_rules.least_labels(1) - 1)], "doc_id long, quality int")
    assert {r["doc_id"] for r in quality_rules.judge(docs, too_few).where("kept").collect()} == {i for i, *_ in rows + junk}


def test_a_pooled_stratum_keeps_its_good_documents(spark):
    def measures(i, lang):
        return (i, lang, False, 0.2 if lang == "xx" else 0.0, 0.0, 0.0, 0.0)

    rows = [measures(i, "xx" if i < 3 else "de" if i < 3000 else "fr") for i in range(3100)] + [measures(5000, "new")]
    measured = spark.createDataFrame(rows, "doc_id long, stratum string, base_failed boolean, symbol_share double, dup_line_share double, repeat_share double, capital_share double")
    labels = spark.createDataFrame([(i, 1) for i in range(3100)], "doc_id long, quality int")
    cuts = {r["_stratum"]: r["symbol_share_cut"] for r in quality_rules.certified_cuts(measured, labels).collect()}
    assert cuts == {"de": 0.06, "fr": 0.06, None: 0.06, "xx": 0.25}


def test_repeated_labels_and_copies_are_one_trial(spark):
    text = lambda i: " ".join(f"w{i}x{j}" for j in range(60))
    docs = spark.createDataFrame([(i, text(i % 300), "en") for i in range(3000)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1) for i in range(3000) for _ in range(4)] + [(None, 1), (5, None)], "doc_id long, quality int")
    cuts = quality_rules.judge(docs, labels).select("symbol_share_cut").distinct().collect()
    assert [r[0] for r in cuts] == [None]


def brute_cuts(trials, risk=quality_rules.RISK, level=quality_rules.LEVEL):
    """{stratum: {rule: cutoff}} of strata that stand alone, from {stratum: [shares of good documents]}, exactly by fractions of integers."""
    per, rules = risk / 4, quality_rules.RULES

    def tail(k, n):
        return sum(math.comb(n, i) * per**i * (1 - per) ** (n - i) for i in range(k + 1))

    out = {}
    for stratum, rows in trials.items():
        out[stratum] = {}
        for r in rules:
            cut = None
            for c in quality_rules.CUTS:
                k = sum(x[r] >= c for x in rows)
                if tail(k, len(rows)) > level / (4 * (len(trials) + 1)) or k > len(rows) * per:
                    break
                cut = c
            out[stratum][r] = cut
    return out


def test_cuts_and_verdicts_against_brute_force(spark):
    import random

    rnd = random.Random(6)
    rows = []
    for lang, n in (("aa", 1600), ("bb", 1400)):
        for _ in range(n):
            i = len(rows)
            odd = rnd.random()
            text = " ".join(f"w{i}x{j}" for j in range(60)) + ("*" * rnd.randrange(20, 300) if odd < 0.003 else "") + ("\nAB CD EF" * rnd.randrange(1, 5) if odd > 0.996 else "")
            rows.append((i, text, lang))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1) for i, *_ in rows], "doc_id long, quality int")
    out = quality_rules.judge(docs, labels).collect()
    trials = {}
    for r in out:
        if not r["base_failed"]:
            trials.setdefault(r["stratum"], []).append({k: r[k] for k in quality_rules.RULES})
    want = brute_cuts(trials)
    for r in out:
        cuts = want[r["stratum"]]
        assert {k: r[f"{k}_cut"] for k in quality_rules.RULES} == cuts
        assert r["kept"] == (not r["base_failed"] and not any(c is not None and r[k] >= c for k, c in cuts.items()))
    assert any(not r["kept"] and not r["base_failed"] for r in out)


def brute_license(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    at, labels = [], set()
    for phrase, label in license_scan.BASE:
        p = phrase.split()
        for i in range(len(w) - len(p) + 1):
            if w[i : i + len(p)] == p:
                at.append(i)
                labels.add(label)
    return len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels))


def test_license_scan(spark):
    rows = [
        (1, "Released under the MIT License.\nUnder the MIT license", "x"),
        (2, None, "x"),
        (3, "", "x"),
        (4, "This work is licensed under the GNU General Public License, version 3.", "x"),
        (5, "Licensed under CC BY-NC 4.0. é Licensed under the Apache License, Version 2.0", "x"),
        (5, "under the mit licenses", "x"),
        (6, "Wörter, mit license? " + "zz " * 20000 + "permission is hereby granted, free of charge, to any person obtaining a copy of this software", "x"),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string, label string")
    out = license_scan.scan(df).collect()
    got = Counter((r["doc_id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) for r in out)
    assert got == Counter((i, *brute_license(t)) for i, t, _ in rows)
    labels = {(r["doc_id"], r["labels"]) for r in out}
    assert (4, "gpl-3") in labels and (6, "mit") in labels and (1, "mit") in labels
    assert license_scan.scan(df.limit(0)).count() == 0


def brute_placements(words, idf, templates, enough):
    """(label, score) of every template at every offset that its index words vote for twice, straight from the definition."""
    chosen = {w for _, t, _ in templates for w in sorted(set(t.split()), key=lambda w: (-idf[w], w))[: license_scan.RAREST]}
    rare = set(sorted(chosen & set(words), key=lambda w: (-idf[w], w))[: license_scan.LOOKED_UP])
    out = []
    for label, text, keys in templates:
        t = text.split()
        total = sum(max(idf[w], 1e-6) for w in t)
        for off in range(-len(t) + 1, len(words)):
            same = [i for i in range(len(t)) if 0 <= off + i < len(words) and words[off + i] == t[i]]
            if sum(t[i] in rare for i in same) < 2:
                continue
            if all(any(t[i : i + len(k.split())] == k.split() == words[off + i : off + i + len(k.split())] and off + i >= 0 for i in range(len(t))) for k in keys):
                score = sum(max(idf[t[i]], 1e-6) for i in same) / total
                if score >= enough:
                    out.append((label, score))
    return out


def test_license_labels_against_brute_force(spark):
    import random

    rnd = random.Random(9)
    fill = lambda n: " ".join(rnd.choice(["alpha", "beta", "the", "software", "license", "free", "of"]) for _ in range(n))
    gpl = next(t for x, t, _ in license_scan.TEMPLATES if x == "gpl-3")
    texts = {
        "gpl header": "/* " + gpl.capitalize() + ". */ " + fill(300),
        "title": "                    GNU GENERAL PUBLIC LICENSE\n   Version 3, 29 June 2007\n" + fill(50),
        "identifier": "// SPDX-License-Identifier: GPL-3.0-only\n" + fill(20),
        "scattered": "the gnu general public license version 3 " + fill(300) + " this work is licensed under",
        "mention": "a review of the gnu general public license version 3 and others",
        "mit": fill(90) + " " + license_scan.TEMPLATES[1][1].replace("files the", "files (the") + " " + fill(9),
        "edited": "Redistribution and use in source and binary forms, with or without any modification, are permitted",
        "two": "SPDX-License-Identifier: MIT OR x " + next(t for x, t, _ in license_scan.TEMPLATES if x == "isc"),
    }
    for k in range(25):
        t = rnd.choice(license_scan.TEMPLATES)[1].split()
        texts[f"noise {k}"] = fill(rnd.randrange(30)) + " " + " ".join(w for w in t if rnd.random() < 0.93) + " " + fill(rnd.randrange(30))
    texts.update({f"plain {k}": fill(40) for k in range(30)})
    names = list(texts)
    df = spark.createDataFrame([(i, texts[n], "x") for i, n in enumerate(names)], "doc_id long, text string, _words string")
    split = {n: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", texts[n].lower()) for n in names}
    vocabulary = {w for t in license_scan.TEMPLATES for w in t[1].split()}
    idf = {w: math.log((len(names) + 1) / (sum(w in s for s in split.values()) + 0.5)) for w in vocabulary}
    labels = {}
    for r in license_scan.scan(df).collect():
        name = names[r["doc_id"]]
        placed = brute_placements(split[name], idf, license_scan.TEMPLATES, license_scan.ENOUGH)
        base = set(filter(None, r["base_labels"].split(",")))
        assert r["labels"] == ",".join(sorted(base | {x for x, _ in placed})), name
        assert abs(r["score"] - max([s for _, s in placed] + [license_scan.ENOUGH if base else 0.0])) < 2e-6
        labels[name] = r["labels"]
    assert [labels[n] for n in ("gpl header", "title", "identifier", "scattered", "mention", "mit", "edited", "two")] == ["gpl-3", "gpl-3", "gpl-3", "", "", "mit", "bsd", "isc,mit"]


def test_license_scan_on_documents(spark):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    for r in license_scan.query(spark, SF).collect():
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == brute_license(texts[r["doc_id"]])
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))


def test_url_filter(spark):
    urls = [None, "", "nourl", "http://EXAMPLE.com", "http://a.example.com/en/x?y", "https://www.example.com/en/", "ftp://x.net/es/1#k", "http://net/fr/", "http://com:80/x", "http://x.y.com/?q=/en/"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)] + [(4, urls[4], "h")], "page_id long, url string, host string")
    rules = spark.createDataFrame(url_filter.RULES, "host string, path string, verdict string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(pages, rules).collect()}
    assert got == {
        0: ("", "", None, "allow"),
        1: ("", "", None, "allow"),
        2: ("", "", None, "allow"),
        3: ("example.com", "", None, "allow"),
        4: ("a.example.com", "/en/x", "example.com/en/", "block"),
        5: ("www.example.com", "/en/", "www.example.com/en/", "allow"),
        6: ("x.net", "/es/1", "net/es/", "block"),
        7: ("net", "/fr/", "net/fr/", "block"),
        8: ("com:80", "/x", None, "allow"),
        9: ("x.y.com", "/", "com/", "allow"),
    }
    assert url_filter.judge_urls(pages, rules).count() == 11
    assert url_filter.judge_urls(pages, rules.limit(0)).where("verdict = 'allow'").count() == 11
    assert url_filter.judge_urls(pages.limit(0), rules).count() == 0
