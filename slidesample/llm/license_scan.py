"""Licence scan with a positional index of rare words.  Native.

Templates are paragraphs, notices, title lines and identifiers of public licences, each with key phrases that must stand where the template
has them.  Inverse document frequencies of all template words come from the whole corpus.  The index holds, for every word
that is among the `RAREST` rarest of some template, its postings: all (template, position) where it stands.  Of each file the `LOOKED_UP`
highest-IDF words of the index are looked up; a place of the word less a position of a posting is an offset at which the template
would lie, and offsets on which two places agree are placements.  A placement is verified word by word: every key phrase must
stand at its own position from there, and the IDF-weighted share of the template's words found at their positions is its score, which must reach
`ENOUGH`.  A key phrase elsewhere in the file counts for nothing.  Base labels come from fixed phrases found at consecutive words.

The index is a constant (it depends on the templates, not on the corpus), and all of a file's work is inside its row: no join and no
shuffle but the counting of document frequencies.

Defined cases: null text is empty: no words, no places, empty labels, score 0; phrases match whole words only; phrases may
overlap and each place counts; repeated rows are scanned one by one; ids may be null; extra columns are ignored; no rows, no result.
"""

from __future__ import annotations

import json
import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let, lower_ascii, table

#: Characters between words after lower-casing (fixed value).
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Base phrases and their labels (fixed values).
BASE = [("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc")]
#: Label, words and key phrases of templates (fixed values, wording of the public licences).
TEMPLATES = [
    ("mit", "released under the mit license", ["under the mit license"]),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction", ["permission is hereby granted free of charge"]),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", ["permission is hereby granted free of charge"]),
    ("apache-2", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", ["licensed under the apache license version 2 0"]),
    ("apache-2", "licensed under the apache license version 2 0", ["apache license version 2 0"]),
    ("apache-2", "apache license version 2 0 january 2004", ["apache license version 2 0 january 2004"]),
    ("gpl-3", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version", ["terms of the gnu general public license", "either version 3"]),
    ("gpl-2", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version", ["terms of the gnu general public license", "either version 2"]),
    ("gpl-3", "gnu general public license version 3 29 june 2007", ["gnu general public license version 3 29 june 2007"]),
    ("gpl-2", "gnu general public license version 2 june 1991", ["gnu general public license version 2 june 1991"]),
    ("gpl-3", "this work is licensed under the gnu general public license version 3", ["licensed under the gnu general public license version 3"]),
    ("gpl-2", "this work is licensed under the gnu general public license version 2", ["licensed under the gnu general public license version 2"]),
    ("lgpl", "you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", ["terms of the gnu lesser general public license"]),
    ("lgpl", "licensed under the gnu lesser general public license", ["licensed under the gnu lesser general public license"]),
    ("agpl-3", "you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation", ["terms of the gnu affero general public license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ["redistribution and use in source and binary forms"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ["redistribution and use in source and binary forms"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", ["distribute this software for any purpose"]),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at", ["terms of the mozilla public license v 2 0"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["free and unencumbered software released into the public domain"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["under cc by nc"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["under cc by sa"]),
    ("cc-by-nc", "this work is licensed under a creative commons attribution noncommercial 4 0 international license", ["creative commons attribution noncommercial 4 0"]),
    ("cc-by-sa", "this work is licensed under a creative commons attribution sharealike 4 0 international license", ["creative commons attribution sharealike 4 0"]),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", ["creative commons attribution 4 0"]),
    ("cc0", "dedicated to the public domain under cc0 1 0 universal", ["public domain under cc0 1 0"]),
]
#: Registered short identifiers and their labels (fixed values).
IDENTIFIERS = {
    "mit": "mit", "apache 2 0": "apache-2", "gpl 2 0": "gpl-2", "gpl 3 0": "gpl-3", "lgpl 2 1": "lgpl", "lgpl 3 0": "lgpl", "agpl 3 0": "agpl-3",
    "bsd 2 clause": "bsd", "bsd 3 clause": "bsd", "isc": "isc", "mpl 2 0": "mpl-2", "unlicense": "unlicense", "cc by 4 0": "cc-by",
    "cc by nc 4 0": "cc-by-nc", "cc by sa 4 0": "cc-by-sa", "cc0 1 0": "cc0",
}
TEMPLATES += [(label, f"spdx license identifier {name}", [f"spdx license identifier {name}"]) for name, label in IDENTIFIERS.items()]
RAREST, LOOKED_UP = 6, 16
ENOUGH = 0.6


def normal(text: Column) -> Column:
    """Lower-cased words joined by single spaces."""
    return F.trim(F.regexp_replace(lower_ascii(F.coalesce(text, F.lit(""))), BETWEEN, " "))


def places(words: Column, phrase: str) -> Column:
    """Start positions (from 0) of `phrase` in the array `words`."""
    parts = phrase.split()
    last = F.size(words) - len(parts)
    matched = lambda i: reduce(lambda a, b: a & b, [F.element_at(words, i + (j + 1)) == p for j, p in enumerate(parts)])
    return F.when(last < 0, F.array().cast("array<int>")).otherwise(F.filter(F.sequence(F.lit(0), last), matched))


def word_idf(docs: DataFrame, vocabulary: list[str], text_col: str = "text") -> dict[str, float]:
    """IDF of each word of the (fixed) vocabulary over all documents."""
    known = F.array(*[F.lit(w) for w in vocabulary])
    found = F.array_intersect(F.split(normal(F.col(text_col)), " "), known)
    counted = docs.select(F.explode(F.concat(found, F.array(F.lit("")))).alias("w")).groupBy("w").count()
    seen = {r["w"]: r["count"] for r in counted.collect()}  # at most len(vocabulary) + 1 rows
    total = seen.get("", 0)
    return {w: math.log((total + 1) / (seen.get(w, 0) + 0.5)) for w in vocabulary}


def positional_index(idf: dict[str, float], templates) -> tuple[list[str], str, str]:
    """(words of the index, rarest first; their postings as JSON; the templates with weights and key positions as JSON)."""
    rows, chosen, postings = [], set(), {}
    for label, text, keys in templates:
        words = text.split()
        weight = [max(idf[w], 1e-6) for w in words]
        at = [next(i for i in range(len(words)) if words[i : i + len(k.split())] == k.split()) for k in keys]
        rows.append({"label": label, "words": words, "weights": [x / sum(weight) for x in weight], "keys": [{"at": i, "words": k.split()} for i, k in zip(at, keys, strict=True)]})
        chosen.update(sorted(set(words), key=lambda w: (-idf[w], w))[:RAREST])
    for t, row in enumerate(rows):
        for i, w in enumerate(row["words"]):
            if w in chosen:
                postings.setdefault(w, []).append({"t": t, "at": i})
    return sorted(chosen, key=lambda w: (-idf[w], w)), json.dumps(postings), json.dumps(rows)


def placements(words: Column, index: Column, postings: Column, templates: Column, enough: float) -> Column:
    """Verified placements in one file: array of (label, score)."""

    def voted(rare: Column) -> Column:
        at = F.filter(F.sequence(F.lit(0), F.size(words) - 1), lambda i: F.array_contains(rare, F.get(words, i)))
        votes = F.flatten(F.transform(at, lambda i: F.transform(F.element_at(postings, F.get(words, i)), lambda p: F.struct(p["t"].alias("t"), (i - p["at"]).alias("off")))))
        agreed = let(F.sort_array(votes), lambda v: F.array_distinct(F.filter(v, lambda x, j: (j > 0) & (F.get(v, F.greatest(j - 1, F.lit(0))) == x))))
        return F.filter(F.transform(agreed, verified), lambda x: x["score"] >= enough)

    def verified(place: Column) -> Column:
        def judged(t: Column) -> Column:
            keyed = F.forall(
                t["keys"], lambda k: F.when(place["off"] + k["at"] < 0, F.lit(False)).otherwise(F.slice(words, F.greatest(place["off"] + k["at"], F.lit(0)) + 1, F.size(k["words"])) == k["words"])
            )
            here = lambda i: F.when(place["off"] + i >= 0, F.get(words, F.greatest(place["off"] + i, F.lit(0))))
            share = F.aggregate(F.transform(t["words"], lambda w, i: F.when(here(i) == w, F.get(t["weights"], i)).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x)
            return F.struct(t["label"].alias("label"), F.when(keyed, share).otherwise(F.lit(0.0)).alias("score"))

        return let(F.get(templates, place["t"]), judged)

    none = F.array().cast("array<struct<label:string,score:double>>")
    return let(F.slice(F.array_intersect(index, words), 1, LOOKED_UP), lambda rare: F.when(F.size(rare) < 2, none).otherwise(voted(rare)))


def scan(docs: DataFrame, templates=TEMPLATES, base=BASE, id_col: str = "doc_id", text_col: str = "text", enough: float = ENOUGH) -> DataFrame:
    """One row per document: id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    vocabulary = sorted({w for t in templates for w in t[1].split()})
    ranked, postings, rows = positional_index(word_idf(docs, vocabulary, text_col), templates)
    index = F.array(*[F.lit(w) for w in ranked])
    postings = F.from_json(F.lit(postings), "map<string, array<struct<t:int,at:int>>>")
    known = F.from_json(F.lit(rows), "array<struct<label:string,words:array<string>,weights:array<double>,keys:array<struct<at:int,words:array<string>>>>>")
    padded = F.concat(F.lit(" "), F.col("_norm"), F.lit(" "))
    nowhere = F.array().cast("array<int>")
    split = docs.select(F.col(id_col), normal(F.col(text_col)).alias("_norm"))
    split = split.select(
        id_col,
        F.array_remove(F.split("_norm", " "), "").alias("_words"),
        *[F.contains(padded, F.lit(f" {phrase} ")).alias(f"_has{k}") for k, (phrase, _) in enumerate(base)],
    )
    found = split.select(
        id_col,
        F.size("_words").cast("long").alias("n_words"),
        F.array(*[F.struct(F.lit(label).alias("label"), F.when(F.col(f"_has{k}"), places(F.col("_words"), phrase)).otherwise(nowhere).alias("at")) for k, (phrase, label) in enumerate(base)]).alias("_base"),
        placements(F.col("_words"), index, postings, known, enough).alias("_placed"),
    )
    starts = F.flatten(F.transform("_base", lambda b: b["at"]))
    with_base = F.transform(F.filter("_base", lambda b: F.size(b["at"]) > 0), lambda b: b["label"])
    joined = lambda labels: F.array_join(F.array_sort(F.array_distinct(labels)), ",")
    best = F.coalesce(F.array_max(F.transform("_placed", lambda x: x["score"])), F.lit(0.0))
    return found.select(
        id_col,
        "n_words",
        F.size(starts).cast("long").alias("n_base"),
        F.array_min(starts).cast("long").alias("first_word"),
        F.array_max(starts).cast("long").alias("last_word"),
        joined(with_base).alias("base_labels"),
        joined(F.concat(with_base, F.transform("_placed", lambda x: x["label"]))).alias("labels"),
        F.round(F.least(F.lit(1.0), F.greatest(best, F.when(F.size(starts) > 0, F.lit(enough)).otherwise(F.lit(0.0)))), 6).alias("score"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


QUERIES = {"op10_license_scan": query}
ORACLE_SQL: dict[str, str] = {}
