"""Quality rules with risk-controlled cutoffs.  Native.

Base rules reject short and repetitive texts.  Further rules reject a text when a share (symbols, repeated lines, repeated
words, capitals) reaches a cutoff.  Cutoffs are chosen per stratum (language) from labelled documents: going from the loosest
cutoff to stricter ones, a cutoff is certified while an exact binomial test still shows that the rule rejects fewer than `risk` / 4 of the
good documents; the first failure ends the walk (fixed-sequence testing), and the level is divided by the
number of rules and tested groups (Bonferroni).  So with probability 1 - `level` the verdict, all four rules together, rejects at most
`risk` of each group's good documents that pass the base rules.  A trial of the test is a distinct text: repeated labels, repeated rows and
exact copies count once (near copies count each).
A group is a stratum with labels enough for a test to succeed at all, or the pool of all other strata (of
all labelled documents, if the others alone are too few).  Pooled strata share the pool's cutoffs, its promise is about the pool as
a whole; a pooled stratum stays at the last cutoff that rejects at most `risk` / 4 of its own good documents.  Only where
all labelled documents together are too few is there no cutoff, and base rules act alone.

Counts come from array expressions inside each row: hashed 3-word windows are sorted with their positions, equal
neighbours mark repeats.  Work per text is n log n, so very long texts are no special case.  Every text is measured once; cutoffs,
verdicts and their joins see narrow rows only.

Defined cases: null or empty text has no words and fails the base rules; null language is the stratum ''; labels without a
document or with null quality are ignored, a document labelled both good and bad counts as good; extra columns are untouched.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import keyed_rows, let, row_keys, shuffled, staged, table

SPACE = r"[\x20\x09-\x0D]+"
SPACES = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"
CAPITALS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Cutoffs from loose to strict; a share at or above the cutoff is rejected.
CUTS = [0.9, 0.8, 0.7, 0.6, 0.5, 0.45, 0.4, 0.35, 0.3, 0.25, 0.2, 0.15, 0.12, 0.1, 0.08, 0.06]
RULES = ["symbol_share", "dup_line_share", "repeat_share", "capital_share"]
#: Share of good documents that the verdict may reject, and the chance that it rejects more.
RISK, LEVEL = 0.02, 0.05
#: Strata with cutoffs of their own, those with most labels; all others use those of strata without labels.  Bounds the broadcast.
MOST_STRATA = 10_000


def repeated_words(words: Column) -> Column:
    """Words inside 3-word windows that occur at least twice in the array."""

    def counted(w: Column) -> Column:
        last = F.size(w) - 2
        windows = F.transform(
            F.sequence(F.lit(1), last), lambda i: F.struct(F.xxhash64(F.element_at(w, i), F.element_at(w, i + 1), F.element_at(w, i + 2)).alias("h"), i.alias("i"))
        )

        def starts(s: Column) -> Column:
            n = F.size(s)
            equal_before = lambda x, j: (j > 0) & (F.element_at(s, F.greatest(j, F.lit(1)))["h"] == x["h"])
            equal_after = lambda x, j: (j + 1 < n) & (F.element_at(s, F.least(j + 2, n))["h"] == x["h"])
            return F.sort_array(F.transform(F.filter(s, lambda x, j: equal_before(x, j) | equal_after(x, j)), lambda x: x["i"]))

        def covered(p: Column) -> Column:
            steps = F.transform(p, lambda x, j: F.when(j == 0, 3).otherwise(F.least(F.lit(3), x - F.element_at(p, F.greatest(j, F.lit(1))))))
            return F.aggregate(steps, F.lit(0), lambda a, b: a + b)

        found = let(let(F.sort_array(windows), starts), covered)
        hashes = F.transform(F.sequence(F.lit(1), last), lambda i: F.xxhash64(F.element_at(w, i), F.element_at(w, i + 1), F.element_at(w, i + 2)))
        return F.when(last < 2, 0).when(F.size(F.array_distinct(hashes)) == last, 0).otherwise(found)

    return let(words, counted)


def removed(text: Column, chars: str) -> Column:
    """How many characters of `text` are among `chars`."""
    return F.length(text) - F.length(F.translate(text, chars, ""))


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Add `_q`, a struct of counts, to every row."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.translate(x, SPACES, "")) > 0)
    words = F.array_remove(F.split(text, SPACE), "")
    first = docs.withColumn("_lines", lines).withColumn("_words", words)
    return first.withColumn(
        "_q",
        F.struct(
            F.size("_words").cast("long").alias("n_words"),
            F.length(F.translate(text, SPACES, "")).cast("long").alias("word_chars"),
            removed(text, SYMBOLS).cast("long").alias("n_symbols"),
            (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
            repeated_words(F.col("_words")).cast("long").alias("n_repeat_words"),
            F.size("_lines").cast("long").alias("n_lines"),
            removed(text, CAPITALS).cast("long").alias("n_capitals"),
        ),
    ).drop("_lines", "_words")


def base_failed(q: str = "_q") -> Column:
    words = F.col(f"{q}.n_words")
    return (words < 50) | (F.lit(100) * F.col(f"{q}.n_repeat_words") > F.lit(50) * words)


def shares(q: str = "_q") -> dict[str, Column]:
    part = lambda a, b: F.when(F.col(f"{q}.{b}") > 0, F.col(f"{q}.{a}") / F.col(f"{q}.{b}")).otherwise(F.lit(0.0))
    return dict(zip(RULES, [part("n_symbols", "word_chars"), part("n_dup_lines", "n_lines"), part("n_repeat_words", "n_words"), part("n_capitals", "word_chars")], strict=True))


def stirling_error(n: Column) -> Column:
    """log(n!) less Stirling's n log n - n + log(2 pi n) / 2, for n >= 1."""
    x = n.cast("double")
    series = (F.lit(1 / 12) - (F.lit(1 / 360) - (F.lit(1 / 1260) - F.lit(1 / 1680) / (x * x)) / (x * x)) / (x * x)) / x
    small = F.least(F.greatest(n, F.lit(1)), F.lit(20)).cast("int")
    table = F.log(F.factorial(small).cast("double")) - (small * F.log(small) - small + 0.5 * F.log(2 * math.pi * small))
    return F.when(n <= 20, table).otherwise(series)


def lower_tail(k: Column, n: Column, p: float) -> Column:
    """P(Binomial(n, p) <= k), exact at every size: the term of k, then downward until terms no longer count (about 10 sqrt(k) of them)."""
    rest = n - k
    off = k * F.log(k / (n * F.lit(p))) + rest * F.log(rest / (n * F.lit(1 - p)))
    last = F.exp(stirling_error(n) - stirling_error(k) - stirling_error(rest) - off + 0.5 * F.log(n / (2 * math.pi * k * rest)))

    def add(acc, i):
        term = acc["t"] * (i * F.lit((1 - p) / p)) / (n - i + 1)
        return F.struct(term.alias("t"), (acc["s"] + term).alias("s"))

    # below n * p the i-th ratio is at most i / k, so after j steps a term is below exp(-j (j - 1) / 2k)
    least = F.greatest(F.lit(1).cast("long"), k - F.ceil(10 * F.sqrt(k)) - 2)
    one = F.lit(1.0)
    terms = F.aggregate(F.sequence(k, least), F.struct(one.alias("t"), one.alias("s")), add, lambda acc: acc["s"])
    return F.when((n == 0) | (k >= n * F.lit(p)), F.lit(1.0)).when(k == 0, F.exp(n * F.lit(math.log1p(-p)))).otherwise(last * terms)


def least_labels(groups: int, risk: float = RISK, level: float = LEVEL) -> int:
    """Good documents that a group needs for a cutoff which rejects none of them."""
    return math.ceil(math.log(level / (groups * len(RULES))) / math.log1p(-risk / len(RULES)))


def certified_cuts(measured: DataFrame, labels: DataFrame, risk: float = RISK, level: float = LEVEL, id_col: str = "doc_id") -> DataFrame:
    """measured(id, stratum, base_failed, the shares, _text) + labels(id, quality) -> one row per stratum with a cutoff (or null) per rule.

    The row of a null stratum holds for all strata without a row.  Who is pooled depends on the numbers of labels only.
    Rows of one stratum with equal `_text` (a hash; the id where there is none) are one trial.
    """
    risk = risk / len(RULES)
    good = labels.where("quality = 1").select(F.col(id_col).alias("_id")).distinct()
    same = "_text" if "_text" in measured.columns else id_col
    reached = [F.sum((F.col(r) >= c).cast("long")).alias(f"{r}_{i}") for r in RULES for i, c in enumerate(CUTS)]
    counts = (
        measured.where(~F.col("base_failed"))
        .select(id_col, "stratum", same, *RULES)
        .join(shuffled(good), F.col(id_col) == F.col("_id"))
        .dropDuplicates(["stratum", same])
        .groupBy("stratum")
        .agg(F.count("*").alias("n"), *reached)
    )
    fields = ["n", *[f"{r}_{i}" for r in RULES for i in range(len(CUTS))]]
    unseen = measured.sparkSession.range(1).select(F.lit(None).cast("string").alias("stratum"), *[F.lit(0).cast("long").alias(c) for c in fields])
    everyone = Window.partitionBy()
    alpha = lambda groups: F.lit(level) / (groups * len(RULES))
    enough = lambda n, groups: n * F.lit(math.log1p(-risk)) <= F.log(alpha(groups))
    # the j-th largest stratum stands alone if it has labels enough for j groups and the pool
    place = F.row_number().over(Window.orderBy(F.col("n").desc(), F.col("stratum").asc_nulls_last()))
    placed = counts.unionByName(unseen).withColumn("_place", place).withColumn("_own", enough(F.col("n"), F.col("_place") + 1) & (F.col("_place") <= MOST_STRATA))
    placed = placed.withColumn("_groups", F.sum(F.col("_own").cast("int")).over(everyone) + 1)
    rest = F.coalesce(F.sum(F.when(~F.col("_own"), F.col("n"))).over(everyone), F.lit(0))
    placed = placed.withColumn("_rest", enough(rest, F.col("_groups")))
    pooled = [F.sum(F.when(~F.col("_own") | ~F.col("_rest"), F.col(c))).over(everyone) for c in fields]
    tests = placed.select("*", *[F.when(F.col("_own"), F.col(c)).otherwise(p).alias(f"_t_{c}") for c, p in zip(fields, pooled, strict=True)])

    def walk(rule: str) -> Column:
        ladder = F.array(*[F.struct(F.lit(c).alias("c"), F.col(f"_t_{rule}_{i}").alias("k"), F.col(f"{rule}_{i}").alias("here")) for i, c in enumerate(CUTS)])
        start = F.struct(F.lit(None).cast("double").alias("cut"), F.lit(True).alias("go"))

        def step(acc, x):
            go = acc["go"] & (x["here"] <= F.col("n") * F.lit(risk)) & (lower_tail(x["k"], F.col("_t_n"), risk) <= alpha(F.col("_groups")))
            return F.struct(F.when(go, x["c"]).otherwise(acc["cut"]).alias("cut"), go.alias("go"))

        return F.aggregate(ladder, start, step, lambda acc: acc["cut"])

    listed = tests.where((F.col("_place") <= MOST_STRATA) | F.col("stratum").isNull())
    return listed.select(F.col("stratum").alias("_stratum"), *[walk(r).alias(f"{r}_cut") for r in RULES])


def measured_rows(docs: DataFrame, id_col: str = "doc_id", stratum_col: str = "lang") -> DataFrame:
    """One narrow row per document: id, keys, stratum, `_text` (hash), `_q`, base_failed, shares."""
    chosen = docs.select(id_col, "text", stratum_col, *row_keys(id_col, "text", stratum_col))
    return with_statistics(chosen).select(
        id_col,
        "_k1",
        "_k2",
        F.coalesce(stratum_col, F.lit("")).alias("stratum"),
        F.xxhash64("text").alias("_text"),
        "_q",
        base_failed().alias("base_failed"),
        *[c.alias(r) for r, c in shares().items()],
    )


def with_cuts(rows: DataFrame, cuts: DataFrame) -> DataFrame:
    """Join the cutoffs (MOST_STRATA rows and one at most) to rows that have `stratum`; add `kept`."""
    cuts = staged(cuts, "quality-cuts")
    unseen = cuts.where("_stratum IS NULL").first()
    joined = rows.join(F.broadcast(cuts.where("_stratum IS NOT NULL")), F.col("stratum") == F.col("_stratum"), "left")
    rejected = F.lit(False)
    for r in RULES:
        joined = joined.withColumn(f"{r}_cut", F.when(F.col("_stratum").isNull(), F.lit(unseen[f"{r}_cut"]).cast("double")).otherwise(F.col(f"{r}_cut")))
        rejected = rejected | F.coalesce(F.col(r) >= F.col(f"{r}_cut"), F.lit(False))
    return joined.withColumn("kept", ~F.col("base_failed") & ~rejected).drop("_stratum")


def judge(docs: DataFrame, labels: DataFrame, risk: float = RISK, level: float = LEVEL) -> DataFrame:
    """One row per document: doc_id, keys, stratum, `_q`, base_failed, shares, cutoffs, kept."""
    measured = staged(measured_rows(docs), "quality-measures")
    return with_cuts(measured, certified_cuts(measured, labels, risk, level))


def kept_documents(docs: DataFrame, labels: DataFrame, risk: float = RISK, level: float = LEVEL) -> DataFrame:
    """The rows of `docs` that pass, with their columns.  Texts are shuffled once, to meet their verdicts."""
    kept = judge(docs, labels, risk, level).where("kept").select("_k1", "_k2").distinct()
    return keyed_rows(docs, "doc_id", "text", "lang").join(shuffled(kept), ["_k1", "_k2"], "left_semi").select("_row.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    counts = [F.col(f"_q.{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    return out.select("doc_id", *counts, "base_failed", "kept", *[f"{r}_cut" for r in RULES])


QUERIES = {"op7_quality_rules": query}
ORACLE_SQL: dict[str, str] = {}
