"""Carry-over: samples that prefer items whose results are already known.

`carry_over` does one window with DataFrame operators.  `carry_chain` does a whole replay in one job: strata do not depend on
each other once the fresh samples are drawn, so rows are dealt by stratum, sorted by window, and streamed; the state is one stratum's
last sample.  `coordinated` needs no chain at all: permanent priorities make successive samples overlap.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slidesample.functions.hashing import priority, priority_value
from slidesample.operators.windows import Slide


COLUMNS = ["window_id", "stratum", "item_id", "seq", "value", "u"]


def carry_over(sample: DataFrame, memo: DataFrame, quotas: DataFrame, carry: str = "biased", surplus: str = "hash", refill: str = "hash") -> DataFrame:
    """Biased sample of one or many windows: window_id, stratum, item_id, seq, value, u, from_memo.

    carry: 'biased' (memo first, quota kept), 'all' (the whole memo, quota ignored), 'none' (fresh sample only).
    surplus (which memo items go): 'hash', 'list' (arrival order), 'newest'.  refill: 'hash', 'sample_order', 'newest_first'.
    """
    fresh = sample.select(*COLUMNS).withColumn("from_memo", F.lit(False))
    if carry == "none":
        return fresh
    known = memo.select(*COLUMNS).withColumn("from_memo", F.lit(True))
    return prefer_known(known.unionByName(fresh), quotas, carry, surplus, refill)


def beside_previous(samples: DataFrame, slide: Slide, seed: str) -> DataFrame:
    """Fresh samples of all windows, each beside what the memo holds of the fresh sample before (`from_memo`), as `prefer_known` takes them.

    Whether an item is still inside follows from its position, its priority from its id: no window is read for them, and each sample is drawn once.
    """
    both = samples.select(*COLUMNS, F.explode(F.array(F.lit(False), F.lit(True))).alias("from_memo"))
    at = F.col("window_id") + F.col("from_memo").cast("long")
    inside = ~F.col("from_memo") | ((at < slide.count) & (F.col("seq") >= at * slide.step + slide.origin))
    both = both.where(inside).withColumn("window_id", at)
    return both.withColumn("u", F.when(F.col("from_memo"), priority(seed, F.col("item_id"), F.col("window_id"))).otherwise(F.col("u")))


def prefer_known(both: DataFrame, quotas: DataFrame, carry: str = "biased", surplus: str = "hash", refill: str = "hash") -> DataFrame:
    """Biased samples out of memo items and fresh ones together; dealt once, by window and stratum."""
    dealt = both.select(*COLUMNS, "from_memo").repartition("window_id", "stratum")
    once = dealt.groupBy("window_id", "stratum", "item_id").agg(F.first("seq").alias("seq"), F.first("value").alias("value"), F.first("u").alias("u"), F.max("from_memo").alias("from_memo"))
    quotas = quotas.where("quota > 0").select("window_id", "stratum", "quota")
    if carry == "all":
        return once.hint("merge").join(quotas, ["window_id", "stratum"], "left_semi").select(*COLUMNS, "from_memo")
    by = {"hash": F.lit(0), "list": F.col("seq"), "newest": -F.col("seq"), "sample_order": F.col("seq"), "newest_first": -F.col("seq")}
    key = F.when(F.col("from_memo"), by[surplus]).otherwise(by[refill])
    order = Window.partitionBy("window_id", "stratum").orderBy(F.col("from_memo").desc(), key, "u", "item_id")
    ranked = once.withColumn("_r", F.row_number().over(order)).hint("merge")  # its rows stay where they are, only quotas travel
    return ranked.join(quotas, ["window_id", "stratum"]).where("_r <= quota").select(*COLUMNS, "from_memo")


def carry_chain(fresh: DataFrame, seed: str, carry: str = "biased", refill: str = "hash", pane: int = 1, changes: bool = False) -> DataFrame:
    """fresh(window_id, lo, stratum, item_id, seq, value, u) -> all biased samples with `from_memo`.

    With `changes` only what changes from one sample to the next leaves: window_id, stratum, item_id, value, sign (1 enters, -1 leaves).

    Memo items are ranked by their priority in the window at hand; refill order is 'hash', 'sample_order' or 'newest_first'
    (newest pane of `pane` positions first, hash inside).
    """

    def moved(w, s, entering, leaving):
        rows = [(w, s, o[0], o[2], 1) for o in entering] + [(w, s, i, v, -1) for i, (_, v) in leaving]
        return pd.DataFrame(rows, columns=["window_id", "stratum", "item_id", "value", "sign"])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        stratum, last_window, memo = None, None, {}
        for part in window_runs(batches):
            w, s, lo = int(part["window_id"].iloc[0]), part["stratum"].iloc[0], int(part["lo"].iloc[0])
            if s != stratum or last_window is None or w != last_window + 1:
                if changes and memo:  # the stratum is not in the next window
                    yield moved(last_window + 1, stratum, [], memo.items())
                memo = {}
            stratum, last_window = s, w
            rows = {r[0]: r for r in zip(part["item_id"], part["seq"], part["value"], part["u"], strict=True)}
            quota = len(rows)
            known = [(priority_value(seed, i, w), i, q, v) for i, (q, v) in memo.items() if q >= lo] if carry != "none" else []
            known.sort(key=lambda k: (k[0], str(k[1])))
            chosen = known if carry == "all" else known[:quota]
            out = [(i, q, v, u, True) for u, i, q, v in chosen]
            taken = {o[0] for o in out}
            order = {"hash": lambda r: (r[3], str(r[0])), "sample_order": lambda r: (r[1], str(r[0])), "newest_first": lambda r: (-(r[1] // pane), r[3], str(r[0]))}[refill]
            rest = sorted((r for i, r in rows.items() if i not in taken), key=order)
            out += [(*r, False) for r in (rest if carry == "all" else rest[: quota - len(out)])]
            before, memo = memo, {o[0]: (o[1], o[2]) for o in out}
            if changes:
                yield moved(w, s, [o for o in out if o[0] not in before], [(i, qv) for i, qv in before.items() if i not in memo])
                continue
            frame = pd.DataFrame(out, columns=["item_id", "seq", "value", "u", "from_memo"])
            frame.insert(0, "stratum", s)
            frame.insert(0, "lo", lo)
            frame.insert(0, "window_id", w)
            yield frame
        if changes and memo:
            yield moved(last_window + 1, stratum, [], memo.items())

    kind = dict(fresh.dtypes)["item_id"]
    dealt = fresh.select("window_id", "lo", "stratum", "item_id", "seq", "value", "u").repartition("stratum").sortWithinPartitions("stratum", "window_id", "u")
    if changes:
        return dealt.mapInPandas(run, f"window_id long, stratum string, item_id {kind}, value decimal(18,2), sign int")
    return dealt.mapInPandas(run, f"window_id long, lo long, stratum string, item_id {kind}, seq long, value decimal(18,2), u long, from_memo boolean")


def chain_counts(fresh: DataFrame, seed: str, slide: Slide, refills: tuple[str, ...] = ("hash",), quotas: dict | None = None) -> DataFrame:
    """What measures need of `carry_chain`, without its rows: window_id, stratum, refill, size, needed, known (from the memo), alive (still inside the next window).

    fresh(window_id, stratum, item_id, seq, rank) with whole numbers as items.  Several chains go over the same samples: one for each refill and for each
    quota of `quotas` (by window and stratum a list, read at position `size`; a sample's first ranks are the sample of a smaller quota).
    One row for each window and stratum travels, so a stratum's task gets its windows in order without sorting items.
    """
    pane = slide.pane

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, out, memos = None, [], {}
        for batch in batches:
            for k in range(batch.num_rows):
                w, s = batch["window_id"][k].as_py(), batch["stratum"][k].as_py()
                ids, seqs, ranks = (batch[c][k].values.to_numpy() for c in ("ids", "seqs", "ranks"))
                order = np.argsort(ranks, kind="stable")
                ids, seqs = ids[order], seqs[order]
                if last != (s, w - 1):
                    memos = {}
                last, lo = (s, w), w * slide.step + slide.origin
                for size, q in enumerate([len(ids)] if quotas is None else quotas[w, s]):
                    for refill in refills:
                        i, at = memos.get((size, refill), (ids[:0], seqs[:0]))
                        i, at = i[at >= lo], at[at >= lo]
                        if len(i) > q:  # only then does it matter which
                            u = np.array([priority_value(seed, x, w) for x in i.tolist()], dtype=np.int64)
                            keep = np.lexsort((i, u))[:q]
                            i, at = i[keep], at[keep]
                        new = np.flatnonzero(~np.isin(ids[:q], i))
                        if refill != "hash":
                            new = new[np.argsort(seqs[new] if refill == "sample_order" else -(seqs[new] // pane), kind="stable")]
                        new, known = new[: q - len(i)], len(i)
                        i, at = np.concatenate([i, ids[new]]), np.concatenate([at, seqs[new]])
                        memos[size, refill] = i, at
                        out.append((w, s, refill, size, len(i), known, int((at >= lo + slide.step).sum())))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    names = ["window_id", "stratum", "refill", "size", "needed", "known", "alive"]
    kinds = [pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
    packed = fresh.groupBy("window_id", "stratum").agg(*[F.collect_list(c).alias(t) for c, t in (("item_id", "ids"), ("seq", "seqs"), ("rank", "ranks"))])
    dealt = packed.repartition("stratum").sortWithinPartitions("stratum", "window_id")
    return dealt.mapInArrow(run, "window_id long, stratum string, refill string, size int, needed long, known long, alive long")


def window_runs(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    held = None
    for pdf in batches:
        pdf = pdf if held is None else pd.concat([held, pdf], ignore_index=True)
        if not len(pdf):
            continue
        change = ((pdf["window_id"] != pdf["window_id"].shift()) | (pdf["stratum"] != pdf["stratum"].shift())).to_numpy().nonzero()[0]
        for a, b in zip(change[:-1], change[1:], strict=True):
            yield pdf.iloc[a:b]
        held = pdf.iloc[change[-1] :]
    if held is not None and len(held):
        yield held


def overlap_with_previous(samples: DataFrame, step: int) -> DataFrame:
    """Adds `known`: the item was also in the sample of the window before (and is still inside)."""
    before = samples.select((F.col("window_id") + 1).alias("window_id"), "stratum", "item_id").withColumn("_k", F.lit(True))
    return samples.join(before, ["window_id", "stratum", "item_id"], "left").withColumn("known", F.coalesce("_k", F.lit(False))).drop("_k")
