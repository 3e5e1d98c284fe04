"""N-gram Jaccard join by grouped prefixes, exact, with connected components.

Every text becomes the set of its distinct word n-grams (64-bit hashes).  With t = percent / 100, sets that link share at least
t * max(sizes) members.  Stages:

1. Document frequencies of all shingles are counted (packed arrays, one bucket of the hash space per group); the most frequent
   ones, at most `HOT`, go last in the global order, so that passages of many documents stay out of prefixes.
2. Each document keeps an extended prefix of its set (n - ceil(t n) + l members, l = 5 % of n): linked sets share at least l of them.
   Equal sets are one class; classes of equal prefix and size are one group.
3. Groups meet on prefix members.  Groups that share too few members with anybody leave.  In every bucket of a member, pairs must
   agree in size, and a parity bitmap of the set bounds the symmetric difference from below (of a group of several classes only the bits
   that all its sets agree on count); what passes is joined to the smallest of its company, so a bucket of thousands gives thousands of edges and
   not millions.
4. Connected candidates form families.  Families are expanded to the representatives of their classes, and their whole texts verified
   exactly inside each family; links again leave as one edge for each document.
5. Components of the links give the smallest reachable document; copies follow their class.

Buckets and families of any size (`joined_up`): each is dealt into blocks of bounded size, and each row goes to one block.  What the blocks
join has one label.  Where a bucket or family still has several, representatives of the labels meet in further blocks, as long as that joins labels; what is open then is
closed exactly: the rows outside the largest label travel to all blocks.  So a family of S near copies costs about S rows and not
S * S / block, and no pair is left out.  Filters never lose a link.  Texts are shuffled once, to meet their families, and again (those of
families only) to meet each other.  Joins that grow with the texts shuffle at every size; those of edges and labels are left to Spark.

Defined cases: null or empty texts have empty sets, link with nothing and are their own component; texts of fewer than n words are one
shingle; repeated rows are members of one class; rows of one id and unlike texts count as one document; a null id gets a size, but no links and
a null component; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import dropped, per_salt, salt, salts_seen, shuffled, staged, table
from .repeats import gram_hashes, mixed, word_hashes

#: Frequent shingles that are ordered last, at most (8 MB).
HOT = 500_000
#: From this document frequency on a shingle may count as frequent.
FREQUENT = 24
#: Rows of a bucket, documents of a family and shingles of a family that meet in one block, at about.
BUCKET_BLOCK, FAMILY_BLOCK, FAMILY_SHINGLES = 1500, 1000, 2_000_000
FLUSH = 4_000_000
#: Bits of a shingle that are counted within a bucket.  Shingles that agree in these count together, which only moves them in the order.
LOW_BITS = 24
#: Bits of the bitmaps: a power of two, at least the size of the set, between these.
LEAST_BITS, MOST_BITS = 256, 4096


def shingles(text: str | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of the word n-grams of a whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = word_hashes(words)
    return np.unique(gram_hashes(h, n, 7)) if len(h) >= n else gram_hashes(h, len(h), 100 + len(h))


def texts_of(batch) -> tuple[list, list]:
    return batch.column(0).to_pylist(), batch.column(1).to_pylist()


# --- frequencies -----------------------------------------------------------------------------------------------------


def counted(batches, n: int, bits: int):
    """doc_id, text -> bucket (leading bits), steps between the next LOW_BITS bits in ascending order, counts; a flush every FLUSH shingles."""

    def flush(held):
        tok, cnt = np.unique(np.concatenate(held) >> np.uint64(64 - LOW_BITS - bits), return_counts=True)
        bucket = (tok >> np.uint64(LOW_BITS)).astype(np.int64)
        edges = np.flatnonzero(np.diff(bucket)) + 1
        starts, ends = np.concatenate([[0], edges]), np.concatenate([edges, [len(tok)]])
        low, cnt = (tok & np.uint64((1 << LOW_BITS) - 1)).astype(np.int64), np.minimum(cnt, 65535).astype(np.uint16)
        packed = [stepped(low[a:b], cnt[a:b]) for a, b in zip(starts, ends, strict=True)]
        return pa.RecordBatch.from_arrays(
            [pa.array(bucket[starts].astype(np.int32)), pa.array([p[0] for p in packed], pa.binary()), pa.array([p[1] for p in packed], pa.binary())], ["bucket", "tokens", "counts"]
        )

    held, size = [], 0
    for batch in batches:
        for text in batch.column(1).to_pylist():
            s = shingles(text, n)
            if len(s):
                held.append(s)
                size += len(s)
            if size >= FLUSH:
                yield flush(held)
                held, size = [], 0
    if held:
        yield flush(held)


def stepped(low: np.ndarray, cnt: np.ndarray) -> tuple[bytes, bytes]:
    """Steps between ascending numbers as 16-bit values; a longer step gets entries of count 0 on the way."""
    steps = np.diff(low, prepend=0)
    extra = steps >> 16
    if extra.any():
        at = np.repeat(np.arange(len(steps)), extra)
        steps = np.insert(steps - extra * 65535, at, 65535)
        cnt = np.insert(cnt, at, 0)
        while (steps > 65535).any():  # 65536 * k is a little more than 65535 * k
            at = np.flatnonzero(steps > 65535)
            steps[at] -= 65535
            steps, cnt = np.insert(steps, at, 65535), np.insert(cnt, at, 0)
    return steps.astype(np.uint16).tobytes(), cnt.tobytes()


def merged(key, pdf, least: int):
    tok = np.concatenate([np.cumsum(np.frombuffer(x, np.uint16).astype(np.int64)) for x in pdf["tokens"]])
    cnt = np.concatenate([np.frombuffer(x, np.uint16) for x in pdf["counts"]]).astype(np.int64)
    order = np.argsort(tok, kind="stable")
    tok, cnt = tok[order], cnt[order]
    starts = np.concatenate([[0], np.flatnonzero(np.diff(tok)) + 1])
    total = np.add.reduceat(cnt, starts)
    keep = total >= least
    return pd.DataFrame({"token": (np.int64(key[0]) << LOW_BITS) + tok[starts][keep], "df": total[keep]})


def frequent_shingles(texts: DataFrame, n: int):
    """(leading bits used, sorted tokens, their order class) of the most frequent shingles; at most HOT."""
    size = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = min(20, max(4, int(size / 6 / 1_000_000).bit_length()))  # about a million shingles a bucket
    packed = texts.mapInArrow(lambda it: counted(it, n, bits), "bucket int, tokens binary, counts binary")
    found = staged(packed.groupBy("bucket").applyInPandas(lambda key, pdf: merged(key, pdf, FREQUENT), "token long, df long"), "jaccard-frequent")
    steps = sorted(((r[0], r[1]) for r in found.groupBy(F.floor(F.log2("df") * 4).alias("step")).count().collect()), reverse=True)
    taken, least = 0, None
    for step, count in steps:
        if taken + count > HOT:
            break
        taken, least = taken + count, step
    if least is None:
        return bits, np.zeros(0, np.uint64), np.zeros(0, np.uint8)
    rows = found.where(F.floor(F.log2("df") * 4) >= least).toPandas().sort_values("token")
    return bits, rows["token"].to_numpy().astype(np.uint64), np.floor(np.log2(rows["df"].to_numpy())).astype(np.uint8)


# --- documents -------------------------------------------------------------------------------------------------------


def needed(n, percent: int):
    """Members that a linked set shares at least: ceil(percent * n / 100)."""
    return -(-percent * n // 100)


def bitmap(s: np.ndarray) -> bytes:
    """Parity bitmap; equal members cancel, so differing bits never outnumber differing members."""
    bits = min(MOST_BITS, max(LEAST_BITS, 1 << max(0, len(s) - 1).bit_length()))
    ones = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(ones.astype(np.uint8), bitorder="little").tobytes()


def fingerprint(s: np.ndarray) -> tuple[int, int]:
    with np.errstate(over="ignore"):
        return int(mixed(s + np.uint64(11)).sum(dtype=np.uint64).view(np.int64)), int(np.bitwise_xor.reduce(mixed(s ^ np.uint64(0xA5A5A5A5A5A5A5A5)), initial=np.uint64(0)).view(np.int64))


def profiled(batches, n: int, percent: int, hot):
    """doc_id, text -> doc_id, size, fingerprint, prefix fingerprint, prefix, heat (log2 of the frequency of its frequent members, else 0), bitmap."""
    for batch in batches:
        bits, hot_tokens, hot_class = hot.value
        cols = {k: [] for k in ("doc_id", "n", "f1", "f2", "pf", "prefix", "heat", "bits")}
        for doc, text in zip(*texts_of(batch), strict=True):
            s = shingles(text, n)
            size = len(s)
            prefix, heat = s, np.zeros(len(s), np.uint8)
            if size:
                length = size - int(needed(size, percent)) + max(1, size // 20)
                if len(hot_tokens):
                    short = s >> np.uint64(64 - LOW_BITS - bits)
                    at = np.minimum(np.searchsorted(hot_tokens, short), len(hot_tokens) - 1)
                    order = np.where(hot_tokens[at] == short, hot_class[at], 0)
                    chosen = np.argsort(order, kind="stable")[:length]
                    prefix, heat = s[chosen], order[chosen]
                else:
                    prefix, heat = s[:length], heat[:length]
            f1, f2 = fingerprint(s)
            for k, v in zip(cols, (doc, size, f1, f2, fingerprint(prefix)[0], prefix.view(np.int64), heat.astype(np.int8), bitmap(s)), strict=True):
                cols[k].append(v)
        kinds = [pa.int64()] * 5 + [pa.list_(pa.int64()), pa.list_(pa.int8()), pa.binary()]
        yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols.values(), kinds, strict=True)], list(cols))


# --- candidates ------------------------------------------------------------------------------------------------------


def runs_of(batches, keys: list[str]):
    """Consecutive rows of equal keys, across batches, as pandas frames."""
    held = None
    for pdf in batches:
        if held is not None:
            pdf = pd.concat([held, pdf], ignore_index=True)
        if not len(pdf):
            continue
        change = np.zeros(len(pdf), bool)
        for k in keys:
            v = pdf[k].to_numpy()
            change[1:] |= v[1:] != v[:-1]
        starts = np.flatnonzero(change)
        edges = np.concatenate([[0], starts])
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            yield pdf.iloc[a:b]
        held = pdf.iloc[edges[-1] :]
    if held is not None and len(held):
        yield held


def folded(column: pa.Array, widths: list[int], fold: np.ufunc, empty: int) -> tuple[np.ndarray, dict[int, np.ndarray]]:
    """Width in words of each bitmap, and per width all bitmaps at least as wide, folded to it; other rows hold `empty`."""
    offsets = np.frombuffer(column.buffers()[1], np.int32, len(column) + 1 + column.offset)[column.offset :].astype(np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8)
    width = np.diff(offsets) // 8
    widths = widths or np.unique(width).tolist()
    level = {w: np.full((len(column), w), np.uint64(empty)) for w in widths}
    for v in widths:
        rows = np.flatnonzero(width == v)
        raw = np.ascontiguousarray(data[offsets[rows][:, None] + np.arange(v * 8)]).view(np.uint64)
        for w in widths:
            if w <= v:
                level[w][rows] = fold.reduce(raw.reshape(len(rows), v // w, w), axis=1)
    return width, level


class Bitmaps:
    """Parity bitmaps of many groups; a wide one folds to a narrower one by XOR of its parts, so any two compare at the narrower width.

    `known` marks the bits that all sets of a group agree on (null: it has one set); a folded bit is known if its parts are.
    """

    def __init__(self, bits: pa.Array, known: pa.Array):
        self.width, self.level = folded(bits, [], np.bitwise_xor, 0)
        self.known = None
        if known.null_count < len(known):
            self.known = folded(known, list(self.level), np.bitwise_and, 2**64 - 1)[1]

    def near(self, i: np.ndarray, j: np.ndarray, limit: np.ndarray) -> np.ndarray:
        """Rows i and j differ in at most `limit` bits, at every width that both have."""
        ok = np.ones(len(i), bool)
        least = np.minimum(self.width[i], self.width[j])
        for w in sorted(self.level):
            at = np.flatnonzero(ok & (least >= w))
            if len(at):
                full = self.level[w]
                apart = full[i[at]] ^ full[j[at]]
                if self.known is not None:
                    apart &= self.known[w][i[at]] & self.known[w][j[at]]
                ok[at] = np.bitwise_count(apart).sum(axis=1, dtype=np.int64) <= limit[at]
        return ok


#: Runs up to this length are compared pair by pair, all runs at once; longer ones leave a spanning forest.
SHORT = 6


def candidate_edges(batches, percent: int):
    """g, i, j, v, n, bits, known (sorted by g, i, j) -> edges a < b."""

    def edges(table: pa.Table):
        gid, n = table["v"].to_numpy(), table["n"].to_numpy()
        run = run_numbers(table)
        maps = Bitmaps(*(table[c].combine_chunks() if table[c].num_chunks != 1 else table[c].chunk(0) for c in ("bits", "known")))

        def may_link(i, j):
            ok = (gid[i] != gid[j]) & (100 * np.minimum(n[i], n[j]) >= percent * np.maximum(n[i], n[j]))
            ok[ok] = maps.near(i[ok], j[ok], (100 - percent) * (n[i[ok]] + n[j[ok]]) // (100 + percent))
            return ok

        size = np.bincount(run)
        found = []
        small = size[run] <= SHORT
        for d in range(1, SHORT):
            i = np.flatnonzero(small[:-d] & (run[:-d] == run[d:])) if len(run) > d else np.zeros(0, np.int64)
            keep = may_link(i, i + d)
            found.append((gid[i[keep]], gid[i[keep] + d]))
        starts = np.concatenate([[0], np.cumsum(size)])
        for r in np.flatnonzero(size > SHORT):
            left = np.arange(starts[r], starts[r + 1])
            while len(left):
                stack, left, company = [left[0]], left[1:], [int(gid[left[0]])]
                while stack and len(left):
                    i = stack.pop()
                    near = may_link(np.full(len(left), i), left)
                    company += gid[left[near]].tolist()
                    stack += left[near].tolist()
                    left = left[~near]
                found.append((np.full(len(company), min(company)), np.array(company)))
        a, b = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
        a, b = a[a != b], b[a != b]
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1) if len(a) else np.zeros((2, 0), np.int64)
        return pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], ["a", "b"])

    held = None
    for batch in batches:
        table = pa.Table.from_batches([batch])
        table = table if held is None else pa.concat_tables([held, table]).combine_chunks()
        if not len(table):
            continue
        run = run_numbers(table)
        last = int(np.searchsorted(run, run[-1]))  # the last run may go on in the next batch
        if last:
            yield edges(table.slice(0, last).combine_chunks())
        held = table.slice(last)
    if held is not None and len(held):
        yield edges(held.combine_chunks())


def run_numbers(table: pa.Table) -> np.ndarray:
    """0, 1, … for consecutive rows of equal (g, i, j)."""
    change = np.zeros(len(table), bool)
    for k in ("g", "i", "j"):
        v = table[k].to_numpy()
        change[1:] |= v[1:] != v[:-1]
    return np.cumsum(change)


def joined_up(narrow: DataFrame, meet, tag: str) -> DataFrame:
    """Components of all pairs inside groups that `meet` accepts: v, label.

    narrow(g, v, i, parts, w, …): a row of group g (weight w), dealt into its block i of `parts`.  meet(rows with g, i, j, …) -> edges a, b.
    """
    edges = staged(meet(narrow.withColumn("j", F.lit(0).cast("long"))), f"{tag}-edges")
    labels = components(edges)
    big = narrow.where("parts > 1").drop("text")  # texts come back where rows meet again
    if big.isEmpty():
        return labels
    last, again, closing = None, 0, False
    while not closing:
        again += 1
        labelled = big.join(labels, "v", "left").withColumn("label", F.coalesce("label", "v"))
        sizes = labelled.groupBy("g", "label").agg(F.sum("w").alias("lw"), F.count("*").alias("n"), F.max("parts").alias("p"))
        several = sizes.groupBy("g").agg(F.count("*").alias("_labels"), F.sum("lw").alias("_w"), F.sum("n").alias("_n"), F.max("p").alias("_parts"), F.max(F.struct("lw", "label")).alias("_top"))
        several = staged(several.where("_labels > 1"), f"{tag}-open")
        count = several.agg(F.sum("_labels")).first()[0]
        if count is None:
            return labels
        closing, last = last is not None and count > 0.7 * last, count  # representatives have joined what they can
        rows = labelled.drop("parts", "i").withColumnRenamed("g", "_g").join(several, F.col("_g") == F.col("g")).drop("_g")
        if not closing:  # about a block's worth of rows of the group, as many of each label as of any other
            block = F.ceil(F.col("_n") / F.col("_parts"))
            nth = F.row_number().over(Window.partitionBy("g", "label").orderBy(F.xxhash64("v", F.lit(100 + again)), "v"))
            rows = rows.withColumn("_nth", nth).where(F.col("_nth") <= F.greatest(F.lit(1), F.floor(block / F.col("_labels")))).drop("_nth")
            rows = rows.withColumn("i", F.pmod(F.xxhash64("v", F.lit(200 + again)), F.ceil(F.col("_labels") / block))).withColumn("j", F.lit(0).cast("long"))
        else:  # all rows outside the largest label meet all others
            rows = rows.withColumn("_travels", F.col("label") != F.col("_top.label"))
            rows = rows.withColumn("_tparts", F.greatest(F.lit(1), F.ceil(F.col("_parts") * (F.col("_w") - F.col("_top.lw")) / F.col("_w"))).cast("long"))
            own_i, own_j = F.pmod(F.xxhash64("v", F.lit(13)), "_parts"), F.pmod(F.xxhash64("v", F.lit(14)), "_tparts")
            across = rows.withColumn("i", own_i).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_tparts") - 1)))
            along = rows.where("_travels").withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_parts") - 1))).withColumn("j", own_j)
            rows = across.unionByName(along).drop("_travels", "_tparts").distinct()
        edges = edges.unionByName(staged(meet(rows.drop("_parts", "_labels", "_w", "_n", "_top", "label")), f"{tag}-edges"))
        labels = components(edges)
    return labels


def agreed_bits(sets: DataFrame) -> DataFrame:
    """n, pf, bits of the sets of groups -> n, pf, bits, known: in `known` the bits that all sets of the group agree on."""
    at = F.explode(F.sequence(F.lit(0), (F.octet_length("bits") / 8 - 1).cast("int")))
    words = sets.select("n", "pf", "bits", at.alias("at")).select("n", "pf", "at", F.conv(F.hex(F.substring("bits", F.col("at") * 8 + 1, F.lit(8))), 16, -10).cast("long").alias("word"))
    words = words.groupBy("n", "pf", "at").agg(F.bit_and("word").alias("all"), F.bit_or("word").alias("any"))
    words = words.groupBy("n", "pf").agg(F.sort_array(F.collect_list(F.struct("at", "all", "any"))).alias("w"))  # 64 words at most

    def packed(word):
        return F.unhex(F.array_join(F.transform("w", lambda x: F.lpad(F.hex(word(x)), 16, "0")), ""))

    return words.select("n", "pf", packed(lambda x: x["any"]).alias("bits"), packed(lambda x: F.bitwise_not(x["any"].bitwiseXOR(x["all"]))).alias("known"))


def components(edges: DataFrame) -> DataFrame:
    """Edges a, b -> v, label: the smallest vertex that v reaches, for every vertex of an edge."""
    spark = edges.sparkSession
    both = staged(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "cc-edges")
    labels = staged(both.groupBy(F.col("a").alias("v")).agg(F.min("b").alias("m")).select("v", F.least("v", "m").alias("label")), "cc-labels")
    while True:
        other = labels.select(F.col("v").alias("b"), F.col("label").alias("_l"))
        best = both.join(other, "b").groupBy(F.col("a").alias("v")).agg(F.min("_l").alias("_m"))
        near = staged(labels.join(best, "v").select("v", F.col("label").alias("_was"), F.least("label", "_m").alias("label")), "cc-step")
        jump = near.select(F.col("v").alias("label"), F.col("label").alias("_far"))
        step = staged(near.join(jump, "label", "left").select("v", "_was", F.least("label", F.coalesce("_far", "label")).alias("label")), "cc-step")
        done = step.where("label <> _was").isEmpty()
        dropped(spark, labels._staged_path, near._staged_path)
        labels = step
        if done:
            dropped(spark, both._staged_path)
            return labels.select("v", "label")


# --- verification ----------------------------------------------------------------------------------------------------


def links_of(ids: list[int], sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Components of the linked pairs among the sets, by exact overlaps: (smallest id, id) for each other member."""
    sizes = np.array([len(s) for s in sets])
    member, doc = np.unique(np.concatenate(sets), return_inverse=True)[1], np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(member, kind="stable")
    post = doc[order]
    first = np.concatenate([[0], np.cumsum(np.bincount(member))])
    bounds = np.concatenate([[0], np.cumsum(sizes)])
    left, out = set(range(len(sets))), []
    while left:
        stack = [left.pop()]
        company = list(stack)
        while stack and left:
            i = stack.pop()
            mine = member[bounds[i] : bounds[i + 1]]
            lens = first[mine + 1] - first[mine]
            at = np.repeat(first[mine] - np.concatenate([[0], np.cumsum(lens)[:-1]]), lens) + np.arange(lens.sum())
            shared = np.bincount(post[at], minlength=len(sets))
            linked = np.flatnonzero(100 * shared >= percent * (sizes + sizes[i] - shared))
            for j in linked.tolist():
                if j in left:
                    left.discard(j)
                    company.append(j)
                    stack.append(j)
        low = min(ids[i] for i in company)
        out += {(low, ids[i]) for i in company if ids[i] != low}
    return out


def verified(batches, n: int, percent: int):
    """g, i, j, v, f1, text (sorted by g, i, j) -> links a, b."""
    for run in runs_of(batches, ["g", "i", "j"]):
        ids, sets = [], []
        for rep, f1, text in zip(run["v"], run["f1"], run["text"], strict=True):
            s = shingles(text, n)
            if len(s) and fingerprint(s)[0] == f1:
                ids.append(int(rep))
                sets.append(s)
        if len(ids) > 1 and (found := links_of(ids, sets, percent)):
            yield pd.DataFrame(found, columns=["a", "b"])


def jaccard_components(docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id."""
    spark = docs.sparkSession
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    hot = spark.sparkContext.broadcast(frequent_shingles(texts, words))  # HOT entries at most
    schema = "doc_id long, n long, f1 long, f2 long, pf long, prefix array<bigint>, heat array<tinyint>, bits binary"
    profiles = staged(texts.mapInArrow(lambda it: profiled(it, words, percent, hot), schema), "jaccard-profiles")
    full = profiles.where("n > 0 AND doc_id IS NOT NULL")

    # classes of equal sets; groups of equal prefix and size
    classes = staged(full.groupBy("n", "f1", "f2").agg(F.min("doc_id").alias("rep"), F.first("pf").alias("pf"), F.first("bits").alias("bits"), salts_seen("doc_id").alias("seen")), "jaccard-classes")
    groups = full.groupBy("n", "pf").agg(F.min("doc_id").alias("gid"), *[F.first(c).alias(c) for c in ("prefix", "heat", "bits")])
    groups = staged(groups, "jaccard-groups")
    several = staged(classes.groupBy("n", "pf").agg(F.count("*").alias("k")).where("k > 1").select("n", "pf"), "jaccard-several")
    agreed = agreed_bits(classes.select("n", "pf", "bits").join(shuffled(several), ["n", "pf"]))  # one row per class, however many copies it has
    agreed = staged(agreed.withColumnRenamed("bits", "any"), "jaccard-agreed")

    # members that several groups share, and groups that share enough of them; the rows of a frequent member never meet in one task
    member = groups.select("gid", F.explode(F.arrays_zip("prefix", "heat")).alias("m"))
    spread = F.greatest(F.lit(1), F.ceil(F.pow(F.lit(2.0), F.col("m.heat") + 1) / BUCKET_BLOCK)).cast("int")
    member = member.select(F.col("gid").alias("v"), F.col("m.prefix").alias("g"), spread.alias("spread"))
    member = member.withColumn("b", F.pmod(F.xxhash64("v", F.lit(3)), "spread").cast("int"))
    member = member.withColumn("c", F.count("*").over(Window.partitionBy("g", "b"))).where("c > 1 OR spread > 1")
    split = F.ceil(F.col("c") / BUCKET_BLOCK)
    dealt = F.col("b") + F.col("spread") * F.pmod(F.xxhash64("v", F.lit(4)), split)
    member = staged(member.select("v", "g", dealt.alias("i"), (F.col("spread") * split).alias("parts")), "jaccard-members")
    alive = groups.select(F.col("gid").alias("v"), "n", "pf", "bits").join(shuffled(member.groupBy("v").agg(F.count("*").alias("k"))), "v")
    alive = alive.where(F.col("k") >= F.greatest(F.lit(1), F.floor(F.ceil(F.col("n") * percent / 100) / 20))).join(shuffled(agreed), ["n", "pf"], "left")
    alive = staged(alive.select("v", "n", F.coalesce("any", "bits").alias("bits"), "known"), "jaccard-alive")

    def candidates(rows: DataFrame) -> DataFrame:
        rows = rows.join(shuffled(alive), "v").select("g", "i", "j", "v", "n", "bits", "known").repartition("g", "i", "j").sortWithinPartitions("g", "i", "j")
        return rows.mapInArrow(lambda it: candidate_edges(it, percent), "a long, b long").distinct()

    family = joined_up(member.withColumn("w", F.lit(1)), candidates, "jaccard-candidates")

    # families of groups, expanded to classes
    named = classes.drop("bits", "seen").join(shuffled(groups.select("n", "pf", "gid")), ["n", "pf"])
    alone = named.join(shuffled(several), ["n", "pf"], "left_semi").select("gid").distinct()
    families = family.withColumnRenamed("v", "gid").join(shuffled(alone), "gid", "full_outer").select("gid", F.coalesce("label", "gid").alias("g"))
    members = staged(named.join(shuffled(families), "gid").select(F.col("rep").alias("v"), "f1", F.col("n").alias("w"), "g"), "jaccard-families")
    sizes = members.groupBy("g").agg(F.count("*").alias("s"), F.sum("w").alias("sw")).where("s > 1")
    parts = F.greatest(F.ceil(F.col("s") / FAMILY_BLOCK), F.ceil(F.col("sw") / FAMILY_SHINGLES))
    members = members.join(shuffled(sizes), "g").withColumn("parts", parts).withColumn("i", F.pmod(F.xxhash64("v", F.lit(3)), "parts")).drop("s", "sw")
    whole = texts.where("doc_id IS NOT NULL").select(F.col("doc_id").alias("v"), "text")
    members = staged(members.join(shuffled(whole), "v"), "jaccard-members-of-families")

    def verify(rows: DataFrame) -> DataFrame:
        if "text" not in rows.columns:
            rows = rows.join(shuffled(members.where("parts > 1").select("v", "text")), "v")
        rows = rows.select("g", "i", "j", "v", "f1", "text").repartition("g", "i", "j").sortWithinPartitions("g", "i", "j")
        return rows.mapInPandas(lambda it: verified(it, words, percent), "a long, b long").distinct()

    label = joined_up(members, verify, "jaccard-links")

    # smallest document of each component
    label = label.withColumnRenamed("v", "rep")
    named = classes.join(shuffled(label), "rep", "left").select("n", "f1", "f2", "seen", F.coalesce("label", "rep").alias("component_id"))
    named = per_salt(staged(named, "jaccard-named"), "seen")
    out = profiles.select("doc_id", "n", "f1", "f2", salt("doc_id").alias("_salt")).join(shuffled(named), ["n", "f1", "f2", "_salt"], "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"), words=4, percent=85)


SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS MATERIALIZED (
  SELECT DISTINCT doc_id, g FROM (
    SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')]
           ELSE list_transform(range(1, len(ws) - 2), lambda i: array_to_string(ws[i:i + 3], ' ')) END) AS g FROM w)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
shared AS (SELECT g FROM s GROUP BY g HAVING count(*) > 1),
c AS MATERIALIZED (SELECT s.doc_id, s.g FROM s JOIN shared USING (g)),
pairs AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM c a JOIN c b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS MATERIALIZED (SELECT x, y FROM pairs JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * k >= 85 * (nx.n + ny.n - k)),
e AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
r(v, u) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.v, e.y FROM r JOIN e ON r.u = e.x)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, m.c AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT v, min(u) AS c FROM r GROUP BY v) m ON m.v = d.doc_id
"""

QUERIES = {"op6_ngram_jaccard": query}
ORACLE_SQL = {"op6_ngram_jaccard": SQL}
