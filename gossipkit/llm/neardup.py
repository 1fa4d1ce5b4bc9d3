"""MinHash near-dedup: SuperMinHash signatures, banding, exact verification, union-find grouping.

1. Each text gives its shingle set's size, digest and band keys. Texts of equal sets form a class at once.
2. Classes that share a band key are compared with the band bucket's pivot, the class that shares most band
   keys; a bucket of n classes gives n - 1 pairs, not n^2. Similarities are exact, on full sets.
3. What a pivot can't connect is compared exactly as well: within the classes of one pivot, those still in
   different components meet in blocks of BLOCK x BLOCK sets; a block returns a spanning forest of its links.
   As any two classes of one bucket share its pivot, no link between bucket mates is lost.
4. Components are the closure of all links; the smallest id of each stays.

With 30 bands of 5 rows a pair at similarity 0.85 misses every bucket with probability 2.3e-8.

Defined cases: a null text or one without words has an empty set and no links; with fewer words than a shingle
the whole sequence is the shingle; rows that share an id are one node; a null id takes no part and is kept;
an empty table gives no rows. Columns of the input are not read but for id and text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spread, stored
from .graph import components
from .minhash import bands, set_keys, shingle_sets, signatures
from .textkernel import U, chunks

BANDS, ROWS = 30, 5
THRESHOLD = (85, 100)
#: A share of a group in the residual comparison has about so many sets and so many shingles at most.
BLOCK, BLOCK_SHINGLES, SALT = 1024, 1 << 20, 16
#: A pivot meets its classes in tasks of about so many.
STAR = 1024
#: Characters of text that are hashed at once in a task, whatever the batch.
CHARACTERS = 1 << 19


def signed(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, the set's digest (ka, kb) and band keys for rows (doc_id, text)."""

    def sign(batches):
        for t in batches:
            texts = t["text"].to_pylist()
            for lo, hi in chunks(texts, CHARACTERS):
                keys, offsets = shingle_sets(texts[lo:hi])
                n = np.diff(offsets)
                ka, kb = set_keys(keys, offsets)
                made = bands(signatures(keys, offsets, BANDS * ROWS), ROWS)
                size = np.where(n > 0, BANDS, 0)
                flat = pa.array(made[n > 0].ravel().view(np.int64))
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), flat)
                cols = [t["doc_id"].slice(lo, hi - lo), pa.array(n), pa.array(ka.view(np.int64)), pa.array(kb.view(np.int64)), lists]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_shingles", "ka", "kb", "bands"])

    return docs.mapInArrow(sign, "doc_id long, n_shingles long, ka long, kb long, bands array<long>")


def sets(docs: DataFrame) -> DataFrame:
    """id and shingle set, as ascending 64-bit keys, for rows (id, text)."""

    def make(batches):
        for t in batches:
            texts = t["text"].to_pylist()
            for lo, hi in chunks(texts, CHARACTERS):
                keys, offsets = shingle_sets(texts[lo:hi])
                body = pa.array([keys[a:b].tobytes() for a, b in zip(offsets, offsets[1:], strict=False)], pa.binary())
                yield pa.RecordBatch.from_arrays([t["id"].slice(lo, hi - lo), body], ["id", "body"])

    return docs.mapInArrow(make, "id long, body binary")


def star_pairs(classes: DataFrame) -> DataFrame:
    """(p, u, n): each class u beside the pivots p of its band buckets, for rows (rep, bands); n is the size of the
    largest bucket that they share."""
    placed = classes.select("rep", F.explode("bands").alias("h"))
    shared = placed.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    # a bucket's size or pivot is one row, so a bucket with many classes is split by the skewed join
    placed = stored(placed.join(shared, "h"), "buckets")
    weight = placed.groupBy("rep").agg(F.sum("n").alias("w"))
    placed = placed.join(weight, "rep")
    pivot = placed.groupBy("h").agg(F.max(F.struct("w", (-F.col("rep")).alias("r"))).alias("top")).select("h", (-F.col("top.r")).alias("p"))
    return placed.join(pivot, "h").filter("rep <> p").groupBy("p", F.col("rep").alias("u")).agg(F.max("n").alias("n"))


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    return len(np.intersect1d(a, b, assume_unique=True))


def tasks(n: str, each: int) -> Column:
    return F.ceil(F.col(n) / F.lit(each)).cast("int")


def verified(pairs: DataFrame, bodies: DataFrame) -> DataFrame:
    """(p, u, linked) with the exact similarity of the full sets. The classes of a pivot are dealt over tasks, the
    pivot's set goes to each of them."""
    salted = pairs.withColumn("salt", F.pmod(F.xxhash64("u"), tasks("n", STAR)).cast("int"))
    pivots = pairs.groupBy("p").agg(F.max("n").alias("n")).join(bodies.select(F.col("id").alias("p"), F.col("body").alias("bp")), "p")
    pivots = pivots.select("p", "bp", F.explode(F.sequence(F.lit(0), tasks("n", STAR) - 1)).alias("salt"))
    both = salted.join(bodies.select(F.col("id").alias("u"), F.col("body").alias("bu")), "u").join(pivots, ["p", "salt"])

    def compare(batches):
        for t in batches:
            ok = []
            for x, y in zip(t["bp"], t["bu"], strict=True):
                a, b = (np.frombuffer(v.as_buffer(), U) for v in (x, y))
                common = overlap(a, b) if min(len(a), len(b)) * THRESHOLD[1] >= max(len(a), len(b)) * THRESHOLD[0] else 0
                ok.append(_linked(common, len(a), len(b)))
            yield pa.RecordBatch.from_arrays([t["p"], t["u"], pa.array(ok, pa.bool_())], ["p", "u", "linked"])

    return both.mapInArrow(compare, "p long, u long, linked boolean")


def _linked(common, a, b):
    return THRESHOLD[1] * common >= THRESHOLD[0] * (a + b - common)


def forest(ids: list[int], bodies: list[bytes], component: list[int]) -> list[tuple[int, int]]:
    """Links of these sets that join components, as a spanning forest: postings count the common shingles."""
    arrays = [np.frombuffer(b, U) for b in bodies]
    size = np.array([len(a) for a in arrays])
    keys, inverse = np.unique(np.concatenate(arrays), return_inverse=True)
    owner = np.repeat(np.arange(len(arrays)), size)
    order = np.argsort(inverse, kind="stable")
    posting, start = owner[order], np.searchsorted(inverse[order], np.arange(len(keys) + 1))
    ends = np.cumsum(size)
    root = {c: c for c in component}

    def find(c):
        while root[c] != c:
            root[c] = c = root[root[c]]
        return c

    out = []
    for i in range(len(arrays)):
        mine = inverse[ends[i] - size[i] : ends[i]]
        n = start[mine + 1] - start[mine]
        at = np.repeat(start[mine] - np.cumsum(n) + n, n) + np.arange(n.sum())
        common = np.bincount(posting[at], minlength=len(arrays))
        for j in np.flatnonzero(_linked(common, size[i], size)):
            if j != i and (a := find(component[i])) != (b := find(component[j])):
                root[max(a, b)] = min(a, b)
                out.append((ids[i], ids[j]))
    return out


def residual(checked: DataFrame, bodies: DataFrame, label: DataFrame, sizes: DataFrame) -> DataFrame:
    """Links (a, b) between classes of one pivot that are in different components so far. sizes: (u, n_shingles)."""
    member = checked.select("p", "u").union(checked.select("p", F.col("p").alias("u"))).distinct()
    member = member.join(label.select(F.col("id").alias("u"), "component"), "u", "left").withColumn("component", F.coalesce("component", "u"))
    # pivots are compared with all; a group matters if two others are in different components
    member = member.filter("u <> p").join(sizes, "u")
    shares = F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK), F.ceil(F.sum("n_shingles") / BLOCK_SHINGLES)).cast("int").alias("k")
    groups = member.groupBy("p").agg(shares, F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi")
    # the members of a large group are dealt over SALT tasks
    groups = groups.select("p", "k", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("salt"))
    member = member.withColumn("salt", F.pmod(F.xxhash64("u"), F.lit(SALT)).cast("int")).join(groups.hint("merge"), ["p", "salt"])
    own = F.pmod(F.xxhash64("u"), F.col("k")).cast("int")
    every = F.sequence(F.lit(0), F.col("k") - 1)
    dealt = member.withColumn("g", own).withColumn("o", F.explode(every))
    dealt = dealt.select("p", "u", "component", F.least("g", "o").alias("i"), F.greatest("g", "o").alias("j"))
    full = dealt.join(bodies.select(F.col("id").alias("u"), "body"), "u")

    def meet(t):
        a, b = [], []
        if len(set(c := t["component"].to_pylist())) > 1:
            found = forest(t["u"].to_pylist(), t["body"].to_pylist(), c)
            a, b = [x for x, _ in found], [y for _, y in found]
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return full.groupBy("p", "i", "j").applyInArrow(meet, "a long, b long")


def group(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each row of docs: key, n_shingles, component_id, kept."""
    plain = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    base = stored(signed(plain), "signed")
    linked = base.filter("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = stored(linked.groupBy("ka", "kb", "n_shingles").agg(F.min("doc_id").alias("rep"), F.any_value("bands").alias("bands"), F.count(F.lit(1)).alias("size")), "classes")
    pairs = stored(star_pairs(classes), "pairs")
    wanted = pairs.select(F.col("p").alias("doc_id")).union(pairs.select(F.col("u").alias("doc_id"))).distinct()
    bodies = stored(sets(plain.join(wanted.hint("merge"), "doc_id", "left_semi").select(F.col("doc_id").alias("id"), "text")), "sets")
    checked = stored(verified(pairs, bodies), "checked")
    links = checked.filter("linked").select(F.col("p").alias("a"), F.col("u").alias("b"))
    label = components(links)
    more = stored(residual(checked, bodies, label, classes.select(F.col("rep").alias("u"), "n_shingles")), "residual")
    if not more.isEmpty():
        label = components(links.union(more))
    # classes that stand alone need no row: their texts are their own component
    found = classes.select("ka", "kb", "n_shingles", "rep", "size").join(label.select(F.col("id").alias("rep"), "component"), "rep", "left").filter("size > 1 OR component IS NOT NULL")
    found = found.select("ka", "kb", "n_shingles", F.coalesce("component", "rep").alias("component"))
    out = base.drop("bands").join(found.hint("merge"), ["ka", "kb", "n_shingles"], "left")
    own = F.when(F.col("n_shingles") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id"))
    own = F.when(F.col("doc_id").isNotNull(), own)
    return out.select(F.col("doc_id").alias(key), "n_shingles", own.alias("component_id"), F.coalesce(own == F.col("doc_id"), F.lit(True)).alias("kept"))


def keep_first(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of docs that are the first of their group, all columns."""
    gone = group(docs, key, text).filter(~F.col("kept")).select(key).distinct()
    return docs.join(gone, key, "left_anti").select(*docs.columns)
