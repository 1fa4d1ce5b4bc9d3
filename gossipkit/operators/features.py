"""Workload features from the given tables."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import uniform

LANGS = ["de", "en", "es", "fr"]
#: Texts whose words a task holds apart at once, texts whose words it looks up together, and words whose buckets it remembers.
TEXTS, GROUP, KNOWN = 64, 2048, 1 << 18
#: Places of a planted direction that are drawn before the rows are read.
DRAWN = 128


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^\\p{L}]+"), lambda w: w != "")


def bucket(word: Column, size: int) -> Column:
    return F.pmod(F.conv(F.substring(F.md5(word.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(size)).cast("int")


def hashed_words(docs: DataFrame, size: int = 256) -> DataFrame:
    """(doc_id, feature, n): how often words of each hash bucket occur in a text."""
    each = docs.select("doc_id", F.explode(words(F.col("text"))).alias("w"))
    return each.groupBy("doc_id", bucket(F.col("w"), size).alias("feature")).agg(F.count(F.lit(1)).alias("n"))


def unit_rows(counts: DataFrame, size: int = 256) -> DataFrame:
    """(doc_id, feature, val): unit-length rows, with a bias of 1 at position size."""
    norm = F.sqrt(F.sum(F.col("n") * F.col("n")).over(Window.partitionBy("doc_id")).cast("double"))
    rows = counts.select("doc_id", "feature", F.round(F.col("n") / norm, 9).alias("val"))
    return rows.union(counts.select("doc_id").distinct().select("doc_id", F.lit(size), F.lit(1.0)))


def joined(text: Column) -> Column:
    """The words of a text with one space between them."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), "[^\\p{L}]+", " "))


def copy_group(text: Column) -> Column:
    """Key that exact copies share: the digest of the normalised text."""
    return F.md5(joined(text).cast("binary"))


def split_of(group: Column) -> Column:
    """train, validation or test (6 : 2 : 2) by group, so that copies of a text are on one side."""
    k = F.pmod(F.conv(F.substring(F.md5(group.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(10))
    return F.when(k < 6, "train").when(k < 8, "validation").otherwise("test")


def language_samples(docs: DataFrame, sites: int = 10, size: int = 256) -> DataFrame:
    """(sample_id, site, split, label, idx, val): the language task, one sparse row a text."""
    label = (F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")) - 1).cast("int")
    return _packed(docs.filter(F.col("lang").isin(LANGS)).select("doc_id", label.alias("label"), "text"), sites, size)


def quality_samples(docs: DataFrame, labels: DataFrame, target: str = "quality", sites: int = 10, size: int = 256) -> DataFrame:
    """The binary task quality, or toxic as the negative control."""
    return _packed(docs.join(labels.select("doc_id", F.col(target).cast("int").alias("label")), "doc_id").select("doc_id", "label", "text"), sites, size)


def _packed(docs: DataFrame, sites: int, size: int) -> DataFrame:
    """The unit rows of texts with a word, packed. A text is counted in the task that reads it, so no word is shuffled;
    doc_id is the key of docs. The values are those of unit_rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Buckets(size)
        for t in batches:
            for at in range(0, t.num_rows, GROUP):
                own = t.slice(at, GROUP)
                own = own.filter(pc.not_equal(own["words"], ""))
                counts = _counts(own["words"], size, known)
                yield pa.RecordBatch.from_arrays([*(own[c] for c in ("doc_id", "label", "split")), *counts], ["doc_id", "label", "split", "idx", "n", "squares"])
                if len(known) > KNOWN:
                    known.clear()

    # texts without a word are dropped in the task, where no filter repeats the expression
    told = docs.filter("doc_id IS NOT NULL").withColumn("words", joined(F.col("text")))
    told = told.select("doc_id", "label", split_of(F.md5(F.col("words").cast("binary"))).alias("split"), "words")
    kinds = dict(told.dtypes)
    got = told.mapInArrow(count, f"doc_id {kinds['doc_id']}, label int, split string, idx array<int>, n array<long>, squares long")
    val = F.transform("n", lambda n: F.round(n / F.sqrt(F.col("squares").cast("double")), 9))
    return got.select(
        F.col("doc_id").alias("sample_id"), F.pmod("doc_id", F.lit(sites)).cast("int").alias("site"), "split", "label",
        F.concat("idx", F.array(F.lit(size))).alias("idx"), F.concat(val, F.array(F.lit(1.0))).alias("val"),
    )


class Buckets(dict):
    """The hash bucket of a word's UTF-8 bytes, found when it is first asked for."""

    def __init__(self, size: int):
        self.size = size

    def __missing__(self, word: bytes) -> int:
        k = self[word] = int.from_bytes(hashlib.md5(word).digest()[:4]) % self.size
        return k


def _utf8(words: pa.Array) -> list[bytes]:
    """The words' bytes, cut from their buffer, which is faster than a Python string each."""
    _, ends, body = words.cast(pa.binary()).buffers()
    at, all_of = np.frombuffer(ends, np.int32)[words.offset : words.offset + len(words) + 1].tolist(), body.to_pybytes()
    return [all_of[a:b] for a, b in zip(at, at[1:], strict=False)]


def _counts(texts: pa.Array, size: int, known: Buckets) -> tuple[pa.Array, pa.Array, pa.Array]:
    """For each text of words, the buckets that occur, how often, and the sum of squares. A word is looked up once for all
    texts given; TEXTS of them are split at once and kept as codes."""
    lengths, codes, dictionaries = [], [], []
    for at in range(0, len(texts), TEXTS):
        words = pc.split_pattern(texts.slice(at, TEXTS), " ")
        each = words.flatten().dictionary_encode()
        lengths.append(pc.list_value_length(words).to_numpy(zero_copy_only=False))
        codes.append(each.indices.to_numpy(zero_copy_only=False))
        dictionaries.append(each.dictionary)
    n = np.zeros((len(texts), size), np.int64)
    if dictionaries:
        distinct = pa.concat_arrays(dictionaries).dictionary_encode()
        buckets = np.fromiter(map(known.__getitem__, _utf8(distinct.dictionary)), np.int64, len(distinct.dictionary))
        of, first = buckets[distinct.indices.to_numpy(zero_copy_only=False)], 0
        for i, (ls, c, d) in enumerate(zip(lengths, codes, dictionaries, strict=True)):
            at = np.repeat(np.arange(len(ls)) * size, ls) + of[first : first + len(d)][c]
            n[i * TEXTS : i * TEXTS + len(ls)] = np.bincount(at, minlength=len(ls) * size).reshape(len(ls), size)
            first += len(d)
    at, feature = np.nonzero(n)
    ends = pa.array(np.searchsorted(at, np.arange(len(texts) + 1)), pa.int32())
    lists = (pa.ListArray.from_arrays(ends, pa.array(v, k)) for v, k in ((feature, pa.int32()), (n[at, feature], pa.int64())))
    return *lists, pa.array((n * n).sum(1), pa.int64())


def planted(c: int) -> list[float]:
    """The first places of class c's direction: the numbers of uniform less a half."""
    return [int(hashlib.md5(f"teacher/{c}/{i}".encode()).hexdigest()[:8], 16) / 4294967296.0 - 0.5 for i in range(DRAWN)]


def vector_samples(emb: DataFrame, sites: int = 10, teacher: bool = True, classes: int = 10) -> DataFrame:
    """Embeddings with the stored label, or with a planted one: the direction, out of ten drawn from a hash, that
    points most along the vector."""
    e = F.transform("embedding", lambda x: x.cast("double"))
    df = emb.select("vec_id", F.pmod("vec_id", F.lit(sites)).cast("int").alias("site"), split_of(F.col("vec_id").cast("string")).alias("split"), e.alias("e"), "label")
    if teacher:
        def score(c):
            # the first places are drawn once a plan, those beyond them with each row
            drawn = F.array(*map(F.lit, planted(c)))
            return F.aggregate(F.transform("e", lambda x, i: x * F.coalesce(F.get(drawn, i), uniform("teacher", c, i) - 0.5)), F.lit(0.0), lambda a, b: a + b)

        scores = F.array(*(score(c) for c in range(classes)))
        df = df.withColumn("_s", scores).withColumn("label", (F.array_position("_s", F.array_max("_s")) - 1).cast("int")).drop("_s")
    n = F.size("e")
    return df.select(F.col("vec_id").alias("sample_id"), "site", "split", F.col("label").cast("int").alias("label"), F.sequence(F.lit(0), n).alias("idx"), F.concat("e", F.array(F.lit(1.0))).alias("val"))


TABULAR = ["l_quantity", "l_discount", "l_tax", "l_extendedprice", "o_totalprice", "p_size", "p_retailprice", "l_linenumber"]


def tabular_samples(lineitem: DataFrame, orders: DataFrame, part: DataFrame, sites: int = 10) -> DataFrame:
    """Line items with their order and part: eight standardised columns, planted label by net price."""
    j = lineitem.join(orders.select("o_orderkey", "o_totalprice"), F.col("l_orderkey") == F.col("o_orderkey")).join(part.select("p_partkey", "p_size", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey"))
    stat = lineitem.sparkSession.range(1).crossJoin(j.agg(*(F.avg(c).alias(f"m_{c}") for c in TABULAR), *(F.stddev_pop(c).alias(f"s_{c}") for c in TABULAR)))
    cols = [(F.col(c) - F.col(f"m_{c}")) / F.greatest(F.col(f"s_{c}"), F.lit(1e-12)) for c in TABULAR]
    key = F.col("l_orderkey") * 8 + F.col("l_linenumber")
    return j.crossJoin(F.broadcast(stat.drop("id"))).select(
        key.alias("sample_id"), F.pmod(key, F.lit(sites)).cast("int").alias("site"), split_of(F.col("l_orderkey").cast("string")).alias("split"),
        (F.col("l_extendedprice") * (1 - F.col("l_discount")) > 45000).cast("int").alias("label"), F.sequence(F.lit(0), F.lit(len(TABULAR))).alias("idx"), F.array(*cols, F.lit(1.0)).alias("val"),
    )
