"""Mixing sources to target weights by iterative proportional fitting.

Tokens are summed by cell (source, language, topic). Raking scales the cells until their sums meet the target
shares of every dimension; a cell's factor over its tokens is its documents' weight. One constant turns weights into
prob, the expected number of copies of a document, such that the expected tokens meet the wanted share of all tokens.
It may be above 1: a bound there would take back what raking gave to rare cells. A hash u of the id decides: a
document has as many copies as there are whole numbers k >= 0 with k + u < prob, so it stays if u < prob, and the
draw repeats exactly. With repeats=False prob is at most 1, the share is still met, and the targets are not.

marginals() compares the expected tokens with the targets; plan warns if one is missed by more than MISSED. That
happens without repeats, if targets name values without tokens or contradict one another, or if ROUNDS are too few.

Targets default to shares proportional to tokens^temper in each dimension. The topic is one of TOPICS clusters:
k-means over hashed words, less the mean of the document's language, so that topics aren't languages again. It is fitted
on all documents, whole texts; every one gets the nearest centre. The driver holds a mean for each language and the centres.

Up to MAX_CELLS cells are raked on the driver. Above that the cells stay a table and each half-step is an
aggregate over it.

Defined cases: null source or language counts as the value ''; a text without words has topic 0 and no tokens and
stays as its cell decides; a null language has the mean of all; a cell without tokens has probability 1; a null id draws as the text 'null';
an empty table gives no rows. with_topics and decided replace columns of the names that they add; remixed returns the
input's own columns unchanged, whatever their names.
"""

from __future__ import annotations

import warnings
from collections import defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import stored
from .textkernel import U, Words, chunks

TOPICS, TEMPER, SHARE, ROUNDS, TOLERANCE = 8, 0.7, 0.8, 40, 1e-10
#: The topics' fit: hashed words, most rounds, parts of 1 that sums count in.
FEATURES, FIT_ROUNDS, UNIT = 256, 20, 1 << 24
#: Rows that a pass over stored counts handles at once, so that they stay in the cache.
BLOCK = 1024
MAX_CELLS = 1 << 18
MISSED = 1e-3
DIMS = ["source", "lang", "topic"]


def numbers(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For a range of texts after the other: how many words of each text have each hash, and its words."""
    for a, b in chunks(texts):
        w = Words(texts[a:b], lower=True)
        n = np.bincount(w.doc * FEATURES + (w.hash % U(FEATURES)).astype(np.int64), minlength=(b - a) * FEATURES)
        yield n.reshape(-1, FEATURES), np.diff(w.first)


_DAMPED = np.log1p(np.arange(256)).astype(np.float32)


def damped(n: np.ndarray) -> np.ndarray:
    """Rows of numbers, damped and of length 1."""
    x = _DAMPED.take(n) if n.dtype == np.uint8 else np.log1p(n.astype(np.float64)).astype(np.float32)
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    return x


def packed(n: np.ndarray) -> list[bytes]:
    """Each row in bytes, one a number where all of the row fit, or eight."""
    small = n.max(axis=1, initial=0) < 256
    return [(r.astype(np.uint8) if s else r.astype(np.int64)).tobytes() for r, s in zip(n, small.tolist(), strict=True)]


def unpacked(data: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Rows of numbers from the bytes of packed ones; row i is data[ends[i] : ends[i + 1]]."""
    wide = np.flatnonzero(np.diff(ends) > FEATURES)
    if not len(wide):
        return data[ends[0] : ends[-1]].reshape(-1, FEATURES)
    n = np.empty((len(ends) - 1, FEATURES), np.int64)
    for i in range(len(n)):
        row = data[ends[i] : ends[i + 1]]
        n[i] = row if len(row) == FEATURES else np.frombuffer(row.tobytes(), np.int64)
    return n


def counted(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For a range of texts after the other: rows of hashed word counts, damped and of length 1, and their words."""
    for n, size in numbers(texts):
        yield damped(n), size


class Topics:
    """Cluster centres, and the mean of each language that was seen; the last mean is that of all."""

    def __init__(self, langs: list[str], means: np.ndarray, centres: np.ndarray | None = None):
        self.rows, self.means = {v: i for i, v in enumerate(langs)}, means
        self.centres = np.zeros((0, FEATURES), np.float32) if centres is None else centres

    def away(self, x: np.ndarray, langs: list[str | None], code: np.ndarray | slice = slice(None)) -> np.ndarray:
        """Rows less their languages' means, of length 1; with code, a row's language is langs[code]."""
        x = x - self.means[np.array([self.rows.get(v, len(self.rows)) for v in langs], np.int64)[code]]
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
        return x

    def of(self, x: np.ndarray, langs: list[str | None], code: np.ndarray | slice = slice(None)) -> np.ndarray:
        return (self.away(x, langs, code) @ self.centres.T).argmax(1) if len(self.centres) else np.zeros(len(x), np.int64)


def counts(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", keep: list[str] | None = None) -> DataFrame:
    """Stored: for each document the columns to keep, under their own names, hashes of key and text, the language, its counts
    and its number of words."""
    keep = keep or []
    whole = F.col(text).cast("string")
    plain = docs.select(*keep, F.xxhash64(F.col(key)).alias("_h"), F.xxhash64(whole).alias("_own"), F.col(lang).cast("string").alias("_lang"), whole.alias("_text"))
    made = [T.StructField("_x", T.BinaryType()), T.StructField("_words", T.LongType())]

    def count(batches):
        for t in batches:
            x, n = [], []
            for rows, size in numbers(t["_text"].to_pylist()):
                x += packed(rows)
                n.append(size)
            yield pa.RecordBatch.from_arrays([*t.columns[:-1], pa.array(x, pa.binary()), pa.array(np.concatenate(n) if n else [], pa.int64())], names=[*t.schema.names[:-1], "_x", "_words"])

    return stored(plain.mapInArrow(count, T.StructType([*plain.schema.fields[:-1], *made])), "counts")


def fitted(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", topics: int = TOPICS) -> Topics:
    """K-means over all documents."""
    return clustered(counts(docs, key, text, lang), topics)


def clustered(seen: DataFrame, topics: int = TOPICS) -> Topics:
    """K-means over counts. Each step is a pass over them in Spark's tasks, and the driver gets one row a language, or a centre.
    Sums are of whole numbers (1 / UNIT), so they are the same in any order."""
    total = summed(seen, lambda x, langs, code: (x, code, langs), "string")
    names = sorted(v for v in total if v is not None)
    whole = sum(total.values(), np.zeros(FEATURES + 1))
    out = Topics(names, np.stack([*(_mean(total[v]) for v in names), _mean(whole)]).astype(np.float32))
    first = seen.orderBy("_h", "_own", "_lang").select("_x", "_lang").first()
    start, lang = (damped(unpacked(np.frombuffer(first._x, np.uint8), np.array([0, len(first._x)])))[0], first._lang) if first else (None, None)
    for _ in range(topics):
        if start is None:
            break
        out.centres = np.concatenate([out.centres, out.away(start[None], [lang])])
        start, lang = farthest(seen, out) if len(out.centres) < topics else (None, None)
    for _ in range(FIT_ROUNDS if len(out.centres) else 0):
        last, shared = out.centres, seen.sparkSession.sparkContext.broadcast(out)
        total = summed(seen, lambda x, langs, code, m=shared: ((y := m.value.away(x, langs, code)), (y @ m.value.centres.T).argmax(1), range(len(m.value.centres))), "int")
        shared.unpersist()
        sums = np.stack([total.get(k, np.zeros(FEATURES + 1))[:-1] for k in range(len(last))])
        length = np.linalg.norm(sums, axis=1, keepdims=True)
        out.centres = np.where(length > 0, sums / np.maximum(length, 1e-9), last).astype(np.float32)
        if (out.centres == last).all():
            break
    return out


def _mean(total: np.ndarray) -> np.ndarray:
    return total[:-1] / max(total[-1], 1)


def _read(t: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, list[str | None], np.ndarray]]:
    """Blocks of a batch: the first row's number, the counts, the batch's languages and each row's place among them."""
    if not len(t):
        return
    # the bytes of all rows stand one after the other and are not copied
    data, lang = t["_x"].cast(pa.large_binary()), t["_lang"].dictionary_encode("encode")
    ends = np.frombuffer(data.buffers()[1], np.int64)[data.offset :][: len(data) + 1]
    x, langs, code = np.frombuffer(data.buffers()[2], np.uint8), lang.dictionary.to_pylist(), lang.indices.to_numpy()
    for a in range(0, len(t), BLOCK):
        yield a, damped(unpacked(x, ends[a : a + BLOCK + 1])), langs, code[a : a + BLOCK]


def summed(seen: DataFrame, of, kind: str) -> dict:
    """Sums of rows by key, their number at the end; of(x, langs, code) gives rows, each one's place among the keys, and the keys."""

    def partial(batches):
        total: dict = {}
        for t in batches:
            for _, *block in _read(t):
                x, at, keys = of(*block)
                used, at = np.unique(at, return_inverse=True)
                one = np.zeros((len(used), len(x)))
                one[at, np.arange(len(x))] = 1
                # whole numbers far below 2^53, so the product is exact
                sums = np.column_stack([one @ np.rint(x * np.float64(UNIT)), one.sum(1)]).astype(np.int64)
                for k, n in zip(used, sums, strict=True):
                    total[keys[k]] = total.get(keys[k], 0) + n
        cols = [pa.array([k for k in total for _ in range(FEATURES + 1)], pa.string() if kind == "string" else pa.int32()), pa.array(np.tile(np.arange(FEATURES + 1, dtype=np.int32), len(total)))]
        yield pa.RecordBatch.from_arrays([*cols, pa.array(np.concatenate([*total.values(), np.zeros(0, np.int64)]).astype(np.int64))], ["k", "j", "s"])

    out: dict = {}
    for r in seen.select("_lang", "_x").mapInArrow(partial, f"k {kind}, j int, s long").groupBy("k", "j").agg(F.sum("s").alias("s")).collect():
        out.setdefault(r.k, np.zeros(FEATURES + 1))[r.j] = r.s / (UNIT if r.j < FEATURES else 1)
    return out


def farthest(seen: DataFrame, model: Topics) -> tuple[np.ndarray, str | None]:
    """Counts and language of the document whose nearest centre is farthest; of equals the one of the least hash."""
    shared = seen.sparkSession.sparkContext.broadcast(model)

    def least(batches):
        best = None
        for t in batches:
            h, own = (t[c].to_numpy(zero_copy_only=False) for c in ("_h", "_own"))
            for a, x, langs, code in _read(t):
                score = np.round((shared.value.away(x, langs, code) @ shared.value.centres.T).max(1).astype(float), 5)
                low = np.flatnonzero(score == score.min())
                i = low[np.lexsort((own[a + low], h[a + low]))[0]]
                lang = langs[code[i]]
                row = (float(score[i]), int(h[a + i]), int(own[a + i]), lang or "", x[i].tobytes(), lang)
                best = row if best is None or row[:5] < best[:5] else best
        cols = [[v] for v in best] if best else [[]] * 6
        types = [pa.float64(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.string()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, types, strict=True)], ["score", "h", "own", "name", "x", "lang"])

    row = seen.select("_h", "_own", "_lang", "_x").mapInArrow(least, "score double, h long, own long, name string, x binary, lang string").orderBy("score", "h", "own", "name").first()
    return np.frombuffer(row.x, np.float32), row.lang


def with_topics(docs: DataFrame, text: str = "text", topics: int = TOPICS, key: str = "doc_id", lang: str = "lang") -> DataFrame:
    """docs with topic and n_tokens (words)."""
    docs = docs.drop("topic", "n_tokens")
    shared = docs.sparkSession.sparkContext.broadcast(fitted(docs, key, text, lang, topics))
    schema = T.StructType([*docs.schema.fields, T.StructField("topic", T.IntegerType()), T.StructField("n_tokens", T.LongType())])

    def vote(batches):
        for t in batches:
            langs, at, topic, size = t[lang].cast(pa.string()).to_pylist(), 0, [], []
            for x, n in counted(t[text].to_pylist()):
                topic.append(np.where(n > 0, shared.value.of(x, langs[at : at + len(n)]), 0).astype(np.int32))
                size.append(n)
                at += len(n)
            cols = [pa.array(np.concatenate(topic) if topic else [], pa.int32()), pa.array(np.concatenate(size) if size else [], pa.int64())]
            yield pa.RecordBatch.from_arrays([*t.columns, *cols], names=[*t.schema.names, "topic", "n_tokens"])

    return docs.mapInArrow(vote, schema)


def cells(docs: DataFrame, dims: list[str] = DIMS) -> DataFrame:
    values = [F.coalesce(F.col(d).cast("string"), F.lit("")).alias(d) for d in dims]
    return docs.groupBy(*values).agg(F.sum("n_tokens").cast("double").alias("tokens"))


def tempered(rows: list[tuple], k: int, temper: float = TEMPER) -> dict[str, float]:
    """Target shares of dimension k: proportional to tokens^temper."""
    total: dict[str, float] = defaultdict(float)
    for *key, tokens in rows:
        total[key[k]] += tokens
    power = {v: t**temper for v, t in total.items() if t > 0}
    return {v: p / sum(power.values()) for v, p in power.items()}


def rake(rows: list[tuple], targets: list[dict[str, float]], rounds: int = ROUNDS) -> dict[tuple, float]:
    """Weight of each cell (key..., tokens): weights times tokens sum to the targets in every dimension."""
    total = sum(r[-1] for r in rows)
    weight = {r[:-1]: 1.0 for r in rows if r[-1] > 0}
    tokens = {r[:-1]: r[-1] for r in rows if r[-1] > 0}
    for _ in range(rounds):
        worst = 0.0
        for k, target in enumerate(targets):
            now: dict[str, float] = defaultdict(float)
            for key, w in weight.items():
                now[key[k]] += w * tokens[key]
            scale = {v: target.get(v, 0.0) * total / n if n else 1.0 for v, n in now.items()}
            worst = max([worst, *(abs(s - 1) for s in scale.values())])
            for key in weight:
                weight[key] *= scale[key[k]]
        if worst < TOLERANCE:
            break
    return weight


def rake_table(cell: DataFrame, targets: dict[str, DataFrame], rounds: int = ROUNDS) -> DataFrame:
    """As rake, for cells too many for the driver: targets hold (dimension, target), the result adds weight.
    Each half-step is an aggregate and a join; the table is written anew each round."""
    dims = list(targets)
    total = cell.agg(F.sum("tokens").alias("total"))
    now = cell.filter("tokens > 0").withColumn("weight", F.lit(1.0))
    for _ in range(rounds):
        for d, target in targets.items():
            margin = now.groupBy(d).agg(F.sum(F.col("weight") * F.col("tokens")).alias("_now")).join(target, d, "left").crossJoin(F.broadcast(total))
            margin = margin.select(d, F.when(F.col("_now") > 0, F.coalesce("target", F.lit(0.0)) * F.col("total") / F.col("_now")).otherwise(1.0).alias("_scale"))
            now = now.join(margin, d).withColumn("weight", F.col("weight") * F.col("_scale")).drop("_scale")
        now = stored(now.select(*dims, "tokens", "weight"), "rake")
    return now


def probabilities(tokens: list[float], weight: list[float], share: float = SHARE) -> list[float]:
    """min(1, c * weight) with c such that the expected tokens are share of all, as far as weights above 0 allow."""
    t, w = np.array(tokens), np.array(weight)
    if not len(t) or share >= 1:
        return np.where(w > 0, 1.0, 0.0).tolist()
    want, order = share * t.sum(), np.argsort(-w)
    t, w = t[order], w[order]
    # cells of the largest weights are at 1; the others share what is left in proportion
    full = np.concatenate([[0.0], np.cumsum(t)[:-1]])
    rest = np.cumsum((t * w)[::-1])[::-1]
    with np.errstate(divide="ignore", invalid="ignore"):
        c = (want - full) / rest
    fits = np.flatnonzero((c * w <= 1 + 1e-12) & (rest > 0) & (c >= 0))
    c = c[fits[0]] if len(fits) else np.inf
    p = np.empty(len(t))
    p[order] = np.where(w > 0, np.minimum(1.0, c * np.where(w > 0, w, 1)), 0.0)
    return p.tolist()


def draw(key: Column, seed: int = 42) -> Column:
    """A number in [0, 1) from the id."""
    text = F.concat_ws("/", F.coalesce(key.cast("string"), F.lit("null")), F.lit(str(seed)))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / float(1 << 32)


def copies(tokens: list[float], weight: list[float], share: float = SHARE) -> list[float]:
    """c * weight with c such that the expected tokens are share of all; the proportions of the weights stay."""
    t, w = np.array(tokens), np.array(weight)
    mass = (t * w).sum()
    return (w * (share * t.sum() / mass if mass > 0 else 0.0)).tolist()


def target_tables(cell: DataFrame, targets: dict[str, dict[str, float]] | None, dims: list[str]) -> dict[str, DataFrame]:
    tables = {}
    for d in dims:
        if targets and targets.get(d):
            tables[d] = cell.sparkSession.createDataFrame(list(targets[d].items()), f"{d} string, target double")
        else:
            power = cell.groupBy(d).agg(F.sum("tokens").alias("t")).filter("t > 0").withColumn("t", F.pow("t", F.lit(TEMPER)))
            tables[d] = power.crossJoin(F.broadcast(power.agg(F.sum("t").alias("all")))).select(d, (F.col("t") / F.col("all")).alias("target"))
    return tables


def marginals(cell: DataFrame, targets: dict[str, dict[str, float]] | None = None, dims: list[str] = DIMS) -> DataFrame:
    """(dim, value, share, target, got) of planned cells: shares of the tokens before, wanted and expected after."""
    all_ = F.broadcast(cell.agg(F.sum("tokens").alias("_t"), F.sum(F.col("tokens") * F.col("prob")).alias("_p")))
    out = []
    for d, target in target_tables(cell, targets, dims).items():
        now = cell.groupBy(d).agg(F.sum("tokens").alias("t"), F.sum(F.col("tokens") * F.col("prob")).alias("p")).join(target, d, "full").crossJoin(all_)
        share, got = (F.coalesce(F.col(a) / F.nullif(F.col(b), F.lit(0.0)), F.lit(0.0)) for a, b in (("t", "_t"), ("p", "_p")))
        out.append(now.select(F.lit(d).alias("dim"), F.col(d).alias("value"), share.alias("share"), F.coalesce("target", F.lit(0.0)).alias("target"), got.alias("got")))
    return reduce(DataFrame.unionByName, out)


def planned(cell: DataFrame, targets: dict[str, dict[str, float]] | None, dims: list[str]) -> DataFrame:
    """cell, with a warning if a target is missed."""
    worst = marginals(cell, targets, dims).select("dim", "value", F.abs(F.col("got") - F.col("target")).alias("off")).orderBy(F.desc("off")).first()
    if worst and worst.off > MISSED:
        warnings.warn(f"mixing misses a target: {worst.dim} '{worst.value}' by {worst.off:.4f}", stacklevel=3)
    return cell


def plan(docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, share: float = SHARE, dims: list[str] = DIMS, rounds: int = ROUNDS, repeats: bool = True) -> DataFrame:
    """Cells with tokens, weight and prob."""
    spark, cell = docs.sparkSession, stored(cells(docs, dims), "cells")
    if cell.count() <= MAX_CELLS:
        rows = sorted(tuple(r) for r in cell.collect())
        aims = [(targets or {}).get(d) or tempered(rows, k) for k, d in enumerate(dims)]
        weight = rake(rows, aims, rounds)
        known = [r for r in rows if r[:-1] in weight]
        prob = dict(zip([r[:-1] for r in known], (copies if repeats else probabilities)([r[-1] for r in known], [weight[r[:-1]] for r in known], share), strict=True))
        made = [(*r, weight.get(r[:-1], 1.0), prob.get(r[:-1], 1.0)) for r in rows]
        return planned(spark.createDataFrame(made, ", ".join(f"{d} string" for d in dims) + ", tokens double, weight double, prob double"), targets, dims)
    raked = rake_table(cell, {d: stored(t, "target") for d, t in target_tables(cell, targets, dims).items()}, rounds)
    all_tokens = cell.agg(F.sum("tokens")).first()[0] or 0.0
    if repeats:
        mass = raked.agg(F.sum(F.col("tokens") * F.col("weight"))).first()[0] or 0.0
        prob = F.lit(share * all_tokens / mass if mass > 0 else 0.0) * F.col("weight")
    else:
        # the constant by bisection on one aggregate each
        lo, hi = 0.0, 1e9
        for _ in range(60):
            c = (lo * hi) ** 0.5 if lo else hi / 2**20
            got = raked.agg(F.sum(F.col("tokens") * F.least(F.lit(1.0), F.lit(c) * F.col("weight")))).first()[0]
            lo, hi = (c, hi) if got < share * all_tokens else (lo, c)
        prob = F.least(F.lit(1.0), F.lit(hi) * F.col("weight"))
    known = raked.withColumn("prob", prob)
    return planned(stored(cell.join(known.select(*dims, "weight", "prob"), dims, "left").fillna(1.0, ["weight", "prob"]), "planned"), targets, dims)


def decided(docs: DataFrame, cell: DataFrame, key: str = "doc_id", dims: list[str] = DIMS) -> DataFrame:
    """docs with prob, kept and copies. The cells are broadcast up to MAX_CELLS rows, otherwise joined by shuffle."""
    small = cell.select(*(F.col(d).alias(f"_{d}") for d in dims), F.col("prob").alias("_prob"))
    small = F.broadcast(small) if cell.count() <= MAX_CELLS else small
    same = [F.coalesce(F.col(d).cast("string"), F.lit("")) == F.col(f"_{d}") for d in dims]
    out = docs.drop("prob", "kept", "copies").join(small, same, "left").withColumn("prob", F.coalesce("_prob", F.lit(1.0))).drop("_prob", *(f"_{d}" for d in dims))
    u = draw(F.col(key))
    return out.withColumn("kept", u < F.col("prob")).withColumn("copies", F.greatest(F.ceil(F.col("prob") - u), F.lit(0)).cast("long"))


def sampled(docs: DataFrame) -> DataFrame:
    """The rows of decided docs, each as often as it has copies."""
    return docs.filter("kept").withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).drop("_copy")


def placed(seen: DataFrame, model: Topics) -> DataFrame:
    """The columns that counts kept, with topic and n_tokens; no text is read again."""
    shared, kept = seen.sparkSession.sparkContext.broadcast(model), [c for c in seen.columns if c not in ("_h", "_own", "_lang", "_x", "_words")]
    schema = T.StructType([*seen.select(*kept).schema.fields, T.StructField("n_tokens", T.LongType()), T.StructField("topic", T.IntegerType())])

    def vote(batches):
        for t in batches:
            topic = [shared.value.of(*block) for _, *block in _read(t)]
            topic = np.where(t["_words"].to_numpy() > 0, np.concatenate(topic) if topic else 0, 0).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*t.columns[: len(kept)], t["_words"], pa.array(topic)], names=schema.names)

    return seen.select(*kept, "_words", "_lang", "_x").mapInArrow(vote, schema).select(*kept, "topic", "n_tokens")


def mix(docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, share: float = SHARE, repeats: bool = True) -> DataFrame:
    """One row for each document: doc_id, source, lang, topic, n_tokens, prob, kept, copies."""
    seen = counts(docs, keep=["doc_id", "source", "lang"])
    seen = stored(placed(seen, clustered(seen)), "topics")
    return decided(seen, plan(seen, targets, share, repeats=repeats))


def remixed(docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, share: float = SHARE, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of docs, each as often as it is drawn, with their own columns. Columns have names by place meanwhile,
    which no name of this module meets."""
    own = {c: c if c in ("source", "lang") else f"column{i}" for i, c in enumerate(docs.columns)}
    seen = with_topics(docs.toDF(*own.values()), own[text], key=own[key])
    cell = plan(stored(seen.select("source", "lang", "topic", "n_tokens"), "topics"), targets, share)
    return sampled(decided(seen, cell, own[key])).select(*(F.col(o).alias(c) for c, o in own.items()))
