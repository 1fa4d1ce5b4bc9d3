"""Language identification by cross-parsing.

For each language a suffix automaton holds all substrings of a bounded sample of labelled text. A text is parsed
greedily into the longest phrases that occur in that sample; the language that needs the fewest phrases per
symbol wins. Texts are parsed whole, in blocks of BLOCK symbols that run side by side as lanes of one table walk.

Symbols: lower-cased letters that occur in the samples; every other letter is one symbol that no sample holds;
a run of other characters is one space.

The fit reads SAMPLE_DOCS documents of each language, those of the least hash of the id, and of each
at most DOC_SYMBOLS symbols; all of them enter the automaton. A language with less text has a smaller automaton,
so its parses are longer; phrase counts are not normalised for that. Held-out documents and lang are never read by a prediction.

Defined cases: a text that is null or has no letter gives 'und' with score 0; ties go to the first label
in order; without any labelled text every prediction is 'und'; a null id is not held out and not learned from.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SAMPLE_DOCS, DOC_SYMBOLS, BLOCK = 64, 1024, 256
SPACE, LANES = 0, 1 << 16
POINTS = 0x110000


def held_out(key: Column) -> Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def training_sample(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang") -> dict[str, list[str]]:
    """Texts by language: SAMPLE_DOCS documents each, at most."""
    plain = docs.select(F.col(key).alias("k"), F.col(text).alias("t"), F.col(lang).alias("l")).filter(F.col("k").isNotNull() & F.col("l").isNotNull() & F.col("t").isNotNull() & ~held_out(F.col("k")))
    order = Window.partitionBy("l").orderBy(F.xxhash64("k"), "k")
    # the ids are ranked without their texts; a rank limit keeps what is shuffled small
    chosen = plain.select("k", "l").withColumn("r", F.row_number().over(order)).filter(F.col("r") <= SAMPLE_DOCS).select("k", "l", "r")
    rows = plain.join(F.broadcast(chosen), ["k", "l"]).select("l", "r", F.left("t", F.lit(DOC_SYMBOLS * 4)).alias("t")).collect()
    out: dict[str, list[str]] = {}
    for r in sorted(rows, key=lambda r: (r.l, r.r, r.t)):
        out.setdefault(r.l, []).append(r.t)
    return out


def points(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), "<u4")


_letters: np.ndarray | None = None


def letter(p: np.ndarray) -> np.ndarray:
    """Whether each code point is a letter."""
    global _letters
    if _letters is None:
        _letters = np.fromiter((chr(c).isalpha() for c in range(POINTS)), bool, POINTS)
    return _letters[np.minimum(p, POINTS - 1)]


class Symbols:
    def __init__(self, samples: dict[str, list[str]]):
        seen = np.unique(np.concatenate([points("".join(t)) for t in samples.values()] or [np.zeros(0, "<u4")]))
        known = seen[letter(seen)]
        self.of = np.full(POINTS, len(known) + 1, np.uint16)  # a letter of no sample
        self.of[~letter(np.arange(POINTS))] = SPACE
        self.of[known] = np.arange(1, len(known) + 1)
        self.n = len(known) + 2

    def __call__(self, text: str) -> np.ndarray:
        s = self.of[np.minimum(points(text), POINTS - 1)]
        keep = s != SPACE
        keep[1:] |= s[:-1] != SPACE
        return s[keep]


def automaton(s: np.ndarray, n: int) -> np.ndarray:
    """Suffix automaton as a table (state, symbol) -> state or -1. Column n keeps the state: it fills lanes up."""
    nxt: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in s.tolist():
        cur = len(nxt)
        nxt.append({})
        link.append(0)
        length.append(length[last] + 1)
        p = last
        while p >= 0 and c not in nxt[p]:
            nxt[p][c] = cur
            p = link[p]
        if p >= 0:
            q = nxt[p][c]
            if length[q] == length[p] + 1:
                link[cur] = q
            else:
                twin = len(nxt)
                nxt.append(dict(nxt[q]))
                link.append(link[q])
                length.append(length[p] + 1)
                while p >= 0 and nxt[p].get(c) == q:
                    nxt[p][c] = twin
                    p = link[p]
                link[q] = link[cur] = twin
        last = cur
    table = np.full((len(nxt), n + 1), -1, np.int32)
    table[:, n] = np.arange(len(nxt))
    for i, d in enumerate(nxt):
        table[i, list(d)] = list(d.values())
    return table


class Model:
    def __init__(self, samples: dict[str, list[str]]):
        self.labels = sorted(samples)
        self.symbols = Symbols(samples)
        self.tables = []
        for x in self.labels:
            parts = [self.symbols(t)[:DOC_SYMBOLS] for t in samples[x]]
            self.tables.append(automaton(np.concatenate(parts or [np.zeros(0, np.uint16)]), self.symbols.n))

    def phrases(self, texts: list[np.ndarray]) -> np.ndarray:
        """Phrases that each text needs in each language."""
        n = self.symbols.n
        blocks = np.array([-(-len(t) // BLOCK) for t in texts], np.int64)
        lanes = np.full(int(blocks.sum()) * BLOCK, n, np.uint16)
        at = 0
        for t, b in zip(texts, blocks, strict=True):
            lanes[at : at + len(t)] = t
            at += int(b) * BLOCK
        steps = np.ascontiguousarray(lanes.reshape(-1, BLOCK).T)
        owner = np.repeat(np.arange(len(texts)), blocks)
        out = np.zeros((len(texts), len(self.labels)), np.int64)
        for k, table in enumerate(self.tables):
            flat, wide, root = table.ravel(), n + 1, np.maximum(table[0], 0)
            state, count = np.zeros(steps.shape[1], np.int32), np.ones(steps.shape[1], np.int64)
            for s in steps:
                new = flat[state * wide + s]
                stuck = new < 0
                count += stuck
                state = np.where(stuck, root[s], new)
            out[:, k] = np.bincount(owner, count, len(texts))
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        labels, scores = ["und"] * len(texts), [0.0] * len(texts)
        coded: list[np.ndarray] = []
        where: list[int] = []

        def settle():
            if where:
                need = self.phrases(coded)
                best = need.argmin(1)
                share = 1 / np.exp(-0.5 * np.minimum(need - need.min(1, keepdims=True), 1000)).sum(1)
                for i, b, s in zip(where, best, share, strict=True):
                    labels[i], scores[i] = self.labels[b], float(s)
            coded.clear()
            where.clear()

        lanes = 0
        for i, t in enumerate(texts):
            s = self.symbols(t or "")
            if self.labels and (s != SPACE).any():
                coded.append(s)
                where.append(i)
                lanes += -(-len(s) // BLOCK)
                if lanes >= LANES:
                    settle()
                    lanes = 0
        settle()
        return labels, scores


_model: tuple[int, Model] | None = None


def model(samples: dict[str, list[str]]) -> Model:
    """The model of these samples, built once in each Python worker."""
    global _model
    name = hash(tuple((k, *v) for k, v in sorted(samples.items())))
    if _model is None or _model[0] != name:
        _model = (name, Model(samples))
    return _model[1]


def identify(docs: DataFrame, samples: dict[str, list[str]], key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each row of docs: key, held_out, lang_pred, score."""
    plain = docs.select(F.col(key).alias("doc_id"), held_out(F.col(key)).alias("held_out"), F.col(text).cast("string").alias("text"))

    def predict(batches):
        for t in batches:
            lang, score = model(samples).predict(t["text"].to_pylist())
            yield pa.RecordBatch.from_arrays([t["doc_id"], t["held_out"], pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    kind = plain.schema["doc_id"].dataType.simpleString()
    return plain.mapInArrow(predict, f"doc_id {kind}, held_out boolean, lang_pred string, score double").withColumnRenamed("doc_id", key)
