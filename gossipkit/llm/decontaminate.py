"""Benchmark decontamination: CGK walks embed item-sized windows, bit-sampling tables propose, edit distance verifies.

Words are compared lower-cased and without ASCII punctuation; an item of L words is found where some stretch of a
text is within floor(L / 5) word edits of it (none for fewer than six words).

Embedding: a walk stands on a window's first word; at each step a public random bit of step and word decides whether
it moves on. Few edits leave most of two walks equal, so edit distance becomes Hamming distance. The walks of all
windows of a text are one table walk from every word on; an item is embedded from its first word and, if it is long
enough, from its middle as well, so that edits at one end don't hide it.
Tables: for each of WALKS walks TABLES tables sample a few steps each; the words at these steps are the key. Items
fill the tables where the steps stand on different words, windows probe them. A step past the end of a text or item never agrees, but for items without
edits: equal windows have equal walks there, so one table finds them all.
Windows that can't reach an item are not walked: within the allowance a stretch holds at least L - floor(L / 5) words
of the benchmark, which loses nothing. Every window that meets an item in a table is verified: so many words around it
must be the item's own, which loses nothing either, then the edit distance of the item to the best stretch decides. At the largest allowance the tables meet over 99 of 100 leaks (tested).

Items are a bounded broadcast of MAX_WORDS words; a larger benchmark is gone through in blocks of that size, one at a
time on the driver, each a pass over the texts.

Defined cases: a null text, document or item, has no words; an item without words is nowhere; equal items are each
reported; ids may be null or of any type; rows of equal ids are reported one by one; an empty benchmark finds nothing
and an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .textkernel import U, Words, chunks

SHARE, WALKS, TABLES, STEPS = 5, 6, 12, 16
#: Steps in a key for items from EDITED and from TWO_ENTRIES words on.
SAMPLED, SAMPLED_LONG = 3, 4
#: Items of this many words and more take part with edits; from TWO_ENTRIES on they are embedded from their middle too.
EDITED, TWO_ENTRIES = 6, 12
MAX_WORDS = (1 << 21) - 1
#: Candidates whose words are held for one verification.
HELD = 4096
PAD = U(0)
CHARACTERS, CELLS = 1 << 18, 1 << 21


def allowed(n):
    return np.where(n >= EDITED, n // SHARE, 0)


def moves(h: np.ndarray, r: int) -> np.ndarray:
    """The bits of walk r for words of these hashes: bit j says whether step j moves on. PAD has none."""
    return ((h * U(0x9E3779B97F4A7C15 + 0xD1B54A32D192ED02 * r & (2**64 - 1))) >> U(32)).astype(np.int64)


def walk(v: np.ndarray, bits: np.ndarray, at: np.ndarray, steps: int, stop: np.ndarray | None = None) -> list[np.ndarray]:
    """The word that each walk stands on at each step: v's values from the places at on; from stop on 0."""
    at, out, go = at.copy(), [], np.empty(len(at), np.int64)
    for j in range(steps):
        out.append(v.take(at) if stop is None else np.where(at < stop, v.take(at), 0))
        np.right_shift(bits.take(at, out=go, mode="clip"), j, out=go)
        at += np.bitwise_and(go, 1, out=go)
    return out


def nearest(items: np.ndarray, sizes: np.ndarray, around: np.ndarray) -> np.ndarray:
    """Least edit distance of each item to any stretch of the row of words beside it; both are padded with PAD."""
    n, wide = around.shape
    last = np.zeros((wide + 1, n), np.int32)
    best = np.full(n, np.iinfo(np.int32).max, np.int32)
    for i in range(1, items.shape[1] + 1):
        row = np.empty_like(last)
        row[0] = i
        same = (around.T != items[:, i - 1]).astype(np.int32)
        row[1:] = np.minimum(last[:-1] + same, last[1:] + 1)
        for j in range(1, wide + 1):
            np.minimum(row[j], row[j - 1] + 1, out=row[j])
        last = row
        done = sizes == i
        if done.any():
            best[done] = row[:, done].min(0)
    return best


class Tables:
    """The tables of one kind of items: without edits and of one length, or with edits."""

    def __init__(self, sizes: np.ndarray, first: np.ndarray, items: np.ndarray, v: np.ndarray, bits: list[np.ndarray], exact: bool):
        least = int(sizes[items].min())
        self.exact, self.length = exact, least
        self.steps = 2 * least if exact else min(STEPS, 8 * least // 5)
        self.walks = 1 if exact else WALKS
        sampled = SAMPLED_LONG if least >= TWO_ENTRIES else SAMPLED
        mid = items[sizes[items] >= TWO_ENTRIES] if not exact else items[:0]
        self.item = np.concatenate([items, mid])
        self.offset = np.concatenate([np.zeros(len(items), np.int64), sizes[mid] // 2])
        self.spans = [] if exact else self._spans(sizes[items])
        rng = np.random.default_rng(least)
        self.places, self.probe = [], []
        # the words that stand in a key at each step of each walk, as a bit map over the lower bits of their rank
        self.seen = np.zeros((self.walks, self.steps, 1 << 16), bool)
        start = first[self.item] + self.offset
        for r in range(self.walks):
            m = walk(v, bits[r], start, self.steps, (first + sizes)[self.item] if exact else None)
            on = walk(np.arange(len(v)), bits[r], start, self.steps)
            tables = [np.arange(self.steps)] if exact else [np.sort(rng.choice(self.steps, sampled, replace=False)) for _ in range(TABLES)]
            self.places.append(tables)
            self.probe.append([self._filled(r, t, [m[j] for j in t], [on[j] for j in t]) for t in tables])

    @staticmethod
    def _spans(sizes: np.ndarray) -> list[tuple[int, int, int]]:
        """(least, largest, is embedded from the middle) of ranges of lengths: the larger at most a quarter more."""
        out: list[tuple[int, int, int]] = []
        for n in np.unique(sizes).tolist():
            if out and n <= out[-1][0] * 5 // 4 and (n >= TWO_ENTRIES) == out[-1][2]:
                out[-1] = (out[-1][0], n, out[-1][2])
            else:
                out.append((n, n, n >= TWO_ENTRIES))
        return out

    @staticmethod
    def key(words: list[np.ndarray]) -> np.ndarray:
        k = words[0].astype(U)
        for w in words[1:]:
            k = (k ^ (k >> U(29))) * U(0xBF58476D1CE4E5B9) + w.astype(U)
        return k

    def _filled(self, r: int, steps: np.ndarray, words: list[np.ndarray], on: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        apart = [w > 0 for w in words] + [x != y for x, y in zip(on, on[1:], strict=False)]
        use = np.arange(len(words[0])) if self.exact else np.flatnonzero(np.logical_and.reduce(apart))
        words = [w[use] for w in words]
        for j, w in zip(steps, words, strict=True):
            self.seen[r, j, w & 0xFFFF] = True
        k = self.key(words)
        order = np.argsort(k, kind="stable")
        return k[order], use[order]

    def starts(self, known: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Places whose windows can be within the allowance of an item, by the words of the benchmark in them."""
        here = np.arange(len(end))
        if self.exact:
            stop = here + self.length
            return np.flatnonzero((stop <= end) & (known[np.minimum(stop, len(end))] - known[:-1] == self.length))
        mask = np.zeros(len(end), bool)
        for lo, hi, middle in self.spans:
            slack = int(allowed(hi))
            can = known[np.minimum(here + hi + slack, end)] - known[:-1] >= lo - int(allowed(lo))
            mask |= can
            if middle:
                # the middle of a window lies between these distances from its start
                a, b = lo // 2 - slack, hi // 2 + slack
                some = np.concatenate([[0], np.cumsum(can)])
                mask |= some[np.maximum(here - a + 1, 0)] > some[np.maximum(here - b, 0)]
        return np.flatnonzero(mask & (end > here))

    def candidates(self, v: np.ndarray, h: np.ndarray, known: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(item, start) of the windows that meet an item in a table."""
        x = self.starts(known, end)
        found, at = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for r in range(self.walks if len(x) else 0):
            m = walk(v, moves(h, r), x, self.steps, x + self.length if self.exact else None)
            may = [seen.take(w, mode="wrap") for seen, w in zip(self.seen[r], m, strict=True)]
            for places, (keys, entry) in zip(self.places[r], self.probe[r], strict=True):
                i = np.flatnonzero(np.logical_and.reduce([may[j] for j in places]))
                k = self.key([m[j][i] for j in places])
                lo, hi = np.searchsorted(keys, k, "left"), np.searchsorted(keys, k, "right")
                n = hi - lo
                use = entry[np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())]
                found.append(self.item[use])
                at.append(np.repeat(x[i], n) - self.offset[use])
        return np.concatenate(found), np.concatenate(at)


class Items:
    """The benchmark, ready for probing."""

    def __init__(self, ids: list, texts: list[str | None]):
        w = Words(texts, plain=True, lower=True)
        self.ids, self.size = ids, np.diff(w.first)
        self.h = np.append(w.hash, PAD)
        # words by rank; those that share the upper bits of their hash stand side by side
        self.vocabulary = np.unique(w.hash)
        self.shift = U(64 - max(16, len(self.vocabulary).bit_length() + 3))
        self.bucket = np.searchsorted(self.vocabulary >> self.shift, np.arange((1 << (64 - int(self.shift))) + 1, dtype=U))
        self.deep = int(np.diff(self.bucket).max(initial=0))
        # one slot after each item, as behind each text
        self.first = w.first[:-1] + np.arange(len(texts))
        slot = np.arange(len(w)) + w.doc
        h = np.zeros(len(w) + len(texts) + 1, U)
        h[slot] = w.hash
        v = self.rank(h)
        bits = [moves(h, r) for r in range(WALKS)]
        kinds = [np.flatnonzero(self.size == n) for n in range(1, EDITED)] + [np.flatnonzero((self.size >= EDITED) & (self.size < TWO_ENTRIES)), np.flatnonzero(self.size >= TWO_ENTRIES)]
        self.words = h
        # (item, word) pairs as a hashed bit map, 16 bits a pair: the words that an item has, and few others
        self.own_bits = max(16, len(w).bit_length() + 4)
        self.own = np.zeros(1 << self.own_bits, bool)
        self.own[self.pair(w.doc, v[slot])] = True
        self.tables = [Tables(self.size, self.first, x, v, bits, exact=int(self.size[x[0]]) < EDITED) for x in kinds if len(x)]

    def rank(self, h: np.ndarray) -> np.ndarray:
        """1 and more for words of the benchmark, 0 for others and PAD."""
        out = np.zeros(len(h), np.int64)
        if len(self.vocabulary):
            b = (h >> self.shift).astype(np.int64)
            lo, hi = self.bucket[b], self.bucket[b + 1]
            for d in range(self.deep):
                k = np.flatnonzero(lo + d < hi)
                same = self.vocabulary[lo[k] + d] == h[k]
                out[k[same]] = lo[k[same]] + d + 1
        out[h == PAD] = 0
        return out

    def pair(self, item: np.ndarray, word: np.ndarray) -> np.ndarray:
        """The place of an item and a word in the bit map."""
        x = (item.astype(U) << U(32) | word.astype(U)) * U(0x9E3779B97F4A7C15)
        return (x >> U(64 - self.own_bits)).astype(np.int64)

    def search(self, texts: list[str | None]) -> list[tuple[int, int, int, int]]:
        """(row, item, distance, word) for each text and item that is in it; the best place, the first of equals."""
        best: dict[tuple[int, int], tuple[int, int]] = {}
        held: list[tuple[int, int, int, np.ndarray]] = []

        def settle():
            for d, k, n, x in self.verified(held):
                best[d, k] = min(best.get((d, k), (n, x)), (n, x))
            held.clear()

        for a, b in chunks(texts, CHARACTERS):
            w = Words(texts[a:b], lower=True, plain=True)
            slot = np.arange(len(w)) + w.doc
            h = np.zeros(len(w) + b - a + 1, U)
            h[slot] = w.hash
            v = self.rank(h)
            first = w.first + np.arange(b - a + 1)
            doc = np.repeat(np.arange(b - a), np.diff(first))
            end = np.append(first[1:][doc] - 1, 0)
            known = np.concatenate([[0], np.cumsum(v > 0)])
            for t in self.tables:
                for d, k, x, around in self.likely(h, v, known, first, doc, *t.candidates(v, h, known, end)):
                    held.append((d + a, k, x, around))
                    if len(held) >= HELD:
                        settle()
        settle()
        return [(d, k, n, x) for (d, k), (n, x) in sorted(best.items())]

    def likely(self, h: np.ndarray, v: np.ndarray, known: np.ndarray, first: np.ndarray, doc: np.ndarray, item: np.ndarray, start: np.ndarray) -> Iterator[tuple[int, int, int, np.ndarray]]:
        """The candidates with enough of the item's words around them: (text, item, word, the words around it)."""
        if not len(item):
            return
        # starts that stand close by are verified together
        whose = doc[np.clip(start, 0, len(doc) - 1)]
        step = allowed(self.size[item]) + 1
        order = np.lexsort((start // step, whose, item, self.size[item]))
        item, whose, start = item[order], whose[order], (start // step * step)[order]
        new = np.append(True, (np.diff(item) != 0) | (np.diff(whose) != 0) | (np.diff(start) != 0))
        item, whose, start = item[new], whose[new], start[new]
        size, slack = self.size[item], allowed(self.size[item])
        lo, hi = np.maximum(start - 2 * slack, first[whose]), np.minimum(start + size + 3 * slack, first[whose + 1] - 1)
        go = np.flatnonzero(known[np.maximum(hi, lo)] - known[lo] >= size - slack)
        at = 0
        while at < len(go):
            # items of like sizes come together, so that a long one pads no others
            n = int(np.searchsorted(size[go], 2 * size[go[at]], "right")) - at
            i = go[at : at + max(1, min(n, CELLS // int(6 * size[go[at]])))]
            at += len(i)
            shared = self.own[self.pair(item[i, None], cut(v, lo[i], hi[i], int((hi[i] - lo[i]).max())))].sum(1)
            for j in i[shared >= size[i] - slack[i]].tolist():
                yield int(whose[j]), int(item[j]), int(max(start[j] - first[whose[j]], 0)), h[lo[j] : hi[j]].copy()

    def verified(self, held: list[tuple[int, int, int, np.ndarray]]) -> Iterator[tuple[int, int, int, int]]:
        """Those within the allowance by edit distance: (text, item, distance, word)."""
        held = sorted(held, key=lambda x: (self.size[x[1]], len(x[3])))
        at = 0
        while at < len(held):
            top = 2 * self.size[held[at][1]]
            part = [x for x in held[at : at + max(1, CELLS // int(6 * top))] if self.size[x[1]] <= top]
            at += len(part)
            item = np.array([k for _, k, *_ in part])
            size, around = self.size[item], np.zeros((len(part), max(1, max(len(x[3]) for x in part))), U)
            for row, x in zip(around, part, strict=True):
                row[: len(x[3])] = x[3]
            near = nearest(cut(self.words, self.first[item], self.first[item] + size, int(size.max())), size, around)
            for (d, k, x, _), n, slack in zip(part, near.tolist(), allowed(size), strict=True):
                if n <= slack:
                    yield d, k, n, x


def cut(h: np.ndarray, start: np.ndarray, stop: np.ndarray, width: int) -> np.ndarray:
    """Words start to stop of each row, padded to width."""
    at = start[:, None] + np.arange(width)
    return np.where(at < stop[:, None], h[np.minimum(at, len(h) - 1)], h.dtype.type(0))


def blocks(benchmark: DataFrame, key: str = "item_id", text: str = "text") -> Iterator[tuple[list, list[str | None]]]:
    """The items in blocks of MAX_WORDS words at most, an item alone if it is longer; one block is held at a time."""
    ids, texts, total = [], [], 0
    for r in benchmark.select(F.col(key).alias("k"), F.col(text).cast("string").alias("t")).orderBy("k").toLocalIterator():
        n = int(np.diff(Words([r.t], plain=True, lower=True).first)[0])
        if total and total + n > MAX_WORDS:
            yield ids, texts
            ids, texts, total = [], [], 0
        total += n
        ids.append(r.k)
        texts.append(r.t)
    yield ids, texts


_items: tuple[int, Items] | None = None


def prepared(block: tuple[list, list[str | None]]) -> Items:
    """Items of a block, prepared once in each Python worker."""
    global _items
    name = hash((tuple(block[0]), tuple(block[1])))
    if _items is None or _items[0] != name:
        _items = (name, Items(*block))
    return _items[1]


def search(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id") -> DataFrame:
    """One row for each text and item in it: the two keys, distance, item_words, at_word."""
    plain = docs.select(F.col(key).alias("doc_id"), F.col(text).cast("string").alias("text"))
    kind = T.StructType([
        T.StructField("doc_id", plain.schema["doc_id"].dataType), T.StructField("item_id", benchmark.schema[item_key].dataType),
        T.StructField("distance", T.IntegerType()), T.StructField("item_words", T.IntegerType()), T.StructField("at_word", T.LongType()),
    ])
    shape = to_arrow_schema(kind)

    def one(block) -> DataFrame:
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def probe(batches):
            for t in batches:
                items = prepared(shared.value)
                found = items.search(t["text"].to_pylist())
                rows = pa.array([d for d, *_ in found], pa.int64())
                own = [t["doc_id"].take(rows).cast(shape.field("doc_id").type), pa.array([items.ids[k] for _, k, *_ in found], shape.field("item_id").type)]
                rest = [pa.array(x, f.type) for x, f in zip(([n for *_, n, _ in found], [int(items.size[k]) for _, k, *_ in found], [x for *_, x in found]), list(shape)[2:], strict=True)]
                yield pa.RecordBatch.from_arrays(own + rest, schema=shape)

        return plain.mapInArrow(probe, kind)

    return reduce(DataFrame.unionByName, map(one, blocks(benchmark, item_key))).withColumnsRenamed({"doc_id": key, "item_id": item_key})


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The rows of docs whose text holds no item; no shuffle, all columns stay."""
    out = docs
    for block in blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def keep(batches, shared=shared):
            for t in batches:
                stay = np.ones(t.num_rows, bool)
                stay[[d for d, *_ in prepared(shared.value).search(t[text].to_pylist())]] = False
                yield t.filter(pa.array(stay))

        out = out.mapInArrow(keep, docs.schema)
    return out
