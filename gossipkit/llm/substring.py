"""Substring dedup by fixed-block anchors.

Every text is cut into reference blocks of BLOCK words that do not overlap. They are indexed by content and
probed with every rolling window of BLOCK words. As LENGTH >= 2 * BLOCK - 1, a repeat of LENGTH words holds a
whole reference block of the text it repeats, so no repeat is missed. Around the hits, windows of LENGTH words
are compared with each other by a 96-bit hash; adjoining ones join up to maximal repeats. A word goes if a
window over it also starts in a text of a smaller id.

Texts are dealt into batches once. A batch sends the distinct keys of its windows, packed, to the buckets of the
key space and gets one bit back for each: a key that many texts share counts once a batch, no pairs of texts
are built, and no key's rows meet in one task as such. Bits of keys go by the keys' order, bits of windows by the
order of settled(), so a batch may be read again in any order of rows.

Defined cases: a null text has no words; a null id counts as larger than all others; rows that share an id do
not remove each other's words; texts under LENGTH words are kept; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packing as P
from .common import spread
from .textkernel import U, Words, chunks

LENGTH, BLOCK, BITS = 13, 7, 48
SENT = "batch int, bucket int, body binary"
LAST = np.iinfo(np.int64).max
OUT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def settled(t: pa.Table) -> pa.Table:
    """A batch's rows in an order of their own. Passes exchange masks by place, and a shuffle that is read again may
    bring the rows in another order; rows that tie are equal."""
    return t.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def ids(t: pa.Table) -> np.ndarray:
    return t["doc_id"].fill_null(LAST).to_numpy()


def gathered(texts: list, k: int, salts: tuple[int, ...]) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """For every word of all texts: the hashes of the window from it on for each salt, whether that window is whole,
    the row of the text, and the word's place in it."""
    parts: list = [[np.zeros(0, U)] * len(salts) + [np.zeros(0, bool), np.zeros(0, np.int64), np.zeros(0, np.int64)]]
    for a, b in chunks(texts):
        w = Words(texts[a:b])
        made = [w.windows(k, s) for s in salts]
        fill = len(w) - len(made[0][0])
        parts.append([*(np.pad(h, (0, fill)) for h, _ in made), np.pad(made[0][1], (0, fill)), w.doc + a, np.arange(len(w)) - w.first[w.doc]])
    *hs, ok, row, at = (np.concatenate(x) for x in zip(*parts, strict=True))
    return hs, ok, row, at


def grouped(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, first): a stable order by the keys, the first the major one, and where each distinct key begins in it."""
    order = np.argsort(keys[0], kind="stable") if len(keys) == 1 else np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    return order, np.flatnonzero(new)


def anchors(texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct block keys of a batch, ascending, with flags (is a reference block; lies in two texts), and for each
    word window its key's index or -1, and its row."""
    (h,), ok, row, at = gathered(texts, BLOCK, (0,))
    h = h >> U(64 - BITS)
    where = np.flatnonzero(ok)
    order, first = grouped(h[where])
    last = np.append(first[1:], len(order)) - 1
    rows = row[where][order]
    block = np.logical_or.reduceat((at[where] % BLOCK == 0)[order], first) if len(first) else np.zeros(0, bool)
    group = np.cumsum(np.bincount(first, minlength=len(order))[: len(order)]) - 1 if len(order) else np.zeros(0, int)
    index = np.full(len(h), -1)
    index[where[order]] = group
    return h[where][order][first], block, rows[first] != rows[last], index, row


def bounds(keys: np.ndarray, n: int, bits: int) -> np.ndarray:
    """Where the ascending keys fall into n equal buckets."""
    edge = [-(-(i << bits) // n) for i in range(1, n)]
    return np.concatenate([[0], np.searchsorted(keys, np.array(edge, U)), [len(keys)]]).astype(int)


def table(rows: list[tuple]) -> pa.Table:
    cols = list(zip(*rows, strict=True)) or [[], [], []]
    return pa.table({"batch": pa.array(cols[0], pa.int32()), "bucket": pa.array(cols[1], pa.int32()), "body": pa.array(cols[2], pa.binary())})


def candidates(index: np.ndarray, active: np.ndarray) -> np.ndarray:
    """For every word, whether a window of LENGTH from it on holds a block window whose key is active."""
    hit = np.concatenate([[0], np.cumsum((index >= 0) & np.append(active, False)[index])])
    return hit[np.minimum(np.arange(len(index)) + LENGTH - BLOCK + 1, len(index))] > hit[:-1]


def window_keys(texts: list, wanted: np.ndarray, doc: np.ndarray):
    """Distinct keys (64 + 32 bits) of the wanted windows of LENGTH, the least id of each, and for every window its
    key's index or -1, its row and its place."""
    (a, b), ok, row, at = gathered(texts, LENGTH, (1, 2))
    where = np.flatnonzero(ok & wanted)
    a, b = a[where], b[where] >> U(32)
    order, first = grouped(a, b)
    least = np.minimum.reduceat(doc[row[where]][order], first) if len(first) else np.zeros(0, np.int64)
    index = np.full(len(ok), -1)
    index[where[order]] = np.cumsum(np.bincount(first, minlength=len(order))[: len(order)]) - 1 if len(order) else 0
    return a[order][first], b[order][first], least, index, row, at


def _by_bucket(replies: pa.Table, sizes: np.ndarray) -> np.ndarray:
    """One array of bits from the replies of the buckets; sizes: keys sent to each."""
    got = dict(zip(replies["bucket"].to_pylist(), replies["body"].to_pylist(), strict=True))
    return np.concatenate([P.unmask(got[i], n) if n else np.zeros(0, bool) for i, n in enumerate(sizes)])


def dedup(docs: DataFrame, key: str = "doc_id", text: str = "text", keep_text: bool = False) -> DataFrame:
    """One row for each row of docs: key, n_words, n_removed, kept_sha256, and with keep_text the kept words."""
    n = spread(docs)
    dealt = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    dealt = dealt.withColumn("batch", F.pmod(F.xxhash64("doc_id", F.substring("text", 1, 64)), F.lit(n)).cast("int")).repartition(n, "batch")
    batches = dealt.groupBy("batch")

    def probe(k, t):
        keys, block, several, *_ = anchors(t["text"].to_pylist())
        cut = bounds(keys, n, BITS)
        return table([(k[0].as_py(), i, P.joined(P.pack_sorted(keys[a:b]), P.mask(block[a:b]), P.mask(several[a:b]))) for i, (a, b) in enumerate(zip(cut, cut[1:], strict=False)) if b > a])

    def meet(k, t):
        """A key is active if it is a reference block somewhere and occurs in two texts."""
        who, parts = t["batch"].to_pylist(), [P.parted(x) for x in t["body"].to_pylist()]
        keys = [P.unpack_sorted(p[0]) for p in parts]
        sizes = [len(x) for x in keys]
        order, first = grouped(np.concatenate(keys))
        block = np.concatenate([P.unmask(p[1], s) for p, s in zip(parts, sizes, strict=True)])[order]
        several = np.concatenate([P.unmask(p[2], s) for p, s in zip(parts, sizes, strict=True)])[order]
        count = np.diff(np.append(first, len(order)))
        on = np.logical_or.reduceat(block, first) & ((count > 1) | np.logical_or.reduceat(several, first))
        back = np.empty(len(order), bool)
        back[order] = np.repeat(on, count)
        return table([(w, k[0].as_py(), P.mask(x)) for w, x in zip(who, np.split(back, np.cumsum(sizes)[:-1]), strict=True)])

    def extend(k, t, replies):
        if not t.num_rows:
            return table([])
        t = settled(t)
        texts, me = t["text"].to_pylist(), t["batch"][0].as_py()
        keys, _, _, index, _ = anchors(texts)
        wanted = candidates(index, _by_bucket(replies, np.diff(bounds(keys, n, BITS))))
        a, b, least, *_ = window_keys(texts, wanted, ids(t))
        cut = bounds(a, n, 64)
        rows = [(me, i, P.joined(P.pack_sorted(a[x:y]), P.planes(b[x:y]), P.planes(least[x:y].view(U)))) for i, (x, y) in enumerate(zip(cut, cut[1:], strict=False)) if y > x]
        # the batch's own note of the windows it asked about passes through under a negative bucket
        return table([*rows, (me, -1 - me, len(wanted).to_bytes(8, "little") + P.mask(wanted))])

    def judge(k, t):
        """One bit for each key: a batch elsewhere has it in a smaller id."""
        if k[0].as_py() < 0:
            return t.select(["batch", "bucket", "body"])
        who, parts = t["batch"].to_pylist(), [P.parted(x) for x in t["body"].to_pylist()]
        a = [P.unpack_sorted(p[0]) for p in parts]
        least = np.concatenate([P.unplaned(p[2]) for p in parts]).view(np.int64)
        order, first = grouped(np.concatenate(a), np.concatenate([P.unplaned(p[1]) for p in parts]))
        best = np.repeat(np.minimum.reduceat(least[order], first), np.diff(np.append(first, len(order))))
        back = np.empty(len(order), bool)
        back[order] = best < least[order]
        return table([(w, k[0].as_py(), P.mask(x)) for w, x in zip(who, np.split(back, np.cumsum([len(x) for x in a])[:-1]), strict=True)])

    def cut_out(k, t, replies):
        if not t.num_rows:
            return _result([], keep_text)
        t = settled(t)
        texts, doc, me = t["text"].to_pylist(), ids(t), t["batch"][0].as_py()
        note = replies.filter(pc.equal(replies["bucket"], -1 - me))["body"][0].as_py()
        size = int.from_bytes(note[:8], "little")
        a, b, least, index, row, at = window_keys(texts, P.unmask(note[8:], size), doc)
        gone = np.zeros(size, bool)
        if len(a):
            elsewhere = _by_bucket(replies, np.diff(bounds(a, n, 64)))
            # index -1 reads the last entry; those windows are masked out
            gone = (index >= 0) & (elsewhere[index] | (doc[row] > least[index]))
        return _result(_kept(texts, t["doc_id"].to_pylist(), gone, row, at), keep_text)

    asked = batches.applyInArrow(probe, SENT)
    active = asked.groupBy("bucket").applyInArrow(meet, SENT)
    compared = batches.cogroup(active.groupBy("batch")).applyInArrow(extend, SENT)
    judged = compared.groupBy("bucket").applyInArrow(judge, SENT)
    out = batches.cogroup(judged.groupBy("batch")).applyInArrow(cut_out, OUT + (", kept_text string" if keep_text else ""))
    return out.withColumnRenamed("doc_id", key)


def _result(rows: list[tuple], keep_text: bool) -> pa.Table:
    names = ["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"][: 4 + keep_text]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()]
    cols = list(zip(*rows, strict=True)) or [[]] * 5
    return pa.table({x: pa.array(cols[i], kinds[i]) for i, x in enumerate(names)})


def _kept(texts: list, doc: list, gone: np.ndarray, row: np.ndarray, at: np.ndarray) -> list[tuple]:
    """Rows (id, words, words removed, digest, kept text) from the windows that go."""
    by_row = np.searchsorted(row, np.arange(len(texts) + 1))
    out = []
    for a, b in chunks(texts):
        w = Words(texts[a:b])
        cover = np.zeros(len(w) + 1, np.int64)
        lo, hi = by_row[a], by_row[b]
        start = w.first[row[lo:hi] - a] + at[lo:hi]
        start = start[gone[lo:hi]]
        np.add.at(cover, start, 1)
        np.add.at(cover, start + LENGTH, -1)
        drop = np.cumsum(cover[:-1]) > 0
        lost = np.concatenate([[0], np.cumsum(drop)])
        # kept words and the byte after each, which becomes the space between
        edge = np.zeros(len(w.data) + 1, np.int8)
        edge[w.start[~drop]] += 1
        edge[w.end[~drop] + 1] -= 1
        stay = np.cumsum(edge[:-1], dtype=np.int8) > 0
        data = w.data.copy()
        data[w.end] = 0x20
        size = np.concatenate([[0], np.cumsum(np.add.reduceat(stay.astype(np.int64), np.cumsum(w.sizes) - w.sizes))])
        body = data[stay].tobytes()
        for i in range(b - a):
            kept = body[size[i] : max(size[i + 1] - 1, size[i])]
            n = int(w.first[i + 1] - w.first[i])
            out.append((doc[a + i], n, int(lost[w.first[i + 1]] - lost[w.first[i]]), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "surrogatepass")))
    return out
