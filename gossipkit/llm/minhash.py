"""Shingle sets and SuperMinHash signatures with numpy."""

from __future__ import annotations

import numpy as np

from .textkernel import U, Words, chunks, finalise

SHINGLE = 5
MATRIX_FROM = 6


def shingle_sets(texts: list[str | None], k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(keys, offsets): the distinct k-word shingles of each lower-cased text, ascending, one text after the other.
    A text of fewer words has its whole sequence as its only shingle, one without words none."""
    parts, sizes = [np.zeros(0, U)], []
    for a, b in chunks(texts):
        w = Words(texts[a:b], lower=True)
        h, _ = w.windows(k)
        for i in range(b - a):
            lo, hi = int(w.first[i]), int(w.first[i + 1])
            if hi - lo >= k:
                own = np.sort(h[lo : hi - k + 1])
                own = own[np.append(True, own[1:] != own[:-1])]
            elif hi > lo:
                one = w.hash[lo : lo + 1].copy()
                for x in w.hash[lo + 1 : hi]:
                    one = finalise(one, 11) + x
                own = finalise(one, 100 + hi - lo)
            else:
                own = h[:0]
            parts.append(own)
            sizes.append(len(own))
    return np.concatenate(parts), np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])


def set_keys(keys: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each set, independent of order."""
    out = []
    for salt in (21, 22):
        total = np.concatenate([np.zeros(1, U), np.cumsum(finalise(keys, salt), dtype=U)])
        out.append(finalise(total[offsets[1:]] - total[offsets[:-1]], salt))
    return out[0], out[1]


def signatures(keys: np.ndarray, offsets: np.ndarray, m: int) -> np.ndarray:
    """SuperMinHash: a row of m values for each set; two rows agree at a place with the sets' Jaccard similarity.

    Every element draws a random order of the m places, one place a step, and offers it the step number with a
    random fraction. A set stops as soon as no later step can lower any of its places."""
    n = len(offsets) - 1
    sig = np.full(n * m, np.iinfo(np.uint64).max, U)
    row = np.repeat(np.arange(n), np.diff(offsets))
    moves: list[tuple[np.ndarray, np.ndarray]] = []  # (place drawn, what the swap put there) of the steps so far
    order: np.ndarray | None = None
    for j in range(m):
        if not len(row):
            break
        x = finalise(keys, 200 + j)
        drawn = (((x & U(0xFFFFFFFF)) * U(m - j)) >> U(32)).astype(np.int64) + j
        if order is None and j == MATRIX_FROM:
            order = np.tile(np.arange(m, dtype=np.int32), (len(row), 1))
            for k, (at, put) in enumerate(moves):
                each = np.arange(len(row))
                order[each, k] = order[each, at]
                order[each, at] = put
        if order is None:
            place, here = drawn.copy(), np.full(len(row), j)
            for at, put in moves:
                np.copyto(place, put, where=at == drawn)
                np.copyto(here, put, where=at == j)
            moves.append((drawn, here))
        else:
            each = np.arange(len(row))
            place, here = order[each, drawn], order[each, j].copy()
            order[each, drawn], order[each, j] = here, place
        np.minimum.at(sig, row * m + place, (U(j) << U(32)) | (x >> U(32)))
        worst = sig.reshape(n, m).max(1) >> U(32)
        go = (worst > U(j))[row]
        if not go.all():
            keys, row = keys[go], row[go]
            moves = [(a[go], b[go]) for a, b in moves] if order is None else []
            order = None if order is None else order[go]
    return sig.reshape(n, m)


def bands(sig: np.ndarray, rows: int) -> np.ndarray:
    """One key for each band of so many places; the band's number is part of it."""
    n, m = sig.shape
    out = np.empty((n, m // rows), U)
    for b in range(m // rows):
        h = np.zeros(n, U)
        for i in range(rows):
            h = finalise(h + sig[:, b * rows + i], 400)
        out[:, b] = finalise(h, 500 + b)
    return out
