"""Word hashing over whole batches of texts with numpy.

A batch is a list of texts; its words are hashed on the UTF-8 bytes, where the separators are single bytes.
All arithmetic is modulo 2^64; every hash passes a finaliser.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
_SEP = np.zeros(256, bool)
_SEP[[0x20, *range(0x09, 0x0E)]] = True
#: Separators of plain words: every ASCII character but letters and digits.
_PLAIN = np.array([c < 128 and not chr(c).isalnum() for c in range(256)])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def finalise(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective 64-bit mixer."""
    x = x + U((0x9E3779B97F4A7C15 * (salt + 1)) & (2**64 - 1))
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


_BYTE = finalise(np.arange(256, dtype=U), 7)
_BYTE[_SEP] = 0
_powers = np.ones(1, U)


def powers(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        step = np.full(max(n, 1 << 12), 0xD6E8FEB86659FD93, U)
        step[0] = 1
        _powers = np.multiply.accumulate(step)
    return _powers


class Words:
    """The words of a batch: data (bytes of all texts, each followed by a line feed), start and end of every word,
    hash of every word, doc (row of its text) and first (for each text the number of words before it)."""

    def __init__(self, texts: list[str | None], lower: bool = False, plain: bool = False):
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        self.sizes = np.fromiter((len(b) + 1 for b in raw), np.int64, len(raw))
        data = np.frombuffer(b"\n".join(raw) + b"\n" if raw else b"", np.uint8)
        self.data = _LOWER[data] if lower else data
        self.sep = sep = (_PLAIN if plain else _SEP)[self.data]
        edge = np.flatnonzero(sep[1:] != sep[:-1]) + 1
        if len(sep) and not sep[0]:
            edge = np.concatenate([[0], edge])
        self.start, self.end = edge[::2], edge[1::2]
        ends = np.cumsum(self.sizes)
        self.doc = np.searchsorted(ends, self.start, "right")
        self.first = np.searchsorted(self.doc, np.arange(len(raw) + 1))
        self.hash = self._hash()

    def __len__(self) -> int:
        return len(self.start)

    def _hash(self) -> np.ndarray:
        if not len(self.start):
            return np.zeros(0, U)
        lo = int(self.start[0])
        body = self.data[lo:]
        size = np.diff(self.start, append=len(self.data))
        inside = np.arange(lo, len(self.data)) - np.repeat(self.start, size)
        value = _BYTE[body] * powers(int(size.max()))[inside]
        value[self.sep[lo:]] = 0
        return finalise(np.add.reduceat(value, self.start - lo))

    def windows(self, k: int, salt: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Hash of the k words from each word on, and whether they all lie in one text."""
        n = max(len(self.hash) - k + 1, 0)
        out = np.zeros(n, U)
        q = U(0x8CB92BA72F3D8DD7 + 2 * salt)
        for i in range(k):
            out = out * q + self.hash[i : i + n]
        return finalise(out, salt), self.doc[:n] == self.doc[k - 1 : k - 1 + n] if n else np.zeros(0, bool)


def chunks(texts: list[str | None], size: int = 2 << 20):
    """Ranges of rows with texts of about this many characters together; a longer text stands alone."""
    a = total = 0
    for i, t in enumerate(texts):
        n = len(t or "") + 1
        if total and total + n > size:
            yield a, i
            a, total = i, 0
        total += n
    if a < len(texts):
        yield a, len(texts)
