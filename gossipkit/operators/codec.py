"""Messages as bytes: Elias and Golomb codes, level-support messages, with numpy."""

from __future__ import annotations

import math
import struct

import numpy as np

HEADER = struct.Struct("<ffIH")
SYMBOL_HEADER = struct.Struct("<fI")


class BitWriter:
    def __init__(self):
        self.parts: list[str] = []

    def number(self, value: int, width: int) -> None:
        if width:
            self.parts.append(format(value, f"0{width}b"))

    def unary(self, n: int) -> None:
        self.parts.append("1" * n + "0")

    def text(self) -> str:
        return "".join(self.parts)


class BitReader:
    def __init__(self, bits: str):
        self.bits, self.at = bits, 0

    def number(self, width: int) -> int:
        out = int(self.bits[self.at : self.at + width] or "0", 2)
        self.at += width
        return out

    def unary(self) -> int:
        end = self.bits.index("0", self.at)
        n, self.at = end - self.at, end + 1
        return n


def whole_bytes(bits: str) -> bytes:
    """Bits with zeros up to a whole byte."""
    return int(bits + "0" * (-len(bits) % 8), 2).to_bytes(-(-len(bits) // 8), "big") if bits else b""


def bits_of(body: bytes) -> BitReader:
    return BitReader(format(int.from_bytes(body, "big"), f"0{8 * len(body)}b") if body else "")


def elias_write(w: BitWriter, k: int, kind: str = "gamma") -> None:
    n = k.bit_length() - 1
    if kind == "gamma":
        w.parts.append("0" * n + format(k, "b"))
    elif kind == "delta":
        elias_write(w, n + 1)
        w.number(k - (1 << n), n)
    else:
        out = "0"
        while k > 1:
            out = format(k, "b") + out
            k = k.bit_length() - 1
        w.parts.append(out)


def elias_read(r: BitReader, kind: str = "gamma") -> int:
    if kind == "gamma":
        n = r.bits.index("1", r.at) - r.at
        r.at += n
        return r.number(n + 1)
    if kind == "delta":
        n = elias_read(r) - 1
        return (1 << n) + r.number(n)
    k = 1
    while r.bits[r.at] == "1":
        k = r.number(k + 1)
    r.at += 1
    return k


def golomb_parameter(count: int, remaining: int, rule: str = "optimal") -> int:
    p = count / remaining
    m = 1 if p >= 1 else max(1, math.ceil(math.log(2 - p) / -math.log(1 - p)))
    return 1 << (m.bit_length() - 1) if rule == "rice" else m


def golomb_write(w: BitWriter, gap: int, m: int) -> None:
    q, r = divmod(gap, m)
    w.unary(q)
    if m > 1:
        b = (m - 1).bit_length()
        short = (1 << b) - m
        w.number(r, b - 1) if r < short else w.number(r + short, b)


def golomb_read(r: BitReader, m: int) -> int:
    q = r.unary()
    if m == 1:
        return q
    b = (m - 1).bit_length()
    short = (1 << b) - m
    low = r.number(b - 1)
    if low >= short:
        low = 2 * low + r.number(1) - short
    return q * m + low


def golomb_sizes(gaps: np.ndarray, m: int) -> np.ndarray:
    b = (m - 1).bit_length()
    return gaps // m + 1 + (0 if m == 1 else b - (gaps % m < (1 << b) - m))


def order_of(counts: np.ndarray) -> np.ndarray:
    """Symbols by falling count, ties by symbol; index 0 stands for symbol -1."""
    return np.lexsort((np.arange(len(counts)), -counts))


def sent_levels(counts: np.ndarray, implied: str = "dominant") -> tuple[int, np.ndarray]:
    """(implied code, codes sent in order) among those that occur; without an implied one the code is -1."""
    order = order_of(counts)
    order = order[counts[order] > 0]
    if implied == "none" or not len(order):
        return -1, order
    return (int(order[0]), order[1:]) if implied == "dominant" else (int(order[-1]), order[:-1])


def passes(sym: np.ndarray, levels: int, implied: str = "dominant"):
    """Yields (count, remaining, gaps) for each transmitted level, over a shrinking set of coordinates."""
    code = sym.astype(np.int64) + 1
    counts = np.bincount(code, minlength=levels + 2)
    for s in sent_levels(counts, implied)[1]:
        here = np.flatnonzero(code == s)
        yield int(counts[s]), len(code), np.diff(here, prepend=-1) - 1
        code = np.delete(code, here)


def message_bits(sym: np.ndarray, levels: int, implied: str = "dominant") -> int:
    """Length of type vector and gaps without writing them."""
    counts = np.bincount(sym.astype(np.int64) + 1, minlength=levels + 2)
    total = sum(2 * (int(c) + 1).bit_length() - 1 for c in counts)
    return total + sum(int(golomb_sizes(g, golomb_parameter(c, n)).sum()) for c, n, g in passes(sym, levels, implied))


def encode(sym: np.ndarray, levels: int, lo: float = 0.0, hi: float = 0.0, elias: str = "gamma", rule: str = "optimal", implied: str = "dominant") -> bytes:
    """A message: header, type vector, gaps, zero bits up to a whole byte."""
    w = BitWriter()
    for c in np.bincount(sym.astype(np.int64) + 1, minlength=levels + 2):
        elias_write(w, int(c) + 1, elias)
    for count, remaining, gaps in passes(sym, levels, implied):
        m = golomb_parameter(count, remaining, rule)
        for g in gaps.tolist():
            golomb_write(w, g, m)
    return HEADER.pack(lo, hi, len(sym), levels) + whole_bytes(w.text())


def decode(message: bytes, elias: str = "gamma", rule: str = "optimal", implied: str = "dominant") -> tuple[np.ndarray, float, float]:
    """(symbols, lo, hi) of a message."""
    lo, hi, d, levels = HEADER.unpack_from(message)
    r = bits_of(message[HEADER.size :])
    counts = np.array([elias_read(r, elias) - 1 for _ in range(levels + 2)])
    rest, sent = sent_levels(counts, implied)
    out, left = np.empty(d, np.int64), np.arange(d)
    for s in sent:
        m = golomb_parameter(int(counts[s]), len(left), rule)
        here = np.cumsum(np.array([golomb_read(r, m) for _ in range(counts[s])]) + 1) - 1
        out[left[here]] = s - 1
        left = np.delete(left, here)
    out[left] = rest - 1
    return out, lo, hi


def symbol_encode(sym: np.ndarray, norm: float = 0.0, form: str = "sparse") -> bytes:
    """Signed levels one by one: 'sparse' sends the number of non-zero ones, then gap, sign and level of each, 'dense' a
    level for every coordinate and a sign where it is not zero."""
    w = BitWriter()
    at = np.flatnonzero(sym) if form == "sparse" else np.arange(len(sym))
    if form == "sparse":
        elias_write(w, len(at) + 1)
    for gap, value in zip(np.diff(at, prepend=-1).tolist(), sym[at].tolist(), strict=True):
        if form == "sparse":
            elias_write(w, gap)
            w.number(int(value < 0), 1)
            elias_write(w, abs(value))
        else:
            elias_write(w, abs(value) + 1)
            w.number(int(value < 0), 1 if value else 0)
    return SYMBOL_HEADER.pack(norm, len(sym)) + whole_bytes(w.text())


def symbol_decode(message: bytes, form: str = "sparse") -> tuple[np.ndarray, float]:
    """(signed levels, norm) of a symbol-wise message."""
    norm, d = SYMBOL_HEADER.unpack_from(message)
    r, out, at = bits_of(message[SYMBOL_HEADER.size :]), np.zeros(d, np.int64), -1
    for i in range(elias_read(r) - 1 if form == "sparse" else d):
        if form == "sparse":
            at += elias_read(r)
            sign = r.number(1)
            out[at] = (1 - 2 * sign) * elias_read(r)
        else:
            mag = elias_read(r) - 1
            out[i] = mag * (1 - 2 * r.number(1)) if mag else 0
    return out, norm
