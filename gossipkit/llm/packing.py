"""Sorted 64-bit keys as compact bytes, and bit masks."""

from __future__ import annotations

import numpy as np
import zstandard


def planes(values: np.ndarray) -> bytes:
    """Unsigned 64-bit values, one plane of bytes after the other, compressed."""
    raw = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    return zstandard.ZstdCompressor(level=1).compress(raw.tobytes())


def unplaned(data: bytes) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(8, -1)
    return np.ascontiguousarray(raw.T).view("<u8").ravel()


def pack_sorted(keys: np.ndarray) -> bytes:
    """Ascending keys as differences; sparse high bytes compress away."""
    return planes(np.diff(keys, prepend=np.uint64(0)))


def unpack_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(unplaned(data), dtype=np.uint64)


def mask(bits: np.ndarray) -> bytes:
    return np.packbits(bits).tobytes()


def unmask(data: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(data, np.uint8), count=n).astype(bool)


def joined(*parts: bytes) -> bytes:
    """Byte strings with their lengths, in one."""
    return b"".join(len(p).to_bytes(8, "little") + p for p in parts)


def parted(data: bytes) -> list[bytes]:
    out, at = [], 0
    while at < len(data):
        n = int.from_bytes(data[at : at + 8], "little")
        out.append(data[at + 8 : at + 8 + n])
        at += 8 + n
    return out
