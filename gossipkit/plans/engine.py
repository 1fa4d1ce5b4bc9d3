"""One training round over all sites with numpy: rows of the state are sites.

The gradients come from outside, so that the same round serves the distributed trainer, where Spark computes
them, and sweeps, where a task holds a bounded workload. Dither is keyed by seed, round, site and coordinate.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np

from ..operators import codec
from .config import GossipConfig

HEADER = 8 * codec.HEADER.size


def uniforms(kind: str, seed: int, t: int, site: int, d: int, label: str = "") -> np.ndarray:
    if kind == "md5":
        key = f"{label}{seed}/{t}/{site}/"
        return np.array([int(hashlib.md5(f"{key}{i}".encode()).hexdigest()[:8], 16) for i in range(d)]) / 4294967296.0
    words = [seed, t, site, *label.encode()]
    return np.random.Generator(np.random.Philox(np.random.SeedSequence(words))).random(d)


def soft(x: np.ndarray, threshold: float) -> np.ndarray:
    return np.sign(x) * np.maximum(np.abs(x) - threshold, 0) if threshold else x


def gamma_bits(k: np.ndarray) -> np.ndarray:
    return 2 * np.floor(np.log2(k) + 1e-12).astype(np.int64) + 1


class Compressor:
    """Compresses one site's difference: returns (value, payload bits, symbols)."""

    def __init__(self, cfg: GossipConfig):
        self.cfg = cfg

    def __call__(self, p: np.ndarray, t: int, site: int, label: str = "") -> tuple[np.ndarray, int, np.ndarray | None]:
        return getattr(self, cfg.compressor if (cfg := self.cfg) else "")(p, uniforms(cfg.dither, cfg.seed, t, site, len(p), label))

    def range(self, p, u):
        cfg, L, d = self.cfg, self.cfg.levels, len(p)
        lo, hi = float(p.min()), float(p.max())
        if cfg.grid == "centred":
            hi = max(abs(lo), abs(hi))
            lo = -hi
        sym = np.zeros(d, np.int64) if hi == lo else np.floor(np.clip((p - lo) / (hi - lo), 0, 1) * L + u).astype(np.int64)
        sym[p == 0] = -1
        s, part = L * L / (L * L + d), (hi - lo) * sym / L
        q = {"outer": s * (lo + part), "inner": lo + s * part, "none": lo + part}[cfg.shrink]
        bits = 0 if (sym < 0).all() else codec.message_bits(sym, L) if cfg.coder == "levelset" else d * int(L + 1).bit_length()
        return np.where(sym < 0, 0.0, q), bits, sym

    def norm(self, p, u):
        s, d = self.cfg.levels, len(p)
        norm = float(np.sqrt(p @ p))
        if norm == 0:
            return np.zeros(d), 0, np.zeros(d, np.int64)
        sym = (np.sign(p) * np.floor(s * np.abs(p) / norm + u)).astype(np.int64)
        tau = 1 + min(d / s**2, d**0.5 / s)
        at = np.flatnonzero(sym)
        sparse = int(gamma_bits(np.diff(at, prepend=-1)).sum() + gamma_bits(np.abs(sym[at])).sum() + len(at)) if len(at) else 0
        dense = int(gamma_bits(np.abs(sym) + 1).sum() + len(at))
        return norm * sym / s / tau, min(sparse, dense), sym

    def _some(self, p, order):
        q = np.zeros(len(p))
        at = order[: self.cfg.keep]
        q[at] = p[at]
        return q, len(at) * (max((len(p) - 1).bit_length(), 1) + 32), None

    def topk(self, p, u):
        return self._some(p, np.lexsort((np.arange(len(p)), -np.abs(p))))

    def randk(self, p, u):
        return self._some(p, np.argsort(u, kind="stable"))

    def identity(self, p, u):
        return p, 32 * len(p), None


class Engine:
    """State of all sites and the methods' rounds."""

    def __init__(self, cfg: GossipConfig, w: np.ndarray, size: int, start: np.ndarray | None = None):
        n = len(w)
        self.cfg, self.w, self.t = cfg, w, 0
        self.x = np.zeros((n, size)) if start is None else np.tile(start, (n, 1))
        self.y = self.x.copy()  # replicas: equal at every holder, one row a site
        self.z = self.x.copy()
        self.track, self.track_y, self.last = np.zeros((3, n, size))
        self.compress = Compressor(cfg)
        self.links = (w > 0).sum(1) - (np.diag(w) > 0)

    def _send(self, p: np.ndarray, label: str = "") -> tuple[np.ndarray, np.ndarray, list]:
        sent = [self.compress(row, self.t, i, label) for i, row in enumerate(p)]
        return np.array([q for q, *_ in sent]), np.array([b for _, b, _ in sent]), [s for *_, s in sent]

    def round(self, gradient: Callable[[np.ndarray, int], np.ndarray]) -> dict:
        """One synchronous round; returns its measures."""
        cfg = self.cfg
        self.t += 1
        eta, g = cfg.step(self.t), gradient(self.x, self.t)
        if not np.isfinite(g).all():
            raise FloatingPointError(f"gradient of round {self.t} is not finite")
        before, messages, extra = self.x, 1, 0
        way = g
        if cfg.method == "tracking":
            self.track += g - self.last
            self.last = g
            q, bits, _ = self._send(self.track - self.track_y, "g")
            self.track_y += q
            self.track = self.track + cfg.gamma * (self.w @ self.track_y - self.track_y)
            way, messages, extra = self.track, 2, bits
        self.z = soft(self.x - eta * way, cfg.threshold * eta)
        p = self.z - self.y
        if cfg.method == "dsgd":
            bits, syms, self.x = np.full(len(p), 32 * p.shape[1]), [None], self.w @ self.z
        elif cfg.method == "local":
            bits, syms, self.x, messages = np.zeros(len(p), int), [None], self.z, 0
        else:
            q, bits, syms = self._send(p)
            self.y = self.y + q
            self.x = self.z + cfg.gamma * (self.w @ self.y - self.y)
        bits = bits + extra
        out = {
            "round": self.t, "messages": messages, "payload_bits": int(bits.sum()), "link_bits": int(((bits + messages * HEADER) * self.links).sum()), "eta": eta,
            "stationarity": float((((before - self.z) / eta) ** 2).sum(1).mean()), "consensus": float(((self.x - self.x.mean(0)) ** 2).sum()),
            "zero_share": float((self.z == 0).mean()), "laplace_rho": float(np.abs(p).mean()), "dominant_share": None, "entropy": None,
        }
        if syms[0] is not None:
            shares = [np.sort(np.unique(s, return_counts=True)[1] / len(s)) for s in syms]
            out |= {"dominant_share": float(np.mean([f[-1] for f in shares])), "entropy": float(np.mean([-(f * np.log2(f)).sum() for f in shares]))}
        return out

    def mean(self, prox: bool = False) -> np.ndarray:
        m = self.x.mean(0)
        return soft(m, self.cfg.threshold * self.cfg.step(max(self.t, 1))) if prox else m
