"""Settings of a run, checked when they are made."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class GossipConfig:
    """One training run. eta is constant, or eta / t^decay for a diminishing step."""

    method: str = "sparse"  # sparse, plain, tracking, exact, dsgd, local
    sites: int = 10
    rounds: int = 100
    levels: int = 16
    mu: float = 1e-3
    eta: float = 0.5
    decay: float = 0.0
    gamma: float = 0.4
    batch: int | None = 16  # samples a site and round; None: all
    seed: int = 42
    compressor: str = "range"  # range, norm, topk, randk, identity
    coder: str = "levelset"  # levelset, symbol, index, raw
    shrink: str = "outer"
    grid: str = "minmax"
    keep: int = 50  # coordinates of topk and randk
    dither: str = "fast"  # fast, or md5: the same numbers as any other engine
    eval_every: int = 1

    def __post_init__(self):
        checks = [
            (self.method in {"sparse", "plain", "tracking", "exact", "dsgd", "local"}, "method"), (self.levels >= 1, "levels"), (self.mu >= 0, "mu"),
            (self.eta > 0, "eta"), (0 < self.gamma <= 1, "gamma"), (self.sites >= 1, "sites"), (self.rounds >= 0, "rounds"), (self.keep >= 1, "keep"),
            (self.compressor in {"range", "norm", "topk", "randk", "identity"}, "compressor"), (self.coder in {"levelset", "symbol", "index", "raw"}, "coder"),
            (self.shrink in {"outer", "inner", "none"}, "shrink"), (self.grid in {"minmax", "centred"}, "grid"), (self.batch is None or self.batch >= 1, "batch"),
        ]
        if bad := [name for ok, name in checks if not ok]:
            raise ValueError(f"out of range: {', '.join(bad)}")

    def step(self, t: int) -> float:
        """Step size of round t, counted from 1."""
        return self.eta / t**self.decay

    @property
    def threshold(self) -> float:
        """Weight of the L1 term that the method's proximal step uses."""
        return 0.0 if self.method in {"plain", "local"} else self.mu


def paper_methods(base: GossipConfig) -> dict[str, GossipConfig]:
    """The compared methods, each with its own compressor and coder."""
    from dataclasses import replace

    return {
        "sparse_range_levelset": replace(base, method="sparse"),
        "exact": replace(base, method="exact", compressor="identity", coder="raw"),
        "plain_norm_symbol": replace(base, method="plain", compressor="norm", coder="symbol"),
        "plain_range_levelset": replace(base, method="plain"),
        "tracking_range_levelset": replace(base, method="tracking"),
    }
