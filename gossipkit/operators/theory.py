"""Closed forms: Laplace code rate, growth curves, stationarity bound, constants of a problem."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RUN_COST = 2.914  # fixed value: worst cost of a run over its information content, in bits


def laplace_rate(d: Column, levels: Column, eps: float = 0.01, base: float | None = None) -> Column:
    """Bits a coordinate for Laplace differences under an adaptive range; base None is the natural logarithm."""
    r = 2 * (F.log(d) - math.log(eps))
    a = r / levels
    log = F.log(1 - F.exp(-a)) if base is None else F.log(1 - F.exp(-a)) / math.log(base)
    return RUN_COST * F.exp(-a / 2) + (F.exp(a / 2) - F.exp(-a / 2)) * (1 - log) * F.exp(1 - a)


def rate_curves(sizes: DataFrame, levels: list[int]) -> DataFrame:
    """Growth of message sizes in the number of levels for vectors of given sizes d: d * exp(-1 / L) against d * log2 L."""
    grid = sizes.withColumn("levels", F.explode(F.array(*map(F.lit, levels))))
    d, x = F.col("d").cast("double"), F.col("levels").cast("double")
    return grid.withColumns({"proposed": d * F.exp(-1 / x), "symbolwise": d * F.log2(x), "laplace_rate": laplace_rate(d, x)})


def stationarity_bound(gap: float, K: float, G: float, sigma2: float, mu: float, d: int, n: int, T: int, lambda2: float, tau: float) -> float:
    """Right-hand side of the convergence bound for constant steps."""
    omega = (1 - abs(lambda2)) ** 2 / (82 * tau)
    a = math.sqrt(2 * G * G + 2 * sigma2 + mu * mu * d)
    first = 2 * math.sqrt(gap * K * (sigma2 + 4 * mu * mu * d + G * a) / ((T + 1) * n * omega))
    return first + 7 * (K * a * gap / ((T + 1) * omega)) ** (2 / 3) + 16 * K * gap / (T + 1)


def tau_range(d: int, levels: int) -> float:
    """Variance factor of the range-dithered quantiser: its contraction is 1 / tau."""
    return 1 + d / levels**2


def range_coverage(rows: DataFrame, eps: float) -> DataFrame:
    """(vectors, covered): share of the vectors (rep, p) whose range stays within rho * 2 (ln d - ln eps), with rho the mean size of
    their values, which is what a Laplace law fits."""
    limit = F.col("rho") * 2 * (F.log(F.col("d").cast("double")) - math.log(eps))
    each = rows.groupBy("rep").agg((F.max("p") - F.min("p")).alias("r"), F.avg(F.abs("p")).alias("rho"), F.count("p").alias("d"))
    return each.agg(F.count(F.lit(1)).alias("vectors"), F.avg((F.col("r") <= limit).cast("double")).alias("covered"))


def drawn(sizes: np.ndarray, features: int, batch: int = 16, draws: int = 32, seed: int = 0) -> tuple[dict[int, np.ndarray], dict[int, list[np.ndarray]]]:
    """For each site with rows: a random unit vector to start the power iteration from, and the places of its mini-batches' rows."""
    rng, starts, picks = np.random.default_rng(seed), {}, {}
    for s, n in enumerate(sizes.tolist()):
        if n:
            v = rng.normal(size=features)
            starts[s] = v / np.linalg.norm(v)
            picks[s] = [rng.choice(n, min(batch, n), replace=False) for _ in range(draws)]
    return starts, picks


def constants(grams: np.ndarray, starts: dict[int, np.ndarray], full: np.ndarray, batches: dict[int, list[np.ndarray]]) -> dict[str, float]:
    """Smoothness (largest eigenvalue of a site's mean Gram matrix by power iteration), largest full-gradient norm and mean variance
    of the gradients of the mini-batches."""
    K, G, var = 0.0, 0.0, []
    for s, v in starts.items():
        for _ in range(50):
            v = grams[s] @ v
            K = max(K, size := float(np.linalg.norm(v)))
            v = v / max(size, 1e-300)
        K = max(K, float(v @ (grams[s] @ v)))
        G = max(G, float(np.linalg.norm(full[s])))
        var.append(float(np.mean([((g - full[s]) ** 2).sum() for g in batches[s]])))
    return {"K": K, "G": G, "sigma2": float(np.mean(var))}
