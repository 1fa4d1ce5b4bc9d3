"""Graphs and mixing tables (src, dst, w), their checks and spectra."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

MAX_DRIVER_SITES = 5000


def fully_connected(spark: SparkSession, n: int) -> DataFrame:
    ids = spark.range(n).select(F.col("id").cast("int").alias("src"))
    other = F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("dst")
    return ids.select("src", other).withColumn("w", F.lit(1.0) / n)


def circulant(spark: SparkSession, n: int, offsets: tuple[int, ...] = (1,)) -> DataFrame:
    """Sites on a circle, each linked to those at the offsets on both sides, with equal weights."""
    steps = sorted({s % n for o in offsets for s in (o, -o)} | {0})
    ids = spark.range(n).select(F.col("id").cast("int").alias("src"), F.explode(F.array(*map(F.lit, steps))).alias("o"))
    return ids.select("src", F.pmod(F.col("src") + F.col("o"), F.lit(n)).cast("int").alias("dst"), (F.lit(1.0) / len(steps)).alias("w"))


def numbered(sites: DataFrame) -> DataFrame:
    """(site, i, n): the sites of a table of one row each, counted from 0; the window sees one row a site."""
    return sites.select("site", (F.row_number().over(Window.orderBy("site")) - 1).alias("i"), F.count(F.lit(1)).over(Window.partitionBy()).alias("n"))


def circulant_of(sites: DataFrame, offsets: tuple[int, ...] = (1,)) -> DataFrame:
    """circulant over the sites of a table, in their order; offsets that meet on a small circle count once."""
    at = numbered(sites)
    step = F.explode(F.array(*map(F.lit, sorted({s for o in offsets for s in (o, -o)} | {0}))))
    to = at.select(F.col("site").alias("src"), "n", "i", step.alias("o")).select("src", F.pmod(F.col("i") + F.col("o"), F.col("n")).alias("i"))
    pairs = to.join(at.select("i", F.col("site").alias("dst")), "i").select("src", "dst").distinct()
    return pairs.withColumn("w", F.lit(1.0) / F.count(F.lit(1)).over(Window.partitionBy("src")))


def full_of(sites: DataFrame) -> DataFrame:
    """fully_connected over the sites of a table."""
    at = numbered(sites)
    return at.select(F.col("site").alias("src"), (F.lit(1.0) / F.col("n")).alias("w")).crossJoin(at.select(F.col("site").alias("dst"))).select("src", "dst", "w")


def ring(spark: SparkSession, n: int) -> DataFrame:
    return circulant(spark, n)


def metropolis(edges: DataFrame) -> DataFrame:
    """Weights 1 / (1 + larger degree) for an undirected edge list (src, dst); the diagonal fills rows up to 1."""
    both = edges.select("src", "dst").union(edges.select(F.col("dst"), F.col("src"))).filter("src <> dst").distinct()
    deg = both.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    w = both.join(deg, "src").join(deg.select(F.col("src").alias("dst"), F.col("deg").alias("deg2")), "dst")
    w = w.select("src", "dst", (F.lit(1.0) / (1 + F.greatest("deg", "deg2"))).alias("w"))
    return w.union(w.groupBy("src").agg((1 - F.sum("w")).alias("w")).select("src", F.col("src").alias("dst"), "w"))


def nation_edges(nation: DataFrame) -> DataFrame:
    """Nations of a region form a clique; the first nations of the regions form a ring."""
    a = nation.select(F.col("n_nationkey").alias("src"), F.col("n_regionkey").alias("r"))
    inside = a.join(a.select(F.col("src").alias("dst"), "r"), "r").filter("src < dst").select("src", "dst")
    heads = a.groupBy("r").agg(F.min("src").alias("src"))
    n = heads.agg(F.count(F.lit(1)).alias("n"))
    nxt = heads.select(F.col("src").alias("dst"), F.col("r").alias("r2"))
    ring_ = heads.crossJoin(F.broadcast(n)).join(nxt, F.col("r2") == (F.col("r") + 1) % F.col("n")).select("src", "dst")
    return inside.union(ring_)


def check_mixing(mixing: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Rows (problem, src, dst) that break an assumption: symmetry, weights from 0 on, rows that sum to 1, one
    component. A site outside the component of the least site is a row with its own component's least site as dst."""
    from ..plans.relational import components

    back = mixing.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("w").alias("w2"))
    odd = mixing.join(back, ["src", "dst"], "left").filter(F.col("w2").isNull() | (F.abs(F.col("w") - F.col("w2")) > tolerance))
    rows = mixing.groupBy("src").agg(F.sum("w").alias("s")).filter(F.abs(F.col("s") - 1) > tolerance)
    out = odd.select(F.lit("asymmetric").alias("problem"), "src", "dst")
    out = out.unionByName(mixing.filter("w < 0").select(F.lit("negative").alias("problem"), "src", "dst"))
    out = out.unionByName(rows.select(F.lit("row sum").alias("problem"), "src", F.col("src").alias("dst")))
    label = components(mixing)
    apart = label.crossJoin(F.broadcast(label.agg(F.min("component").alias("least")))).filter("component <> least")
    return out.unionByName(apart.select(F.lit("component").alias("problem"), F.col("site").alias("src"), F.col("component").alias("dst")))


def matrix(mixing: DataFrame) -> np.ndarray:
    """The mixing matrix on the driver, up to MAX_DRIVER_SITES sites."""
    n = mixing.agg(F.max("src")).first()[0] + 1
    if n > MAX_DRIVER_SITES:
        raise ValueError(f"{n} sites: use the edge join instead")
    out = np.zeros((n, n))
    for r in mixing.collect():
        out[r.src, r.dst] += r.w
    return out


def connected(w: np.ndarray) -> bool:
    seen = np.zeros(len(w), bool)
    seen[:1] = True
    for _ in range(len(w)):
        seen |= (w[seen] > 0).any(0)
    return bool(seen.all())


def spectrum(w: np.ndarray) -> dict[str, float]:
    """Second largest absolute eigenvalue, spectral gap, and norm of I - W."""
    e = np.sort(np.abs(np.linalg.eigvalsh(w)))[::-1]
    second = float(e[1]) if len(e) > 1 else 0.0
    return {"lambda2": second, "gap": 1 - second, "beta": float(np.linalg.norm(np.eye(len(w)) - w, 2))}


def safe_gamma(w: np.ndarray, contraction: float) -> float:
    """A consensus step that a published analysis of compressed gossip proves safe; very conservative."""
    s = spectrum(w)
    d, b, c = s["gap"], s["beta"], contraction
    return d * d * c / (16 * d + d * d + 4 * b * b + 2 * d * b * b - 8 * d * c)


def assign(key: Column, n: int, how: str = "hash") -> Column:
    """Site of a row: 'hash' deals independent shards, 'modulo' is the same in any engine."""
    return F.pmod(F.xxhash64(key) if how == "hash" else key, F.lit(n)).cast("int")
