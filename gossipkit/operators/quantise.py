"""Compression operators in the coordinate layout (site, coord, p).

Each takes and returns a DataFrame; statistics of a vector are one small aggregate a site, joined back by
broadcast (as many rows as there are sites).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import soft_threshold, uniform  # noqa: F401

ZERO = -1


def site_range(df: DataFrame, keys: list[str] = ["site"]) -> DataFrame:  # noqa: B006
    return df.groupBy(*keys).agg(F.min("p").alias("lo"), F.max("p").alias("hi"), F.count(F.lit(1)).alias("d"))


def with_range(df: DataFrame, keys: list[str] = ["site"], bounds: tuple[float, float] | None = None) -> DataFrame:  # noqa: B006
    stat = site_range(df, keys)
    if bounds:
        stat = stat.withColumns({"lo": F.lit(float(bounds[0])), "hi": F.lit(float(bounds[1]))})
    return df.join(F.broadcast(stat), keys)


def centred(df: DataFrame) -> DataFrame:
    """The range made symmetric, so that 0 is a grid point for an even number of levels."""
    top = F.greatest(F.abs("lo"), F.abs("hi"))
    return df.withColumn("_top", top).withColumns({"lo": -F.col("_top"), "hi": F.col("_top")}).drop("_top")


def level(p: Column, lo: Column, hi: Column, levels: int, u: Column) -> Column:
    """Level 0..levels of a value in its range; ZERO for an exact zero; level 0 if the range is a point."""
    inside = F.least(F.greatest((p - lo) / (hi - lo), F.lit(0.0)), F.lit(1.0))
    return F.when(p == 0, ZERO).when(hi == lo, 0).otherwise(F.floor(inside * levels + u)).cast("int")


def shrinkage(levels: int, d: Column) -> Column:
    return F.lit(float(levels * levels)) / (levels * levels + d)


def restore(sym: Column, lo: Column, hi: Column, levels: int, d: Column, shrink: str = "outer") -> Column:
    """Value of a symbol; the shrinking factor acts on the value ('outer'), on the normalised value ('inner') or not."""
    s, part = shrinkage(levels, d), (hi - lo) * sym / float(levels)
    value = {"outer": s * (lo + part), "inner": lo + s * part, "none": lo + part}[shrink]
    return F.when(sym == ZERO, 0.0).otherwise(value)


def range_dither(df: DataFrame, levels: int, seed: int = 42, rnd: Column | int = 1, grid: str = "minmax", shrink: str = "outer", bounds: tuple[float, float] | None = None, keys: list[str] = ["site"], dither: Callable[..., Column] = uniform) -> DataFrame:  # noqa: B006
    """Range-dithered quantiser: adds lo, hi, d, sym and q."""
    df = with_range(df, keys, bounds)
    if grid == "centred":
        df = centred(df)
    u = dither(seed, rnd, F.col("site"), F.col("coord"))
    df = df.withColumn("sym", level(F.col("p"), F.col("lo"), F.col("hi"), levels, u))
    return df.withColumn("q", restore(F.col("sym"), F.col("lo"), F.col("hi"), levels, F.col("d"), shrink))


def norm_factor(levels: int, d: Column) -> Column:
    return 1 + F.least(d / float(levels * levels), F.sqrt(d) / float(levels))


def norm_dither(df: DataFrame, levels: int, seed: int = 42, rnd: Column | int = 1, rescale: bool = True, dither: Callable[..., Column] = uniform) -> DataFrame:
    """Norm-scaled stochastic quantiser: sign and random level of |p| / norm; adds norm, d, sym and q.
    The squares are rounded before the sum, so that its order does not matter."""
    sq = F.round(F.col("p") * F.col("p"), 12).cast("decimal(38,12)")
    stat = df.groupBy("site").agg(F.sqrt(F.sum(sq).cast("double")).alias("norm"), F.count(F.lit(1)).alias("d"))
    df = df.join(F.broadcast(stat), "site")
    u = dither(seed, rnd, F.col("site"), F.col("coord"))
    mag = F.when(F.col("norm") == 0, 0).otherwise(F.floor(levels * F.abs("p") / F.col("norm") + u))
    df = df.withColumn("sym", (F.signum("p") * mag).cast("int"))
    value = F.col("norm") * F.col("sym") / float(levels)
    return df.withColumn("q", value / norm_factor(levels, F.col("d")) if rescale else value)


def _ranked(df: DataFrame, k: int, order: list[Column]) -> DataFrame:
    """The first k coordinates of each site. A window with a limit on its rank prunes before the shuffle."""
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("site").orderBy(*order))
    return df.withColumn("rank", rank).filter(F.col("rank") <= k)


def kept_only(df: DataFrame, kept: DataFrame) -> DataFrame:
    """df with q: the value where kept has the coordinate, else 0."""
    return df.join(kept.select("site", "coord", "q"), ["site", "coord"], "left").withColumn("q", F.coalesce("q", F.lit(0.0)))


def top_k(df: DataFrame, k: int) -> DataFrame:
    return _ranked(df, k, [F.abs("p").desc(), F.col("coord")]).withColumn("q", F.col("p"))


def rand_k(df: DataFrame, k: int, seed: int = 42, rnd: int = 1, label: str | None = "rand", dither: Callable[..., Column] = uniform) -> DataFrame:
    key = [x for x in (label, seed, rnd) if x is not None]
    return _ranked(df, k, [dither(*key, F.col("site"), F.col("coord")), F.col("coord")]).withColumn("q", F.col("p"))


def rescale_unbiased(df: DataFrame, tau: Column | float) -> DataFrame:
    """An unbiased operator becomes a contraction after division by its variance factor."""
    return df.withColumn("q", F.col("q") / tau)


def identity(df: DataFrame) -> DataFrame:
    return df.withColumn("q", F.col("p"))


def error_ratio(df: DataFrame) -> DataFrame:
    """(site, ratio): squared error of q over the squared norm of p."""
    return df.groupBy("site").agg((F.sum(F.pow(F.col("q") - F.col("p"), 2)) / F.sum(F.pow("p", F.lit(2)))).alias("ratio"))
