"""Scalar column functions: proximal map, counter-based dither, code lengths, Laplace draws."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def soft_threshold(x: Column, threshold: Column | float) -> Column:
    """Proximal map of threshold * |.|; the identity for threshold 0."""
    if isinstance(threshold, (int, float)):
        if threshold == 0:
            return x
        threshold = F.lit(float(threshold))
    return F.signum(x) * F.greatest(F.abs(x) - threshold, F.lit(0.0))


def uniform(*parts: Column | int | str) -> Column:
    """A number in [0, 1) from a counter key: the first 32 bits of an MD5. Any engine gives the same number, and so
    does a task that runs again."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    text = F.concat_ws("/", *(c.cast("string") for c in cols))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def fast_uniform(*parts: Column | int | str) -> Column:
    """As uniform, from xxhash64: for runs that no other engine has to repeat."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.shiftrightunsigned(F.xxhash64(*cols), 11).cast("double") / F.lit(float(1 << 53))


def laplace(u: Column, rho: float) -> Column:
    """Inverse distribution function of the Laplace law of diversity rho."""
    c = u - 0.5
    return -rho * F.signum(c) * F.log(1 - 2 * F.abs(c))


def bit_length(k: Column) -> Column:
    """Binary digits of a whole number of 1 or more, without floating point."""
    return F.length(F.bin(k)).cast("long")


def elias_bits(k: Column, kind: str = "gamma") -> Column:
    """Code length of a whole number of 1 or more: Elias gamma, delta or omega."""
    n = bit_length(k) - 1
    if kind == "gamma":
        return 2 * n + 1
    if kind == "delta":
        return n + 2 * (bit_length(n + 1) - 1) + 1
    if kind != "omega":
        raise ValueError(kind)
    # four groups cover numbers below 2^65536
    total, left = F.lit(1).cast("long"), k.cast("long")
    for _ in range(6):
        total = F.when(left > 1, total + bit_length(left)).otherwise(total)
        left = F.when(left > 1, bit_length(left) - 1).otherwise(left)
    return total


def power_of_two(n: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), n.cast("int"))


def golomb_parameter(p: Column, rule: str = "optimal") -> Column:
    """Group size for runs between events of probability p: the least m with (1-p)^m + (1-p)^(m+1) <= 1, or the power
    of two below it (rule 'rice'). An event that is certain has m = 1."""
    m = F.when(p >= 1, 1).otherwise(F.greatest(F.ceil(F.log(2 - p) / -F.log(1 - p)), F.lit(1))).cast("long")
    return power_of_two(bit_length(m) - 1) if rule == "rice" else m


def golomb_bits(gap: Column, m: Column) -> Column:
    """Code length of a run: unary quotient, truncated binary remainder."""
    b = F.when(m > 1, bit_length(m - 1)).otherwise(0)
    short = power_of_two(b) - m
    return F.floor(gap / m) + 1 + F.when(m == 1, 0).otherwise(b - F.when(gap % m < short, 1).otherwise(0))
