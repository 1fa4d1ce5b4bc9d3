"""Cost and accuracy measures over states (site, coord, x, z, ...) and traces (run_id, round, ...)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import soft_threshold


def objective(data_loss: DataFrame, state: DataFrame, mu: float) -> DataFrame:
    """(site, data_loss, l1, total) for per-site losses (site, data_loss)."""
    l1 = state.groupBy("site").agg((mu * F.sum(F.abs("x"))).alias("l1"))
    return data_loss.join(l1, "site").withColumn("total", F.col("data_loss") + F.col("l1"))


def consensus_error(state: DataFrame) -> DataFrame:
    """(error): squared distance of all models to their mean, one pass."""
    per = state.groupBy("coord").agg((F.var_pop("x") * F.count("x")).alias("v"))
    return per.agg(F.sum("v").alias("error"))


def consensus_violation(state: DataFrame, mixing: DataFrame) -> DataFrame:
    """(error): squared differences over all undirected links."""
    e = F.broadcast(mixing.filter("src < dst").select("src", "dst"))
    a = state.select(F.col("site").alias("src"), "coord", F.col("x").alias("a")).join(e, "src")
    both = a.join(state.select(F.col("site").alias("dst"), "coord", F.col("x").alias("b")), ["dst", "coord"])
    return both.agg(F.sum(F.pow(F.col("a") - F.col("b"), 2)).alias("error"))


def stationarity(before: DataFrame, after: DataFrame, eta: float) -> DataFrame:
    """(site, norm2): squared norm of (x - z) / eta, x before the round and z in it."""
    both = before.select("site", "coord", F.col("x").alias("x0")).join(after.select("site", "coord", "z"), ["site", "coord"])
    return both.groupBy("site").agg(F.sum(F.pow((F.col("x0") - F.col("z")) / eta, 2)).alias("norm2"))


def stationarity_at_mean(mean: DataFrame, grads: DataFrame, mu: float, eta: float) -> DataFrame:
    """(norm2): the same at one model (coord, x) for gradients (coord, g) of the mean loss there."""
    both = mean.join(grads, "coord", "left")
    x = F.col("x")
    z = soft_threshold(x - eta * F.coalesce("g", F.lit(0.0)), mu * eta)
    return both.agg(F.sum(F.pow((x - z) / eta, 2)).alias("norm2"))


def zero_share(df: DataFrame, col: str = "z") -> DataFrame:
    return df.groupBy("site").agg(F.avg((F.col(col) == 0).cast("double")).alias("zero_share"))


def laplace_fit(df: DataFrame, bins: int = 1024) -> DataFrame:
    """(site, rho, ks): diversity by maximum likelihood and the largest distance between the distributions.

    Equal values are counted first; the empirical distribution is a running count within bins of a site's range on top
    of the counts of the bins before, so that no site's values are sorted in one task."""
    per = df.groupBy("site", "p").agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n")
    site = per.groupBy("site").agg(F.min("p").alias("lo"), F.max("p").alias("hi"), total.alias("all"), (F.sum(F.col("n") * F.abs("p")) / total).alias("rho"))
    place = F.when(F.col("hi") > F.col("lo"), F.floor((F.col("p") - F.col("lo")) / (F.col("hi") - F.col("lo")) * bins)).otherwise(0)
    binned = per.join(F.broadcast(site), "site").withColumn("bin", place)
    head = binned.groupBy("site", "bin").agg(total.alias("here"))
    before = Window.partitionBy("site").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    head = head.select("site", "bin", F.coalesce(F.sum("here").over(before), F.lit(0)).alias("before"))
    inside = Window.partitionBy("site", "bin").orderBy("p").rowsBetween(Window.unboundedPreceding, 0)
    own = (F.col("before") + F.sum("n").over(inside)) / F.col("all")
    cdf = F.when(F.col("p") < 0, 0.5 * F.exp(F.col("p") / F.col("rho"))).otherwise(1 - 0.5 * F.exp(-F.col("p") / F.col("rho")))
    return binned.join(head, ["site", "bin"]).withColumn("k", F.abs(cdf - own)).groupBy("site").agg(F.first("rho").alias("rho"), F.max("k").alias("ks"))


def histogram(df: DataFrame, col: str = "p", bins: int = 20) -> DataFrame:
    """(site, bin, n): counts in equal bins 1..bins of a site's own range; the top value falls in the last bin, and all
    values in bin 1 where the range is a point."""
    ends = df.groupBy("site").agg(F.min(col).alias("lo"), F.max(col).alias("hi"))
    bin_ = F.when(F.col("hi") > F.col("lo"), F.least(F.width_bucket(F.col(col), F.col("lo"), F.col("hi"), F.lit(bins)), F.lit(bins))).otherwise(1)
    return df.join(F.broadcast(ends), "site").groupBy("site", bin_.cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def quantiles(df: DataFrame, probs: list[float], col: str = "p", bins: int = 4096) -> DataFrame:
    """(site, prob, value): the least value whose share of values up to it reaches prob, exact.

    Equal values are counted first; counts by bins of a site's range name the bin that holds each quantile, and only that
    bin's distinct values are put in order."""
    per = df.groupBy("site", F.col(col).alias("v")).agg(F.count(F.lit(1)).alias("n"))
    ends = per.groupBy("site").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.sum("n").alias("all"))
    place = F.when(F.col("hi") > F.col("lo"), F.floor((F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo")) * bins)).otherwise(0)
    binned = per.join(F.broadcast(ends), "site").withColumn("bin", place)
    w = Window.partitionBy("site").orderBy("bin")
    head = binned.groupBy("site", "bin").agg(F.sum("n").alias("here"), F.first("all").alias("all"))
    head = head.withColumn("upto", F.sum("here").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    head = head.withColumn("prob", F.explode(F.array(*map(F.lit, probs))))
    share = F.col("upto") / F.col("all")
    before = (F.col("upto") - F.col("here")) / F.col("all")
    goal = head.filter((share >= F.col("prob")) & ((before < F.col("prob")) | (F.col("upto") == F.col("here"))))
    goal = goal.select("site", "bin", "prob", (F.col("upto") - F.col("here")).alias("before"))
    inside = Window.partitionBy("site", "prob").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    rows = binned.join(F.broadcast(goal), ["site", "bin"]).withColumn("share", (F.col("before") + F.sum("n").over(inside)) / F.col("all"))
    return rows.filter(F.col("share") >= F.col("prob")).groupBy("site", "prob").agg(F.min("v").alias("value"))


def quantiles_approx(df: DataFrame, probs: list[float], col: str = "p", accuracy: int = 10000) -> DataFrame:
    """The same from a digest of bounded size; ranks are off by at most 1 / accuracy of the values."""
    per = df.groupBy("site").agg(F.percentile_approx(col, probs, accuracy).alias("value"))
    return per.select("site", F.explode(F.arrays_zip(F.array(*map(F.lit, probs)).alias("prob"), "value")).alias("r")).select("site", "r.prob", "r.value")


def cumulative(trace: DataFrame, bits: str = "bits") -> DataFrame:
    w = Window.partitionBy("run_id").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
    return trace.withColumn("cum_bits", F.sum(bits).over(w))


def to_target(trace: DataFrame, cutoff: float, metric: str = "accuracy", bits: str = "bits") -> DataFrame:
    """(run_id, reached, rounds, cum_bits): the first round at the cut-off, or the last one where no round is."""
    c = cumulative(trace, bits)
    ok = F.col(metric) >= cutoff
    first = F.min(F.when(ok, F.struct("round", "cum_bits")))
    last = F.max(F.struct("round", "cum_bits"))
    out = c.groupBy("run_id").agg(first.alias("f"), last.alias("l"))
    return out.select("run_id", F.col("f").isNotNull().alias("reached"), F.coalesce("f", "l").alias("c")).select("run_id", "reached", F.col("c.round").alias("rounds"), F.col("c.cum_bits").alias("cum_bits"))


def saving(targets: DataFrame) -> DataFrame:
    """(run_a, run_b, saving): per cent of bits that run_a saves against run_b."""
    a, b = (targets.select(F.col("run_id").alias(f"run_{k}"), F.col("cum_bits").alias(k)) for k in "ab")
    return a.join(b, F.col("run_a") != F.col("run_b")).select("run_a", "run_b", (100 * (1 - F.col("a") / F.col("b"))).alias("saving"))


def slope(trace: DataFrame, metric: str) -> DataFrame:
    """(run_id, slope) of log(running mean of the metric) over log(round)."""
    w = Window.partitionBy("run_id").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
    run = trace.withColumn("m", F.avg(metric).over(w)).filter("m > 0")
    return run.groupBy("run_id").agg(F.regr_slope(F.log("m"), F.log("round")).alias("slope"))


def moving_average(trace: DataFrame, metric: str, k: int = 5) -> DataFrame:
    w = Window.partitionBy("run_id").orderBy("round").rowsBetween(-(k - 1), 0)
    return trace.withColumn(f"{metric}_ma", F.avg(metric).over(w))


def support_overlap(state: DataFrame, col: str = "z") -> DataFrame:
    """(a, b, jaccard) of the non-zero coordinates of each two sites, from one aggregate over the coordinates."""
    held = state.filter(F.col(col) != 0).groupBy("coord").agg(F.sort_array(F.collect_set("site")).alias("s"))
    size = state.groupBy("site").agg(F.sum((F.col(col) != 0).cast("long")).alias("n"))
    pair = held.select(F.explode("s").alias("a"), "s").select("a", F.explode("s").alias("b")).filter("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("both"))
    out = pair.join(size.select(F.col("site").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("site").alias("b"), F.col("n").alias("nb")), "b")
    return out.select("a", "b", (F.col("both") / (F.col("na") + F.col("nb") - F.col("both"))).alias("jaccard"))
