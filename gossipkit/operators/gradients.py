"""Gradients as joins and sums: samples (sample_id, site, label, feature, val), model (feature[, class], w)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import uniform


def long_rows(samples: DataFrame) -> DataFrame:
    """One row for each value of packed samples."""
    return samples.select("sample_id", "site", "label", F.inline(F.arrays_zip(F.col("idx").alias("feature"), F.col("val").alias("val"))))


def counts(rows: DataFrame) -> DataFrame:
    return rows.select("site", "sample_id").distinct().groupBy("site").agg(F.count(F.lit(1)).alias("n_site"))


def softmax_gradient(rows: DataFrame, model: DataFrame, classes: int) -> DataFrame:
    """(site, coord, g): mean over each site's samples; coord = feature * classes + class."""
    scores = rows.join(model, "feature").groupBy("sample_id", "class").agg(F.sum(F.col("val") * F.col("w")).alias("s"))
    w = Window.partitionBy("sample_id")
    e = F.exp(F.col("s") - F.max("s").over(w))
    prob = scores.withColumn("e", e).select("sample_id", "class", (F.col("e") / F.sum("e").over(w)).alias("prob"))
    miss = F.col("prob") - F.when(F.col("class") == F.col("label"), 1.0).otherwise(0.0)
    total = rows.join(prob, "sample_id").groupBy("site", (F.col("feature") * classes + F.col("class")).alias("coord")).agg(F.sum(F.col("val") * miss).alias("t"))
    return total.join(F.broadcast(counts(rows)), "site").select("site", "coord", (F.col("t") / F.col("n_site")).alias("g"))


def softmax_start_gradient(rows: DataFrame, classes: int) -> DataFrame:
    """softmax_gradient at the all-zero model, where every class has the same probability."""
    each = rows.withColumn("class", F.explode(F.sequence(F.lit(0), F.lit(classes - 1))))
    miss = 1.0 / classes - F.when(F.col("class") == F.col("label"), 1.0).otherwise(0.0)
    total = each.groupBy("site", (F.col("feature") * classes + F.col("class")).alias("coord")).agg(F.sum(F.col("val") * miss).alias("t"))
    return total.join(F.broadcast(counts(rows)), "site").select("site", "coord", (F.col("t") / F.col("n_site")).alias("g"))


def _slope(kind: str, m: Column) -> Column:
    """Derivative of a margin loss."""
    if kind == "logistic":
        return -1 / (1 + F.exp(m))
    if kind == "hinge":
        return F.when(m >= 1, 0.0).when(m > 0, m - 1).otherwise(-1.0)
    if kind == "least_squares":
        return m - 1
    raise ValueError(kind)


def margin_gradient(rows: DataFrame, model: DataFrame, kind: str) -> DataFrame:
    """(site, coord, g) of a binary loss of label * score; labels 0 and 1; coord is the feature."""
    sign = F.col("label") * 2.0 - 1
    scores = rows.join(F.broadcast(model), "feature").groupBy("sample_id").agg(F.sum(F.col("val") * F.col("w")).alias("s"))
    total = rows.join(scores, "sample_id").groupBy("site", F.col("feature").alias("coord")).agg(F.sum(F.col("val") * sign * _slope(kind, sign * F.col("s"))).alias("t"))
    return total.join(F.broadcast(counts(rows)), "site").select("site", "coord", (F.col("t") / F.col("n_site")).alias("g"))


def bernoulli_batch(samples: DataFrame, share: float, rnd: int, seed: int = 42) -> DataFrame:
    """Each row with probability share, by a hash of its id: the same rows however the table is partitioned."""
    return samples.filter(uniform("batch", seed, rnd, F.col("sample_id")) < share)


def softmax_scores(rows: DataFrame, model: DataFrame) -> DataFrame:
    """(sample_id, site, label, class, s)."""
    return rows.join(model, "feature").groupBy("sample_id", "site", "label", "class").agg(F.sum(F.col("val") * F.col("w")).alias("s"))


def softmax_loss(scores: DataFrame) -> DataFrame:
    """(site, data_loss): mean cross-entropy of each site."""
    top = scores.groupBy("sample_id", "site").agg(F.max("s").alias("m"), F.collect_list("s").alias("all"), F.max(F.when(F.col("class") == F.col("label"), F.col("s"))).alias("own"))
    total = F.aggregate("all", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("m")))
    return top.groupBy("site").agg(F.avg(F.log(total) + F.col("m") - F.col("own")).alias("data_loss"))


def softmax_accuracy(scores: DataFrame) -> DataFrame:
    """(site, accuracy): share of rows whose label scores highest; the first class of equals."""
    best = scores.groupBy("sample_id", "site", "label").agg(F.max_by("class", F.struct("s", -F.col("class"))).alias("guess"))
    return best.groupBy("site").agg(F.avg((F.col("guess") == F.col("label")).cast("double")).alias("accuracy"))
