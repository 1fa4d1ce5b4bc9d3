"""Connected components of a link table, distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Rows (id, component): the smallest id that each linked id reaches.

    Union-find as joins: an id keeps the least label it knows. In a round every link offers the label of one end
    to the other end and to the root the other end points to, and labels jump to the label of their label; the
    number of rounds is logarithmic. Rounds are written to the shared folder. Offers are combined map-side, so
    a much-linked id costs one row a task."""
    both = links.select(F.col(a).alias("x"), F.col(b).alias("y")).filter(F.col("x") != F.col("y"))
    both = stored(both.union(both.select("y", "x")).distinct(), "links")
    labels = stored(both.groupBy("x").agg(F.least(F.first("x"), F.min("y")).alias("l")).withColumnRenamed("x", "id"), "labels")
    while True:
        ends = both.join(labels.select(F.col("id").alias("x"), F.col("l").alias("lx")), "x").join(labels.select(F.col("id").alias("y"), F.col("l").alias("ly")), "y").filter(F.col("lx") < F.col("ly"))
        # without links between labels the labels are final once they point to roots
        offers = ends.select(F.inline(F.array(F.struct(F.col("y").alias("id"), F.col("lx").alias("o")), F.struct(F.col("ly").alias("id"), F.col("lx").alias("o")))))
        jump = labels.join(labels.select(F.col("id").alias("l"), F.col("l").alias("up")), "l")
        best = offers.groupBy("id").agg(F.min("o").alias("o"))
        new = jump.join(best, "id", "left").select("id", F.least("up", F.coalesce("o", "up")).alias("new"), F.col("l").alias("old"))
        new = stored(new, "labels")
        labels = new.select("id", F.col("new").alias("l"))
        if new.filter("new <> old").isEmpty():
            return labels.withColumnRenamed("l", "component")
