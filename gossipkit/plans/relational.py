"""Rounds in the coordinate layout, for models of any size: state rows (site, coord, x, y), all steps as joins and
aggregates, lineage cut once a round by a table in the shared folder."""

from __future__ import annotations

import os
import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import bit_length, fast_uniform, soft_threshold, uniform
from ..operators import codec, levelset
from ..operators.quantise import kept_only, norm_dither, rand_k, range_dither, top_k
from .config import GossipConfig


def shared_dir(df: DataFrame) -> str:
    """spark.checkpoint.dir, or a folder beside the warehouse where it is unset."""
    conf = df.sparkSession.conf
    return conf.get("spark.checkpoint.dir", None) or os.path.join(conf.get("spark.sql.warehouse.dir", "spark-warehouse"), "_rounds")


def cut(df: DataFrame, label: str = "state") -> DataFrame:
    path = f"{shared_dir(df).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    spark = df.sparkSession
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    # states that nobody forgets go with the driver
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)
    return spark.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Deletes the table of a state that a later one has replaced, if cut wrote it."""
    spark, root = df.sparkSession, shared_dir(df).rstrip("/")
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/state-" in path and path.split(":", 1)[-1].lstrip("/").startswith(root.split(":", 1)[-1].lstrip("/")):
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def start(df: DataFrame) -> DataFrame:
    """All-zero models and replicas for the (site, coord) of df."""
    return df.select("site", "coord", F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))


def neighbour_mean(values: DataFrame, mixing: DataFrame, col: str = "y") -> DataFrame:
    """(site, coord, mixed): weighted sums over neighbours. The mixing table is broadcast where Spark's own statistics put it
    under its limit; a larger one is joined by shuffle. The values are aggregated by (site, coord), which combines before
    the shuffle."""
    sent = values.select(F.col("site").alias("src"), "coord", col).join(mixing, "src")
    return sent.groupBy(F.col("dst").alias("site"), "coord").agg(F.sum(F.col("w") * F.col(col)).alias("mixed"))


def uniform_mean(values: DataFrame, col: str = "y") -> DataFrame:
    """neighbour_mean for equal weights between all sites: one mean a coordinate instead of a row for each link."""
    mean = values.groupBy("coord").agg(F.avg(col).alias("mixed"))
    return values.select("site", "coord").join(mean, "coord")


def mix(state: DataFrame, mixing: DataFrame | None, gamma: float) -> DataFrame:
    """x <- z + gamma * (weighted neighbour replicas - own replica); mixing None stands for equal weights."""
    mixed = uniform_mean(state) if mixing is None else neighbour_mean(state, mixing)
    out = state.join(mixed, ["site", "coord"], "left").withColumn("x", F.col("z") + gamma * (F.coalesce("mixed", F.lit(0.0)) - F.col("y")))
    return out.drop("mixed")


def local_part(state: DataFrame, grads: DataFrame, cfg: GossipConfig, t: int, decimals: int | None = None) -> DataFrame:
    """Gradient step, proximal map and difference to the replica: columns x, y, z, p."""
    eta = cfg.step(t)
    g = F.coalesce("g", F.lit(0.0))
    df = state.join(grads, ["site", "coord"], "left").withColumn("z", soft_threshold(F.col("x") - eta * g, cfg.threshold * eta))
    p: Column = F.col("z") - F.col("y")
    return df.withColumn("p", F.round(p, decimals) if decimals else p).drop("g")


def compressed(df: DataFrame, cfg: GossipConfig, t: int) -> DataFrame:
    """Adds q, what the receivers get of p, and for the quantisers sym."""
    dither = {"md5": uniform, "fast": fast_uniform}[cfg.dither]
    if cfg.compressor == "identity":
        return df.withColumn("q", F.col("p"))
    if cfg.compressor == "topk":
        return kept_only(df, top_k(df, cfg.keep))
    if cfg.compressor == "randk":
        return kept_only(df, rand_k(df, cfg.keep, cfg.seed, t, None, dither))
    if cfg.compressor == "norm":
        return norm_dither(df, cfg.levels, cfg.seed, t, dither=dither)
    return range_dither(df, cfg.levels, cfg.seed, t, cfg.grid, cfg.shrink, dither=dither)


def one_round(state: DataFrame, grads: DataFrame, mixing: DataFrame | None, cfg: GossipConfig, t: int, decimals: int | None = None) -> DataFrame:
    """(site, coord, x, y, z, p, q, ...) after round t for gradients (site, coord, g). dsgd averages the neighbours'
    models as they are, local doesn't communicate; tracking is tracking_round."""
    way = local_part(state, grads, cfg, t, decimals)
    if cfg.method == "local":
        return way.withColumns({"x": F.col("z"), "q": F.lit(0.0)})
    if cfg.method == "dsgd":
        mixed = uniform_mean(way, "z") if mixing is None else neighbour_mean(way, mixing, "z")
        return way.join(mixed, ["site", "coord"], "left").withColumns({"x": F.coalesce("mixed", F.lit(0.0)), "q": F.col("p")}).drop("mixed")
    return mix(compressed(way, cfg, t).withColumn("y", F.col("y") + F.col("q")), mixing, cfg.gamma)


def links(state: DataFrame, mixing: DataFrame | None) -> DataFrame:
    """(site, links): how many others each site sends to."""
    if mixing is None:
        sites = state.select("site").distinct()
        return sites.crossJoin(F.broadcast(sites.agg((F.count(F.lit(1)) - 1).alias("links"))))
    return mixing.filter("w > 0 AND src <> dst").groupBy(F.col("src").alias("site")).agg(F.count(F.lit(1)).alias("links"))


def payload(sent: DataFrame, cfg: GossipConfig, sym: str = "sym") -> DataFrame:
    """(site, payload_bits): the length of each site's coded message of a round; a message of zeros costs nothing."""
    size = sent.groupBy("site").agg(F.count(F.lit(1)).alias("d"))
    if cfg.method == "dsgd" or cfg.compressor == "identity":
        return size.select("site", (F.col("d") * 32).alias("payload_bits"))
    if cfg.compressor in {"topk", "randk"}:
        k = F.least(F.lit(cfg.keep), F.col("d"))
        # the binary digits of the largest position
        return size.select("site", (k * (F.when(F.col("d") > 1, bit_length(F.col("d") - 1)).otherwise(1) + 32)).alias("payload_bits"))
    rows = sent.select("site", "coord", F.col(sym).alias("sym"))
    if cfg.compressor == "norm":
        sparse, dense = (levelset.symbol_bits(rows, cfg.levels, form).select("site", F.col("payload_bits").alias(form)) for form in ("sparse", "dense"))
        some = rows.groupBy("site").agg(F.max(F.abs("sym")).alias("most"))
        return sparse.join(dense, "site").join(some, "site").select("site", F.when(F.col("most") == 0, 0).otherwise(F.least("sparse", "dense")).alias("payload_bits"))
    some = rows.groupBy("site").agg(F.max("sym").alias("most"))
    if cfg.coder == "levelset":
        bits = levelset.bits(rows, cfg.levels).select("site", (F.col("type_bits") + F.col("gap_bits")).alias("payload_bits"))
    else:
        bits = levelset.fixed_bits(rows, cfg.levels + 2)
    return bits.join(some, "site").select("site", F.when(F.col("most") < 0, 0).otherwise(F.col("payload_bits")).alias("payload_bits"))


HEADER = 8 * codec.HEADER.size
TRACE = "round int, messages int, payload_bits long, link_bits long, stationarity double, consensus double, zero_share double, measure double"


def measured(before: DataFrame, after: DataFrame, mixing: DataFrame | None, cfg: GossipConfig, t: int, measure: float | None) -> tuple:
    """A trace row of round t: messages, bits and the round's measures, as the engine counts them."""
    messages = {"tracking": 2, "local": 0}.get(cfg.method, 1)
    if messages:
        bits = payload(after, cfg)
        if messages == 2:
            bits = bits.unionByName(payload(after, cfg, "track_sym")).groupBy("site").agg(F.sum("payload_bits").alias("payload_bits"))
        own = F.col("payload_bits") + messages * HEADER
        total = bits.join(links(after, mixing), "site", "left").agg(F.sum("payload_bits").alias("p"), F.sum(own * F.coalesce("links", F.lit(0))).alias("l")).first()
        sent = (int(total.p), int(total.l))
    else:
        sent = (0, 0)
    eta, sites = cfg.step(t), after.agg(F.count_distinct("site").alias("n"), F.avg((F.col("z") == 0).cast("double")).alias("zero")).first()
    moved = after.select("site", "coord", "z").join(before.select("site", "coord", "x"), ["site", "coord"]).agg(F.sum(F.pow((F.col("x") - F.col("z")) / eta, 2))).first()[0]
    apart = after.groupBy("coord").agg((F.var_pop("x") * F.count("x")).alias("v")).agg(F.sum("v")).first()[0]
    return (t, messages, *sent, float(moved) / sites.n, float(apart), float(sites.zero), measure)


def run_traced(
    state: DataFrame, gradient: Callable[[DataFrame, int], DataFrame], mixing: DataFrame | None, cfg: GossipConfig, measure: Callable[[DataFrame], float] | None = None, cutoff: float | None = None, decimals: int | None = None,
) -> tuple[DataFrame, DataFrame]:
    """(state, trace): cfg.rounds rounds, or fewer if measure, a number of the state such as its validation accuracy, reaches
    cutoff. The trace has bits, messages and measures of each round. Only the last state's table is kept."""
    if cfg.method == "tracking" and "track" not in state.columns:
        state = tracking_start(state)
    rows, keep = [], ["site", "coord", "x", "y", "z"] + (["track", "track_y", "last"] if cfg.method == "tracking" else [])
    for t in range(1, cfg.rounds + 1):
        held = state.select(*[c for c in keep if c in state.columns])
        made = (tracking_round if cfg.method == "tracking" else one_round)(held, gradient(state.select("site", "coord", "x"), t), mixing, cfg, t, decimals)
        after = cut(made.select(*keep, *(c for c in ("sym", "track_sym") if c in made.columns)))
        got = float(measure(after)) if measure else None
        rows.append(measured(state, after, mixing, cfg, t, got))
        if t > 1:  # the first state is the caller's
            forget(state)
        state = after
        if cutoff is not None and got is not None and got >= cutoff:
            break
    return state.select(*[c for c in keep if c in state.columns]), state.sparkSession.createDataFrame(rows, TRACE)


def run(state: DataFrame, gradient: Callable[[DataFrame, int], DataFrame], mixing: DataFrame | None, cfg: GossipConfig, decimals: int | None = None) -> DataFrame:
    """cfg.rounds rounds; gradient gets (site, coord, x) and the round."""
    for t in range(1, cfg.rounds + 1):
        after = cut(one_round(state, gradient(state.select("site", "coord", "x"), t), mixing, cfg, t, decimals).select("site", "coord", "x", "y", "z"))
        if t > 1:  # the first state is the caller's
            forget(state)
        state = after
    return state


def tracking_start(df: DataFrame) -> DataFrame:
    """start, with all-zero trackers, their replicas and last gradients."""
    zero = F.lit(0.0)
    return start(df).withColumns({"track": zero, "track_y": zero, "last": zero})


def tracking_round(state: DataFrame, grads: DataFrame, mixing: DataFrame | None, cfg: GossipConfig, t: int, decimals: int | None = None) -> DataFrame:
    """A round of compressed proximal tracking: the tracker gains the change of the gradient, is sent compressed and
    mixed, and takes the gradient's place; then the model is sent as in one_round. Two messages a link."""
    g = F.coalesce("g", F.lit(0.0))
    s = state.join(grads, ["site", "coord"], "left").withColumn("track", F.col("track") + g - F.col("last")).withColumn("last", g).drop("g")
    diff = F.col("track") - F.col("track_y")
    p = s.select("site", "coord", (F.round(diff, decimals) if decimals else diff).alias("p"))
    # the same dither as the engine's: its key is the label g before the seed
    q = compressed(p, replace(cfg, seed=f"g{cfg.seed}"), t)
    q = q.select("site", "coord", "q", *([F.col("sym").alias("track_sym")] if "sym" in q.columns else []))
    s = s.join(q, ["site", "coord"]).withColumn("track_y", F.col("track_y") + F.col("q")).drop("q")
    mixed = uniform_mean(s, "track_y") if mixing is None else neighbour_mean(s, mixing, "track_y")
    s = s.join(mixed, ["site", "coord"], "left").withColumn("track", F.col("track") + cfg.gamma * (F.coalesce("mixed", F.lit(0.0)) - F.col("track_y"))).drop("mixed")
    way = s.select("site", "coord", F.col("track").alias("g"))
    return one_round(s, way, mixing, cfg, t, decimals)


def run_tracking(state: DataFrame, gradient: Callable[[DataFrame, int], DataFrame], mixing: DataFrame | None, cfg: GossipConfig) -> DataFrame:
    """run for tracking_round, from tracking_start."""
    for t in range(1, cfg.rounds + 1):
        state = cut(tracking_round(state, gradient(state.select("site", "coord", "x"), t), mixing, cfg, t).select("site", "coord", "x", "y", "z", "track", "track_y", "last"))
    return state


def average_consensus(values: DataFrame, mixing: DataFrame, gamma: float = 1.0, rounds: int = 30, cfg: GossipConfig | None = None) -> DataFrame:
    """Gossip averaging of (site, coord, x) without gradients: x <- x + gamma (W x - x), or, with cfg, replicas that
    compressed differences move stand for the neighbours' values."""
    if cfg:
        state = values.select("site", "coord", "x", F.lit(0.0).alias("y"))
        for t in range(1, rounds + 1):
            sent = compressed(state.withColumn("z", F.col("x")).withColumn("p", F.col("x") - F.col("y")), cfg, t)
            state = cut(mix(sent.withColumn("y", F.col("y") + F.col("q")), mixing, gamma).select("site", "coord", "x", "y"))
        return state.select("site", "coord", "x")
    for _ in range(rounds):
        mixed = neighbour_mean(values, mixing, "x")
        values = cut(values.join(mixed, ["site", "coord"]).select("site", "coord", (F.col("x") + gamma * (F.col("mixed") - F.col("x"))).alias("x")))
    return values


def components(mixing: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """(site, component): the least site that links reach, for graphs beyond a matrix; labels spread over links and
    then jump to their label's label until none changes."""
    links = mixing.filter("w > 0 AND src <> dst").select("src", "dst")
    links = cut(links.union(links.select("dst", "src")).distinct(), "links")
    label = cut(mixing.select(F.col("src").alias("site")).union(mixing.select("dst")).distinct().withColumn("component", F.col("site")), "components")
    for _ in range(max_rounds):
        near = links.join(label.withColumnRenamed("site", "src"), "src").groupBy(F.col("dst").alias("site")).agg(F.min("component").alias("near"))
        least = label.join(near, "site", "left").select("site", F.col("component").alias("old"), F.least("component", F.coalesce("near", "component")).alias("c"))
        above = label.select(F.col("site").alias("c"), F.col("component").alias("up"))
        moved = cut(least.join(above, "c").select("site", "old", F.least("c", "up").alias("component")), "components")
        label = moved.select("site", "component")
        if moved.filter("component <> old").isEmpty():
            return label
    raise RuntimeError("labels still change")
