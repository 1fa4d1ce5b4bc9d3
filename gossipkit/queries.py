"""Queries of the methods, measures and workloads over the given tables."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.columns import elias_bits, golomb_bits, golomb_parameter, soft_threshold, uniform
from .operators import codec, features, gradients, joins, levelset, measures, quantise, theory, topology
from .plans import relational, trainers, workloads
from .plans.config import GossipConfig
from .sources.tables import load
from .streaming import online

LEVELS, SPARSE, SITES, CLASSES = 16, 0.05, 10, 4
CFG = GossipConfig(sites=SITES, levels=LEVELS, mu=1e-3, eta=0.5, gamma=0.4, dither="md5", rounds=1)


def r6(c: Column) -> Column:
    """Six decimals, without a negative zero."""
    return F.round(c, 6) + 0.0


def coords(spark, d) -> DataFrame:
    """Embeddings as one long vector for each of ten sites."""
    e = load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("j", "v"))
    return e.select(F.pmod("vec_id", F.lit(SITES)).cast("int").alias("site"), (F.floor(F.col("vec_id") / SITES) * 64 + F.col("j")).alias("coord"), F.col("v").cast("double").alias("p"))


def residuals(spark, d) -> DataFrame:
    """The same after soft-thresholding: exact zeros among small values."""
    return coords(spark, d).withColumn("p", soft_threshold(F.col("p"), SPARSE))


def symbols(spark, d) -> DataFrame:
    return quantise.range_dither(residuals(spark, d), LEVELS)


def types(spark, d) -> DataFrame:
    return levelset.type_vector(symbols(spark, d), LEVELS)


def site_assignment(spark, d):
    e = load(spark, d, "embeddings").select(topology.assign(F.col("vec_id"), SITES, "modulo").alias("site"), features.split_of(F.col("vec_id").cast("string")).alias("split"))
    return e.groupBy("site", "split").agg(F.count(F.lit(1)).alias("n"))


def split_counts(spark, d):
    docs = load(spark, d, "documents").select(features.split_of(features.copy_group(F.col("text"))).alias("split"), "lang")
    return docs.groupBy("split", "lang").agg(F.count(F.lit(1)).alias("n"))


def prox_sparsity_sweep(spark, d):
    grid = F.explode(F.array(*map(F.lit, (0.0, 0.01, 0.05, 0.1, 0.2)))).alias("mu")
    z = coords(spark, d).select("p", grid).withColumn("z", soft_threshold(F.col("p"), F.col("mu")))
    return z.groupBy("mu").agg(F.count_if(F.col("z") == 0).alias("zeros"), r6(F.sum(F.abs("z"))).alias("l1"))


def prox_embeddings(spark, d):
    return residuals(spark, d).select("site", "coord", r6(F.col("p")).alias("z"))


def residual_range(spark, d):
    return quantise.site_range(residuals(spark, d)).select("site", r6(F.col("lo")).alias("lo"), r6(F.col("hi")).alias("hi"), "d")


def range_dither_symbols(spark, d):
    return symbols(spark, d).groupBy("site", "sym").agg(F.count(F.lit(1)).alias("n"), F.sum("coord").alias("check"))


def range_dither_values(spark, d):
    s = symbols(spark, d)
    for k in ("inner", "none"):
        s = s.withColumn(k, quantise.restore(F.col("sym"), F.col("lo"), F.col("hi"), LEVELS, F.col("d"), k))
    return s.select("site", "coord", r6(F.col("q")).alias("outer"), r6(F.col("inner")).alias("inner"), r6(F.col("none")).alias("none"))


def centred_dither_symbols(spark, d):
    s = quantise.range_dither(residuals(spark, d), LEVELS, grid="centred")
    return s.groupBy("site", "sym").agg(F.count(F.lit(1)).alias("n"), F.sum("coord").alias("check"))


def fixed_range_symbols(spark, d):
    s = quantise.range_dither(residuals(spark, d), LEVELS, bounds=(-0.25, 0.25))
    return s.groupBy("site", "sym").agg(F.count(F.lit(1)).alias("n"), F.sum("coord").alias("check"))


def norm_symbols(spark, d):
    return quantise.norm_dither(residuals(spark, d), LEVELS)


def norm_dither_symbols(spark, d):
    return norm_symbols(spark, d).groupBy("site", "sym").agg(F.count(F.lit(1)).alias("n"), F.sum("coord").alias("check"))


def topk_keep(spark, d):
    return quantise.top_k(residuals(spark, d), 50).select("site", "coord", "rank", r6(F.col("q")).alias("q"))


def randk_keep(spark, d):
    return quantise.rand_k(residuals(spark, d), 50).select("site", "coord", "rank", r6(F.col("q")).alias("q"))


def quantiser_error_ratio(spark, d):
    r = residuals(spark, d)
    range_, norm = quantise.error_ratio(quantise.range_dither(r, LEVELS)), quantise.error_ratio(quantise.norm_dither(r, LEVELS))
    out = range_.select("site", r6(F.col("ratio")).alias("range_ratio")).join(norm.select("site", r6(F.col("ratio")).alias("norm_ratio")), "site")
    n = quantise.site_range(r).select("site", r6(F.col("d") / (LEVELS * LEVELS + F.col("d"))).alias("limit"))
    return out.join(n, "site")


def level_order(spark, d):
    return levelset.level_order(types(spark, d)).select("site", "sym", "cnt", F.col("rank").cast("int").alias("rank"))


def level_entropy(spark, d):
    return levelset.entropy(types(spark, d)).select("site", r6(F.col("f0")).alias("f0"), r6(F.col("entropy")).alias("entropy"))


def bound_of(variant):
    return lambda spark, d: levelset.bound(types(spark, d), variant).select("site", r6(F.col("bound")).alias("bound"))


def run_lengths(spark, d):
    runs = levelset.run_lengths(symbols(spark, d), levelset.level_order(types(spark, d)))
    return runs.groupBy("site", "rank").agg(F.count(F.lit(1)).alias("runs"), F.sum("gap").alias("total"), F.max("gap").alias("longest"), F.sum(F.col("seq") * F.col("gap")).alias("check"))


def golomb_table(spark, d):
    """Code lengths of runs as long as the customers' numbers in the orders."""
    g = load(spark, d, "orders").select(F.col("o_custkey").alias("gap")).filter("gap >= 0").distinct().withColumn("p", F.explode(F.array(*map(F.lit, (0.9, 0.5, 0.3, 0.12, 0.03)))))
    for rule in ("optimal", "rice"):
        g = g.withColumn(rule, golomb_bits(F.col("gap"), golomb_parameter(F.col("p"), rule)).cast("long"))
    return g


def elias_table(spark, d):
    k = load(spark, d, "orders").select(F.col("o_orderkey").alias("k")).filter("k > 0")
    return k.select("k", *(elias_bits(F.col("k"), x).alias(x) for x in ("gamma", "delta", "omega")))


def levelset_bits(spark, d):
    return levelset.bits(symbols(spark, d), LEVELS)


def levelset_bits_by_level(spark, d):
    return levelset.gap_bits(symbols(spark, d), levelset.level_order(types(spark, d))).select("site", F.col("rank").cast("int").alias("rank"), "sym", "m", "runs", "bits")


def levelset_natural_bits(spark, d):
    return levelset.bits(symbols(spark, d), LEVELS, order="natural").select("site", "gap_bits")


def bits_by_coder(spark, d):
    s, n = symbols(spark, d), norm_symbols(spark, d)
    parts = [
        levelset.bits(s, LEVELS).select("site", F.lit("levelset").alias("coder"), (F.col("type_bits") + F.col("gap_bits")).alias("payload_bits")),
        levelset.symbol_bits(n, LEVELS, "sparse").select("site", F.lit("symbol_sparse").alias("coder"), "payload_bits"),
        levelset.symbol_bits(n, LEVELS, "dense").select("site", F.lit("symbol_dense").alias("coder"), "payload_bits"),
        levelset.fixed_bits(s, LEVELS + 2).select("site", F.lit("fixed").alias("coder"), "payload_bits"),
        levelset.raw_bits(s).select("site", F.lit("raw32").alias("coder"), "payload_bits"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def levelset_encode_bytes(spark, d):
    """Real messages, decoded again: their exact length must be the relational one."""
    import pyarrow as pa

    def send(t):
        order = np.argsort(t["coord"].to_numpy())
        sym = t["sym"].to_numpy()[order]
        body = codec.encode(sym, LEVELS, t["lo"][0].as_py(), t["hi"][0].as_py())
        back, *_ = codec.decode(body)
        return pa.table({"site": t["site"].slice(0, 1), "bytes": [len(body)], "bits": [codec.message_bits(sym, LEVELS)], "equal": [bool((back == sym).all())]})

    sent = symbols(spark, d).select("site", "coord", "sym", "lo", "hi").groupBy("site").applyInArrow(send, "site int, bytes long, bits long, equal boolean")
    rel = levelset_bits(spark, d).select("site", (F.col("type_bits") + F.col("gap_bits")).alias("relational_bits"))
    return sent.join(rel, "site")


def levelset_block_bits(spark, d):
    return levelset.block_bits(symbols(spark, d), LEVELS, 1024)


def levelset_messages(spark, d):
    """Messages by block, read back: symbols that differ from those sent."""
    s = symbols(spark, d)
    back = levelset.received(levelset.messages(s, LEVELS, 1024), 1024).select("site", "coord", F.col("sym").alias("got"))
    wrong = F.count_if(~F.col("sym").eqNullSafe(F.col("got")))
    return s.join(back, ["site", "coord"], "full").groupBy("site").agg(F.count(F.lit(1)).alias("n"), wrong.alias("wrong"))


def levelset_implied_bits(spark, d):
    """Gap bits where the dominant level, the last one or none is implied."""
    s, out = symbols(spark, d), None
    for implied in ("dominant", "last", "none"):
        part = levelset.bits(s, LEVELS, implied=implied).select("site", F.lit(implied).alias("implied"), "gap_bits")
        out = part if out is None else out.unionByName(part)
    return out


def symbol_messages(spark, d):
    """Symbol-wise messages by block, read back: their bytes, and symbols that differ from those sent."""
    s = norm_symbols(spark, d)
    sent = levelset.symbol_messages(s, 1024)
    size = sent.groupBy("site").agg(F.sum(F.length("body")).alias("bytes"))
    back = levelset.symbols_received(sent, 1024).select("site", "coord", F.col("sym").alias("got"))
    wrong = F.count_if(~F.col("sym").eqNullSafe(F.col("got")))
    return s.join(back, ["site", "coord"], "full").groupBy("site").agg(F.count(F.lit(1)).alias("n"), wrong.alias("wrong")).join(size, "site")


def index_value_bits(spark, d):
    r = residuals(spark, d)
    return levelset.kept_bits(quantise.top_k(r, 50), quantise.site_range(r))


def norm_values(spark, d):
    """The norm-scaled quantiser unbiased, and divided by its variance factor."""
    unbiased = quantise.norm_dither(residuals(spark, d), LEVELS, rescale=False).withColumn("tau", quantise.norm_factor(LEVELS, F.col("d")))
    scaled = quantise.rescale_unbiased(unbiased.withColumn("unbiased", F.col("q")), F.col("tau"))
    return scaled.select("site", "coord", r6(F.col("unbiased")).alias("unbiased"), r6(F.col("q")).alias("rescaled"))


def residual_quantiles(spark, d):
    r = residuals(spark, d).withColumn("p", F.abs("p"))
    return measures.quantiles(r, [0.5, 0.9, 0.99, 1.0]).select("site", "prob", r6(F.col("value")).alias("value"))


def residual_histogram(spark, d):
    return measures.histogram(residuals(spark, d))


def level_standing(spark, d):
    """Where each level stands among its site's levels by count; a window sees one row a level."""
    from pyspark.sql import Window

    w = Window.partitionBy("site").orderBy("cnt", "sym")
    columns = {"percent": r6(F.percent_rank().over(w)), "share": r6(F.cume_dist().over(w)), "quarter": F.ntile(4).over(w)}
    return types(spark, d).withColumns(columns).select("site", "sym", *columns)


def type_maps(spark, d):
    """The type vector as a map from level to count."""
    t = types(spark, d).groupBy("site").agg(F.map_from_entries(F.collect_list(F.struct("sym", "cnt"))).alias("t"))
    used = F.size(F.map_filter("t", lambda k, v: v > 0))
    return t.select("site", F.element_at("t", F.lit(-1)).alias("zeros"), used.cast("long").alias("used"))


def event_props(spark, d):
    """The key k of the events' JSON by month."""
    e = load(spark, d, "events").select(F.date_format("ts", "yyyy-MM").alias("month"), F.get_json_object("props", "$.k").cast("long").alias("k"))
    return e.groupBy("month").agg(F.count("k").alias("n"), F.sum("k").alias("total"), F.max("k").alias("top"))


def lineitem_residuals(spark, d):
    """Quantities of each part at ten sites of suppliers, less what one supplier line adds on average, thresholded: whole
    vectors over all parts, zero where a site has none."""
    part = load(spark, d, "part").select(F.col("p_partkey").alias("coord"), F.explode(F.sequence(F.lit(0), F.lit(SITES - 1))).alias("site"))
    sold = load(spark, d, "lineitem").groupBy(F.pmod("l_suppkey", F.lit(SITES)).cast("int").alias("site"), F.col("l_partkey").alias("coord")).agg(F.sum("l_quantity").alias("s"))
    rows = part.join(sold, ["site", "coord"], "left")
    return rows.select("site", "coord", soft_threshold(F.coalesce(F.col("s") - 25.0, F.lit(0.0)), 5.0).alias("p"))


def lineitem_bits(spark, d):
    """Bits of the line items' residuals by number of levels."""
    rows, out = lineitem_residuals(spark, d), None
    for levels in (4, 16, 64):
        part = levelset.bits(quantise.range_dither(rows, levels), levels).select("site", F.lit(levels).alias("levels"), "type_bits", "gap_bits")
        out = part if out is None else out.unionByName(part)
    return out


def event_sites(spark, d):
    """The sites that hold events."""
    return load(spark, d, "events").select(F.pmod("user_id", F.lit(SITES)).cast("int").alias("site")).filter("site IS NOT NULL").distinct()


def spectra_closed(spark, d):
    """Second eigenvalue, norm of I - W and safe step of ring and full graph over the sites that hold events."""
    sites, rows = topology.numbered(event_sites(spark, d)).select(F.col("i").alias("site")), []
    for name, m in (("ring", topology.circulant_of(sites)), ("full", topology.full_of(sites))):
        w = topology.matrix(m)
        s = topology.spectrum(w)
        rows.append((name, s["lambda2"], s["beta"], topology.safe_gamma(w, 0.2)))
    out = spark.createDataFrame(rows, "graph string, lambda2 double, beta double, safe_gamma double")
    return out.select("graph", *(r6(F.col(c)).alias(c) for c in ("lambda2", "beta", "safe_gamma")))


def event_pairs_stream(spark, d):
    """event_pairs as a join of two streams, read from the events' file and stored in the shared folder."""
    events = online.file_stream(spark, d, "events")
    viewed, bought = (events.filter(F.col("event_type") == t).select("event_id", "user_id", "ts") for t in ("view", "purchase"))
    pairs = online.pairs(viewed, bought, "user_id", 86400)
    return online.finished(pairs.select("a.user_id"), "event_pairs").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


def stream_messages(spark, d):
    """What each site's stream of events sends along the links of a graph: a stream joined with a static table."""
    events = online.file_stream(spark, d, "events").select(F.pmod("user_id", F.lit(SITES)).cast("int").alias("site"), F.col("value").alias("x"))
    out = online.finished(online.along_links(events, topology.ring(spark, SITES)), "messages")
    return out.groupBy("dst").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("wx"), 2).alias("total"))


def coder_cost(spark, d):
    """Seconds of the relational lengths and of writing messages, by vector size and number of levels."""
    return workloads.coder_cost(spark, [1 << 14, 1 << 17], [4, 64])


def mixing_of(kind):
    """Mixing tables over the sites that hold events."""
    make = {"ring": topology.circulant_of, "full": topology.full_of, "circulant": lambda sites: topology.circulant_of(sites, (1, 2))}[kind]
    return lambda spark, d: make(event_sites(spark, d)).select("src", "dst", r6(F.col("w")).alias("w"))


def nation_mixing(spark, d):
    return topology.metropolis(topology.nation_edges(load(spark, d, "nation")))


def mixing_nation(spark, d):
    return nation_mixing(spark, d).select("src", "dst", r6(F.col("w")).alias("w"))


def mixing_check(spark, d):
    """The nation graph's table with one link cut and one weight raised: what the checks report."""
    bad = nation_mixing(spark, d).filter("NOT (src = 0 AND dst = 5)").withColumn("w", F.when(F.expr("src = 3 AND dst = 3"), F.col("w") + 0.5).otherwise(F.col("w")))
    return topology.check_mixing(bad)


def spectra(spark, d):
    rows = []
    for name, m in (("ring", topology.ring(spark, SITES)), ("full", topology.fully_connected(spark, SITES)), ("nation", nation_mixing(spark, d))):
        w = topology.matrix(m)
        s = topology.spectrum(w)
        rows.append((name, len(w), s["lambda2"], s["gap"], s["beta"], topology.safe_gamma(w, 0.2), topology.connected(w)))
    return spark.createDataFrame(rows, "graph string, sites int, lambda2 double, gap double, beta double, safe_gamma double, connected boolean")


def nation_components(spark, d):
    """Links inside regions only: the parts of the graph."""
    n = load(spark, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("r"))
    inside = n.select(F.col("k").alias("src"), "r").join(n.select(F.col("k").alias("dst"), "r"), "r").filter("src < dst")
    return relational.components(topology.metropolis(inside))


def event_values(spark, d):
    e = load(spark, d, "events").groupBy(F.pmod("user_id", F.lit(SITES)).cast("int").alias("site")).agg(F.avg("value").alias("x"))
    return e.select("site", F.lit(0).alias("coord"), "x")


def gossip_one_round(spark, d):
    v = event_values(spark, d)
    mixed = relational.neighbour_mean(v, topology.ring(spark, SITES), "x")
    return v.join(mixed, ["site", "coord"]).select("site", r6(F.col("x") + 0.4 * (F.col("mixed") - F.col("x"))).alias("x"))


def gossip_mean_preserved(spark, d):
    v = event_values(spark, d)
    mixed = relational.neighbour_mean(v, nation_ring(spark), "x")
    return v.agg(r6(F.avg("x")).alias("before")).crossJoin(mixed.agg(r6(F.avg("mixed")).alias("after")))


def nation_ring(spark):
    return topology.circulant(spark, SITES, (1, 3))


def average_consensus_events(spark, d):
    out = relational.average_consensus(event_values(spark, d), topology.circulant(spark, SITES, (1, 2)), 1.0, 24)
    return out.select("site", F.round("x", 3).alias("x"))


def average_consensus_compressed(spark, d):
    """Averaging with quantised differences."""
    return relational.average_consensus(event_values(spark, d), topology.circulant(spark, SITES, (1, 2)), 0.5, 16, CFG).select("site", "x")


def language_rows(spark, d):
    docs = load(spark, d, "documents")
    return gradients.long_rows(features.language_samples(docs, SITES, 64).filter("split = 'train'"))


def fixed_model(spark, n, classes=None):
    f = spark.range(n).select(F.col("id").cast("int").alias("feature"))
    if classes:
        f = f.withColumn("class", F.explode(F.sequence(F.lit(0), F.lit(classes - 1))))
    return f.withColumn("w", uniform("model", *(F.col(c) for c in f.columns)) - 0.5)


def softmax_gradient(spark, d):
    g = gradients.softmax_gradient(language_rows(spark, d), fixed_model(spark, 65, CLASSES), CLASSES)
    return g.select("site", "coord", r6(F.col("g")).alias("g"))


def bernoulli_batch(spark, d):
    s = features.language_samples(load(spark, d, "documents"), SITES, 64).filter("split = 'train'")
    return gradients.bernoulli_batch(s, 0.25, 1).groupBy("site").agg(F.count(F.lit(1)).alias("n"), F.sum("sample_id").alias("check"))


def objective_fixed(spark, d):
    """Loss, L1 term and objective of each site at one model."""
    model = fixed_model(spark, 65, CLASSES)
    loss = gradients.softmax_loss(gradients.softmax_scores(language_rows(spark, d), model))
    sites = F.explode(F.sequence(F.lit(0), F.lit(SITES - 1))).alias("site")
    state = model.select(sites, (F.col("feature") * CLASSES + F.col("class")).alias("coord"), F.col("w").alias("x"))
    return measures.objective(loss, state, CFG.mu).select("site", *(r6(F.col(c)).alias(c) for c in ("data_loss", "l1", "total")))


def accuracy_fixed(spark, d):
    scores = gradients.softmax_scores(language_rows(spark, d), fixed_model(spark, 65, CLASSES))
    return gradients.softmax_accuracy(scores).select("site", r6(F.col("accuracy")).alias("accuracy"))


def margin_gradient(kind):
    def query(spark, d):
        s = features.quality_samples(load(spark, d, "documents"), load(spark, d, "labels"), "quality", SITES, 64).filter("split = 'train'")
        return gradients.margin_gradient(gradients.long_rows(s), fixed_model(spark, 65), kind).select("site", "coord", r6(F.col("g")).alias("g"))

    return query


def first_round(spark, d, cfg):
    """Round 1 from the all-zero start on the language task, with differences rounded before the quantiser."""
    g = gradients.softmax_start_gradient(language_rows(spark, d), CLASSES)
    grid = spark.range(SITES).select(F.col("id").cast("int").alias("site"), F.explode(F.sequence(F.lit(0), F.lit(65 * CLASSES - 1))).alias("coord"))
    return relational.one_round(relational.start(grid), g, topology.ring(spark, SITES), cfg, 1, decimals=9)


def round1(**change):
    cfg = replace(CFG, **change)
    return lambda spark, d: first_round(spark, d, cfg).select("site", "coord", r6(F.col("x")).alias("x"), r6(F.col("y")).alias("y"), r6(F.col("z")).alias("z"))


def stationarity_round1(spark, d):
    out = first_round(spark, d, CFG)
    zero = out.select("site", "coord", F.lit(0.0).alias("x"))
    return measures.stationarity(zero, out, CFG.eta).select("site", r6(F.col("norm2")).alias("norm2"))


def tracking_round1(spark, d):
    g = gradients.softmax_start_gradient(language_rows(spark, d), CLASSES)
    grid = spark.range(SITES).select(F.col("id").cast("int").alias("site"), F.explode(F.sequence(F.lit(0), F.lit(65 * CLASSES - 1))).alias("coord"))
    out = relational.tracking_round(relational.tracking_start(grid), g, topology.ring(spark, SITES), replace(CFG, method="tracking"), 1, decimals=9)
    return out.select("site", "coord", *(r6(F.col(c)).alias(c) for c in ("x", "y", "z", "track", "track_y")))


def stationarity_at_mean(spark, d):
    """The mean model after round 1, with full gradients."""
    mean = first_round(spark, d, CFG).groupBy("coord").agg(F.avg("x").alias("x"))
    model = mean.select(F.floor(F.col("coord") / CLASSES).cast("int").alias("feature"), F.pmod("coord", F.lit(CLASSES)).alias("class"), F.col("x").alias("w"))
    g = gradients.softmax_gradient(language_rows(spark, d), model, CLASSES).groupBy("coord").agg((F.sum("g") / SITES).alias("g"))
    return measures.stationarity_at_mean(mean, g, CFG.mu, CFG.eta).select(r6(F.col("norm2")).alias("norm2"))


def consensus_error_round1(spark, d):
    return measures.consensus_error(first_round(spark, d, CFG)).select(r6(F.col("error")).alias("error"))


def consensus_violation_round1(spark, d):
    return measures.consensus_violation(first_round(spark, d, CFG), topology.ring(spark, SITES)).select(r6(F.col("error")).alias("error"))


def zero_share_round1(spark, d):
    return measures.zero_share(first_round(spark, d, replace(CFG, mu=0.01))).select("site", r6(F.col("zero_share")).alias("zero_share"))


def support_overlap_round1(spark, d):
    return measures.support_overlap(first_round(spark, d, replace(CFG, mu=0.01))).select("a", "b", r6(F.col("jaccard")).alias("jaccard"))


def hashed_words(spark, d):
    h = features.hashed_words(load(spark, d, "documents"), 256)
    return h.groupBy("feature").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("n"))


def order_trace(spark, d):
    """A made-up trace: priorities are runs, orders by key are rounds; one run never reaches the cut-off."""
    from pyspark.sql import Window

    o = load(spark, d, "orders").select(F.col("o_orderpriority").alias("run_id"), "o_orderkey")
    n = F.row_number().over(Window.partitionBy("run_id").orderBy("o_orderkey"))
    t = o.withColumn("round", n).withColumn("bits", 1000 + F.col("o_orderkey") % 977)
    cap = F.when(F.col("run_id") == "5-LOW", 0.5).otherwise(1.0)
    return t.withColumn("accuracy", F.round(cap * (1 - 20.0 / (20.0 + F.col("round"))), 6))


def cumulative_bits(spark, d):
    return measures.cumulative(order_trace(spark, d)).select("run_id", "round", "cum_bits")


def bits_to_cutoff(spark, d):
    return measures.to_target(order_trace(spark, d), 0.7)


def bit_saving(spark, d):
    return measures.saving(measures.to_target(order_trace(spark, d), 0.7)).select("run_a", "run_b", r6(F.col("saving")).alias("saving"))


def rate_slope(spark, d):
    return measures.slope(order_trace(spark, d).withColumn("miss", 1 - F.col("accuracy")), "miss").select("run_id", r6(F.col("slope")).alias("slope"))


def moving_accuracy(spark, d):
    return measures.moving_average(order_trace(spark, d), "accuracy").select("run_id", "round", r6(F.col("accuracy_ma")).alias("ma"))


def table_r_rollup(spark, d):
    t = measures.to_target(order_trace(spark, d), 0.7)
    return t.rollup("reached", "run_id").agg(F.sum("cum_bits").alias("bits"), F.grouping_id().cast("long").alias("level"))


def laplace_fit(spark, d):
    return measures.laplace_fit(coords(spark, d)).select("site", r6(F.col("rho")).alias("rho"), r6(F.col("ks")).alias("ks"))


def vector_sizes(spark, d):
    """(site, d): coordinates of each site's vector of embeddings."""
    e = load(spark, d, "embeddings").select(F.pmod("vec_id", F.lit(SITES)).cast("int").alias("site"), F.size("embedding").alias("k"))
    return e.groupBy("site").agg(F.sum("k").alias("d"))


def rate_curves(spark, d):
    c = theory.rate_curves(vector_sizes(spark, d), [2, 4, 8, 16, 64, 256])
    return c.select("site", "d", "levels", *(r6(F.col(x)).alias(x) for x in ("proposed", "symbolwise", "laplace_rate")))


def stationarity_bound(spark, d):
    """The bound for models as large as each site's vector; one row a site comes to the driver."""
    rows = [
        (r.site, T, n, theory.stationarity_bound(1.4, 1.0, 1.0, 0.5, 1e-3, r.d, n, T, 0.87268, theory.tau_range(r.d, 16)))
        for r in vector_sizes(spark, d).collect() for T in (100, 10000, 1000000) for n in (2, 10, 50)
    ]
    return spark.createDataFrame(rows, "site int, rounds long, sites long, bound double").select("site", "rounds", "sites", r6(F.col("bound")).alias("bound"))


def range_coverage(spark, d):
    """Embeddings whose range a Laplace law of their mean size covers with probability 0.99."""
    rows = load(spark, d, "embeddings").select(F.col("vec_id").alias("rep"), F.explode("embedding").alias("p")).withColumn("p", F.col("p").cast("double"))
    return theory.range_coverage(rows, 0.01).select("vectors", r6(F.col("covered")).alias("covered"))


def event_windows(spark, d):
    return online.windows(load(spark, d, "events")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n", F.round("total", 2).alias("total"))


def event_sessions(spark, d):
    s = online.sessions(load(spark, d, "events"))
    return s.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def asof_events(spark, d):
    """The last signup of a user before each purchase."""
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    bought, signed = (e.filter(F.col("event_type") == t).drop("event_type") for t in ("purchase", "signup"))
    return joins.as_of(bought, signed, "user_id", "ts", "event_id").select("event_id", "event_id_as_of")


def event_pairs(spark, d):
    """Purchases within a day after a view, by user."""
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    viewed, bought = (e.filter(F.col("event_type") == t).drop("event_type") for t in ("view", "purchase"))
    return joins.interval(viewed, bought, "user_id", "ts", 86400).groupBy(F.col("a.user_id").alias("user_id")).agg(F.count(F.lit(1)).alias("n"))


def train_language(spark, d):
    """The distributed trainer: Spark computes each round's gradients."""
    s = features.language_samples(load(spark, d, "documents"), SITES, 256)
    s = s.withColumn("bucket", F.pmod(F.xxhash64("sample_id"), F.lit(8)).cast("int"))
    stored = relational.cut(s, "samples")
    return trainers.train(stored, topology.matrix(topology.ring(spark, SITES)), replace(CFG, dither="fast", rounds=12, eval_every=6, eta=1.0)).trace


def relational_task(spark, d):
    """(grid of sites and coordinates, gradient) of the language task as joins over stored samples."""
    stored = relational.cut(language_rows(spark, d), "rows")
    grid = spark.range(SITES).select(F.col("id").cast("int").alias("site"), F.explode(F.sequence(F.lit(0), F.lit(65 * CLASSES - 1))).alias("coord"))
    return grid, lambda x, t: site_softmax(stored, x)


def train_relational(spark, d):
    """Three rounds in the coordinate layout, gradients as joins."""
    grid, gradient = relational_task(spark, d)
    out = relational.run(relational.start(grid), gradient, topology.ring(spark, SITES), replace(CFG, rounds=3), decimals=9)
    return out.select("site", "coord", *(r6(F.col(c)).alias(c) for c in ("x", "y", "z")))


def relational_trace(spark, d):
    """Bits, messages and measures of two rounds in the coordinate layout, for methods and compressors."""
    grid, gradient = relational_task(spark, d)
    ring, out = topology.ring(spark, SITES), None
    changes = {"sparse_range_levelset": {}, "tracking_range_levelset": {"method": "tracking"}, "topk_index": {"compressor": "topk", "coder": "index", "gamma": 0.05}}
    for name, change in changes.items():
        trace = relational.run_traced(relational.start(grid), gradient, ring, replace(CFG, rounds=2, dither="fast", **change))[1].withColumn("run_id", F.lit(name))
        out = trace if out is None else out.unionByName(trace)
    return out


def site_softmax(rows, x):
    """Gradient where every site has its own model (site, coord, x)."""
    model = x.select("site", F.floor(F.col("coord") / CLASSES).alias("feature"), F.pmod("coord", F.lit(CLASSES)).alias("class"), F.col("x").alias("w"))
    from pyspark.sql import Window

    scores = rows.join(model, ["site", "feature"]).groupBy("sample_id", "site", "label", "class").agg(F.sum(F.col("val") * F.col("w")).alias("s"))
    w = Window.partitionBy("sample_id")
    e = F.exp(F.col("s") - F.max("s").over(w))
    prob = scores.withColumn("e", e).withColumn("miss", F.col("e") / F.sum("e").over(w) - (F.col("class") == F.col("label")).cast("double")).select("sample_id", "class", "miss")
    total = rows.join(prob, "sample_id").groupBy("site", (F.col("feature") * CLASSES + F.col("class")).alias("coord")).agg(F.sum(F.col("val") * F.col("miss")).alias("t"))
    return total.join(F.broadcast(gradients.counts(rows)), "site").select("site", "coord", (F.col("t") / F.col("n_site")).alias("g"))


def planted_training(spark, d):
    """Tabular task: line items with planted labels, logistic loss, trained where the rows are."""
    s = features.tabular_samples(load(spark, d, "lineitem"), load(spark, d, "orders"), load(spark, d, "part"), SITES)
    stored = relational.cut(s, "tabular")
    cfg = replace(CFG, dither="fast", rounds=8, eval_every=8, batch=None, eta=2.0)
    return trainers.train(stored, topology.matrix(topology.ring(spark, SITES)), cfg, "logistic", 9, 2).trace


def quality_runs(spark, d):
    """Binary tasks with logistic and hinge loss: quality, and toxic as the control."""
    docs, labels, out = load(spark, d, "documents"), load(spark, d, "labels"), None
    ring = {"ring": topology.matrix(topology.ring(spark, SITES))}
    for target in ("quality", "toxic"):
        pool = trainers.pooled(features.quality_samples(docs, labels, target, SITES), 257, SITES)
        for loss in ("logistic", "hinge"):
            t = trainers.sweep(spark, workloads.runs_of(ring, {loss: replace(workloads.BASE, rounds=60, eval_every=60)}, target), pool, loss, 257, 2)
            out = t if out is None else out.unionByName(t)
    return out.groupBy("run_id").agg(F.max("accuracy").alias("accuracy"), F.sum("link_bits").alias("link_bits"))


def language_net(spark, d):
    """The three-layer net on the language task."""
    ring = {"ring": topology.matrix(topology.ring(spark, SITES))}
    cfgs = {"sparse": replace(workloads.BASE, rounds=30, eta=0.5, eval_every=10)}
    return trainers.sweep(spark, workloads.runs_of(ring, cfgs, "language"), workloads.language_pool(spark, d), "mlp3", 257, 4).filter("accuracy IS NOT NULL").select("run_id", "round", "loss", "accuracy", "link_bits")


W = workloads
QUERIES = {
    "site_assignment": site_assignment, "split_counts": split_counts, "prox_embeddings": prox_embeddings, "prox_sparsity_sweep": prox_sparsity_sweep,
    "residual_range": residual_range, "range_dither_symbols": range_dither_symbols, "range_dither_values": range_dither_values, "centred_dither_symbols": centred_dither_symbols,
    "fixed_range_symbols": fixed_range_symbols, "norm_dither_symbols": norm_dither_symbols, "topk_keep": topk_keep, "randk_keep": randk_keep, "quantiser_error_ratio": quantiser_error_ratio,
    "type_vector": types, "level_order": level_order, "level_entropy": level_entropy, "levelset_bound_printed": bound_of("printed"), "levelset_bound_sound": bound_of("sound"),
    "run_lengths": run_lengths, "golomb_bits": golomb_table, "elias_bits": elias_table, "levelset_bits": levelset_bits, "levelset_bits_by_level": levelset_bits_by_level,
    "levelset_natural_bits": levelset_natural_bits, "bits_by_coder": bits_by_coder, "levelset_encode_bytes": levelset_encode_bytes,
    "mixing_ring": mixing_of("ring"), "mixing_fc": mixing_of("full"), "mixing_circulant": mixing_of("circulant"), "mixing_nation": mixing_nation, "mixing_check": mixing_check, "mixing_spectra": spectra,
    "gossip_one_round": gossip_one_round, "gossip_mean_preserved": gossip_mean_preserved, "average_consensus_events": average_consensus_events,
    "softmax_gradient": softmax_gradient, "logistic_gradient": margin_gradient("logistic"), "hinge_gradient": margin_gradient("hinge"), "least_squares_gradient": margin_gradient("least_squares"),
    "sparse_gossip_round1": round1(), "plain_gossip_round1": round1(method="plain"), "exact_gossip_round1": round1(method="exact", compressor="identity", coder="raw"),
    "plain_norm_round1": round1(method="plain", compressor="norm", coder="symbol"), "stationarity_round1": stationarity_round1, "consensus_error_round1": consensus_error_round1,
    "consensus_violation_round1": consensus_violation_round1, "zero_share_round1": zero_share_round1, "support_overlap_round1": support_overlap_round1, "hashed_words": hashed_words,
    "cumulative_bits": cumulative_bits, "bits_to_cutoff": bits_to_cutoff, "bit_saving": bit_saving, "rate_slope": rate_slope, "moving_accuracy": moving_accuracy, "table_r_rollup": table_r_rollup,
    "laplace_fit": laplace_fit, "rate_curves": rate_curves, "stationarity_bound": stationarity_bound, "event_windows": event_windows, "event_sessions": event_sessions,
    "train_language": train_language, "train_relational": train_relational, "relational_trace": relational_trace, "train_tabular": planted_training, "quality_runs": quality_runs, "language_net": language_net,
    "table_r": W.table_r, "language_targets": lambda s, d: W.targets(W.language_traces(s, d)), "language_curves": lambda s, d: W.language_traces(s, d).filter("accuracy IS NOT NULL"),
    "method_savings": W.method_savings, "tuned_targets": W.tuned_targets, "mu_sweep": W.mu_sweep, "level_sweep": W.level_sweep, "speedup": W.speedup, "rate_slopes": W.rate_slopes, "other_compressors": W.other_compressors,
    "levelset_block_bits": levelset_block_bits, "levelset_messages": levelset_messages, "nation_components": nation_components, "average_consensus_compressed": average_consensus_compressed,
    "bernoulli_batch": bernoulli_batch, "objective_fixed": objective_fixed, "accuracy_fixed": accuracy_fixed, "tracking_round1": tracking_round1, "stationarity_at_mean": stationarity_at_mean,
    "asof_events": asof_events, "event_pairs": event_pairs, "central_prox": W.central_prox, "label_skew": W.label_skew, "problem_constants": W.problem_constants,
    "ablation_report": W.ablation_report, "tracking_report": W.tracking_report, "net_targets": W.net_targets,
    "net_curves": lambda s, d: W.curves(W.net_traces(s, d)), "vector_curves": lambda s, d: W.curves(W.vector_traces(s, d)),
    "levelset_implied_bits": levelset_implied_bits, "symbol_messages": symbol_messages, "index_value_bits": index_value_bits, "norm_values": norm_values,
    "residual_quantiles": residual_quantiles, "residual_histogram": residual_histogram, "level_standing": level_standing, "type_maps": type_maps,
    "event_props": event_props, "lineitem_bits": lineitem_bits, "spectra_closed": spectra_closed, "event_pairs_stream": event_pairs_stream,
    "stream_messages": stream_messages, "coder_cost": coder_cost,
    "laplace_study": lambda s, d: W.laplace_study(s), "range_coverage": range_coverage,
}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three distributed rounds of sparse compressed gossip on the language task."""
    s = features.language_samples(load(spark, sf_dir, "documents"), 4, 256)
    stored = relational.cut(s.withColumn("bucket", F.lit(0)), "samples")
    cfg = replace(CFG, sites=4, rounds=3, batch=None, dither="fast", eval_every=3)
    return trainers.train(stored, topology.matrix(topology.ring(spark, 4)), cfg).trace
