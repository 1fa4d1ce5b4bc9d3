"""Experiment workloads on the given tables: compared methods, sweeps, ablations, studies."""

from __future__ import annotations

import time
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import fast_uniform, laplace
from ..operators import codec, features, levelset, quantise, theory, topology
from ..operators.losses import LOSSES
from ..operators.measures import saving, slope, to_target
from ..sources.tables import load
from .config import GossipConfig, paper_methods
from .trainers import Pool, pooled, site_gradients, site_grams, sweep

SITES, WORDS = 10, 256
#: Shared by all methods and not tuned; tuned_targets gives each method its own number of levels.
BASE = GossipConfig(sites=SITES, rounds=150, eta=1.0, eval_every=2)
VECTORS = replace(BASE, eta=0.1, rounds=80)


def graphs(spark: SparkSession) -> dict[str, np.ndarray]:
    return {"ring": topology.matrix(topology.ring(spark, SITES)), "full": topology.matrix(topology.fully_connected(spark, SITES))}


def language_pool(spark: SparkSession, sf_dir: str) -> Pool:
    return pooled(features.language_samples(load(spark, sf_dir, "documents"), SITES, WORDS), WORDS + 1, SITES)


def vector_pool(spark: SparkSession, sf_dir: str) -> Pool:
    return pooled(features.vector_samples(load(spark, sf_dir, "embeddings"), SITES), 65, SITES)


def runs_of(graph: dict[str, np.ndarray], configs: dict[str, GossipConfig], label: str) -> list:
    return [(f"{label}/{g}/{c}", w, cfg) for g, w in graph.items() for c, cfg in configs.items()]


def language_traces(spark: SparkSession, sf_dir: str, configs: dict[str, GossipConfig] | None = None, graph: dict | None = None) -> DataFrame:
    """The language task, a linear model of 1028 weights, compared methods on both graphs."""
    return sweep(spark, runs_of(graph or graphs(spark), configs or paper_methods(BASE), "language"), language_pool(spark, sf_dir))


def vector_traces(spark: SparkSession, sf_dir: str, configs: dict[str, GossipConfig] | None = None, graph: dict | None = None) -> DataFrame:
    """Embeddings with planted labels and the residual dense net."""
    cfgs = configs or paper_methods(VECTORS)
    return sweep(spark, runs_of(graph or graphs(spark), cfgs, "vectors"), vector_pool(spark, sf_dir), "residual_mlp", 65, 10)


def named(trace: DataFrame) -> DataFrame:
    part = F.split("run_id", "/")
    return trace.withColumns({"workload": part[0], "graph": part[1], "method": part[2]})


def targets(trace: DataFrame, share: float = 0.97) -> DataFrame:
    """Bits and rounds to the cut-off of each workload and graph: a share of the exact method's best validation
    accuracy there. Rows (workload, graph, method, cutoff, reached, rounds, cum_bits, accuracy)."""
    t = named(trace)
    best = t.filter("method = 'exact'").groupBy("workload", "graph").agg((F.max("validation") * share).alias("cutoff"))
    t = t.join(F.broadcast(best), ["workload", "graph"]).withColumn("ok", (F.col("validation") >= F.col("cutoff")).cast("int"))
    hit = to_target(t, 1, "ok", "link_bits")
    end = t.groupBy("run_id", "workload", "graph", "method", "cutoff").agg(F.max_by("accuracy", F.when(F.col("accuracy").isNotNull(), F.col("round"))).alias("final_accuracy"), F.avg("zero_share").alias("zero_share"))
    return end.join(hit, "run_id")


def net_traces(spark: SparkSession, sf_dir: str, configs: dict[str, GossipConfig] | None = None, graph: dict | None = None) -> DataFrame:
    """The language task with the three-layer net of 18,624 weights, compared methods on both graphs."""
    cfgs = configs or paper_methods(replace(BASE, eta=0.5, rounds=80, mu=1e-4))
    return sweep(spark, runs_of(graph or graphs(spark), cfgs, "net"), language_pool(spark, sf_dir), "mlp3", WORDS + 1, 4)


def table_r(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Communication until the cut-off: a row for each method, for each setting (three-layer net or image-like task, ring or
    fully connected) the KiB, the rounds and whether the cut-off was reached; else the figures are those of the whole run."""
    trace = net_traces(spark, sf_dir).unionByName(vector_traces(spark, sf_dir))
    t = targets(trace).withColumn("setting", F.concat_ws("_", "workload", "graph"))
    cell = [F.round(F.first("cum_bits") / 8192, 2).alias("kib"), F.first("rounds").alias("rounds"), F.first("reached").alias("reached")]
    return t.groupBy("method").pivot("setting", ["net_ring", "net_full", "vectors_ring", "vectors_full"]).agg(*cell)


def curves(trace: DataFrame) -> DataFrame:
    """(workload, graph, method, round, cum_bits, accuracy, validation, loss, objective): what the curves show, at the
    rounds that were evaluated."""
    w = Window.partitionBy("run_id").orderBy("round")
    t = named(trace.withColumn("cum_bits", F.sum("link_bits").over(w))).filter("accuracy IS NOT NULL")
    return t.select("workload", "graph", "method", "round", "cum_bits", "accuracy", "validation", "loss", "objective")


def mu_runs(base: GossipConfig, mus) -> dict[str, GossipConfig]:
    return {f"mu={m:g}": replace(base, mu=m) for m in mus} | {"exact": replace(base, method="exact", compressor="identity", coder="raw")}


def mu_sweep(spark: SparkSession, sf_dir: str, mus=(0.0, 1e-4, 1e-3, 5e-3, 1e-2)) -> DataFrame:
    """Weights of the L1 term on the ring: the linear language model and the residual net of the image-like task."""
    ring = {"ring": graphs(spark)["ring"]}
    words = language_traces(spark, sf_dir, mu_runs(BASE, mus), ring)
    return targets(words.unionByName(vector_traces(spark, sf_dir, mu_runs(VECTORS, mus), ring)))


def level_sweep(spark: SparkSession, sf_dir: str, levels=(4, 8, 16, 64, 256)) -> DataFrame:
    ring = {"ring": graphs(spark)["ring"]}
    cfgs = {f"L={x}": replace(BASE, levels=x) for x in levels} | {"exact": replace(BASE, method="exact", compressor="identity", coder="raw")}
    return targets(language_traces(spark, sf_dir, cfgs, ring))


def tuned_targets(spark: SparkSession, sf_dir: str, levels=(2, 4, 8, 16)) -> DataFrame:
    """Each method at its own number of levels, from one grid: the cheapest setting that reaches the cut-off on
    validation, on the ring."""
    ring, cfgs = {"ring": graphs(spark)["ring"]}, {}
    for name, cfg in paper_methods(BASE).items():
        cfgs |= {name: cfg} if name == "exact" else {f"{name}:{x}": replace(cfg, levels=x) for x in levels}
    t = targets(language_traces(spark, sf_dir, cfgs, ring)).filter("reached")
    each = t.withColumn("setting", F.col("method")).withColumn("method", F.split("method", ":")[0])
    best = F.min_by(F.struct("setting", "rounds", "cum_bits", "final_accuracy", "zero_share"), F.struct("cum_bits", "setting"))
    return each.groupBy("method").agg(best.alias("b")).select("method", "b.*")


def method_savings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per cent of bits that each method saves against each other one on the language task."""
    t = targets(language_traces(spark, sf_dir))
    out = None
    for g in ("ring", "full"):
        s = saving(t.filter(F.col("graph") == g)).withColumn("graph", F.lit(g))
        out = s if out is None else out.unionByName(s)
    return out


def net_targets(spark: SparkSession, sf_dir: str, mus=(1e-4, 1e-3)) -> DataFrame:
    """The three-layer net on the language task, both graphs: bits to the cut-off of every method, the sparse ones at each
    weight of the L1 term; all rows are reported."""
    base = replace(BASE, eta=0.5, rounds=80)
    cfgs = {}
    for name, cfg in paper_methods(base).items():
        cfgs |= {f"{name}:mu={m:g}": replace(cfg, mu=m) for m in mus} if name.startswith(("sparse", "tracking")) else {name: replace(cfg, mu=mus[0])}
    return targets(net_traces(spark, sf_dir, cfgs))


def ablation_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the sparse step and what the coder save by themselves: one difference a row, both graphs."""
    pairs = {"sparse step": ("sparse_range_levelset", "plain_range_levelset"), "quantiser and coder": ("plain_range_levelset", "plain_norm_symbol")}
    t = targets(language_traces(spark, sf_dir, {k: v for k, v in paper_methods(BASE).items() if not k.startswith("tracking")})).select("graph", "method", "reached", "rounds", "cum_bits").cache()
    out = None
    for name, (a, b) in pairs.items():
        left, right = (t.filter(F.col("method") == m).select("graph", F.col("cum_bits").alias(f"bits_{k}"), F.col("reached").alias(f"reached_{k}")) for k, m in (("with", a), ("without", b)))
        row = left.join(right, "graph").withColumns({"effect": F.lit(name), "saving": 100 * (1 - F.col("bits_with") / F.col("bits_without"))})
        out = row if out is None else out.unionByName(row)
    return out


def tracking_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds, messages and bits to the cut-off of the method and of tracking, which sends two messages a round."""
    keep = ("sparse_range_levelset", "tracking_range_levelset", "exact")
    trace = language_traces(spark, sf_dir, {k: v for k, v in paper_methods(BASE).items() if k in keep}).cache()
    sent = trace.groupBy("run_id").agg(F.max("messages").alias("messages_a_round"))
    return targets(trace).join(sent, "run_id").select("graph", "method", "reached", "rounds", "messages_a_round", "cum_bits", "final_accuracy")


def central_prox(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All samples in one place: proximal steps without communication, beside ten sites' rounds on both graphs."""
    pool = language_pool(spark, sf_dir)
    one = pool.at_sites(F.lit(0), 1)
    # the batch of one place is as large as the batches of all sites together
    cfg = replace(BASE, sites=1, batch=BASE.batch * SITES, method="dsgd", rounds=60, eval_every=20)
    central = sweep(spark, [("language/central/prox", np.ones((1, 1)), cfg)], one)
    many = sweep(spark, runs_of(graphs(spark), {"sparse": replace(BASE, rounds=60, eval_every=20)}, "language"), pool)
    both = central.unionByName(many).filter("accuracy IS NOT NULL")
    return both.select("run_id", "round", "loss", "objective", "accuracy", "validation", "zero_share")


def label_skew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sites that hold one language each (eight sites, two a language) against the same samples dealt by id."""
    iid, out = pooled(features.language_samples(load(spark, sf_dir, "documents"), 8, WORDS), WORDS + 1, 8), None
    skewed = iid.at_sites(F.col("label") * 2 + F.pmod("sample_id", F.lit(2)), 8)
    w = topology.matrix(topology.ring(spark, 8))
    for name, pool in (("iid", iid), ("skewed", skewed)):
        t = sweep(spark, [(f"language/ring/{name}", w, replace(BASE, sites=8, rounds=60, eval_every=60))], pool)
        out = t if out is None else out.unionByName(t)
    return out.groupBy("run_id").agg(F.max("accuracy").alias("accuracy"), F.avg("consensus").alias("consensus"), F.sum("link_bits").alias("link_bits"))


def problem_constants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smoothness, gradient and variance constants of the language task at the zero model, and the second moments
    of the sites' mini-batch gradients beside their bound 2 n (G^2 + sigma^2)."""
    pool, loss = language_pool(spark, sf_dir), LOSSES["softmax"](WORDS + 1, 4)
    sizes, zero = pool.sizes, loss.start()
    full = site_gradients(pool.fit, np.tile(zero, (SITES, 1)), loss, WORDS + 1)[0]
    starts, draws = theory.drawn(sizes, WORDS + 1)
    rng = np.random.default_rng(1)
    batches = {s: [rng.choice(n, min(16, n), replace=False) for _ in range(64)] for s, n in enumerate(sizes.tolist()) if n}
    rows = pool.picked({s: np.unique(np.concatenate([*draws[s], *batches[s]])) for s in batches})
    spread = {s: [loss.value_grad(zero, *rows.take(s, p))[1] for p in draws[s]] for s in draws}
    c = theory.constants(site_grams(pool.fit, SITES, WORDS + 1), starts, full, spread)
    moment = sum((float(np.mean([(loss.value_grad(zero, *rows.take(s, p))[1] ** 2).sum() for p in picks])) for s, picks in batches.items()), 0.0)
    limit = 2 * SITES * (c["G"] ** 2 + c["sigma2"])
    return spark.createDataFrame([(c["K"], c["G"], c["sigma2"], moment, limit)], "smoothness double, gradient double, variance double, second_moment double, second_moment_limit double")


def speedup(spark: SparkSession, sf_dir: str, sizes=(2, 5, 10, 20)) -> DataFrame:
    """Mean stationarity of runs of more sites over the same documents."""
    docs, out = language_pool(spark, sf_dir), None
    for n in sizes:
        pool = docs.at_sites(F.pmod("sample_id", F.lit(n)), n)
        w = topology.matrix(topology.fully_connected(spark, n))
        s = sweep(spark, [(f"language/full/n={n}", w, replace(BASE, sites=n, rounds=60, eval_every=60))], pool)
        s = s.groupBy("run_id").agg(F.avg("stationarity").alias("stationarity"), F.max("accuracy").alias("accuracy")).withColumn("sites", F.lit(n))
        out = s if out is None else out.unionByName(s)
    return out


def rate_slopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Log-log slopes of stationarity and consensus over rounds."""
    trace = language_traces(spark, sf_dir, {"sparse": BASE}).cache()
    return slope(trace, "stationarity").withColumnRenamed("slope", "stationarity_slope").join(slope(trace, "consensus").withColumnRenamed("slope", "consensus_slope"), "run_id")


def other_compressors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Further operators under the same scheme, with a smaller consensus step where they contract less."""
    cfgs = {
        "topk": replace(BASE, compressor="topk", coder="index", gamma=0.05), "randk": replace(BASE, compressor="randk", coder="index", gamma=0.02),
        "centred": replace(BASE, grid="centred"), "fixed": replace(BASE, coder="raw"), "diminishing": replace(BASE, decay=0.5, eta=4.0), "dsgd": replace(BASE, method="dsgd"),
        "local": replace(BASE, method="local"), "full_batch": replace(BASE, batch=None), "exact": replace(BASE, method="exact", compressor="identity", coder="raw"),
    }
    return targets(language_traces(spark, sf_dir, cfgs, {"ring": graphs(spark)["ring"]}))


def laplace_study(spark: SparkSession, dims=(1000, 20000), levels=(2, 4, 8, 64), eps: float = 0.01) -> DataFrame:
    """Measured entropy and code length, sound and printed bound, and the closed form, for generated Laplace vectors."""
    out = None
    for i, d in enumerate(dims):
        p = spark.range(d).select(F.lit(i).alias("site"), F.col("id").alias("coord"), laplace(fast_uniform(7, d, F.col("id")), 1.0).alias("p"))
        for x in levels:
            q = quantise.range_dither(p, x).cache()
            types = levelset.type_vector(q, x)
            row = levelset.entropy(types).join(levelset.bits(q, x), "site").join(levelset.bound(types, "sound").withColumnRenamed("bound", "sound"), "site")
            row = row.join(levelset.bound(types, "printed").withColumnRenamed("bound", "printed"), "site")
            row = row.select(F.lit(d).alias("d"), F.lit(x).alias("levels"), "entropy", (F.col("gap_bits") / d).alias("code"), "sound", "printed")
            row = row.withColumn("closed_form", theory.laplace_rate(F.lit(float(d)), F.lit(float(x)), eps))
            out = row if out is None else out.unionByName(row)
    return out


def coder_cost(spark: SparkSession, dims: list[int], levels: list[int], sites: int = 4) -> DataFrame:
    """(d, levels, seconds, message_seconds, message_bits): wall time of the relational lengths of generated Laplace vectors
    at all sites and of writing one site's message, there the least of three tries."""
    rows = []
    for d in dims:
        at = spark.range(d * sites).select((F.col("id") % sites).cast("int").alias("site"), F.floor(F.col("id") / sites).alias("coord"))
        p = at.withColumn("p", laplace(fast_uniform(7, F.col("site"), F.col("coord")), 1.0))
        for x in levels:
            q = quantise.range_dither(p, x).select("site", "coord", "sym").cache()
            sym = np.array([r.sym for r in q.filter("site = 0").orderBy("coord").select("sym").toLocalIterator()])
            q.count()
            relational = _seconds(lambda: levelset.bits(q, x).write.format("noop").mode("overwrite").save())
            written = min(_seconds(lambda: codec.encode(sym, x)) for _ in range(3))
            rows.append((d, x, relational, written, codec.message_bits(sym, x)))
            q.unpersist()
    return spark.createDataFrame(rows, "d long, levels int, seconds double, message_seconds double, message_bits long")


def _seconds(action) -> float:
    start = time.perf_counter()
    action()
    return time.perf_counter() - start
