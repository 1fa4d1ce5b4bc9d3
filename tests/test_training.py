from dataclasses import replace

import numpy as np
import pytest
from gossipkit.operators import topology
from gossipkit.operators.losses import LOSSES
from gossipkit.operators.theory import stationarity_bound, tau_range
from gossipkit.plans import relational, trainers
from gossipkit.plans.config import GossipConfig
from gossipkit.plans.engine import Compressor, Engine
from gossipkit.sources import datasources
from pyspark.sql import functions as F


def ring(n):
    w = np.zeros((n, n))
    for i in range(n):
        for o in (-1, 0, 1):
            w[i, (i + o) % n] += 1 / 3
    return w


@pytest.mark.parametrize("name", list(LOSSES))
def test_gradients_against_differences(name):
    rng = np.random.default_rng(1)
    loss = LOSSES[name](6, 2 if name in {"logistic", "hinge", "least_squares"} else 3)
    w, x, y = rng.normal(size=loss.size), rng.normal(size=(8, 6)), rng.integers(0, 2, 8)
    g = loss.value_grad(w, x, y)[1]
    for i in rng.choice(loss.size, 5):
        e = np.zeros(loss.size)
        e[i] = 1e-6
        assert abs((loss.value_grad(w + e, x, y)[0] - loss.value_grad(w - e, x, y)[0]) / 2e-6 - g[i]) < 1e-5


@pytest.mark.parametrize("kind,levels", [("range", 8), ("range", 64), ("norm", 16), ("topk", 16), ("randk", 16)])
def test_contraction(kind, levels):
    rng, d = np.random.default_rng(2), 400
    c = Compressor(GossipConfig(compressor=kind, levels=levels, keep=100))
    p = np.where(rng.random(d) < 0.3, 0, rng.laplace(size=d))
    err = np.mean([((c(p, t, 0)[0] - p) ** 2).sum() for t in range(200)]) / (p @ p)
    limit = {"range": 1 - 1 / tau_range(d, levels), "norm": 1 - 1 / (1 + min(d / levels**2, d**0.5 / levels)), "topk": 0.75, "randk": 0.75}[kind]
    assert err <= limit * 1.03
    assert not c(np.zeros(d), 1, 0)[0].any()


def test_aggregation_preserves_the_mean():
    e = Engine(GossipConfig(rounds=1), ring(10), 50)
    rng = np.random.default_rng(0)
    for _ in range(3):
        e.round(lambda x, t: rng.normal(size=x.shape))
        assert np.allclose(e.x.mean(0), e.z.mean(0), atol=1e-12)


def test_methods_send_what_they_say():
    g = lambda x, t: x - 1
    runs = {m: Engine(GossipConfig(method=m, **kw), ring(6), 40).round(g) for m, kw in {"sparse": {}, "tracking": {}, "dsgd": {}, "exact": {"compressor": "identity", "coder": "raw"}, "local": {}}.items()}
    assert [runs[m]["messages"] for m in runs] == [1, 2, 1, 1, 0]
    assert runs["exact"]["payload_bits"] == 6 * 40 * 32 == runs["dsgd"]["payload_bits"] and runs["sparse"]["payload_bits"] < runs["exact"]["payload_bits"] / 4


def test_consensus_and_convergence():
    target = np.random.default_rng(5).normal(size=(10, 30))
    e = Engine(GossipConfig(mu=0.0, eta=0.2, decay=0.5, levels=64), ring(10), 30)
    first = [e.round(lambda x, t: x - target) for _ in range(400)]
    assert np.abs(e.mean() - target.mean(0)).max() < 0.1 and first[-1]["consensus"] < first[5]["consensus"]


def test_relational_rounds_equal_the_engine(spark):
    """Both runtimes give the same models, symbol for symbol, whatever the partitioning."""
    n, d, rng = 4, 12, np.random.default_rng(7)
    cfg = GossipConfig(sites=n, rounds=3, dither="md5", mu=0.01, eta=0.5)
    target = rng.normal(size=(n, d))
    e = Engine(cfg, ring(n), d)
    for _ in range(3):
        e.round(lambda x, t: x - target)
    goal = spark.createDataFrame([(i, j, float(target[i, j])) for i in range(n) for j in range(d)], "site int, coord int, goal double")
    grads = lambda x, t: x.join(goal, ["site", "coord"]).select("site", "coord", (F.col("x") - F.col("goal")).alias("g"))
    for parts in (1, 5):
        out = relational.run(relational.start(goal.repartition(parts)), grads, topology.ring(spark, n), cfg)
        got = np.zeros((n, d))
        for r in out.collect():
            got[r.site, r.coord] = r.x
        assert np.allclose(got, e.x, atol=1e-9)


SETTINGS = [
    {}, {"method": "plain", "grid": "centred"}, {"method": "tracking"}, {"method": "exact", "compressor": "identity", "coder": "raw"}, {"compressor": "norm", "coder": "symbol", "levels": 4},
    {"compressor": "topk", "coder": "index", "keep": 3, "gamma": 0.1}, {"compressor": "randk", "coder": "index", "keep": 3, "gamma": 0.1}, {"method": "dsgd"}, {"method": "local"}, {"coder": "raw"},
]


@pytest.mark.parametrize("change", SETTINGS, ids=lambda c: "-".join(map(str, c.values())) or "sparse")
def test_relational_traces_equal_the_engine(spark, change):
    """All methods and compressors: models, bits over all links and measures, round by round."""
    n, d, rng = 4, 20, np.random.default_rng(8)
    cfg = GossipConfig(**({"sites": n, "rounds": 2, "dither": "md5", "mu": 0.01, "eta": 0.5, "levels": 8} | change))
    target = rng.normal(size=(n, d))
    e = Engine(cfg, ring(n), d)
    want = [e.round(lambda x, t: x - target) for _ in range(2)]
    goal = spark.createDataFrame([(i, j, float(target[i, j])) for i in range(n) for j in range(d)], "site int, coord int, goal double").cache()
    grads = lambda x, t: x.join(goal, ["site", "coord"]).select("site", "coord", (F.col("x") - F.col("goal")).alias("g"))
    state, trace = relational.run_traced(relational.start(goal), grads, topology.ring(spark, n), cfg)
    got = np.zeros((n, d))
    for r in state.collect():
        got[r.site, r.coord] = r.x
    assert np.allclose(got, e.x, atol=1e-9)
    for r, w in zip(trace.orderBy("round").collect(), want, strict=True):
        assert (r.messages, r.payload_bits, r.link_bits) == (w["messages"], w["payload_bits"], w["link_bits"])
        assert abs(r.stationarity - w["stationarity"]) < 1e-6 and abs(r.consensus - w["consensus"]) < 1e-6 and abs(r.zero_share - w["zero_share"]) < 1e-9


def test_relational_run_stops_at_the_cutoff(spark):
    cfg = GossipConfig(sites=4, rounds=9, dither="fast", eta=0.5)
    grads = lambda x, t: x.select("site", "coord", (F.col("x") - 1).alias("g"))
    grid = spark.range(4).select(F.col("id").cast("int").alias("site"), F.explode(F.sequence(F.lit(0), F.lit(9))).alias("coord"))
    far = lambda s: -s.agg(F.max(F.abs(F.col("x") - 1))).first()[0]
    state, trace = relational.run_traced(relational.start(grid), grads, None, cfg, far, -0.3)
    rows = trace.orderBy("round").collect()
    assert 1 < len(rows) < 9 and rows[-1].measure >= -0.3 > rows[-2].measure and state.count() == 40


def test_uniform_mean_rewrite(spark):
    v = spark.createDataFrame([(i, j, float(i * j)) for i in range(5) for j in range(3)], "site int, coord int, y double")
    a = relational.neighbour_mean(v, topology.fully_connected(spark, 5)).select("site", "coord", F.round("mixed", 9))
    assert set(a.collect()) == set(relational.uniform_mean(v).select("site", "coord", F.round("mixed", 9)).collect())


def test_distributed_gradients_equal_local_ones(spark):
    datasources.register(spark)
    s = spark.read.format("planted").option("n", 300).option("sites", 3).load()
    loss, x = LOSSES["logistic"](21, 2), np.random.default_rng(0).normal(size=(3, 21))
    g, value, n = trainers.site_gradients(s, x, loss, 21)
    rows = s.collect()
    for i in range(3):
        own = [r for r in rows if r.site == i]
        v, e = loss.value_grad(x[i], np.array([r.val for r in own]), np.array([r.label for r in own]))
        assert n[i] == len(own) and np.allclose(g[i], e) and abs(v - value[i]) < 1e-9


def test_training_learns_and_is_sparse(spark):
    datasources.register(spark)
    s = spark.read.format("planted").option("n", 2000).option("sites", 4).option("zeros", 0.5).load().cache()
    cfg = GossipConfig(sites=4, rounds=25, batch=None, eta=0.5, mu=0.01, eval_every=25)
    out = trainers.train(s, ring(4), cfg, "logistic", 21, 2)
    assert out.trace.filter("round = 25").first().validation > 0.85 and out.state.count() == 4
    pool = trainers.pooled(s, 21, 4)
    runs = [(f"x/ring/{m}", ring(4), replace(cfg, method=m, batch=16)) for m in ("sparse", "plain", "tracking")]
    rows = trainers.sweep(spark, runs, pool, "logistic", 21, 2).collect()
    assert len(rows) == 75 and {r.run_id for r in rows} == {r for r, *_ in runs}


def test_sources(spark, tmp_path):
    datasources.register(spark)
    w = spark.read.format("topology").option("kind", "ring").option("n", 10).load()
    assert topology.check_mixing(w).isEmpty() and w.count() == 30
    p = spark.read.format("laplace").option("n", 20000).option("rho", 2.0).load()
    assert abs(p.agg(F.avg(F.abs("p"))).first()[0] - 2.0) < 0.1


def test_spectrum_and_bad_tables(spark):
    s = topology.spectrum(ring(10))
    assert abs(s["lambda2"] - (1 + 2 * np.cos(np.pi / 5)) / 3) < 1e-12 and topology.connected(ring(10))
    assert topology.spectrum(np.full((4, 4), 0.25))["lambda2"] < 1e-12 and not topology.connected(np.eye(3))
    bad = spark.createDataFrame([(0, 1, 0.5), (0, 0, 0.5), (1, 1, 1.2), (1, 0, -0.2)], "src int, dst int, w double")
    assert {r.problem for r in topology.check_mixing(bad).collect()} == {"asymmetric", "negative"}
    apart = spark.createDataFrame([(a, b, 0.5) for p in ((0, 1), (2, 3)) for a in p for b in p], "src int, dst int, w double")
    assert {tuple(r) for r in topology.check_mixing(apart).collect()} == {("component", 2, 2), ("component", 3, 2)}
    with pytest.raises(ValueError):
        GossipConfig(levels=0, gamma=2)


def test_bound_falls_with_rounds_and_sites():
    b = lambda T, n: stationarity_bound(1, 1, 1, 1, 1e-3, 100, n, T, 0.5, 2)
    assert b(100, 10) > b(10000, 10) > b(10000, 40)


@pytest.mark.parametrize("method", ["sparse", "tracking"])
def test_stream_equals_batch(spark, tmp_path, method):
    """Rounds fed as micro-batches give the models of the same rounds in a loop."""
    from gossipkit.sources.tables import load_state
    from gossipkit.streaming.online import train_online

    datasources.register(spark)
    s = spark.read.format("planted").option("n", 400).option("sites", 4).load().select("site", "label", "idx", "val")
    parts = [s.filter(F.col("idx").isNotNull()).limit(n) for n in (150, 250)]
    for i, p in enumerate(parts):
        p.coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    cfg = GossipConfig(sites=4, rounds=2, batch=None, method=method)
    stream = spark.readStream.schema(s.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    train_online(stream, ring(4), cfg, str(tmp_path / "out"), "logistic", 21, 2).awaitTermination()
    loss = LOSSES["logistic"](21, 2)
    for order in ((0, 1), (1, 0)):
        e = Engine(cfg, ring(4), 21)
        for i in order:
            e.round(lambda x, t, i=i: trainers.site_gradients(spark.read.parquet(str(tmp_path / f"in/{i}")), x, loss, 21)[0])
        got = np.array([r.x for r in load_state(spark, str(tmp_path / "out"), "online", 1).orderBy("site").collect()])
        if np.allclose(got, e.x, atol=1e-9):
            return
    raise AssertionError("neither order of the files gives the stream's models")
