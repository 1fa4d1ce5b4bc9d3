"""Tracking as joins, messages by block, joins by time, components, streaming state."""

import datetime as dt
import random

import numpy as np
from gossipkit.operators import gradients, joins, levelset, measures, quantise, topology
from gossipkit.plans import relational
from gossipkit.plans.config import GossipConfig
from gossipkit.plans.engine import Engine
from gossipkit.sources.tables import read_messages, write_messages
from gossipkit.streaming import online
from gossipkit.streaming.online import running_types
from pyspark.sql import functions as F


def test_relational_tracking_equals_the_engine(spark):
    n, d, rng = 4, 10, np.random.default_rng(3)
    cfg = GossipConfig(method="tracking", sites=n, rounds=3, dither="md5", mu=0.01, eta=0.3)
    target, w = rng.normal(size=(n, d)), topology.matrix(topology.ring(spark, n))
    e = Engine(cfg, w, d)
    for _ in range(3):
        e.round(lambda x, t: x - target)
    goal = spark.createDataFrame([(i, j, float(target[i, j])) for i in range(n) for j in range(d)], "site int, coord int, goal double")
    grads = lambda x, t: x.join(goal, ["site", "coord"]).select("site", "coord", (F.col("x") - F.col("goal")).alias("g"))
    out = relational.run_tracking(relational.tracking_start(goal), grads, topology.ring(spark, n), cfg)
    got, track = np.zeros((n, d)), np.zeros((n, d))
    for r in out.collect():
        got[r.site, r.coord], track[r.site, r.coord] = r.x, r.track
    assert np.allclose(got, e.x, atol=1e-9) and np.allclose(track, e.track, atol=1e-9)


def test_compressed_averaging_keeps_the_mean_and_shrinks_the_spread(spark):
    rng = np.random.default_rng(4)
    v = spark.createDataFrame([(i, j, float(rng.normal())) for i in range(6) for j in range(20)], "site int, coord int, x double")
    out = relational.average_consensus(v, topology.fully_connected(spark, 6), 0.5, 10, GossipConfig(sites=6, levels=64))
    a, b = (df.groupBy("coord").agg(F.avg("x").alias("m"), F.var_pop("x").alias("v")).orderBy("coord").collect() for df in (v, out))
    assert np.allclose([r.m for r in a], [r.m for r in b], atol=1e-9)
    assert sum(r.v for r in b) < 0.05 * sum(r.v for r in a)


def test_messages_by_block(spark, tmp_path):
    rng = np.random.default_rng(5)
    p = spark.createDataFrame([(s, i, float(rng.laplace() * (rng.random() < 0.5))) for s in range(3) for i in range(250)], "site int, coord long, p double")
    sym = quantise.range_dither(p, 8)
    for block in (None, 64, 1000):
        sent = levelset.messages(sym, 8, block)
        assert sent.count() == 3 * (4 if block == 64 else 1)
        write_messages(sent, str(tmp_path / "m"), f"b{block}", 1)
        back = levelset.received(read_messages(spark, str(tmp_path / "m"), f"b{block}", 1), block)
        want = sym.select("site", "coord", "sym")
        assert back.select("site", "coord", "sym").exceptAll(want).isEmpty() and back.count() == 750
    one = levelset.bits(sym, 8).select("site", "type_bits", "gap_bits")
    whole = levelset.block_bits(sym, 8, 1000).drop("blocks")
    assert one.exceptAll(whole).isEmpty()


def test_joins_by_time(spark):
    rnd, t0 = random.Random(6), dt.datetime(2024, 1, 1)
    # one key holds most rows; times repeat and fall on the bins' borders
    made = lambda n, base: [(base + i, None if i % 50 == 7 else rnd.choice([1, 1, 1, 2, 3]), t0 + dt.timedelta(minutes=15 * rnd.randrange(300))) for i in range(n)]
    a, b = made(200, 0), made(150, 1000)
    left, right = (spark.createDataFrame(x, "id long, k int, ts timestamp") for x in (a, b))
    got = {r.id: r.id_as_of for r in joins.as_of(left, right, "k", "ts", "id", 3600).collect()}
    for i, k, ts in a:
        before = [(t, j) for j, q, t in b if q == k and k is not None and t <= ts]
        assert got[i] == (max(before)[1] if before else None)
    pairs = {(r.a.id, r.b.id) for r in joins.interval(left, right, "k", "ts", 3600).collect()}
    assert pairs == {(i, j) for i, k, s in a for j, q, t in b if k is not None and k == q and 0 <= (t - s).total_seconds() <= 3600}
    assert joins.as_of(left.limit(0), right, "k", "ts", "id").isEmpty()
    assert {r.id_as_of for r in joins.as_of(left.filter("k IS NOT NULL"), right.limit(0), "k", "ts", "id").collect()} == {None}


def test_components(spark):
    chain = [(i, i + 1) for i in range(12)] + [(20, 21), (21, 22), (30, 30)]
    mixing = spark.createDataFrame([(a, b, 0.5) for a, b in chain] + [(13, 20, 0.0)], "src int, dst int, w double")
    got = {r.site: r.component for r in relational.components(mixing).collect()}
    assert got == {i: 0 for i in range(13)} | {13: 13, 20: 20, 21: 20, 22: 20, 30: 30}


def test_bernoulli_batches(spark):
    s = spark.range(20000).select(F.col("id").alias("sample_id"))
    one, two = gradients.bernoulli_batch(s, 0.3, 1), gradients.bernoulli_batch(s.repartition(7), 0.3, 1)
    assert one.exceptAll(two).isEmpty() and abs(one.count() / 20000 - 0.3) < 0.02
    assert not one.exceptAll(gradients.bernoulli_batch(s, 0.3, 2)).isEmpty()


def test_running_types_of_a_stream(spark, tmp_path):
    rows = [(i % 3, i % 6 - 1, float(i % 5) - 2) for i in range(90)]
    df = spark.createDataFrame(rows, "site int, sym int, p double")
    for i in range(3):
        df.filter(F.abs(F.hash("site", "sym", "p")) % 3 == i).coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    held = {}

    def note(batch, _):
        held.update({r.site: (list(r.counts), r.rho, r.d) for r in batch.collect()})

    running_types(stream, 4).writeStream.outputMode("update").foreachBatch(note).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    for s in range(3):
        own = [r for r in rows if r[0] == s]
        counts = [sum(r[1] == k for r in own) for k in range(-1, 5)]
        assert held[s][0] == counts and held[s][2] == len(own) and abs(held[s][1] - sum(abs(r[2]) for r in own) / len(own)) < 1e-12


def test_quantiles_and_histogram(spark):
    rng = np.random.default_rng(9)
    vectors = {0: rng.normal(size=400).round(2), 1: np.full(7, 3.5), 2: np.array([1.0]), 3: np.r_[np.zeros(300), 1e6]}
    df = spark.createDataFrame([(s, i, float(x)) for s, v in vectors.items() for i, x in enumerate(v)], "site int, coord int, p double")
    probs = [0.0, 0.25, 0.5, 0.99, 1.0]
    want = {(s, q): np.sort(v)[max(int(np.ceil(round(q * len(v), 9))) - 1, 0)] for s, v in vectors.items() for q in probs}
    for bins in (1, 16, 4096):
        assert {(r.site, r.prob): r.value for r in measures.quantiles(df, probs, bins=bins).collect()} == want
    near = {(r.site, r.prob): r.value for r in measures.quantiles_approx(df, probs).collect()}
    assert near == want
    bars = {(r.site, r.bin): r.n for r in measures.histogram(df, bins=10).collect()}
    counts = np.histogram(vectors[0], 10)[0]
    assert sum(n for (s, _), n in bars.items() if s == 0) == 400 and abs(bars[0, 1] - counts[0]) <= 1
    assert bars[1, 1] == 7 and bars[2, 1] == 1 and bars[3, 1] == 300 and bars[3, 10] == 1
    assert measures.quantiles(df.limit(0), probs).isEmpty() and measures.histogram(df.limit(0)).isEmpty()


def write_parts(df, path, parts):
    """Each part a file of its own, in order."""
    for i, part in enumerate(parts):
        df.sparkSession.createDataFrame(part, df.schema).coalesce(1).write.parquet(f"{path}/{i}")


def test_stream_pairs_across_batches(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    rows = [(i, i % 3, t0 + dt.timedelta(minutes=7 * i)) for i in range(60)]
    df = spark.createDataFrame(rows, "id long, k int, ts timestamp")
    write_parts(df, tmp_path / "in", [rows[:20], rows[20:40], rows[40:]])
    read = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True)
    left = read.parquet(str(tmp_path / "in")).filter("id % 2 = 0")
    right = read.parquet(str(tmp_path / "in")).filter("id % 2 = 1")
    got = online.finished(online.pairs(left, right, "k", 3600).select(F.col("a.id").alias("a"), F.col("b.id").alias("b")), "pairs")
    want = {(i, j) for i, k, s in rows for j, q, t in rows if i % 2 == 0 and j % 2 == 1 and k == q and 0 <= (t - s).total_seconds() <= 3600}
    assert {(r.a, r.b) for r in got.collect()} == want and len(want) > 20


def test_late_rows_leave_windows_but_not_training(spark, tmp_path):
    """A row later than the watermark is missing from its window; the plain stream still delivers it."""
    t0 = dt.datetime(2024, 1, 1)
    at = lambda h: t0 + dt.timedelta(hours=h)
    batches = [[(1, at(1), "view", 1.0)], [(2, at(30), "view", 1.0)], [(3, at(31), "view", 1.0)], [(4, at(2), "view", 1.0), (5, at(32), "view", 1.0)], [(6, at(80), "view", 1.0)]]
    df = spark.createDataFrame(batches[0], "event_id long, ts timestamp, event_type string, value double")
    write_parts(df, tmp_path / "in", batches)
    read = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True)
    stream = read.parquet(str(tmp_path / "in"))
    days = {r.start: r.n for r in online.finished(online.windows(stream), "windows").collect()}
    assert days[t0] == 1 and days[t0 + dt.timedelta(days=1)] == 3
    assert {r.event_id for r in online.finished(stream, "all").collect()} == {1, 2, 3, 4, 5, 6}
