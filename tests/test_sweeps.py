"""Sweeps over tables of any size: rows of batches by place, evaluation where the rows are."""

import hashlib
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest
from gossipkit.operators import features, theory
from gossipkit.operators.losses import LOSSES
from gossipkit.plans import trainers
from gossipkit.plans.config import GossipConfig
from gossipkit.plans.engine import Engine
from gossipkit.sources import datasources
from pyspark.sql import functions as F

W = np.full((3, 3), 1 / 3)


def plain(rows, cfg, features):
    """A run with all rows dense in one place: (loss, test accuracy, validation accuracy) of each round."""
    rows = sorted(rows, key=lambda r: r.sample_id)
    x, y = np.zeros((len(rows), features)), np.array([r.label for r in rows])
    for i, r in enumerate(rows):
        x[i, r.idx] = r.val
    split, site = np.array([r.split for r in rows]), np.array([r.site for r in rows])
    loss, last, out = LOSSES["logistic"](features, 2), [], []
    e = Engine(cfg, W, loss.size, loss.start())

    def gradient(m, t):
        g, last[:] = np.zeros_like(m), []
        for s in range(3):
            own = np.flatnonzero((split == "train") & (site == s))
            if cfg.batch is not None and cfg.batch < len(own):
                own = own[np.random.Generator(np.random.Philox(np.random.SeedSequence([cfg.seed, t, s, 1]))).choice(len(own), cfg.batch, replace=False)]
            v, g[s] = loss.value_grad(m[s], x[own], y[own])
            last.append(v)
        return g

    for _ in range(cfg.rounds):
        e.round(gradient)
        out.append((np.mean(last), *((loss.predict(e.mean(), x[split == k]) == y[split == k]).mean() for k in ("test", "validation"))))
    return out


@pytest.mark.parametrize("local", [1 << 15, 0], ids=["task", "table"])
def test_sweep_equals_a_plain_run(spark, monkeypatch, local):
    """Batches, whole sites in a task and whole sites by Spark; ids that are negative, far apart and in no order."""
    datasources.register(spark)
    monkeypatch.setattr(trainers, "LOCAL_ROWS", local)
    monkeypatch.setattr(trainers, "MODEL_BYTES", 1 << 10)
    s = spark.read.format("planted").option("n", 600).option("sites", 3).load()
    s = s.withColumn("sample_id", F.col("sample_id") * F.when(F.col("sample_id") % 2 == 0, -1000003).otherwise(7)).cache()
    base = GossipConfig(sites=3, rounds=4, eta=0.5, mu=0.01)
    cfgs = {"batch": base, "all": replace(base, batch=None), "large": replace(base, batch=100000, rounds=2)}
    out = trainers.sweep(spark, [(k, W, c) for k, c in cfgs.items()], trainers.pooled(s, 21, 3), "logistic", 21, 2).collect()
    rows = s.collect()
    for k, c in cfgs.items():
        got = [(r.loss, r.accuracy, r.validation) for r in sorted((r for r in out if r.run_id == k), key=lambda r: r["round"])]
        assert np.allclose(got, plain(rows, c, 21), atol=1e-9)


def test_sweep_above_the_old_bound(spark):
    """More values than fitted on the driver before (2^26 of 257 features); accuracy counts every held-out row."""
    n = 262_000
    part = F.when(F.col("id") % 10 < 6, "train").when(F.col("id") % 10 < 8, "validation").otherwise("test")
    s = spark.range(n).select(F.col("id").alias("sample_id"), (F.col("id") % 3).cast("int").alias("site"), part.alias("split"), (F.col("id") % 7 < 3).cast("int").alias("label"))
    s = s.withColumn("idx", F.array((F.col("sample_id") % 7).cast("int"), F.lit(256))).withColumn("val", F.array(F.lit(1.0), F.lit(1.0)))
    cfg = GossipConfig(sites=3, rounds=3, eta=0.5, eval_every=3)
    pool = trainers.pooled(s, 257, 3)
    got = trainers.sweep(spark, [("x", W, cfg)], pool, "logistic", 257, 2).filter("round = 3").first()
    assert pool.sizes.sum() == s.filter("split = 'train'").count() and 0 <= got.accuracy <= 1
    # every class of ids has one score, so each accuracy is a number of whole sevenths of its split
    counts = {r.k: r.n for r in s.filter("split = 'test'").groupBy((F.col("sample_id") % 7).alias("k")).agg(F.count(F.lit(1)).alias("n")).collect()}
    whole = sum(counts.values())
    assert min(abs(got.accuracy - sum(counts[k] for k in range(7) if m >> k & 1) / whole) for m in range(128)) < 1e-12


def test_constants_equal_dense_ones(spark):
    datasources.register(spark)
    s = spark.read.format("planted").option("n", 300).option("sites", 3).load()
    pool, loss = trainers.pooled(s, 21, 3), LOSSES["logistic"](21, 2)
    grams, full = trainers.site_grams(pool.fit, 3, 21), trainers.site_gradients(pool.fit, np.zeros((3, 21)), loss, 21)[0]
    starts, draws = theory.drawn(pool.sizes, 21)
    rows = pool.picked({s: np.arange(n) for s, n in enumerate(pool.sizes.tolist())})
    c = theory.constants(grams, starts, full, {s: [loss.value_grad(loss.start(), *rows.take(s, p))[1] for p in draws[s]] for s in draws})
    dense = [rows.take(s, np.arange(n))[0] for s, n in enumerate(pool.sizes.tolist())]
    assert all(np.allclose(g, x.T @ x / len(x)) for g, x in zip(grams, dense, strict=True))
    assert abs(c["K"] - max(np.linalg.eigvalsh(g)[-1] for g in grams)) < 0.05 * c["K"] and c["G"] == max(np.linalg.norm(g) for g in full) and c["sigma2"] > 0


def test_blocks_hold_every_row(spark, monkeypatch):
    """Passes over packed rows are passes over the rows, also where a site fills several blocks and a row has no value."""
    datasources.register(spark)
    monkeypatch.setattr(trainers, "BLOCK", 7)
    s = spark.read.format("planted").option("n", 300).option("sites", 3).load()
    none = s.limit(1).select(F.lit(-1).cast("long").alias("sample_id"), F.lit(1).alias("site"), F.lit("train").alias("split"), F.lit(1).alias("label"), F.array().cast("array<int>").alias("idx"), F.array().cast("array<double>").alias("val"))
    s = s.select(none.columns).unionByName(none).cache()
    packed = trainers.blocks(s).cache()
    assert packed.count() > 40
    loss, x = LOSSES["logistic"](21, 2), np.random.default_rng(3).normal(size=(3, 21))
    for a, b in zip(trainers.site_gradients(s, x, loss, 21), trainers.site_gradients(packed, x, loss, 21), strict=True):
        assert np.allclose(a, b, rtol=0, atol=1e-12)


def test_samples_are_counted_where_they_are_read(spark, sf):
    """The rows of the language task are unit_rows of hashed_words, letter case and odd texts included; no word is shuffled."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang")
    odd = [(-3, "Straße ÉCOLE ΣΑΣ Σ á x"), (-4, None), (-5, "123 !!"), (-6, "  İstanbul 𐐀𐐁 ﬁn "), (None, "a b"), (-9, "a\x00b  é")]
    docs = docs.unionByName(spark.createDataFrame([(k, t, "de") for k, t in odd], "doc_id long, text string, lang string"))
    got = features.language_samples(docs, 10, 64)
    want = features.unit_rows(features.hashed_words(docs.filter("doc_id IS NOT NULL"), 64), 64)
    rows = {(r.sample_id, i, v) for r in got.collect() for i, v in zip(r.idx, r.val, strict=True)}
    assert rows == {tuple(r) for r in want.join(docs.filter(F.col("lang").isin(features.LANGS)).select("doc_id"), "doc_id").collect()}
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()


def test_words_are_looked_up_once(monkeypatch):
    """One look-up a word for all texts given, however many are split at once; counts are those of each text by itself."""

    class Told(features.Buckets):
        asked = 0

        def __getitem__(self, word):
            self.asked += 1
            return super().__getitem__(word)

    monkeypatch.setattr(features, "TEXTS", 3)
    texts = ["a straße a", "b", "z a b " * 5 + "é"] * 7
    known = Told(16)
    idx, n, squares = (c.to_pylist() for c in features._counts(pa.array(["skipped", *texts]).slice(1), 16, known))
    assert known.asked == 5
    for i, t in enumerate(texts):
        want = np.bincount([int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % 16 for w in t.split()], minlength=16)
        assert idx[i] == np.flatnonzero(want).tolist() and n[i] == want[want > 0].tolist() and squares[i] == (want**2).sum()
    assert [c.to_pylist() for c in features._counts(pa.array([], pa.string()), 16, known)] == [[], [], []]


def test_planted_directions(spark):
    """Labels by directions drawn before and, beyond DRAWN places, with the rows."""
    rng, wide = np.random.default_rng(5), features.DRAWN + 9
    rows = [(i, rng.normal(size=wide if i % 2 else 40).astype(np.float32).tolist(), 0) for i in range(40)] + [(40, [0.0] * features.DRAWN + [1.0] * 9, 0)]
    got = {r.sample_id: r.label for r in features.vector_samples(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), 3).collect()}
    teacher = np.array([[int(hashlib.md5(f"teacher/{c}/{i}".encode()).hexdigest()[:8], 16) / 2**32 - 0.5 for i in range(wide)] for c in range(10)])
    assert got == {k: int(np.argmax(teacher[:, : len(e)] @ np.array(e))) for k, e, _ in rows}
    assert all(features.planted(c) == teacher[c, : features.DRAWN].tolist() for c in range(10))
