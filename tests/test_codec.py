import math

import numpy as np
import pytest
from gossipkit.operators import codec, levelset
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

HAND = [0, 0, 2, 0, 1, 0, 0, 2, 0, 0, 1, 0]


@settings(max_examples=80, deadline=None)
@given(st.integers(1, 40), st.lists(st.integers(-1, 40), min_size=1, max_size=300), st.sampled_from(["gamma", "delta", "omega"]), st.sampled_from(["optimal", "rice"]))
def test_round_trip(levels, raw, elias, rule):
    sym = np.array([min(s, levels) for s in raw])
    body = codec.encode(sym, levels, -1.0, 2.0, elias, rule)
    back, lo, hi = codec.decode(body, elias, rule)
    assert (back == sym).all() and (lo, hi) == (-1.0, 2.0)
    if elias == "gamma" and rule == "optimal":
        assert len(body) == codec.HEADER.size + -(-codec.message_bits(sym, levels) // 8)


@pytest.mark.parametrize("k,gamma,delta,omega", [(1, 1, 1, 1), (2, 3, 4, 3), (3, 3, 4, 3), (4, 5, 5, 6), (7, 5, 5, 6), (8, 7, 8, 7), (16, 9, 9, 11), (100, 13, 11, 13)])
def test_elias_lengths(k, gamma, delta, omega):
    for kind, n in (("gamma", gamma), ("delta", delta), ("omega", omega)):
        w = codec.BitWriter()
        codec.elias_write(w, k, kind)
        assert len(w.text()) == n and codec.elias_read(codec.BitReader(w.text()), kind) == k


def test_worked_example(spark):
    """Dominant 0 is implied; level 1 has gaps 4 and 5, level 2 gaps 2 and 3 among the rest: 14 bits, 13 for the counts."""
    assert [g.tolist() for *_, g in codec.passes(np.array(HAND), 2)] == [[4, 5], [2, 3]]
    df = spark.createDataFrame([(0, i, s) for i, s in enumerate(HAND)], "site int, coord int, sym int")
    r = levelset.bits(df, 2).first()
    # the reserved zero symbol adds its count of none, one bit
    assert (r.gap_bits, r.type_bits) == (14, 13 + 1)
    order = levelset.level_order(levelset.type_vector(df, 2))
    gaps = {(x["rank"], x.seq): x.gap for x in levelset.run_lengths(df, order).collect()}
    assert gaps == {(1, 1): 4, (1, 2): 5, (2, 1): 2, (2, 2): 3}


def test_golomb_cost_stays_below_the_constant():
    for p in np.linspace(0.001, 0.999, 400):
        m = codec.golomb_parameter(int(p * 1e6), 10**6)
        gaps = np.arange(0, 20000)
        w = p * (1 - p) ** gaps
        mean = float((w * codec.golomb_sizes(gaps, m)).sum() / w.sum())
        assert mean <= -math.log2(p) + 2.914 + 1e-6


def test_sound_bound_holds_where_the_printed_one_may_not(spark):
    rng = np.random.default_rng(3)
    sym = np.where(rng.random(20000) < 0.01, 1, 0)
    df = spark.createDataFrame([(0, i, int(s)) for i, s in enumerate(sym)], "site int, coord int, sym int")
    types = levelset.type_vector(df, 1)
    sound, printed = (levelset.bound(types, v).first().bound for v in ("sound", "printed"))
    h, code = levelset.entropy(types).first().entropy, levelset.bits(df, 1).first().gap_bits / len(sym)
    assert code <= sound and printed < h <= code + 0.01


def test_degenerate_vectors(spark):
    from gossipkit.operators import quantise

    rows = [(0, i, 0.0) for i in range(5)] + [(1, i, 2.5) for i in range(5)] + [(2, 0, -1.0)] + [(3, i, float(i == 2)) for i in range(5)]
    q = quantise.range_dither(spark.createDataFrame(rows, "site int, coord int, p double"), 4, shrink="none").collect()
    assert all(r.sym == -1 and r.q == 0 for r in q if r.site == 0)
    assert all(r.sym == 0 and r.q == 2.5 for r in q if r.site == 1) and [r.q for r in q if r.site == 2] == [-1.0]
    assert [r.q for r in q if r.site == 3 and r.coord == 2] == [1.0]


def test_soft_threshold_is_the_proximal_map(spark):
    from gossipkit.functions.columns import soft_threshold

    grid = np.linspace(-3, 3, 60001)
    for h in (-2.0, -0.3, 0.0, 0.2, 1.7):
        got = spark.range(1).select(soft_threshold(F.lit(h), 0.5).alias("z")).first().z
        assert abs(got - grid[np.argmin((grid - h) ** 2 / 2 + 0.5 * np.abs(grid))]) < 2e-4


def test_runs_by_bins(spark):
    """However the coordinates are cut into bins, the runs are those of the whole vector."""
    rng = np.random.default_rng(5)
    rows = [(site, int(c), int(v)) for site in range(3) for c, v in enumerate(rng.choice([-1, 0, 1, 2, 3, 4], 500, p=[0.5, 0.05, 0.2, 0.15, 0.05, 0.05])) if rng.random() < 0.9]
    df = spark.createDataFrame(rows, "site int, coord long, sym int")
    ordered = levelset.level_order(levelset.type_vector(df, 4))
    plain, rank = {}, {(r.site, r.sym): r.rank for r in ordered.collect()}
    for site in range(3):
        seen = [rank[s, v] for s, _, v in sorted(rows) if s == site]
        for r in sorted({x for x in seen if x}):
            open_, n, seq = [x for x in seen if x == 0 or x >= r], 0, 0
            for x in open_:
                n += 1
                if x == r:
                    seq += 1
                    plain[site, r, seq] = n - 1
                    n = 0
    for bins in (7, 100, 1 << 16):
        got = {(r.site, r.rank, r.seq): r.gap for r in levelset.run_lengths(df, ordered, bins).collect()}
        assert got == plain


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-1, 9), min_size=1, max_size=200), st.sampled_from(["dominant", "last", "none"]))
def test_implied_levels(raw, implied):
    sym = np.array(raw)
    body = codec.encode(sym, 9, implied=implied)
    assert (codec.decode(body, implied=implied)[0] == sym).all()
    assert len(body) == codec.HEADER.size + -(-codec.message_bits(sym, 9, implied) // 8)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-20, 20), max_size=200), st.sampled_from(["sparse", "dense"]))
def test_symbol_messages(raw, form):
    back, norm = codec.symbol_decode(codec.symbol_encode(np.array(raw, np.int64), 1.5, form), form)
    assert back.tolist() == raw and norm == 1.5


def test_implied_levels_relational(spark):
    """The relational lengths of each variant are those of the messages."""
    rng = np.random.default_rng(8)
    vectors = [rng.choice([-1, 0, 2, 3], 400, p=[0.5, 0.3, 0.15, 0.05]), np.full(9, 2), np.arange(-1, 5)]
    df = spark.createDataFrame([(i, c, int(v)) for i, sym in enumerate(vectors) for c, v in enumerate(sym)], "site int, coord int, sym int")
    for implied in ("dominant", "last", "none"):
        got = {r.site: r.type_bits + r.gap_bits for r in levelset.bits(df, 4, implied=implied).collect()}
        assert got == {i: codec.message_bits(sym, 4, implied) for i, sym in enumerate(vectors)}


def test_omega_of_large_numbers(spark):
    """Lengths of the recursive code, group by group; from 2^16 on it has a fourth group."""
    from gossipkit.functions.columns import elias_bits
    from pyspark.sql import functions as F

    def length(k):
        return 1 if k == 1 else k.bit_length() + length(k.bit_length() - 1)

    ks = [1, 2, 3, 4, 15, 16, 255, 256, 65535, 65536, 65537, 150000, 9_000_000, 2**40]
    rows = spark.createDataFrame([(k,) for k in ks], "k long").select("k", elias_bits(F.col("k"), "omega").alias("n")).collect()
    assert {r.k: r.n for r in rows} == {k: length(k) for k in ks} and length(65536) == 28


def test_omega_of_order_keys(spark, tmp_path):
    """The query's lengths are those of codes that are written and read back, also where omega has a fourth group."""
    from gossipkit.queries import elias_table

    ks = [1, 2, 16, 65535, 65536, 149999, 2**31, 2**40]
    spark.createDataFrame([(k,) for k in [*ks, 0, -5, None]], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    rows = {r.k: r for r in elias_table(spark, str(tmp_path)).collect()}
    assert sorted(rows) == ks
    for k in ks:
        for kind in ("gamma", "delta", "omega"):
            w = codec.BitWriter()
            codec.elias_write(w, k, kind)
            assert len(w.text()) == rows[k][kind] and codec.elias_read(codec.BitReader(w.text()), kind) == k
