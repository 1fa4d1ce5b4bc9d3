"""Level-support coder, relational: type vector, level order, supports, run lengths, exact code lengths.

Levels are visited by falling frequency. The most frequent one is implied: its coordinates are those that no
other level explains. The coordinates of each further level are located among those not yet explained.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import elias_bits, golomb_bits, golomb_parameter
from . import codec

#: Coordinates of a bin: what one task sees of a site.
BIN = 1 << 16
HEADER_BITS = 64 + 32 + 16  # two range ends of 32 bits, dimension, number of levels


def bin_counts(df: DataFrame, bins: int = BIN) -> DataFrame:
    """(site, bin, sym, c): the one aggregate over the symbols from which type vectors and prefix sums come."""
    place = F.floor(F.col("coord") / bins).cast("long").alias("bin")
    return df.groupBy("site", place, "sym").agg(F.count(F.lit(1)).alias("c"))


def type_vector(df: DataFrame, levels: int, bins: int = BIN) -> DataFrame:
    """(site, sym, cnt) over the whole alphabet, -1 (exact zero) to levels."""
    counted = bin_counts(df, bins).groupBy("site", "sym").agg(F.sum("c").alias("cnt"))
    whole = counted.groupBy("site").agg(F.map_from_entries(F.collect_list(F.struct("sym", "cnt"))).alias("t"))
    rows = whole.select("site", "t", F.explode(F.sequence(F.lit(-1), F.lit(levels))).alias("sym"))
    return rows.select("site", "sym", F.coalesce(F.col("t")[F.col("sym")], F.lit(0)).alias("cnt"))


def level_order(types: DataFrame, order: str = "frequency", implied: str = "dominant") -> DataFrame:
    """Adds rank, the order in which symbols are sent; rank 0 is implied and not sent. Order 'frequency' visits by falling
    count, ties by symbol, 'natural' as symbols are numbered. Implied is the 'dominant' symbol, the 'last' one visited
    that occurs, or 'none'."""
    w = Window.partitionBy("site")
    falling, plain = [F.col("cnt").desc(), F.col("sym")], [F.col("sym")]
    visited = falling if order == "frequency" else plain
    if implied == "none":
        return types.withColumn("rank", F.row_number().over(w.orderBy(*visited)))
    held = F.col("cnt") > 0
    first = {"dominant": falling, "last": [held.desc(), *(c.desc() for c in ([F.col("sym")] if order == "natural" else [-F.col("cnt"), F.col("sym")]))]}[implied]
    # the implied symbol goes first, the others keep their order
    ranked = types.withColumn("_first", F.row_number().over(w.orderBy(*first)) == 1)
    return ranked.withColumn("rank", F.row_number().over(w.orderBy(F.col("_first").desc(), *visited)) - 1).drop("_first")


def visits(ordered: DataFrame) -> DataFrame:
    """Transmitted levels with the number of coordinates not explained before each."""
    w = Window.partitionBy("site")
    before = F.coalesce(F.sum(F.when(F.col("rank") > 0, F.col("cnt"))).over(w.orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    seen = ordered.withColumns({"d": F.sum("cnt").over(w), "_before": before})
    return seen.filter("rank > 0 AND cnt > 0").withColumn("remaining", F.col("d") - F.col("_before")).drop("_before")


def supports(df: DataFrame, ordered: DataFrame) -> DataFrame:
    """(site, rank, coord): each coordinate under its level."""
    return df.join(F.broadcast(ordered.select("site", "sym", "rank")), ["site", "sym"]).select("site", "rank", "sym", "coord")


def binned_runs(df: DataFrame, ordered: DataFrame, bins: int = BIN) -> DataFrame:
    """(site, bin, rank, gaps, upto): for each bin of coordinates and transmitted level with holders there, the number of
    unexplained coordinates between each holder and the one before it, for the first one those of the bin up to and with
    it; upto is that number for the last holder. A task sees one bin, not a site."""
    def count(t):
        order = np.argsort(t["coord"].to_numpy(), kind="stable")
        rank = t["rank"].to_numpy()[order]
        # holders by level; the lower levels' holders before each one are found by merging their places
        by_rank = np.argsort(rank, kind="stable")
        ranks, first = np.unique(rank[by_rank], return_index=True)
        place = dict(zip(ranks.tolist(), np.split(by_rank, first[1:]), strict=True))
        out, explained = [], np.zeros(len(rank), np.int64)
        for r in (x for x in ranks.tolist() if x > 0):
            at = place[r]
            upto = at + 1 - np.cumsum(explained)[at]
            explained[at] = 1
            gaps = np.diff(upto, prepend=0) - 1
            gaps[0] = upto[0]
            out.append((r, gaps, int(upto[-1])))
        n = len(out)
        return pa.table({
            "site": pa.array([t["site"][0].as_py()] * n, t["site"].type), "bin": pa.array([t["bin"][0].as_py()] * n, pa.int64()), "rank": pa.array([r for r, *_ in out], pa.int32()),
            "gaps": pa.array([g for _, g, _ in out], pa.list_(pa.int64())), "upto": pa.array([u for *_, u in out], pa.int64()),
        })

    rows = supports(df, ordered).select("site", F.floor(F.col("coord") / bins).cast("long").alias("bin"), "rank", "coord")
    kind = df.schema["site"].dataType.simpleString()
    return rows.groupBy("site", "bin").applyInArrow(count, f"site {kind}, bin long, rank int, gaps array<long>, upto long")


def run_lengths(df: DataFrame, ordered: DataFrame, bins: int = BIN) -> DataFrame:
    """(site, rank, seq, gap): unexplained coordinates between holders of each transmitted level. Bins are counted one by
    one; prefix sums over a row for each bin and level join them exactly."""
    runs = binned_runs(df, ordered, bins)
    top = F.max("rank").over(Window.partitionBy("site")).alias("top")
    held = bin_counts(df, bins).join(F.broadcast(ordered.select("site", "sym", "rank", top)), ["site", "sym"])
    grid = held.groupBy("site", "bin").agg(F.sum("c").alias("all"), F.first("top").alias("top"), F.map_from_entries(F.collect_list(F.struct("rank", "c"))).alias("t"))
    grid = grid.filter("top > 0").select("site", "bin", "all", "t", F.explode(F.sequence(F.lit(1), F.col("top").cast("int"))).alias("rank"))
    grid = grid.select("site", "bin", "all", "rank", F.coalesce(F.col("t")[F.col("rank")], F.lit(0)).alias("c"))
    lower = Window.partitionBy("site", "bin").orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    grid = grid.withColumn("open", F.col("all") - F.coalesce(F.sum("c").over(lower), F.lit(0)))
    before = Window.partitionBy("site", "rank").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    grid = grid.withColumns({"opened": F.coalesce(F.sum("open").over(before), F.lit(0)), "holders": F.coalesce(F.sum("c").over(before), F.lit(0))})
    ends = grid.join(runs.select("site", "bin", "rank", "upto"), ["site", "bin", "rank"])
    start = ends.withColumn("last", F.coalesce(F.max(F.col("opened") + F.col("upto")).over(before), F.lit(0)))
    start = start.select("site", "bin", "rank", "holders", (F.col("opened") - F.col("last") - 1).alias("shift"))
    each = runs.join(start, ["site", "bin", "rank"]).select("site", "rank", "holders", "shift", F.posexplode("gaps").alias("i", "gap"))
    gap = F.when(F.col("i") == 0, F.col("gap") + F.col("shift")).otherwise(F.col("gap"))
    return each.select("site", "rank", (F.col("holders") + F.col("i") + 1).cast("int").alias("seq"), gap.cast("long").alias("gap"))


def gap_bits(df: DataFrame, ordered: DataFrame, rule: str = "optimal") -> DataFrame:
    """(site, rank, runs, m, bits): what each transmitted level costs."""
    v = visits(ordered).select("site", "rank", "sym", golomb_parameter(F.col("cnt") / F.col("remaining"), rule).alias("m"))
    runs = run_lengths(df, ordered).join(F.broadcast(v), ["site", "rank"])
    return runs.groupBy("site", "rank", "sym", "m").agg(F.count(F.lit(1)).alias("runs"), F.sum(golomb_bits(F.col("gap"), F.col("m"))).cast("long").alias("bits"))


def bits(
    df: DataFrame, levels: int, elias: str = "gamma", rule: str = "optimal", order: str = "frequency", implied: str = "dominant"
) -> DataFrame:
    """(site, type_bits, gap_bits, header_bits, total_bits) of each site's message."""
    types = type_vector(df, levels)
    head = types.groupBy("site").agg(F.sum(elias_bits(F.col("cnt") + 1, elias)).cast("long").alias("type_bits"))
    gaps = gap_bits(df, level_order(types, order, implied), rule).groupBy("site").agg(F.sum("bits").alias("gap_bits"))
    out = head.join(gaps, "site", "left").withColumns({"gap_bits": F.coalesce("gap_bits", F.lit(0)), "header_bits": F.lit(HEADER_BITS).cast("long")})
    return out.withColumn("total_bits", F.col("type_bits") + F.col("gap_bits") + F.col("header_bits"))


def pmf(types: DataFrame) -> DataFrame:
    """Level frequencies by falling size, with their running sums."""
    w = Window.partitionBy("site")
    f = level_order(types).withColumn("f", F.col("cnt") / F.sum("cnt").over(w)).filter("cnt > 0")
    run = F.coalesce(F.sum("cnt").over(w.orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) / F.sum("cnt").over(w)
    return f.withColumns({"before": run, "f0": F.first("f").over(w.orderBy("rank"))})


def entropy(types: DataFrame) -> DataFrame:
    """(site, f0, entropy): share of the most frequent level, bits a coordinate."""
    return pmf(types).groupBy("site").agg(F.max("f").alias("f0"), (-F.sum(F.col("f") * F.log2("f"))).alias("entropy"))


def bound(types: DataFrame, variant: str = "sound") -> DataFrame:
    """(site, bound): gap bits a coordinate from the frequencies alone. 'printed' discounts the implied level's
    coordinates from what is searched, which can fall below the entropy; 'sound' does not."""
    f, f0 = F.col("f"), F.col("f0")
    left = 1 - F.col("before") if variant == "printed" else 1 - (F.col("before") - f0)
    term = F.when(F.col("rank") > 0, f * F.log2(left)).otherwise(0.0)
    h = -F.sum(f * F.log2(f))
    return pmf(types).groupBy("site").agg((h + 2.914 * (1 - F.max("f0")) + F.max(f0 * F.log2(f0)) + F.sum(term)).alias("bound"))


def symbol_bits(df: DataFrame, levels: int, form: str = "sparse") -> DataFrame:
    """Symbol-wise Elias code of signed levels: 'sparse' sends gap, sign and level of non-zero ones, 'dense' a
    level for every coordinate and a sign where it is not zero. A 32-bit norm is part of the header."""
    mag = F.abs("sym")
    if form == "dense":
        one = elias_bits(mag + 1) + F.when(mag > 0, 1).otherwise(0)
        return df.groupBy("site").agg(F.sum(one).cast("long").alias("payload_bits"))
    # the place before a bin's first one is the last of the bins before
    some = df.filter("sym <> 0").withColumn("bin", F.floor(F.col("coord") / BIN))
    last = some.groupBy("site", "bin").agg(F.max("coord").alias("top"))
    last = last.select("site", "bin", F.lag("top", 1, -1).over(Window.partitionBy("site").orderBy("bin")).alias("top"))
    inside = F.lag("coord", 1).over(Window.partitionBy("site", "bin").orderBy("coord"))
    runs = some.withColumn("inside", inside).join(last, ["site", "bin"]).withColumn("gap", F.col("coord") - F.coalesce("inside", "top"))
    some = runs.groupBy("site").agg(F.sum(elias_bits(F.col("gap")) + 1 + elias_bits(mag)).cast("long").alias("payload_bits"))
    return df.select("site").distinct().join(some, "site", "left").withColumn("payload_bits", F.coalesce("payload_bits", F.lit(0)))


def fixed_bits(df: DataFrame, alphabet: int) -> DataFrame:
    """Equal-length symbols."""
    return df.groupBy("site").agg((F.count(F.lit(1)) * (alphabet - 1).bit_length()).cast("long").alias("payload_bits"))


def raw_bits(df: DataFrame, width: int = 32) -> DataFrame:
    return df.groupBy("site").agg((F.count(F.lit(1)) * width).cast("long").alias("payload_bits"))


def index_value_bits(d: int, k: int) -> int:
    """A position and a 32-bit value for each of k coordinates."""
    return k * (max((d - 1).bit_length(), 1) + 32)


def kept_bits(kept: DataFrame, sizes: DataFrame) -> DataFrame:
    """(site, kept, payload_bits) of the kept coordinates (site, coord) of vectors of sizes (site, d)."""
    n = kept.groupBy("site").agg(F.count(F.lit(1)).alias("kept"))
    place = F.length(F.bin(F.col("d") - 1))
    return n.join(F.broadcast(sizes.select("site", "d")), "site").select("site", "kept", (F.col("kept") * (place + 32)).alias("payload_bits"))


def symbol_messages(df: DataFrame, block: int, form: str = "sparse") -> DataFrame:
    """(site, block, body): real symbol-wise messages of rows (site, coord, sym, norm), one a block of coordinates."""
    def send(t):
        order = np.argsort(t["coord"].to_numpy(), kind="stable")
        body = codec.symbol_encode(t["sym"].to_numpy()[order], t["norm"][0].as_py(), form)
        return pa.table({"site": t["site"].slice(0, 1), "block": t["block"].slice(0, 1), "body": pa.array([body], pa.binary())})

    rows = df.select("site", F.floor(F.col("coord") / block).cast("long").alias("block"), "coord", "sym", "norm")
    return rows.groupBy("site", "block").applyInArrow(send, "site int, block long, body binary")


def symbols_received(sent: DataFrame, block: int, form: str = "sparse") -> DataFrame:
    """(site, coord, sym, norm) of symbol-wise messages over coordinates from 0 on without holes."""
    def read(batches):
        for t in batches:
            for site, at, body in zip(t["site"].to_pylist(), t["block"].to_pylist(), t["body"].to_pylist(), strict=True):
                sym, norm = codec.symbol_decode(body, form)
                n = len(sym)
                columns = [np.full(n, site, np.int32), np.arange(n) + at * block, sym.astype(np.int32), np.full(n, norm)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["site", "coord", "sym", "norm"])

    return sent.mapInArrow(read, "site int, coord long, sym int, norm double")


def by_block(df: DataFrame, block: int) -> DataFrame:
    """Symbols with site and block of coordinates as their vector: blocks are coded one by one, so no site's symbols meet
    in one task, at the price of a type vector for each block."""
    return df.withColumn("site", F.shiftleft(F.col("site").cast("long"), 32) + F.floor(F.col("coord") / block))


def block_bits(df: DataFrame, levels: int, block: int) -> DataFrame:
    """(site, blocks, type_bits, gap_bits) of a code by blocks."""
    per = bits(by_block(df, block), levels)
    return per.groupBy(F.shiftright("site", 32).cast("int").alias("site")).agg(F.count(F.lit(1)).alias("blocks"), F.sum("type_bits").alias("type_bits"), F.sum("gap_bits").alias("gap_bits"))


def messages(df: DataFrame, levels: int, block: int | None = None) -> DataFrame:
    """(site, block, body): real messages of rows (site, coord, sym, lo, hi), one a site, or one a block of coordinates."""
    def send(t):
        order = np.argsort(t["coord"].to_numpy(), kind="stable")
        body = codec.encode(t["sym"].to_numpy()[order], levels, t["lo"][0].as_py(), t["hi"][0].as_py())
        return pa.table({"site": t["site"].slice(0, 1), "block": t["block"].slice(0, 1), "body": pa.array([body], pa.binary())})

    at = F.floor(F.col("coord") / block) if block else F.lit(0)
    rows = df.select("site", at.cast("long").alias("block"), "coord", "sym", "lo", "hi")
    return rows.groupBy("site", "block").applyInArrow(send, "site int, block long, body binary")


def received(sent: DataFrame, block: int | None = None) -> DataFrame:
    """(site, coord, sym, lo, hi) of messages over coordinates from 0 on without holes."""
    def read(batches):
        for t in batches:
            for site, at, body in zip(t["site"].to_pylist(), t["block"].to_pylist(), t["body"].to_pylist(), strict=True):
                sym, lo, hi = codec.decode(body)
                n, base = len(sym), at * (block or 0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, site, np.int32)), pa.array(np.arange(n) + base), pa.array(sym.astype(np.int32)), pa.array(np.full(n, lo)), pa.array(np.full(n, hi))], ["site", "coord", "sym", "lo", "hi"])

    return sent.mapInArrow(read, "site int, coord long, sym int, lo double, hi double")
