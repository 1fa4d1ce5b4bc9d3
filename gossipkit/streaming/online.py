"""Online rounds: one micro-batch is one round, its id the round's number.

State lives in round-addressed directories. A batch that is run again after a failure reads the same earlier state
and writes the same directory, so a round counts once."""

from __future__ import annotations

import uuid
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout
from pyspark.sql.streaming.query import StreamingQuery

from ..operators.losses import LOSSES
from ..plans.config import GossipConfig
from ..plans.engine import Engine
from ..plans.relational import shared_dir
from ..plans.trainers import site_gradients
from ..sources.tables import load, load_state, save_state


def train_online(stream: DataFrame, w: np.ndarray, cfg: GossipConfig, path: str, loss: str = "softmax", features: int = 257, classes: int = 4, run_id: str = "online") -> StreamingQuery:
    """Starts a query over samples (site, label, idx, val); states are under path by round."""
    model = LOSSES[loss](features, classes)
    cfg = replace(cfg, batch=None)
    # tracking goes on from its tracker, the tracker's replica and the last gradient
    kept = ["x", "y", "track", "track_y", "last"] if cfg.method == "tracking" else ["x", "y"]

    def one(batch: DataFrame, t: int) -> None:
        spark, engine = batch.sparkSession, Engine(cfg, w, model.size, model.start())
        if t:
            rows = load_state(spark, path, run_id, t - 1).orderBy("site").collect()
            for k in kept:
                setattr(engine, k, np.array([r[k] for r in rows]))
        engine.t = t
        trace = engine.round(lambda x, _: site_gradients(batch, x, model, features)[0])
        state = [(i, *(getattr(engine, k)[i].tolist() for k in kept), trace["link_bits"]) for i in range(len(w))]
        save_state(spark.createDataFrame(state, "site int, " + "".join(f"{k} array<double>, " for k in kept) + "link_bits long"), path, run_id, t)

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()


def windows(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Counts and sums by window and type; rows later than the watermark are left out of a stream's windows."""
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    return events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    if events.isStreaming:
        events = events.withWatermark("ts", gap)
    s = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def pairs(left: DataFrame, right: DataFrame, key: str, seconds: int, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """(a, b): rows of the right stream within the given seconds after a row of the left one, by key. The watermarks and
    the interval let both sides' state go."""
    a, b = left.withWatermark(ts, late).alias("a"), right.withWatermark(ts, late).alias("b")
    within = F.col(f"b.{ts}").between(F.col(f"a.{ts}"), F.col(f"a.{ts}") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return a.join(b, (F.col(f"a.{key}") == F.col(f"b.{key}")) & within)


def along_links(stream: DataFrame, mixing: DataFrame) -> DataFrame:
    """(src, dst, wx) for a stream (site, x): each value weighted along its site's links. The mixing table has a row a
    link; the planner picks the join by its size."""
    links = mixing.withColumnRenamed("src", "site")
    return stream.join(links, "site").select(F.col("site").alias("src"), "dst", (F.col("w") * F.col("x")).alias("wx"))


def file_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's Parquet file or folder as a stream. The pattern matches that one path; a plain path has to be a folder."""
    stream = spark.readStream.schema(load(spark, sf_dir, name).schema).parquet(f"{sf_dir}/{name}.parque[t]")
    # watermarks need instants; times without a zone are read as UTC, whatever the session's zone
    plain = [f.name for f in stream.schema if f.dataType.typeName() == "timestamp_ntz"]
    micros = "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', `{}`)"
    return stream.withColumns({c: F.timestamp_micros(F.expr(micros.format(c))) for c in plain}) if plain else stream


def finished(stream: DataFrame, name: str) -> DataFrame:
    """All rows that a stream appends until its source is read, stored with its checkpoint in the shared folder."""
    path = f"{shared_dir(stream).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    sink = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/checkpoint")
    sink.trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/rows")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, also when a source replays it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_types(symbols: DataFrame, levels: int) -> DataFrame:
    """(site, counts, rho, d) after each micro-batch for the sites in it, over a stream of rows (site, sym, p): the
    running type vector, from symbol -1 on, and the running Laplace diversity. The state of a site is levels + 2 counts
    and a sum; rows are summed batch by batch and not held."""
    state = "counts array<long>, total double"

    def update(key, batches, held):
        counts, total = np.zeros(levels + 2, np.int64), 0.0
        if held.exists:
            old, total = held.get
            counts += np.array(old, np.int64)
        for b in batches:
            counts += np.bincount(b["sym"].to_numpy() + 1, minlength=levels + 2)
            total += float(np.abs(b["p"].to_numpy()).sum())
        held.update((counts.tolist(), total))
        d = int(counts.sum())
        yield pd.DataFrame({"site": [key[0]], "counts": [counts.tolist()], "rho": [total / max(d, 1)], "d": [d]})

    rows = symbols.select("site", "sym", "p").groupBy("site")
    return rows.applyInPandasWithState(update, "site int, counts array<long>, rho double, d long", state, "update", GroupStateTimeout.NoTimeout)
