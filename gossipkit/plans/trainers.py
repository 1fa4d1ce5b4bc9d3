"""Trainers: rounds whose gradients Spark computes, and sweeps of whole runs."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.losses import LOSSES
from ..operators.topology import MAX_DRIVER_SITES
from .config import GossipConfig
from .engine import Engine
from .relational import cut

#: Values of all sites' models that the driver holds and broadcasts; beyond it use plans.relational.
MAX_STATE = 1 << 24
#: Partial gradients of a site that one task adds up.
FAN, TASK_BYTES = 64, 32 << 20
#: Up to so many training rows a run on all rows of a site gets them in its task; beyond it Spark sums each round's gradients.
LOCAL_ROWS = 1 << 15
#: Ranges of ids in which the places of training rows are counted; rows made dense at once and bytes of models in one pass of an evaluation.
BINS, CHUNK, MODEL_BYTES = 1024, 1024, 32 << 20
#: Samples of a site that are packed in one row for repeated passes.
BLOCK = 256
TRACE = (
    "run_id string, round int, messages int, payload_bits long, link_bits long, eta double, stationarity double, consensus double, zero_share double, "
    "laplace_rho double, dominant_share double, entropy double, loss double, objective double, accuracy double, validation double"
)
TRACE_FIELDS = [f.split() for f in TRACE.split(", ")]


@dataclass
class TrainResult:
    """state: rows (site, x, z, y); trace: one row a round; model: the mean over sites."""

    state: DataFrame
    trace: DataFrame
    model: np.ndarray


def dense(idx: pa.Array, val: pa.Array, features: int) -> np.ndarray:
    """Rows of a batch's lists of positions and values."""
    out = np.zeros((len(idx), features))
    n = pc.fill_null(pc.list_value_length(idx), 0).to_numpy(zero_copy_only=False)
    out[np.repeat(np.arange(len(idx)), n), idx.flatten().to_numpy(zero_copy_only=False)] = val.flatten().to_numpy(zero_copy_only=False)
    return out


def site_gradients(samples: DataFrame, x: np.ndarray, loss, features: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per site: mean gradient, mean loss and number of its rows in samples. A task sums its rows per site; the sums meet by
    site and salt and then by site, so that no task holds more than FAN gradients of a site at once, however many
    tasks there were, and the driver gets one row a site."""
    size = x.shape[1]
    model = samples.sparkSession.sparkContext.broadcast(x)

    def partial(batches):
        total: dict[int, list] = {}
        for t in batches:
            for s, rows, y in _by_site(t, features):
                v, g = loss.value_grad(model.value[s], rows, y)
                acc = total.setdefault(s, [0, 0.0, np.zeros(size)])
                acc[0], acc[1], acc[2] = acc[0] + len(y), acc[1] + v * len(y), acc[2] + g * len(y)
        yield _sums([(s, *a) for s, a in total.items()])

    grad, value, count = np.zeros_like(x), np.zeros(len(x)), np.zeros(len(x), np.int64)
    for r in _added(samples, samples.select("site", "label", "idx", "val", *(c for c in samples.columns if c == "ends")).mapInArrow(partial, SUMS), size):
        count[r.site], value[r.site], grad[r.site] = r.n, r.loss / r.n, np.array(r.grad) / r.n
    model.unpersist()
    return grad, value, count


def _by_site(t: pa.RecordBatch, features: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(site, dense rows, labels) of a batch of samples, or of rows that blocks made."""
    if "ends" not in t.schema.names:
        site, y, rows = t["site"].to_numpy(zero_copy_only=False), t["label"].to_numpy(zero_copy_only=False), dense(t["idx"], t["val"], features)
        for s in np.unique(site):
            yield int(s), rows[site == s], y[site == s]
        return
    for i, s in enumerate(t["site"].to_pylist()):
        y, ends, idx, val = (np.frombuffer(t[c][i].as_buffer(), k) for c, k in BODY)
        rows = np.zeros((len(y), features))
        rows[np.repeat(np.arange(len(y)), np.diff(ends, prepend=0)), idx] = val
        yield s, rows, y


BODY = [("label", np.int32), ("ends", np.int32), ("idx", np.int32), ("val", np.float64)]


def blocks(samples: DataFrame) -> DataFrame:
    """(site, label, ends, idx, val): up to BLOCK samples of a site in a row, their columns as bytes, for passes that would
    otherwise move every list value by value once a round. ends has each sample's end in idx and val."""

    def pack(batches):
        for t in batches:
            site = t["site"].to_numpy(zero_copy_only=False)
            for s in np.unique(site):
                at = np.flatnonzero(site == s)
                for a in range(0, len(at), BLOCK):
                    own = t.take(pa.array(at[a : a + BLOCK]))
                    ends = np.cumsum(pc.fill_null(pc.list_value_length(own["idx"]), 0).to_numpy(zero_copy_only=False))
                    cols = {"label": own["label"], "ends": ends, "idx": own["idx"].flatten(), "val": own["val"].flatten()}
                    body = [pa.array([np.asarray(cols[c]).astype(k).tobytes()], pa.binary()) for c, k in BODY]
                    yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), *body], ["site", *cols])

    return samples.select("site", "label", "idx", "val").mapInArrow(pack, "site int, label binary, ends binary, idx binary, val binary")


SUMS = "site int, n long, loss double, grad array<double>"


def _added(samples: DataFrame, sums: DataFrame, size: int) -> list:
    """The tasks' sums, one row a site."""

    def add(t):
        g = np.zeros(size)
        for v in t["grad"]:
            g += np.asarray(v.values)
        return pa.Table.from_batches([_sums([(t["site"][0].as_py(), sum(t["n"].to_pylist()), sum(t["loss"].to_pylist()), g)])])

    # input for more than about FAN tasks is summed in two levels
    if int(str(samples._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) > FAN * TASK_BYTES:
        sums = sums.withColumn("salt", F.floor(F.spark_partition_id() / F.lit(FAN))).groupBy("site", "salt").applyInArrow(add, SUMS)
    return sums.groupBy("site").applyInArrow(add, SUMS).collect()


def site_grams(samples: DataFrame, sites: int, features: int) -> np.ndarray:
    """Each site's mean of x x' over its rows."""

    def partial(batches):
        total: dict[int, list] = {}
        for t in batches:
            site, rows = t["site"].to_numpy(zero_copy_only=False), dense(t["idx"], t["val"], features)
            for s in np.unique(site):
                own = rows[site == s]
                acc = total.setdefault(int(s), [0, 0.0, np.zeros((features, features))])
                acc[0], acc[2] = acc[0] + len(own), acc[2] + own.T @ own
        yield _sums([(s, n, v, g.ravel()) for s, (n, v, g) in total.items()])

    out = np.zeros((sites, features, features))
    for r in _added(samples, samples.select("site", "idx", "val").mapInArrow(partial, SUMS), features * features):
        out[r.site] = np.array(r.grad).reshape(features, features) / r.n
    return out


def _sums(rows: list) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[], [], [], []]
    return pa.RecordBatch.from_arrays(
        [pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64()), pa.array([np.asarray(g) for g in cols[3]], pa.list_(pa.float64()))], ["site", "n", "loss", "grad"]
    )


def batched(samples: DataFrame, cfg: GossipConfig, t: int, buckets: int) -> DataFrame:
    """The rows of round t: one hash bucket, read by partition pruning where samples are stored by bucket."""
    return samples if cfg.batch is None else samples.filter(F.col("bucket") == (t - 1) % buckets)


def train(samples: DataFrame, w: np.ndarray, cfg: GossipConfig, loss: str = "softmax", features: int = 257, classes: int = 4, buckets: int = 8, run_id: str = "run") -> TrainResult:
    """Trains on samples of any size: rows (site, split, label, idx, val), with bucket if batches are wanted."""
    if len(w) > MAX_DRIVER_SITES:
        raise ValueError("too many sites for a mixing matrix on the driver")
    model = LOSSES[loss](features, classes)
    if len(w) * model.size > MAX_STATE:
        raise ValueError("the sites' models exceed the broadcast bound")
    spark, engine = samples.sparkSession, Engine(cfg, w, model.size, model.start())
    fit, held = samples.filter("split = 'train'"), samples.filter("split = 'validation'")
    trace = []
    for t in range(1, cfg.rounds + 1):
        seen: dict = {}

        def gradient(x, t):
            g, value, n = site_gradients(batched(fit, cfg, t, buckets), x, model, features)
            seen["loss"] = float((value * n).sum() / max(n.sum(), 1))
            return g

        row = engine.round(gradient) | {"run_id": run_id, "accuracy": None, "validation": None}
        row["loss"], row["objective"] = seen["loss"], seen["loss"] + cfg.mu * float(np.abs(engine.mean()).sum())
        if t % cfg.eval_every == 0 or t == cfg.rounds:
            row["validation"] = accuracy(held, engine.mean(), model, features)
        trace.append(row)
    state = spark.createDataFrame([(i, *(a[i].tolist() for a in (engine.x, engine.z, engine.y))) for i in range(len(w))], "site int, x array<double>, z array<double>, y array<double>")
    return TrainResult(state, spark.createDataFrame([[r[f] for f, _ in TRACE_FIELDS] for r in trace], TRACE), engine.mean())


def accuracy(samples: DataFrame, weights: np.ndarray, loss, features: int) -> float | None:
    model = samples.sparkSession.sparkContext.broadcast(weights)

    def hits(batches):
        for t in batches:
            ok = loss.predict(model.value, dense(t["idx"], t["val"], features)) == t["label"].to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array([int(ok.sum())]), pa.array([len(ok)])], ["ok", "n"])

    return samples.select("label", "idx", "val").mapInArrow(hits, "ok long, n long").agg((F.sum("ok") / F.sum("n")).alias("a")).first().a


class Pool:
    """A workload of any size for sweeps: rows (sample_id, site, split, label, idx, val) stored in the shared folder, and the
    number of training rows of each site. A training row's place is its position among its site's by id."""

    def __init__(self, rows: DataFrame, features: int, sites: int):
        self.rows, self.features = rows, features
        self.fit, self.held = rows.filter("split = 'train'"), rows.filter("split IN ('validation', 'test')")
        self.sizes = np.zeros(sites, np.int64)
        for r in self.fit.groupBy("site").count().collect():
            if 0 <= r.site < sites:
                self.sizes[r.site] = r["count"]

    def at_sites(self, site, sites: int) -> Pool:
        """The same rows, dealt to sites by another column."""
        return Pool(self.rows.withColumn("site", site.cast("int")), self.features, sites)

    def placed(self) -> DataFrame:
        """(site, sample_id, own, place) of the training rows. Places are counted within ranges of ids and put together by
        prefix sums, so no task sees a whole site."""
        keys = self.fit.select("site", "sample_id", F.xxhash64("label", "idx", "val").alias("own"))
        ends = keys.agg(F.min("sample_id").alias("lo"), F.max("sample_id").alias("hi")).first()
        width = 1 if ends.lo is None else (ends.hi - ends.lo) // BINS + 1
        keys = keys.withColumn("bin", F.expr(f"(sample_id - {ends.lo or 0}L) div {width}L"))
        before = F.sum("n").over(Window.partitionBy("site").orderBy("bin")) - F.col("n")
        start = keys.groupBy("site", "bin").agg(F.count(F.lit(1)).alias("n")).select("site", "bin", before.alias("start"))
        inside = F.row_number().over(Window.partitionBy("site", "bin").orderBy("sample_id", "own")) - 1
        return keys.withColumn("i", inside).join(start, ["site", "bin"]).select("site", "sample_id", "own", (F.col("start") + F.col("i")).alias("place"))

    def picked(self, places: dict[int, np.ndarray]) -> Picked:
        """Rows at the wanted places of each site, on the driver."""
        want = pa.table({"site": np.repeat(np.array(list(places), np.int32), [len(p) for p in places.values()]), "place": np.concatenate([*places.values(), np.zeros(0, np.int64)]).astype(np.int64)})
        spark = self.rows.sparkSession
        found = self.placed().join(F.broadcast(spark.createDataFrame(want)), ["site", "place"])
        rows = self.fit.withColumn("own", F.xxhash64("label", "idx", "val")).join(F.broadcast(found), ["site", "sample_id", "own"])
        rows = rows.select("site", "place", "label", F.col("idx").cast("array<int>").alias("idx"), F.col("val").cast("array<double>").alias("val")).dropDuplicates(["site", "place"])
        return Picked(rows.toArrow().combine_chunks(), self.features)


class Picked:
    """Some training rows, kept sparse; looked up by site and place."""

    def __init__(self, rows: pa.Table, features: int):
        site, place = (rows[c].to_numpy().astype(np.int64) for c in ("site", "place"))
        rows = rows.take(pa.array(order := np.lexsort((place, site)))).combine_chunks()
        self.features, self.site, self.place, self.label = features, site[order], place[order], rows["label"].to_numpy()
        parts = [pa.concat_arrays(rows[c].chunks) if rows[c].num_chunks else pa.array([], rows[c].type) for c in ("idx", "val")]
        self.first = np.concatenate([[0], np.cumsum(pc.list_value_length(parts[0]).to_numpy(zero_copy_only=False))]).astype(np.int64)
        self.idx, self.val = (p.flatten().to_numpy(zero_copy_only=False) for p in parts)

    def take(self, site: int, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Dense rows and labels."""
        lo, hi = np.searchsorted(self.site, [site, site + 1])
        at = lo + np.searchsorted(self.place[lo:hi], places)
        if len(at) and (at.max() >= hi or (self.place[at] != places).any()):
            raise LookupError(f"rows of site {site} that were not picked")
        n = self.first[at + 1] - self.first[at]
        flat = np.repeat(self.first[at] - np.cumsum(n) + n, n) + np.arange(n.sum())
        x = np.zeros((len(at), self.features))
        x[np.repeat(np.arange(len(at)), n), self.idx[flat]] = self.val[flat]
        return x, self.label[at]


def pooled(samples: DataFrame, features: int, sites: int) -> Pool:
    """samples, stored for a sweep."""
    return Pool(cut(samples.select("sample_id", "site", "split", "label", "idx", "val"), "samples"), features, sites)


def batch_of(cfg: GossipConfig, t: int, site: int, n: int) -> np.ndarray:
    """Places of the training rows that a site with n of them takes in round t."""
    if cfg.batch is None or cfg.batch >= n:
        return np.arange(n)
    return np.random.Generator(np.random.Philox(np.random.SeedSequence([cfg.seed, t, site, 1]))).choice(n, cfg.batch, replace=False)


def wanted(runs: list[GossipConfig], sizes: np.ndarray) -> dict[int, np.ndarray]:
    """All places that the runs' batches take, by site: at most rounds x batch of each site and kind of batch."""
    out = {}
    kinds = {(c.seed, c.batch): c for c in sorted(runs, key=lambda c: c.rounds)}.values()
    for s, n in enumerate(sizes.tolist()):
        out[s] = np.unique(np.concatenate([np.zeros(0, np.int64), *(batch_of(c, t, s, n) for c in kinds for t in range(1, c.rounds + 1 if c.batch is not None and c.batch < n else 2))]))
    return out


def simulate(local, w: np.ndarray, cfg: GossipConfig, model) -> Iterator[dict]:
    """The rounds of one run. local(x, t) gives the sites' gradients and mean losses, nan where a site has no rows. Evaluated
    rounds have the mean model."""
    engine = Engine(cfg, w, model.size, model.start())
    last: dict = {}

    def gradient(x, t):
        g, value = local(x, t)
        last["loss"] = float(np.nanmean(value))
        return g

    for t in range(1, cfg.rounds + 1):
        row, m = engine.round(gradient), engine.mean()
        row |= {"loss": last["loss"], "objective": last["loss"] + cfg.mu * float(np.abs(m).sum()), "accuracy": None, "validation": None}
        yield row | {"model": m.tobytes() if t % cfg.eval_every == 0 or t == cfg.rounds else None}


def from_rows(rows: Picked, sizes: np.ndarray, cfg: GossipConfig, model):
    """Gradients of a run in its own task."""

    def local(x, t):
        out, value = np.zeros_like(x), np.full(len(x), np.nan)
        for s, n in enumerate(sizes.tolist()):
            if n:
                value[s], out[s] = model.value_grad(x[s], *rows.take(s, batch_of(cfg, t, s, n)))
        return out, value

    return local


def from_table(fit: DataFrame, model, features: int):
    """Gradients of a run over all rows where they are."""

    def local(x, t):
        g, value, n = site_gradients(fit, x, model, features)
        return g, np.where(n > 0, value, np.nan)

    return local


def evaluated(models: list[np.ndarray], held: DataFrame, model, features: int) -> dict[tuple[int, str], float]:
    """Accuracy of each model on all rows of each split."""
    shared = held.sparkSession.sparkContext.broadcast(models)

    def hits(batches):
        total: dict[str, np.ndarray] = {}
        for t in batches:
            split = np.array(t["split"].to_pylist())
            for a in range(0, len(split), CHUNK):
                own = t.slice(a, CHUNK)
                x, y = dense(own["idx"], own["val"], features), own["label"].to_numpy(zero_copy_only=False)
                right = np.array([model.predict(m, x) == y for m in shared.value])
                for k in set(split[a : a + CHUNK]):
                    of = split[a : a + CHUNK] == k
                    total[k] = total.get(k, 0) + np.column_stack([right[:, of].sum(1), np.full(len(right), of.sum())])
        for k, n in total.items():
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n))), pa.array([str(k)] * len(n)), pa.array(n[:, 0]), pa.array(n[:, 1])], ["m", "split", "ok", "n"])

    rows = held.select("split", "label", "idx", "val").mapInArrow(hits, "m long, split string, ok long, n long").groupBy("m", "split").agg(F.sum("ok").alias("ok"), F.sum("n").alias("n")).collect()
    shared.unpersist()
    return {(r.m, r.split): r.ok / r.n for r in rows}


def sweep(spark: SparkSession, runs: list[tuple[str, np.ndarray, GossipConfig]], pool: Pool, loss: str = "softmax", features: int = 257, classes: int = 4) -> DataFrame:
    """The traces of many runs (run_id, mixing matrix, settings) over one workload. A run is a task with the rows of its batches,
    whose number the settings bound; a run on all rows of a large table has its gradients summed by Spark. All models to
    evaluate meet all held-out rows where those are."""
    model, todo = LOSSES[loss](features, classes), dict(enumerate(runs))
    spread = {i for i, (_, _, c) in todo.items() if c.batch is None and pool.sizes.sum() > LOCAL_ROWS}
    near = [i for i in todo if i not in spread]
    rows = pool.picked(wanted([runs[i][2] for i in near], pool.sizes))
    shared = spark.sparkContext.broadcast((rows, pool.sizes, {i: (runs[i][1], asdict(runs[i][2])) for i in near}))

    def go(batches):
        own, sizes, settings = shared.value
        for t in batches:
            for k in t["id"].to_pylist():
                w, cfg = settings[near[k]][0], GossipConfig(**settings[near[k]][1])
                yield _traced(near[k], simulate(from_rows(own, sizes, cfg, model), w, cfg, model))

    fit = cut(blocks(pool.fit), "blocks") if spread else None
    parts = [spark.range(0, len(near), 1, len(near)).mapInArrow(go, f"i int, {TRACE}, model binary")] if near else []
    for i in sorted(spread):
        _, w, cfg = runs[i]
        made = _traced(i, simulate(from_table(fit, model, features), w, cfg, model))
        parts.append(spark.createDataFrame(pa.Table.from_batches([made]), f"i int, {TRACE}, model binary"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    out = cut(out, "runs")
    shared.unpersist()
    scores, group = [], []

    def score():
        got = evaluated([np.frombuffer(r.model) for r in group], pool.held, model, features)
        scores.extend((r.i, r.round, got.get((k, "test")), got.get((k, "validation"))) for k, r in enumerate(group))
        group.clear()

    for r in out.filter("model IS NOT NULL").select("i", "round", "model").toLocalIterator():
        group.append(r)
        if len(group) * 8 * model.size >= MODEL_BYTES:
            score()
    if group:
        score()
    names = spark.createDataFrame([(i, r) for i, (r, *_) in todo.items()], "i int, run_id string")
    found = spark.createDataFrame(scores, "i int, round int, accuracy double, validation double")
    out = out.drop("model", "run_id", "accuracy", "validation").join(F.broadcast(names), "i").join(F.broadcast(found), ["i", "round"], "left")
    return cut(out.select(*(f for f, _ in TRACE_FIELDS)), "traces")


def _traced(i: int, rows: Iterator[dict]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist([{"i": i, "run_id": None} | r for r in rows], schema=ARROW)


_KINDS = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
ARROW = pa.schema([("i", pa.int32()), *((f, _KINDS[k]) for f, k in TRACE_FIELDS), ("model", pa.binary())])
