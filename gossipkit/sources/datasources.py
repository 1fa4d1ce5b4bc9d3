"""Python data sources: graphs, Laplace vectors and planted samples of any size, made where they are read."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Split(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self):
        n, parts = self.rows(), int(self.options.get("partitions", 8))
        step = max(-(-n // parts), 1)
        return [Range(a, min(a + step, n)) for a in range(0, n, step)]


class TopologySource(DataSource):
    """Options kind (ring, full, circulant), n, offsets (comma-separated)."""

    @classmethod
    def name(cls):
        return "topology"

    def schema(self):
        return "src int, dst int, w double"

    def reader(self, schema):
        return _Topology(self.options)


class _Topology(_Split):
    def rows(self):
        return int(self.options["n"])

    def read(self, part):
        n, kind = self.rows(), self.options.get("kind", "ring")
        offsets = [int(x) for x in self.options.get("offsets", "1").split(",")] if kind != "full" else range(n)
        steps = sorted({s % n for o in offsets for s in (o, -o)} | {0})
        for i in range(part.lo, part.hi):
            for s in steps:
                yield i, (i + s) % n, 1.0 / len(steps)


class LaplaceSource(DataSource):
    """Options n (coordinates), sites, rho, seed."""

    @classmethod
    def name(cls):
        return "laplace"

    def schema(self):
        return "site int, coord long, p double"

    def reader(self, schema):
        return _Laplace(self.options)


class _Laplace(_Split):
    def rows(self):
        return int(self.options["n"]) * int(self.options.get("sites", 1))

    def read(self, part):
        import numpy as np

        sites, rho = int(self.options.get("sites", 1)), float(self.options.get("rho", 1.0))
        rng = np.random.default_rng([int(self.options.get("seed", 42)), part.lo])
        for i, p in zip(range(part.lo, part.hi), rng.laplace(0, rho, part.hi - part.lo), strict=True):
            yield i % sites, i // sites, float(p)


class PlantedSource(DataSource):
    """Options n, features, sites, zeros (share of zero weights), seed: binary samples of a sparse planted model."""

    @classmethod
    def name(cls):
        return "planted"

    def schema(self):
        return "sample_id long, site int, split string, label int, idx array<int>, val array<double>"

    def reader(self, schema):
        return _Planted(self.options)


class _Planted(_Split):
    def rows(self):
        return int(self.options["n"])

    def read(self, part):
        import numpy as np

        k, sites, seed = int(self.options.get("features", 20)), int(self.options.get("sites", 10)), int(self.options.get("seed", 42))
        w = np.random.default_rng(seed).normal(size=k)
        w[: int(k * float(self.options.get("zeros", 0.5)))] = 0
        rng = np.random.default_rng([seed, part.lo])
        for i in range(part.lo, part.hi):
            x = rng.normal(size=k)
            yield i, i % sites, ("train", "train", "train", "validation", "test")[i // sites % 5], int(x @ w > 0), list(range(k + 1)), [*map(float, x), 1.0]


def register(spark) -> None:
    for source in (TopologySource, LaplaceSource, PlantedSource):
        spark.dataSource.register(source)
