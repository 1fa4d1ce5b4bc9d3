"""SQL surface: scalar SQL functions that the optimiser inlines, Arrow functions for real messages, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

INT = T.IntegerType()

SCALARS = {
    "soft_threshold(x DOUBLE, t DOUBLE)": ("DOUBLE", "signum(x) * greatest(abs(x) - t, 0D)"),
    "dither(seed BIGINT, rnd BIGINT, site BIGINT, coord BIGINT)": ("DOUBLE", "CAST(conv(substr(md5(concat_ws('/', seed, rnd, site, coord)), 1, 8), 16, 10) AS DOUBLE) / 4294967296D"),
    "level_of(p DOUBLE, lo DOUBLE, hi DOUBLE, levels INT, u DOUBLE)": ("INT", "CAST(CASE WHEN p = 0 THEN -1 WHEN hi = lo THEN 0 ELSE floor(least(greatest((p - lo) / (hi - lo), 0D), 1D) * levels + u) END AS INT)"),
}


@F.pandas_udf(T.BinaryType())
def levelset_encode(sym: pd.Series, levels: pd.Series) -> pd.Series:
    """A message of each array of symbols."""
    from ..operators.codec import encode

    return pd.Series([encode(np.asarray(s), int(x)) for s, x in zip(sym, levels, strict=True)])


@F.pandas_udf(T.ArrayType(INT))
def levelset_decode(message: pd.Series) -> pd.Series:
    from ..operators.codec import decode

    return pd.Series([decode(bytes(m))[0].astype(np.int32) for m in message])


@F.udtf(returnType=T.StructType().add("src", INT).add("dst", INT).add("w", T.DoubleType()))
class Topology:
    """topology(kind, n): ring or full."""

    def eval(self, kind: str, n: int):
        steps = range(n) if kind == "full" else sorted({0, 1 % n, -1 % n})
        for i in range(n):
            for s in steps:
                yield i, (i + s) % n, 1.0 / len(steps)


@F.udtf(returnType=T.StructType().add("site", INT).add("rank", INT).add("seq", INT).add("gap", INT))
class LevelRuns:
    """level_runs(TABLE(...) PARTITION BY site ORDER BY coord) over columns site, coord, sym: the run lengths of each
    transmitted level."""

    def __init__(self):
        self.site, self.sym = None, []

    def eval(self, row):
        self.site = row["site"]
        self.sym.append(row["sym"])

    def terminate(self):
        from ..operators.codec import passes

        sym = np.array(self.sym)
        for rank, (_, _, gaps) in enumerate(passes(sym, max(int(sym.max()), 1)), 1):
            for seq, g in enumerate(gaps.tolist(), 1):
                yield self.site, rank, seq, g


def register(spark: SparkSession) -> None:
    for head, (kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
    spark.udf.register("levelset_encode", levelset_encode)
    spark.udf.register("levelset_decode", levelset_decode)
    spark.udtf.register("topology", Topology)
    spark.udtf.register("level_runs", LevelRuns)
