"""Queries that once made their data up read a given table: their results follow it."""

import pytest
from gossipkit import oracles, queries
from oracle import same
from pyspark.sql import functions as F

READS = {
    "golomb_bits": "orders", "mixing_circulant": "events", "mixing_fc": "events", "mixing_ring": "events", "range_coverage": "embeddings", "rate_curves": "embeddings", "spectra_closed": "events",
    "stationarity_bound": "embeddings",
}


@pytest.mark.parametrize("name", sorted(READS))
def test_results_follow_the_table(spark, sf, tmp_path, name):
    """On tables with fewer rows and sites the result is another one, and still the SQL's."""
    keys = {"orders": F.col("o_custkey") % 3 == 0, "events": F.col("user_id") % 10 < 7, "embeddings": F.col("vec_id") % 4 != 1}
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        if t in keys:
            spark.read.parquet(f"{sf}/{t}.parquet").filter(keys[t]).toPandas().to_parquet(tmp_path / f"{t}.parquet", coerce_timestamps="us")
        else:
            (tmp_path / f"{t}.parquet").symlink_to(f"{sf}/{t}.parquet")
    few = same(spark, str(tmp_path), queries.QUERIES[name], oracles.ORACLES[name])
    assert sorted(few) != sorted(same(spark, sf, queries.QUERIES[name], oracles.ORACLES[name]))
