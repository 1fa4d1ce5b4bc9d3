"""Several executors give the rows that one JVM gives: shuffles that are read again may come in another order there."""

import json
import os
import subprocess
import sys

import pytest
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
NAMES = ["op3_substring", "op7_token_file", "op8_near_dedup", "pipeline"]


def digest(df):
    """Rows and an order-free hash of them."""
    row = df.select(F.xxhash64(*sorted(df.columns)).alias("h")).agg(F.count("h").alias("n"), F.bit_xor("h").alias("x"), F.sum(F.col("h") % 1000003).alias("s")).first()
    return [row.n, row.x, row.s]


def main(master, sf, shared):
    sys.path.insert(0, ROOT)
    os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, os.environ.get("PYTHONPATH", "")])
    import __spark_entry__ as entry
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(master).config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.executor.memory", "1000m").config("spark.checkpoint.dir", f"file://{shared}").config("spark.sql.warehouse.dir", f"{shared}/warehouse").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    # many files make many map tasks, whose rows reach a reader in no fixed order
    for name in ("documents", "benchmark"):
        spark.read.parquet(f"{sf}/{name}.parquet").repartition(12).write.parquet(f"file://{shared}/in/{name}.parquet")
    sf = f"file://{shared}/in"
    print("DIGESTS " + json.dumps({x: digest(entry.queries()[x](spark, sf)) for x in NAMES}))
    spark.stop()


@pytest.fixture(scope="module")
def clustered(sf, tmp_path_factory):
    shared = tmp_path_factory.mktemp("cluster")
    args = [sys.executable, os.path.abspath(__file__), "local-cluster[4,1,1200]", sf.replace("0.001", "0.01"), str(shared)]
    out = subprocess.run(args, cwd=shared, capture_output=True, text=True, timeout=900, check=True).stdout
    return json.loads(out.split("DIGESTS ")[1].splitlines()[0])


@pytest.mark.parametrize("name", NAMES)
def test_executors_agree_with_one_jvm(spark, sf, clustered, name):
    import __spark_entry__ as entry

    assert clustered[name] == digest(entry.queries()[name](spark, sf.replace("0.001", "0.01")))


if __name__ == "__main__":
    main(*sys.argv[1:])
