"""Given tables with declared columns, sample and state tables, imports of other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's Parquet files; columns are pruned by what a query selects."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, fmt: str, path: str, schema: str) -> DataFrame:
    """Samples or edge lists from csv, json, orc or parquet with a declared schema."""
    reader = spark.read.format(fmt).schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def write_samples(samples: DataFrame, path: str, buckets: int = 8, seed: int = 42) -> None:
    """Samples by mini-batch bucket: a round reads one directory. Deals by (bucket, site) once."""
    dealt = samples.withColumn("bucket", F.pmod(F.xxhash64("sample_id", F.lit(seed)), F.lit(buckets)).cast("int"))
    dealt.repartition("bucket", "site").write.partitionBy("bucket").mode("overwrite").parquet(path)


def save_state(state: DataFrame, path: str, run_id: str, rnd: int) -> None:
    """A round's state in a directory of its own: a half-written round is never read."""
    state.write.mode("overwrite").parquet(f"{path}/run={run_id}/round={rnd:08d}")


def load_state(spark: SparkSession, path: str, run_id: str, rnd: int) -> DataFrame:
    return spark.read.parquet(f"{path}/run={run_id}/round={rnd:08d}")


def append_trace(trace: DataFrame, path: str) -> None:
    trace.write.mode("append").partitionBy("run_id").parquet(path)


def write_messages(sent: DataFrame, path: str, run_id: str, rnd: int) -> None:
    """A round's encoded messages (site, block, body) in a directory of their own."""
    sent.write.mode("overwrite").parquet(f"{path}/run={run_id}/round={rnd:08d}")


def read_messages(spark: SparkSession, path: str, run_id: str, rnd: int) -> DataFrame:
    return spark.read.schema("site int, block long, body binary").parquet(f"{path}/run={run_id}/round={rnd:08d}")
