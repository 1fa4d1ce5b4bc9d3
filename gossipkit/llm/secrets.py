"""Secret scans with an incremental blob ledger.

Every version of a text is addressed by the SHA-256 of its content. The ledger holds the pairs of blob and
rule version that were scanned, with their findings; a run scans the blobs whose pair is not there, once
each, and joins the findings back to every path that holds the blob. A Ledger is a Parquet folder that every run adds to,
so a later run, of another version of the table or after a failure, scans only what is new.

A blob that many paths hold is one key of that join: paths are dealt over SALT tasks a blob, and only blobs with findings
are sent to each. Rows are added to a ledger before they are reported; a pair that two runs add at once is read as one.

Defined cases: a null text is the empty blob; paths of equal content share one scan; without a finding
spans is empty and the digest that of the empty string; an empty table scans nothing and gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import spans as S
from .common import scratch, stored

RULE_VERSION = "r1"
SALT = 8
FOUND = "array<struct<start:int,rank:int,end:int,kind:string>>"
LEDGER = f"blob binary, rule_version string, found {FOUND}"
#: The base kinds in their order, with the least length of a match or its value.
KINDS = ["assign", "access", "hex"]
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]++)"""
PATTERNS = {
    "assign": ASSIGN,
    "access": r"AKIA[A-Z0-9]{12,}+",
    "hex": r"[0-9a-f]{32,}+",
    "pem": r"-----BEGIN\x20(?:[A-Z]+\x20)*PRIVATE\x20KEY-----",
    "jwt": r"eyJ[A-Za-z0-9_-]{10,}+\.eyJ[A-Za-z0-9_-]{10,}+\.[A-Za-z0-9_-]{10,}+",
    "hub": r"gh[pousr]_[A-Za-z0-9]{36}(?![A-Za-z0-9])",
    "bearer": r"(?i:bearer)\x20[A-Za-z0-9+/_.=-]{20,}+",
}
#: Plain text that must occur where a pattern can match, or none.
NEEDS = {"access": ["AKIA"], "pem": ["-----BEGIN"], "jwt": ["eyJ"], "hub": ["ghp_", "gho_", "ghu_", "ghs_", "ghr_"]}


def _valid(kind: str):
    return (lambda v: F.char_length(F.regexp_extract(v, ASSIGN, 1)) >= 8) if kind == "assign" else (lambda v: F.lit(True))


def findings(text: Column) -> Column:
    """All spans of a text, as structs (start, rank, end, kind)."""
    def of(rank: int, kind: str) -> Column:
        found = S.tagged(S.find(text, PATTERNS[kind], _valid(kind)), kind, rank)
        if kind not in NEEDS:
            return found
        some = F.contains(text, F.lit(NEEDS[kind][0]))
        for x in NEEDS[kind][1:]:
            some = some | F.contains(text, F.lit(x))
        return F.when(some, found).otherwise(F.array().cast(FOUND))

    return F.concat(*(of(i, k) for i, k in enumerate(PATTERNS)))


def addressed(versions: DataFrame, text: str = "text") -> DataFrame:
    whole = F.coalesce(F.col(text), F.lit(""))
    return versions.withColumn("blob", F.unhex(F.sha2(whole.cast("binary"), 256)))


def scan(versions: DataFrame, ledger: DataFrame | None = None, rule_version: str = RULE_VERSION, text: str = "text") -> DataFrame:
    """New ledger rows (blob, rule_version, found) for the blobs that the ledger lacks at this rule version."""
    # one row of each content: map-side first, so that copies are not shuffled
    once = addressed(versions.select(F.col(text).alias("text"))).dropDuplicates(["blob"])
    if ledger is not None:
        once = once.join(ledger.filter(F.col("rule_version") == rule_version).select("blob").hint("merge"), "blob", "left_anti")
    return once.select("blob", F.lit(rule_version).alias("rule_version"), findings(F.coalesce(F.col("text"), F.lit(""))).alias("found"))


def report(versions: DataFrame, ledger: DataFrame, key: str = "doc_id", rule_version: str = RULE_VERSION, text: str = "text") -> DataFrame:
    """One row for each path: counts and digest of the base spans, and all spans."""
    hits = ledger.filter((F.col("rule_version") == rule_version) & (F.size("found") > 0)).select("blob", "found")
    paths = addressed(versions.select(F.col(key).alias("key"), F.col(text).alias("text"))).select("key", "blob", F.pmod(F.xxhash64("key"), F.lit(SALT)).alias("salt"))
    each = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALT - 1).cast("long")))
    hits = hits.groupBy("blob").agg(F.any_value("found").alias("found")).select("blob", "found", each.alias("salt"))
    df = paths.join(hits, ["blob", "salt"], "left").withColumn("found", F.coalesce("found", F.array().cast(FOUND)))
    base = F.filter("found", lambda s: s["rank"] < len(KINDS))
    count = lambda k: F.size(F.filter("found", lambda s: s["kind"] == k)).cast("long")
    return df.select(
        F.col("key").alias(key), *(count(k).alias(f"n_{k}") for k in KINDS), F.sha2(S.rendered(base).cast("binary"), 256).alias("base_sha256"),
        S.rendered(F.col("found")).alias("spans"), F.hex("blob").alias("blob"),
    )


def run(versions: DataFrame, ledger: DataFrame | None = None, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(report, grown ledger); the new ledger rows are written before they are used."""
    new = stored(scan(versions, ledger, text=text), "secrets")
    grown = new if ledger is None else ledger.unionByName(new)
    return report(versions, grown, key, text=text), grown


class Ledger:
    """A ledger in a folder; runs add to it."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def rows(self) -> DataFrame | None:
        """All pairs scanned so far; None before the first run."""
        at = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        if not at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at):
            return None
        return self.spark.read.schema(LEDGER).parquet(self.path)

    def add(self, versions: DataFrame, text: str = "text", rule_version: str = RULE_VERSION) -> None:
        """Scans the blobs of these rows that the ledger lacks at this rule version."""
        scan(versions, self.rows(), rule_version, text).write.mode("append").parquet(self.path)


def history(commits: Iterable[DataFrame], paths: DataFrame, ledger: Ledger, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Scans commit after commit into the ledger, what it lacks of each; the report of all paths."""
    for rows in commits:
        ledger.add(rows, text)
    return report(paths, ledger.rows(), key, text=text)


def new_ledger(spark: SparkSession) -> Ledger:
    """A ledger in the shared folder."""
    return Ledger(spark, scratch(spark, "secrets"))
