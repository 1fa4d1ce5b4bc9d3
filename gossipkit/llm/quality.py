"""Rule bitmask ledger (DataFrame functions only).

Every rule is evaluated once. A document's ledger row holds the measurements and ``fail_bits``, one bit for
each rule it fails. A policy is a version with two masks: a document is rejected if it fails any rule of
``hard`` or at least ``soft_limit`` rules of ``soft``. New policies and ablations read the ledger, never the text.

Defined cases: a null or empty text has no words and fails the rule on length; a null id is carried along;
in a ledger, columns of the input whose names it uses are replaced by its own; accepted() returns the input's columns
unchanged, whatever their names; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SEPARATOR_CLASS, SEPARATORS, stored, words

WINDOW = 8
MEASURES = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words"]

#: The order fixes the bits: rule i owns bit i.
RULES: dict[str, Column | None] = dict.fromkeys(
    ["too_short", "repeats_itself", "symbol_heavy", "repeated_lines", "word_length", "pipe_table"]
)


def _rules() -> list[tuple[str, Column]]:
    c = F.col
    return [
        ("too_short", c("n_words") < 20),
        ("repeats_itself", 100 * c("n_repeat_words") > 30 * c("n_words")),
        ("symbol_heavy", 100 * c("n_symbols") > 15 * c("word_chars")),
        ("repeated_lines", (c("n_lines") >= 4) & (100 * c("n_dup_lines") > 50 * c("n_lines"))),
        ("word_length", (c("word_chars") < 2 * c("n_words")) | (c("word_chars") > 25 * c("n_words"))),
        ("pipe_table", 100 * c("n_symbols") > 40 * c("n_words")),
    ]


def mask_of(*names: str) -> int:
    return sum(1 << list(RULES).index(n) for n in names)


@dataclass(frozen=True)
class Policy:
    """Rejects on any failed rule of hard, or on soft_limit failed rules of soft."""

    version: str
    hard: int
    soft: int = 0
    soft_limit: int = 2

    def rejects(self, bits: Column) -> Column:
        hard = bits.bitwiseAND(F.lit(self.hard)) != 0
        return hard | (F.bit_count(bits.bitwiseAND(F.lit(self.soft))) >= self.soft_limit)


POLICIES = {
    "v1": Policy("v1", hard=mask_of("too_short", "repeats_itself")),
    "v2": Policy("v2", hard=mask_of("too_short", "repeats_itself", "symbol_heavy"), soft=mask_of("repeated_lines", "word_length", "pipe_table")),
}
CURRENT = "v2"


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds the measurements; every text is split into words once."""
    # the input's columns wait in one struct, where their names meet no other
    own = [F.col("row").getField(c).alias(c) for c in docs.columns if c not in MEASURES]
    docs = docs.select(F.struct("*").alias("row"), F.col(text).cast("string").alias("text"))
    whole = F.coalesce(F.col("text"), F.lit(""))
    plain = F.translate(whole, SEPARATORS, "")
    lines = F.filter(F.split(whole, "\n", -1), lambda x: F.rlike(x, F.lit("[^" + SEPARATOR_CLASS[1:])))
    df = docs.withColumns({
        "_w": words(F.col("text")), "_lines": lines,
        "word_chars": F.char_length(plain).cast("long"),
        "n_symbols": (F.char_length(whole) - F.char_length(F.translate(whole, "#*$%&|<>", ""))).cast("long"),
    })
    df = df.withColumns({
        "n_words": F.when(F.col("word_chars") == 0, 0).otherwise(F.size("_w")).cast("long"),
        "n_lines": F.size("_lines").cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "_h": F.when(F.size("_w") >= WINDOW, F.transform(F.sequence(F.lit(1), F.size("_w") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice("_w", i, WINDOW)))),
    })
    # a sort is needed only where a window occurs twice
    twice = F.size(F.array_distinct("_h")) < F.size("_h")
    df = df.withColumn("_s", F.when(twice, F.sort_array(F.transform("_h", lambda x, i: F.struct(x.alias("h"), i.alias("p"))))))
    near = F.expr("filter(_s, (x, i) -> (i > 0 AND get(_s, i - 1).h = x.h) OR get(_s, i + 1).h <=> x.h)")
    at = F.sort_array(F.transform(near, lambda x: x["p"]))
    covered = F.aggregate(
        at, F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")),
        lambda a, p: F.struct((a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n"), p.alias("last")), lambda a: a["n"],
    )
    return df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).select(*own, *MEASURES)


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """Measurements and fail_bits of every document, next to the input's own columns."""
    df = measure(docs, text)
    bits = sum((F.when(cond, F.lit(1 << i)).otherwise(F.lit(0)) for i, (_, cond) in enumerate(_rules())), F.lit(0))
    return df.withColumn("fail_bits", bits.cast("long"))


def recorded(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """The ledger as a table: key, measurements and fail_bits, written once (to path, or to the shared folder). Policies
    and ablations read it; texts are not read again."""
    led = ledger(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), "text").drop("text").withColumnRenamed("key", key)
    if path is None:
        return stored(led, "ledger")
    led.write.parquet(path)
    return docs.sparkSession.read.schema(led.schema).parquet(path)


def apply_policy(led: DataFrame, policy: Policy = POLICIES[CURRENT]) -> DataFrame:
    base = F.col("fail_bits").bitwiseAND(F.lit(mask_of("too_short", "repeats_itself"))) != 0
    return led.withColumns({"base_failed": base, "kept": ~(base | policy.rejects(F.col("fail_bits"))), "policy": F.lit(policy.version)})


def accepted(docs: DataFrame, policy: Policy = POLICIES[CURRENT], text: str = "text") -> DataFrame:
    """The rows of docs that the policy keeps, with their own columns only."""
    judged = apply_policy(ledger(docs.select(F.struct("*").alias("whole"), F.col(text).alias("text"))), policy)
    # a filter on a deterministic column would be pushed down and evaluate every measurement again for each use
    once = judged.withColumn("kept", F.col("kept") & (F.monotonically_increasing_id() >= 0))
    return once.filter("kept").select("whole.*")


def ablation(led: DataFrame, policy: Policy = POLICIES[CURRENT]) -> DataFrame:
    """For each rule: failures, documents rejected without it, documents that only it rejects."""
    # one row for each mask of failures, at most 2^rules: the policies see each once
    masks = led.groupBy("fail_bits").agg(F.count(F.lit(1)).alias("c"))
    bits, aggs = F.col("fail_bits"), []
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("c"))), F.lit(0))
    for i, name in enumerate(RULES):
        less = Policy(policy.version, policy.hard & ~(1 << i), policy.soft & ~(1 << i), policy.soft_limit)
        aggs.append(F.struct(
            F.lit(name).alias("rule"), total(F.getbit(bits, F.lit(i)) == 1).alias("failed"), total(less.rejects(bits)).alias("rejected_without"),
            total(policy.rejects(bits) & ~less.rejects(bits)).alias("only_by_rule"),
        ).alias(name))
    return masks.agg(total(F.lit(True)).alias("n"), total(policy.rejects(bits)).alias("rejected"), *aggs).select("n", "rejected", F.inline(F.array(*RULES)))
