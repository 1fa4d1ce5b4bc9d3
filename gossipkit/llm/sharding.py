"""Permutation-filled lookup table for shards (DataFrame functions only on the data's path).

Every shard has a preference order over the slots of a prime-sized table, given by an offset and a step.
Shards take turns: each claims the first slot of its order that is still free. A key's slot is its hash
modulo the table size, so placing a document is one broadcast lookup. The table's size depends on the
number of shards alone; it is filled on the driver and checked against MAX_SLOTS.

Defined cases: a null key is placed as the text 'null'; equal keys get equal shards; an input column
named slot or shard is replaced; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MAX_SLOTS = 1 << 22
SLOTS_PER_SHARD = 100


def prime_from(n: int) -> int:
    """The least prime of n or more."""
    n = max(n, 2)
    while any(n % k == 0 for k in range(2, int(n**0.5) + 1)):
        n += 1
    return n


def _number(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def fill(shards: list[str], weights: dict[str, int] | None = None, slots: int | None = None) -> list[int]:
    """The table: the index of the shard that holds each slot. A shard of weight w takes w turns a round."""
    size = prime_from(slots or SLOTS_PER_SHARD * len(shards))
    if not shards or size > MAX_SLOTS:
        raise ValueError(f"{len(shards)} shards, {size} slots: 1 shard at least, {MAX_SLOTS} slots at most")
    table, free = [-1] * size, size
    place = [_number(f"{s}/offset") % size for s in shards]
    step = [_number(f"{s}/step") % (size - 1) + 1 for s in shards]
    turns = [i for i, s in enumerate(shards) for _ in range((weights or {}).get(s, 1))]
    while free:
        for i in turns:
            while table[place[i]] >= 0:
                place[i] = (place[i] + step[i]) % size
            table[place[i]] = i
            free -= 1
            if not free:
                break
    return table


def slot_of(key: Column, size: int) -> Column:
    text = F.coalesce(key.cast("string"), F.lit("null"))
    return F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(size)).cast("int")


def lookup(spark: SparkSession, table: list[int]) -> DataFrame:
    """The table as rows (slot, shard); its size is bounded by MAX_SLOTS."""
    packed = F.split(F.lit(",".join(map(str, table))), ",")
    return spark.range(1).select(F.posexplode(packed).alias("slot", "shard")).select("slot", F.col("shard").cast("int"))


def assign(docs: DataFrame, key: str, shards: list[str], weights: dict[str, int] | None = None) -> DataFrame:
    """Adds slot and shard (an index into shards) to every row; no shuffle."""
    table = fill(shards, weights)
    keyed = docs.drop("slot", "shard").withColumn("slot", slot_of(F.col(key), len(table)))
    return keyed.join(F.broadcast(lookup(docs.sparkSession, table)), "slot", "left")


def moved(before: list[int], after: list[int], old: list[str], new: list[str]) -> float:
    """Share of slots whose shard changes between two tables of one size."""
    return sum(old[a] != new[b] for a, b in zip(before, after, strict=True)) / len(before)
