"""Pattern matches with code-point offsets, from DataFrame functions alone.

``split`` gives what lies between the matches and ``regexp_extract_all`` the matches; their lengths add up
to offsets. Loops in the patterns are possessive where that changes nothing, so that the matcher neither
backtracks over long runs nor recurses.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

AROUND = 24
SPAN = "array<struct<start:int,end:int,value:string,before:string,after:string>>"


def find(text: Column, pattern: str, valid: Callable[[Column], Column] = lambda v: F.lit(True)) -> Column:
    """Leftmost non-overlapping matches that are valid, with AROUND characters of each side up to the next match."""
    pieces = F.split(text, pattern, -1)

    def gather(parts: Column) -> Column:
        found = F.when(F.size(parts) > 1, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(F.array().cast("array<string>"))
        zipped = F.transform(found, lambda v, i: F.struct(v.alias("v"), F.get(parts, i).alias("b"), F.get(parts, i + 1).alias("a")))

        def step(acc: Column, m: Column) -> Column:
            start = acc["at"] + F.char_length(m["b"])
            end = start + F.char_length(m["v"])
            span = F.struct(start.alias("start"), end.alias("end"), m["v"].alias("value"), F.right(m["b"], F.lit(AROUND)).alias("before"), F.left(m["a"], F.lit(AROUND)).alias("after"))
            return F.struct(end.alias("at"), F.when(valid(m["v"]), F.concat(acc["s"], F.array(span))).otherwise(acc["s"]).alias("s"))

        return F.aggregate(zipped, F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("s")), step, lambda a: a["s"])

    # a lambda variable holds the pieces, so that the text is split once
    return F.get(F.transform(F.array(pieces), gather), F.lit(0))


def digits(v: Column) -> Column:
    return F.regexp_replace(v, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """Whether a string of digits passes the mod-10 checksum."""
    def add(acc: Column, i: Column) -> Column:
        d = F.substr(number, -i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return acc + F.when(d > 9, d - 9).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.char_length(number)), F.lit(0), add) % 10 == 0


def rendered(spans: Column) -> Column:
    """kind:start:end of structs (start, rank, end, kind), by start, then rank."""
    return F.array_join(F.transform(F.sort_array(spans), lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def tagged(spans: Column, kind: str, rank: int) -> Column:
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("rank"), s["end"].alias("end"), F.lit(kind).alias("kind")))
