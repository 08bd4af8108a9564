"""Column expressions for places of regex matches; DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def lower_ascii(text: Column) -> Column:
    """Lower-cases A-Z only; null becomes empty."""
    out = F.coalesce(text.cast("string"), F.lit(""))
    return F.when(out.rlike("[A-Z]"), _swap(out)).otherwise(out)


def _swap(text: Column) -> Column:
    # lower() also maps other letters; translate() maps just these
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


#: Matches that one pass of the running sum copies; passes over the sums of blocks follow.
BLOCK = 128
_PLACES = "array<struct<s:int,e:int,m:string>>"


def matches(text: Column, regex: Column) -> Column:
    """array<struct<s,e,m>>: 0-based start and end of each match of a pattern that never matches empty.

    Places are running sums of the lengths of gaps and matches, taken block by block: a sum over
    one array would copy what it has made at every match.
    """
    found = F.regexp_extract_all(text, regex, F.lit(0))
    gaps = F.split(text, regex, -1)
    zipped = F.arrays_zip(found.alias("m"), F.slice(gaps, 1, F.size(found)).alias("g"))
    blocks = F.transform(F.sequence(F.lit(0), F.size(found) - 1, F.lit(BLOCK)), lambda k: F.slice(zipped, k + 1, F.lit(BLOCK)))
    zero = F.struct(F.lit(0).cast("int").alias("at"), F.array().cast(_PLACES).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["g"])
        end = start + F.length(x["m"])
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(F.struct(start.alias("s"), end.alias("e"), x["m"].alias("m")))).alias("out"))

    walked = F.transform(blocks, lambda b: F.aggregate(b, zero, step))
    first = F.array(F.lit(0).cast("int"))
    ends = lambda w: F.aggregate(w, first, lambda acc, x: F.concat(acc, F.array(F.element_at(acc, -1) + x["at"])))
    shifted = lambda w: F.flatten(F.zip_with(w, F.slice(ends(w), F.lit(1), F.size(w)), lambda x, at: F.transform(x["out"], lambda p: F.struct((p["s"] + at).alias("s"), (p["e"] + at).alias("e"), p["m"].alias("m")))))
    # one element, so that the walk is made once
    return F.when(F.size(found) > 0, F.flatten(F.transform(F.array(walked), shifted))).otherwise(F.array().cast(_PLACES))
