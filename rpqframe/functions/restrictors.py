"""Path restrictors: walk, trail, acyclic, simple.

Every contiguous part of a trail, acyclic or simple path satisfies the same restrictor, so a join
may test each concatenation and lose nothing. ``extends`` assumes both parts are valid.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WALK, TRAIL, ACYCLIC, SIMPLE = RESTRICTORS = ("walk", "trail", "acyclic", "simple")
#: Stronger restrictors imply weaker ones; acyclic paths are simple, simple ones are trails.
STRENGTH = {WALK: 0, TRAIL: 1, SIMPLE: 2, ACYCLIC: 3}


def stronger(a: str, b: str) -> str:
    return max(a, b, key=STRENGTH.get)


def _distinct(col: Column) -> Column:
    return F.size(F.array_distinct(col)) == F.size(col)


def restrict(tau: str) -> Column:
    """The test of a whole path row."""
    if tau == WALK:
        return F.lit(True)
    if tau == TRAIL:
        return _distinct(F.col("edges"))
    if tau == ACYCLIC:
        return _distinct(F.col("nodes"))
    if tau == SIMPLE:  # only the first and the last node may coincide
        return (F.col("len") == 0) | (_distinct(F.slice("nodes", F.lit(1), F.col("len"))) & _distinct(F.slice("nodes", F.lit(2), F.col("len"))))
    raise ValueError(f"no such restrictor: {tau}")


def extends(tau: str, a: str = "a", b: str = "b") -> Column:
    """The test that the concatenation of two valid linkable paths is valid."""
    tail = F.slice(F.col(f"{b}.nodes"), F.lit(2), F.col(f"{b}.len"))
    if tau == WALK:
        return F.lit(True)
    if tau == TRAIL:
        return ~F.arrays_overlap(F.col(f"{a}.edges"), F.col(f"{b}.edges"))
    if tau == ACYCLIC:
        return ~F.arrays_overlap(F.col(f"{a}.nodes"), tail)
    if tau == SIMPLE:
        inner_a = F.slice(F.col(f"{a}.nodes"), F.lit(2), F.col(f"{a}.len"))
        new = F.slice(F.col(f"{b}.nodes"), F.lit(2), F.greatest(F.col(f"{b}.len") - 1, F.lit(0)))
        closed = (F.col(f"{a}.src") == F.col(f"{a}.dst")) & (F.col(f"{a}.len") > 0) | (F.col(f"{b}.src") == F.col(f"{b}.dst")) & (F.col(f"{b}.len") > 0)
        proper = ~F.arrays_overlap(F.col(f"{a}.nodes"), new) & ~F.arrays_overlap(inner_a, tail) & ~closed
        return (F.col(f"{a}.len") == 0) | (F.col(f"{b}.len") == 0) | proper
    raise ValueError(f"no such restrictor: {tau}")
