"""Selection conditions and projection terms over path rows.

Conditions are two-valued: a simple condition over something undefined is false, so its negation is
true. Labels and properties are looked up late, by joins on ids; path rows never carry them.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rpqframe.functions.paths import LAST, edge_at, node_at, path_order, seq_text
from rpqframe.functions.restrictors import restrict


@dataclass(frozen=True)
class Term:
    """kind: id, label, prop, length, seq; what: node or edge; i: position from 1 or LAST."""

    kind: str
    what: str = ""
    i: int | str = 0
    key: str = ""

    def __str__(self) -> str:
        at = "len()+1" if self.i == LAST and self.what == "node" else "len()" if self.i == LAST else self.i
        return {"id": f"{self.what}({at})", "label": f"label({self.what}({at}))", "prop": f"prop({self.what}({at}),{self.key})"}.get(self.kind, f"{self.kind}()")


def node(i):
    return Term("id", "node", i)


def edge(i):
    return Term("id", "edge", i)


def label(what: str, i) -> Term:
    return Term("label", what, i)


def prop(what: str, i, key: str) -> Term:
    return Term("prop", what, i, key)


LENGTH, SEQ = Term("length"), Term("seq")


@dataclass(frozen=True)
class Cmp:
    term: Term
    op: str
    value: object

    def __str__(self) -> str:
        return f"{self.term} {self.op} {self.value!r}"


@dataclass(frozen=True)
class Is:
    tau: str

    def __str__(self) -> str:
        return f"is{self.tau.capitalize()}()"


@dataclass(frozen=True)
class And:
    left: object
    right: object

    def __str__(self) -> str:
        return f"({self.left} AND {self.right})"


@dataclass(frozen=True)
class Or:
    left: object
    right: object

    def __str__(self) -> str:
        return f"({self.left} OR {self.right})"


@dataclass(frozen=True)
class Not:
    inner: object

    def __str__(self) -> str:
        return f"(NOT {self.inner})"


def conjuncts(c) -> list:
    return conjuncts(c.left) + conjuncts(c.right) if isinstance(c, And) else [c]


def conjunction(cs: list):
    return reduce(And, cs)


def terms_of(c) -> set[Term]:
    if isinstance(c, (And, Or)):
        return terms_of(c.left) | terms_of(c.right)
    if isinstance(c, Not):
        return terms_of(c.inner)
    return {c.term} if isinstance(c, Cmp) else set()


def positions(c) -> set:
    return {(t.what, t.i) for t in terms_of(c)} | ({("path", 0)} if _whole(c) else set())


def _whole(c) -> bool:
    if isinstance(c, (And, Or)):
        return _whole(c.left) or _whole(c.right)
    return _whole(c.inner) if isinstance(c, Not) else isinstance(c, Is) or c.term.kind in ("length", "seq")


def _slot(t: Term) -> str:
    return f"__{t.what}_{t.i}"


def lookup(df: DataFrame, terms: set[Term], nodes: Callable[[], DataFrame], edges: Callable[[], DataFrame]) -> DataFrame:
    """Adds a struct column (label, props) for each node or edge position that the terms need."""
    for what, i in sorted({(t.what, t.i) for t in terms if t.kind in ("label", "prop")}, key=str):
        table, key = (nodes, "id") if what == "node" else (edges, "eid")
        need = {t.kind for t in terms if (t.what, t.i) == (what, i)}
        fields = [c for c, k in (("label", "label"), ("props", "prop")) if k in need]
        slot = f"__{what}_{i}"
        side = table().select(F.col(key).alias(f"{slot}_key"), F.struct(*fields).alias(slot))
        at = node_at(i) if what == "node" else edge_at(i)
        df = df.withColumn(f"{slot}_at", at).join(side, F.col(f"{slot}_at") == F.col(f"{slot}_key"), "left").drop(f"{slot}_key", f"{slot}_at")
    return df


def term_column(t: Term) -> Column:
    """The value of a term; null where it is undefined or out of range."""
    if t.kind == "length":
        return F.col("len")
    if t.kind == "seq":
        return seq_text()
    if t.kind == "id":
        return node_at(t.i) if t.what == "node" else edge_at(t.i)
    return F.col(f"{_slot(t)}.label") if t.kind == "label" else F.col(f"{_slot(t)}.props")[t.key]


def _typed(col: Column, value) -> tuple[Column, Column]:
    """Property values are text; numbers compare as numbers, times as times."""
    if isinstance(value, bool):
        return F.expr("true") & col.try_cast("boolean"), F.lit(value)
    if isinstance(value, int):
        return col.try_cast("decimal(38,10)"), F.lit(value).cast("decimal(38,10)")
    if isinstance(value, float):
        return col.try_cast("double"), F.lit(value)
    if not isinstance(value, str):
        return col.try_cast("timestamp"), F.lit(value)
    return col, F.lit(value)


def condition_column(c) -> Column:
    """A condition over rows that ``lookup`` has prepared."""
    if isinstance(c, And):
        return condition_column(c.left) & condition_column(c.right)
    if isinstance(c, Or):
        return condition_column(c.left) | condition_column(c.right)
    if isinstance(c, Not):
        return ~condition_column(c.inner)
    if isinstance(c, Is):
        return restrict(c.tau)
    col = term_column(c.term)
    left, right = (col, F.lit(c.value)) if c.term.kind != "prop" else _typed(col, c.value)
    test = {"=": left == right, "!=": left != right, "<": left < right, "<=": left <= right, ">": left > right, ">=": left >= right}[c.op]
    return F.coalesce(test, F.lit(False))


def at_first(c):
    """A condition on the last node as one on the first, for reversed paths."""
    if isinstance(c, (And, Or)):
        return type(c)(at_first(c.left), at_first(c.right))
    return Not(at_first(c.inner)) if isinstance(c, Not) else replace(c, term=replace(c.term, i=1))


def pins(c) -> bool:
    """Whether the condition pins one node or edge to few: an equality on its id, label or property."""
    return isinstance(c, Cmp) and c.op == "=" and c.term.kind in ("id", "label", "prop")


def pinned_ids(c: Cmp, nodes: Callable[[], DataFrame], edges: Callable[[], DataFrame]) -> DataFrame:
    """The ids of the nodes or edges that have the label or property value of a pinning condition."""
    t = c.term
    table, key = (nodes, "id") if t.what == "node" else (edges, "eid")
    left, right = (F.col("label"), F.lit(c.value)) if t.kind == "label" else _typed(F.col("props")[t.key], c.value)
    return table().where(left == right).select(F.col(key).alias("__pin"))


def keep_pinned(df: DataFrame, c: Cmp, ids: DataFrame) -> DataFrame:
    t = c.term
    at = node_at(t.i) if t.what == "node" else edge_at(t.i)
    return df.join(ids, at == F.col("__pin"), "left_semi")


def select(df: DataFrame, c, nodes: Callable[[], DataFrame], edges: Callable[[], DataFrame]) -> DataFrame:
    """Paths for which the condition holds; equalities become semi-joins on the pinned position."""
    rest = []
    for part in conjuncts(c):
        if not pins(part):
            rest.append(part)
        elif part.term.kind == "id":
            df = df.where(F.coalesce(term_column(part.term) == F.lit(part.value), F.lit(False)))
        else:
            df = keep_pinned(df, part, pinned_ids(part, nodes, edges))
    if rest:
        c = conjunction(rest)
        cols = df.columns
        df = lookup(df, terms_of(c), nodes, edges).where(condition_column(c)).select(*cols)
    return df


def project(df: DataFrame, terms: list, nodes: Callable[[], DataFrame], edges: Callable[[], DataFrame], ordered: bool = False) -> DataFrame:
    """One row per path; a term is (alias, Term or condition). ``ordered``: rows in path order, after all look-ups."""
    need: set[Term] = set()
    for _, t in terms:
        need |= {t} if isinstance(t, Term) else terms_of(t)
    df = lookup(df, need, nodes, edges)
    df = df.orderBy(*path_order()) if ordered else df
    return df.select(*[(term_column(t) if isinstance(t, Term) else condition_column(t)).alias(a) for a, t in terms])
