"""From queries to algebra: match, then where, then return."""

from __future__ import annotations

from rpqframe.functions.conditions import Cmp, Is, Not, label
from rpqframe.functions.restrictors import STRENGTH
from rpqframe.operators.algebra import Expr, Join, Paths0, Paths1, Project, Recur, Select, Union, satisfied
from rpqframe.plans.lang import Query
from rpqframe.plans.regex import Alt, Cat, Lab, Neg, Opt, Plus, Regex


def match_expr(r: Regex, tau: str) -> Expr:
    out = _match(r, tau)
    # joins test what they make and what they are given; what no join makes (an edge alone) is tested here
    return out if STRENGTH[satisfied(out)] >= STRENGTH[tau] else Select(out, Is(tau))


def _match(r: Regex, tau: str) -> Expr:
    if isinstance(r, Lab):
        return Select(Paths1(), Cmp(label("edge", 1), "=", r.name))
    if isinstance(r, Neg):
        return Select(Paths1(), Not(Cmp(label("edge", 1), "=", r.name)))
    if isinstance(r, Cat):
        return Join(_match(r.left, tau), _match(r.right, tau), tau)
    if isinstance(r, Alt):
        return Union(_match(r.left, tau), _match(r.right, tau))
    inner = _match(r.inner, tau)
    if isinstance(r, Plus):
        return Recur(inner, tau)
    return Union(inner if isinstance(r, Opt) else Recur(inner, tau), Paths0())


def where_expr(cond, e: Expr) -> Expr:
    return e if cond is None else Select(e, cond)


def return_expr(terms: tuple, limit: int, e: Expr) -> Project:
    return Project(e, terms, limit)


def translate(q: Query) -> Project:
    return return_expr(q.returns, q.limit, where_expr(q.where, match_expr(q.regex, q.tau)))
