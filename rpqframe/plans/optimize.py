"""Rewrites of algebra trees that Catalyst cannot make, as it sees one level of a recursion at a time.

Every rewrite keeps the bag of paths; each can be left out by name.
"""

from __future__ import annotations

from dataclasses import replace

from rpqframe.functions.conditions import LENGTH, Cmp, Is, Not, conjuncts, pins, positions, terms_of
from rpqframe.functions.restrictors import STRENGTH, WALK, stronger
from rpqframe.operators.algebra import Expr, Join, Paths0, Paths1, Recur, Select, Union, satisfied

#: In order of application.
REWRITES = ("split_conditions", "tighten_restrictor", "push_length", "label_leaves", "push_source", "push_target", "fuse_left_into_recursion", "merge_label_alternatives")


def rewrite(e: Expr, alphabet: list[str], skip: tuple[str, ...] = (), drop_dedupe: bool = False) -> Expr:
    for name in REWRITES:
        if name not in skip:
            e = globals()[name](e, alphabet)
    return _no_dedupe(e) if drop_dedupe else e


def _map(e: Expr, f) -> Expr:
    """Rebuild bottom-up."""
    changed = {k: _map(v, f) for k, v in vars(e).items() if isinstance(v, Expr)}
    return f(replace(e, **changed) if changed else e)


def _no_dedupe(e: Expr) -> Expr:
    """Where every path has one derivation, recursion needs no duplicate removal."""
    return _map(e, lambda x: replace(x, dedupe=False) if isinstance(x, Recur) else x)


def split_conditions(e: Expr, alphabet: list[str]) -> Expr:
    """A conjunction becomes a chain of selections; a double negation goes."""

    def step(x: Expr) -> Expr:
        if not isinstance(x, Select):
            return x
        out = x.inner
        for c in reversed(conjuncts(x.cond)):
            while isinstance(c, Not) and isinstance(c.inner, Not):
                c = c.inner.inner
            out = Select(out, c)
        return out

    return _map(e, step)


def tighten_restrictor(e: Expr, alphabet: list[str]) -> Expr:
    """A selection of trails (simple, acyclic paths) above joins lets the joins themselves test it.

    Exact for stronger restrictors, as all parts of a valid path are valid.
    """

    def push(x: Expr, tau: str) -> Expr:
        if isinstance(x, (Join, Recur)):
            x = replace(x, tau=stronger(x.tau, tau))
        return replace(x, **{k: push(v, tau) for k, v in vars(x).items() if isinstance(v, Expr)}) if x.children() else x

    return _map(e, lambda x: replace(x, inner=push(x.inner, x.cond.tau)) if isinstance(x, Select) and isinstance(x.cond, Is) and x.cond.tau != WALK else x)


def push_length(e: Expr, alphabet: list[str]) -> Expr:
    """An upper bound of the length bounds every recursion below."""

    def bound(x: Expr, n: int) -> Expr:
        if isinstance(x, Recur):
            x = replace(x, whole_len=n if x.whole_len is None else min(n, x.whole_len))
        return replace(x, **{k: bound(v, n) for k, v in vars(x).items() if isinstance(v, Expr)}) if x.children() else x

    def step(x: Expr) -> Expr:
        if isinstance(x, Select) and isinstance(x.cond, Cmp) and x.cond.term == LENGTH and x.cond.op in ("=", "<", "<=") and isinstance(x.cond.value, int):
            return replace(x, inner=bound(x.inner, x.cond.value - (x.cond.op == "<")))
        return x

    return _map(e, step)


def label_leaves(e: Expr, alphabet: list[str]) -> Expr:
    """A label test on an edge leaf becomes the leaf's labels, so a scan reads these only."""

    def step(x: Expr) -> Expr:
        if not (isinstance(x, Select) and isinstance(x.inner, Paths1)):
            return x
        own = alphabet if x.inner.labels is None else list(x.inner.labels)
        c, neg = (x.cond.inner, True) if isinstance(x.cond, Not) else (x.cond, False)
        if isinstance(c, Cmp) and c.op == "=" and c.term.kind == "label" and c.term.what == "edge" and c.term.i == 1:
            return Paths1(tuple(a for a in own if (a == c.value) != neg))
        return x

    return _map(e, step)


def _about(c, i) -> bool:
    return bool(terms_of(c)) and positions(c) == {("node", i)}


def push_source(e: Expr, alphabet: list[str]) -> Expr:
    """Conditions on the first node seed the first level of a recursion; its base stays whole."""

    def push(x: Expr, c) -> Expr:
        if isinstance(x, Select):
            return replace(x, inner=push(x.inner, c))
        if isinstance(x, Join):
            return replace(x, left=push(x.left, c))
        if isinstance(x, Union):
            return Union(push(x.left, c), push(x.right, c))
        if isinstance(x, Recur):
            return replace(x, seed=(*x.seed, c)) if x.start is None else replace(x, start=push(x.start, c))
        return Select(x, c)

    return _map(e, lambda x: push(x.inner, x.cond) if isinstance(x, Select) and _about(x.cond, 1) else x)


def push_target(e: Expr, alphabet: list[str]) -> Expr:
    """Conditions on the last node move below joins and unions, down to recursions.

    A condition that pins few nodes seeds a recursion that has no other seed, which then runs to the left; others filter its levels.
    """

    def push(x: Expr, c) -> Expr:
        if isinstance(x, Select):
            return replace(x, inner=push(x.inner, c))
        if isinstance(x, Join):
            return replace(x, right=push(x.right, c))
        if isinstance(x, Union):
            return Union(push(x.left, c), push(x.right, c))
        if isinstance(x, Recur) and x.start is None and not x.seed and pins(c):
            return replace(x, target=(*x.target, c))
        return Select(x, c)

    return _map(e, lambda x: push(x.inner, x.cond) if isinstance(x, Select) and _about(x.cond, "last") else x)


def fuse_left_into_recursion(e: Expr, alphabet: list[str]) -> Expr:
    """A join with a recursion on its right runs as a loop from the left side.

    The recursion over the whole graph is never made. A star on the right keeps the left side itself too.
    """

    def step(x: Expr) -> Expr:
        if not isinstance(x, Join):
            return x
        r, conds = x.right, []
        while isinstance(r, Select):
            conds.append(r.cond)
            r = r.inner
        if isinstance(r, Recur) and r.target:  # the left side is the better start
            conds += reversed(r.target)
            r = replace(r, target=())
        wrap = lambda y: y if not conds else wrap_all(y)

        def wrap_all(y: Expr) -> Expr:
            for c in reversed(conds):
                y = Select(y, c)
            return y

        if any(not _about(c, "last") for c in conds):
            return x
        if isinstance(r, Recur) and r.start is None and not r.seed and r.max_len is None and r.tau == x.tau:
            return wrap(replace(r, start=Join(x.left, r.inner, x.tau)))
        if isinstance(r, Union):
            return wrap(Union(_map(Join(x.left, r.left, x.tau), step), _map(Join(x.left, r.right, x.tau), step)))
        if isinstance(r, Paths0):
            return wrap(x.left if STRENGTH[satisfied(x.left)] >= STRENGTH[x.tau] else Select(x.left, Is(x.tau)))
        return x

    return _map(e, step)


def merge_label_alternatives(e: Expr, alphabet: list[str]) -> Expr:
    """A union of leaves with different labels is one scan."""

    def step(x: Expr) -> Expr:
        if isinstance(x, Union) and isinstance(x.left, Paths1) and isinstance(x.right, Paths1) and x.left.labels is not None and x.right.labels is not None and not set(x.left.labels) & set(x.right.labels):
            return Paths1(x.left.labels + x.right.labels)
        if isinstance(x, Union) and isinstance(x.left, Select) and isinstance(x.right, Select) and x.left.cond == x.right.cond:
            both = step(Union(x.left.inner, x.right.inner))
            return Select(both, x.left.cond) if not isinstance(both, Union) else x
        return x

    return _map(e, step)
