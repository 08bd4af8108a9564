"""Path algebra expressions: leaves, selection, join, union, recursive join, projection.

Expressions are values; ``rpqframe.plans.lower`` turns them into DataFrames.
"""

from __future__ import annotations

from dataclasses import dataclass

from rpqframe.functions.conditions import Is
from rpqframe.functions.restrictors import ACYCLIC, SIMPLE, STRENGTH, WALK, stronger


class Expr:
    """A path algebra expression."""

    def children(self) -> list[Expr]:
        return [x for x in vars(self).values() if isinstance(x, Expr)]

    def tree(self, depth: int = 0) -> str:
        return "\n".join(["  " * depth + self.title(), *[c.tree(depth + 1) for c in self.children()]])

    def title(self) -> str:
        return type(self).__name__.lower()


@dataclass(frozen=True)
class Paths0(Expr):
    def title(self):
        return "paths0"


@dataclass(frozen=True)
class Paths1(Expr):
    """Paths of length 1; ``labels`` (None: all) is set by the optimizer."""

    labels: tuple[str, ...] | None = None

    def title(self):
        return "paths1" + (f"[{'|'.join(self.labels)}]" if self.labels is not None else "")


@dataclass(frozen=True)
class Select(Expr):
    inner: Expr
    cond: object

    def title(self):
        return f"select {self.cond}"


@dataclass(frozen=True)
class Join(Expr):
    left: Expr
    right: Expr
    tau: str

    def title(self):
        return f"join {self.tau}"


@dataclass(frozen=True)
class Union(Expr):
    left: Expr
    right: Expr

    def title(self):
        return "union"


@dataclass(frozen=True)
class Recur(Expr):
    """The recursive join of ``inner``; ``max_len`` bounds its own paths.

    Set by the optimizer: ``start`` replaces the first level, ``seed`` conditions filter it, ``target``
    conditions on the last node turn the recursion around, ``whole_len`` bounds the whole path that it is the last part of.
    """

    inner: Expr
    tau: str
    start: Expr | None = None
    max_len: int | None = None
    dedupe: bool = True
    seed: tuple = ()
    target: tuple = ()
    whole_len: int | None = None

    def title(self):
        bounds = [x for x in (self.max_len, self.whole_len) if x is not None]
        return (
            f"recursive join {self.tau}" + (f", at most {min(bounds)}" if bounds else "") + (", from its second branch" if self.start else "")
            + "".join(f", from {c}" for c in self.seed) + "".join(f", to the left from {c}" for c in self.target)
        )


@dataclass(frozen=True)
class Project(Expr):
    inner: Expr
    terms: tuple
    limit: int = 0

    def title(self):
        return f"project {', '.join(a for a, _ in self.terms)}" + (f" first {self.limit}" if self.limit else "")


def min_len(e: Expr) -> int:
    """A lower bound of the path lengths."""
    if isinstance(e, Paths0):
        return 0
    if isinstance(e, Paths1):
        return 1
    if isinstance(e, Join):
        return min_len(e.left) + min_len(e.right)
    if isinstance(e, Union):
        return min(min_len(e.left), min_len(e.right))
    if isinstance(e, Recur):
        return min_len(e.start) if e.start is not None else min_len(e.inner)
    return min_len(e.inner)


def lengths(e: Expr) -> tuple[int, int] | None:
    """The least and the greatest length of the paths, where no recursion leaves it open."""
    if isinstance(e, (Paths0, Paths1)):
        return (int(isinstance(e, Paths1)),) * 2
    if isinstance(e, Recur):
        return None
    parts = [lengths(c) for c in e.children()]
    if None in parts:
        return None
    if isinstance(e, Join):
        return parts[0][0] + parts[1][0], parts[0][1] + parts[1][1]
    return min(p[0] for p in parts), max(p[1] for p in parts)


def satisfied(e: Expr) -> str:
    """The strongest restrictor that all paths of an expression are known to satisfy."""
    if isinstance(e, Paths0):
        return ACYCLIC
    if isinstance(e, Paths1):
        return SIMPLE  # an edge may be a self-loop
    if isinstance(e, (Join, Recur)):
        return e.tau
    if isinstance(e, Union):
        return min(satisfied(e.left), satisfied(e.right), key=STRENGTH.get)
    own = e.cond.tau if isinstance(e, Select) and isinstance(e.cond, Is) else WALK
    return stronger(satisfied(e.inner), own)


def has_recursion(e: Expr) -> bool:
    return isinstance(e, Recur) or any(has_recursion(c) for c in e.children())
