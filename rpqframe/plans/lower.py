"""From algebra trees to DataFrames, and the front door ``rpq``.

Everything but recursion stays one lazy plan. Under a limit, operators above a recursion are
applied level by level, so the recursion stops as soon as enough answers are certain.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame

from rpqframe.functions import conditions as C
from rpqframe.functions.paths import distinct_paths, path_order, paths0, paths1, reversed_paths
from rpqframe.functions.restrictors import STRENGTH, restrict
from rpqframe.operators.algebra import Expr, Join, Paths0, Paths1, Project, Recur, Select, Union, has_recursion, lengths, min_len, satisfied
from rpqframe.operators.automata import is_unambiguous
from rpqframe.operators.fixpoint import BROADCAST_ROWS, Trace, join_paths, recursive_join, reliable
from rpqframe.plans.lang import Query, parse
from rpqframe.plans.optimize import label_leaves, rewrite
from rpqframe.plans.regex import normalize
from rpqframe.plans.translate import translate
from rpqframe.sources.graph import PropertyGraph


@dataclass
class Config:
    """mode: paper (recursion gives sets, the rest bags), set (distinct paths), derivation (a row per derivation).

    strategy: linear, doubling (rounds, where nothing seeds or stops it), left (towards the first node), sql (one recursive query).
    """

    mode: str = "paper"
    order: str = "total"
    strategy: str = "linear"
    max_len: int | None = None
    skip: tuple[str, ...] = ()
    trace: Trace = field(default_factory=Trace)


def evaluate(e: Expr, g: PropertyGraph, cfg: Config | None = None) -> DataFrame:
    cfg = cfg or Config()
    e = label_leaves(e, g.edge_labels)
    if isinstance(e, Project):
        return _project(e, g, cfg)
    return _paths(e, g, cfg, None)


def _leaf(e: Paths1, g: PropertyGraph) -> DataFrame:
    return paths1(g.edges_of(e.labels))


def _select(df: DataFrame, c, g: PropertyGraph) -> DataFrame:
    return C.select(df, c, g.nodes_of, g.edges_of)


def _paths(e: Expr, g: PropertyGraph, cfg: Config, limit: int | None) -> DataFrame:
    """Path rows. With a limit, at least the first rows by (len, nodes, edges) of that number are among them."""
    if isinstance(e, Paths0):
        return paths0(g.nodes)
    if isinstance(e, Paths1):
        return _leaf(e, g)
    if isinstance(e, Union):
        return _paths(e.left, g, cfg, limit).unionByName(_paths(e.right, g, cfg, limit))
    if isinstance(e, Select) and not has_recursion(e):
        return _select(_paths(e.inner, g, cfg, None), e.cond, g)
    if isinstance(e, Join) and not has_recursion(e):
        return _join(e, g, cfg)
    post, core, extra = _above_recursion(e, g, cfg)
    if core is None:  # recursion on the right of a join that could not be fused
        if isinstance(e, Select):
            return _select(_paths(e.inner, g, cfg, None), e.cond, g)
        return _join(e, g, cfg)
    if isinstance(core, Union):
        if limit is not None and e is not core:
            return _limited_union(e, core, g, cfg, limit)
        both = _paths(core, g, cfg, limit)
        return both if post is None else post(both)
    start = None if core.start is None else _paths(core.start, g, cfg, None)
    base = _paths(core.inner, g, cfg, None)
    bounds = [x for x in (core.max_len, core.whole_len, cfg.max_len) if x is not None]
    strategy = cfg.strategy if start is None and limit is None and not core.seed and not core.target else "linear"
    conds, seed, turn = core.seed, None, cfg.strategy == "left" and start is None and not core.seed
    if core.target or turn:  # to the left: the recursion over reversed paths, turned around again
        conds, base = tuple(C.at_first(c) for c in core.target), reversed_paths(base)
        above = post
        post = reversed_paths if above is None else lambda d: above(reversed_paths(d))
    if conds:
        seed = lambda d: reduce(lambda x, c: _select(x, c, g), conds, d)
    return recursive_join(
        base, core.tau, start=start, seed=seed, dedupe=core.dedupe and cfg.mode != "derivation", strategy=strategy, max_len=min(bounds) if bounds else None, limit=limit, post=post, post_min_len=extra, trace=cfg.trace,
        base_lengths=lengths(core.inner),
    )


def _valid(df: DataFrame, e: Expr, tau: str) -> DataFrame:
    """The paths of an expression that a join under a restrictor may use: its test assumes valid parts."""
    return df if STRENGTH[satisfied(e)] >= STRENGTH[tau] else df.where(restrict(tau))


def _join(e: Join, g: PropertyGraph, cfg: Config) -> DataFrame:
    right = e.right
    small = isinstance(right, Paths1) and right.labels is not None and sum(g.counts.get(x, BROADCAST_ROWS + 1) for x in right.labels) <= BROADCAST_ROWS
    return join_paths(_valid(_paths(e.left, g, cfg, None), e.left, e.tau), _valid(_paths(right, g, cfg, None), right, e.tau), e.tau, small)


def _above_recursion(e: Expr, g: PropertyGraph, cfg: Config):
    """What stands above the one recursion of a subtree, as a function of its paths; that recursion (or a union with one); length added."""
    if isinstance(e, (Recur, Union)):
        return None, e, 0
    if isinstance(e, Select):
        post, core, extra = _above_recursion(e.inner, g, cfg)
        keep = (lambda d: _select(d, e.cond, g))
        if core is not None and C.pins(e.cond) and e.cond.term.kind != "id":
            ids = reliable(C.pinned_ids(e.cond, g.nodes_of, g.edges_of))  # once, not at every level
            keep = (lambda d: C.keep_pinned(d, e.cond, ids))
        return (keep if post is None else lambda d: keep(post(d))), core, extra
    if isinstance(e, Join) and has_recursion(e.left) and not has_recursion(e.right):
        post, core, extra = _above_recursion(e.left, g, cfg)
        right = _valid(_paths(e.right, g, cfg, None), e.right, e.tau)
        return (lambda d: join_paths(_valid(d if post is None else post(d), e.left, e.tau), right, e.tau)), core, extra + min_len(e.right)
    return None, None, 0


def _limited_union(e: Expr, core: Union, g: PropertyGraph, cfg: Config, limit: int) -> DataFrame:
    """Operators above a union apply to each branch, each with its own stop."""

    def swap(x: Expr, branch: Expr) -> Expr:
        if x is core:
            return branch
        return Select(swap(x.inner, branch), x.cond) if isinstance(x, Select) else Join(swap(x.left, branch), x.right, x.tau)

    return _paths(swap(e, core.left), g, cfg, limit).unionByName(_paths(swap(e, core.right), g, cfg, limit))


def _project(e: Project, g: PropertyGraph, cfg: Config) -> DataFrame:
    limit = e.limit or None
    df = _paths(e.inner, g, cfg, limit)
    if cfg.mode == "set":
        df = distinct_paths(df)
    if limit is not None:
        df = df.orderBy(*path_order()).limit(limit) if cfg.order == "total" else df.limit(limit)
    return C.project(df, list(e.terms), g.nodes_of, g.edges_of, ordered=limit is not None and cfg.order == "total")


def plan(g: PropertyGraph, q: Query, cfg: Config) -> Project:
    regex = normalize(q.regex) if cfg.mode == "set" else q.regex
    e = translate(Query(q.tau, regex, q.where, q.returns, q.limit))
    if cfg.max_len is not None:  # of the whole path; the optimizer bounds the recursions by it
        e = replace(e, inner=Select(e.inner, C.Cmp(C.LENGTH, "<=", cfg.max_len)))
    if "all" in cfg.skip:
        return e
    unique = "drop_dedupe" not in cfg.skip and is_unambiguous(regex, g.edge_labels)
    return rewrite(e, g.edge_labels, cfg.skip, unique)


def rpq(g: PropertyGraph, text: str, *, mode: str = "paper", order: str = "total", strategy: str = "linear", max_len: int | None = None, skip: tuple[str, ...] = (), timeout_s: float | None = None, trace: Trace | None = None) -> DataFrame:
    """Answer a query; rows are lazy except for the levels of a recursion."""
    cfg = Config(mode, order, strategy, max_len, skip, trace or Trace())
    if timeout_s is not None:
        cfg.trace.deadline = time.monotonic() + timeout_s
    return evaluate(plan(g, parse(text), cfg), g, cfg)


def rpq_paths(g: PropertyGraph, text: str, **options) -> DataFrame:
    """The path rows of a query instead of its projection, under its limit."""
    trace = options.pop("trace", None)
    cfg = Config(**options, trace=trace or Trace())
    e = plan(g, parse(text), cfg)
    df = _paths(e.inner, g, cfg, e.limit or None)
    df = distinct_paths(df) if cfg.mode == "set" else df
    return df.orderBy(*path_order()).limit(e.limit) if e.limit else df


def explain_rpq(g: PropertyGraph, text: str, spark_plan: bool = False) -> str:
    """The query, its algebra tree and the rewritten tree; with ``spark_plan`` it is run as far as its recursions go and Spark's plan of the rest follows."""
    q = parse(text)
    cfg = Config()
    made = plan(g, q, cfg)
    parts = [f"query: {q.tau} {q.regex}", "algebra:", translate(q).tree(1), "rewritten:", made.tree(1)]
    if spark_plan:
        df = evaluate(made, g, cfg)
        parts += ["levels:", *[f"  {x['op']} {x['level']}: {x['rows']} rows, {x['bytes']} bytes" for x in cfg.trace.levels], "spark:", df._jdf.queryExecution().toString()]
    return "\n".join(parts)
