"""Baselines: graph and automaton traversed together, breadth first or depth first.

A frontier row is a path with its automaton state. One step joins it with the transitions (a table of
a few rows) and with the edges, under the same restrictor tests as the algebra. Beyond that, edges
that no run can take are left out where there are many, and a small frontier over few edges goes many
steps ahead in one task, in the same order, unless lengths or answers are bounded.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from rpqframe.functions.paths import PATH_COLUMNS, PATH_SCHEMA, paths0
from rpqframe.functions.restrictors import ACYCLIC, SIMPLE, TRAIL, WALK
from rpqframe.operators import local
from rpqframe.operators.automata import Dfa, compile_dfa
from rpqframe.operators.fixpoint import BROADCAST_ROWS, LOCAL_FRONTIER, LOCAL_ROWS, MAX_LEVEL_ROWS, RecursionExplosion, Trace, counted, new_folder, reliable
from rpqframe.plans.regex import Regex
from rpqframe.sources.graph import PropertyGraph



def _may_add(tau: str):
    """Whether one more edge (eid, to) keeps a valid path valid."""
    if tau == WALK:
        return F.lit(True)
    if tau == TRAIL:
        return ~F.array_contains("edges", F.col("eid"))
    if tau == ACYCLIC:
        return ~F.array_contains("nodes", F.col("to"))
    assert tau == SIMPLE
    inner = F.slice("nodes", F.lit(2), F.col("len"))
    not_closed = (F.col("len") == 0) | (F.col("src") != F.col("dst"))
    return not_closed & ~F.array_contains(inner, F.col("to"))


class _Product:
    def __init__(self, g: PropertyGraph, regex: Regex, tau: str, seeds: DataFrame | None = None):
        self.tau = tau
        self.dfa: Dfa = compile_dfa(regex, g.edge_labels)
        labels = sorted({x for _, x in self.dfa.moves})
        edges = g.edges_of(labels).select("eid", F.col("label").alias("on"), F.col("src").alias("at"), F.col("dst").alias("to"))
        if g.stored and all(x in g.counts for x in labels):  # the same files that the algebra reads
            self.edges, n = edges, sum(g.counts[x] for x in labels)
        else:
            self.edges, n = counted(edges)
        if n > BROADCAST_ROWS:
            self.edges, n = counted(self._takable(seeds))
        self.small = n <= BROADCAST_ROWS
        self.sent = None
        spark = g.spark
        self.moves = spark.createDataFrame(self.dfa.rows() or [(-1, "", -1)], "state int, on string, next int").coalesce(1)
        self.finals = [int(x) for x in self.dfa.finals]

    def _takable(self, seeds: DataFrame | None) -> DataFrame:
        """Edges of a label that start where an edge into a state that reads the label ends, or at a seed; no run takes others."""
        parts = []
        for x in sorted({x for _, x in self.dfa.moves}):
            own = self.edges.where(F.col("on") == x)
            states = {s for s, y in self.dfa.moves if y == x}
            if 0 not in states or seeds is not None:
                into = sorted({y for (_, y), n in self.dfa.moves.items() if n in states})
                at = self.edges.where(F.col("on").isin(into)).select(F.col("to").alias("at"))
                if 0 in states:
                    at = at.union(seeds.select(F.col("id").alias("at")))
                own = own.join(at.distinct(), "at", "left_semi").select(*self.edges.columns)
            parts.append(own)
        out = parts[0]
        for x in parts[1:]:
            out = out.unionByName(x)
        return out

    def ahead(self, frontier: DataFrame, deep: bool) -> tuple[DataFrame, int, int, int]:
        """The states that one task makes from a small frontier (and which are open or not fresh), the number of fresh and of open ones, the longest path."""
        if self.sent is None:
            self.sent = self.edges.sparkSession.sparkContext.broadcast(local.Moves(self.edges.toArrow(), self.dfa.moves))
        seen = Observation()
        made = local.traversed(frontier, self.sent, self.tau, deep, LOCAL_ROWS)
        made = reliable(made.observe(seen, F.count(F.when(F.col("fresh"), 1)).alias("fresh"), F.count(F.when(F.col("open"), 1)).alias("open"), F.max("len").alias("longest")))
        return made, seen.get["fresh"], seen.get["open"], seen.get["longest"] or 0

    def start(self, g: PropertyGraph, seeds: DataFrame | None) -> DataFrame:
        ids = g.nodes.select("id") if seeds is None else seeds.select("id")
        return paths0(ids).withColumn("state", F.lit(0))

    def step(self, frontier: DataFrame) -> DataFrame:
        edges = F.broadcast(self.edges) if self.small else self.edges
        f = frontier.join(F.broadcast(self.moves), "state")
        f = f.join(edges, (f["dst"] == edges["at"]) & (f["on"] == edges["on"])).where(_may_add(self.tau))
        return f.select("src", F.col("to").alias("dst"), (F.col("len") + 1).alias("len"), F.concat("nodes", F.array("to")).alias("nodes"), F.concat("edges", F.array("eid")).alias("edges"), F.col("next").alias("state"))

    def accepted(self, frontier: DataFrame) -> DataFrame:
        return frontier.where(F.col("state").isin(self.finals)).select(*PATH_COLUMNS) if self.finals else frontier.where("false").select(*PATH_COLUMNS)


def bfs_automaton(g: PropertyGraph, regex: Regex, tau: str, *, seeds: DataFrame | None = None, max_len: int | None = None, limit: int | None = None, post=None, trace: Trace | None = None) -> DataFrame:
    """Level-synchronous traversal. Levels are lengths, so a limit is reached once that many are accepted."""
    if tau == WALK and max_len is None and limit is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len or a limit")
    trace, post = trace or Trace(), post or (lambda d: d)
    p = _Product(g, regex, tau, seeds)
    (frontier, n), out, found, level = counted(p.start(g, seeds)), [], 0, 0
    local_steps, told, tried = p.small and max_len is None and limit is None, False, False
    while True:
        trace.check()
        trace.add("frontier", n, level)
        if n > MAX_LEVEL_ROWS:
            raise RecursionExplosion(f"level {level} has {n} product states")
        if not n:
            break
        if not told:
            part = post(p.accepted(frontier))
            if limit is not None:
                part, more = counted(part)
                found += more
            out.append(part)
        if limit is not None and found >= limit or max_len is not None and level >= max_len:
            break
        if local_steps and n <= LOCAL_FRONTIER and not tried:
            made, fresh, still, longest = p.ahead(frontier, deep=False)
            told, tried = True, still > 0 and not fresh  # a level that is too much for one task is a join
            if not tried:
                out.append(post(p.accepted(made.where("fresh"))))
                frontier, n, level = made.where("open").drop("fresh", "open"), still, max(level, longest)
            continue
        frontier, n = counted(p.step(frontier))
        level, told, tried = level + 1, False, False
    return _union(g, out)


def dfs_automaton(g: PropertyGraph, regex: Regex, tau: str, *, seeds: DataFrame | None = None, max_len: int | None = None, limit: int | None = None, post=None, block_rows: int = 10_000, trace: Trace | None = None) -> DataFrame:
    """Depth first over blocks: the deepest block of product states is expanded next.

    The driver's stack holds references to materialised blocks of about ``block_rows`` rows. Without a limit the answer is the breadth-first one; with a
    limit it is any that many paths, as found first.
    """
    if tau == WALK and max_len is None and limit is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len or a limit")
    trace, post = trace or Trace(), post or (lambda d: d)
    p = _Product(g, regex, tau, seeds)
    stack, out, found = [(*counted(p.start(g, seeds)), 0, False)], [], 0
    while stack:
        trace.check()
        block, n, depth, told = stack.pop()
        if not n:
            continue
        trace.add("block", n, depth)
        if not told:
            part = post(p.accepted(block))
            if limit is not None:
                part, more = counted(part)
                found += more
            out.append(part)
        if limit is not None and found >= limit:
            break
        if max_len is not None and depth >= max_len:
            continue
        if p.small and max_len is None and limit is None and n <= LOCAL_FRONTIER:
            made, _, still, longest = p.ahead(block, deep=True)
            out.append(post(p.accepted(made.where("fresh"))))
            stack.append((made.where("open").drop("fresh", "open"), still, max(depth, longest), True))
            continue
        kids, m = counted(p.step(block))
        blocks = -(-m // block_rows)
        if blocks > 1:  # written once by block, so that each is a folder of its own
            path = new_folder(g.spark, "blocks")
            kids.withColumn("block", F.pmod(F.xxhash64("src", "edges"), F.lit(blocks))).write.partitionBy("block").parquet(path)
            sizes = {r["block"]: r["count"] for r in g.spark.read.parquet(path).groupBy("block").count().collect()}
            stack += [(g.spark.read.schema(kids.schema).parquet(f"{path}/block={k}"), v, depth + 1, False) for k, v in sorted(sizes.items())]
        else:
            stack.append((kids, m, depth + 1, False))
    return _union(g, out)


def dfs_local(edges: list[tuple[int, str, int, int]], dfa: Dfa, tau: str, seeds: list[int], max_len: int | None = None) -> list[tuple[list[int], list[int]]]:
    """Plain recursion over a small edge list (eid, label, src, dst); an oracle for tests."""
    by_src: dict[int, list] = {}
    for e in edges:
        by_src.setdefault(e[2], []).append(e)
    out = []

    def valid(nodes: list[int], path: list[int]) -> bool:
        if tau == TRAIL:
            return len(set(path)) == len(path)
        if tau == ACYCLIC:
            return len(set(nodes)) == len(nodes)
        if tau == SIMPLE:
            return len(path) == 0 or len(set(nodes[:-1])) == len(path) and len(set(nodes[1:])) == len(path)
        return True

    def go(nodes: list[int], path: list[int], state: int) -> None:
        if state in dfa.finals:
            out.append((nodes, path))
        if max_len is not None and len(path) >= max_len:
            return
        for eid, label, _, dst in by_src.get(nodes[-1], ()):
            nxt = dfa.moves.get((state, label))
            if nxt is not None and valid(nodes + [dst], path + [eid]):
                go(nodes + [dst], path + [eid], nxt)

    for s in seeds:
        go([s], [], 0)
    return out


def group_paths(edges: DataFrame, group: str, regex: Regex, tau: str, alphabet: list[str], max_len: int | None = None) -> DataFrame:
    """group, src, dst, len, nodes, edges: depth-first search inside each group of edges (such as a conversation), one group in memory at a time."""
    if tau == WALK and max_len is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len")
    dfa = compile_dfa(regex, alphabet)

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = [(int(a), str(b), int(c), int(d)) for a, b, c, d in zip(pdf["eid"], pdf["label"], pdf["src"], pdf["dst"])]
        ids = sorted({r[2] for r in rows} | {r[3] for r in rows})
        found = dfs_local(rows, dfa, tau, ids, max_len)
        key = pdf[group].iloc[0]
        return pd.DataFrame({group: [key] * len(found), "src": [n[0] for n, _ in found], "dst": [n[-1] for n, _ in found], "len": [len(e) for _, e in found], "nodes": [n for n, _ in found], "edges": [e for _, e in found]})

    kind = edges.schema[group].dataType.simpleString()
    return edges.groupBy(group).applyInPandas(search, f"`{group}` {kind}, {PATH_SCHEMA}")


def expansions(g: PropertyGraph, regex: Regex, tau: str, seeds: DataFrame | None = None, max_len: int | None = None) -> DataFrame:
    """n_expanded, n_states: product states that the traversal expands, and distinct (node, state) among them."""
    if tau == WALK and max_len is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len")
    p = _Product(g, regex, tau, seeds)
    (frontier, n), parts, level = counted(p.start(g, seeds)), [], 0
    while n and (max_len is None or level <= max_len):
        parts.append(frontier.select("dst", "state"))
        frontier, n = counted(p.step(frontier))
        level += 1
    return _union(g, parts, "dst bigint, state int").agg(F.count("*").alias("n_expanded"), F.countDistinct("dst", "state").alias("n_states"))


def reachable_pairs(g: PropertyGraph, regex: Regex, seeds: DataFrame | None = None, trace: Trace | None = None) -> DataFrame:
    """src, dst of matching walks, without the paths; ends on any graph, as pairs are visited once.

    Few edges are sent to all tasks, each of which searches from its own sources and stores nothing.
    """
    trace = trace or Trace()
    p = _Product(g, regex, WALK, seeds)
    ids = g.nodes.select("id") if seeds is None else seeds.select("id")
    if p.small:
        return local.reach_local(p.edges, p.dfa.rows(), p.finals, p.dfa.states(), ids)
    edges = p.edges
    frontier = reliable(ids.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0).alias("state")))
    parts = [frontier]
    while True:
        trace.check()
        n = frontier.count()
        trace.add("pairs", n, None)
        if not n:
            break
        f = frontier.join(F.broadcast(p.moves), "state")
        nxt = f.join(edges, (f["dst"] == edges["at"]) & (f["on"] == edges["on"])).select("src", F.col("to").alias("dst"), F.col("next").alias("state")).distinct()
        seen = parts[0]
        for x in parts[1:]:
            seen = seen.union(x)
        frontier = reliable(nxt.join(seen, ["src", "dst", "state"], "left_anti"))
        parts.append(frontier)
        if len(parts) > 24:  # keep the union flat
            merged = parts[0]
            for x in parts[1:]:
                merged = merged.union(x)
            parts = [reliable(merged)]
    all_pairs = parts[0]
    for x in parts[1:]:
        all_pairs = all_pairs.union(x)
    return all_pairs.where(F.col("state").isin(p.finals)).select("src", "dst").distinct()


def _union(g: PropertyGraph, parts: list[DataFrame], schema: str = PATH_SCHEMA) -> DataFrame:
    if not parts:
        return g.spark.createDataFrame([], schema)
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out
