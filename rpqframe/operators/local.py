"""Searches inside tasks, over edges or base paths that every task holds whole.

A small base (the measured bytes of the recursion decide) is sent to all tasks once. Each task then follows its own sources
to their ends and hands on what it finds in batches, so nothing is shuffled or stored between levels, and work is
spread over sources. A larger base is left to the joins of ``fixpoint`` and ``baselines``.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rpqframe.functions.paths import PATH_COLUMNS, PATH_SCHEMA
from rpqframe.functions.restrictors import ACYCLIC, SIMPLE, TRAIL

#: Node ids, and rows, of one batch that a task hands on.
BATCH_IDS, BATCH_ROWS = 1 << 20, 10_000


class Steps:
    """Base paths by their first node, in flat arrays."""

    def __init__(self, base: DataFrame):
        t = base.select("src", "nodes", "edges").toArrow()
        src = t.column("src").to_numpy()
        order = np.argsort(src, kind="stable")
        t = t.take(pa.array(order))
        self.src = src[order]
        self.nodes, self.edges = (self._flat(t, c) for c in ("nodes", "edges"))
        self.known: dict[int, list[tuple[list[int], list[int]]]] = {}

    @staticmethod
    def _flat(t: pa.Table, name: str) -> tuple[np.ndarray, np.ndarray]:
        lists = pa.concat_arrays([pa.array([], pa.list_(pa.int64())), *[c.cast(pa.list_(pa.int64())) for c in t.column(name).chunks]])
        return np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False)

    def after(self, node: int) -> list[tuple[list[int], list[int]]]:
        """The nodes after the first, and the edges, of each base path from a node."""
        if node not in self.known:
            (n_at, n), (e_at, e) = self.nodes, self.edges
            lo, hi = np.searchsorted(self.src, node), np.searchsorted(self.src, node, side="right")
            self.known[node] = [(n[n_at[i] + 1 : n_at[i + 1]].tolist(), e[e_at[i] : e_at[i + 1]].tolist()) for i in range(lo, hi)]
        return self.known[node]


class _Batch:
    """Path rows on their way out of a task."""

    def __init__(self):
        self.nodes, self.edges, self.n_at, self.e_at = array("q"), array("q"), array("i", [0]), array("i", [0])

    def add(self, nodes: array, edges: array) -> bool:
        """Whether the batch is full now."""
        self.nodes.extend(nodes)
        self.edges.extend(edges)
        self.n_at.append(len(self.nodes))
        self.e_at.append(len(self.edges))
        return len(self.nodes) >= BATCH_IDS or len(self.n_at) > BATCH_ROWS

    def take(self) -> pa.RecordBatch:
        n_at, e_at = np.array(self.n_at, np.int32), np.array(self.e_at, np.int32)
        nodes, edges = np.array(self.nodes, np.int64), np.array(self.edges, np.int64)
        lists = lambda at, flat: pa.ListArray.from_arrays(pa.array(at), pa.array(flat))
        columns = [pa.array(nodes[n_at[:-1]]), pa.array(nodes[n_at[1:] - 1]), pa.array(np.diff(e_at)), lists(n_at, nodes), lists(e_at, edges)]
        self.__init__()
        return pa.RecordBatch.from_arrays(columns, names=PATH_COLUMNS)


def _follow(nodes: list[int], edges: list[int], steps: Steps, tau: str, max_len: int | None, most_steps: int) -> Iterator[tuple[array, array]]:
    """Every path that extends one path by base paths, depth first; the two arrays are those of the search itself."""
    if tau == SIMPLE and edges and nodes[0] == nodes[-1]:
        return  # a closed simple path goes nowhere
    src, own_nodes, own_edges = nodes[0], array("q", nodes), array("q", edges)
    used = set(edges) if tau == TRAIL else set(nodes)
    stack, taken = [iter(steps.after(nodes[-1]))], []
    while stack:
        tail, more = next(stack[-1], (None, None))
        if tail is None:
            stack.pop()
            if taken:
                gone = taken.pop()
                if tau == TRAIL:
                    used.difference_update(own_edges[-gone:])
                elif tau in (ACYCLIC, SIMPLE):
                    used.difference_update(own_nodes[-gone:])
                del own_nodes[-gone:], own_edges[-gone:]
            continue
        if not more or max_len is not None and len(own_edges) + len(more) > max_len:
            continue
        closes = tau == SIMPLE and tail[-1] == src
        if tau == TRAIL and not used.isdisjoint(more) or tau in (ACYCLIC, SIMPLE) and not used.isdisjoint(tail[:-1] if closes else tail):
            continue
        own_nodes.extend(tail)
        own_edges.extend(more)
        yield own_nodes, own_edges
        if closes:
            del own_nodes[-len(more) :], own_edges[-len(more) :]
            continue
        if len(stack) >= most_steps:
            raise RuntimeError(f"paths go on after {most_steps} more levels")
        used.update(more if tau == TRAIL else tail if tau in (ACYCLIC, SIMPLE) else ())
        taken.append(len(more))
        stack.append(iter(steps.after(tail[-1])))


def extensions(frontier: DataFrame, base: DataFrame, tau: str, max_len: int | None, most_steps: int) -> DataFrame:
    """All paths that extend a path of the frontier by one or more base paths, a row for each derivation; made when they are read."""
    spark = frontier.sparkSession
    sent = spark.sparkContext.broadcast(Steps(base))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        steps, out = sent.value, _Batch()
        for batch in batches:
            for nodes, edges in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for found in _follow(nodes, edges, steps, tau, max_len, most_steps):
                    if out.add(*found):
                        yield out.take()
        yield out.take()

    return _dealt(frontier.select("nodes", "edges"), "nodes").mapInArrow(run, PATH_SCHEMA)


def _dealt(rows: DataFrame, *by: str) -> DataFrame:
    """Even shares for the tasks: a few rows can stand for long searches."""
    return rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), *by)


class Adjacency:
    """Edges by source, with nodes as positions."""

    def __init__(self, edges: pa.Table):
        src, dst, eid = (edges.column(c).to_numpy() for c in ("src", "dst", "eid"))
        self.ids = np.unique(np.concatenate([src, dst]))
        order = np.lexsort((eid, dst, src))
        at, self.to, self.eid = np.searchsorted(self.ids, src[order]), np.searchsorted(self.ids, dst[order]), eid[order]
        self.first = np.searchsorted(at, np.arange(len(self.ids) + 1))
        self.known: dict[int, list[tuple[int, int]]] = {}

    def place(self, node: int) -> int | None:
        k = int(np.searchsorted(self.ids, node))
        return k if k < len(self.ids) and self.ids[k] == node else None

    def after(self, k: int) -> list[tuple[int, int]]:
        """(node, edge) of each edge from a node, in order."""
        if k not in self.known:
            a, b = self.first[k], self.first[k + 1]
            self.known[k] = list(zip(self.to[a:b].tolist(), self.eid[a:b].tolist()))
        return self.known[k]


def _shortest_from(start: int, graph: Adjacency, closed: bool, all_ties: bool) -> Iterator[tuple[array, array]]:
    """The shortest paths from one node, level by level; nodes of a level stand in the order of their first path."""
    src = int(graph.ids[start])
    reached, level = {start}, [(start, [(array("q", [src]), array("q"))])]
    back = not closed  # whether the pair of the node with itself is done
    while level:
        new: dict[int, list[tuple[array, array]]] = {}
        for v, paths in level:
            for w, eid in graph.after(v):
                if w == start and back or w != start and w in reached:
                    continue
                own = new.setdefault(w, [])
                if all_ties or not own:
                    to = int(graph.ids[w])
                    own += [(nodes + array("q", [to]), edges + array("q", [eid])) for nodes, edges in paths]
        for found in new.values():
            yield from found
        back = back or start in new
        new.pop(start, None)
        reached.update(new)
        # in the order of making: by the first path of the node before, then by the node
        level = list(new.items())


def shortest_local(edges: DataFrame, closed: bool, all_ties: bool) -> DataFrame:
    """``shortest_paths`` of few edges: each task holds all edges and searches from its own sources."""
    spark = edges.sparkSession
    sent = spark.sparkContext.broadcast(Adjacency(edges.select("src", "dst", "eid").toArrow()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph, out = sent.value, _Batch()
        for batch in batches:
            for node in batch.column(0).to_pylist():
                for found in _shortest_from(graph.place(node), graph, closed, all_ties):
                    if out.add(*found):
                        yield out.take()
        yield out.take()

    return _dealt(edges.select("src").distinct(), "src").mapInArrow(run, PATH_SCHEMA)


class ProductGraph:
    """Product states (node, automaton state) as numbers, with the next ones of each."""

    def __init__(self, edges: pa.Table, moves: list[tuple[int, str, int]], finals: list[int], states: int):
        at, to = edges.column("at").to_numpy(), edges.column("to").to_numpy()
        on = np.array(edges.column("on").to_pylist(), dtype=object)
        self.ids, self.states, self.finals = np.unique(np.concatenate([at, to])), states, finals
        at, to = np.searchsorted(self.ids, at), np.searchsorted(self.ids, to)
        a = np.concatenate([np.zeros(0, np.int64), *[at[on == x] * states + s for s, x, _ in moves]])
        b = np.concatenate([np.zeros(0, np.int64), *[to[on == x] * states + n for _, x, n in moves]])
        order = np.argsort(a, kind="stable")
        self.to = b[order]
        self.first = np.searchsorted(a[order], np.arange(len(self.ids) * states + 1))
        self.known: list[tuple[int, ...]] | None = None

    def reached(self, node: int) -> np.ndarray:
        """The nodes that stand at the end of an accepted walk from a node."""
        k = int(np.searchsorted(self.ids, node))
        if k == len(self.ids) or self.ids[k] != node:
            return np.array([node] if 0 in self.finals else [], dtype=np.int64)
        if self.known is None:
            ends, to = self.first.tolist(), self.to.tolist()
            self.known = [tuple(to[x:y]) for x, y in zip(ends, ends[1:])]
        after, start = self.known, k * self.states
        seen, todo = {start}, [start]
        while todo:
            for y in after[todo.pop()]:
                if y not in seen:
                    seen.add(y)
                    todo.append(y)
        all_of = np.fromiter(seen, np.int64, len(seen))
        return self.ids[np.unique(all_of[np.isin(all_of % self.states, self.finals)] // self.states)]


def reach_local(edges: DataFrame, moves: list[tuple[int, str, int]], finals: list[int], states: int, ids: DataFrame) -> DataFrame:
    """src, dst of accepted walks over few edges (at, on, to): each task searches from its own sources."""
    sent = edges.sparkSession.sparkContext.broadcast(ProductGraph(edges.select("at", "on", "to").toArrow(), moves, finals, states))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = sent.value
        pack = lambda own, sizes, found: pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(own, np.int64), sizes)), pa.array(np.concatenate([np.zeros(0, np.int64), *found]))], names=["src", "dst"])
        for batch in batches:
            own, sizes, found, n = [], [], [], 0
            for node in batch.column(0).to_pylist():
                own.append(node)
                found.append(graph.reached(node))
                sizes.append(len(found[-1]))
                n += sizes[-1]
                if n >= BATCH_IDS:
                    yield pack(own, sizes, found)
                    own, sizes, found, n = [], [], [], 0
            yield pack(own, sizes, found)

    return _dealt(ids.select("id").distinct(), "id").mapInArrow(run, "src bigint, dst bigint")


class Moves:
    """Edges (eid, on, at, to) by source and label, for a search over the product with an automaton."""

    def __init__(self, edges: pa.Table, moves: dict[tuple[int, str], int]):
        self.at = edges.column("at").to_numpy()
        order = np.argsort(self.at, kind="stable")
        self.at = self.at[order]
        self.to, self.eid = edges.column("to").to_numpy()[order], edges.column("eid").to_numpy()[order]
        self.on = edges.column("on").take(pa.array(order)).to_pylist()
        self.moves = moves

    def after(self, node: int, state: int) -> list[tuple[int, int, int]]:
        lo, hi = np.searchsorted(self.at, node), np.searchsorted(self.at, node, side="right")
        return [(int(self.eid[i]), int(self.to[i]), self.moves[state, self.on[i]]) for i in range(lo, hi) if (state, self.on[i]) in self.moves]


def _kids(row: tuple, graph: Moves, tau: str) -> list[tuple]:
    nodes, edges, state = row
    if tau == SIMPLE and edges and nodes[0] == nodes[-1]:
        return []
    out = []
    for eid, to, state in graph.after(nodes[-1], state):
        if tau == TRAIL and eid in edges or tau == ACYCLIC and to in nodes or tau == SIMPLE and to in nodes[1:]:
            continue
        out.append((nodes + [to], edges + [eid], state))
    return out


def traverse(rows: list[tuple], graph: Moves, tau: str, deep: bool, most: int) -> list[list]:
    """[row, fresh, open] of the product states after the given ones, until about ``most`` are made or none is open.

    Breadth first in whole levels, or depth first. An open state is not expanded yet; a given one that stays open is
    among them and not fresh.
    """
    all_rows = [[r, False, True] for r in rows]
    todo, work = list(range(len(rows))), 0
    while todo:
        kids: list[tuple] = []
        turn = [todo[-1]] if deep else todo
        for i in turn:
            new = _kids(all_rows[i][0], graph, tau)
            kids += new
            work += sum(len(k[0]) for k in new)
            if not deep and (len(all_rows) + len(kids) > most + len(rows) or work > 100 * most):
                return [r for r in all_rows if r[1] or r[2]]
        for i in turn:
            all_rows[i][2] = False
        made = range(len(all_rows), len(all_rows) + len(kids))
        all_rows += [[k, True, True] for k in kids]
        todo = todo[:-1] + list(made) if deep else list(made)
        if deep and (len(all_rows) > most + len(rows) or work > 100 * most):
            break
    return [r for r in all_rows if r[1] or r[2]]


def traversed(frontier: DataFrame, sent, tau: str, deep: bool, most: int) -> DataFrame:
    """Path columns, state, fresh, open: ``traverse`` of a small frontier in one task; ``sent`` is the broadcast graph."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [(r["nodes"], r["edges"], r["state"]) for batch in batches for r in batch.to_pylist()]
        ints = pa.list_(pa.int64())
        made = traverse(rows, sent.value, tau, deep, most)
        for at in range(0, len(made), 1_000):
            part = made[at : at + 1_000]
            cols = {
                "src": pa.array([r[0][0] for r, _, _ in part], pa.int64()), "dst": pa.array([r[0][-1] for r, _, _ in part], pa.int64()), "len": pa.array([len(r[1]) for r, _, _ in part], pa.int32()),
                "nodes": pa.array([r[0] for r, _, _ in part], ints), "edges": pa.array([r[1] for r, _, _ in part], ints), "state": pa.array([r[2] for r, _, _ in part], pa.int32()),
                "fresh": pa.array([x for _, x, _ in part], pa.bool_()), "open": pa.array([x for _, _, x in part], pa.bool_()),
            }
            yield pa.RecordBatch.from_pydict(cols)

    return frontier.select("nodes", "edges", "state").coalesce(1).mapInArrow(run, f"{PATH_SCHEMA}, state int, fresh boolean, open boolean")
