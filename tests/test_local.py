"""Searches inside tasks against joins level by level and plain enumeration."""

import random

import pytest
from pyspark.sql import functions as F

from rpqframe.functions.paths import paths1
from rpqframe.functions.restrictors import restrict
from rpqframe.operators import aggregate, baselines, fixpoint
from rpqframe.operators.automata import compile_dfa
from rpqframe.operators.baselines import bfs_automaton, dfs_automaton, dfs_local, reachable_pairs
from rpqframe.operators.fixpoint import Trace, join_paths, recursive_join
from rpqframe.plans.regex import parse_regex
from rpqframe.plans.workload import stored_by_label
from rpqframe.sources.graph import EDGE_SCHEMA, NODE_SCHEMA, from_frames, toy_graph
from tests.test_random_graphs import many_graphs

PATTERNS = ("(a.b)+", "a+.b?", "(a|b)+")


def frame(spark, edges):
    return spark.createDataFrame(edges, "eid bigint, src bigint, dst bigint").coalesce(1)


def graph(spark, edges):
    nodes = sorted({e[2] for e in edges} | {e[3] for e in edges})
    return from_frames(spark.createDataFrame([(i, "N", {}) for i in nodes], NODE_SCHEMA).coalesce(1), spark.createDataFrame([(*e, {}) for e in edges], EDGE_SCHEMA).coalesce(1), ["N"], ["a", "b"])


def keys(df):
    return sorted((tuple(x.nodes), tuple(x.edges), x.src, x.dst, x.len) for x in df.collect())


def listed(found):
    return sorted((tuple(n), tuple(e), n[0], n[-1], len(e)) for n, e in found)


@pytest.mark.parametrize("method", [bfs_automaton, dfs_automaton])
def test_chain_is_a_few_blocks(spark, method):
    edges = [(100 + i, "ab"[i % 2], i, i + 1) for i in range(60)]
    trace = Trace()
    found = method(graph(spark, edges), parse_regex("(a.b)+"), "trail", seeds=spark.range(1), trace=trace)
    assert found.count() == 30 and len(trace.levels) <= 3


@pytest.mark.parametrize("method", [bfs_automaton, dfs_automaton])
@pytest.mark.parametrize("rows", [2, 50_000])
def test_blocks_equal_enumeration(spark, monkeypatch, method, rows):
    monkeypatch.setattr(baselines, "LOCAL_ROWS", rows)
    parts, _ = many_graphs(random.Random(5), 8)
    edges = [e for part, _ in parts for e in part]
    seeds = [e[2] for e in edges][:6]
    g = graph(spark, edges)
    for rx, tau in zip(PATTERNS, ("trail", "simple", "acyclic")):
        want = dfs_local(edges, compile_dfa(parse_regex(rx), ["a", "b"]), tau, sorted(set(seeds)))
        ids = spark.createDataFrame([(s,) for s in sorted(set(seeds))], "id bigint").coalesce(1)
        assert keys(method(g, parse_regex(rx), tau, seeds=ids)) == listed(want), (rx, tau)


def test_edges_that_no_run_takes_are_left_out(spark, monkeypatch):
    monkeypatch.setattr(baselines, "BROADCAST_ROWS", 6)
    edges = [(1, "a", 1, 2), (2, "b", 2, 3), (3, "a", 3, 4), (4, "b", 4, 1)] + [(10 + i, "b", 100 + i, 200 + i) for i in range(9)]
    g, seeds = graph(spark, edges), spark.range(1, 2)
    made = baselines._Product(g, parse_regex("(a.b)+"), "trail", seeds)
    assert made.small and sorted(r.eid for r in made.edges.collect()) == [1, 2, 3, 4]
    want = dfs_local(edges, compile_dfa(parse_regex("(a.b)+"), ["a", "b"]), "trail", [1])
    assert keys(bfs_automaton(g, parse_regex("(a.b)+"), "trail", seeds=seeds)) == listed(want)


def test_labels_are_stored_when_used(spark):
    made = []
    g = toy_graph(spark)
    for x, f in list(g.edge_frames.items()):
        g.edge_frames[x] = lambda x=x, f=f: made.append(x) or f()
    g.whole = None
    s = stored_by_label(g)
    assert s.edges_of(["likes"]).count() == s.edges_of(["likes"]).count() == s.counts["likes"] == 3
    assert made == ["likes"] and "knows" in s.counts and s.counts.get("knows", -1) == 6 and s.counts.get("none", -1) == -1


@pytest.mark.parametrize("closed", [True, False])
@pytest.mark.parametrize("ties", [True, False])
def test_shortest_paths_from_each_source(spark, monkeypatch, closed, ties):
    r = random.Random(6)
    edges = frame(spark, [(100 + i, r.randint(0, 9), r.randint(0, 9)) for i in range(26)] + [(90, 3, 3), (91, 20, 21), (92, 20, 21)]).cache()
    trace = Trace()
    found = keys(aggregate.shortest_paths(edges, closed, ties, trace))
    assert not trace.levels  # no level is written
    monkeypatch.setattr(aggregate, "BROADCAST_BYTES", -1)
    assert found == keys(aggregate.shortest_paths(edges, closed, ties, trace)) and trace.levels


def test_reachable_pairs_from_each_source(spark, monkeypatch):
    parts, nodes = many_graphs(random.Random(7), 10)
    g = graph(spark, [e for part, _ in parts for e in part])
    for rx in (*PATTERNS, "a*"):
        trace = Trace()
        found = sorted(tuple(r) for r in reachable_pairs(g, parse_regex(rx), trace=trace).collect())
        assert not trace.levels  # nothing is stored
        with monkeypatch.context() as m:
            m.setattr(baselines, "BROADCAST_ROWS", -1)
            assert found == sorted(tuple(r) for r in reachable_pairs(g, parse_regex(rx), trace=trace).collect()) and trace.levels
    nothing = spark.createDataFrame([], "id bigint")
    assert reachable_pairs(g, parse_regex("a+"), seeds=nothing).count() == 0


@pytest.mark.parametrize("strategy", ["linear", "doubling"])
def test_large_recursions_end_in_the_reading_tasks(spark, monkeypatch, strategy):
    parts, _ = many_graphs(random.Random(8), 25)
    one = paths1(frame(spark, [(e, a, b) for part, _ in parts for e, _, a, b in part])).cache()
    for tau in ("trail", "simple", "acyclic"):
        two = join_paths(one.where(restrict(tau)), one.where(restrict(tau)), tau).cache()
        bases = [one, two, one.unionByName(two)]  # the last has several derivations of a path
        for base in bases if strategy == "linear" else bases[:2]:
            monkeypatch.setattr(fixpoint, "STREAM_BYTES", 1 << 40)
            want = keys(recursive_join(base, tau, dedupe=False))
            monkeypatch.setattr(fixpoint, "STREAM_BYTES", 0)
            trace = Trace()
            assert keys(recursive_join(base, tau, dedupe=False, strategy=strategy, trace=trace)) == want and len(trace.levels) == 1
    bounded = recursive_join(one, "walk", dedupe=False, max_len=3)
    monkeypatch.setattr(fixpoint, "STREAM_BYTES", 1 << 40)
    assert keys(bounded) == keys(recursive_join(one, "walk", dedupe=False, max_len=3))


def test_streamed_chains_are_not_cut(spark, monkeypatch):
    monkeypatch.setattr(fixpoint, "STREAM_BYTES", 0)
    chain = paths1(frame(spark, [(100 + i, i, i + 1) for i in range(30)]))
    assert recursive_join(chain, "acyclic", dedupe=False).agg(F.count("*"), F.sum("len")).first()[:] == (465, sum((31 - n) * n for n in range(1, 31)))
    monkeypatch.setattr(fixpoint, "MAX_LEVELS", 9)
    with pytest.raises(Exception, match="paths go on"):
        recursive_join(chain, "acyclic", dedupe=False).count()


def test_restricted_set_operations_move_nothing(spark):
    parts, _ = many_graphs(random.Random(9), 20)
    one = paths1(frame(spark, [(e, a, b) for part, _ in parts for e, _, a, b in part])).cache()
    trails, simple = recursive_join(one, "trail", dedupe=False), recursive_join(one, "simple", dedupe=False)
    both, rest = aggregate.intersect_restricted(trails, "simple"), aggregate.except_restricted(trails, "simple")
    assert keys(both) == keys(aggregate.intersect_paths(trails, simple)) == keys(simple)
    assert keys(rest) == keys(aggregate.except_paths(trails, simple)) and rest.count()
    assert not any("Exchange" in d._jdf.queryExecution().executedPlan().toString() for d in (both, rest))
