"""Random graphs and patterns against plain enumeration."""

import random
import time

import pytest

from rpqframe.functions.paths import paths1
from rpqframe.operators import fixpoint
from rpqframe.operators.automata import compile_dfa
from rpqframe.operators.baselines import dfs_local
from rpqframe.operators.fixpoint import join_paths, recursive_join
from rpqframe.plans import metrics
from rpqframe.plans.lower import rpq_paths
from rpqframe.plans.regex import Alt, Cat, Lab, Opt, Plus, Star
from rpqframe.sources.graph import EDGE_SCHEMA, NODE_SCHEMA, from_frames
from rpqframe.streaming.edges import PathTable


def pattern(r: random.Random, depth: int):
    if depth == 0 or r.random() < 0.25:
        return Lab(r.choice("ab"))
    kind = r.choice([Cat, Alt, Plus, Star, Opt])
    return kind(pattern(r, depth - 1), pattern(r, depth - 1)) if kind in (Cat, Alt) else kind(pattern(r, depth - 1))


def many_graphs(r: random.Random, n_graphs: int):
    """Disjoint random graphs in one, each with a self-loop; the edge list of each, and its nodes."""
    parts, nodes, eid = [], [], 0
    for k in range(n_graphs):
        ids = [10 * k + i for i in range(1, r.randint(2, 4) + 1)]
        edges = [(r.choice(ids), r.choice(ids)) for _ in range(r.randint(1, 4))]
        edges.append((ids[0],) * 2)
        part = []
        for a, b in edges:
            eid += 1
            part.append((10**6 + eid, r.choice("ab"), a, b))
        parts.append((part, ids))
        nodes += ids
    return parts, nodes


@pytest.mark.parametrize("seed", range(6))
def test_random_graphs(spark, seed):
    r = random.Random(seed)
    parts, nodes = many_graphs(r, 60)
    edges = [(*e, {}) for part, _ in parts for e in part]
    g = from_frames(spark.createDataFrame([(i, "N", {}) for i in nodes], NODE_SCHEMA).coalesce(1), spark.createDataFrame(edges, EDGE_SCHEMA).coalesce(1), ["N"], ["a", "b"])
    a, b = Lab("a"), Lab("b")
    for rx in ([Cat(a, b), Cat(a, Opt(b)), Opt(Cat(a, b)), Plus(Alt(a, b))][seed % 4], pattern(r, 2)):
        for tau in ("trail", "simple", "acyclic", "walk"):
            bound = 3 if tau == "walk" else None
            dfa = compile_dfa(rx, ["a", "b"])
            want = sorted((tuple(n), tuple(e)) for part, ids in parts for n, e in dfs_local(part, dfa, tau, ids, bound))
            got = rpq_paths(g, f"MATCH {tau} p = (x)-[{rx}]->(y) RETURN p", mode="set", max_len=bound)
            assert sorted((tuple(x.nodes), tuple(x.edges)) for x in got.collect()) == want, (rx, tau)


def chain(spark, n: int):
    return paths1(spark.createDataFrame([(100 + i, i, i + 1) for i in range(n)], "eid bigint, src bigint, dst bigint"))


def test_every_derivation_is_kept(spark):
    base = chain(spark, 13)
    two = join_paths(base, base, "trail")
    found = recursive_join(base.unionByName(two), "trail", dedupe=False)
    fib = [1, 1]
    while len(fib) < 15:
        fib.append(fib[-1] + fib[-2])
    assert found.count() == sum((14 - n) * fib[n] for n in range(1, 14))


def test_long_chains_are_not_cut(spark, monkeypatch):
    monkeypatch.setattr(fixpoint, "MAX_LEVELS", 3)
    monkeypatch.setattr(fixpoint, "LOCAL_FRONTIER", 0)
    with pytest.raises(fixpoint.RecursionExplosion):
        recursive_join(chain(spark, 9), "trail", dedupe=False)
    monkeypatch.setattr(fixpoint, "MAX_LEVELS", 9)
    assert recursive_join(chain(spark, 9), "trail", dedupe=False).count() == 45


def test_large_bases_stay_where_they_are(spark, monkeypatch):
    monkeypatch.setattr(fixpoint, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(fixpoint._Base, "drop", lambda self: plans.append(self))
    plans = []
    assert recursive_join(chain(spark, 6), "trail", dedupe=False).count() == 21
    layout = plans[0]
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        text = join_paths(chain(spark, 6), layout.rows.hint("merge"), "trail")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert text.count("Exchange hashpartitioning") == 1 and "Bucketed: true" in text


def test_look_ahead_equals_levels(spark, monkeypatch):
    r = random.Random(3)
    parts, _ = many_graphs(r, 30)
    base = paths1(spark.createDataFrame([(e, a, b) for part, _ in parts for e, _, a, b in part], "eid bigint, src bigint, dst bigint")).cache()
    for tau in ("trail", "simple", "acyclic"):
        ahead = sorted(tuple(x.edges) for x in recursive_join(base, tau, dedupe=False, seed=lambda d: d.where("src % 10 = 1")).collect())
        monkeypatch.setattr(fixpoint, "LOCAL_ROWS", 3)  # too few for any level: every level is a join
        assert ahead == sorted(tuple(x.edges) for x in recursive_join(base, tau, dedupe=False, seed=lambda d: d.where("src % 10 = 1")).collect())
        monkeypatch.undo()


def test_paths_kept_up_by_batches(spark, tmp_path):
    r = random.Random(4)
    parts, _ = many_graphs(r, 20)
    edges = [(e, a, b) for part, _ in parts for e, _, a, b in part]
    r.shuffle(edges)
    schema = "eid bigint, src bigint, dst bigint"
    kept = PathTable(spark, str(tmp_path / "paths"))
    for k in range(3):
        kept.add(spark.createDataFrame(edges[k::3], schema), k)
    kept.add(spark.createDataFrame(edges[2::3], schema), 2)  # a batch that runs again
    want = recursive_join(paths1(spark.createDataFrame(edges, schema)), "trail", dedupe=False)
    assert sorted(tuple(x.edges) for x in kept.paths().collect()) == sorted(tuple(x.edges) for x in want.collect())


def test_jobs_are_cancelled_and_failures_named(spark):
    begin = time.monotonic()
    slow = spark.range(8).repartition(8).selectExpr("java_method('java.lang.Thread', 'sleep', 20000L) as x", "id")
    seconds, paths, status = metrics.timed(lambda: slow, 2.0, fixpoint.Trace(), spark)
    assert status == "timeout" and paths == 0 and time.monotonic() - begin < 15
    assert metrics.failure_kind("java.lang.OutOfMemoryError: Java heap space") == metrics.failure_kind("ExecutorLostFailure: exited with code 137") == "memory" and metrics.failure_kind("no such column") is None
