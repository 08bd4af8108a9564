"""Aggregation and set operations over path rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rpqframe.functions.paths import PATH_COLUMNS, paths1
from rpqframe.functions.restrictors import WALK, restrict
from rpqframe.operators import local
from rpqframe.operators.fixpoint import BROADCAST_BYTES, Store, Trace, join_paths, row_bytes


def path_stats(paths: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Count, lengths and distinct ends of paths, by columns."""
    return paths.groupBy(*(by or [])).agg(
        F.count("*").alias("n_paths"), F.min("len").alias("min_len"), F.max("len").alias("max_len"), F.sum("len").alias("sum_len"), F.countDistinct("src").alias("n_sources"), F.countDistinct("dst").alias("n_targets")
    )


def length_rollup(paths: DataFrame, *by: str) -> DataFrame:
    """Counts by the given columns and length, with all subtotals."""
    return paths.rollup(*by, "len").agg(F.count("*").alias("n_paths"))


def length_cube(paths: DataFrame, *by: str) -> DataFrame:
    return paths.cube(*by, "len").agg(F.count("*").alias("n_paths"))


def endpoint_pairs(paths: DataFrame) -> DataFrame:
    return paths.select("src", "dst").distinct()


def shortest_per_pair(paths: DataFrame, all_ties: bool = False) -> DataFrame:
    """The shortest path of each pair of ends: one, or all of that length."""
    if not all_ties:  # one row per pair: a partial aggregation, no sort
        best = paths.groupBy("src", "dst").agg(F.min(F.struct("len", "nodes", "edges")).alias("p"))
        return best.select("src", "dst", "p.len", "p.nodes", "p.edges")
    rank = F.rank().over(Window.partitionBy("src", "dst").orderBy("len"))
    return paths.withColumn("__r", rank).where("__r = 1").select(*PATH_COLUMNS)


def shortest_paths(edges: DataFrame, closed: bool = True, all_ties: bool = False, trace: Trace | None = None) -> DataFrame:
    """The shortest path over some edges of each pair of nodes that has one: the first by (nodes, edges), or all of that length.

    Few edges are sent to all tasks, each of which searches breadth first from its own sources and stores nothing. More of
    them go level by level; a pair that is reached goes on no more, so work is bounded by pairs, not by paths. Shortest
    paths repeat no edge and no inner node: they are those of trails and simple paths, and without ``closed`` (pairs
    of a node with itself) those of acyclic paths.
    """
    trace = trace or Trace()
    base, sizes = Store(edges.sparkSession, "base").put(paths1(edges), 0, (1, 1))
    base = base.select(*PATH_COLUMNS)
    if row_bytes(sizes) <= BROADCAST_BYTES:
        return local.shortest_local(base.select("src", "dst", F.get("edges", F.lit(0)).alias("eid")), closed, all_ties)
    store = Store(edges.sparkSession)
    keep = (lambda d: d) if closed else (lambda d: d.where("src <> dst"))
    one = (lambda d: d) if all_ties else (lambda d: d.groupBy("src", "dst").agg(F.min(F.struct("len", "nodes", "edges")).alias("p")).select("src", "dst", "p.*"))
    level, (part, found) = 1, store.put(one(keep(base)), 1, (1, 1))
    while found:
        trace.check()
        trace.add("shortest", sum(found.values()), level, row_bytes(found))
        # a closed path or a reached pair is not extended to a shorter one
        grown = join_paths(part.where("src <> dst").select(*PATH_COLUMNS), base, WALK)
        new = keep(grown).join(store.rows().select("src", "dst").distinct(), ["src", "dst"], "left_anti").select(*PATH_COLUMNS)
        level += 1
        part, found = store.put(one(new), level, (level, level))
    return store.rows()


def running_counts(paths: DataFrame) -> DataFrame:
    """Paths of each length and of at most that length."""
    per = paths.groupBy("len").agg(F.count("*").alias("n_paths"))
    return per.withColumn("n_up_to", F.sum("n_paths").over(Window.orderBy("len").rowsBetween(Window.unboundedPreceding, 0)))


def intersect_restricted(paths: DataFrame, tau: str) -> DataFrame:
    """``intersect_paths`` of a set of paths with those of them that satisfy a restrictor: no path has to meet its equal."""
    return paths.select(*PATH_COLUMNS).where(restrict(tau))


def except_restricted(paths: DataFrame, tau: str) -> DataFrame:
    """``except_paths`` of a set of paths and those of them that satisfy a restrictor."""
    return paths.select(*PATH_COLUMNS).where(~restrict(tau))


def intersect_paths(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*PATH_COLUMNS).intersectAll(b.select(*PATH_COLUMNS))


def except_paths(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*PATH_COLUMNS).exceptAll(b.select(*PATH_COLUMNS))
