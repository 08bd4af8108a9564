"""Recursive join: the least fixpoint of extending paths by base paths.

Set-at-a-time and semi-naive: each level joins only the newest paths with the base. Levels are
chunks of one parquet folder in the shared folder, so lineage stays short, a lost executor costs one
level and the answer is one scan; the driver sees counters only, which the write itself observes.

What moves is decided by measured bytes. A small base is broadcast. A large one is written once in
buckets of its first node: a small frontier is broadcast to it and prunes its buckets, a large
frontier is shuffled to the buckets, and the base itself never moves again. A frontier of a few paths
over a small base goes many levels ahead in one task, so that a long thin chain is not one job a level.
A recursion of unambiguous steps over a small base that has written ``STREAM_BYTES`` writes no further level: its last
level is dealt out and tasks make what follows when the answer is read.
"""

from __future__ import annotations

import atexit
import re
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from rpqframe.functions.paths import PATH_COLUMNS, PATH_SCHEMA, concat_paths, distinct_paths
from rpqframe.functions.restrictors import ACYCLIC, SIMPLE, TRAIL, WALK, extends, restrict
from rpqframe.operators import local

#: Bytes of path rows that may be broadcast, as measured when they were written.
BROADCAST_BYTES = 32 << 20
#: Edges of one label that may be broadcast (a path row of one edge takes about 100 bytes).
BROADCAST_ROWS = 200_000
#: Rows of one level; beyond it the recursion raises, it never truncates.
MAX_LEVEL_ROWS = 2_000_000_000
MAX_LEVELS = 10_000
#: A frontier of at most so many paths goes ahead in one task, which makes at most so many rows at a time.
LOCAL_FRONTIER, LOCAL_ROWS = 1_000, 50_000
#: Bytes of written path rows beyond which the rest of a recursion over a small base is not written: tasks make it when it is read.
STREAM_BYTES = 64 << 20
#: Lengths of one level that its write can count; a wider range is counted by a job of its own.
COUNTED_LENGTHS = 48
#: Distinct last nodes of a frontier that prune the buckets of a large base.
PRUNING_NODES = 1_000


class RecursionExplosion(RuntimeError):
    """A level outgrew its guard, a chain outgrew the number of levels, or a walk has no bound."""


class QueryTimeout(RuntimeError):
    pass


@dataclass
class Trace:
    """Counters of one evaluation: rows, bytes and longest path of each level or block."""

    levels: list[dict] = field(default_factory=list)
    deadline: float | None = None

    def add(self, op: str, rows: int, longest: int | None, size: int = 0) -> None:
        self.levels.append({"op": op, "level": sum(x["op"] == op for x in self.levels), "rows": rows, "longest": longest or 0, "bytes": size})

    def check(self) -> None:
        if self.deadline is not None and time.monotonic() > self.deadline:
            raise QueryTimeout("the query exceeded its time limit")


_MADE: dict[str, SparkSession] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints.

    Where it is unset, local mode takes a folder of its own; a cluster has none that all executors see, so it must name one.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", "") or sc.getConf().get("spark.checkpoint.dir", "")
        if not named and not re.match(r"local(\[|$)", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="rpqframe-checkpoint-"))
    return sc.getCheckpointDir()


def new_folder(spark: SparkSession, kind: str) -> str:
    path = f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"
    _MADE[path] = spark
    return path


def drop_folder(path: str) -> None:
    spark = _MADE.pop(path, None)
    if spark is not None:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def release() -> None:
    """Delete all folders that evaluations of this process wrote; frames that read them are invalid afterwards."""
    for path in list(_MADE):
        try:
            drop_folder(path)
        except Exception:  # the session may have ended before
            return


def reliable(df: DataFrame) -> DataFrame:
    """Write the rows to the shared folder and read them back.

    Lineage ends here, and so do the constraints and estimates of the plan, which would grow with
    every level; the files' size decides later joins instead.
    """
    path = new_folder(df.sparkSession, "rows")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def counted(df: DataFrame) -> tuple[DataFrame, int]:
    """The materialised rows and their number, which the write observes."""
    seen = Observation()
    out = reliable(df.observe(seen, F.count(F.lit(1)).alias("n")))
    return out, seen.get["n"]


def _lengths(df: DataFrame) -> dict[int, int]:
    return {r["len"]: r["count"] for r in df.groupBy("len").count().collect()}


def row_bytes(sizes: dict[int, int]) -> int:
    """Bytes of path rows by their lengths."""
    return sum(n * (72 + 16 * k) for k, n in sizes.items())


class Store:
    """Path rows of one evaluation in chunks of one folder; a chunk holds one or more whole levels."""

    SCHEMA = f"{PATH_SCHEMA}, level int"

    def __init__(self, spark: SparkSession, kind: str = "paths"):
        self.spark, self.root, self.chunks = spark, new_folder(spark, kind), 0

    def put(self, df: DataFrame, level: int | None = None, lengths: tuple[int, int] | None = None) -> tuple[DataFrame, dict[int, int]]:
        """Write a chunk; its rows and the number of them by length. ``level`` None: the rows have a level column."""
        df = df if level is None else df.select(*PATH_COLUMNS, F.lit(level).alias("level"))
        seen = None
        if lengths is not None and lengths[1] - lengths[0] < COUNTED_LENGTHS:
            seen = Observation()
            df = df.observe(seen, *[F.count(F.when(F.col("len") == k, 1)).alias(f"n{k}") for k in range(lengths[0], lengths[1] + 1)])
        path = f"{self.root}/chunk={self.chunks}"
        self.chunks += 1
        df.write.parquet(path)
        rows = self.spark.read.schema(self.SCHEMA).parquet(path).where("level >= 0")
        if seen is None:
            return rows, _lengths(rows)
        return rows, {k: n for k in range(lengths[0], lengths[1] + 1) if (n := seen.get[f"n{k}"])}

    def rows(self) -> DataFrame:
        return self.spark.read.schema(f"{self.SCHEMA}, chunk int").parquet(self.root).where("level >= 0").select(*PATH_COLUMNS)


def join_paths(a: DataFrame, b: DataFrame, tau: str, small_b: bool = False, small_a: bool = False) -> DataFrame:
    """Concatenations of linkable pairs that satisfy the restrictor, of paths that do so themselves.

    An equi-join with a residual test of what the concatenation adds.
    """
    left = (F.broadcast(a) if small_a and not small_b else a).alias("a")
    right = (F.broadcast(b) if small_b else b).alias("b")
    return left.join(right, (F.col("a.dst") == F.col("b.src")) & extends(tau)).select(*concat_paths())


class _Base:
    """The base of one recursion, laid out once by its size."""

    def __init__(self, rows: DataFrame, sizes: dict[int, int], store: Store):
        self.rows, self.n, self.sizes = rows, sum(sizes.values()), sizes
        self.small = row_bytes(sizes) <= BROADCAST_BYTES
        self.table = None
        if not self.small:
            spark = rows.sparkSession
            buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-row_bytes(sizes) // (128 << 20)))
            self.table = f"rpq_base_{uuid.uuid4().hex}"
            self.folder = new_folder(spark, "base")
            rows.select(*PATH_COLUMNS).repartition(buckets, "src").write.bucketBy(buckets, "src").sortBy("src").option("path", self.folder).saveAsTable(self.table)
            self.rows = spark.table(self.table)

    def extend(self, delta: DataFrame, n: int, size: int, tau: str) -> DataFrame:
        if self.small:
            return join_paths(delta, self.rows, tau, small_b=True)
        if size > BROADCAST_BYTES:
            return join_paths(delta, self.rows, tau)
        rows = self.rows
        if n <= PRUNING_NODES:
            rows = rows.where(F.col("src").isin([r[0] for r in delta.select("dst").distinct().collect()]))
        return join_paths(delta, rows, tau, small_a=True)

    def drop(self) -> None:
        if self.table is not None:
            self.rows.sparkSession.sql(f"DROP TABLE IF EXISTS {self.table}")
            drop_folder(self.folder)


def recursive_join(
    base: DataFrame,
    tau: str,
    *,
    start: DataFrame | None = None,
    seed: Callable[[DataFrame], DataFrame] | None = None,
    dedupe: bool = True,
    strategy: str = "linear",
    max_len: int | None = None,
    limit: int | None = None,
    post: Callable[[DataFrame], DataFrame] | None = None,
    post_min_len: int = 0,
    trace: Trace | None = None,
    max_level_rows: int = MAX_LEVEL_ROWS,
    base_lengths: tuple[int, int] | None = None,
) -> DataFrame:
    """All paths of one or more base paths, or of a start path and any number of base paths.

    ``seed`` filters the first level; it reads the materialised base, so nothing is made twice.
    ``dedupe``: drop paths found before (a set); without it one row for each derivation, which is the
    same when every path has one derivation. ``post`` is what stands above (selections and joins);
    with ``limit`` it is applied to every chunk, and levels stop once that many accepted paths are shorter
    than anything later can be. Lengths of ``post`` are those of the whole path; it adds ``post_min_len`` at least.
    ``base_lengths`` bounds the lengths of base paths where they are known.
    """
    trace = trace or Trace()
    spark = base.sparkSession
    plain = start is None and limit is None and max_len is None and seed is None
    if strategy == "sql":
        if start is not None or seed is not None:
            raise ValueError("the SQL strategy takes no start and no seed")
        found = _sql(base, tau, dedupe, max_len, limit)
        return found if post is None else post(found)
    if strategy == "doubling" and plain:
        found = _doubling(base, tau, dedupe, trace, max_level_rows)
        return found if post is None else post(found)
    if tau == WALK and max_len is None and limit is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len or a limit")
    unique = distinct_paths if dedupe else (lambda d: d)
    bound = (lambda d: d) if max_len is None else (lambda d: d.where(F.col("len") <= max_len))
    store = Store(spark)
    # without a seed or a start the base is the first level itself
    whole = start is None and seed is None
    scratch = store if whole else Store(spark, "base")
    every, sizes = scratch.put(unique(bound(base.where(restrict(tau)))), 0, base_lengths)
    steps = every.where("len > 0") if 0 in sizes else every  # paths of length 0 extend nothing
    own = {k: n for k, n in sizes.items() if k}
    layout = _Base(steps, own, scratch)
    m, most = min(own, default=0), max(own, default=0)
    accepted: dict[int, int] = {}
    kept = Store(spark, "accepted") if post is not None and limit is not None else None

    def emit(part: DataFrame, found: dict[int, int]) -> None:
        if kept is not None:
            _, found = kept.put(post(part.select(*PATH_COLUMNS)), 0)
        for k, n in found.items():
            accepted[k] = accepted.get(k, 0) + n

    def level_of(chunk: DataFrame, k: int) -> DataFrame:
        return chunk.where(F.col("level") == k).select(*PATH_COLUMNS)

    level, more, by_level = 0, True, None
    if whole:
        first = every
    elif start is not None:
        first, sizes = store.put(unique(bound(start.where(restrict(tau)))), 0)
    elif layout.small and not dedupe:  # the first level is a part of a small base: one task may have it and go on
        first, by_level, more = _ahead(seed(every.select(*PATH_COLUMNS)), layout.rows, tau, max_len, -1, store, trace, limit)
        sizes = _total(by_level)
    else:
        first, sizes = store.put(seed(every.select(*PATH_COLUMNS)), 0, (min(sizes, default=0), max(sizes, default=0)))
    emit(first, sizes)
    if by_level is not None:
        sizes = by_level.get(0, {})
    if start is None:
        sizes = {k: n for k, n in sizes.items() if k}
        first = first.where("len > 0")
    first_low = min(sizes, default=0)
    delta = first.select(*PATH_COLUMNS)
    if by_level:
        for k in range(max(by_level)):
            trace.add("recursion", sum(by_level[k].values()), max(by_level[k]), row_bytes(by_level[k]))
        level = max(by_level)
        sizes = {k: n for k, n in by_level[level].items() if k}
        delta = level_of(first, level)
        if not more:
            trace.add("recursion", sum(sizes.values()), max(sizes, default=0), row_bytes(sizes))
            sizes = {}
    past: list[tuple[DataFrame, int]] = []
    rest: DataFrame | None = None
    written = 0
    tried = -1  # the level at which going ahead was too much
    while sizes:
        trace.check()
        n, low, high, size = sum(sizes.values()), min(sizes), max(sizes), row_bytes(sizes)
        trace.add("recursion", n, high, size)
        if n > max_level_rows:
            raise RecursionExplosion(f"level {level} has {n} paths; levels so far: {[x['rows'] for x in trace.levels]}")
        if limit is not None and sum(v for k, v in accepted.items() if k < first_low + (level + 1) * m + post_min_len) >= limit:
            break  # no later path is shorter
        if not layout.n or max_len is not None and low + m > max_len:
            break
        if level >= MAX_LEVELS:
            raise RecursionExplosion(f"paths go on after {level} levels")
        written += size
        if layout.small and not dedupe and limit is None and written > STREAM_BYTES:
            rest = local.extensions(delta, layout.rows, tau, max_len, MAX_LEVELS - level)
            break
        if layout.small and not dedupe and n <= LOCAL_FRONTIER and tried != level:
            chunk, by_level, more = _ahead(delta, layout.rows, tau, max_len, level, store, trace, limit)
            if by_level:
                emit(chunk, _total(by_level))
                last = max(by_level)
                written += sum(row_bytes(by_level[k]) for k in range(level + 1, last))
                for k in range(level + 1, last):
                    trace.add("recursion", sum(by_level[k].values()), max(by_level[k]), row_bytes(by_level[k]))
                level, sizes = last, by_level[last]
                delta = level_of(chunk, last)
                if not more:
                    trace.add("recursion", sum(sizes.values()), max(sizes), row_bytes(sizes))
                    break
                continue
            if not more:
                break
            tried = level
        nxt = unique(bound(layout.extend(delta, n, size, tau)))
        if dedupe:
            past.append((delta, high))
            for old, old_high in past:  # levels whose lengths can coincide
                if old_high >= low + m:
                    nxt = nxt.join(old.select("src", "edges"), ["src", "edges"], "left_anti").select(*PATH_COLUMNS)
        level += 1
        chunk, sizes = store.put(nxt, level, (low + m, high + most if max_len is None else min(high + most, max_len)))
        delta = chunk.select(*PATH_COLUMNS)
        emit(chunk, sizes)
    layout.drop()
    if scratch is not store:
        drop_folder(scratch.root)
    if kept is not None:
        drop_folder(store.root)
        return kept.rows()
    found = store.rows() if rest is None else store.rows().unionByName(rest)
    return found if post is None else post(found)


def _total(by_level: dict[int, dict[int, int]]) -> dict[int, int]:
    """Paths by length over all levels."""
    out: dict[int, int] = {}
    for sizes in by_level.values():
        for k, n in sizes.items():
            out[k] = out.get(k, 0) + n
    return out


def _ahead(delta: DataFrame, base: DataFrame, tau: str, max_len: int | None, level: int, store: Store, trace: Trace, limit: int | None) -> tuple[DataFrame, dict[int, dict[int, int]], bool]:
    """Whole next levels of a small frontier over a small base, made by one task; their sizes; whether more may follow.

    A level that would make too many rows is left out; a row of level -1 says so. Before level 0 the frontier
    itself is the first level. Under a limit a task makes a few times what is asked, and the next one twice that.
    """
    end = None if trace.deadline is None else trace.deadline - time.monotonic()
    most = LOCAL_ROWS if limit is None else min(LOCAL_ROWS, max(2_000, 2 * limit) << min(store.chunks, 16))

    def run(frontier: pa.Table, steps: pa.Table) -> pa.Table:
        return expand(frontier, steps, tau, max_len, level, end, most)

    # the frontier can be a part of the base: new names tell their columns apart
    one = lambda d: d.select(*PATH_COLUMNS, F.lit(0).alias("one")).toDF(*PATH_COLUMNS, "one").groupBy("one")
    made = one(delta).cogroup(one(base)).applyInArrow(run, Store.SCHEMA)
    path = f"{store.root}/chunk={store.chunks}"
    store.chunks += 1
    made.write.parquet(path)
    every = store.spark.read.schema(Store.SCHEMA).parquet(path)
    sizes: dict[int, dict[int, int]] = {}
    for r in every.groupBy("level", "len").count().collect():
        sizes.setdefault(r["level"], {})[r["len"]] = r["count"]
    more = sizes.pop(-1, None) is not None
    return every.where("level >= 0"), sizes, more


def _lists(t: pa.Table, name: str):
    col = t.column(name).combine_chunks()
    if isinstance(col, pa.ChunkedArray):  # no rows
        col = pa.concat_arrays(col.chunks) if col.num_chunks else pa.array([], t.schema.field(name).type)
    at, flat = col.offsets.to_numpy(), col.values.to_numpy(zero_copy_only=False)
    return lambda i: flat[at[i] : at[i + 1]].tolist()


def expand(frontier: pa.Table, steps: pa.Table, tau: str, max_len: int | None, level: int, seconds: float | None, most: int = LOCAL_ROWS) -> pa.Table:
    """The levels after a frontier, breadth first, until they end or hold ``most`` rows or the time is over."""
    first = steps.column("src").to_numpy()
    order = np.argsort(first, kind="stable")
    first = first[order]
    nodes_of, edges_of = _lists(steps, "nodes"), _lists(steps, "edges")
    cache: dict[int, list[tuple[list[int], list[int]]]] = {}

    def follow(at: int) -> list[tuple[list[int], list[int]]]:
        if at not in cache:
            lo, hi = np.searchsorted(first, at), np.searchsorted(first, at, side="right")
            cache[at] = [(nodes_of(i)[1:], edges_of(i)) for i in order[lo:hi].tolist()]
        return cache[at]

    f_nodes, f_edges = _lists(frontier, "nodes"), _lists(frontier, "edges")
    rows = [(f_nodes(i), f_edges(i)) for i in range(frontier.num_rows)]
    out: list[tuple[int, list[int], list[int]]] = []
    begin, more, work = time.monotonic(), False, 0
    if level < 0:
        level = 0
        out = [(0, *r) for r in rows]
        rows = [r for r in rows if r[1]]  # paths of length 0 extend nothing
    while rows:
        nxt: list[tuple[list[int], list[int]]] = []
        for nodes, edges in rows:
            used = set(edges) if tau == TRAIL else set(nodes) if tau == ACYCLIC else None
            if tau == SIMPLE and edges and nodes[0] == nodes[-1]:
                continue  # a closed simple path goes nowhere
            for tail, more_edges in follow(nodes[-1]):
                if max_len is not None and len(edges) + len(more_edges) > max_len:
                    continue
                if tau == TRAIL and not used.isdisjoint(more_edges) or tau == ACYCLIC and not used.isdisjoint(tail):
                    continue
                path = nodes + tail
                if tau == SIMPLE and (len(set(path[:-1])) < len(path) - 1 or len(set(path[1:])) < len(path) - 1):
                    continue
                nxt.append((path, edges + more_edges))
                work += len(path)
            if len(out) + len(nxt) > most or work > 100 * most or seconds is not None and time.monotonic() - begin > seconds:
                more = True
                break
        if more or not nxt:
            break
        level += 1
        out += [(level, *r) for r in nxt]
        rows = nxt
    ints = pa.list_(pa.int64())
    table = {
        "src": pa.array([r[1][0] for r in out], pa.int64()), "dst": pa.array([r[1][-1] for r in out], pa.int64()), "len": pa.array([len(r[2]) for r in out], pa.int32()),
        "nodes": pa.array([r[1] for r in out], ints), "edges": pa.array([r[2] for r in out], ints), "level": pa.array([r[0] for r in out], pa.int32()),
    }
    made = pa.table(table)
    if more:
        none = {"src": [None], "dst": [None], "len": [None], "nodes": [None], "edges": [None], "level": [-1]}
        made = pa.concat_tables([made, pa.table({k: pa.array(v, made.schema.field(k).type) for k, v in none.items()})])
    return made


def _doubling(base: DataFrame, tau: str, dedupe: bool, trace: Trace, max_level_rows: int) -> DataFrame:
    """Rounds that double the number of base steps; logarithmic in the longest path.

    Keeps the paths of exactly 2^r base steps and those of fewer; sound because parts of valid paths are
    valid. Every round copies the node and edge lists, so bytes grow with the square of the length.
    """
    if tau == WALK:
        raise RecursionExplosion("walks through a cycle never end: give max_len or a limit")
    spark, unique = base.sparkSession, distinct_paths if dedupe else (lambda d: d)
    base = base.where(restrict(tau))
    zero = base.where("len = 0")
    rounds = Store(spark)
    exact, sizes = rounds.put(unique(base.where("len > 0")), 0)
    steps, small = exact.select(*PATH_COLUMNS), row_bytes(sizes) <= BROADCAST_BYTES
    fewer, n_fewer, written = None, 0, 0
    while sizes:
        trace.check()
        n, exact = sum(sizes.values()), exact.select(*PATH_COLUMNS)
        trace.add("recursion", n, max(sizes), row_bytes(sizes))
        written += row_bytes(sizes)
        if small and not dedupe and written > STREAM_BYTES:
            grown = exact if fewer is None else fewer.unionByName(exact)
            return zero.unionByName(grown).unionByName(local.extensions(exact, steps, tau, None, MAX_LEVELS))
        if n + n_fewer > max_level_rows:
            raise RecursionExplosion(f"{n + n_fewer} paths after {len(trace.levels)} rounds")
        grown = exact if fewer is None else fewer.unionByName(exact).unionByName(join_paths(exact, fewer, tau))
        nxt = join_paths(exact, exact, tau, row_bytes(sizes) <= BROADCAST_BYTES)
        if fewer is not None or dedupe:
            grown, n_fewer = counted(unique(grown))
        else:
            n_fewer = n
        fewer = grown
        low, high = min(sizes), max(sizes)
        exact, sizes = rounds.put(unique(nxt), 0, (2 * low, 2 * high))
    result = zero if fewer is None else zero.unionByName(fewer)
    return unique(result)


def _sql(base: DataFrame, tau: str, dedupe: bool, max_len: int | None, limit: int | None) -> DataFrame:
    """The recursion as one recursive query of Spark SQL.

    It has no duplicate removal between levels, so the expression must be unambiguous, and the
    session's ``spark.sql.cteRecursionRowLimit`` bounds its rows: beyond it the query fails.
    """
    if dedupe:
        raise ValueError("the SQL strategy needs an unambiguous expression")
    if tau == WALK and max_len is None:
        raise RecursionExplosion("walks through a cycle never end: give max_len")
    spark, view = base.sparkSession, f"rpq_{uuid.uuid4().hex}"
    reliable(base.where(restrict(tau)).select(*PATH_COLUMNS)).createOrReplaceTempView(view)
    tail = "slice(b.nodes, 2, b.len)"
    both = f"concat(r.nodes, {tail})"
    test = {
        WALK: "true",
        TRAIL: "NOT arrays_overlap(r.edges, b.edges)",
        ACYCLIC: f"NOT arrays_overlap(r.nodes, {tail})",
        SIMPLE: f"size(array_distinct(slice({both}, 1, r.len + b.len))) = r.len + b.len AND size(array_distinct({tail})) + size(array_distinct(slice(r.nodes, 2, r.len))) = r.len + b.len AND NOT arrays_overlap(slice(r.nodes, 2, r.len), {tail})",
    }[tau]
    within = "true" if max_len is None else f"r.len + b.len <= {max_len}"
    first = "true" if max_len is None else f"len <= {max_len}"
    return spark.sql(f"""
        WITH RECURSIVE r(src, dst, len, nodes, edges) MAX RECURSION LEVEL {MAX_LEVELS} AS (
            SELECT src, dst, len, nodes, edges FROM {view} WHERE {first}
            UNION ALL
            SELECT r.src, b.dst, r.len + b.len, {both}, concat(r.edges, b.edges)
            FROM r JOIN {view} AS b ON r.dst = b.src WHERE b.len > 0 AND r.len > 0 AND {test} AND {within})
        SELECT * FROM r""")


__all__ = ["PATH_SCHEMA", "QueryTimeout", "RecursionExplosion", "Store", "Trace", "counted", "join_paths", "recursive_join", "release", "reliable", "shared_folder"]
