"""Approximate nearest neighbours: a hash-prefix forest.

Each tree keeps the rows' long hash strings (64 signs of random projections) as a sorted array. A
query descends each tree to its longest matching prefix, then all trees ascend together, one
level at a time, until the other rows that share a prefix of that length in some tree, summed over the trees,
reach ``share`` of the others and at least ``k`` and ``FLOOR`` of them are distinct (all, where there are
fewer); these are its candidates, whose cosines are computed exactly.

The rows are dealt into blocks by a hash of their id and each block holds its own forest, so no
block grows with a group of copies; the queries go to the blocks in blocks too. The best of each
block are merged by one top-k per query.

``share`` states the work against the recall. Vectors without structure (cosines of the nearest
around 0.44, as in the test tables) need most of the rows; for clustered vectors a small
share, or ``candidates`` (an absolute number for each block), is enough.

Defined results: vectors null, empty, zero or with null or non-finite components take no part; vectors
of another length are never compared; rows that repeat an id count once (the smallest vector); ties
go to the smaller id; a query without candidates has no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rpqframe.llm.common import pick

TREES, BITS, SEED = 24, 64, 20240
BLOCK_ROWS, BLOCK_QUERIES = 8192, 2048
#: Distinct candidates in each block at least: small blocks and rare lengths are searched whole.
FLOOR = 256


def projections(dim: int, trees: int, seed: int = SEED) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, trees * BITS))


def hash_strings(x: np.ndarray, planes: np.ndarray, trees: int) -> np.ndarray:
    """(rows, trees) of 64-bit strings; their unsigned order is the order of the strings."""
    bits = (x @ planes > 0).reshape(len(x), trees, 8, 8)
    return np.ascontiguousarray(np.packbits(bits, axis=3)[..., 0]).view(">u8").astype(np.uint64)[..., 0]


class Forest:
    """Sorted arrays of hash strings, one per tree."""

    def __init__(self, x: np.ndarray, trees: int = TREES, seed: int = SEED):
        self.trees, self.planes = trees, projections(x.shape[1], trees, seed)
        h = hash_strings(x, self.planes, trees)
        self.order = np.argsort(h, axis=0, kind="stable")
        self.sorted = np.take_along_axis(h, self.order, axis=0)
        self.rows = len(x)

    def ranges(self, q: np.ndarray, level: int, tree: int) -> tuple[np.ndarray, np.ndarray]:
        """Places in the tree's array of the strings that share the first ``level`` bits."""
        if level == 0:
            return np.zeros(len(q), dtype=np.int64), np.full(len(q), self.rows)
        rest = np.uint64((1 << (BITS - level)) - 1)
        low = q & ~rest
        return np.searchsorted(self.sorted[:, tree], low), np.searchsorted(self.sorted[:, tree], low | rest, side="right")

    def longest(self, q: np.ndarray, tree: int) -> int:
        """The longest prefix that any of the queries shares with its neighbours in the array."""
        at = np.searchsorted(self.sorted[:, tree], q)
        near = np.minimum(self.sorted[np.minimum(at, self.rows - 1), tree] ^ q, self.sorted[np.maximum(at - 1, 0), tree] ^ q)
        return BITS - int(near.min()).bit_length()

    def found(self, spans: np.ndarray) -> np.ndarray:
        """The rows in one query's places of all trees."""
        mask = np.zeros(self.rows, dtype=bool)
        for t in range(self.trees):
            mask[self.order[spans[t, 0] : spans[t, 1], t]] = True
        return mask

    def candidates(self, x: np.ndarray, least: int, distinct: int = 0, own: np.ndarray | None = None):
        """For each query the row numbers of its candidates: descend, then ascend synchronously.

        ``least`` bounds the sum over the trees, ``distinct`` the different rows; both without the
        query's own row, whose number ``own`` gives (-1 if it is not among the rows).
        """
        itself = np.zeros(len(x), dtype=np.int64) if own is None else (own >= 0).astype(np.int64)
        q = hash_strings(x, self.planes, self.trees)
        level = np.zeros(len(q), dtype=np.int64)
        open_ = np.arange(len(q))
        for depth in range(max(self.longest(q[:, t], t) for t in range(self.trees)), -1, -1):
            at = np.stack([np.stack(self.ranges(q[open_, t], depth, t), axis=1) for t in range(self.trees)], axis=1)
            counts = at[:, :, 1] - at[:, :, 0] - itself[open_, None]
            done = counts.sum(axis=1) >= least
            for k in np.flatnonzero(done & (counts.max(axis=1) < distinct)):
                done[k] = self.found(at[k]).sum() - itself[open_[k]] >= distinct
            done |= depth == 0
            level[open_[done]] = depth
            open_ = open_[~done]
            if not len(open_):
                break
        spans = np.zeros((len(q), self.trees, 2), dtype=np.int64)
        for depth in np.unique(level):
            own = np.flatnonzero(level == depth)
            for t in range(self.trees):
                spans[own, t, 0], spans[own, t, 1] = self.ranges(q[own, t], int(depth), t)
        for k in range(len(q)):
            yield np.flatnonzero(self.found(spans[k]))


def _matrix(table: pa.Table, name: str) -> np.ndarray:
    col = table.column(name).combine_chunks()
    return np.asarray(col.values.to_numpy(zero_copy_only=False), dtype=np.float64)[col.offsets[0].as_py() : col.offsets[-1].as_py()].reshape(len(col), -1)


def search(vectors: DataFrame, query_filter, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 5, trees: int = TREES, share: float = 1.0, candidates: int | None = None, block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """query_id, rank, id_col, score of the k nearest found of each row for which ``query_filter(id column)`` holds."""
    src = pick(vectors, id_col, vec_col).toDF("id", "v").where("id is not null and v is not null and size(v) > 0")
    src = src.withColumn("v", F.transform("v", lambda x: x.cast("double")))
    src = src.where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0))
    rows = src.groupBy("id").agg(F.min("v").alias("v")).withColumn("dim", F.size("v"))
    queries = rows.where(query_filter(F.col("id")))
    n, nq = src.count(), src.where(query_filter(F.col("id"))).count()
    r_blocks, q_blocks = max(1, -(-n // block_rows)), max(1, -(-nq // block_queries))
    block = lambda many: F.pmod(F.xxhash64("id"), F.lit(many)).cast("int")
    all_of = lambda many: F.explode(F.sequence(F.lit(0), F.lit(many - 1)))
    left = rows.withColumn("rb", block(r_blocks)).withColumn("qb", all_of(q_blocks))
    right = queries.withColumn("qb", block(q_blocks)).withColumn("rb", all_of(r_blocks))

    def best(base: pa.Table, asked: pa.Table) -> pa.Table:
        out_q, out_i, out_s = [], [], []
        if base.num_rows and asked.num_rows:
            x, y = _matrix(base, "v"), _matrix(asked, "v")
            ids, qids = base.column("id").to_numpy(), asked.column("id").to_numpy()
            norms = np.sqrt((x * x).sum(axis=1))
            forest = Forest(x, trees)
            row_of = {i: n for n, i in enumerate(ids.tolist())}
            own = np.array([row_of.get(i, -1) for i in qids.tolist()])
            least = candidates or int(np.ceil(share * len(x)))
            for qid, q, found in zip(qids, y, forest.candidates(y, least, max(k, FLOOR) if candidates is None else k, own)):
                found = found[ids[found] != qid]
                s = (x[found] * q).sum(axis=1) / (norms[found] * np.sqrt((q * q).sum()))
                top = np.lexsort((ids[found], -s))[:k] if len(s) <= 4 * k else _top(s, ids[found], k)
                out_q += [int(qid)] * len(top)
                out_i += ids[found][top].tolist()
                out_s += s[top].tolist()
        return pa.table({"query_id": pa.array(out_q, pa.int64()), id_col: pa.array(out_i, pa.int64()), "score": pa.array(out_s, pa.float64())})

    keys = ["dim", "rb", "qb"]
    found = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(best, f"query_id bigint, `{id_col}` bigint, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), id_col))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", id_col, "score")


def _top(s: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    least = np.partition(s, len(s) - k)[len(s) - k]
    near = np.flatnonzero(s >= least)
    return near[np.lexsort((ids[near], -s[near]))[:k]]
