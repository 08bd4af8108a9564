"""Near-duplicate removal by SimHash and exact Jaccard similarity of five-word shingles.

Texts are compared with A-Z lower-cased and split at ASCII blanks, as the fingerprints are. Two
texts link if their sets of shingles have a similarity of ``NUM / DEN`` or more; the smallest id of
each component stays. The first candidates are texts whose 64-bit fingerprints of the same shingles lie within
``DISTANCE`` bits, found by multi-index hashing (``simhash.links``): almost equal texts. No fingerprint
separates all such texts from others, so the rest
come from a prefix filter, which misses none: with the shingles of all texts in one order, similar
sets share one of their first n - ceil(t n) + 1. The order puts shingles that are common in a
sample last; the sample decides the work only, never the result.

Equal sets are one node. A node keeps its prefix and an odd sketch: the parities of its
shingles in ``BUCKETS`` buckets. Two sketches differ in no more bits than the sets differ in
shingles, so a pair whose sketches differ in more than similar sets can is dropped, and no similar one is.
Each set that shares a prefix shingle is paired with the least and the greatest set of that shingle,
found by plain aggregates, so a hot shingle is split like any other rows; of these pairs the
one of least sketch distance is verified first, with those of near fingerprints. Then only pairs whose components still differ are
compared, so a large group of near copies does not emit its square. Every link is verified
on complete sets, which are made for the texts of candidate pairs alone.

Defined results: texts without words have one empty set and link to each other; texts of fewer words
than a shingle have one shingle of all of them; rows with a null id and exact repeats of a kept id stay;
an empty table gives an empty result; extra columns are carried along.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import checkpoint, fresh, pick, text_slices
from rpqframe.llm.components import connected_components
from rpqframe.llm.simhash import fingerprint_of, links as fingerprint_links, shingle_hashes

SIZE = 5
#: Bits in which the fingerprints of a candidate pair may differ; with two segments three bits cost no more than two.
DISTANCE = 3
NUM, DEN = 4, 5
#: One text in so many is sampled for the order of shingles; of the common ones so many are kept.
SAMPLE, COMMON = 8, 100_000
#: Bits of an odd sketch.
BUCKETS = 1024
#: Ids of candidate texts that may be broadcast to the scan of the texts (8 bytes each).
BROADCAST_IDS = 2_000_000


def _hashes(raw: bytes | None, size: int) -> list[int]:
    return shingle_hashes((raw or b"").lower().split(), size)


def _grams(hashes: list[int]) -> np.ndarray:
    return np.unique(np.array(hashes, dtype=np.uint64).view(np.int64))


def _odd(g: np.ndarray) -> np.ndarray:
    """Parities of the shingles by bucket, as 64-bit integers."""
    counts = np.bincount((g.view(np.uint64) >> np.uint64(32)).astype(np.int64) % BUCKETS, minlength=BUCKETS)
    return np.packbits((counts & 1).astype(np.uint8)).view(np.int64)


def _prefix_len(n: int) -> int:
    return n - -(-NUM * n // DEN) + 1


def _sigs(sets: list[np.ndarray]) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(g.tobytes()) for g in sets], dtype=np.uint64).view(np.int64)


def _flat(parts: list[np.ndarray]) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(g) for g in parts])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64)))


def complete_sets(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """sig (a hash of the set), grams: the set of each row of id and text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in text_slices(batch):
                sets = [_grams(_hashes(raw, size)) for raw in texts]
                yield pa.RecordBatch.from_arrays([pa.array(_sigs(sets)), _flat(sets)], names=["sig", "grams"])

    return docs.mapInArrow(run, "sig bigint, grams array<bigint>")


def prints(docs: DataFrame, size: int, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """id, sig (a hash of the set), fp (the fingerprint), n, odd, prefix (the first shingles in the common order) of each row of id and text."""
    known, counts = common

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in text_slices(batch):
                hashes = [_hashes(raw, size) for raw in texts]
                fps = np.array([fingerprint_of(h) for h in hashes], dtype=np.uint64).view(np.int64)
                sets, parts = [_grams(h) for h in hashes], []
                for g in sets:
                    k = _prefix_len(len(g))
                    if len(known) and k < len(g):
                        at = np.minimum(np.searchsorted(known, g), len(known) - 1)
                        g = g[np.lexsort((g, np.where(known[at] == g, counts[at], 0)))]
                    parts.append(g[:k])
                yield pa.RecordBatch.from_arrays(
                    [rows.column(0), pa.array(_sigs(sets)), pa.array(fps), pa.array([len(g) for g in sets], pa.int32()), _flat([_odd(g) for g in sets]), _flat(parts)], names=["id", "sig", "fp", "n", "odd", "prefix"]
                )

    return docs.mapInArrow(run, f"id {docs.schema['id'].dataType.simpleString()}, sig bigint, fp bigint, n int, odd array<bigint>, prefix array<bigint>")


def common_shingles(docs: DataFrame, size: int = SIZE) -> tuple[np.ndarray, np.ndarray]:
    """The shingles that stand in more than one text of a sample, sorted, with their counts."""
    some = complete_sets(docs.where(F.pmod(F.xxhash64("text"), F.lit(SAMPLE)) == 0).dropDuplicates(["text"]), size)
    often = some.select(F.explode("grams").alias("g")).groupBy("g").agg(F.count("*").alias("c")).where("c > 1")
    rows = sorted((r.g, r.c) for r in often.orderBy(F.desc("c"), "g").limit(COMMON).collect())
    return np.array([g for g, _ in rows], dtype=np.int64), np.array([c for _, c in rows], dtype=np.int64)


def _possible(x: str, y: str) -> Column:
    """Whether sizes and sketches (columns n, odd of both) allow the similarity; false for no similar pair."""
    n, m = F.col(f"{x}.n"), F.col(f"{y}.n")
    sizes = DEN * F.least(n, m) >= NUM * F.greatest(n, m)
    return sizes & (_distance(x, y) * (NUM + DEN) <= (DEN - NUM) * (n + m))


def _distance(x: str, y: str) -> Column:
    return sum((F.bit_count(F.get(f"{x}.odd", F.lit(i)).bitwiseXOR(F.get(f"{y}.odd", F.lit(i)))) for i in range(BUCKETS // 64)), F.lit(0))


class _Links:
    """Verified links between sets, which are named by their hash."""

    def __init__(self, docs: DataFrame, rows: DataFrame, size: int):
        self.docs, self.rows, self.size = docs, rows, size
        self.nodes = checkpoint(rows.groupBy("sig").agg(F.min("id").alias("rep"), F.first("n").alias("n"), F.first("odd").alias("odd")))

    def candidates(self) -> tuple[DataFrame, DataFrame]:
        """(gram, sig) of shared prefix shingles, and pairs (a, b) of each with the ends of its shingle, if possible."""
        entries = self.rows.select("sig", F.explode("prefix").alias("gram"))
        ends = entries.groupBy("gram").agg(F.min("sig").alias("lo"), F.max("sig").alias("hi")).where("lo <> hi")
        shared = checkpoint(entries.join(ends, "gram").dropDuplicates(["gram", "sig"]))
        pair = lambda e: F.struct(F.least("sig", e).alias("a"), F.greatest("sig", e).alias("b"))
        pairs = shared.select(F.explode(F.array(pair("lo"), pair("hi"))).alias("p")).select("p.*").where("a <> b").distinct()
        return shared.select("gram", "sig"), pairs

    def near_prints(self) -> DataFrame:
        """Pairs (a, b) of sets whose fingerprints lie within ``DISTANCE`` bits: each with the least set of its fingerprint, and these of near fingerprints."""
        own = self.rows.select("fp", "sig").distinct()
        firsts = checkpoint(own.groupBy("fp").agg(F.min("sig").alias("first")))
        end = lambda x: firsts.select(F.col("fp").alias(x), F.col("first").alias(f"_{x}"))
        near = fingerprint_links(firsts.select("fp"), DISTANCE).join(end("a"), "a").join(end("b"), "b").select("_a", "_b")
        pairs = near.union(own.join(firsts, "fp").select("first", "sig")).toDF("x", "y").where("x <> y")
        return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()

    def possible(self, pairs: DataFrame) -> DataFrame:
        """The pairs that sizes and sketches allow, with the distance of the sketches."""
        side = lambda x: self.nodes.select(F.col("sig").alias(x), F.struct("n", "odd").alias(f"_{x}"))
        both = pairs.join(side("a"), "a").join(side("b"), "b")
        return both.where(_possible("_a", "_b")).select("a", "b", _distance("_a", "_b").alias("d"))

    def verified(self, pairs: DataFrame) -> DataFrame:
        """Of the materialised pairs (a, b) those that are similar."""
        need = checkpoint(self.nodes.join(pairs.select(F.explode(F.array("a", "b")).alias("sig")).distinct(), "sig").select("sig", F.col("rep").alias("id")))
        ids = need.select("id").distinct()
        named = self.docs.where("id is not null").join(F.broadcast(ids) if need.count() <= BROADCAST_IDS else ids, "id", "left_semi")
        # an id may be null, or repeated with another text: the hash tells whose set it is
        sets = complete_sets(named.unionByName(self.docs.where("id is null")), self.size)
        # both sides read the one shuffle by sig, which serves the join by a as well
        sets = sets.join(need.select("sig"), "sig", "left_semi").dropDuplicates(["sig"]).withColumn("n", F.size("grams"))
        side = lambda x: sets.select(F.col("sig").alias(x), F.col("n").alias(f"n{x}"), F.col("grams").alias(f"g{x}"))
        both = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b").withColumn("k", F.size(F.array_intersect("ga", "gb")))
        return both.where((NUM + DEN) * F.col("k") >= NUM * (F.col("na") + F.col("nb"))).select("a", "b")


def similar_links(docs: DataFrame, rows: DataFrame, size: int = SIZE) -> DataFrame:
    """Verified links (a, b) between hashes of sets, whose transitive closure is that of all similar pairs.

    ``docs`` has id and text, ``rows`` their prints.
    """
    links = _Links(docs, rows, size)
    shared, pairs = links.candidates()
    ends = checkpoint(links.possible(pairs))
    nearest = ends.groupBy("b").agg(F.min(F.struct("d", "a")).alias("m")).select("m.a", "b")
    nearest = nearest.union(ends.groupBy("a").agg(F.min(F.struct("d", "b")).alias("m")).select("a", "m.b"))
    tried = checkpoint(nearest.union(links.possible(links.near_prints()).select("a", "b")).distinct())
    first = checkpoint(links.verified(tried))
    comps = connected_components(first)
    member = shared.join(comps.withColumnRenamed("node", "sig"), "sig", "left").withColumn("component", F.coalesce("component", "sig"))
    mixed = member.groupBy("gram").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("gram")
    member = checkpoint(member.join(mixed, "gram", "left_semi").join(links.nodes.drop("rep"), "sig"))
    u, v = member.alias("u"), member.alias("v")
    rest = u.join(v, (F.col("u.gram") == F.col("v.gram")) & (F.col("u.sig") < F.col("v.sig")) & (F.col("u.component") != F.col("v.component")) & _possible("u", "v"))
    rest = checkpoint(rest.select(F.col("u.sig").alias("a"), F.col("v.sig").alias("b")).distinct().join(tried, ["a", "b"], "left_anti"))
    return first.union(links.verified(rest))


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE) -> DataFrame:
    """id_col, component_id (smallest id reachable by similar texts), one row per input row."""
    src = pick(docs, id_col, text_col).toDF("id", "text")
    rows = checkpoint(prints(src, size, common_shingles(src, size)))
    firsts = rows.groupBy("sig").agg(F.min("id").alias("first_id"))
    comps = connected_components(similar_links(src, rows, size))
    labelled = firsts.join(comps.withColumnRenamed("node", "sig"), "sig", "left").withColumn("component", F.coalesce("component", "sig"))
    named = labelled.groupBy("component").agg(F.min("first_id").alias("component_id"))
    return rows.select("id", "sig").join(labelled.join(named, "component").select("sig", "component_id"), "sig").select(F.col("id").alias(id_col), "component_id")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE) -> DataFrame:
    """The documents without near copies: the smallest id of each component stays."""
    near, gone = near_components(docs, id_col, text_col, size), fresh("gone", docs)
    # the size of the written table decides whether the texts are shuffled
    gone_ids = checkpoint(near.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias(gone)).distinct())
    return docs.join(gone_ids, docs[f"`{id_col}`"] == gone_ids[gone], "left_anti")
