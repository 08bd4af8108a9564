"""SimHash near-duplicate detection with multi-index hashing.

Texts are compared with A-Z lower-cased and split at ASCII blanks. A 64-bit fingerprint is cut into
``segments`` segments, and each segment has a table of fingerprints by its value. Fingerprints within
``distance`` bits differ in at most distance // segments bits of some segment, so each fingerprint enumerates
the Hamming ball of that radius around each of its segment values, fetches what the tables hold
there, and keeps what lies within the distance on all 64 bits. With radius one a ball needs only
the value and those that lack one of its set bits, as the other of two neighbours finds the pair.

A value that more than ``FULL`` fingerprints share is over-full: its entries are split further by the value of
one of distance + 1 pieces of the remaining bits, of which at least one is equal for every pair sought. Only
different fingerprints meet, so copies cost nothing, and a fingerprint has a bounded number of others
within the distance.

Defined results: a null or empty text has fingerprint zero and links like any other; rows
repeated in the input are repeated in the result; a null id never becomes a component's id
(a component of null ids only has a null id); an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import checkpoint, fresh, join_dealt, pick, text_slices
from rpqframe.llm.components import connected_components

SEED = 42
BITS = 64
CHUNK = 1 << 16
#: Fingerprints of one segment value beyond which its entries are split.
FULL = 256
#: Over-full values that may be broadcast (16 bytes each).
BROADCAST_KEYS = 1_000_000


def shingle_hashes(words: list[bytes], size: int, digest=xxhash.xxh64_intdigest) -> list[int]:
    if not words:
        return []
    if len(words) <= size:
        return [digest(b" ".join(words), SEED)]
    ends = list(accumulate(map(len, words), lambda a, n: a + 1 + n))
    starts = [0, *[e + 1 for e in ends[:-1]]]
    joined = b" ".join(words)
    return [digest(joined[s:e], SEED) for s, e in zip(starts, ends[size - 1 :])]


def fingerprint(raw: bytes | None, size: int = 3) -> int:
    """Unsigned fingerprint: a bit is set if it is set in over half of the shingle hashes."""
    return fingerprint_of(shingle_hashes((raw or b"").lower().split(), size))


def fingerprint_of(hashes: list[int]) -> int:
    if not hashes:
        return 0
    counts = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(hashes), CHUNK):
        part = np.array(hashes[at : at + CHUNK], dtype=">u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3) -> DataFrame:
    """One row per input row: id_col, fp (the fingerprint as a signed 64-bit integer)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in text_slices(batch):
                fps = np.array([fingerprint(t, size) for t in texts], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(fps)], names=["id", "fp"])

    src = pick(docs, id_col, text_col).toDF("id", "text")
    id_type = src.schema["id"].dataType.simpleString()
    return src.mapInArrow(run, f"id {id_type}, fp bigint").withColumnRenamed("id", id_col)


def _bits(fp: Column, start: int, width: int) -> Column:
    return F.shiftrightunsigned(fp, start).bitwiseAND(F.lit((1 << width) - 1))


def _cut(start: int, width: int, parts: int) -> list[tuple[int, int]]:
    """Start and width of each of the parts of a run of bits."""
    ends = [start + width * k // parts for k in range(parts + 1)]
    return [(a, b - a) for a, b in zip(ends, ends[1:])]


def _pieces(fp: Column, key: Column, segments: list[tuple[int, int]], parts: int) -> Column:
    """For an over-full value of a segment: the keys of the pieces of the bits outside it."""
    out = []
    for k, (start, width) in enumerate(segments):
        rest = F.shiftleft(F.shiftrightunsigned(fp, start + width), start).bitwiseOR(_bits(fp, 0, start)) if start + width < BITS else _bits(fp, 0, start)
        own = [F.struct(F.lit(j).alias("j"), _bits(rest, a, w).alias("v")) for j, (a, w) in enumerate(_cut(0, BITS - width, parts))]
        out.append(F.when(F.shiftrightunsigned(key, 56) == k, F.array(*own)))
    return F.coalesce(*out)


def links(distinct_fp: DataFrame, distance: int = 2, segments: int = 2, full: int = FULL) -> DataFrame:
    """All pairs (a, b), a < b, of the fingerprints of the one column fp that differ in at most ``distance`` bits."""
    cut, radius = _cut(0, BITS, segments), distance // segments
    if segments < 2 or max(w for _, w in cut) > 56:
        raise ValueError("a segment has at most 56 bits")
    fp = F.col("fp")
    tag = lambda k: k << 56
    entries, probes = [], []
    for k, (start, width) in enumerate(cut):
        value = _bits(fp, start, width)
        entries.append(value + F.lit(tag(k)))
        masks = [sum(1 << i for i in c) for r in range(1, radius + 1) for c in combinations(range(width), r)]
        ball = F.transform(F.array(*[F.lit(m).cast("bigint") for m in masks]), lambda m: value.bitwiseXOR(m)) if masks else F.array().cast("array<bigint>")  # noqa: B023
        if radius == 1:
            ball = F.filter(ball, lambda v: v < value)  # noqa: B023
        probes.append(F.transform(F.concat(F.array(value), ball), lambda v: v + F.lit(tag(k))))  # noqa: B023
    # even tasks whatever the input's partitions: a fingerprint makes some thirty probes
    prints = distinct_fp.repartition(int(distinct_fp.sparkSession.conf.get("spark.sql.shuffle.partitions")), "fp")
    table = prints.select("fp", F.explode(F.array(*entries)).alias("key"))
    probe = prints.select("fp", F.explode(F.concat(*probes)).alias("key"))
    over = checkpoint(table.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > full).select("key"))
    n_over = over.count()
    found = lambda p, t, on: p.join(t.withColumnRenamed("fp", "other"), on).where((F.col("fp") != F.col("other")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("other"))) <= distance)).select("fp", "other")
    if not n_over:
        pairs = found(probe, table, ["key"])
    else:
        few = F.broadcast(over) if n_over <= BROADCAST_KEYS else over
        parted = lambda d: d.join(few, "key", "left_semi").select("fp", "key", F.explode(_pieces(fp, F.col("key"), cut, distance + 1)).alias("x")).select("fp", "key", "x.j", "x.v")
        pairs = found(probe.join(few, "key", "left_anti"), table.join(few, "key", "left_anti"), ["key"]).union(found(parted(probe), parted(table), ["key", "j", "v"]))
    return pairs.select(F.least("fp", "other").alias("a"), F.greatest("fp", "other").alias("b")).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, distance: int = 2) -> DataFrame:
    """id_col, fingerprint (16 hex digits), component_id (smallest id reachable), one row per input row."""
    fps = checkpoint(fingerprints(docs, id_col, text_col, size))
    firsts = checkpoint(fps.groupBy("fp").agg(F.min(id_col).alias("first_id"), F.count("*").alias("n")))
    comps = connected_components(links(firsts.select("fp"), distance))
    labelled = firsts.join(comps.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    named = labelled.groupBy("component").agg(F.min("first_id").alias("component_id"))
    by_fp = labelled.join(named, "component").select("fp", "n", "component_id")
    return join_dealt(fps, by_fp, ["fp"], "n", fps.count()).select(
        id_col, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, distance: int = 2) -> DataFrame:
    """The documents without near copies: the smallest id of each component stays.

    Rows with a null id and exact repeats of a kept id stay as they are: they cannot be told apart.
    """
    near = near_duplicates(docs, id_col, text_col, size, distance)
    name = fresh("gone", docs)
    gone = near.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias(name)).distinct()
    return docs.join(gone, docs[f"`{id_col}`"] == gone[name], "left_anti")
