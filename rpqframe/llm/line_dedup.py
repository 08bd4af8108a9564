"""Line dedup with a deletion-neighbourhood join.

Lines are compared without outer blanks. A line is dropped if the same line stands earlier: in a
document of smaller id, or further up in the same one. So is a line of at least ``min_chars`` characters
if such a line within one edit (a character inserted, deleted or replaced) stands earlier; shorter ones
are too little to judge by edits.

Exact repeats go by hash, pre-aggregated before the shuffle. Every first occurrence then emits its deletion
neighbourhood, hashed, from coarse to fine, and only lines that share a variant with another go on:
variants that lack the front or the back half; of the lacking half, variants that lack one block of
``BLOCK`` characters; of the lacking block, variants that lack one character. An edit touches
one half, one block and one character only, and lengths of the kept parts are taken such that lines whose
lengths differ by one share a variant too. At the finest grain each line is linked to the earliest
one of each variant, and the edit distance of the lines themselves is verified. So no pairs are
emitted, a line that a third of all documents repeat is one row after map-side aggregation, and a
variant that many lines share is dealt out over several tasks.

Defined results: null and empty texts have no lines and stay; documents with a null id stay as they
are and make no others go; rows repeated in the input lose the same lines; blank lines stay; a document of which
only blank text remains after a drop has ``text`` blank; an empty table gives an empty result;
extra columns are carried along.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import checkpoint, fresh, join_dealt, pick, text_slices

MIN_CHARS = 16
BLOCK = 16


def _split(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _exact_drops(docs: DataFrame) -> DataFrame:
    """id, exact: the places of lines that stand earlier elsewhere."""
    lines = F.transform(_split(F.col("text")), lambda x, i: F.struct(i.alias("at"), F.trim(x).alias("line")))
    lines = docs.where("text is not null").select("id", F.explode(F.filter(lines, lambda x: x["line"] != "")).alias("x"))
    hashed = lines.select("id", "x.at", F.xxhash64("x.line").alias("h"), F.xxhash64(F.lit("second"), "x.line").alias("h2"))
    firsts = checkpoint(hashed.groupBy("h", "h2").agg(F.min(F.struct("id", "at")).alias("first"), F.count("*").alias("n")).where("n > 1"))
    total = firsts.agg(F.sum("n")).first()[0] or 0
    late = join_dealt(hashed, firsts, ["h", "h2"], "n", total).where(F.struct("id", "at") > F.col("first"))
    return late.groupBy("id").agg(F.collect_set("at").alias("exact"))


def variant_keys(line: str) -> list[tuple[int, int]]:
    """(key, kept) of the variants: a signed hash, and the characters kept, negative at the line's end."""
    n, half = len(line), len(line) // 2
    kept = (half, half - 1, -half) if n % 2 == 0 else (half, -half - 1, -half)
    return [(_signed(line[:k].encode(), 1) if k >= 0 else _signed(line[k:].encode(), 2), k) for k in kept]


def _signed(raw: bytes, seed: int) -> int:
    h = xxhash.xxh64_intdigest(raw, seed)
    return h - (1 << 64) if h >> 63 else h


def _variants(marked: DataFrame, min_chars: int) -> DataFrame:
    """id, at, key, kept: the variants of all first occurrences."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, texts in text_slices(batch):
                places, numbers, keys, sizes = [], [], [], []
                for i, (raw, exact) in enumerate(zip(texts, rows.column(2).to_pylist())):
                    gone = set(exact)
                    for at, line in enumerate(raw.decode("utf-8", "replace").split("\n")):
                        line = line.strip(" ")
                        if len(line) >= min_chars and at not in gone:
                            for key, kept in variant_keys(line):
                                places.append(i)
                                numbers.append(at)
                                keys.append(key)
                                sizes.append(kept)
                ids = rows.column(0).take(pa.array(places, pa.int64()))
                yield pa.RecordBatch.from_arrays([ids, pa.array(numbers, pa.int32()), pa.array(keys, pa.int64()), pa.array(sizes, pa.int32())], names=["id", "at", "key", "kept"])

    src = marked.where("text is not null").select("id", "text", "exact")
    return src.mapInArrow(run, f"id {src.schema['id'].dataType.simpleString()}, at int, key bigint, kept int")


def _shared(keyed: DataFrame, key: str) -> DataFrame:
    """The materialised rows whose key another row has too."""
    counts = checkpoint(keyed.groupBy(key).agg(F.count("*").alias("n")).where("n > 1"))
    total = counts.agg(F.sum("n")).first()[0] or 0
    return join_dealt(keyed, counts, [key], "n", total).drop("n")


def lacking(line: str, kept: int) -> str:
    return line[kept:] if kept >= 0 else line[: len(line) + kept]


def block_keys(key: int, part: str, block: int = BLOCK) -> list[tuple[int, int, int]]:
    """(key, p, q) of the variants of a part that lack all but its first p and last q characters."""
    out = []
    for p in range(0, len(part) + 1, block):
        for q in {max(len(part) - p - block, 0), max(len(part) - p - block - 1, 0)}:
            raw = f"{key} {p} {q} {part[:p]}\0{part[len(part) - q :] if q else ''}"
            out.append((_signed(raw.encode("utf-8", "replace"), 3), p, q))
    return out


def _blocks(rows: DataFrame) -> DataFrame:
    """id, at, key, kept, p, q, key2: the block variants of lines that share a half."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, texts in text_slices(batch, "line"):
                places, found = [], []
                for i, (raw, key, kept) in enumerate(zip(texts, part.column(2).to_pylist(), part.column(3).to_pylist())):
                    own = block_keys(key, lacking(raw.decode("utf-8", "replace"), kept))
                    places += [i] * len(own)
                    found += own
                at = pa.array(places, pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [*[part.column(k).take(at) for k in range(4)], pa.array([x[1] for x in found], pa.int32()), pa.array([x[2] for x in found], pa.int32()), pa.array([x[0] for x in found], pa.int64())],
                    names=["id", "at", "key", "kept", "p", "q", "key2"],
                )

    src = rows.select("id", "at", "key", "kept", "line")
    return src.mapInArrow(run, f"id {src.schema['id'].dataType.simpleString()}, at int, key bigint, kept int, p int, q int, key2 bigint")


def _near_drops(marked: DataFrame, min_chars: int) -> DataFrame:
    """id, near: places of first occurrences that have an earlier neighbour within one edit.

    ``marked`` has doc rows: id, text, exact (the places of lines that are gone).
    """
    places = _shared(checkpoint(_variants(marked, min_chars)), "key").groupBy("id").agg(F.collect_list(F.struct("at", "key", "kept")).alias("found"))
    joined = marked.join(places.hint("shuffle_hash"), "id").select("id", _split(F.col("text")).alias("lines"), F.explode("found").alias("f"))
    texts = checkpoint(joined.select("id", "f.at", "f.key", "f.kept", F.trim(F.get("lines", F.col("f.at"))).alias("line")).dropDuplicates(["id", "at", "key", "kept", "line"]))
    finer = _shared(checkpoint(_blocks(texts)), "key2")
    rows = finer.join(texts, ["id", "at", "key", "kept"])
    front = F.expr("substring(line, kept + 1, length(line))")
    part = F.when(F.col("kept") >= 0, front).otherwise(F.expr("left(line, length(line) + kept)"))
    rows = rows.withColumn("part", part).select("key2", "id", "at", F.expr("substring(part, p + 1, length(part) - p - q)").alias("b"))
    pairs = checkpoint(_character_links(rows))
    own = texts.select("id", "at", "line").distinct()
    both = pairs.join(own, ["id", "at"]).join(own.toDF("o_id", "o_at", "o_line"), ["o_id", "o_at"])
    late = both.where(F.levenshtein("line", "o_line", 1) >= 0).select("id", "at")
    return late.groupBy("id").agg(F.collect_set("at").alias("near"))


def _character_links(rows: DataFrame) -> DataFrame:
    """id, at, o_id, o_at: places linked to an earlier one whose block equals theirs but for one character.

    Lines of one key differ in their block ``b`` only. Blocks that are equal once one character is masked are
    one replacement apart, all of them from each other; a block equal to another less one
    character is one deletion apart. Both need only the earliest line of each variant.
    """
    each = F.sequence(F.lit(1), F.greatest(F.length("b"), F.lit(1)))
    less = lambda i: F.concat(F.substring("b", F.lit(1), i - 1), F.substring("b", i + 1, F.length("b")))
    entry = lambda kind, v: F.struct(F.lit(kind).alias("kind"), v.alias("v"))
    masked = F.transform(each, lambda i: entry("masked", F.xxhash64(F.lit("masked"), "key2", i, less(i))))
    shorter = F.array_distinct(F.transform(each, lambda i: entry("shorter", F.xxhash64(F.lit("whole"), "key2", less(i)))))
    variants = F.concat(masked, shorter, F.array(entry("own", F.xxhash64(F.lit("whole"), "key2", "b"))))
    out = checkpoint(rows.select("id", "at", F.explode(variants).alias("x")).select("id", "at", "x.*"))
    pos = F.struct("id", "at")
    least = lambda kind: F.min(F.when(F.col("kind") == kind, pos)).alias(kind)
    firsts = checkpoint(out.groupBy("v").agg(least("masked"), least("shorter"), least("own"), F.count("*").alias("n")).where("n > 1"))
    total = firsts.agg(F.sum("n")).first()[0] or 0
    other = F.when(F.col("kind") == "masked", F.col("masked")).when(F.col("kind") == "shorter", F.col("own")).otherwise(F.col("shorter"))
    joined = join_dealt(out, firsts, ["v"], "n", total).withColumn("o", other)
    return joined.where(pos > F.col("o")).select("id", "at", F.col("o.id").alias("o_id"), F.col("o.at").alias("o_at")).distinct()


def line_decisions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """id, text, exact, near: one row per input row with an id, with the places of dropped lines."""
    src = pick(docs, id_col, text_col).toDF("id", "text").where("id is not null")
    none = F.array().cast("array<int>")
    exact = checkpoint(_exact_drops(src))
    # the one shuffle of the texts; all joins by id below use it
    marked = src.repartition("id").join(exact.hint("shuffle_hash"), "id", "left").withColumn("exact", F.coalesce("exact", none))
    near = _near_drops(marked, min_chars)
    return marked.join(near.hint("shuffle_hash"), "id", "left").select("id", "text", "exact", F.coalesce("near", none).alias("near"))


def kept_text(text: Column, exact: Column, near: Column) -> Column:
    lines = _split(text)
    keep = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.concat(exact, near))
    return F.when(F.size(exact) + F.size(near) == 0, text).otherwise(F.array_join(F.transform(keep, lambda i: F.get(lines, i)), "\n"))


def dedup_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """id_col, n_lines, n_exact, n_near, n_kept, kept_sha256, for each row with an id."""
    d = line_decisions(docs, id_col, text_col, min_chars)
    n = F.coalesce(F.size(_split(F.col("text"))), F.lit(0))
    return d.select(
        F.col("id").alias(id_col), n.alias("n_lines"), F.size("exact").alias("n_exact"), F.size("near").alias("n_near"),
        (n - F.size("exact") - F.size("near")).alias("n_kept"), F.sha2(kept_text(F.col("text"), F.col("exact"), F.col("near")), 256).alias("kept_sha256"),
    )


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, drop_emptied: bool = True) -> DataFrame:
    """The documents without the dropped lines; documents that a drop left blank go, unless told otherwise."""
    drops = line_decisions(docs, id_col, text_col, min_chars).where(F.size("exact") + F.size("near") > 0)
    gone, exact, near, hit = (fresh(x, docs) for x in ("id", "exact", "near", "hit"))
    drops = drops.select(F.col("id").alias(gone), F.col("exact").alias(exact), F.col("near").alias(near)).dropDuplicates([gone])
    joined = docs.join(drops.hint("shuffle_hash"), docs[f"`{id_col}`"] == drops[gone], "left")
    found = F.col(gone).isNotNull()
    text = F.when(found, kept_text(F.col(f"`{text_col}`"), F.col(exact), F.col(near))).otherwise(F.col(f"`{text_col}`"))
    out = joined.select(*[(text if c == text_col else F.col(f"`{c}`")).alias(c) for c in docs.columns], found.alias(hit))
    return (out.where(~F.col(hit) | (F.trim(F.regexp_replace(F.col(f"`{text_col}`"), r"\s+", " ")) != "")) if drop_emptied else out).drop(hit)
