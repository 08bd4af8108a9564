"""Benchmark decontamination by a broadcast hash set of normalised n-grams.

The test items' word windows go to the workers as one hash set. Its size is bounded: items are
read in order and dealt into sets of at most ``max_windows`` windows; each further set is a
further pass over the rows in place, so a larger benchmark costs passes and no executor ever
holds more than one set. A worker marks the words that occur in the benchmark at all,
looks only at places where a full window of such words stands, and verifies the exact words.

Defined results: null or wordless texts have no words and no hits; an item with a null id or
without words is ignored; rows of an item that is repeated are taken together; repeated document
rows stay repeated; an empty table on either side is fine; extra columns are carried along.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rpqframe.llm.common import _NOT_WORD, ascii_words, fresh, pick, text_slices

NGRAM = 13
#: Windows in one broadcast set, and bytes of their text and entries.
MAX_WINDOWS, MAX_BYTES = 500_000, 128 << 20


def item_windows(text: bytes | None, n: int) -> list[bytes]:
    words = ascii_words(text or b"")
    if not words:
        return []
    n = min(n, len(words))
    return [b" ".join(words[i : i + n]) for i in range(len(words) - n + 1)]


def window_sets(items: DataFrame, id_col: str, text_col: str, n: int, max_windows: int) -> Iterator[dict[bytes, set[str]]]:
    """Sets of windows with the ids of their items, each of bounded size."""
    rows = pick(items, id_col, text_col).toDF("id", "text").where("id is not null").select(F.col("id").cast("string"), "text")
    current: dict[bytes, set[str]] = {}
    size = 0
    for row in rows.toLocalIterator():
        for w in item_windows(None if row.text is None else row.text.encode(), n):
            own = current.setdefault(w, set())
            size += 400 + len(w) if not own else 0
            own.add(row.id)
            if len(current) >= max_windows or size >= MAX_BYTES:  # within a huge item too
                yield current
                current, size = {}, 0
    yield current


class Matcher:
    """Finds the spans of words inside any occurrence of a window."""

    def __init__(self, windows: dict[bytes, set[str]]):
        self.windows = windows
        self.lengths = sorted({w.count(b" ") + 1 for w in windows})
        self.known = dict.fromkeys({w for k in windows for w in k.split(b" ")}, 1)

    def find(self, docs: list[list[bytes]]) -> list[tuple[list[tuple[int, int]], set[str]]]:
        out: list[tuple[list[tuple[int, int]], set[str]]] = [([], set()) for _ in docs]
        if not self.lengths or not docs:
            return out
        get = self.known.get
        sizes = np.array([len(d) for d in docs])
        starts = np.concatenate([[0], np.cumsum(sizes + 1)])  # a gap after each text
        flags = np.zeros(starts[-1] + 1, dtype=np.int64)
        for d, at in zip(docs, starts):
            if d:
                flags[at : at + len(d)] = np.fromiter((get(w, 0) for w in d), dtype=np.int64, count=len(d))
        total = np.concatenate([[0], np.cumsum(flags)])
        for n in self.lengths:
            if len(total) <= n:
                continue
            at = np.flatnonzero(total[n:] - total[:-n] == n)
            which = np.searchsorted(starts, at, side="right") - 1
            for p, k in zip((at - starts[which]).tolist(), which.tolist()):
                ids = self.windows.get(b" ".join(docs[k][p : p + n]))
                if ids:
                    spans, found = out[k]
                    spans.append((p, p + n))
                    found |= ids
        return out


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    merged: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if merged and a <= merged[-1][1]:
            merged[-1] = (merged[-1][0], max(b, merged[-1][1]))
        else:
            merged.append((a, b))
    return merged


def cut_words(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text without the words of the spans and what stands between the words of one span."""
    low, offs, at = raw.lower().translate(_NOT_WORD), [], 0
    for w in low.split():
        at = low.index(w, at)
        offs.append((at, at + len(w)))
        at += len(w)
    out, frm = [], 0
    for a, b in spans:
        out.append(raw[frm : offs[a][0]])
        frm = offs[b - 1][1]
    return b"".join([*out, raw[frm:]])


HITS = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("spans", T.ArrayType(T.ArrayType(T.IntegerType()))),
        T.StructField("items", T.ArrayType(T.StringType())),
    ]
)
_HITS = pa.struct([("n_words", pa.int64()), ("spans", pa.list_(pa.list_(pa.int32()))), ("items", pa.list_(pa.string()))])


def find_hits(docs: DataFrame, items: DataFrame, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", n: int = NGRAM, max_windows: int = MAX_WINDOWS, hits_col: str = "hits") -> DataFrame:
    """The documents with a struct column: n_words, merged word spans [start, end), item ids found.

    A column of the name ``hits_col`` in the input is replaced.
    """
    spark = docs.sparkSession
    src = docs.drop(hits_col)
    keep = src.columns
    out = src.select(*[F.col(f"`{c}`") for c in keep], F.lit(None).cast(HITS).alias(hits_col))
    schema = out.schema
    for windows in window_sets(items, item_id, item_text, n, max_windows):
        shared = spark.sparkContext.broadcast(windows)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(shared.value)
            for batch in batches:
                for rows, texts in text_slices(batch, text_col):
                    words = [ascii_words(t or b"") for t in texts]
                    before = rows.column(rows.num_columns - 1).to_pylist()
                    hits = []
                    for ws, old, (spans, ids) in zip(words, before, matcher.find(words)):
                        spans = merge_spans(spans + [tuple(s) for s in (old or {}).get("spans") or []])
                        hits.append({"n_words": len(ws), "spans": [list(s) for s in spans], "items": sorted(ids | set((old or {}).get("items") or []))})
                    yield pa.RecordBatch.from_arrays([*rows.columns[:-1], pa.array(hits, _HITS)], names=rows.schema.names)

        out = out.mapInArrow(run, schema)
    return out


def contamination(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", share: int = 20, n: int = NGRAM, max_windows: int = MAX_WINDOWS) -> DataFrame:
    """id_col, n_words, n_hit, n_items, items_sha256, contaminated (a hit word in every ``share`` or more)."""
    name = fresh("hits", docs)
    hits = find_hits(pick(docs, id_col, text_col), items, text_col, n=n, max_windows=max_windows, hits_col=name)
    h = hits.select(
        id_col,
        F.col(f"{name}.n_words").alias("n_words"),
        F.aggregate(f"{name}.spans", F.lit(0).cast("bigint"), lambda acc, s: acc + s[1] - s[0]).alias("n_hit"),
        F.size(f"{name}.items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join(f"{name}.items", ","), 256).alias("items_sha256"),
    )
    return h.withColumn("contaminated", (F.col("n_hit") > 0) & (F.lit(share) * F.col("n_hit") >= F.col("n_words")))


def remove_contaminated(docs: DataFrame, items: DataFrame, text_col: str = "text", share: int = 20, n: int = NGRAM, max_windows: int = MAX_WINDOWS, spans_only: bool = False) -> DataFrame:
    """Drop contaminated documents, or with ``spans_only`` cut the spans out of them; others stay untouched."""
    name = fresh("hits", docs)
    hits = find_hits(docs, items, text_col, n=n, max_windows=max_windows, hits_col=name)
    n_hit = F.aggregate(f"{name}.spans", F.lit(0).cast("bigint"), lambda acc, s: acc + s[1] - s[0])
    bad = (n_hit > 0) & (F.lit(share) * n_hit >= F.col(f"{name}.n_words"))
    if not spans_only:
        return hits.where(~bad).drop(name)

    @F.pandas_udf("string")
    def cut(texts, spans):
        return texts.combine(spans, lambda t, s: t if t is None else cut_words(t.encode(), [tuple(x) for x in s]).decode("utf-8", "replace"))

    clean = F.when(bad, cut(F.col(f"`{text_col}`"), F.col(f"{name}.spans"))).otherwise(F.col(f"`{text_col}`"))
    return hits.withColumn(text_col, clean).drop(name)


def digest(ids: set[str]) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()
