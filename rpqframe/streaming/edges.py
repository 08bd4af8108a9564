"""Bounded patterns over a stream of edges: each batch of new edges is joined to stored ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.functions.paths import PATH_SCHEMA, paths1
from rpqframe.functions.restrictors import TRAIL, restrict
from rpqframe.operators.fixpoint import join_paths, recursive_join, reliable


def edge_stream(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Event rows as edges from users to event types, with a watermark."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks take no other type
    return timed.withWatermark("ts", late).select("ts", F.col("event_id").alias("eid"), F.col("event_type").alias("label"), F.col("user_id").alias("src"))


def windowed_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Edges by label in tumbling or sliding windows; works on streams and tables."""
    edges = edge_stream(events, late) if events.isStreaming else events.select("ts", F.col("event_type").alias("label"))
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    return edges.groupBy(win.alias("w"), "label").agg(F.count("*").alias("n_edges")).select(F.col("w.start").alias("start"), "label", "n_edges")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Edges of each source in sessions without a longer gap."""
    edges = edge_stream(events, late) if events.isStreaming else events.select("ts", F.col("user_id").alias("src"))
    return edges.groupBy(F.session_window("ts", gap).alias("w"), "src").agg(F.count("*").alias("n_edges")).select(F.col("w.start").alias("start"), "src", "n_edges")


def two_step_paths(first: DataFrame, second: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: an edge of the first stream followed by one of the second from the same source within a time."""
    first, second = (d.withColumn("ts", F.col("ts").cast("timestamp")) for d in (first, second))
    a = first.withWatermark("ts", late).select(F.col("event_id").alias("e1"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = second.withWatermark("ts", late).select(F.col("event_id").alias("e2"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    near = (F.col("u1") == F.col("u2")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"interval {within}"))
    return a.join(b, near).select("u1", "e1", "e2", "t1", "t2")


class PathTable:
    """All paths over the edges seen so far, under a restrictor, kept up by micro-batches.

    A new path holds a new edge. Cut before its first new edge, it is an old path or nothing, that edge, and any
    further edges; the cut is unique, so each new path is found once. Edges and paths are parquet folders by
    batch, so a batch that runs again replaces what it wrote.
    """

    def __init__(self, spark: SparkSession, folder: str, tau: str = TRAIL, max_len: int | None = None):
        self.spark, self.folder, self.tau, self.max_len = spark, folder, tau, max_len

    def _before(self, kind: str, schema: str, batch: int | None) -> DataFrame:
        where = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{kind}")
        if not where.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(where):
            return self.spark.createDataFrame([], schema)
        rows = self.spark.read.schema(f"{schema}, batch long").parquet(f"{self.folder}/{kind}")
        return (rows if batch is None else rows.where(F.col("batch") < batch)).drop("batch")

    def edges(self, before: int | None = None) -> DataFrame:
        return self._before("edges", "eid bigint, src bigint, dst bigint", before)

    def paths(self, before: int | None = None) -> DataFrame:
        return self._before("paths", PATH_SCHEMA, before)

    def add(self, edges: DataFrame, batch: int) -> None:
        """Take in the edges (eid, src, dst) of one batch; fits ``foreachBatch``. An edge seen before is not new."""
        old = self.edges(batch)
        new = reliable(edges.select("eid", "src", "dst").dropDuplicates(["eid"]).join(old.select("eid"), "eid", "left_anti").select("eid", "src", "dst"))
        first = paths1(new).where(restrict(self.tau))
        start = first.unionByName(join_paths(self.paths(batch), first, self.tau))
        base = paths1(old.unionByName(new))
        found = recursive_join(base, self.tau, start=start, dedupe=False, max_len=self.max_len, base_lengths=(1, 1))
        found.write.mode("overwrite").parquet(f"{self.folder}/paths/batch={batch}")
        new.write.mode("overwrite").parquet(f"{self.folder}/edges/batch={batch}")
