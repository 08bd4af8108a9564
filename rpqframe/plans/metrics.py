"""Measures: elapsed time over runs, timeouts, answers, memory failures, intermediate paths, redundancy."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from contextlib import contextmanager, nullcontext

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.operators.fixpoint import QueryTimeout, RecursionExplosion, Trace

METRICS_SCHEMA = "query string, shape string, method string, restrictor string, sf string, run int, seconds double, paths bigint, levels int, intermediate_rows bigint, peak_rows bigint, status string"


@contextmanager
def cancelled_after(spark: SparkSession, seconds: float | None):
    """Jobs that this thread starts inside are cancelled once the time is over; gives a function that tells whether they were."""
    if seconds is None:
        yield lambda: False
        return
    tag, fired = f"rpq-{uuid.uuid4().hex}", threading.Event()

    def stop() -> None:
        fired.set()
        spark.sparkContext.cancelJobsWithTag(tag)

    timer = threading.Timer(max(seconds, 0.0), stop)
    timer.daemon = True
    spark.sparkContext.addJobTag(tag)
    timer.start()
    try:
        yield fired.is_set
    finally:
        timer.cancel()
        spark.sparkContext.removeJobTag(tag)


#: What Spark and its cluster managers say of a task, executor or driver that ran out of memory or disk.
_MEMORY = ("OutOfMemory", "Java heap space", "GC overhead limit", "No space left", "Container killed", "exit code 137", "exited with code 137", "OOMKilled", "exceeding memory limits", "UNABLE_TO_ACQUIRE_MEMORY", "maxResultSize", "Cannot broadcast the table")


def failure_kind(text: str) -> str | None:
    """memory for the text of a failure of memory or disk, else None."""
    return "memory" if any(x in text for x in _MEMORY) else None


def timed(make: Callable[[], DataFrame], timeout_s: float, trace: Trace, spark: SparkSession | None = None) -> tuple[float, int, str]:
    """Seconds from submission to the last answer, number of answers, and how it ended. With a session, jobs are cancelled at the timeout."""
    begin = time.perf_counter()
    trace.deadline = time.monotonic() + timeout_s
    paths, status = 0, "ok"
    with nullcontext(lambda: False) if spark is None else cancelled_after(spark, timeout_s) as stopped:
        try:
            paths = len(make().collect())
        except QueryTimeout:
            status = "timeout"
        except RecursionExplosion:
            status = "explosion"
        except Exception as e:  # failures of memory are a measure here; everything else is an error
            status = "timeout" if stopped() else failure_kind(str(e))
            if status is None:
                raise
    seconds = time.perf_counter() - begin
    return seconds, paths, "timeout" if status == "ok" and seconds > timeout_s else status


def by_query(metrics: DataFrame) -> DataFrame:
    """Mean time over the runs of each query that all ended."""
    ok = F.min((F.col("status") == "ok").cast("int")) == 1
    return metrics.groupBy("query", "shape", "method", "restrictor", "sf").agg(F.when(ok, F.avg("seconds")).alias("seconds"), F.max("paths").alias("paths"), F.max("intermediate_rows").alias("intermediate_rows"), F.max("peak_rows").alias("peak_rows"))


def by_shape(metrics: DataFrame) -> DataFrame:
    """Mean over the queries of a shape; queries that timed out are counted and left out of the mean."""
    q = by_query(metrics)
    return q.groupBy("shape", "method", "restrictor", "sf").agg(F.avg("seconds").alias("seconds"), F.count("*").alias("queries"), F.sum(F.col("seconds").isNull().cast("int")).alias("not_ended"), F.sum("intermediate_rows").alias("intermediate_rows"))


def summary(metrics: DataFrame) -> DataFrame:
    """min, median, avg and max over the shapes that ended."""
    s = by_shape(metrics).where("seconds is not null")
    return s.groupBy("method", "restrictor", "sf").agg(F.min("seconds").alias("min"), F.expr("percentile(seconds, 0.5)").alias("median"), F.avg("seconds").alias("avg"), F.max("seconds").alias("max"), F.count("*").alias("shapes"))


def speedups(metrics: DataFrame, engine: str = "algebra") -> DataFrame:
    """How many times longer each other method took, by shape."""
    s = by_shape(metrics)
    own = s.where(F.col("method") == engine).select("shape", "restrictor", "sf", F.col("seconds").alias("own"))
    return s.where(F.col("method") != engine).join(own, ["shape", "restrictor", "sf"]).select("shape", "restrictor", "sf", "method", (F.col("seconds") / F.col("own")).alias("ratio"))


def failures(metrics: DataFrame) -> DataFrame:
    return metrics.where("status <> 'ok'").groupBy("method", "restrictor", "status").agg(F.countDistinct("query").alias("queries"))


def redundancy(trace: Trace, distinct_states: int) -> float:
    """Expanded product states for each distinct (node, state) among them."""
    return sum(x["rows"] for x in trace.levels) / max(1, distinct_states)
