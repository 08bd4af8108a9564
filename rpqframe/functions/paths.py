"""Path rows: src, dst, len, nodes, edges; node positions count from 1."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PATH_COLUMNS = ["src", "dst", "len", "nodes", "edges"]
PATH_SCHEMA = "src bigint, dst bigint, len int, nodes array<bigint>, edges array<bigint>"
LAST = "last"


def paths0(nodes: DataFrame) -> DataFrame:
    """One path of length 0 for each node."""
    return nodes.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0).alias("len"), F.array("id").alias("nodes"), F.array().cast("array<bigint>").alias("edges"))


def paths1(edges: DataFrame) -> DataFrame:
    """One path of length 1 for each edge."""
    return edges.select("src", "dst", F.lit(1).alias("len"), F.array("src", "dst").alias("nodes"), F.array("eid").alias("edges"))


def linkable(a: str = "a", b: str = "b") -> Column:
    return F.col(f"{a}.dst") == F.col(f"{b}.src")


def concat_paths(a: str = "a", b: str = "b") -> list[Column]:
    """The columns of the concatenation of two linkable paths; the shared node stands once."""
    return [
        F.col(f"{a}.src").alias("src"),
        F.col(f"{b}.dst").alias("dst"),
        (F.col(f"{a}.len") + F.col(f"{b}.len")).alias("len"),
        F.concat(f"{a}.nodes", F.slice(F.col(f"{b}.nodes"), F.lit(2), F.col(f"{b}.len"))).alias("nodes"),
        F.concat(f"{a}.edges", f"{b}.edges").alias("edges"),
    ]


def reversed_paths(df: DataFrame) -> DataFrame:
    """Each path from its last node to its first."""
    return df.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "len", F.reverse("nodes").alias("nodes"), F.reverse("edges").alias("edges"))


def node_at(i: int | str) -> Column:
    return F.col("dst") if i == LAST else F.col("src") if i == 1 else F.get("nodes", F.lit(i - 1))


def edge_at(i: int | str) -> Column:
    return F.get("edges", F.col("len") - 1) if i == LAST else F.get("edges", F.lit(i - 1))


def seq() -> Column:
    """Node and edge ids in turn."""
    steps = F.flatten(F.zip_with(F.slice("nodes", F.lit(1), F.col("len")), "edges", lambda n, e: F.array(n, e)))
    return F.concat(steps, F.array("dst"))


def seq_text() -> Column:
    return F.array_join(F.transform(seq(), lambda x: x.cast("string")), ",")


def path_order() -> list[Column]:
    return [F.col("len"), F.col("nodes"), F.col("edges")]


def distinct_paths(df: DataFrame) -> DataFrame:
    """Equal paths have equal sources and edges, so these are the key."""
    return df.dropDuplicates(["src", "edges"])


def bag_subset(a: DataFrame, b: DataFrame) -> bool:
    return a.select("nodes", "edges").exceptAll(b.select("nodes", "edges")).isEmpty()


def bag_equal(a: DataFrame, b: DataFrame) -> bool:
    return bag_subset(a, b) and bag_subset(b, a)


def label_words(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """Adds the edge labels of each path in order, joined by dots; empty for length 0."""
    own = paths.withColumn("__key", F.struct("nodes", "edges"))
    steps = own.select("__key", F.posexplode("edges").alias("at", "eid")).distinct().join(edges.select("eid", "label"), "eid")
    words = steps.groupBy("__key").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "label"))), lambda x: x["label"]), ".").alias("word"))
    return own.join(words, "__key", "left").withColumn("word", F.coalesce("word", F.lit(""))).drop("__key")
