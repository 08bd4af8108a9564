"""Property graphs as two DataFrames, nodes and edges."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.sources import tables as T

NODE_SCHEMA = "id bigint, label string, props map<string,string>"
EDGE_SCHEMA = "eid bigint, label string, src bigint, dst bigint, props map<string,string>"


@dataclass
class PropertyGraph:
    """Frames by label, made on demand, so a query plans only the labels it uses."""

    spark: SparkSession
    node_frames: dict[str, Callable[[], DataFrame]]
    edge_frames: dict[str, Callable[[], DataFrame]]
    counts: dict[str, int] = field(default_factory=dict)
    stored: bool = False  # label frames are scans of files
    whole: tuple[DataFrame, DataFrame] | None = None  # nodes and edges of all labels, where one scan gives several labels

    @property
    def edge_labels(self) -> list[str]:
        return list(self.edge_frames)

    @property
    def node_labels(self) -> list[str]:
        return list(self.node_frames)

    def nodes_of(self, labels: Iterable[str] | None = None) -> DataFrame:
        if self.whole is not None:
            return _of_labels(self.whole[0], labels)
        return _union(self.spark, [self.node_frames[x]() for x in (self.node_frames if labels is None else labels)], NODE_SCHEMA)

    def edges_of(self, labels: Iterable[str] | None = None) -> DataFrame:
        if self.whole is not None:
            return _of_labels(self.whole[1], labels)
        names = list(self.edge_frames) if labels is None else [x for x in labels if x in self.edge_frames]
        return _union(self.spark, [self.edge_frames[x]() for x in names], EDGE_SCHEMA)

    @property
    def nodes(self) -> DataFrame:
        return self.nodes_of()

    @property
    def edges(self) -> DataFrame:
        return self.edges_of()

    def edge_count(self, label: str) -> int:
        """Rows of a label, counted once; decides what may be broadcast."""
        if label not in self.counts:
            self.counts[label] = self.edges_of([label]).count()
        return self.counts[label]


def _of_labels(df: DataFrame, labels: Iterable[str] | None) -> DataFrame:
    if labels is None:
        return df
    names = list(labels)
    return df.where(F.col("label") == names[0] if len(names) == 1 else F.col("label").isin(names))


def _union(spark: SparkSession, frames: list[DataFrame], schema: str) -> DataFrame:
    if not frames:
        return spark.createDataFrame([], schema)
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def from_frames(nodes: DataFrame, edges: DataFrame, node_labels: list[str] | None = None, edge_labels: list[str] | None = None) -> PropertyGraph:
    """A graph of two frames; label lists spare a scan."""
    spark = nodes.sparkSession
    nl = node_labels or [r[0] for r in nodes.select("label").distinct().orderBy("label").collect()]
    el = edge_labels or [r[0] for r in edges.select("label").distinct().orderBy("label").collect()]
    return PropertyGraph(spark, {x: (lambda x=x: nodes.where(F.col("label") == x)) for x in nl}, {x: (lambda x=x: edges.where(F.col("label") == x)) for x in el}, whole=(nodes, edges))


def graph_from_tables(spark: SparkSession, sf_dir: str, fanout: int = 1) -> PropertyGraph:
    """The test graph of the relational tables."""
    t = T.Tables(spark, sf_dir, fanout)
    return PropertyGraph(spark, {k: (lambda f=f: f(t)) for k, f in T.NODES.items()}, {k: (lambda f=f: f(t)) for k, f in T.EDGES.items()})


def load_graph(spark: SparkSession, nodes_path: str, edges_path: str, fmt: str = "csv") -> PropertyGraph:
    """A graph of a node file and an edge file; properties are JSON text in CSV, maps elsewhere."""
    if fmt == "csv":
        n = spark.read.csv(nodes_path, header=True, schema="id bigint, label string, props string", escape='"')
        e = spark.read.csv(edges_path, header=True, schema="eid bigint, label string, src bigint, dst bigint, props string", escape='"')
        as_map = lambda d: d.withColumn("props", F.coalesce(F.from_json("props", "map<string,string>"), F.create_map().cast("map<string,string>")))
        n, e = as_map(n), as_map(e)
    else:
        n, e = spark.read.format(fmt).schema(NODE_SCHEMA).load(nodes_path), spark.read.format(fmt).schema(EDGE_SCHEMA).load(edges_path)
    return from_frames(n, e)


def save_graph(g: PropertyGraph, path: str, buckets: int | None = None) -> PropertyGraph:
    """Write nodes and edges as parquet partitioned by label, so that a label scan prunes the rest."""
    g.nodes.write.mode("overwrite").partitionBy("label").parquet(f"{path}/nodes")
    edges = g.edges if buckets is None else g.edges.repartition(buckets, "src").sortWithinPartitions("label", "src")
    edges.write.mode("overwrite").partitionBy("label").parquet(f"{path}/edges")
    return open_graph(g.spark, path)


def open_graph(spark: SparkSession, path: str) -> PropertyGraph:
    order = lambda d, cols: d.select(*cols)
    n = order(spark.read.parquet(f"{path}/nodes"), ["id", "label", "props"])
    e = order(spark.read.parquet(f"{path}/edges"), ["eid", "label", "src", "dst", "props"])
    out = from_frames(n, e)
    out.stored = True
    return out


def validate(g: PropertyGraph) -> dict[str, int]:
    """Violations by kind; all zero for a sound graph."""
    n, e = g.nodes, g.edges
    ids = n.select(F.col("id"))
    bad = lambda side: e.join(ids, e[side] == ids["id"], "left_anti").count()
    return {
        "null_labels": n.where("label is null").count() + e.where("label is null").count(),
        "null_ends": e.where("src is null or dst is null").count(),
        "dangling_src": bad("src"),
        "dangling_dst": bad("dst"),
        "repeated_node_ids": n.groupBy("id").count().where("count > 1").count(),
        "repeated_edge_ids": e.groupBy("eid").count().where("count > 1").count(),
        "shared_ids": ids.join(e.select(F.col("eid").alias("id")), "id", "left_semi").count(),
    }


def stats(g: PropertyGraph) -> DataFrame:
    """Per edge label: edges, distinct sources and targets, largest out-degree."""
    deg = g.edges.groupBy("label", "src").agg(F.count("*").alias("d"))
    out = deg.groupBy("label").agg(F.sum("d").alias("n_edges"), F.count("*").alias("n_sources"), F.max("d").alias("max_out_degree"))
    targets = g.edges.groupBy("label").agg(F.countDistinct("dst").alias("n_targets"))
    return out.join(targets, "label").select("label", "n_edges", "n_sources", "n_targets", "max_out_degree")


def catalog(g: PropertyGraph) -> DataFrame:
    """owner, label, key of every property in use."""
    keys = lambda d, owner: d.select(F.lit(owner).alias("owner"), "label", F.explode(F.map_keys("props")).alias("key")).distinct()
    return keys(g.nodes, "node").union(keys(g.edges, "edge"))


def median_degree_seed(g: PropertyGraph, label: str) -> int | None:
    """The smallest node id whose out-degree over a label is the median of the nodes that have such an edge."""
    deg = g.edges_of([label]).groupBy("src").agg(F.count("*").alias("d"))
    med = deg.agg(F.expr("percentile_disc(0.5) within group (order by d)").alias("m"))
    row = deg.join(F.broadcast(med), deg["d"] == med["m"]).agg(F.min("src")).first()
    return row[0]


def toy_graph(spark: SparkSession) -> PropertyGraph:
    """A small graph with a cycle, parallel edges, a self-loop, and an isolated node without properties."""
    n = [(1, "Person", {"name": "Ida", "age": "30"}), (2, "Person", {"name": "Ravi"}), (3, "Person", {"name": "Mei"}), (4, "Person", {"name": "Omar"}), (5, "Person", {})]
    n += [(i, "Post", {}) for i in (11, 12, 13)]
    e = [(101, "knows", 1, 2, {"since": "2019"}), (102, "knows", 2, 3, {}), (104, "knows", 2, 3, {}), (103, "knows", 3, 1, {}), (105, "knows", 4, 4, {}), (106, "knows", 3, 4, {})]
    e += [(111, "likes", 1, 11, {}), (112, "likes", 3, 12, {}), (113, "likes", 4, 13, {}), (121, "hasCreator", 11, 3, {}), (122, "hasCreator", 12, 4, {}), (123, "hasCreator", 13, 1, {})]
    return from_frames(spark.createDataFrame(n, NODE_SCHEMA).coalesce(1), spark.createDataFrame(e, EDGE_SCHEMA).coalesce(1), ["Person", "Post"], ["knows", "likes", "hasCreator"])
