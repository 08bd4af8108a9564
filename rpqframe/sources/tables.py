"""The test graph: nodes and edges derived from the relational tables.

An id is kind * 10^15 + key, with other kinds for nodes than for edges, so their ids never meet.
"""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SPAN = 10**15
NODE_KIND = {k: i for i, k in enumerate(["Person", "Event", "Order", "Part", "Supplier", "Nation", "Region", "Turn", "Conversation", "Tag", "Club"], 1)}
EDGE_KIND = {
    k: i
    for i, k in enumerate(
        ["knows", "likes", "hasCreator", "nextEvent", "hasTag", "hasInterest", "isLocatedIn", "isPartOf", "hasNation", "replyOf", "inConversation", "placed", "placedBy", "contains", "suppliedBy", "buysFrom", "firstSupplier", "hasMember", "hasModerator", "followedBy", "precededBy"],
        21,
    )
}


#: The columns in use, so that no job has to look for them.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


class Tables:
    def __init__(self, spark: SparkSession, sf_dir: str, fanout: int = 1):
        self.spark, self.sf_dir, self.fanout = spark, sf_dir, fanout

    def read(self, name: str) -> DataFrame:
        return self.spark.read.schema(SCHEMAS[name]).parquet(f"{self.sf_dir}/{name}.parquet")

    @cached_property
    def tags(self) -> DataFrame:
        """name, tag: the distinct event types and market segments in order; a handful of rows."""
        names = self.read("events").select(F.col("event_type").alias("name")).union(self.read("customer").select("c_mktsegment")).distinct()
        return names.select("name", F.row_number().over(Window.orderBy("name")).cast("bigint").alias("tag"))


def nid(kind: str, key) -> Column:
    return (F.lit(NODE_KIND[kind] * SPAN) + (F.col(key) if isinstance(key, str) else key)).cast("bigint")


def _nodes(df: DataFrame, kind: str, key, **props: str) -> DataFrame:
    pairs = F.array(*[F.struct(F.lit(k).alias("k"), F.col(c).cast("string").alias("v")) for k, c in props.items()])
    known = F.map_from_entries(F.filter(pairs, lambda p: p["v"].isNotNull())) if props else F.create_map().cast("map<string,string>")
    return df.select(nid(kind, key).alias("id"), F.lit(kind).alias("label"), known.cast("map<string,string>").alias("props"))


def _edges(df: DataFrame, label: str, key, src: Column, dst: Column, **props: str) -> DataFrame:
    eid = (F.lit(EDGE_KIND[label] * SPAN) + (F.col(key) if isinstance(key, str) else key)).cast("bigint")
    pairs = [x for k, c in props.items() for x in (F.lit(k), F.col(c).cast("string"))]
    return df.select(eid.alias("eid"), F.lit(label).alias("label"), src.alias("src"), dst.alias("dst"), F.create_map(*pairs).cast("map<string,string>").alias("props"))


NODES = {
    "Person": lambda t: _nodes(t.read("customer"), "Person", "c_custkey", id="c_custkey", name="c_name", balance="c_acctbal", segment="c_mktsegment"),
    "Event": lambda t: _nodes(t.read("events"), "Event", "event_id", id="event_id", type="event_type", time="ts", value="value"),
    "Order": lambda t: _nodes(t.read("orders"), "Order", "o_orderkey", id="o_orderkey", status="o_orderstatus", date="o_orderdate", priority="o_orderpriority"),
    "Part": lambda t: _nodes(t.read("part"), "Part", "p_partkey", id="p_partkey", name="p_name", brand="p_brand", type="p_type", size="p_size"),
    "Supplier": lambda t: _nodes(t.read("supplier"), "Supplier", "s_suppkey", id="s_suppkey", name="s_name"),
    "Nation": lambda t: _nodes(t.read("nation"), "Nation", "n_nationkey", id="n_nationkey", name="n_name"),
    "Region": lambda t: _nodes(t.read("region"), "Region", "r_regionkey", id="r_regionkey", name="r_name"),
    "Turn": lambda t: _nodes(t.read("conversations"), "Turn", F.col("conv_id") * 100 + F.col("turn"), role="role", turn="turn"),
    "Conversation": lambda t: _nodes(t.read("conversations").select("conv_id").distinct(), "Conversation", "conv_id", id="conv_id"),
    "Tag": lambda t: _nodes(t.tags, "Tag", "tag", name="name"),
    "Club": lambda t: _nodes(_members(t).select("club").distinct(), "Club", "club", id="club"),
}


def _members(t: Tables) -> DataFrame:
    c = t.read("customer").select("c_custkey", "c_nationkey", "c_acctbal", F.col("c_mktsegment").alias("name"))
    return c.join(F.broadcast(t.tags), "name").withColumn("club", F.col("tag") * 1000 + F.col("c_nationkey"))


def following(events: DataFrame, value: str) -> DataFrame:
    """Adds ``next``: the value of the next row by (ts, event_id) over the whole table.

    Days are the partitions; the first row of the next day that has any closes each day's last row,
    so no task orders the whole table.
    """
    day = F.to_date("ts")
    rows = events.withColumn("day", day)
    within = rows.withColumn("next", F.lead(value).over(Window.partitionBy("day").orderBy("ts", "event_id")))
    heads = rows.groupBy("day").agg(F.min(F.struct("ts", "event_id", value)).alias("head"))
    after = heads.select("day", F.lead(f"head.{value}").over(Window.orderBy("day")).alias("later"))
    return within.join(F.broadcast(after), "day").withColumn("next", F.coalesce("next", "later")).drop("later", "day")


def knows(t: Tables) -> DataFrame:
    bought = t.read("events").where("event_type = 'purchase'").select("event_id", "ts", "user_id")
    pairs = following(bought, "user_id").where("next is not null and next <> user_id")
    rank = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return _edges(pairs.withColumn("r", rank).where(F.col("r") <= t.fanout), "knows", "event_id", nid("Person", "user_id"), nid("Person", "next"), since="ts")


def likes(t: Tables) -> DataFrame:
    """As-of join: the latest strictly earlier view of another user for each user's first purchases."""
    ev = t.read("events").select("event_id", "ts", "user_id", "event_type", F.to_date("ts").alias("day"))
    rank = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    first = ev.where("event_type = 'purchase'").withColumn("r", rank).where(F.col("r") <= t.fanout).select("event_id", "ts", "user_id", "day", F.lit(None).cast("boolean").alias("view"))
    views = ev.where("event_type = 'view'").select("event_id", "ts", "user_id", "day", F.lit(True).alias("view"))
    order = Window.partitionBy("day").orderBy("ts", "event_id")
    me = F.struct("ts", "event_id", "user_id")
    lagged = views.withColumn("prev", F.lag(me).over(order)).withColumn("change", F.when(F.col("prev.user_id") != F.col("user_id"), F.col("prev")))
    # the latest earlier view by someone else than this view's user
    lagged = lagged.withColumn("other", F.last("change", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0))).drop("prev", "change")
    both = first.withColumn("other", F.lit(None).cast(lagged.schema["other"].dataType)).unionByName(lagged)
    seen = both.withColumn("v", F.last(F.when(F.col("view"), F.struct("ts", "event_id", "user_id", "other")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, -1)))
    same_day = seen.where("view is null").withColumn("own", F.when(F.col("v.user_id") != F.col("user_id"), F.struct("v.ts", "v.event_id", "v.user_id")).otherwise(F.col("v.other")))
    tops = views.groupBy("day").agg(F.max(me).alias("a"))
    seconds = views.join(F.broadcast(tops), "day").where("user_id <> a.user_id").groupBy("day").agg(F.max(me).alias("b"))
    # a day's latest views by two users, in order over all days; each with the latest one by another user before it
    entries = tops.join(seconds, "day", "left").select("day", F.explode(F.array_compact(F.array("b", "a"))).alias("e"))
    line = Window.orderBy("e.ts", "e.event_id")
    entries = entries.withColumn("prev", F.lag("e").over(line)).withColumn("change", F.when(F.col("prev.user_id") != F.col("e.user_id"), F.col("prev")))
    entries = entries.withColumn("other", F.last("change", ignorenulls=True).over(line.rowsBetween(Window.unboundedPreceding, 0)))
    heads = entries.groupBy("day").agg(F.max(F.struct("e", "other")).alias("head"))
    # one row per day: the latest of all earlier days serves purchases without a view on their own day
    earlier = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)
    days = ev.select("day").distinct().join(heads, "day", "left").select("day", F.last("head", ignorenulls=True).over(earlier).alias("h"))
    # both kinds in one pass, so that the days are dealt out and ordered once
    before = F.when(F.col("h.e.user_id") != F.col("user_id"), F.col("h.e")).otherwise(F.col("h.other"))
    found = same_day.join(F.broadcast(days), "day", "left").select("event_id", "user_id", F.coalesce("own", before).alias("own"))
    return _edges(found.where("own is not null"), "likes", "event_id", nid("Person", "user_id"), nid("Event", F.col("own.event_id")))


def next_event(t: Tables) -> DataFrame:
    ev = t.read("events").withColumn("next", F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    return _edges(ev.where("next is not null"), "nextEvent", "event_id", nid("Event", "event_id"), nid("Event", "next"))


def contains(t: Tables) -> DataFrame:
    li = t.read("lineitem")
    rank = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"))
    return _edges(li.withColumn("r", rank), "contains", F.col("l_orderkey") * 1000 + F.col("r"), nid("Order", "l_orderkey"), nid("Part", "l_partkey"), quantity="l_quantity", shipdate="l_shipdate", returnflag="l_returnflag")


def buys_from(t: Tables) -> DataFrame:
    lines = t.read("lineitem").join(t.read("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    cents = lines.groupBy("o_custkey", "l_suppkey").agg(F.sum(F.round(F.col("l_extendedprice") * 100).cast("bigint")).alias("cents"))
    best = cents.groupBy("o_custkey").agg((-F.max(F.struct("cents", (-F.col("l_suppkey")).alias("s")))["s"]).alias("s"))
    return _edges(best, "buysFrom", "o_custkey", nid("Person", "o_custkey"), nid("Supplier", "s"))


def first_supplier(t: Tables) -> DataFrame:
    lines = t.read("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    orders = t.read("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_orderdate")
    first = lines.join(orders, "l_orderkey").groupBy("o_custkey").agg(F.min(F.struct("o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"))["l_suppkey"].alias("s"))
    return _edges(first, "firstSupplier", "o_custkey", nid("Person", "o_custkey"), nid("Supplier", "s"))


def located(t: Tables) -> DataFrame:
    people = _edges(t.read("customer"), "isLocatedIn", "c_custkey", nid("Person", "c_custkey"), nid("Nation", "c_nationkey"))
    firms = _edges(t.read("supplier"), "isLocatedIn", F.col("s_suppkey") + F.lit(SPAN // 2), nid("Supplier", "s_suppkey"), nid("Nation", "s_nationkey"))
    return people.unionByName(firms)


def moderators(t: Tables) -> DataFrame:
    top = _members(t).groupBy("club").agg((-F.max(F.struct("c_acctbal", (-F.col("c_custkey")).alias("k")))["k"]).alias("k"))
    return _edges(top, "hasModerator", "club", nid("Club", "club"), nid("Person", "k"))


def _transitions(t: Tables) -> DataFrame:
    """a, b: the tags of event types that follow each other in some user's events; a type can follow itself."""
    after = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    pairs = t.read("events").select(F.col("event_type").alias("name"), after.alias("next")).where("next is not null").distinct()
    both = pairs.join(F.broadcast(t.tags.withColumnRenamed("tag", "a")), "name").select("a", F.col("next").alias("name"))
    return both.join(F.broadcast(t.tags.withColumnRenamed("tag", "b")), "name").select("a", "b")


def _turn(k=0) -> Column:
    return nid("Turn", F.col("conv_id") * 100 + F.col("turn") - k)


def _by_name(t: Tables, table: str, label: str, key: str, name: str, kind: str) -> DataFrame:
    rows = t.read(table).join(F.broadcast(t.tags.withColumnRenamed("name", name)), name)
    return _edges(rows, label, key, nid(kind, key), nid("Tag", "tag"))


EDGES = {
    "knows": knows,
    "likes": likes,
    "hasCreator": lambda t: _edges(t.read("events"), "hasCreator", "event_id", nid("Event", "event_id"), nid("Person", "user_id")),
    "nextEvent": next_event,
    "hasTag": lambda t: _by_name(t, "events", "hasTag", "event_id", "event_type", "Event"),
    "hasInterest": lambda t: _by_name(t, "customer", "hasInterest", "c_custkey", "c_mktsegment", "Person"),
    "isLocatedIn": located,
    "isPartOf": lambda t: _edges(t.read("nation"), "isPartOf", "n_nationkey", nid("Nation", "n_nationkey"), nid("Region", "n_regionkey")),
    "hasNation": lambda t: _edges(t.read("nation"), "hasNation", "n_nationkey", nid("Region", "n_regionkey"), nid("Nation", "n_nationkey")),
    "replyOf": lambda t: _edges(t.read("conversations").where("turn > 0"), "replyOf", F.col("conv_id") * 100 + F.col("turn"), _turn(), _turn(1)),
    "inConversation": lambda t: _edges(t.read("conversations"), "inConversation", F.col("conv_id") * 100 + F.col("turn"), _turn(), nid("Conversation", "conv_id")),
    "placed": lambda t: _edges(t.read("orders"), "placed", "o_orderkey", nid("Person", "o_custkey"), nid("Order", "o_orderkey"), date="o_orderdate"),
    "placedBy": lambda t: _edges(t.read("orders"), "placedBy", "o_orderkey", nid("Order", "o_orderkey"), nid("Person", "o_custkey")),
    "contains": contains,
    "suppliedBy": lambda t: _edges(t.read("lineitem").select("l_partkey", "l_suppkey").distinct(), "suppliedBy", F.col("l_partkey") * 10**7 + F.col("l_suppkey"), nid("Part", "l_partkey"), nid("Supplier", "l_suppkey")),
    "buysFrom": buys_from,
    "firstSupplier": first_supplier,
    "hasMember": lambda t: _edges(_members(t), "hasMember", "c_custkey", nid("Club", "club"), nid("Person", "c_custkey")),
    "hasModerator": moderators,
    "followedBy": lambda t: _edges(_transitions(t), "followedBy", F.col("a") * 1000 + F.col("b"), nid("Tag", "a"), nid("Tag", "b")),
    "precededBy": lambda t: _edges(_transitions(t), "precededBy", F.col("b") * 1000 + F.col("a"), nid("Tag", "b"), nid("Tag", "a")),
}
