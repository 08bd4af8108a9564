"""DuckDB SQL over the same tables: the graph's edges, and patterns as recursive SQL with visited lists."""

from __future__ import annotations

from rpqframe.functions.restrictors import ACYCLIC, SIMPLE, TRAIL, WALK
from rpqframe.operators.automata import compile_dfa
from rpqframe.plans.regex import parse_regex
from rpqframe.plans.workload import seed_label, witness
from rpqframe.sources.tables import EDGE_KIND, EDGES, NODE_KIND, SPAN


def _n(kind: str, key: str) -> str:
    return f"CAST({NODE_KIND[kind] * SPAN} + {key} AS BIGINT)"


def _e(label: str, key: str, src: str, dst: str, rest: str) -> str:
    return f"SELECT CAST({EDGE_KIND[label] * SPAN} + {key} AS BIGINT) AS eid, '{label}' AS label, {src} AS src, {dst} AS dst FROM {rest}"


TAGS = "(SELECT name, row_number() OVER (ORDER BY name) AS tag FROM (SELECT event_type AS name FROM events UNION SELECT c_mktsegment FROM customer))"
MEMBERS = f"(SELECT c_custkey, c_acctbal, tag * 1000 + c_nationkey AS club FROM customer JOIN {TAGS} ON name = c_mktsegment)"


TRANSITIONS = f"(SELECT x.tag AS a, y.tag AS b FROM (SELECT DISTINCT event_type, nxt FROM (SELECT event_type, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL) JOIN {TAGS} AS x ON x.name = event_type JOIN {TAGS} AS y ON y.name = nxt)"


def edge_sql(label: str, fanout: int = 1) -> str:
    person, event = (lambda k: _n("Person", k)), (lambda k: _n("Event", k))
    turn = lambda k: _n("Turn", f"conv_id * 100 + {k}")
    first = f"(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM events WHERE event_type = 'purchase') WHERE r <= {fanout})"
    return {
        "knows": lambda: _e(label, "event_id", person("user_id"), person("nxt"), f"(SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM (SELECT event_id, ts, user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events WHERE event_type = 'purchase') WHERE nxt IS NOT NULL AND nxt <> user_id) WHERE r <= {fanout}"),
        "likes": lambda: _e(label, "p_id", person("p_user"), event("v.id"), f"(SELECT p.event_id AS p_id, p.user_id AS p_user, max({{'ts': w.ts, 'id': w.event_id}}) AS v FROM {first} AS p JOIN events AS w ON w.event_type = 'view' AND w.user_id <> p.user_id AND (w.ts < p.ts OR w.ts = p.ts AND w.event_id < p.event_id) GROUP BY 1, 2)"),
        "hasCreator": lambda: _e(label, "event_id", event("event_id"), person("user_id"), "events"),
        "nextEvent": lambda: _e(label, "event_id", event("event_id"), event("nxt"), "(SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL"),
        "hasTag": lambda: _e(label, "event_id", event("event_id"), _n("Tag", "tag"), f"events JOIN {TAGS} ON name = event_type"),
        "hasInterest": lambda: _e(label, "c_custkey", person("c_custkey"), _n("Tag", "tag"), f"customer JOIN {TAGS} ON name = c_mktsegment"),
        "isLocatedIn": lambda: _e(label, "c_custkey", person("c_custkey"), _n("Nation", "c_nationkey"), "customer") + " UNION ALL " + _e(label, f"{SPAN // 2} + s_suppkey", _n("Supplier", "s_suppkey"), _n("Nation", "s_nationkey"), "supplier"),
        "isPartOf": lambda: _e(label, "n_nationkey", _n("Nation", "n_nationkey"), _n("Region", "n_regionkey"), "nation"),
        "hasNation": lambda: _e(label, "n_nationkey", _n("Region", "n_regionkey"), _n("Nation", "n_nationkey"), "nation"),
        "replyOf": lambda: _e(label, "conv_id * 100 + turn", turn("turn"), turn("turn - 1"), "conversations WHERE turn > 0"),
        "inConversation": lambda: _e(label, "conv_id * 100 + turn", turn("turn"), _n("Conversation", "conv_id"), "conversations"),
        "placed": lambda: _e(label, "o_orderkey", person("o_custkey"), _n("Order", "o_orderkey"), "orders"),
        "placedBy": lambda: _e(label, "o_orderkey", _n("Order", "o_orderkey"), person("o_custkey"), "orders"),
        "contains": lambda: _e(label, "l_orderkey * 1000 + r", _n("Order", "l_orderkey"), _n("Part", "l_partkey"), "(SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY " + LINE_ORDER + ") AS r FROM lineitem)"),
        "suppliedBy": lambda: _e(label, f"l_partkey * {10**7} + l_suppkey", _n("Part", "l_partkey"), _n("Supplier", "l_suppkey"), "(SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)"),
        "buysFrom": lambda: _e(label, "o_custkey", person("o_custkey"), _n("Supplier", "l_suppkey"), "(SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY cents DESC, l_suppkey) AS r FROM (SELECT o_custkey, l_suppkey, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY 1, 2)) WHERE r = 1"),
        "firstSupplier": lambda: _e(label, "o_custkey", person("o_custkey"), _n("Supplier", "l_suppkey"), "(SELECT o_custkey, l_suppkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey) AS r FROM lineitem JOIN orders ON o_orderkey = l_orderkey) WHERE r = 1"),
        "hasMember": lambda: _e(label, "c_custkey", _n("Club", "club"), person("c_custkey"), MEMBERS),
        "hasModerator": lambda: _e(label, "club", _n("Club", "club"), person("c_custkey"), f"(SELECT *, row_number() OVER (PARTITION BY club ORDER BY c_acctbal DESC, c_custkey) AS r FROM {MEMBERS}) WHERE r = 1"),
        "followedBy": lambda: _e(label, "a * 1000 + b", _n("Tag", "a"), _n("Tag", "b"), TRANSITIONS),
        "precededBy": lambda: _e(label, "b * 1000 + a", _n("Tag", "b"), _n("Tag", "a"), TRANSITIONS),
    }[label]()


LINE_ORDER = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"

_NODE_KEYS = {
    "Person": ("c_custkey", "customer"), "Event": ("event_id", "events"), "Order": ("o_orderkey", "orders"), "Part": ("p_partkey", "part"), "Supplier": ("s_suppkey", "supplier"), "Nation": ("n_nationkey", "nation"), "Region": ("r_regionkey", "region"),
    "Turn": ("conv_id * 100 + turn", "conversations"), "Conversation": ("conv_id", "(SELECT DISTINCT conv_id FROM conversations)"), "Tag": ("tag", TAGS), "Club": ("club", f"(SELECT DISTINCT club FROM {MEMBERS})"),
}


def node_sql() -> str:
    return " UNION ALL ".join(f"SELECT {_n(k, key)} AS id, '{k}' AS label FROM {table} AS t_{k}" for k, (key, table) in _NODE_KEYS.items())


def edges_sql(labels, fanout: int = 1) -> str:
    return " UNION ALL ".join(f"({edge_sql(x, fanout)})" for x in labels)


def median_seed_sql(label: str, fanout: int = 1) -> str:
    deg = f"(SELECT src, count(*) AS d FROM ({edge_sql(label, fanout)}) GROUP BY src)"
    return f"SELECT min(src) AS id FROM {deg} WHERE d = (SELECT quantile_disc(d, 0.5) FROM {deg})"


def _may_add(tau: str) -> str:
    closed = "(p.len > 0 AND p.src = p.dst)"
    return {
        WALK: "true",
        TRAIL: "NOT list_contains(p.edges, e.eid)",
        ACYCLIC: "NOT list_contains(p.nodes, e.dst)",
        SIMPLE: f"NOT {closed} AND NOT list_contains(p.nodes[2:], e.dst)",
    }[tau]


def paths_sql(template: str, tau: str, *, seeds: str | None = None, max_len: int | None = None, fanout: int = 1, mid: str = "") -> str:
    """WITH clause that ends with ``found``: src, dst, len, nodes, edges, seq of all answers."""
    dfa = compile_dfa(parse_regex(template), list(EDGES))
    labels = sorted({x for _, x in dfa.moves})
    moves = ", ".join(f"({s}, '{x}', {n})" for s, x, n in dfa.rows())
    bound = "" if max_len is None else f" AND p.len < {max_len}"
    finals = ", ".join(map(str, sorted(dfa.finals)))
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges_sql(labels, fanout)}), t(state, label, nxt) AS (VALUES {moves}), seeds AS ({seeds or f"SELECT id FROM ({node_sql()})"}), p AS (
SELECT id AS src, id AS dst, CAST(0 AS BIGINT) AS len, [id] AS nodes, CAST([] AS BIGINT[]) AS edges, CAST(id AS VARCHAR) AS seq, 0 AS state FROM seeds
UNION ALL
SELECT p.src, e.dst, p.len + 1, list_append(p.nodes, e.dst), list_append(p.edges, e.eid), p.seq || ',' || e.eid || ',' || e.dst, t.nxt
FROM p JOIN t ON t.state = p.state JOIN e ON e.label = t.label AND e.src = p.dst WHERE {_may_add(tau)}{bound}
), found AS (SELECT src, dst, len, nodes, edges, seq FROM p WHERE state IN ({finals})){mid}
"""


def rpq_sql(template: str, tau: str, *, seeds: str | None = None, max_len: int | None = None, limit: int | None = None, fanout: int = 1) -> str:
    tail = f" ORDER BY len, nodes, edges LIMIT {limit}" if limit else ""
    return paths_sql(template, tau, seeds=seeds, max_len=max_len, fanout=fanout) + f"SELECT src, dst, len, seq FROM found{tail}"


def witness_seed_sql(template: str) -> str:
    """The seed of a template among the nodes that its witness word starts from."""
    word = witness(parse_regex(template))
    chain = f"SELECT DISTINCT e0.src FROM ({edge_sql(word[0])}) AS e0 " + " ".join(f"JOIN ({edge_sql(x)}) AS e{k} ON e{k}.src = e{k - 1}.dst" for k, x in enumerate(word[1:], 1))
    deg = f"(SELECT src, count(*) AS d FROM ({edge_sql(word[0])}) WHERE src IN ({chain}) GROUP BY src)"
    return f"SELECT min(src) AS id FROM {deg} WHERE d = (SELECT quantile_disc(d, 0.5) FROM {deg})"


def shape_sql(names: list[str], tau: str, limit: int, max_len: int | None = None) -> str:
    """The answers of several templates, each from its own seed."""
    return " UNION ALL ".join(f"SELECT '{t}' AS template, * FROM ({rpq_sql(t, tau, seeds=witness_seed_sql(t), limit=limit, max_len=max_len)})" for t in names)


def seeded_sql(template: str, tau: str, limit: int | None, max_len: int | None = None) -> str:
    return rpq_sql(template, tau, seeds=median_seed_sql(seed_label(template)), limit=limit, max_len=max_len)
