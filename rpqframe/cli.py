"""Command line: load a graph, run a query, print the table, the number of paths and the time."""

from __future__ import annotations

import argparse
import sys
import time

from pyspark.sql import SparkSession

from rpqframe.plans.lang import parse
from rpqframe.plans.lower import explain_rpq, rpq
from rpqframe.sources.graph import graph_from_tables, load_graph, toy_graph


def main(argv: list[str] | None = None) -> int:
    p = argparse.ArgumentParser(prog="rpqframe", description=__doc__)
    p.add_argument("--nodes")
    p.add_argument("--edges")
    p.add_argument("--format", default="csv")
    p.add_argument("--tables", help="folder of the relational tables")
    p.add_argument("--query", required=True)
    p.add_argument("--limit", type=int, default=0, help="used where the query has none")
    p.add_argument("--timeout", type=float, default=120.0)
    p.add_argument("--max-len", type=int)
    p.add_argument("--explain", action="store_true")
    a = p.parse_args(argv)
    spark = SparkSession.builder.appName("rpqframe").getOrCreate()
    g = load_graph(spark, a.nodes, a.edges, a.format) if a.nodes else graph_from_tables(spark, a.tables) if a.tables else toy_graph(spark)
    text = a.query if parse(a.query).limit or not a.limit else f"{a.query} LIMIT {a.limit}"
    if a.explain:
        print(explain_rpq(g, text))
        return 0
    begin = time.perf_counter()
    df = rpq(g, text, timeout_s=a.timeout, max_len=a.max_len)
    n = 0
    print(" | ".join(df.columns))
    for row in df.toLocalIterator():
        print(" | ".join("null" if v is None else str(v) for v in row))
        n += 1
    print(f"{n} paths in {time.perf_counter() - begin:.3f} s")
    return 0


if __name__ == "__main__":
    sys.exit(main())
