"""Headline queries; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

from rpqframe.functions.restrictors import RESTRICTORS
from rpqframe.plans.lower import rpq_paths
from rpqframe.plans.workload import SHAPES, materialized, run_method, templates, witness_seed
from rpqframe.queries import running_example
from rpqframe.sources.graph import graph_from_tables


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def run(name: str, make) -> None:
        begin = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - begin, 3)
        print(name, times[name], file=sys.stderr, flush=True)

    g = materialized(graph_from_tables(spark, sf))
    seeds = {t: witness_seed(g, t) for t in dict.fromkeys(templates(s)[0] for s, _ in SHAPES)}
    for t in ("likes.hasCreator", "knows+"):  # compiled code, open files and workers, as a loaded engine has
        run_method("algebra", g, t, witness_seed(g, t)).collect()
    run("running_example", lambda: running_example(spark, sf))
    for tau in ("trail", "simple", "acyclic"):
        run(f"all_sources_knows_{tau}", lambda tau=tau: rpq_paths(g, f"MATCH {tau} p = (x)-[knows+]->(y) RETURN p", strategy="doubling"))
    run("join_contains_suppliedBy", lambda: rpq_paths(g, "MATCH TRAIL p = (x)-[contains.suppliedBy]->(y) RETURN p"))
    for k, (shape, _) in enumerate(SHAPES, 1):
        t = templates(shape)[0]
        run(f"shape_{k:02d}_algebra", lambda t=t: run_method("algebra", g, t, seeds[t]))
    for k in (1, 4, 14, 25):
        t = templates(SHAPES[k - 1][0])[0]
        for method in ("bfs", "dfs"):
            run(f"shape_{k:02d}_{method}", lambda t=t, m=method: run_method(m, g, t, seeds[t]))
    for tau in RESTRICTORS:
        t = templates("(A.B)+")[0]
        run(f"shape_08_algebra_{tau}", lambda tau=tau: run_method("algebra", g, t, seeds[t], tau))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
