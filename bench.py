"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

from pyspark.sql import SparkSession

ENGINES = ("reshuffle2", "colocated", "resident")
GRAPHS = ("call_next", "call_top", "related", "follow")
ROUNDS = 10
#: A generated graph with hubs, where a round moves enough rows to outweigh the start of its jobs: vertices, out-edges, rounds.
HUBS, HUB_ROUNDS = (500_000, 20), 3


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1").rstrip("/")
    cpus = os.environ.get("BENCH_CPUS", "8")
    base = tempfile.mkdtemp(prefix="netprop-bench-")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", f"file://{base}/shared").config("spark.sql.warehouse.dir", f"{base}/warehouse").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from netprop import experiments
    from netprop.operators import workloads

    queries: dict[str, float] = {}
    rounds: dict[str, float] = {}
    traffic: dict[str, dict] = {}

    def timed(name, job):
        began = time.perf_counter()
        result = job()
        queries[name] = round(time.perf_counter() - began, 3)
        rounds[name] = round(sum(t["ms"] for t in result.trace) / 1000 / result.rounds, 4)  # the load counts
        traffic[name] = {k: result.trace[-1][k] for k in ("shuffle_rows", "shuffle_bytes", "stored_rows", "stored_bytes")}

    workloads.run(spark, sf_dir, "hops", "call_next", "resident", 2)  # warm-up, not counted
    for problem in ("hops", "influence"):
        for graph in GRAPHS:
            for engine in ENGINES:
                timed(f"{problem}_{engine}_{graph}", lambda p=problem, g=graph, e=engine: workloads.run(spark, sf_dir, p, g, e, ROUNDS, "fixed"))
    hubs = experiments.hub_graph(spark, HUBS)
    for engine in ENGINES:
        timed(f"influence_{engine}_hubs", lambda e=engine: workloads.run_on(hubs, "influence", e, HUB_ROUNDS, "fixed"))
    ratios = {}
    for problem, graph in [(p, g) for p in ("hops", "influence") for g in GRAPHS] + [("influence", "hubs")]:
        base_time = rounds[f"{problem}_reshuffle2_{graph}"]
        ratios[f"{problem}_{graph}"] = {e: round(base_time / rounds[f"{problem}_{e}_{graph}"], 2) for e in ENGINES[1:]}
    print(json.dumps({"metric": "total time of two problems on four graphs and three execution models, ten rounds each, and three rounds on a generated graph of some 10^7 edges", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": sf_dir.rpartition("sf")[2], "mean_round_sec": rounds, "times_as_fast_as_reshuffle": ratios, "last_round": traffic}))
    spark.stop()


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
