"""The experiments, each runnable: ``python -m netprop.experiments W5 --sf /root/testdata/sf0.1 --out w5.json``.

W1, W2    both problems on four graphs by every execution model
W3, W4    time by size of the graph, and R2 against vertices and edges
W5        time by number of cores, each count in a session of its own, and by partitions
W6, W7    total time by number of rounds with its straight line: influence; hops on deep graphs
W8        the memory wall: the resident model with little memory, by storage level
W9        messages and active vertices a round of the two problems
W10       the first round against the others, from W6 and W7
W11       placements: edge cut, balance, time
W12       combiner on, off and salted on a generated graph with hubs: rows and bytes through exchanges
W13       coverage and accuracy by share of seeds and rounds

Everything is printed as tables of rows and, with ``--out``, written as JSON.
"""

from __future__ import annotations

import argparse
import json
import os
import subprocess
import sys
import tempfile

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop.operators import engines, graphs, measure, workloads

#: Vertices and out-edges of the generated graph with hubs: about 10^7 edges.
HUB_GRAPH = (1_000_000, 10)


def start(cores: int | str = "*", memory: str = "8g", partitions: int = 8) -> SparkSession:
    base = tempfile.mkdtemp(prefix="netprop-experiment-")  # one process: driver and executor share it
    spark = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", memory).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", str(partitions)).config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", f"file://{base}/shared").config("spark.sql.warehouse.dir", f"{base}/warehouse").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def rows(df: DataFrame) -> list[dict]:
    """A measure's rows: a handful per run."""
    return [r.asDict() for r in df.collect()]


def hub_graph(spark: SparkSession, size: tuple[int, int] = HUB_GRAPH) -> graphs.Graph:
    from dataclasses import replace

    from netprop import session

    graph = graphs.power_law(spark, *size)
    return replace(graph, edges=session.stored(graph.edges, "hubs"))


def models(spark, sf_dir, problem, rounds=10, names=workloads.STAND_INS) -> dict:
    trace = workloads.compare_engines(spark, sf_dir, problem, names, rounds=rounds).cache()
    return {"mean_round_ms": rows(measure.mean_round_ms(trace)), "speed_up": rows(measure.speedup(trace, "reshuffle2")), "traffic": rows(traffic(trace))}


def traffic(trace: DataFrame) -> DataFrame:
    """Per run: rows and bytes through exchanges, rows and bytes stored, of a round after the load."""
    return trace.where("round > 0").groupBy(*measure.RUN).agg(*[F.avg(c).cast("long").alias(c) for c in ("shuffle_rows", "shuffle_bytes", "stored_rows", "stored_bytes")])


def sizes(spark, sf_dir, problem, rounds=10) -> dict:
    """One graph at three sizes, and three graphs at one."""
    folder = os.path.dirname(sf_dir.rstrip("/"))
    dirs = [d for d in (f"{folder}/sf{x}" for x in ("0.001", "0.01", "0.1")) if os.path.isdir(d)]
    trace = workloads.compare_sizes(spark, dirs, problem, "follow", rounds=rounds).cache()
    profile = None
    for d in dirs:
        row = graphs.graph_profile(workloads.build(spark, d, "follow")).select(F.lit(f"follow@{os.path.basename(d)}").alias("graph"), "vertices", "edges")
        profile = row if profile is None else profile.unionByName(row)
    return {"mean_round_ms": rows(measure.mean_round_ms(trace)), "fit": rows(measure.size_fit(trace, profile))}


def one_run(sf_dir: str, problem: str, graph: str, engine: str, rounds: int, cores: int, memory: str = "8g", partitions: int = 8, storage: str = "MEMORY_AND_DISK", size: str = "") -> list[dict] | None:
    """The trace of one run in a session of its own; None where the run fails."""
    task = json.dumps([sf_dir, problem, graph, engine, rounds, cores, memory, partitions, storage, size])
    done = subprocess.run([sys.executable, "-m", "netprop.experiments", "--task", task], capture_output=True, text=True, cwd=os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    last = done.stdout.strip().rpartition("\n")[2]
    return json.loads(last) if done.returncode == 0 and last.startswith("[") else None


def task(sf_dir, problem, graph, engine, rounds, cores, memory, partitions, storage, size) -> list[dict]:
    spark = start(cores, memory, partitions)
    options = engines.EngineOptions(partitions=partitions, storage=storage)
    if graph == "hubs":
        found = workloads.run_on(hub_graph(spark, tuple(map(int, size.split("x")))), problem, engine, rounds, options=options)
    else:
        g = workloads.ready(spark, sf_dir, graph)
        found = workloads.run_on(g, problem, engine, rounds, "fixed", options, workloads.source_of, lambda g: workloads.labels_for(spark, sf_dir, graph, g))
    return [t | {"engine": engine, "graph": graph, "cores": cores} for t in found.trace]


def _trace(spark, runs: list[list[dict]]) -> DataFrame:
    from netprop import schemas

    return spark.createDataFrame([tuple(t.get(f.name) for f in schemas.TRACE) for run in runs for t in run], schemas.TRACE).cache()


def cores(spark, sf_dir, problem, counts=(1, 2, 4, 8), names=("follow",), which=("reshuffle2", "colocated", "resident"), rounds=3) -> dict:
    """Time by cores, the factor against the fewest, and the fewest near the best."""
    runs = [one_run(sf_dir, problem, g, e, rounds, c) for g in names for e in which for c in counts]
    trace = _trace(spark, [r for r in runs if r])
    parts = workloads.compare_partitions(spark, sf_dir, problem, names[0], (1, 2, 4, 8, 16, 32), ("resident",), rounds).cache()
    by_parts = parts.groupBy("engine", "partitions").agg((F.sum("ms") / F.max("round")).alias("mean_ms"))
    return {"by_cores": rows(measure.scale_out(trace)), "by_partitions": rows(by_parts)}


def totals(spark, sf_dir, problem, graph, which=("reshuffle2", "colocated", "resident"), rounds=10) -> dict:
    """Cumulative time by round, its straight line and R2, the first round against the others, and where the resident model has paid for its load."""
    workloads.run(spark, sf_dir, problem, graph, "resident", 2)  # warm-up
    trace = workloads.compare_engines(spark, sf_dir, problem, (graph,), which, rounds).cache()
    return {"total_ms": rows(measure.cumulative_ms(trace)), "fit": rows(measure.linear_fit(trace)), "first_round": rows(measure.first_round_ratio(trace)), "break_even": rows(measure.break_even(trace, base="reshuffle2"))}


def memory_wall(spark, sf_dir, size="400000x10", memories=("600m", "1g", "4g"), levels=("MEMORY_ONLY", "MEMORY_AND_DISK", "DISK_ONLY"), rounds=2) -> dict:
    """The resident model on a graph with hubs by memory and storage level (a run that fails has no time), and the model map-side join beside it; with the need that is computed beforehand."""
    n, m = map(int, size.split("x"))
    program = workloads.problems.influence_program("overwrite", "all", "known")
    graph = hub_graph(spark, (n // 10, m))
    overhead = engines.cache_overhead(spark, graph.edges, 10)
    need = engines.memory_need(n, n * m, program, overhead=overhead)
    out = []
    for memory in memories:
        for engine, level in [*(("resident", x) for x in levels), ("colocated", "DISK_ONLY")]:
            found = one_run(sf_dir, "influence", "hubs", engine, rounds, 4, memory, 8, level, size)
            out.append({"memory": memory, "engine": engine, "storage": level, "mean_ms": sum(t["ms"] for t in found) / rounds if found else None})
    return {"need_bytes": need, "cache_overhead": overhead, "runs": out}


def communication(spark, sf_dir, graph="follow") -> dict:
    out = {}
    for problem in ("hops", "influence"):
        found = workloads.run(spark, sf_dir, problem, graph, "resident", 10)
        out[problem] = [{k: t[k] for k in ("round", "active", "messages", "improved", "shuffle_rows", "shuffle_bytes")} for t in found.trace]
    return out


def placements(spark, sf_dir, parts=8) -> dict:
    out = {}
    for name in ("follow", "entity", "wordlink"):
        graph = workloads.ready(spark, sf_dir, name)
        if name == "wordlink":
            attribute = workloads.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.hash("lang").cast("long").alias("value"))
        else:
            attribute = workloads.places_of(spark, sf_dir) if name == "entity" else graph.vertices.select("id", F.pmod("id", F.lit(2)).cast("long").alias("value"))
        out[name] = rows(workloads.compare_placements(spark, graph, 0, attribute, parts))
    return out


def combiner(spark, sf_dir, size=HUB_GRAPH, rounds=2, partitions=8) -> dict:
    graph = hub_graph(spark, size)
    found = workloads.compare_combine(spark, graph, graphs.mask_labels(graphs.coin_labels(graph)), rounds, partitions, hub_degree=10_000)
    return {k: [{c: t[c] for c in ("round", "ms", "messages", "shuffle_rows", "shuffle_bytes")} for t in r.trace] for k, r in found.items()} | {"largest_in_degree": rows(graphs.top_hubs(graph, 1))}


EXPERIMENTS = {
    "W1": lambda s, d: models(s, d, "influence"),
    "W2": lambda s, d: models(s, d, "hops"),
    "W3": lambda s, d: sizes(s, d, "influence"),
    "W4": lambda s, d: sizes(s, d, "hops"),
    "W5": lambda s, d: {p: cores(s, d, p) for p in ("influence", "hops")},
    "W6": lambda s, d: totals(s, d, "influence", "call_top"),
    "W7": lambda s, d: {g: totals(s, d, "hops", g) for g in ("chain", "sequence")},
    "W8": memory_wall,
    "W9": communication,
    "W10": lambda s, d: {p: totals(s, d, p, "follow")["first_round"] for p in ("influence", "hops")},
    "W11": placements,
    "W12": combiner,
    "W13": lambda s, d: rows(workloads.seed_sweep(s, d)),
}


def main() -> None:
    args = argparse.ArgumentParser(description=__doc__, formatter_class=argparse.RawDescriptionHelpFormatter)
    args.add_argument("which", nargs="*", choices=[*EXPERIMENTS, []], help="W1 ... W13")
    args.add_argument("--sf", default="/root/testdata/sf0.1")
    args.add_argument("--cores", default="*")
    args.add_argument("--out")
    args.add_argument("--task", help=argparse.SUPPRESS)
    given = args.parse_args()
    if given.task:
        print(json.dumps(task(*json.loads(given.task))))
        return
    spark, found = start(given.cores), {}
    for name in given.which:
        found[name] = EXPERIMENTS[name](spark, given.sf)
        print(name, json.dumps(found[name], default=str), flush=True)
    if given.out:
        with open(given.out, "w") as f:
            json.dump(found, f, default=str, indent=1)
    spark.stop()


if __name__ == "__main__":
    main()
