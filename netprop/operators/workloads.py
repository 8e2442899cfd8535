"""The experiment workloads on the given tables: traces of problems, engines, graphs, sizes, partitions."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop import session
from netprop.operators import engines, graphs, problems
from netprop.operators.graphs import Graph
from netprop.sources.tables import table

ENGINES = ("reshuffle2", "reshuffle1", "reduce_merge", "colocated", "resident")
#: Graphs that stand for the four networks, smallest first.
STAND_INS = ("call_next", "call_top", "related", "follow")


def build(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    t = lambda n: table(spark, sf_dir, n)
    return {
        "call": lambda: graphs.call_graph(t("events")), "call_top": lambda: graphs.call_graph(t("events"), (1, 2)), "call_next": lambda: graphs.call_graph(t("events"), (3, 4)),
        "related": lambda: graphs.related_graph(t("lineitem")), "follow": lambda: graphs.follow_graph(t("orders"), t("lineitem")), "sequence": lambda: graphs.sequence_graph(t("lineitem")),
        "chain": lambda: graphs.chain_graph(t("orders")), "entity": lambda: graphs.entity_graph(t("orders"), t("lineitem"), t("supplier"), t("nation")),
        "wordlink": lambda: graphs.wordlink_graph(t("documents")), "host": lambda: graphs.host_graph(t("pages")),
    }[name]()


def ready(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The graph with its edges written once: a run reads them several times."""
    graph = build(spark, sf_dir, name)
    return replace(graph, edges=session.stored(graph.edges, f"edges-{name}"))


def places_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(id, value)``: the nation of customers, their orders, suppliers and nations in the entity graph, by which it may be placed."""
    t = lambda n: table(spark, sf_dir, n)
    key = lambda c, k: (F.col(c).cast("long") * 8 + k).alias("id")
    customers = t("customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("value"))
    orders = t("orders").join(customers, F.col("o_custkey") == F.col("c_custkey")).select(key("o_orderkey", 1), "value")
    rows = customers.select(key("c_custkey", 0), "value").unionByName(orders)
    return rows.unionByName(t("supplier").select(key("s_suppkey", 3), F.col("s_nationkey").cast("long").alias("value"))).unionByName(t("nation").select(key("n_nationkey", 4), F.col("n_nationkey").cast("long").alias("value")))


def labels_for(spark: SparkSession, sf_dir: str, name: str, graph: Graph) -> DataFrame:
    """Scalar labels: duration shares on call graphs, coins elsewhere."""
    if name.startswith("call"):
        events = table(spark, sf_dir, "events")
        ranks = (3, 4) if name == "call_next" else (1, 2)
        return share_labels(events, ranks)
    return graphs.coin_labels(graph)


def share_labels(events: DataFrame, ranks: tuple[int, int] = (1, 2)) -> DataFrame:
    """Share of talk time in the more popular of two tariffs; calls to oneself are talk time too."""
    popular = graphs.rank_tariffs(events, "event_type")
    name = popular.where(F.col("rank") == ranks[0]).select(F.col("tariff").alias("first"))
    own = events.select(F.col("user_id").alias("src"), F.col("event_type").alias("tariff"), F.round(F.col("value") * 100).cast("long").alias("dur"))
    calls = graphs.only_tariffs(own, events, ranks).join(F.broadcast(name))  # one row
    return graphs.duration_share(calls, F.col("first"))


def source_of(graph: Graph, name: str) -> int:
    return graph.edges.agg(F.min("src")).first()[0] if name == "chain" else 0


def run(spark: SparkSession, sf_dir: str, problem: str, name: str, engine: str, rounds: int = 10, stop: str = "fixed", partitions: int | None = None) -> engines.RunResult:
    return run_on(ready(spark, sf_dir, name), problem, engine, rounds, stop, engines.EngineOptions(partitions=partitions), source_of, lambda g: labels_for(spark, sf_dir, name, g))


def run_on(graph: Graph, problem: str, engine: str, rounds: int = 10, stop: str = "fixed", options: engines.EngineOptions | None = None, source=None, labels=graphs.coin_labels) -> engines.RunResult:
    """One problem on one graph: hops from ``source`` (a function of graph and name; else vertex 0), or influence of masked ``labels``."""
    if problem == "hops":
        return problems.shortest_hops(graph, source(graph, graph.name) if source else 0, engine, rounds, stop, options=options)
    return problems.relational_influence(graph, graphs.mask_labels(labels(graph)), rounds, engine, "overwrite", stop=stop, options=options)


def compare_engines(spark: SparkSession, sf_dir: str, problem: str, names=STAND_INS, which=ENGINES, rounds: int = 10) -> DataFrame:
    """Traces of one problem on several graphs and engines, as one frame (W1, W2)."""
    return _traces(spark, [(problem, n, e, rounds, None, sf_dir) for n in names for e in which])


def compare_sizes(spark: SparkSession, sf_dirs: list[str], problem: str, name: str = "follow", which=ENGINES, rounds: int = 10) -> DataFrame:
    """Traces of one graph at several sizes (W3, W4); graph names carry the size."""
    return _traces(spark, [(problem, name, e, rounds, None, d) for d in sf_dirs for e in which], sized=True)


def compare_partitions(spark: SparkSession, sf_dir: str, problem: str, name: str, counts=(1, 2, 4, 8, 16, 32), which=ENGINES, rounds: int = 10) -> DataFrame:
    """Traces by partition count within one session; core counts need sessions of their own (experiments.cores)."""
    return _traces(spark, [(problem, name, e, rounds, p, sf_dir) for p in counts for e in which])


def compare_combine(spark: SparkSession, graph: Graph, labels: DataFrame, rounds: int = 3, partitions: int | None = None, hub_degree: int = 100) -> dict[str, engines.RunResult]:
    """Influence with the combiner, without, and with salted hubs (W12)."""
    kinds = {"on": {}, "off": {"combine": False}, "salted": {"salt": 8, "hub_degree": hub_degree}}
    return {k: problems.relational_influence(graph, labels, rounds, options=engines.EngineOptions(partitions=partitions, **o)) for k, o in kinds.items()}


def compare_placements(spark: SparkSession, graph: Graph, source: int, attribute: DataFrame, parts: int, engine: str = "resident") -> DataFrame:
    """``(strategy, cut, vertices, edges, messages, mean_ms)``: edge cut, balance and time of a hop search by placement (W11)."""
    from netprop.operators import placement

    rows = []
    for strategy in ("hash", "range", "cluster"):
        placed = session.stored(placement.part_of(graph, strategy, parts, attribute), "placed")
        moved, names = placement.relabel(graph, placed, parts)
        moved = replace(moved, edges=session.stored(moved.edges, "moved"))
        at = names.where(F.col("id") == source).first()["new_id"]
        result = problems.shortest_hops(moved, at, engine, options=engines.EngineOptions(partitions=parts))
        cut, even = placement.edge_cut(graph, placed).first(), placement.balance(graph, placed).first()
        rows.append((strategy, cut["cut"], even["vertices"], even["edges"], even["messages"], sum(t["ms"] for t in result.trace) / max(result.rounds, 1)))
    return spark.createDataFrame(rows, "strategy string, cut double, vertices double, edges double, messages double, mean_ms double")


def _traces(spark: SparkSession, jobs: list[tuple], sized: bool = False) -> DataFrame:
    from netprop import schemas

    rows = []
    for problem, name, engine, rounds, partitions, sf_dir in jobs:
        result = run(spark, sf_dir, problem, name, engine, rounds, "fixed", partitions)
        label = f"{name}@{sf_dir.rstrip('/').rpartition('/')[2]}" if sized else name
        rows += [t | {"engine": engine, "graph": label} for t in result.trace]
    return spark.createDataFrame([tuple(t.get(f.name) for f in schemas.TRACE) for t in rows], schemas.TRACE)


def seed_sweep(spark: SparkSession, sf_dir: str, shares=(0.1, 0.3, 0.5, 0.7, 0.9), rounds=(1, 3, 10), seeds=("clamped", "overwrite")) -> DataFrame:
    """Coverage and accuracy on the word-link graph by share of seeds and number of rounds (W13)."""
    from netprop.operators import measure

    graph = build(spark, sf_dir, "wordlink")
    truth, classes = graphs.class_index(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("name")))
    k, out = classes.count(), None
    for share in shares:
        mask = graphs.mask_labels(truth, share)
        hidden = truth.join(mask.select("id"), "id", "left_anti")
        for r in rounds:
            for how in seeds:
                found = problems.relational_influence_classes(graph, mask, k, r, seeds=how)
                row = measure.holdout_scores(problems.decide(found), truth, hidden).select(F.lit(share).alias("share"), F.lit(r).alias("rounds"), F.lit(how).alias("seeds"), "*")
                out = row if out is None else out.unionByName(row)
    return out
