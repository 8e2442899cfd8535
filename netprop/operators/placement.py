"""Placement of vertices on partitions by hash, range or cluster, through relabelling.

The engines deal vertices by Spark's hash of the id. To place a vertex on a part
of one's own, it gets a new id from those integers whose hash falls on that part;
then every engine runs unchanged, with one exchange a round, and the ids are
mapped back at the end.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F
from pyspark.sql.window import Window

from netprop import session
from netprop.operators import problems
from netprop.operators.graphs import Graph, undirected
from netprop.operators.ranks import numbered

#: Vertices that one step of the id pool covers.
POOL_STEP = 64


def part_of(graph: Graph, strategy: str, parts: int, attribute: DataFrame | None = None, rounds: int = 5) -> DataFrame:
    """``(id, part)``. 'hash': as the engines deal; 'range': by an ``(id, value)`` attribute; 'cluster': by communities."""
    if strategy == "hash":
        return graph.vertices.select("id", F.pmod(F.hash("id"), F.lit(parts)).alias("part"))
    if strategy == "range":
        rows = graph.vertices.join(attribute, "id", "left")
        sizes = rows.groupBy("value").agg(F.count("*").alias("n"))
        before = Window.orderBy("value").rowsBetween(Window.unboundedPreceding, -1)
        total = sizes.agg(F.sum("n").alias("all"))
        bins = sizes.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).join(F.broadcast(total))  # one row per attribute value
        bins = bins.select("value", F.least(F.lit(parts - 1), F.floor(F.col("before") * parts / F.col("all"))).cast("int").alias("part"))
        return rows.join(bins, rows["value"].eqNullSafe(bins["value"])).select("id", "part")
    if strategy == "cluster":
        return pack(communities(graph, rounds), parts)
    raise ValueError("hash, range or cluster")


def communities(graph: Graph, rounds: int = 5) -> DataFrame:
    """``(id, community)``: each vertex takes the heaviest label among its neighbours, ties to the smaller, a few times over."""
    edges = session.stored(undirected(graph).edges, "undirected")
    now = session.stored(graph.vertices.select("id", F.col("id").alias("community")), "communities")
    for _ in range(rounds):
        votes = edges.join(now, F.col("src") == F.col("id")).groupBy(F.col("dst").alias("id"), "community").agg(F.sum("w").alias("w"))
        won = votes.groupBy("id").agg(F.max_by("community", F.struct("w", -F.col("community"))).alias("new"))
        now = session.stored(now.join(won, "id", "left").select("id", F.least(F.coalesce("new", "community"), "community").alias("community")), "communities")
    return now


def pack(grouped: DataFrame, parts: int) -> DataFrame:
    """Communities in order of size onto parts: each part takes the next full share of vertices, so large ones may span parts."""
    sizes = grouped.groupBy("community").agg(F.count("*").alias("n"))
    # a community starts after those of larger size, and after earlier ones of its own size: one row per size in the window
    same = numbered(sizes, ["community"], "k", "n").withColumnRenamed("k", "earlier")
    each = sizes.groupBy("n").agg((F.sum("n")).alias("mass"))
    larger = each.select("n", F.coalesce(F.sum("mass").over(Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("larger"))
    placed = same.join(larger, "n").select("community", (F.col("larger") + F.col("earlier") * F.col("n")).alias("before"))
    total = sizes.agg(F.sum("n").alias("all"))
    rows = numbered(grouped, ["id"], "k", "community").join(placed, "community").join(F.broadcast(total))  # one row
    return rows.select("id", F.least(F.lit(parts - 1), F.floor((F.col("before") + F.col("k")) * parts / F.col("all"))).cast("int").alias("part"))


def relabel(graph: Graph, placed: DataFrame, parts: int) -> tuple[Graph, DataFrame]:
    """The graph under new ids whose hash is the wanted part, and the map ``(id, new_id)``."""
    spark = placed.sparkSession
    placed = session.stored(numbered(placed, ["id"], "k", "part"), "placed")
    most = placed.groupBy("part").count().agg(F.max("count")).first()[0] or 0
    size = 2 * parts * (most + POOL_STEP)
    while True:
        pool = spark.range(size).select(F.col("id").alias("new_id"), F.pmod(F.hash("id"), F.lit(parts)).alias("part"))
        if (pool.groupBy("part").count().agg(F.min("count"), F.count("*")).first() or (0, 0))[0] >= most:
            break
        size *= 2
    pool = numbered(pool, ["new_id"], "k", "part")
    names = session.stored(placed.join(pool, ["part", "k"]).select("id", "new_id"), "names")
    edges = graph.edges.join(names.select(F.col("id").alias("src"), F.col("new_id").alias("s")), "src").join(names.select(F.col("id").alias("dst"), F.col("new_id").alias("d")), "dst")
    return Graph(edges.select(F.col("s").alias("src"), F.col("d").alias("dst"), "w"), names.select(F.col("new_id").alias("id")), graph.name), names


def restore(state: DataFrame, names: DataFrame) -> DataFrame:
    return state.withColumnRenamed("id", "new_id").join(names, "new_id").select("id", *[c for c in state.columns if c != "id"])


def edge_cut(graph: Graph, placed: DataFrame) -> DataFrame:
    """One row: share of edges whose ends stand on different parts."""
    a, b = (placed.select(F.col("id").alias(e), F.col("part").alias(f"part_{e}")) for e in ("src", "dst"))
    return graph.edges.join(a, "src").join(b, "dst").agg(F.avg((F.col("part_src") != F.col("part_dst")).cast("double")).alias("cut"))


def balance(graph: Graph, placed: DataFrame) -> DataFrame:
    """One row: largest part against the mean, in vertices, out-edges and messages received."""
    v = placed.groupBy("part").agg(F.count("*").alias("v"))
    o = graph.edges.join(placed, F.col("src") == F.col("id")).groupBy("part").agg(F.count("*").alias("o"))
    m = graph.edges.join(placed, F.col("dst") == F.col("id")).groupBy("part").agg(F.count("*").alias("m"))
    return v.join(o, "part", "left").join(m, "part", "left").agg(*[(F.max(c) / F.avg(F.coalesce(c, F.lit(0)))).alias(n) for c, n in (("v", "vertices"), ("o", "edges"), ("m", "messages"))])


def placed_hops(graph: Graph, source: int, placed: DataFrame, parts: int, engine: str = "resident") -> DataFrame:
    from netprop.operators.engines import EngineOptions

    moved, names = relabel(graph, placed, parts)
    at = names.where(F.col("id") == source).first()["new_id"]
    return restore(problems.shortest_hops(moved, at, engine, options=EngineOptions(partitions=parts)).state, names)
