"""The two problems and their variants: hop counts and relational influence."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.window import Window

from netprop import session
from netprop.operators.engines import Engine, EngineOptions, RunResult, engine_of, options_of
from netprop.operators.graphs import Graph
from netprop.operators.program import VertexProgram

FAR = 2147483647


# ------------------------------------------------------------------------- hops


def hop_program(activation: str = "improved") -> VertexProgram:
    better = lambda: F.col("_d").isNotNull() & (F.col("hops").isNull() | (F.col("_d") < F.col("hops")))
    return VertexProgram(
        "hops", {"hops": "int"}, {"_d": lambda: F.col("hops") + 1}, {"_d": "min"}, {"hops": lambda: F.when(better(), F.col("_d")).otherwise(F.col("hops"))},
        lambda: F.col("hops").isNotNull(), better, activation, {"uses": "src dst"},
    )


def distance_program() -> VertexProgram:
    better = lambda: F.col("_d").isNotNull() & (F.col("distance").isNull() | (F.col("_d") < F.col("distance")))
    return VertexProgram(
        "distance", {"distance": "double"}, {"_d": lambda: F.col("distance") + F.col("w")}, {"_d": "min"}, {"distance": lambda: F.when(better(), F.col("_d")).otherwise(F.col("distance"))},
        lambda: F.col("distance").isNotNull(), better, "improved",
    )


def _sourced(graph: Graph, source: int | list[int], column: str, zero) -> DataFrame:
    sources = [source] if isinstance(source, int) else list(source)
    vertices = session.stored(graph.vertices, "vertices")
    found = vertices.where(F.col("id").isin(sources)).count()
    if found != len(set(sources)):
        raise ValueError("a source is not a vertex of the graph")
    at = F.col("id").isin(sources)
    return vertices.select("id", F.when(at, F.lit(zero)).alias(column), at.alias("_active"))


def shortest_hops(
    graph: Graph, source: int | list[int], engine: str | Engine = "resident", max_rounds: int | None = None, stop: str = "quiescent", activation: str = "improved",
    unreached: str = "null", options: EngineOptions | None = None,
) -> RunResult:
    """Fewest edges from the source (or the nearest of several): ``(id, hops)``; null, or 2147483647 with ``unreached='max'``, where there is no path.

    ``stop='quiescent'`` goes on until no message is pending, however deep the graph; 'fixed' runs ``max_rounds`` rounds (10).
    """
    result = engine_of(engine).run(graph, hop_program(activation), _sourced(graph, source, "hops", 0), max_rounds, stop, options_of(engine, options))
    if unreached == "max":
        result.state = result.state.select("id", F.coalesce("hops", F.lit(FAR)).alias("hops"))
    return result


def shortest_paths(graph: Graph, source: int | list[int], engine: str | Engine = "resident", max_rounds: int | None = None, options: EngineOptions | None = None) -> RunResult:
    """Least sum of weights from the source: ``(id, distance)``."""
    return engine_of(engine).run(graph, distance_program(), _sourced(graph, source, "distance", 0.0), max_rounds, "quiescent", options_of(engine, options))


def recursive_sql_hops(spark: SparkSession, graph: Graph, source: int, max_rounds: int = 10) -> DataFrame:
    """Hop counts up to ``max_rounds`` as one recursive query: every path is walked, ids once a level; the engine allows 100 levels, and any number of rows by ``LIMIT ALL``."""
    graph.edges.select("src", "dst").createOrReplaceTempView("netprop_hop_edges")
    return spark.sql(f"""
        WITH RECURSIVE walk(id, hops) AS (
          SELECT CAST({source} AS BIGINT), 0
          UNION ALL
          SELECT DISTINCT e.dst, walk.hops + 1 FROM walk JOIN netprop_hop_edges e ON e.src = walk.id WHERE walk.hops < {max_rounds}
        ) SELECT id, CAST(min(hops) AS INT) AS hops FROM (SELECT * FROM walk LIMIT ALL) GROUP BY id""")


def hop_histogram(result: DataFrame) -> DataFrame:
    return result.groupBy("hops").agg(F.count("*").alias("vertices"))


def unreached(result: DataFrame) -> DataFrame:
    return result.where("hops is null").select("id")


# -------------------------------------------------------------------- influence


def influence_program(seeds: str, activation: str, gate: str, columns: tuple[str, ...] = ("p",)) -> VertexProgram:
    """Weighted mean of the labelled in-neighbours; every class has its own likelihood, all share one denominator."""

    def new(c):
        mean = F.when(F.col("_sw") > 0, F.col(f"_s_{c}") / F.col("_sw"))
        if seeds == "overwrite":
            return lambda: F.coalesce(mean, F.col(c))
        if seeds == "clamped":
            return lambda: F.when(F.col("is_seed"), F.col(c)).otherwise(F.coalesce(mean, F.col(c)))
        return lambda: F.coalesce(F.col(c), mean)  # 'first': a label once held stays

    first = columns[0]
    update = {c: new(c) for c in columns} | {"is_seed": lambda: F.col("is_seed")}
    return VertexProgram(
        "influence", {c: "double" for c in columns} | {"is_seed": "boolean"},
        {f"_s_{c}": (lambda c=c: F.col(c) * F.col("w")) for c in columns} | {"_sw": lambda: F.col("w")}, {f"_s_{c}": "sum" for c in columns} | {"_sw": "sum"},
        update, (lambda: F.col(first).isNotNull()), lambda: ~update[first]().eqNullSafe(F.col(first)), activation, {"gate": gate},
    )


def relational_influence(
    graph: Graph, labels: DataFrame, rounds: int = 10, engine: str | Engine = "resident", seeds: str = "clamped", gate: str = "known", activation: str = "all",
    prior: float | None = None, stop: str = "fixed", options: EngineOptions | None = None,
) -> RunResult:
    """Likelihood of every vertex from the labels of some: ``(id, p)``.

    ``seeds``: known labels are 'clamped', 'overwrite'n like all others, or a label
    once held stays ('first'). ``gate='known'``: vertices without a label send
    nothing; 'all': they start from ``prior``. ``activation``: 'all' labelled
    vertices send each round, or only those that got a message ('messaged').
    """
    if seeds not in ("clamped", "overwrite", "first") or gate not in ("known", "all"):
        raise ValueError("seeds: clamped, overwrite, first; gate: known, all")
    if gate == "all" and prior is None:
        raise ValueError("gate='all' needs a prior")
    known = labels.groupBy("id").agg(F.max("p").alias("p"))
    ids = graph.vertices.select("id").unionByName(labels.select("id")).distinct()
    start = F.col("p") if gate == "known" else F.coalesce("p", F.lit(prior))
    state = ids.join(known, "id", "left").select("id", start.alias("p"), F.col("p").isNotNull().alias("is_seed"))
    result = engine_of(engine).run(graph, influence_program(seeds, activation, gate), state, rounds, stop, options_of(engine, options))
    result.state = result.state.select("id", "p")
    return result


def relational_influence_classes(
    graph: Graph, labels: DataFrame, classes: int, rounds: int = 10, engine: str | Engine = "resident", seeds: str = "clamped", layout: str = "array", options: EngineOptions | None = None
) -> DataFrame:
    """Likelihood of each class: ``(id, class, p)`` rows with p above 0, from ``(id, class, p)`` labels.

    ``layout='array'``: a column per class, on any engine; 'long': a row per
    vertex and class that occurs, for many classes, on its own loop.
    """
    if layout == "long":
        return _classes_long(graph, labels, rounds, seeds, options)
    columns = tuple(f"p{k}" for k in range(classes))
    known = labels.groupBy("id").agg(*[F.coalesce(F.sum(F.when(F.col("class") == k, F.col("p"))), F.lit(0.0)).alias(c) for k, c in enumerate(columns)])
    ids = graph.vertices.select("id").unionByName(labels.select("id")).distinct()
    state = ids.join(known, "id", "left").withColumn("is_seed", F.col(columns[0]).isNotNull())
    out = engine_of(engine).run(graph, influence_program(seeds, "all", "known", columns), state, rounds, "fixed", options_of(engine, options)).state
    cells = F.array(*[F.struct(F.lit(k).alias("class"), F.col(c).alias("p")) for k, c in enumerate(columns)])
    return out.select("id", F.explode(cells).alias("x")).select("id", "x.class", "x.p").where("p > 0")


def _classes_long(graph: Graph, labels: DataFrame, rounds: int, seeds: str, options: EngineOptions | None) -> DataFrame:
    spark = labels.sparkSession
    n = (options or EngineOptions()).sized(spark).partitions
    with session.loop_conf(spark, n):
        structure = graph.edges.select("src", "dst", "w").repartition(n, "src").persist()
        known = labels.groupBy("id", "class").agg(F.sum("p").alias("p")).where("p > 0")
        marks = labels.select("id").distinct().withColumn("is_seed", F.lit(True)).persist()
        now = session.stored(known, "classes")
        for _ in range(rounds):
            sent = structure.join(now, F.col("src") == F.col("id"))
            mass = sent.groupBy(F.col("dst").alias("id"), "class").agg(F.sum(F.col("p") * F.col("w")).alias("lw"))
            holders = now.select("id").distinct()
            total = structure.join(holders, F.col("src") == F.col("id")).groupBy(F.col("dst").alias("id")).agg(F.sum("w").alias("sw"))
            new = mass.join(total, "id").select("id", "class", (F.col("lw") / F.col("sw")).alias("p"))
            if seeds == "clamped":
                new = new.join(marks, "id", "left_anti").unionByName(now.join(marks, "id", "left_semi"))
                stay = now.join(total, "id", "left_anti").join(marks, "id", "left_anti")
            else:
                stay = now.join(total, "id", "left_anti")
            now = session.stored(new.unionByName(stay), "classes")
        structure.unpersist()
        marks.unpersist()
    return now


def decide(result: DataFrame, rule: str = "argmax") -> DataFrame:
    """'threshold': ``(id, positive)`` of ``(id, p)``, ties positive. 'argmax': ``(id, class)`` of ``(id, class, p)``, p to 9 places, ties to the smaller class."""
    if rule == "threshold":
        return result.where("p is not null").select("id", (F.col("p") >= 0.5).alias("positive"))
    return result.groupBy("id").agg(F.max_by("class", F.struct(F.round("p", 9), -F.col("class"))).alias("class"))


def transferred_influence(source: DataFrame, target: Graph, labels: DataFrame, rounds: int = 10, engine: str | Engine = "resident", seeds: str = "clamped", options: EngineOptions | None = None) -> RunResult:
    """Across networks: influence on ``target`` whose unlabelled vertices start from the mean likelihood of ``(id, p)`` results of another network."""
    prior = source.agg(F.avg("p")).first()[0]
    return relational_influence(target, labels, rounds, engine, seeds, gate="known" if prior is None else "all", prior=prior, options=options)


def transfer_prior(source: DataFrame, target: Graph) -> DataFrame:
    """Across networks: each vertex of ``target`` starts with the class distribution of ``(id, class, p)`` results: ``(id, class, p)``."""
    share = source.groupBy("class").agg(F.sum("p").alias("m"))
    total = share.agg(F.sum("m").alias("t"))
    dist = share.join(F.broadcast(total)).select("class", (F.col("m") / F.col("t")).alias("p"))  # one row per class
    return target.vertices.select("id", F.explode(_literal(dist)).alias("x")).select("id", "x.class", "x.p")


def _literal(dist: DataFrame):
    rows = dist.orderBy("class").collect()  # classes are few
    return F.array(*[F.struct(F.lit(r["class"]).cast("int").alias("class"), F.lit(r["p"]).alias("p")) for r in rows]) if rows else F.array().cast("array<struct<class:int,p:double>>")


def neighbour_label_features(graph: Graph, labels: DataFrame) -> DataFrame:
    """``(id, class, share)``: share of labelled in-neighbour weight that each class has."""
    sent = graph.edges.join(labels, F.col("src") == F.col("id")).select(F.col("dst").alias("id"), "class", (F.col("w") * F.col("p")).alias("m"))
    got = sent.groupBy("id", "class").agg(F.sum("m").alias("m"))
    return got.select("id", "class", (F.col("m") / F.sum("m").over(Window.partitionBy("id"))).alias("share"))


def brute(edges: list[tuple], state: dict, kind: str, rounds: int, seeds: str = "clamped", marked: set | None = None) -> dict:
    """Plain loops over a small graph, for tests: hop counts, or likelihoods of ``state`` (id to value or None)."""
    now = dict(state)
    for _ in range(rounds):
        new = dict(now)
        if kind == "hops":
            for s, d, _w in edges:
                if now[s] is not None and (new[d] is None or now[s] + 1 < new[d]):
                    new[d] = now[s] + 1
        else:
            for v in now:
                into = [(now[s], w) for s, d, w in edges if d == v and now[s] is not None]
                if into and not (seeds == "clamped" and v in (marked or ())) and not (seeds == "first" and now[v] is not None):
                    new[v] = sum(p * w for p, w in into) / sum(w for _, w in into)
        now = new
    return now
