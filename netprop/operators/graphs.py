"""Graphs: the value type, builders from the given tables, labels, transforms, generators, profiles."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, functions as F
from pyspark.sql.window import Window

from netprop import schemas

#: Seconds of the order column in one cell of :func:`ordered_lead`.
CELL_SECONDS = 3600


@dataclass(frozen=True)
class Graph:
    """Directed weighted edges; isolated vertices come from ``extra``."""

    edges: DataFrame
    extra: DataFrame | None = None
    name: str = "graph"

    @classmethod
    def of(cls, edges: DataFrame, vertices: DataFrame | None = None, name: str = "graph", multi: str = "sum") -> Graph:
        """``multi``: parallel edges are summed, or kept as they are. Weights of 0 or less are refused by :meth:`checked`."""
        edges = schemas.conform(edges if "w" in edges.columns else edges.withColumn("w", F.lit(1.0)), schemas.EDGES)
        if multi == "sum":
            edges = edges.groupBy("src", "dst").agg(F.sum("w").alias("w"))
        elif multi != "keep":
            raise ValueError("multi is 'sum' or 'keep'")
        return cls(edges, vertices, name)

    @property
    def vertices(self) -> DataFrame:
        ids = self.edges.select(F.col("src").alias("id")).unionByName(self.edges.select(F.col("dst").alias("id")))
        return (ids if self.extra is None else ids.unionByName(self.extra.select(F.col("id").cast("long")))).distinct()

    def checked(self) -> Graph:
        """Fails where an edge has a null end or a weight that is null or not above 0."""
        if self.edges.where("src is null or dst is null or w is null or not w > 0").take(1):
            raise ValueError("edges need ids and weights above 0")
        return self

    def named(self, name: str) -> Graph:
        return replace(self, name=name)


# ----------------------------------------------------------------- call records


def ordered_lead(df: DataFrame, ts: str, tie: str, value: str, out: str, cell_seconds: int = CELL_SECONDS) -> DataFrame:
    """``value`` of the next row by (ts, tie), as a global lead without a single-task window.

    Rows are led within cells of time; the last row of a cell takes the first
    value of the next cell that has rows, from a table of one row per cell.
    """
    cell = F.floor(F.unix_micros(F.col(ts).cast("timestamp")) / F.lit(cell_seconds * 1_000_000)).cast("long")
    df = df.withColumn("_cell", cell)
    firsts = df.groupBy("_cell").agg(F.min(F.struct(ts, tie, value)).getField(value).alias("_v"))
    follow = firsts.select("_cell", F.lead("_v").over(Window.orderBy("_cell")).alias("_next"))
    within = Window.partitionBy("_cell").orderBy(ts, tie)
    led = df.withColumn("_lead", F.lead(value).over(within)).withColumn("_last", F.lead(tie).over(within).isNull())
    return led.join(follow, "_cell").withColumn(out, F.when(F.col("_last"), F.col("_next")).otherwise(F.col("_lead"))).drop("_cell", "_lead", "_last", "_next")


def call_records(events: DataFrame, to_self: bool = False) -> DataFrame:
    """Each event is a call from its user to the user of the next event, in hundredths of its value; calls to oneself only ``to_self``."""
    led = ordered_lead(events.select("event_id", "ts", "user_id", "event_type", "value"), "ts", "event_id", "user_id", "dst")
    rows = led.select("ts", F.col("user_id").alias("src"), "dst", F.col("event_type").alias("tariff"), F.round(F.col("value") * 100).cast("long").alias("dur"))
    return rows.where("dst is not null" if to_self else "dst is not null and src <> dst")


def rank_tariffs(calls: DataFrame, by: str = "tariff") -> DataFrame:
    """``(tariff, n, rank)``, most frequent first, ties by name: as many rows as there are tariffs."""
    counts = calls.groupBy(F.col(by).alias("tariff")).agg(F.count("*").alias("n"))
    return counts.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "tariff")))


def only_tariffs(calls: DataFrame, events: DataFrame, ranks: tuple[int, ...]) -> DataFrame:
    wanted = rank_tariffs(events, "event_type").where(F.col("rank").isin(*ranks)).select("tariff")
    return calls.join(F.broadcast(wanted), "tariff", "left_semi")  # a handful of tariff names


def call_graph(events: DataFrame, ranks: tuple[int, ...] | None = None) -> Graph:
    calls = call_records(events)
    if ranks:
        calls = only_tariffs(calls, events, ranks)
    edges = calls.groupBy("src", "dst").agg(F.sum("dur").cast("double").alias("w")).where("w > 0")
    return Graph(edges, name="call" if not ranks else "call_top" if ranks == (1, 2) else "call_next")


def duration_share(calls: DataFrame, tariff: str | Column, among: DataFrame | None = None) -> DataFrame:
    """``(id, p)``: share of a caller's talk time spent in ``tariff``."""
    if among is not None:
        calls = calls.join(F.broadcast(among.select("tariff")), "tariff", "left_semi")
    mine = F.sum(F.when(F.col("tariff") == (F.lit(tariff) if isinstance(tariff, str) else tariff), F.col("dur")).otherwise(0))
    return calls.groupBy(F.col("src").alias("id")).agg((mine / F.nullif(F.sum("dur"), F.lit(0))).alias("p")).where("p is not null")


# ------------------------------------------------------------- other given tables


def related_graph(lineitem: DataFrame) -> Graph:
    """Parts that share an order, both ways; a part's out-weights are equal and sum to 1."""
    rows = lineitem.select("l_orderkey", "l_partkey").distinct()
    other = rows.select("l_orderkey", F.col("l_partkey").alias("dst"))
    pairs = rows.join(other, "l_orderkey").where("l_partkey <> dst").select(F.col("l_partkey").alias("src"), "dst").distinct()
    degree = pairs.groupBy("src").agg(F.count("*").alias("k"))
    return Graph(pairs.join(degree, "src").select("src", "dst", (F.lit(1.0) / F.col("k")).alias("w")), name="related")


def from_related_lists(df: DataFrame, id_col: str = "id", list_col: str = "related") -> Graph:
    """Records with a list of related ids: each edge weighs one over the length of the list."""
    rows = df.select(F.col(id_col).alias("src"), F.array_distinct(list_col).alias("r"))
    return Graph.of(rows.select("src", F.explode("r").alias("dst"), (F.lit(1.0) / F.size("r")).alias("w")), df.select(F.col(id_col).alias("id")), "related")


def follow_graph(orders: DataFrame, lineitem: DataFrame) -> Graph:
    """Customers follow suppliers they traded with; suppliers follow customers who returned a line. Ids 2 * key and 2 * key + 1."""
    trades = orders.select("o_orderkey", "o_custkey").join(lineitem.select("l_orderkey", "l_suppkey", "l_returnflag"), F.col("o_orderkey") == F.col("l_orderkey"))
    customer, supplier = (F.col("o_custkey") * 2).cast("long"), (F.col("l_suppkey") * 2 + 1).cast("long")
    ways = F.array(F.struct(customer.alias("src"), supplier.alias("dst")), F.when(F.col("l_returnflag") == "R", F.struct(supplier.alias("src"), customer.alias("dst"))))
    pairs = trades.select(F.explode(ways).alias("e")).where("e is not null").select("e.src", "e.dst").distinct()
    return Graph(pairs.withColumn("w", F.lit(1.0)), name="follow")


def sequence_graph(lineitem: DataFrame) -> Graph:
    """From the part of a line to that of the next line of the order; w counts."""
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    steps = lineitem.select("l_orderkey", "l_linenumber", "l_suppkey", F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst"), "l_partkey")
    return Graph(steps.where("dst is not null and src <> dst").groupBy("src", "dst").agg(F.count("*").cast("double").alias("w")), name="sequence")


def chain_graph(orders: DataFrame) -> Graph:
    """From an order to the customer's next; a root -1 - customer points to the first."""
    order = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    before = F.coalesce(F.lag("o_orderkey").over(order), -1 - F.col("o_custkey"))
    return Graph(orders.select(before.cast("long").alias("src"), F.col("o_orderkey").cast("long").alias("dst"), F.lit(1.0).alias("w")), name="chain")


def entity_graph(orders: DataFrame, lineitem: DataFrame, supplier: DataFrame, nation: DataFrame) -> Graph:
    """Customer, order, part, supplier, nation, region (kinds 0 to 5): ids key * 8 + kind."""
    key = lambda c, k: (F.col(c).cast("long") * 8 + k)
    pair = lambda df, a, i, b, j: df.select(key(a, i).alias("src"), key(b, j).alias("dst"))
    parts = [
        pair(orders, "o_custkey", 0, "o_orderkey", 1), pair(lineitem, "l_orderkey", 1, "l_partkey", 2), pair(lineitem, "l_partkey", 2, "l_suppkey", 3),
        pair(supplier, "s_suppkey", 3, "s_nationkey", 4), pair(nation, "n_nationkey", 4, "n_regionkey", 5),
    ]
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return Graph(rows.distinct().withColumn("w", F.lit(1.0)), name="entity")


def wordlink_graph(documents: DataFrame, links: int = 10, shortest: int = 4, least: int = 2, most: int = 20) -> Graph:
    """Documents that share rare words: the ``links`` with most shared words, ties by id. ``most`` bounds pairs per word."""
    words = documents.select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), "[^\\p{L}]+"))).alias("t")).where(F.length("t") >= shortest)
    rare = words.groupBy("t").agg(F.count("*").alias("df")).where(F.col("df").between(least, most)).select("t")
    mine = words.join(rare, "t")
    pairs = mine.select("t", F.col("doc_id").alias("src")).join(mine.select("t", F.col("doc_id").alias("dst")), "t").where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("w"))
    top = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return Graph(pairs.withColumn("_r", F.row_number().over(top)).where(F.col("_r") <= links).select("src", "dst", F.col("w").cast("double").alias("w")), documents.select(F.col("doc_id").alias("id")), "wordlink")


def host_graph(pages: DataFrame) -> Graph:
    """Bipartite: a host points to the paths that its pages link; ids are hashes."""
    links = pages.select(F.lower(F.parse_url("url", F.lit("HOST"))).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))).alias("path"))
    return Graph.of(links.select(F.xxhash64("host").alias("src"), F.xxhash64("host", "path").alias("dst"), F.lit(1.0).alias("w")), name="host")


# ----------------------------------------------------------------------- labels


def coin_column(c: Column) -> Column:
    """1 or 0 by multiplicative hashing of an id."""
    return ((c * F.lit(2654435761)) % F.lit(4294967296) < F.lit(2147483648)).cast("int")


def coin_labels(graph: Graph) -> DataFrame:
    return graph.vertices.select("id", coin_column(F.col("id")).cast("double").alias("p"))


def mask_labels(labels: DataFrame, share: float = 0.7) -> DataFrame:
    """Seeds: the labels of ids whose last digit is below ten times ``share``."""
    return labels.where(F.pmod("id", F.lit(10)) < round(10 * share))


def part_labels(part: DataFrame, by: str = "p_type") -> DataFrame:
    return part.select(F.col("p_partkey").alias("id"), F.col(by).alias("name"))


def class_index(named: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(id, class, p = 1) and the class table of (id, name) rows; classes are numbered by name, from 0."""
    classes = named.select("name").distinct().withColumn("class", F.row_number().over(Window.orderBy("name")) - 1).select("class", "name")
    return named.join(F.broadcast(classes), "name").select("id", "class", F.lit(1.0).alias("p")), classes


# -------------------------------------------------------------------- transforms


def reverse(graph: Graph) -> Graph:
    return replace(graph, edges=graph.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def undirected(graph: Graph) -> Graph:
    return Graph.of(graph.edges.unionByName(reverse(graph).edges), graph.extra, graph.name)


def induced(graph: Graph, ids: DataFrame) -> Graph:
    """The part of the graph between the given ids."""
    keep = ids.select("id").distinct()
    edges = graph.edges.join(keep, F.col("src") == F.col("id"), "left_semi").join(keep, F.col("dst") == F.col("id"), "left_semi")
    return Graph(edges, keep, graph.name)


def dedupe(graph: Graph) -> Graph:
    """Parallel edges as one, their weights summed."""
    return Graph.of(graph.edges, graph.extra, graph.name)


def compact_ids(graph: Graph) -> tuple[Graph, DataFrame]:
    """The graph under ids 0, 1, 2, ... in the order of the old ones, and the map ``(id, new_id)``."""
    from netprop.operators.ranks import numbered

    names = numbered(graph.vertices, ["id"], "new_id")
    edges = graph.edges.join(names.select(F.col("id").alias("src"), F.col("new_id").alias("s")), "src").join(names.select(F.col("id").alias("dst"), F.col("new_id").alias("t")), "dst")
    return Graph(edges.select(F.col("s").alias("src"), F.col("t").alias("dst"), "w"), names.select(F.col("new_id").alias("id")), graph.name), names


def drop_isolated(graph: Graph) -> Graph:
    return replace(graph, extra=None)


def thin_edges(graph: Graph, k: int) -> Graph:
    """One edge in ``k``, by arithmetic on its ends."""
    return replace(graph, edges=graph.edges.where(F.pmod(F.col("src") * 31 + F.col("dst"), F.lit(k)) == 0))


def reciprocal(graph: Graph) -> DataFrame:
    """Pairs linked both ways."""
    return graph.edges.select("src", "dst").intersect(graph.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def zero_in_degree(graph: Graph) -> DataFrame:
    return graph.vertices.exceptAll(graph.edges.select(F.col("dst").alias("id")).distinct())


def adjacency_form(graph: Graph) -> DataFrame:
    """Vertex records ``(id, adj)``: outgoing edges as an array, empty for vertices without."""
    lists = graph.edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list(F.struct("dst", "w"))).alias("adj"))
    none = F.array().cast("array<struct<dst:bigint,w:double>>")
    return graph.vertices.join(lists, "id", "left").select("id", F.coalesce("adj", none).alias("adj"))


# -------------------------------------------------------------------- generators


def path(spark: SparkSession, n: int) -> Graph:
    return Graph(spark.range(n).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("w")), name="path")


def star(spark: SparkSession, n: int) -> Graph:
    """1 ... n point to 0."""
    return Graph(spark.range(1, n + 1).select(F.col("id").alias("src"), F.lit(0).cast("long").alias("dst"), F.lit(1.0).alias("w")), name="star")


def grid(spark: SparkSession, a: int, b: int) -> Graph:
    cell = spark.range(a * b).select(F.col("id").alias("src"), F.explode(F.array(F.when(F.col("id") % b < b - 1, F.col("id") + 1), F.when(F.col("id") < (a - 1) * b, F.col("id") + b))).alias("dst"))
    return Graph(cell.where("dst is not null").withColumn("w", F.lit(1.0)), name="grid")


def power_law(spark: SparkSession, n: int, m: int, alpha: float = 1.0) -> Graph:
    """``n * m`` edges whose targets follow a power law: target i is drawn with density falling as i ** -(alpha / (1 + alpha))."""
    draw = F.pmod(F.col("id") * 2654435761, F.lit(1 << 32)) / float(1 << 32)
    dst = F.floor(F.pow(draw, 1.0 + alpha) * n).cast("long")
    edges = spark.range(n * m).select(F.floor(F.col("id") / m).cast("long").alias("src"), dst.alias("dst")).where("src <> dst")
    return Graph.of(edges, name="power_law")


def two_blocks(spark: SparkSession, n: int, inside: int, across: int) -> Graph:
    """Two halves by parity: each vertex points to ``inside`` of its own and ``across`` of the other."""
    steps = F.concat(F.transform(F.sequence(F.lit(1), F.lit(max(inside, 1))), lambda k: k * 2), F.transform(F.sequence(F.lit(1), F.lit(max(across, 1))), lambda k: k * 2 - 1 + 2 * (F.col("id") % 7))) if across else F.transform(F.sequence(F.lit(1), F.lit(inside)), lambda k: k * 2)
    edges = spark.range(n).select(F.col("id").alias("src"), F.explode(steps).alias("s")).select("src", F.pmod(F.col("src") + F.col("s"), F.lit(n)).alias("dst")).where("src <> dst")
    return Graph.of(edges, name="two_blocks")


# ---------------------------------------------------------------------- profiles


def graph_profile(graph: Graph) -> DataFrame:
    """One row: vertices, edges, average degree, largest in-degree."""
    v = graph.vertices.agg(F.count("*").alias("vertices"))
    into = graph.edges.groupBy("dst").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum("k"), F.lit(0)).alias("edges"), F.coalesce(F.max("k"), F.lit(0)).alias("max_in_degree"))
    return v.join(into).select("vertices", "edges", F.round(F.col("edges") / F.nullif(F.col("vertices"), F.lit(0)), 6).alias("avg_degree"), "max_in_degree")  # one row beside one row


def degree_histogram(graph: Graph) -> DataFrame:
    return graph.edges.groupBy("dst").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("vertices"))


def hub_share(graph: Graph, q: float = 0.99) -> DataFrame:
    """Share of edges that end at vertices whose in-degree reaches the q-quantile."""
    into = graph.edges.groupBy("dst").agg(F.count("*").alias("k"))
    bar = into.agg(F.percentile_approx("k", q, 10000).alias("bar"))
    return into.join(F.broadcast(bar)).agg((F.sum(F.when(F.col("k") >= F.col("bar"), F.col("k")).otherwise(0)) / F.sum("k")).alias("share"))


def top_hubs(graph: Graph, k: int = 10) -> DataFrame:
    return graph.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_degree")).orderBy(F.desc("in_degree"), "id").limit(k)
