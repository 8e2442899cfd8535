"""Support operators, each a query with its SQL twin: (callable, sql)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from netprop.functions import udfs
from netprop import session
from netprop.operators import engines, graphs, measure, placement, problems, workloads
from netprop.operators.ranks import numbered
from netprop.plans import oracle
from netprop.sources import tables
from netprop.sources.tables import table
from netprop.streaming import calls as streaming

#: A fixed trace on which measures can be held against SQL.
_TRACE = [(e, "influence", g, r, ms) for g, rows in (("g1", {"reshuffle": (30, 10, 10, 10), "resident": (20, 10, 12, 11)}), ("g2", {"reshuffle": (40, 41, 39, 40), "resident": (90, 8, 7, 9)})) for e, times in rows.items() for r, ms in enumerate(times)]
_TRACE_SQL = "(VALUES " + ", ".join(f"('{e}', '{p}', '{g}', {r}, {ms})" for e, p, g, r, ms in _TRACE) + ") t(engine, problem, graph, round, ms)"


def trace(spark) -> DataFrame:
    rows = spark.createDataFrame(_TRACE, "engine string, problem string, graph string, round int, ms long")
    return rows.withColumn("run_id", F.concat_ws("/", "engine", "graph")).withColumn("cores", F.lit(4))


#: A trace from the given lines: two engines by line status, a graph per return flag, a round per line number, its time the quantities.
_WHOLE = "l_linestatus IS NOT NULL AND l_returnflag IS NOT NULL AND l_linenumber IS NOT NULL AND l_quantity IS NOT NULL"
_LINES_SQL = f"(SELECT CASE WHEN l_linestatus = 'F' THEN 'reshuffle' ELSE 'resident' END AS engine, 'influence' AS problem, l_returnflag AS graph, CAST(l_linenumber - 1 AS INTEGER) AS round, CAST(SUM(CAST(ROUND(l_quantity) AS BIGINT)) AS BIGINT) AS ms FROM lineitem WHERE {_WHOLE} GROUP BY 1, 2, 3, 4) t"


def line_trace(spark, d) -> DataFrame:
    rows = _t(spark, d, "lineitem").where(_WHOLE)
    engine = F.when(F.col("l_linestatus") == "F", "reshuffle").otherwise("resident")
    keys = (engine.alias("engine"), F.lit("influence").alias("problem"), F.col("l_returnflag").alias("graph"), (F.col("l_linenumber") - 1).cast("int").alias("round"))
    out = rows.groupBy(*keys).agg(F.sum(F.round("l_quantity").cast("long")).alias("ms"))
    return out.withColumn("run_id", F.concat_ws("/", "engine", "graph")).withColumn("cores", F.lit(4))


ENTRIES: dict[str, tuple] = {}


def _entry(name: str, sql: str | None = None):
    def add(f):
        ENTRIES[name] = (f, sql)
        return f

    return add


def _t(spark, sf_dir, name):
    return table(spark, sf_dir, name)


# ------------------------------------------------------------ filters and scans


@_entry("project_edges", "SELECT l_orderkey AS src, l_partkey AS dst, CAST(l_quantity AS DOUBLE) AS w FROM lineitem")
def project_edges(spark, d):
    return _t(spark, d, "lineitem").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"), F.col("l_quantity").cast("double").alias("w"))


@_entry("filter_tariff", "SELECT event_id, event_type FROM events WHERE event_type IN ('click', 'signup')")
def filter_tariff(spark, d):
    return _t(spark, d, "events").where(F.col("event_type").isin("click", "signup")).select("event_id", "event_type")


@_entry("filter_between_dates", "SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1996-03-31'")
def filter_between_dates(spark, d):
    return _t(spark, d, "orders").where("o_orderdate between timestamp_ntz '1996-01-01' and timestamp_ntz '1996-03-31'").select("o_orderkey")


@_entry("filter_like", "SELECT p_partkey FROM part WHERE p_type LIKE 'S%' OR p_brand LIKE '%1'")
def filter_like(spark, d):
    return _t(spark, d, "part").where(F.col("p_type").like("S%") | F.col("p_brand").like("%1")).select("p_partkey")


@_entry("filter_in_subquery", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000) AND NOT EXISTS (SELECT 1 FROM nation WHERE n_nationkey = c_nationkey AND n_regionkey = 0)")
def filter_in_subquery(spark, d):
    for n in ("customer", "orders", "nation"):
        _t(spark, d, n).createOrReplaceTempView(f"np_{n}")
    return spark.sql("SELECT c_custkey FROM np_customer WHERE c_custkey IN (SELECT o_custkey FROM np_orders WHERE o_totalprice > 100000) AND NOT EXISTS (SELECT 1 FROM np_nation WHERE n_nationkey = c_nationkey AND n_regionkey = 0)")


@_entry("filter_null_safe", "SELECT d.doc_id, l.quality IS NOT DISTINCT FROM NULL AS unlabelled FROM documents d LEFT JOIN labels l USING (doc_id)")
def filter_null_safe(spark, d):
    rows = _t(spark, d, "documents").select("doc_id").join(_t(spark, d, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.col("quality").eqNullSafe(F.lit(None)).alias("unlabelled"))


# ------------------------------------------------------------------------ joins


@_entry("join_merge", "SELECT o_orderpriority, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_merge(spark, d):
    o, li = _t(spark, d, "orders"), _t(spark, d, "lineitem")
    return o.hint("MERGE").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@_entry("join_shuffle_hash", "SELECT c_mktsegment, COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def join_shuffle_hash(spark, d):
    o, c = _t(spark, d, "orders"), _t(spark, d, "customer")
    return o.join(c.hint("SHUFFLE_HASH"), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@_entry("join_broadcast", "SELECT n_name, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark, d):
    c, n = _t(spark, d, "customer"), _t(spark, d, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("n"))  # 25 nations


@_entry("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def join_anti(spark, d):
    c, o = _t(spark, d, "customer"), _t(spark, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@_entry("join_theta", f"{oracle.graph('related')}, k AS (SELECT dst, COUNT(*) AS k FROM e GROUP BY dst) SELECT b.name, COUNT(*) AS n FROM k JOIN (VALUES ('low', 0, 99), ('mid', 100, 149), ('high', 150, 1000000)) b(name, lo, hi) ON k.k BETWEEN b.lo AND b.hi GROUP BY b.name")
def join_theta(spark, d):
    k = workloads.build(spark, d, "related").edges.groupBy("dst").agg(F.count("*").alias("k"))
    bands = spark.createDataFrame([("low", 0, 99), ("mid", 100, 149), ("high", 150, 1000000)], "name string, lo long, hi long")
    return k.join(F.broadcast(bands), F.col("k").between(F.col("lo"), F.col("hi"))).groupBy("name").agg(F.count("*").alias("n"))  # three bands


def range_join(a: DataFrame, b: DataFrame, at: str, start: str, end: str, width: int) -> DataFrame:
    """Rows of ``a`` whose ``at`` lies in [start, end] of a row of ``b``, through bins of ``width``: an equi-join, then the exact test."""
    left = a.withColumn("_bin", F.floor(F.col(at) / width))
    right = b.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor(F.col(end) / width))))
    return left.join(right, "_bin").where(F.col(at).between(F.col(start), F.col(end))).drop("_bin")


@_entry("join_range_binned", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON epoch_us(b.ts) BETWEEN epoch_us(a.ts) AND epoch_us(a.ts) + 20000000 AND a.event_type = 'purchase' AND b.event_type = 'view'")
def join_range_binned(spark, d):
    e = _t(spark, d, "events").select("event_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("first"), F.col("us").alias("lo"), (F.col("us") + 20_000_000).alias("hi"))
    b = e.where("event_type = 'view'").select(F.col("event_id").alias("second"), "us")
    return range_join(b, a, "us", "lo", "hi", 20_000_000).select("first", "second")


@_entry("join_interval", "SELECT a.event_id AS first, b.event_id AS back FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) > epoch_us(a.ts) AND epoch_us(b.ts) <= epoch_us(a.ts) + 600000000")
def join_interval(spark, d):
    e = _t(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    b = e.select("user_id", F.col("event_id").alias("back"), F.col("us").alias("later"))
    return e.join(b, "user_id").where("later > us and later <= us + 600000000").select(F.col("event_id").alias("first"), "back")


@_entry("join_asof", """SELECT c.event_id, l.value AS label FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') l ON c.user_id = l.user_id AND c.ts >= l.ts""")
def join_asof(spark, d):
    """Last label of the user before each click: both in one stream of rows, last value carried on."""
    e = _t(spark, d, "events").where("event_type in ('click', 'signup')")
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type").desc(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    carried = F.last(F.when(F.col("event_type") == "signup", F.col("value")), ignorenulls=True).over(order)
    return e.withColumn("label", carried).where("event_type = 'click'").select("event_id", "label")


# ----------------------------------------------------------------- aggregations


@_entry("agg_min_message", f"{oracle.graph('follow')} SELECT dst, MIN(src) AS low, COUNT(*) AS n FROM e GROUP BY dst")
def agg_min_message(spark, d):
    return workloads.build(spark, d, "follow").edges.groupBy("dst").agg(F.min("src").alias("low"), F.count("*").alias("n"))


def salted_sum(df: DataFrame, key: str, value: str, parts: int) -> DataFrame:
    """Sum per key in two steps, the first spread over ``parts`` of each key."""
    first = df.withColumn("_part", F.pmod(F.xxhash64(*df.columns), F.lit(parts))).groupBy(key, "_part").agg(F.sum(value).alias("_s"))
    return first.groupBy(key).agg(F.sum("_s").alias("total"))


@_entry("agg_salted", "SELECT l_suppkey, SUM(CAST(ROUND(l_quantity) AS BIGINT))::BIGINT AS total FROM lineitem GROUP BY l_suppkey")
def agg_salted(spark, d):
    rows = _t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", F.round("l_quantity").cast("long").alias("q"))
    return salted_sum(rows, "l_suppkey", "q", 8)


@_entry("agg_adjacency", f"{oracle.graph('call_top')} SELECT v.id, COUNT(e.dst) AS degree, COALESCE(MIN(e.dst), -1) AS first FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id")
def agg_adjacency(spark, d):
    a = graphs.adjacency_form(workloads.build(spark, d, "call_top"))
    return a.select("id", F.size("adj").cast("long").alias("degree"), F.coalesce(F.try_element_at("adj", F.lit(1)).getField("dst"), F.lit(-1)).cast("long").alias("first"))


@_entry("agg_distinct", f"{oracle.graph('entity')} SELECT COUNT(DISTINCT src) AS senders, COUNT(DISTINCT dst) AS receivers FROM e")
def agg_distinct(spark, d):
    return workloads.build(spark, d, "entity").edges.agg(F.countDistinct("src").alias("senders"), F.countDistinct("dst").alias("receivers"))


@_entry("agg_approx_distinct")
def agg_approx_distinct(spark, d):
    return workloads.build(spark, d, "related").edges.agg(F.approx_count_distinct("src", 0.02).alias("senders"))


@_entry("agg_percentile", f"{oracle.graph('follow')}, k AS (SELECT COUNT(*) AS k FROM e GROUP BY dst) SELECT QUANTILE_CONT(k, 0.5) AS median, QUANTILE_CONT(k, 0.9) AS p90 FROM k")
def agg_percentile(spark, d):
    k = workloads.build(spark, d, "follow").edges.groupBy("dst").agg(F.count("*").alias("k"))
    return k.agg(F.percentile("k", 0.5).alias("median"), F.percentile("k", 0.9).alias("p90"))


@_entry("agg_cube", f"SELECT engine, graph, CAST(SUM(ms) AS BIGINT) AS ms FROM {_LINES_SQL} GROUP BY CUBE (engine, graph)")
def agg_cube(spark, d):
    return line_trace(spark, d).cube("engine", "graph").agg(F.sum("ms").alias("ms"))


@_entry("agg_rollup", "SELECT o_orderstatus, o_orderpriority, COUNT(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, d):
    return _t(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@_entry("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, COUNT(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(spark, d):
    _t(spark, d, "orders").createOrReplaceTempView("np_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, COUNT(*) AS n FROM np_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")


@_entry("agg_pivot", f"SELECT graph, CAST(SUM(CASE WHEN engine = 'resident' THEN ms END) AS BIGINT) AS resident, CAST(SUM(CASE WHEN engine = 'reshuffle' THEN ms END) AS BIGINT) AS reshuffle FROM {_LINES_SQL} GROUP BY graph")
def agg_pivot(spark, d):
    return measure.wide(line_trace(spark, d), ["resident", "reshuffle"]).drop("problem")


@_entry("agg_having", f"{oracle.graph('follow')} SELECT dst, COUNT(*) AS n, COUNT(*) FILTER (WHERE MOD(src, 4) = 0) AS even FROM e GROUP BY dst HAVING COUNT(*) > 100")
def agg_having(spark, d):
    g = workloads.build(spark, d, "follow").edges.groupBy("dst").agg(F.count("*").alias("n"), F.count_if(F.col("src") % 4 == 0).alias("even"))
    return g.where("n > 100")


@_entry("agg_bool", f"{oracle.graph('follow')} SELECT BOOL_OR(w > 0) AS any_edge, BOOL_AND(w > 0) AS all_edges FROM e")
def agg_bool(spark, d):
    return workloads.build(spark, d, "follow").edges.agg(F.bool_or(F.col("w") > 0).alias("any_edge"), F.bool_and(F.col("w") > 0).alias("all_edges"))


# ---------------------------------------------------------------------- windows


@_entry("win_lead_callee", f"SELECT src, dst, tariff, dur FROM ({oracle._CALLS}) WHERE dst IS NOT NULL AND src <> dst")
def win_lead_callee(spark, d):
    return graphs.call_records(_t(spark, d, "events")).select("src", "dst", "tariff", "dur")


@_entry("win_rank_tariff", "SELECT event_type AS tariff, COUNT(*) AS n, CAST(ROW_NUMBER() OVER (ORDER BY COUNT(*) DESC, event_type) AS INTEGER) AS rank FROM events GROUP BY event_type")
def win_rank_tariff(spark, d):
    return graphs.rank_tariffs(_t(spark, d, "events"), "event_type")


@_entry("win_range_period", "SELECT event_id, CAST(SUM(CAST(ROUND(value * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 604800000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS trailing FROM events")
def win_range_period(spark, d):
    e = _t(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.sum(F.round(F.col("value") * 100).cast("long")).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-604800000000, 0)).alias("trailing"))


@_entry("win_ntile", f"{oracle.graph('follow')}, k AS (SELECT dst, COUNT(*) AS k FROM e GROUP BY dst) SELECT dst, CAST(NTILE(10) OVER (ORDER BY k, dst) AS INTEGER) AS decile, ROUND(PERCENT_RANK() OVER (ORDER BY k), 6) AS rank FROM k")
def win_ntile(spark, d):
    """Deciles and ranks from gapless numbers and the degree histogram: no window holds all vertices."""
    k = workloads.build(spark, d, "follow").edges.groupBy("dst").agg(F.count("*").alias("k"))
    at = numbered(k, ["k", "dst"], "at")
    sizes = at.groupBy("k").agg(F.count("*").alias("n"))
    below = sizes.select("k", F.coalesce(F.sum("n").over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("below"))  # a row per degree
    total = sizes.agg(F.sum("n").alias("all"))
    wide = F.floor(F.col("all") / 10) + 1  # rows in each of the first, longer deciles
    longer = F.col("all") % 10
    decile = F.when(F.col("at") < longer * wide, F.floor(F.col("at") / wide)).otherwise(longer + F.floor((F.col("at") - longer * wide) / F.greatest(wide - 1, F.lit(1)))) + 1
    return at.join(below, "k").join(F.broadcast(total)).select("dst", decile.cast("int").alias("decile"), F.round(F.col("below") / (F.col("all") - 1), 6).alias("rank"))  # one row


@_entry("win_lag_delta", f"SELECT engine, graph, round, CAST(ms - LAG(ms) OVER (PARTITION BY engine, graph ORDER BY round) AS BIGINT) AS delta_ms FROM {_TRACE_SQL}")
def win_lag_delta(spark, d):
    return measure.round_delta(trace(spark)).select("engine", "graph", "round", "delta_ms")


@_entry("win_moving_mean", f"SELECT engine, graph, round, ROUND(AVG(ms) OVER (PARTITION BY engine, graph ORDER BY round ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth_ms FROM {_TRACE_SQL}")
def win_moving_mean(spark, d):
    return measure.smoothed_ms(trace(spark)).select("engine", "graph", "round", F.round("smooth_ms", 6).alias("smooth_ms"))


# --------------------------------------------------------------------- measures


_TOTAL = f"(SELECT *, SUM(ms) OVER (PARTITION BY engine, graph ORDER BY round) AS total FROM {_LINES_SQL})"


@_entry("cost_cumulative", f"SELECT engine, graph, round, CAST(total AS BIGINT) AS total_ms FROM {_TOTAL}")
def cost_cumulative(spark, d):
    return measure.cumulative_ms(line_trace(spark, d)).select("engine", "graph", "round", "total_ms")


@_entry("cost_fit", f"SELECT engine, graph, ROUND(REGR_SLOPE(total, round), 3) AS slope, ROUND(REGR_INTERCEPT(total, round), 3) AS intercept, ROUND(REGR_R2(total, round), 6) AS r2 FROM {_TOTAL} WHERE round > 0 GROUP BY engine, graph")
def cost_fit(spark, d):
    return measure.linear_fit(line_trace(spark, d)).select("engine", "graph", *[F.round(c, k).alias(c) for c, k in (("slope", 3), ("intercept", 3), ("r2", 6))])


@_entry("cost_break_even", f"SELECT a.graph, MIN(CASE WHEN a.total <= b.total THEN a.round END) AS break_even FROM {_TOTAL} a JOIN {_TOTAL} b ON a.graph = b.graph AND a.round = b.round AND a.engine = 'resident' AND b.engine = 'reshuffle' WHERE a.round > 0 GROUP BY a.graph")
def cost_break_even(spark, d):
    return measure.break_even(line_trace(spark, d)).select("graph", "break_even")


@_entry("cost_mean_round", f"SELECT engine, graph, ROUND(SUM(ms)::DOUBLE / MAX(round), 6) AS mean_ms FROM {_LINES_SQL} GROUP BY engine, graph")
def cost_mean_round(spark, d):
    return measure.mean_round_ms(line_trace(spark, d)).select("engine", "graph", F.round("mean_ms", 6).alias("mean_ms"))


@_entry("cost_speedup", f"WITH m AS (SELECT engine, graph, SUM(ms)::DOUBLE / MAX(round) AS m FROM {_LINES_SQL} GROUP BY engine, graph) SELECT a.engine, a.graph, ROUND(b.m / a.m, 6) AS times, ROUND((1 - a.m / b.m) * 100, 6) AS percent_less FROM m a JOIN m b ON a.graph = b.graph AND b.engine = 'reshuffle'")
def cost_speedup(spark, d):
    return measure.speedup(line_trace(spark, d)).select("engine", "graph", F.round("times", 6).alias("times"), F.round("percent_less", 6).alias("percent_less"))


@_entry("cost_first_round", f"SELECT engine, graph, ROUND(SUM(CASE WHEN round <= 1 THEN ms END)::DOUBLE / AVG(CASE WHEN round > 1 THEN ms END), 6) AS ratio FROM {_LINES_SQL} GROUP BY engine, graph")
def cost_first_round(spark, d):
    return measure.first_round_ratio(line_trace(spark, d)).select("engine", "graph", F.round("ratio", 6).alias("ratio"))


# ------------------------------------------------- sort, sets, scalar functions


@_entry("sort_hubs", f"{oracle.graph('follow')} SELECT dst AS id, COUNT(*) AS in_degree FROM e GROUP BY dst ORDER BY in_degree DESC, id LIMIT 10")
def sort_hubs(spark, d):
    return graphs.top_hubs(workloads.build(spark, d, "follow"), 10)


@_entry("set_intersect", f"{oracle.graph('call_top')} SELECT src, dst FROM e INTERSECT SELECT dst, src FROM e")
def set_intersect(spark, d):
    return graphs.reciprocal(workloads.build(spark, d, "call_top"))


@_entry("set_except", f"{oracle.graph('entity')} SELECT id FROM v EXCEPT SELECT dst FROM e")
def set_except(spark, d):
    return graphs.zero_in_degree(workloads.build(spark, d, "entity"))


@_entry("sample_mod", f"{oracle.graph('related')} SELECT src, dst FROM e WHERE MOD(src * 31 + dst, 5) = 0")
def sample_mod(spark, d):
    return graphs.thin_edges(workloads.build(spark, d, "related"), 5).edges.select("src", "dst")


@_entry("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("k"))


@_entry("fn_date", "SELECT strftime(o_orderdate, '%Y-%m') AS month, COUNT(*) AS n FROM orders GROUP BY 1")
def fn_date(spark, d):
    return _t(spark, d, "orders").groupBy(F.date_format(F.date_trunc("month", F.col("o_orderdate")), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@_entry("fn_array", "SELECT vec_id, ROUND(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 4) AS norm2, len(embedding) AS n FROM embeddings")
def fn_array(spark, d):
    squares = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return _t(spark, d, "embeddings").select("vec_id", F.round(squares, 4).alias("norm2"), F.size("embedding").cast("long").alias("n"))


@_entry("fn_string", "SELECT doc_id, lower(substr(text, 1, 8)) AS head, length(text) AS n FROM documents")
def fn_string(spark, d):
    return _t(spark, d, "documents").select("doc_id", F.lower(F.substring("text", 1, 8)).alias("head"), F.length("text").cast("long").alias("n"))


@_entry("fn_regexp", """SELECT page_id, regexp_extract(url, '^https?://([^/?#]*)', 1) AS host, len(regexp_extract_all(html, 'href="(/[^"]*)"')) AS links FROM pages""")
def fn_regexp(spark, d):
    return _t(spark, d, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/?#]*)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(0))).cast("long").alias("links"))


# -------------------------------------------------------------- functions, streams


@_entry("udf_coin", f"SELECT o_orderkey AS id, CAST(({oracle.COIN.replace('id', 'o_orderkey')}) AS INTEGER) AS coin FROM orders")
def udf_coin(spark, d):
    udfs.register(spark)
    _t(spark, d, "orders").createOrReplaceTempView("np_orders")
    return spark.sql("SELECT o_orderkey AS id, coin(o_orderkey) AS coin FROM np_orders")


@_entry("udf_entropy", "SELECT vec_id, ROUND(-SUM(p * LN(p)), 4) AS entropy FROM (SELECT vec_id, abs(x) / SUM(abs(x)) OVER (PARTITION BY vec_id) AS p FROM (SELECT vec_id, CAST(UNNEST(embedding) AS DOUBLE) AS x FROM embeddings)) WHERE p > 0 GROUP BY vec_id")
def udf_entropy(spark, d):
    return _t(spark, d, "embeddings").select("vec_id", F.round(udfs.entropy(F.transform("embedding", lambda x: F.abs(x).cast("double"))), 4).alias("entropy"))


@_entry("udaf_weighted_mean", "SELECT l_suppkey, ROUND(SUM(l_discount * l_quantity) / SUM(l_quantity), 6) AS mean FROM lineitem GROUP BY l_suppkey")
def udaf_weighted_mean(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_suppkey").agg(udfs.weighted_mean("l_discount", "l_quantity").alias("mean")).select("l_suppkey", F.round("mean", 6).alias("mean"))


@_entry("udtf_related", "SELECT CAST(a AS BIGINT) AS src, CAST(b AS BIGINT) AS dst FROM (VALUES (10, 11), (10, 12), (11, 10)) t(a, b)")
def udtf_related(spark, d):
    udfs.register(spark)
    return spark.sql("SELECT src, dst FROM (SELECT * FROM VALUES (10L, array(11L, 12L)), (11L, array(10L)) AS t(id, r)), LATERAL related_edges(id, r)")


_WINDOWED = "SELECT date_trunc('day', ts) AS day, src, dst, CAST(SUM(dur) AS BIGINT) AS w FROM ({}) WHERE dst IS NOT NULL AND src <> dst GROUP BY 1, 2, 3".format(oracle._CALLS)


@_entry("stream_windowed_edges", f"SELECT strftime(day, '%Y-%m-%d') AS day, src, dst, w FROM ({_WINDOWED})")
def stream_windowed_edges(spark, d):
    return streaming.windowed_edges_of(spark, graphs.call_records(_t(spark, d, "events")), "1 day").withColumn("day", F.date_format("day", "yyyy-MM-dd"))


@_entry("stream_dedup", "SELECT event_type, COUNT(*) AS n FROM events GROUP BY event_type")
def stream_dedup(spark, d):
    return streaming.deduplicated_counts(spark, _t(spark, d, "events"))


@_entry("stream_incremental_hops", oracle.hops("call"))
def stream_incremental_hops(spark, d):
    return streaming.incremental_hops_of(spark, workloads.build(spark, d, "call"), 0, 4)


@_entry("stream_last_callee", f"SELECT src, dst FROM (SELECT src, dst, ROW_NUMBER() OVER (PARTITION BY src ORDER BY ts DESC) AS r FROM ({oracle._CALLS}) WHERE dst IS NOT NULL AND src <> dst) WHERE r = 1")
def stream_last_callee(spark, d):
    return streaming.last_callee_of(spark, graphs.call_records(_t(spark, d, "events")))


# ------------------------------------------------- filters and joins of the methods


_MASKED = f"SELECT id, p FROM ({oracle.share_labels()}) WHERE MOD(id, 10) < 7"


def _labelled(spark, d):
    """The large call graph and its masked labels."""
    graph = workloads.build(spark, d, "call_top")
    return graph, graphs.mask_labels(workloads.labels_for(spark, d, "call_top", graph))


@_entry("filter_null_label", f"{oracle.graph('call_top')}, lab AS ({_MASKED}) SELECT v.id FROM v LEFT JOIN lab ON lab.id = v.id WHERE lab.p IS NOT NULL")
def filter_null_label(spark, d):
    graph, known = _labelled(spark, d)
    return graph.vertices.join(known, "id", "left").where("p is not null").select("id")


@_entry("filter_improved", f"{oracle.graph('follow')}, n AS (SELECT 0::BIGINT AS id, 0 AS d UNION SELECT dst, 1 FROM e WHERE src = 0), c AS (SELECT e.dst AS id, MIN(n.d) + 1 AS cand FROM n JOIN e ON e.src = n.id GROUP BY e.dst) SELECT c.id, CAST(c.cand AS INTEGER) AS cand FROM c LEFT JOIN (SELECT id, MIN(d) AS d FROM n GROUP BY id) k ON k.id = c.id WHERE k.d IS NULL OR c.cand < k.d")
def filter_improved(spark, d):
    """Offers of the second round that are strictly better than what is known."""
    graph = workloads.ready(spark, d, "follow")
    near = problems.shortest_hops(graph, 0, max_rounds=1, stop="fixed", options=engines.EngineOptions(partitions=8)).state
    offers = graph.edges.join(near.where("hops is not null"), F.col("src") == F.col("id")).groupBy(F.col("dst").alias("to")).agg(F.min(F.col("hops") + 1).alias("cand"))
    return offers.join(near, F.col("to") == F.col("id")).where("hops is null or cand < hops").select("id", F.col("cand").cast("int").alias("cand"))


@_entry("filter_seed", "SELECT doc_id AS id FROM documents WHERE MOD(doc_id, 10) < 7")
def filter_seed(spark, d):
    return graphs.mask_labels(_t(spark, d, "documents").select(F.col("doc_id").alias("id")))


@_entry("case_class", f"SELECT id, CASE WHEN p >= 0.5 THEN 'first' ELSE 'second' END AS said FROM ({oracle.share_labels()}) WHERE p IS NOT NULL")
def case_class(spark, d):
    graph = workloads.build(spark, d, "call_top")
    return problems.decide(workloads.labels_for(spark, d, "call_top", graph), "threshold").select("id", F.when(F.col("positive"), "first").otherwise("second").alias("said"))


@_entry("join_colocated", f"{oracle.graph('follow')} SELECT v.id, COUNT(*) AS n FROM v JOIN e ON e.src = v.id GROUP BY v.id")
def join_colocated(spark, d):
    """Tables bucketed alike join and aggregate without an exchange."""
    graph = workloads.build(spark, d, "follow")
    names = [tables.bucketed_name(x) for x in ("structure", "state")]
    try:
        with session.loop_conf(spark, 8):
            edges, state = tables.save_bucketed(graph.edges, names[0], 8, "src"), tables.save_bucketed(graph.vertices, names[1], 8, "id")
            found = state.hint("MERGE").join(edges.hint("MERGE"), F.col("src") == F.col("id")).groupBy("id").agg(F.count("*").alias("n"))
            if engines.count_exchanges(found):
                raise AssertionError("a join in place needs no exchange")
            return session.stored(found, "joined")
    finally:
        tables.drop(spark, names)


@_entry("join_left", f"{oracle.graph('call_top')} SELECT v.id, COALESCE(SUM(e.w), 0.0) AS got FROM v LEFT JOIN e ON e.dst = v.id GROUP BY v.id")
def join_left(spark, d):
    """Vertices without a message keep their place."""
    graph = workloads.build(spark, d, "call_top")
    got = graph.edges.groupBy(F.col("dst").alias("id")).agg(F.sum("w").alias("got"))
    return graph.vertices.join(got, "id", "left").select("id", F.coalesce("got", F.lit(0.0)).alias("got"))


@_entry("join_right", "SELECT c_custkey, COUNT(o_orderkey) AS n FROM orders RIGHT JOIN customer ON o_custkey = c_custkey GROUP BY c_custkey")
def join_right(spark, d):
    o, c = _t(spark, d, "orders"), _t(spark, d, "customer")
    return o.join(c, o.o_custkey == c.c_custkey, "right").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


def _two(a: str, b: str) -> str:
    return f"WITH a AS (SELECT src AS id FROM ({oracle.EDGES[a]}) UNION SELECT dst FROM ({oracle.EDGES[a]})), b AS (SELECT src AS id FROM ({oracle.EDGES[b]}) UNION SELECT dst FROM ({oracle.EDGES[b]}))"


@_entry("join_full", f"{_two('sequence', 'related')} SELECT COALESCE(a.id, b.id) AS id, a.id IS NOT NULL AS in_first, b.id IS NOT NULL AS in_second FROM a FULL JOIN b ON a.id = b.id")
def join_full(spark, d):
    a, b = (workloads.build(spark, d, n).vertices.withColumn(c, F.lit(True)) for n, c in (("sequence", "in_first"), ("related", "in_second")))
    return a.join(b, "id", "full").select("id", F.col("in_first").isNotNull().alias("in_first"), F.col("in_second").isNotNull().alias("in_second"))


@_entry("join_semi", f"{oracle.graph('follow')} SELECT src, dst FROM e WHERE src IN (SELECT id FROM v WHERE MOD(id, 4) < 2) AND dst IN (SELECT id FROM v WHERE MOD(id, 4) < 2)")
def join_semi(spark, d):
    graph = workloads.build(spark, d, "follow")
    return graphs.induced(graph, graph.vertices.where("id % 4 < 2")).edges.select("src", "dst")


@_entry("join_cross", f"SELECT g.t AS threshold, COUNT(*) FILTER (WHERE p >= g.t) AS positive FROM ({oracle.share_labels()}), (VALUES (0.25::DOUBLE), (0.5), (0.75)) g(t) GROUP BY g.t")
def join_cross(spark, d):
    """Every label against a grid of three thresholds, which is broadcast."""
    graph = workloads.build(spark, d, "call_top")
    grid = spark.createDataFrame([(0.25,), (0.5,), (0.75,)], "threshold double")
    return workloads.labels_for(spark, d, "call_top", graph).crossJoin(F.broadcast(grid)).groupBy("threshold").agg(F.count_if(F.col("p") >= F.col("threshold")).alias("positive"))


@_entry("join_self", "SELECT a.l_suppkey AS src, b.l_suppkey AS dst, COUNT(*) AS n FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey GROUP BY 1, 2")
def join_self(spark, d):
    rows = _t(spark, d, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("src")).distinct()
    return rows.join(rows.withColumnRenamed("src", "dst"), "l_orderkey").where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("n"))


@_entry("join_multiway", "SELECT r_name, COUNT(*) AS lines FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY r_name")
def join_multiway(spark, d):
    t = {n: _t(spark, d, n) for n in ("customer", "orders", "lineitem", "nation", "region")}
    rows = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    return rows.join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("lines"))


# -------------------------------------------------- aggregations of the methods


_PAIR = f"{oracle.graph('call_top')}, lab AS ({_MASKED}) SELECT e.dst, ROUND(SUM(lab.p * e.w), 4) AS lw, SUM(e.w) AS sw FROM e JOIN lab ON lab.id = e.src GROUP BY e.dst"


def _messages(spark, d):
    graph, known = _labelled(spark, d)
    return graph.edges.join(known, F.col("src") == F.col("id")).select("dst", (F.col("p") * F.col("w")).alias("lw"), F.col("w").alias("sw"))


def _summed(messages: DataFrame) -> DataFrame:
    return messages.groupBy("dst").agg(F.round(F.sum("lw"), 4).alias("lw"), F.sum("sw").alias("sw"))


@_entry("agg_sum_pair", _PAIR)
def agg_sum_pair(spark, d):
    return _summed(_messages(spark, d))


@_entry("agg_no_partial", _PAIR)
def agg_no_partial(spark, d):
    """The same without sums before the exchange: rows are dealt by receiver first."""
    return _summed(_messages(spark, d).repartition(8, "dst"))


@_entry("agg_share", f"SELECT user_id AS id, ROUND(SUM(CASE WHEN event_type = 'click' THEN {oracle.DUR} ELSE 0 END)::DOUBLE / SUM({oracle.DUR}), 6) AS p FROM events GROUP BY user_id HAVING SUM({oracle.DUR}) <> 0")
def agg_share(spark, d):
    rows = _t(spark, d, "events").select(F.col("user_id").alias("src"), F.col("event_type").alias("tariff"), F.round(F.col("value") * 100).cast("long").alias("dur"))
    return graphs.duration_share(rows, "click").select("id", F.round("p", 6).alias("p"))


@_entry("agg_max_by", f"SELECT user_id, event_type AS most FROM (SELECT user_id, event_type, ROW_NUMBER() OVER (PARTITION BY user_id ORDER BY SUM({oracle.DUR}) DESC, event_type DESC) AS r FROM events GROUP BY user_id, event_type) WHERE r = 1")
def agg_max_by(spark, d):
    rows = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("dur"))
    return rows.groupBy("user_id").agg(F.max_by("event_type", F.struct("dur", "event_type")).alias("most"))


@_entry("agg_regr", "SELECT l_returnflag, ROUND(REGR_SLOPE(l_extendedprice, l_quantity), 3) AS slope, ROUND(REGR_R2(l_extendedprice, l_quantity), 6) AS r2 FROM lineitem GROUP BY l_returnflag")
def agg_regr(spark, d):
    y, x = F.col("l_extendedprice").cast("double"), F.col("l_quantity").cast("double")
    return _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope(y, x), 3).alias("slope"), F.round(F.regr_r2(y, x), 6).alias("r2"))


@_entry("agg_unpivot", f"SELECT engine, graph, 'ms' AS measure, CAST(SUM(ms) AS BIGINT) AS value FROM {_LINES_SQL} GROUP BY engine, graph UNION ALL SELECT engine, graph, 'rounds', CAST(MAX(round) AS BIGINT) FROM {_LINES_SQL} GROUP BY engine, graph")
def agg_unpivot(spark, d):
    rows = line_trace(spark, d).groupBy("engine", "graph").agg(F.sum("ms").alias("ms"), F.max("round").cast("long").alias("rounds"))
    return rows.unpivot(["engine", "graph"], ["ms", "rounds"], "measure", "value")


@_entry("agg_filter", "SELECT o_custkey, COUNT(*) FILTER (WHERE o_orderstatus = 'F') AS done, COUNT(*) FILTER (WHERE o_orderstatus <> 'F') AS open FROM orders GROUP BY o_custkey")
def agg_filter(spark, d):
    _t(spark, d, "orders").createOrReplaceTempView("np_orders")
    return spark.sql("SELECT o_custkey, COUNT(*) FILTER (WHERE o_orderstatus = 'F') AS done, COUNT(*) FILTER (WHERE o_orderstatus <> 'F') AS open FROM np_orders GROUP BY o_custkey")


# ------------------------------------------------------- windows of the methods


@_entry("win_chain", "SELECT o_orderkey, LAG(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before FROM orders")
def win_chain(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("before"))


@_entry("win_weight_share", "SELECT l_partkey, l_suppkey, ROUND(COUNT(*)::DOUBLE / SUM(COUNT(*)) OVER (PARTITION BY l_partkey), 6) AS share FROM lineitem GROUP BY l_partkey, l_suppkey")
def win_weight_share(spark, d):
    n = _t(spark, d, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.count("*").alias("n"))
    return n.select("l_partkey", "l_suppkey", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("l_partkey")), 6).alias("share"))


@_entry("win_topk_links", "SELECT src, dst, CAST(r AS INTEGER) AS r FROM (SELECT o_custkey AS src, l_suppkey AS dst, ROW_NUMBER() OVER (PARTITION BY o_custkey ORDER BY COUNT(*) DESC, l_suppkey) AS r FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey, l_suppkey) WHERE r <= 3")
def win_topk_links(spark, d):
    o, li = _t(spark, d, "orders"), _t(spark, d, "lineitem")
    n = o.join(li, o.o_orderkey == li.l_orderkey).groupBy(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("n"), "dst"))).where("r <= 3").select("src", "dst", "r")


@_entry("win_cumulative", "SELECT o_orderkey, COUNT(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far FROM orders")
def win_cumulative(spark, d):
    order = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return _t(spark, d, "orders").select("o_orderkey", F.count("*").over(order).alias("so_far"))


@_entry("win_first_last", "SELECT o_orderkey, FIRST_VALUE(o_orderkey) OVER w AS first, LAST_VALUE(o_orderkey) OVER w AS last, NTH_VALUE(o_orderkey, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _t(spark, d, "orders").select("o_orderkey", F.first_value("o_orderkey").over(w).alias("first"), F.last_value("o_orderkey").over(w).alias("last"), F.nth_value("o_orderkey", 2).over(w).alias("second"))


# ------------------------------------------- sort, sets, functions of the methods


@_entry("sort_within", f"{oracle.graph('follow')} SELECT src, COUNT(*) AS n, MIN(dst) AS first FROM e GROUP BY src")
def sort_within(spark, d):
    """Edges dealt by sender and sorted there, so that the first row of a sender is its least receiver: no second sort, no exchange."""
    edges = workloads.build(spark, d, "follow").edges.repartition(8, "src").sortWithinPartitions("src", "dst")
    return edges.groupBy("src").agg(F.count("*").alias("n"), F.first("dst").alias("first"))


@_entry("limit_offset", f"{oracle.graph('follow')} SELECT dst AS id, COUNT(*) AS in_degree FROM e GROUP BY dst ORDER BY in_degree DESC, id LIMIT 10 OFFSET 10")
def limit_offset(spark, d):
    k = workloads.build(spark, d, "follow").edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_degree"))
    return k.orderBy(F.desc("in_degree"), "id").offset(10).limit(10)


@_entry("set_union_all", f"{oracle.graph('call_top')} SELECT id, COUNT(*) AS n FROM (SELECT dst AS id FROM e UNION ALL SELECT id FROM v) GROUP BY id")
def set_union_all(spark, d):
    """Messages and the vertices' own records, as a full reshuffle sends them."""
    graph = workloads.build(spark, d, "call_top")
    return graph.edges.select(F.col("dst").alias("id")).unionByName(graph.vertices.select("id")).groupBy("id").agg(F.count("*").alias("n"))


@_entry("set_union", f"{_two('call_top', 'call_next')} SELECT id FROM a UNION SELECT id FROM b")
def set_union(spark, d):
    a, b = (workloads.build(spark, d, n).vertices for n in ("call_top", "call_next"))
    return a.union(b).distinct()


def _users(spark, d, kind):
    return _t(spark, d, "events").where(F.col("event_type") == kind).select("user_id")


@_entry("set_intersect_all", "SELECT user_id, COUNT(*) AS n FROM (SELECT user_id FROM events WHERE event_type = 'click' INTERSECT ALL SELECT user_id FROM events WHERE event_type = 'view') GROUP BY user_id")
def set_intersect_all(spark, d):
    return _users(spark, d, "click").intersectAll(_users(spark, d, "view")).groupBy("user_id").agg(F.count("*").alias("n"))


@_entry("set_except_all", "SELECT user_id, COUNT(*) AS n FROM (SELECT user_id FROM events WHERE event_type = 'click' EXCEPT ALL SELECT user_id FROM events WHERE event_type = 'view') GROUP BY user_id")
def set_except_all(spark, d):
    return _users(spark, d, "click").exceptAll(_users(spark, d, "view")).groupBy("user_id").agg(F.count("*").alias("n"))


@_entry("fn_math", "SELECT l_orderkey, l_linenumber, ROUND(ABS(l_discount - 0.05::DOUBLE), 4) AS gap, GREATEST(l_partkey, l_suppkey) AS most, LEAST(l_partkey, l_suppkey) AS least, CAST(FLOOR(SQRT(l_quantity)) AS BIGINT) AS root, MOD(l_partkey, 7) AS rest, ROUND(LN(l_extendedprice), 6) AS log, ROUND(POW(1 + l_tax, 2), 6) AS square FROM lineitem")
def fn_math(spark, d):
    c = F.col
    return _t(spark, d, "lineitem").select(
        "l_orderkey", "l_linenumber", F.round(F.abs(c("l_discount") - F.lit(0.05)), 4).alias("gap"), F.greatest("l_partkey", "l_suppkey").alias("most"), F.least("l_partkey", "l_suppkey").alias("least"),
        F.floor(F.sqrt("l_quantity")).cast("long").alias("root"), F.pmod("l_partkey", F.lit(7).cast("long")).alias("rest"), F.round(F.ln("l_extendedprice"), 6).alias("log"), F.round(F.pow(1 + c("l_tax"), F.lit(2.0)), 6).alias("square"),
    )


@_entry("fn_map", "SELECT c_nationkey, c_mktsegment AS segment, COUNT(*) AS n, COUNT(DISTINCT c_mktsegment) OVER (PARTITION BY c_nationkey) AS segments FROM customer GROUP BY c_nationkey, c_mktsegment".replace("COUNT(DISTINCT c_mktsegment) OVER", "COUNT(*) OVER"))
def fn_map(spark, d):
    """Counts by segment as a map per nation, and back to rows."""
    n = _t(spark, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    maps = n.groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m"))
    return maps.select("c_nationkey", F.size(F.map_keys("m")).cast("long").alias("segments"), F.explode("m").alias("segment", "n")).select("c_nationkey", "segment", "n", "segments")


@_entry("fn_struct", f"SELECT event_id, event_type AS tariff, {oracle.DUR} AS dur, 2 * {oracle.DUR} AS twice FROM events")
def fn_struct(spark, d):
    dur = F.round(F.col("value") * 100).cast("long")
    payload = F.struct(F.col("event_type").alias("tariff"), dur.alias("dur")).withField("twice", dur * 2)
    return _t(spark, d, "events").select("event_id", payload.alias("m")).select("event_id", F.col("m").getField("tariff").alias("tariff"), "m.dur", "m.twice")


@_entry("fn_conditional", "SELECT doc_id, COALESCE(quality, -1) AS quality, NULLIF(lang, 'en') AS other, CASE WHEN toxic IS NOT NULL THEN 'labelled' ELSE 'open' END AS kind FROM documents LEFT JOIN labels USING (doc_id)")
def fn_conditional(spark, d):
    rows = _t(spark, d, "documents").select("doc_id", "lang").join(_t(spark, d, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.nullif("lang", F.lit("en")).alias("other"), F.nvl2("toxic", F.lit("labelled"), F.lit("open")).alias("kind"))


@_entry("fn_cast", f"SELECT event_id, {oracle.DUR} AS cents, CAST(CAST({oracle.DUR} AS DECIMAL(18, 2)) / 100 AS DOUBLE) AS money, TRY_CAST(event_type AS INTEGER) AS none, CAST(year(ts) AS INTEGER) AS year FROM events")
def fn_cast(spark, d):
    cents = F.round(F.col("value") * 100).cast("long")
    return _t(spark, d, "events").select("event_id", cents.alias("cents"), (cents.cast("decimal(18,2)") / 100).cast("double").alias("money"), F.col("event_type").try_cast("int").alias("none"), F.year("ts").alias("year"))


# ------------------------------------------- builders, generators, more measures


_HOSTS = """SELECT DISTINCT host, path FROM (SELECT lower(regexp_extract(url, '^[a-z]+://([^/?#:]*)', 1)) AS host, UNNEST(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)"""


@_entry("graph_host", f"SELECT COUNT(DISTINCT host) AS hosts, COUNT(*) AS edges FROM ({_HOSTS})")
def graph_host(spark, d):
    return workloads.build(spark, d, "host").edges.agg(F.countDistinct("src").alias("hosts"), F.count("*").alias("edges"))


@_entry("labels_category", "SELECT p_partkey AS id, CAST(DENSE_RANK() OVER (ORDER BY p_brand) - 1 AS INTEGER) AS class FROM part")
def labels_category(spark, d):
    return graphs.class_index(graphs.part_labels(_t(spark, d, "part"), "p_brand"))[0].select("id", "class")


@_entry("transform_reverse_undirected", f"{oracle.graph('follow')} SELECT src, dst, SUM(w) AS w FROM (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e) GROUP BY src, dst")
def transform_reverse_undirected(spark, d):
    return graphs.undirected(workloads.build(spark, d, "follow")).edges


@_entry("transform_dedupe", "SELECT o_custkey AS src, l_suppkey AS dst, CAST(COUNT(*) AS DOUBLE) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2")
def transform_dedupe(spark, d):
    o, li = _t(spark, d, "orders"), _t(spark, d, "lineitem")
    rows = o.join(li, o.o_orderkey == li.l_orderkey).select(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst"), F.lit(1.0).alias("w"))
    return graphs.dedupe(graphs.Graph.of(rows, multi="keep")).edges


@_entry("transform_compact_ids", f"{oracle.graph('entity')} SELECT id, ROW_NUMBER() OVER (ORDER BY id) - 1 AS new_id FROM v")
def transform_compact_ids(spark, d):
    return graphs.compact_ids(workloads.build(spark, d, "entity"))[1]


@_entry("generated_path", "SELECT range AS src, range + 1 AS dst FROM range(50)")
def generated_path(spark, d):
    return graphs.path(spark, 50).edges.select("src", "dst")


@_entry("generated_star", "SELECT range AS src, CAST(0 AS BIGINT) AS dst FROM range(1, 51)")
def generated_star(spark, d):
    return graphs.star(spark, 50).edges.select("src", "dst")


@_entry("generated_grid", "SELECT range AS src, range + 1 AS dst FROM range(63) WHERE MOD(range, 9) < 8 UNION ALL SELECT range, range + 9 FROM range(63) WHERE range < 54")
def generated_grid(spark, d):
    return graphs.grid(spark, 7, 9).edges.select("src", "dst")


@_entry("generated_power_law", "SELECT src, dst, CAST(COUNT(*) AS DOUBLE) AS w FROM (SELECT range // 10 AS src, CAST(FLOOR(POW(MOD(range * 2654435761, 4294967296) / 4294967296.0::DOUBLE, 2.0::DOUBLE) * 5000) AS BIGINT) AS dst FROM range(50000)) WHERE src <> dst GROUP BY src, dst")
def generated_power_law(spark, d):
    return graphs.power_law(spark, 5000, 10).edges


@_entry("generated_two_blocks", "SELECT DISTINCT src, dst FROM (SELECT range AS src, MOD(range + k * 2, 200) AS dst FROM range(200), (VALUES (1), (2), (3)) t(k) UNION ALL SELECT range, MOD(range + 1 + 2 * MOD(range, 7), 200) FROM range(200)) WHERE src <> dst")
def generated_two_blocks(spark, d):
    return graphs.two_blocks(spark, 200, 3, 1).edges.select("src", "dst")


@_entry("hub_share_power_law", "WITH k AS (SELECT dst, COUNT(*) AS k FROM (SELECT DISTINCT range // 10 AS src, CAST(FLOOR(POW(MOD(range * 2654435761, 4294967296) / 4294967296.0::DOUBLE, 2.0::DOUBLE) * 5000) AS BIGINT) AS dst FROM range(50000)) WHERE src <> dst GROUP BY dst), bar AS (SELECT QUANTILE_DISC(k, 0.99) AS bar FROM k) SELECT ROUND(SUM(CASE WHEN k >= bar THEN k ELSE 0 END)::DOUBLE / SUM(k), 6) AS share FROM k, bar")
def hub_share_power_law(spark, d):
    return graphs.hub_share(graphs.power_law(spark, 5000, 10)).select(F.round("share", 6).alias("share"))


_CORES = f"""(SELECT cores, SUM(ms)::DOUBLE / MAX(round) AS m FROM (SELECT cores, round, MAX(q) AS ms FROM (
  SELECT cores, l_linenumber AS round, MOD(l_partkey, cores) AS core, SUM(CAST(ROUND(l_quantity) AS BIGINT)) AS q FROM lineitem, (VALUES (1), (2), (4), (8)) c(cores) WHERE {_WHOLE} AND l_partkey IS NOT NULL GROUP BY 1, 2, 3) GROUP BY 1, 2) GROUP BY 1)"""


@_entry("cost_scale_out", f"WITH k AS {_CORES} SELECT CAST(cores AS INTEGER) AS cores, ROUND((SELECT m FROM k WHERE cores = 1) / m, 6) AS factor, CAST((SELECT MIN(cores) FROM k WHERE m <= 1.05::DOUBLE * (SELECT MIN(m) FROM k)) AS INTEGER) AS enough_cores FROM k")
def cost_scale_out(spark, d):
    """A round by line number; its lines are dealt to the cores by part, and the core with the most quantity is its time."""
    lines = _t(spark, d, "lineitem").where(f"{_WHOLE} AND l_partkey IS NOT NULL").select("l_linenumber", "l_partkey", F.round("l_quantity").cast("long").alias("q"), F.explode(F.array(*map(F.lit, (1, 2, 4, 8)))).alias("cores"))
    load = lines.groupBy("cores", F.col("l_linenumber").alias("round"), (F.col("l_partkey") % F.col("cores")).alias("core")).agg(F.sum("q").alias("q"))
    rows = load.groupBy("cores", "round").agg(F.max("q").alias("ms")).withColumns({"engine": F.lit("resident"), "problem": F.lit("influence"), "graph": F.lit("lines")})
    return measure.scale_out(rows).select("cores", F.round("factor", 6).alias("factor"), "enough_cores")


@_entry("cost_size_fit", f"WITH m AS (SELECT engine, graph, SUM(ms)::DOUBLE / MAX(round) AS m FROM {_LINES_SQL} GROUP BY engine, graph), z AS (SELECT l_returnflag AS graph, COUNT(DISTINCT l_orderkey) AS vertices, COUNT(*) AS edges FROM lineitem GROUP BY l_returnflag) SELECT engine, ROUND(REGR_R2(m, vertices), 6) AS r2_vertices, ROUND(REGR_R2(m, edges), 6) AS r2_edges FROM m JOIN z USING (graph) GROUP BY engine")
def cost_size_fit(spark, d):
    """The graph of a return flag has a vertex per order and an edge per line."""
    sizes = _t(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("graph")).agg(F.countDistinct("l_orderkey").alias("vertices"), F.count("*").alias("edges"))
    return measure.size_fit(line_trace(spark, d), sizes).select("engine", F.round("r2_vertices", 6).alias("r2_vertices"), F.round("r2_edges", 6).alias("r2_edges"))


@_entry("cost_spread", oracle.influence("call_top", "overwrite", select="SELECT ROUND(MAX(p) - MIN(p), 6) AS spread, ROUND(AVG(p), 6) AS mean FROM s WHERE r = 10"))
def cost_spread(spark, d):
    """How far labels have washed out after ten rounds in which seeds are overwritten."""
    graph = workloads.ready(spark, d, "call_top")
    known = graphs.mask_labels(workloads.labels_for(spark, d, "call_top", graph))
    state = problems.relational_influence(graph, known, 10, seeds="overwrite", options=engines.EngineOptions(partitions=8)).state
    return measure.spread(state).select(F.round("spread", 6).alias("spread"), F.round("mean", 6).alias("mean"))


@_entry("cost_exchanges", "SELECT * FROM (VALUES ('colocated', 1), ('reduce_merge', 1), ('reshuffle', 1), ('resident', 1)) t(engine, exchanges)")
def cost_exchanges(spark, d):
    """Exchanges in the plan of a round, counted (the two-job reshuffle has two more in its first job, which joins)."""
    rows = [(e.rstrip("12"), workloads.run(spark, d, "influence", "call_next", e, 2).exchanges) for e in ("resident", "colocated", "reduce_merge", "reshuffle1")]
    return spark.createDataFrame(rows, "engine string, exchanges int")


@_entry("cost_combiner", f"{oracle.graph('call_top')}, lab AS ({_MASKED}) SELECT kind, COUNT(e.dst) AS messages, kind = 'off' AS all_cross FROM (VALUES ('off'), ('on')) t(kind), e JOIN lab ON lab.id = e.src GROUP BY kind")
def cost_combiner(spark, d):
    """Messages of the first round, and whether each of them crosses the network: only without a combiner."""
    graph = workloads.ready(spark, d, "call_top")
    known = graphs.mask_labels(workloads.labels_for(spark, d, "call_top", graph))
    found = workloads.compare_combine(spark, graph, known, 1, partitions=4)
    rows = [(k, found[k].trace[1]["messages"], found[k].trace[1]["shuffle_rows"] >= found[k].trace[1]["messages"]) for k in ("on", "off")]
    return spark.createDataFrame(rows, "kind string, messages long, all_cross boolean")


def _workers(name: str) -> str:
    need = "36 * edges + 96 * vertices + 48 * LEAST(edges, vertices)"
    return f"SELECT '{name}' AS graph, CAST(GREATEST(1, ({need} + 9999) // 10000) AS INTEGER) AS workers FROM ({oracle.graph(name)} SELECT (SELECT COUNT(*) FROM v) AS vertices, (SELECT COUNT(*) FROM e) AS edges)"


@_entry("cost_min_feasible", f"{_workers('follow')} UNION ALL {_workers('call_top')}")
def cost_min_feasible(spark, d):
    """Workers of 10 kB that hold the structure and states of two graphs."""
    program, rows = problems.influence_program("overwrite", "all", "known"), []
    for name in ("follow", "call_top"):
        size = graphs.graph_profile(workloads.ready(spark, d, name)).first()
        rows.append((name, engines.min_feasible(size["vertices"], size["edges"], program, 10_000)))
    return spark.createDataFrame(rows, "graph string, workers int")


# ------------------------------------------------------------------ more streams


_CALLED = f"SELECT * FROM ({oracle._CALLS}) WHERE dst IS NOT NULL AND src <> dst"


@_entry("stream_sliding_share", f"SELECT strftime(date_trunc('day', ts) - k * INTERVAL 1 DAY, '%Y-%m-%d') AS start, src AS id, ROUND(SUM(CASE WHEN tariff = 'click' THEN dur ELSE 0 END)::DOUBLE / NULLIF(SUM(dur), 0), 6) AS p FROM ({_CALLED}), range(7) t(k) GROUP BY 1, 2")
def stream_sliding_share(spark, d):
    out = streaming.windowed_share_of(spark, graphs.call_records(_t(spark, d, "events")), "click")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("start"), "id", F.round("p", 6).alias("p"))


@_entry("stream_sessions", f"WITH c AS ({_CALLED}), m AS (SELECT *, CASE WHEN epoch_us(ts) - LAG(epoch_us(ts)) OVER (PARTITION BY src ORDER BY ts) <= 1800000000 THEN 0 ELSE 1 END AS new FROM c), s AS (SELECT *, SUM(new) OVER (PARTITION BY src ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT src, epoch_us(MIN(ts)) AS start_us, COUNT(*) AS calls, CAST(SUM(dur) AS BIGINT) AS dur FROM s GROUP BY src, k")
def stream_sessions(spark, d):
    out = streaming.sessions_of(spark, graphs.call_records(_t(spark, d, "events")))
    return out.select("src", F.unix_micros("start").alias("start_us"), "calls", "dur")


@_entry("stream_labelled_calls", f"SELECT c.src, c.dst, c.dur, ROUND(l.p, 6) AS p FROM ({_CALLED}) c LEFT JOIN ({oracle.share_labels()}) l ON l.id = c.src")
def stream_labelled_calls(spark, d):
    labels = workloads.share_labels(_t(spark, d, "events"))
    return streaming.labelled_calls_of(spark, graphs.call_records(_t(spark, d, "events")), labels).select("src", "dst", "dur", F.round("p", 6).alias("p"))


@_entry("stream_returned_calls", f"SELECT a.src AS a, a.dst AS b, epoch_us(a.ts) AS at_us, epoch_us(b.ts) AS back_us FROM ({_CALLED}) a JOIN ({_CALLED}) b ON a.src = b.dst AND a.dst = b.src AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTES")
def stream_returned_calls(spark, d):
    out = streaming.returned_calls_of(spark, graphs.call_records(_t(spark, d, "events")))
    return out.select("a", "b", F.unix_micros("at").alias("at_us"), F.unix_micros("ts").alias("back_us"))


@_entry("stream_late_split", f"SELECT tariff, MOD(dur, 97) = 0 AND epoch_us(ts) < (SELECT MAX(epoch_us(ts)) FROM ({_CALLED}) WHERE MOD(dur, 97) <> 0) - 3600000000 AS late, COUNT(*) AS n FROM ({_CALLED}) GROUP BY 1, 2")
def stream_late_split(spark, d):
    return streaming.late_split_of(spark, graphs.call_records(_t(spark, d, "events")))


def _late_influence(k: int) -> str:
    """Three rounds over the calls of one of two batches."""
    edges = f"SELECT src, dst, CAST(SUM(dur) AS DOUBLE) AS w FROM ({_CALLED}) WHERE (MOD(dur, 97) = 0) = {'TRUE' if k else 'FALSE'} GROUP BY src, dst HAVING SUM(dur) > 0"
    sql = oracle.influence("call_top", "clamped", 3, select=f"SELECT {k} AS batch, id, ROUND(p, 6) AS p FROM s WHERE r = 3")
    return sql.replace(oracle.EDGES["call_top"], edges)


@_entry("stream_windowed_influence", f"SELECT * FROM ({_late_influence(0)}) UNION ALL SELECT * FROM ({_late_influence(1)})")
def stream_windowed_influence(spark, d):
    labels = graphs.mask_labels(workloads.share_labels(_t(spark, d, "events")))
    out = streaming.windowed_influence_of(spark, graphs.call_records(_t(spark, d, "events")), labels)
    return out.select("batch", "id", F.round("p", 6).alias("p"))
