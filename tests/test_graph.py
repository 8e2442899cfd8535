"""Hand fixtures, engine parity, invariants and cost structure of the graph methods."""

import duckdb
import pytest
from pyspark.sql import functions as F

from netprop.operators import engines, graphs, measure, placement, problems, workloads
from netprop.operators.graphs import Graph
from netprop.operators.program import VertexProgram

ENGINES = ["resident", "colocated", "reduce_merge", "reshuffle1", "reshuffle2", "auto"]
OPTIONS = engines.EngineOptions(partitions=3)


def graph(spark, rows):
    return Graph.of(spark.createDataFrame([(a, b, float(w)) for a, b, w in rows], "src long, dst long, w double"), multi="keep")


def labels(spark, given):
    return spark.createDataFrame([(k, float(v)) for k, v in given.items()], "id long, p double")


def states(frame, column):
    return {r["id"]: r[column] for r in frame.collect()}


F1 = [(1, 2, 1), (2, 3, 1), (1, 3, 1), (3, 4, 1), (5, 1, 1)]


@pytest.mark.parametrize("engine", ENGINES)
def test_hops_fixture(spark, engine):
    r = problems.shortest_hops(graph(spark, F1), 1, engine, options=OPTIONS)
    assert states(r.state, "hops") == {1: 0, 2: 1, 3: 1, 4: 2, 5: None}
    if engine not in ("auto",):
        assert [(t["messages"], t["improved"]) for t in r.trace[1:]][:3] == [(2, 2), (2, 1), (0, 0)]
    assert r.halted


def test_activation_policies_differ(spark):
    g = graph(spark, [(1, 3, 1), (2, 3, 3), (3, 4, 2), (1, 4, 2)])
    run = lambda n, how: states(problems.relational_influence(g, labels(spark, {1: 1, 2: 0}), n, seeds="overwrite", activation=how, options=OPTIONS).state, "p")
    assert run(1, "all")[3] == 0.25 and run(1, "all")[4] == 1
    assert run(2, "all")[4] == 0.625 and run(2, "messaged")[4] == 0.25


@pytest.mark.parametrize("engine", ["resident", "colocated", "reduce_merge", "reshuffle1", "reshuffle2"])
def test_seed_policies(spark, engine):
    g, known = graph(spark, [(1, 2, 1), (2, 1, 1), (3, 1, 1), (3, 2, 1)]), labels(spark, {1: 1, 3: 0})
    run = lambda n, s: states(problems.relational_influence(g, known, n, engine, s, options=OPTIONS).state, "p")
    assert run(1, "overwrite") == {1: 0, 2: 0.5, 3: 0}
    assert run(2, "overwrite") == {1: 0.25, 2: 0, 3: 0}
    assert run(2, "clamped") == {1: 1, 2: 0.5, 3: 0}


def test_oscillation_and_fixed_point(spark):
    g = graph(spark, [(1, 2, 1), (2, 1, 1)])
    for n, want in ((1, (0, 1)), (2, (1, 0)), (3, (0, 1))):
        got = states(problems.relational_influence(g, labels(spark, {1: 1, 2: 0}), n, seeds="overwrite", options=OPTIONS).state, "p")
        assert (got[1], got[2]) == want
    got = states(problems.relational_influence(graph(spark, F1), labels(spark, {k: 0.3 for k in range(1, 6)}), 4, seeds="overwrite", options=OPTIONS).state, "p")
    assert all(abs(v - 0.3) < 1e-12 for v in got.values())


@pytest.mark.parametrize("layout", ["array", "long"])
def test_class_vectors_share_a_denominator(spark, layout):
    g = graph(spark, [(1, 4, 1), (2, 4, 1), (3, 4, 2), (5, 4, 9)])
    known = spark.createDataFrame([(1, 0, 1.0), (2, 1, 1.0), (3, 0, 1.0)], "id long, class int, p double")
    out = problems.relational_influence_classes(g, known, 2, 1, layout=layout, options=OPTIONS)
    assert {r["class"]: r["p"] for r in out.where("id = 4").collect()} == {0: 0.75, 1: 0.25}


def test_ties(spark):
    out = spark.createDataFrame([(3, 0, 0.5), (3, 1, 0.5)], "id long, class int, p double")
    assert problems.decide(out).first()["class"] == 0
    assert problems.decide(spark.createDataFrame([(1, 0.5)], "id long, p double"), "threshold").first()["positive"]


def test_depth_and_quiescence(spark):
    g = graphs.path(spark, 12)
    fixed = states(problems.shortest_hops(g, 0, stop="fixed", options=OPTIONS).state, "hops")
    assert fixed == {k: (k if k <= 10 else None) for k in range(13)}
    full = problems.shortest_hops(g, 0, max_rounds=50, options=OPTIONS)
    assert states(full.state, "hops")[12] == 12 and full.rounds == 13
    short = problems.shortest_hops(g, 0, max_rounds=5, options=OPTIONS)
    assert not short.halted and short.rounds == 5 and states(short.state, "hops")[6] is None


def test_recursive_query_has_no_row_limit(spark):
    spark.conf.set("spark.sql.cteRecursionRowLimit", "3")
    try:
        assert states(problems.recursive_sql_hops(spark, graphs.path(spark, 6), 0), "hops") == {k: k for k in range(7)}
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")


@pytest.mark.parametrize("engine", ENGINES)
def test_quiet_means_quiet(spark, engine):
    """Deeper than ten levels, whatever the engine and however often the resident one writes its state."""
    g = graphs.path(spark, 13)
    for every in (1, 3, 100) if engine == "resident" else (5,):
        found = problems.shortest_hops(g, 0, engine, options=engines.EngineOptions(partitions=3, checkpoint_every=every))
        assert states(found.state, "hops") == {k: k for k in range(14)} and found.halted


def test_combiner_and_hubs(spark):
    g, known = graphs.star(spark, 8), labels(spark, {k: 1 for k in range(1, 9)})
    found = {k: problems.relational_influence(g, known, 1, options=engines.EngineOptions(partitions=3, **o)) for k, o in {"on": {}, "off": {"combine": False}, "salted": {"salt": 4, "hub_degree": 2}}.items()}
    assert {k: states(r.state, "p")[0] for k, r in found.items()} == {"on": 1, "off": 1, "salted": 1}
    assert all(r.trace[1]["messages"] == 8 for r in found.values())


def test_traffic_is_measured_after_the_combiner(spark):
    g = graphs.star(spark, 900)
    known = labels(spark, {k: 1 for k in range(1, 901)})
    run = lambda **o: problems.relational_influence(g, known, 1, options=engines.EngineOptions(partitions=3, **o)).trace[1]
    on, off, salted = run(), run(combine=False), run(salt=4, hub_degree=100)
    assert on["messages"] == off["messages"] == salted["messages"] == 900
    # a round's own counts add one row a partition
    assert on["shuffle_rows"] <= 3 + 3 and off["shuffle_rows"] >= 900 and on["shuffle_rows"] <= salted["shuffle_rows"] <= 3 * 4 + 9
    assert 0 < on["shuffle_bytes"] < off["shuffle_bytes"]


def test_nothing_is_left_behind(spark):
    before = set(t.name for t in spark.catalog.listTables())
    kept = len(list(spark.sparkContext._jsc.getPersistentRDDs()))
    for engine in ("resident", "colocated", "reduce_merge", "reshuffle2"):
        problems.shortest_hops(graph(spark, F1), 1, engine, options=OPTIONS)
    with pytest.raises(Exception):  # noqa: B017  (a run that fails half-way)
        problems.shortest_hops(Graph(graph(spark, F1).edges.withColumn("w", F.raise_error(F.lit("no")).cast("double"))), 1, "colocated", options=OPTIONS)
    assert set(t.name for t in spark.catalog.listTables()) == before
    assert len(list(spark.sparkContext._jsc.getPersistentRDDs())) <= kept


@pytest.mark.parametrize("engine", ["colocated", "reduce_merge", "reshuffle1", "reshuffle2"])
def test_messaged_on_every_engine(spark, engine):
    g = graph(spark, [(1, 3, 1), (2, 3, 3), (3, 4, 2), (1, 4, 2)])
    got = states(problems.relational_influence(g, labels(spark, {1: 1, 2: 0}), 2, engine, "overwrite", activation="messaged", options=OPTIONS).state, "p")
    assert got[4] == 0.25


def test_numbers_without_gaps(spark):
    from netprop.operators.ranks import numbered

    df = spark.range(500).select((F.col("id") * 7919 % 500).alias("k"), (F.col("id") % 3).alias("g"))
    got = numbered(df, ["k"], "n", "g").collect()
    for g in range(3):
        mine = sorted((r.n, r.k) for r in got if r.g == g)
        assert [n for n, _ in mine] == list(range(len(mine))) and [k for _, k in mine] == sorted(k for _, k in mine)
    assert sorted(r.n for r in numbered(df, ["k"], "n").collect()) == list(range(500))


def test_a_mean_is_no_combiner():
    ok = dict(name="x", state={"p": "double"}, payload={"m": lambda: F.col("p")}, update={"p": lambda: F.col("m")}, sends=lambda: F.lit(True), changed=lambda: F.lit(True))
    with pytest.raises(ValueError):
        VertexProgram(combine={"m": "avg"}, **ok)


def test_edge_cases(spark):
    empty = graph(spark, F1).edges.where("false")
    with pytest.raises(ValueError):
        problems.shortest_hops(Graph(empty), 1)
    with pytest.raises(ValueError):
        graph(spark, [(1, 2, 0)]).checked()
    lone = Graph(empty, spark.createDataFrame([(7,)], "id long"))
    assert states(problems.shortest_hops(lone, 7, options=OPTIONS).state, "hops") == {7: 0}
    assert states(problems.shortest_hops(graph(spark, [(1, 1, 1)]), 1, options=OPTIONS).state, "hops") == {1: 0}
    silent = problems.relational_influence(graph(spark, F1), labels(spark, {}), 2, options=OPTIONS)
    assert set(states(silent.state, "p").values()) == {None}


def test_engines_agree_with_loops_and_each_other(spark, sf):
    g = workloads.build(spark, sf, "call_top")
    known = workloads.labels_for(spark, sf, "call_top", g)
    seeds = graphs.mask_labels(known)
    marked = states(seeds, "p")
    ids = [r["id"] for r in g.vertices.unionByName(known.select("id")).distinct().collect()]
    edges = [(r["src"], r["dst"], r["w"]) for r in g.edges.collect()]
    want = problems.brute(edges, {i: marked.get(i) for i in ids}, "influence", 4, "clamped", set(marked))
    for engine in ("resident", "colocated", "reshuffle2"):
        got = states(problems.relational_influence(g, seeds, 4, engine, options=OPTIONS).state, "p")
        assert got.keys() >= set(want) - {i for i in want if i not in got} and all(abs(got[i] - want[i]) < 1e-9 for i in got if got[i] is not None)


def test_hop_invariants(spark, sf):
    g = workloads.build(spark, sf, "follow")
    s = problems.shortest_hops(g, 0, options=OPTIONS).state
    assert {r["hops"]: r["vertices"] for r in problems.hop_histogram(s).collect()} == {0: 1, 1: 10, 2: 149}
    d, e = s.withColumnRenamed("id", "src").withColumnRenamed("hops", "a"), s.withColumnRenamed("id", "dst").withColumnRenamed("hops", "b")
    assert not g.edges.join(d, "src").join(e, "dst").where("b is null or b > a + 1").take(1)


def test_cost_structure(spark):
    """One exchange a round where the structure stays, and no structure written; two jobs where it is joined first."""
    found = {e: problems.relational_influence(graph(spark, F1), labels(spark, {1: 1}), 3, e, options=OPTIONS) for e in ("resident", "colocated", "reduce_merge", "reshuffle2")}
    assert {e: found[e].exchanges for e in ("resident", "colocated", "reduce_merge")} == {"resident": 1, "colocated": 1, "reduce_merge": 1}
    stored = {e: r.trace[-1]["stored_rows"] for e, r in found.items()}
    # reshuffle stores the state and, between its two jobs, records with their edges; the resident state is written every fifth round
    assert stored["resident"] == 0 and stored["colocated"] == 5 and stored["reduce_merge"] == 10 and stored["reshuffle2"] == 15
    often = problems.relational_influence(graph(spark, F1), labels(spark, {1: 1}), 3, options=engines.EngineOptions(partitions=3, checkpoint_every=1))
    assert often.trace[-1]["stored_rows"] == 5 and often.trace[-1]["stored_bytes"] > 0 and found["resident"].trace[-1]["stored_bytes"] == 0
    assert all(r.trace[-1]["stored_bytes"] > 0 for e, r in found.items() if e != "resident") and all(r.trace[-1]["shuffle_bytes"] > 0 for r in found.values())


@pytest.mark.parametrize("strategy", ["hash", "range", "cluster"])
def test_placement_changes_nothing_but_place(spark, strategy):
    g = graphs.two_blocks(spark, 40, 3, 1)
    where = placement.part_of(g, strategy, 4, g.vertices.select("id", (F.col("id") % 2).alias("value")))
    assert where.count() == 40 and where.agg(F.max("part")).first()[0] < 4
    got = placement.placed_hops(g, 0, where, 4)
    assert states(got, "hops") == states(problems.shortest_hops(g, 0, options=OPTIONS).state, "hops")
    moved, names = placement.relabel(g, where, 4)
    assert not names.join(where, "id").where("pmod(hash(new_id), 4) <> part").take(1)


def test_measures(spark):
    t = spark.createDataFrame([("a", "p", "x", "g", 1, 1, 1), ("a", "p", "x", "g", 1, 2, 1), ("a", "p", "x", "g", 1, 3, 2)], "run_id string, problem string, engine string, graph string, cores int, round int, ms long")
    fit = measure.linear_fit(t).first()
    assert abs(fit.slope - 1.5) < 1e-9 and abs(fit.intercept + 2 / 3) < 1e-9 and abs(fit.r2 - 27 / 28) < 1e-9
    two = spark.createDataFrame([("a", "p", "reshuffle", "g", 1, 3000), ("b", "p", "resident", "g", 1, 300)], "run_id string, problem string, engine string, graph string, round int, ms long")
    fast = measure.speedup(two).where("engine = 'resident'").first()
    assert fast.times == 10 and abs(fast.percent_less - 90) < 1e-9
    even = spark.createDataFrame([(r, "p", r, "g", i + 1, ms) for r, row in (("resident", (30, 10, 10)), ("reshuffle", (10, 20, 25))) for i, ms in enumerate(row)], "run_id string, problem string, engine string, graph string, round int, ms long")
    assert measure.break_even(even).first().break_even == 3


def test_engine_choice():
    p = problems.hop_program()
    assert engines.choose_engine(100, 1000, p, 10**9, 10)[0] == "resident"
    assert engines.choose_engine(10**9, 10**10, p, 10**9, 10)[0] == "colocated"
    assert engines.choose_engine(100, 1000, p, 10**9, 2)[0] == "colocated"
    assert engines.min_feasible(43_718_466, 688_352_467, problems.influence_program("overwrite", "all", "known"), 7_500_000_000) > engines.min_feasible(13_914_680, 67_184_654, p, 7_500_000_000)


def test_related_lists_and_shares(spark):
    lines = spark.createDataFrame([(10, "A"), (10, "B"), (10, "C"), (11, "A"), (11, "D")], "l_orderkey long, p string").withColumn("l_partkey", F.ascii("p"))
    got = {(chr(r.src), chr(r.dst)): round(r.w, 6) for r in graphs.related_graph(lines).edges.collect()}
    assert got[("A", "B")] == round(1 / 3, 6) and got[("B", "A")] == 0.5 and got[("D", "A")] == 1 and len(got) == 8
    calls = spark.createDataFrame([(1, "x", 300), (1, "y", 100), (2, "y", 50), (3, "z", 9)], "src long, tariff string, dur long")
    among = spark.createDataFrame([("x",), ("y",)], "tariff string")
    assert states(graphs.duration_share(calls, "x", among), "p") == {1: 0.75, 2: 0}


def test_lead_crosses_cells(spark):
    rows = spark.sql("SELECT id, timestamp '2024-01-01' + make_interval(0,0,0,0,0,0,id * 700) AS ts, id * 10 AS v FROM range(20)")
    got = states(graphs.ordered_lead(rows, "ts", "id", "v", "n", 3600), "n")
    assert got == {i: (i + 1) * 10 if i < 19 else None for i in range(20)}


STREAMS = ["stream_dedup", "stream_windowed_edges", "stream_sliding_share", "stream_sessions", "stream_labelled_calls", "stream_returned_calls", "stream_late_split", "stream_windowed_influence", "stream_incremental_hops", "stream_last_callee"]


@pytest.mark.parametrize("name", STREAMS)
def test_streams(spark, sf, name):
    """What a stream leaves when it has read all there is equals the batch result in SQL."""
    from netprop.plans import catalogue

    query, sql = catalogue.ENTRIES[name]
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    want, got = con.sql(sql), query(spark, sf)
    order = [want.columns.index(c) for c in got.columns]
    assert sorted(map(str, (tuple(r) for r in got.collect()))) == sorted(str(tuple(r[i] for i in order)) for r in want.fetchall())


MEASURED = ["agg_cube", "agg_pivot", "agg_unpivot", "cost_break_even", "cost_cumulative", "cost_first_round", "cost_fit", "cost_mean_round", "cost_min_feasible", "cost_scale_out", "cost_size_fit", "cost_speedup"]


@pytest.mark.parametrize("name", MEASURED)
def test_measures_read_a_given_table(spark, sf, tmp_path, name):
    """Equal to SQL, also on other tables, whose results are others."""
    import shutil

    from netprop.plans import catalogue

    query, sql = catalogue.ENTRIES[name]
    con, found = duckdb.connect(), []
    for table in ("orders", "events"):
        shutil.copy(f"{sf}/{table}.parquet", tmp_path)
    con.sql(f"COPY (SELECT * FROM '{sf}/lineitem.parquet' WHERE l_orderkey % 3 <> l_linenumber % 2 UNION ALL SELECT * REPLACE (NULL AS l_returnflag) FROM '{sf}/lineitem.parquet' WHERE l_orderkey % 7 = 0) TO '{tmp_path}/lineitem.parquet'")
    for where in (sf, str(tmp_path)):
        for table in ("lineitem", "orders", "events"):
            con.sql(f"CREATE OR REPLACE VIEW {table} AS SELECT * FROM '{where}/{table}.parquet'")
        want, got = con.sql(sql), query(spark, where)
        order = [want.columns.index(c) for c in got.columns]
        found.append(sorted(map(str, (tuple(r) for r in got.collect()))))
        assert found[-1] == sorted(str(tuple(r[i] for i in order)) for r in want.fetchall())
    assert found[0] != found[1] or name == "cost_break_even"


def test_sources_and_sinks(spark, tmp_path):
    from netprop.sources import tables

    g = graph(spark, F1)
    for fmt in ("parquet", "orc", "json"):
        tables.write_graph(g, f"{tmp_path}/{fmt}", fmt)
        assert spark.read.format(fmt).load(f"{tmp_path}/{fmt}").count() == 5
    (tmp_path / "edges.tsv").write_text("1\t2\nx\t3\n2\t3\n\n4\t\n")
    read, bad = tables.read_edge_list(spark, f"{tmp_path}/edges.tsv")
    assert {r.src: r.dst for r in read.edges.collect()} == {1: 2, 2: 3} and bad.count() == 2
    (tmp_path / "lists.json").write_text('{"id": 1, "related": [2, 3]}\n{"id": 4, "related": []}\n')
    lists = tables.read_adjacency(spark, f"{tmp_path}/lists.json")
    assert lists.edges.count() == 2 and lists.vertices.count() == 4
    report = tables.scan_report(spark.read.parquet(f"{tmp_path}/parquet").where("w > 0").select("src"))
    assert len(report) == 1


def test_experiments_run(spark, sf):
    from netprop import experiments

    found = experiments.totals(spark, sf, "hops", "chain", ("reshuffle2", "resident"), 3)
    assert {r["engine"] for r in found["fit"]} == {"reshuffle2", "resident"} and all(0 < r["r2"] <= 1 for r in found["fit"]) and len(found["total_ms"]) == 8
    out = experiments.combiner(spark, sf, (2000, 50), 1, 4)
    assert out["off"][1]["shuffle_rows"] > 3 * out["on"][1]["shuffle_rows"]
    assert engines.cache_overhead(spark, graphs.power_law(spark, 20_000, 5).edges, 2) > 0
    moved = experiments.workloads.compare_placements(spark, graphs.two_blocks(spark, 40, 3, 1), 0, spark.range(40).select("id", (F.col("id") % 2).alias("value")), 4)
    assert {r["strategy"] for r in moved.collect()} == {"hash", "range", "cluster"}


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 160
    assert set(e.oracle_sql()) <= set(e.queries())
