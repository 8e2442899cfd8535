"""Registry of the graph queries: name -> callable(spark, sf_dir), and their SQL twins."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop.operators import engines, graphs, measure, placement, problems, workloads
from netprop.plans import catalogue, oracle
from netprop.sources.tables import table

GRAPHS = tuple(oracle.EDGES)
#: Graphs on which every engine is run; the others are run on the resident engine.
ENGINE_GRAPHS = ("call_next", "call_top", "related", "follow")
PARTITIONS = 8


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hop counts from customer 0 on the follower graph, resident engine."""
    return hops(spark, sf_dir, "follow", "resident")


def _options(**how) -> engines.EngineOptions:
    return engines.EngineOptions(partitions=PARTITIONS, **how)


def edges(spark, sf_dir, name):
    return workloads.build(spark, sf_dir, name).edges.select("src", "dst", F.round("w", 6).alias("w"))


def profile(spark, sf_dir, name):
    return graphs.graph_profile(workloads.build(spark, sf_dir, name))


def degrees(spark, sf_dir, name):
    return graphs.degree_histogram(workloads.build(spark, sf_dir, name))


def _hops(spark, sf_dir, name, engine="resident", stop="quiescent", source=None, activation="improved"):
    """Quiescent runs end when no message is pending, fixed ones after ten rounds."""
    graph = workloads.ready(spark, sf_dir, name)
    return problems.shortest_hops(graph, workloads.source_of(graph, name) if source is None else source, engine, None, stop, activation, options=_options())


def hops(spark, sf_dir, name, engine="resident", stop="quiescent", source=None, activation="improved"):
    return _hops(spark, sf_dir, name, engine, stop, source, activation).state


def hop_histogram(spark, sf_dir, name):
    return problems.hop_histogram(hops(spark, sf_dir, name))


def unreached(spark, sf_dir, name):
    return problems.unreached(hops(spark, sf_dir, name))


def hop_messages(spark, sf_dir, name):
    result = _hops(spark, sf_dir, name)
    return result.trace_frame(spark).where("round > 0").select("round", F.col("active").alias("senders"), "messages")


def hops_sql(spark, sf_dir, name):
    graph = workloads.ready(spark, sf_dir, name)
    return problems.recursive_sql_hops(spark, graph, 0, 10)


def distance(spark, sf_dir, name):
    graph = workloads.ready(spark, sf_dir, name)
    return problems.shortest_paths(graph, 0, options=_options()).state.select("id", F.round("distance", 6).alias("distance"))


def labels(spark, sf_dir, name):
    graph = workloads.build(spark, sf_dir, name)
    return workloads.labels_for(spark, sf_dir, name, graph).select("id", F.round("p", 6).alias("p"))


def _influence(spark, sf_dir, name, engine="resident", seeds="overwrite", mask=True, activation="all", rounds=10, prior=None):
    graph = workloads.ready(spark, sf_dir, name)
    known = workloads.labels_for(spark, sf_dir, name, graph)
    gate = "known" if prior is None else "all"
    return problems.relational_influence(graph, graphs.mask_labels(known) if mask else known, rounds, engine, seeds, gate, activation, prior, options=_options())


def influence(spark, sf_dir, name, engine="resident", seeds="overwrite", mask=True, activation="all", rounds=10, prior=None):
    return _influence(spark, sf_dir, name, engine, seeds, mask, activation, rounds, prior).state.select("id", F.round("p", 6).alias("p"))


def decided(spark, sf_dir, name):
    return problems.decide(_influence(spark, sf_dir, name, seeds="clamped").state, "threshold")


def transferred(spark, sf_dir):
    """What the small call network learnt is the start of the large one's unlabelled vertices."""
    source = _influence(spark, sf_dir, "call_next", seeds="clamped").state
    graph = workloads.ready(spark, sf_dir, "call_top")
    known = graphs.mask_labels(workloads.labels_for(spark, sf_dir, "call_top", graph))
    return problems.transferred_influence(source, graph, known, options=_options()).state.select("id", F.round("p", 6).alias("p"))


def influence_messages(spark, sf_dir, name):
    return _influence(spark, sf_dir, name).trace_frame(spark).where("round > 0").select("round", F.col("active").alias("senders"), "messages")


def _classed(spark, sf_dir, name):
    rows = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("name")) if name == "wordlink" else graphs.part_labels(table(spark, sf_dir, "part"))
    truth, classes = graphs.class_index(rows)
    return workloads.build(spark, sf_dir, name), truth, classes.count()


def influence_classes(spark, sf_dir, name, layout="array", seeds="clamped"):
    graph, truth, k = _classed(spark, sf_dir, name)
    out = problems.relational_influence_classes(graph, graphs.mask_labels(truth), k, 10, seeds=seeds, layout=layout, options=_options())
    return out.where("p > 0").select("id", "class", F.round("p", 6).alias("p"))


def class_scores(spark, sf_dir, name, seeds="clamped"):
    graph, truth, k = _classed(spark, sf_dir, name)
    mask = graphs.mask_labels(truth)
    found = problems.relational_influence_classes(graph, mask, k, 10, seeds=seeds, options=_options())
    hidden = truth.join(mask.select("id"), "id", "left_anti")
    return measure.holdout_scores(problems.decide(found), truth, hidden).select("hidden", "labelled", "right")


def placed_hops(spark, sf_dir, strategy):
    """Hop counts after relabelling for a placement (range: by nation): the same as without."""
    graph = workloads.ready(spark, sf_dir, "entity" if strategy == "range" else "follow")
    attribute = workloads.places_of(spark, sf_dir) if strategy == "range" else None
    placed = placement.part_of(graph, strategy, PARTITIONS, attribute)
    return placement.placed_hops(graph, 0, placed, PARTITIONS)


def placement_report(spark, sf_dir):
    """Edge cut and balance of the three placements of the word-link graph, range by language."""
    graph = workloads.build(spark, sf_dir, "wordlink")
    lang = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("value"))
    out = None
    for strategy in ("hash", "range", "cluster"):
        placed = placement.part_of(graph, strategy, PARTITIONS, lang)
        row = placement.edge_cut(graph, placed).join(placement.balance(graph, placed)).select(F.lit(strategy).alias("strategy"), F.round("cut", 6).alias("cut"), F.round("vertices", 6).alias("vertices"))  # one row beside one row
        out = row if out is None else out.unionByName(row)
    return out


def combine(spark, sf_dir, kind):
    graph = workloads.ready(spark, sf_dir, "call_top")
    known = graphs.mask_labels(workloads.labels_for(spark, sf_dir, "call_top", graph))
    how = {"on": {}, "off": {"combine": False}, "salted": {"salt": 4, "hub_degree": 10}}[kind]
    return problems.relational_influence(graph, known, 10, "resident", "overwrite", options=_options(**how)).state.select("id", F.round("p", 6).alias("p"))


def engine_agreement(spark, sf_dir):
    """Resident against the full reshuffle on the follower graph: nothing may differ."""
    a, b = (influence(spark, sf_dir, "follow", e) for e in ("resident", "reshuffle2"))
    return measure.agreement(a, b, "p")


def transfer(spark, sf_dir):
    """Class distribution of the part graph's labels as the start of another network (the customers' follower graph)."""
    truth, _ = graphs.class_index(graphs.part_labels(table(spark, sf_dir, "part")))
    return problems.transfer_prior(truth, workloads.build(spark, sf_dir, "follow")).select("id", "class", F.round("p", 6).alias("p"))


def neighbour_features(spark, sf_dir):
    graph, truth, _ = _classed(spark, sf_dir, "wordlink")
    return problems.neighbour_label_features(graph, graphs.mask_labels(truth)).select("id", "class", F.round("share", 6).alias("share"))


def engine_trace(spark, sf_dir):
    """W1 and W2 at three rounds on the smallest graph: mean time per engine (rows only: times differ by run)."""
    out = [workloads.compare_engines(spark, sf_dir, p, ("call_next",), rounds=3) for p in ("influence", "hops")]
    return measure.mean_round_ms(out[0].unionByName(out[1]))


QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def _add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLE_SQL[name] = " ".join(sql.split("\n"))


for _g in GRAPHS:
    _add(f"graph_{_g}", partial(edges, name=_g), oracle.edges(_g))
    _add(f"profile_{_g}", partial(profile, name=_g), oracle.profile(_g))
    _add(f"degree_hist_{_g}", partial(degrees, name=_g), oracle.degrees(_g))
    _add(f"hops_resident_{_g}", partial(hops, name=_g), oracle.hops(_g))
for _g in ENGINE_GRAPHS:
    for _e in ("colocated", "reduce_merge", "reshuffle1", "reshuffle2", "auto"):
        _add(f"hops_{_e}_{_g}", partial(hops, name=_g, engine=_e), oracle.hops(_g))
        _add(f"influence_{_e}_{_g}", partial(influence, name=_g, engine=_e), oracle.influence(_g, "overwrite"))
    _add(f"messages_per_round_hops_{_g}", partial(hop_messages, name=_g), oracle.hop_messages(_g))
    _add(f"messages_per_round_influence_{_g}", partial(influence_messages, name=_g), oracle.influence_messages(_g))
for _g in ("call_top", "call_next", "related", "follow", "sequence"):
    _add(f"influence_resident_{_g}", partial(influence, name=_g), oracle.influence(_g, "overwrite"))
    _add(f"influence_clamped_{_g}", partial(influence, name=_g, seeds="clamped"), oracle.influence(_g, "clamped"))
for _g in ("follow", "sequence", "entity", "chain"):
    _add(f"hop_histogram_{_g}", partial(hop_histogram, name=_g), oracle.hops(_g, select="SELECT CAST(best.d AS INTEGER) AS hops, COUNT(*) AS vertices FROM v LEFT JOIN best ON best.id = v.id GROUP BY best.d"))
    _add(f"unreached_{_g}", partial(unreached, name=_g), oracle.hops(_g, select="SELECT v.id FROM v LEFT JOIN best ON best.id = v.id WHERE best.d IS NULL"))
for _g in ("chain", "follow"):
    _add(f"hops_fixed10_{_g}", partial(hops, name=_g, stop="fixed"), oracle.hops(_g, 10))
for _e in ("colocated", "reduce_merge", "reshuffle1", "reshuffle2"):
    _add(f"hops_{_e}_chain", partial(hops, name="chain", engine=_e), oracle.hops("chain"))
    _add(f"influence_messaged_{_e}_follow", partial(influence, name="follow", engine=_e, mask=False, activation="messaged"), oracle.influence("follow", "overwrite", mask=False, activation="messaged"))
_add("hops_broadcast_follow", partial(hops, name="follow", activation="all", stop="fixed"), oracle.hops("follow", 10))
_add("hops_nearest_follow", partial(hops, name="follow", source=[0, 7]), oracle.nearest("follow", (0, 7)))
for _g in ("entity", "chain", "wordlink"):
    _add(f"influence_resident_{_g}", partial(influence, name=_g), oracle.influence(_g, "overwrite"))
_add("influence_gate_all_follow", partial(influence, name="follow", prior=0.25), oracle.influence("follow", "overwrite", prior="0.25::DOUBLE"))
_add("influence_one_round_follow", partial(influence, name="follow", seeds="clamped", rounds=1), oracle.influence("follow", "clamped", 1))
_add("decide_threshold_call_top", partial(decided, name="call_top"), oracle.influence("call_top", "clamped", select="SELECT id, p >= 0.5 AS positive FROM s WHERE r = 10 AND p IS NOT NULL"))
_add("influence_transferred_call_top", transferred, f"WITH prior AS (SELECT AVG(p) AS p FROM ({oracle.influence('call_next', 'clamped', select='SELECT id, p FROM s WHERE r = 10')})) SELECT * FROM ({oracle.influence('call_top', 'clamped', prior='(SELECT p FROM prior)')})")
_add("hops_recursive_sql_follow", partial(hops_sql, name="follow"), oracle.hops("follow", 10, select="SELECT id, CAST(d AS INTEGER) AS hops FROM best"))
_add("distance_call_top", partial(distance, name="call_top"), oracle.distance("call_top"))
_add("labels_share", partial(labels, name="call_top"), f"SELECT id, ROUND(p, 6) AS p FROM ({oracle.share_labels()})")
_add("labels_coin", partial(labels, name="follow"), f"{oracle.graph('follow')} SELECT id, {oracle.COIN} AS p FROM v")
_add("influence_first_follow", partial(influence, name="follow", seeds="first"), oracle.influence("follow", "first"))
_add("influence_messaged_follow", partial(influence, name="follow", mask=False, activation="messaged"), oracle.influence("follow", "overwrite", mask=False, activation="messaged"))
_add("influence_all_labels_follow", partial(influence, name="follow", mask=False), oracle.influence("follow", "overwrite", mask=False))
_add("influence_multi_wordlink", partial(influence_classes, name="wordlink"), oracle.classes("wordlink", 4))
_add("influence_multi_long_wordlink", partial(influence_classes, name="wordlink", layout="long"), oracle.classes("wordlink", 4))
_add("influence_multi_related", partial(influence_classes, name="related"), oracle.classes("related", 6))
_add("influence_scores_wordlink", partial(class_scores, name="wordlink"), oracle.class_scores("wordlink", 4))
_add("influence_scores_overwrite_wordlink", partial(class_scores, name="wordlink", seeds="overwrite"), oracle.class_scores("wordlink", 4, "overwrite"))
for _s, _g in (("hash", "follow"), ("range", "entity"), ("cluster", "follow")):
    _add(f"placement_{_s}", partial(placed_hops, strategy=_s), oracle.hops(_g))
_add("placement_report", placement_report)
for _k in ("on", "off", "salted"):
    _add(f"combine_{_k}", partial(combine, kind=_k), oracle.influence("call_top", "overwrite"))
_add("engine_agreement", engine_agreement, f"{oracle.graph('follow')} SELECT COUNT(*) AS vertices, CAST(0 AS BIGINT) AS one_side, CAST(0 AS BIGINT) AS null_on_one, 0.0::DOUBLE AS max_difference FROM v")
_add("transfer_prior", transfer, f"{oracle.graph('follow')}, d AS (SELECT DENSE_RANK() OVER (ORDER BY p_type) - 1 AS class, COUNT(*)::DOUBLE / (SELECT COUNT(*) FROM part) AS p FROM part GROUP BY p_type) SELECT v.id, CAST(d.class AS INTEGER) AS class, ROUND(d.p, 6) AS p FROM v, d")
_add("neighbour_features_wordlink", neighbour_features, f"""{oracle.graph('wordlink')}, t AS ({oracle._CLASS['wordlink']}), m AS (SELECT e.dst AS id, t.class, SUM(e.w) AS m FROM e JOIN t ON t.id = e.src WHERE MOD(t.id, 10) < 7 GROUP BY e.dst, t.class)
  SELECT id, CAST(class AS INTEGER) AS class, ROUND(m / SUM(m) OVER (PARTITION BY id), 6) AS share FROM m""")
_add("engine_trace", engine_trace)
for _name, (_q, _sql) in catalogue.ENTRIES.items():
    _add(_name, _q, _sql)
