"""SQL twins of the graph queries for DuckDB."""

from __future__ import annotations

DUR = "CAST(ROUND(value * 100) AS BIGINT)"
_CALLS = f"SELECT user_id AS src, LEAD(user_id) OVER (ORDER BY ts, event_id) AS dst, event_type AS tariff, {DUR} AS dur, ts FROM events"
_RANKS = "SELECT event_type AS tariff, COUNT(*) AS n, ROW_NUMBER() OVER (ORDER BY COUNT(*) DESC, event_type) AS rank FROM events GROUP BY event_type"


def _call(ranks: str | None) -> str:
    own = f" AND tariff IN (SELECT tariff FROM ({_RANKS}) WHERE rank IN ({ranks}))" if ranks else ""
    return f"SELECT src, dst, CAST(SUM(dur) AS DOUBLE) AS w FROM ({_CALLS}) WHERE dst IS NOT NULL AND src <> dst{own} GROUP BY src, dst HAVING SUM(dur) > 0"


_PARTS = "SELECT DISTINCT l_orderkey, l_partkey FROM lineitem"
_PAIRS = f"SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM ({_PARTS}) a JOIN ({_PARTS}) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey"
_WORDS = r"SELECT DISTINCT doc_id, UNNEST(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS t FROM documents"
EDGES = {
    "call": _call(None),
    "call_top": _call("1, 2"),
    "call_next": _call("3, 4"),
    "related": f"SELECT src, dst, 1.0::DOUBLE / COUNT(*) OVER (PARTITION BY src) AS w FROM ({_PAIRS})",
    "follow": """SELECT DISTINCT src, dst, 1.0::DOUBLE AS w FROM (
        SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey
        UNION ALL SELECT l_suppkey * 2 + 1, o_custkey * 2 FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R')""",
    "sequence": """SELECT src, dst, CAST(COUNT(*) AS DOUBLE) AS w FROM (
        SELECT l_partkey AS src, LEAD(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem)
        WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst""",
    "chain": "SELECT COALESCE(LAG(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), -1 - o_custkey) AS src, o_orderkey AS dst, 1.0::DOUBLE AS w FROM orders",
    "entity": """SELECT DISTINCT src, dst, 1.0::DOUBLE AS w FROM (
        SELECT o_custkey * 8 AS src, o_orderkey * 8 + 1 AS dst FROM orders UNION ALL SELECT l_orderkey * 8 + 1, l_partkey * 8 + 2 FROM lineitem
        UNION ALL SELECT l_partkey * 8 + 2, l_suppkey * 8 + 3 FROM lineitem UNION ALL SELECT s_suppkey * 8 + 3, s_nationkey::BIGINT * 8 + 4 FROM supplier
        UNION ALL SELECT n_nationkey::BIGINT * 8 + 4, n_regionkey::BIGINT * 8 + 5 FROM nation)""",
    "wordlink": f"""SELECT src, dst, CAST(w AS DOUBLE) AS w FROM (
        SELECT src, dst, w, ROW_NUMBER() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM (
        SELECT a.doc_id AS src, b.doc_id AS dst, COUNT(*) AS w FROM rare a JOIN rare b ON a.t = b.t AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id)) WHERE r <= 10""",
}
_PRE = {
    "wordlink": f"""words AS MATERIALIZED (SELECT * FROM ({_WORDS}) WHERE length(t) >= 4),
      rare AS MATERIALIZED (SELECT doc_id, t FROM words WHERE t IN (SELECT t FROM words GROUP BY t HAVING COUNT(*) BETWEEN 2 AND 20)), """
}
SOURCE = {g: "0" for g in EDGES} | {"chain": "(SELECT MIN(src) FROM e)"}


def graph(name: str, recursive: bool = False) -> str:
    """WITH clause that defines ``e`` (edges) and ``v`` (vertex ids)."""
    extra = " UNION SELECT doc_id FROM documents" if name == "wordlink" else ""
    return f"WITH {'RECURSIVE ' if recursive else ''}{_PRE.get(name, '')}e AS MATERIALIZED ({EDGES[name]}), v AS MATERIALIZED (SELECT src AS id FROM e UNION SELECT dst FROM e{extra})"


def edges(name: str) -> str:
    return f"{graph(name)} SELECT src, dst, ROUND(w, 6) AS w FROM e"


def profile(name: str) -> str:
    return f"""{graph(name)} SELECT (SELECT COUNT(*) FROM v) AS vertices, (SELECT COUNT(*) FROM e) AS edges,
      ROUND((SELECT COUNT(*) FROM e)::DOUBLE / (SELECT COUNT(*) FROM v), 6) AS avg_degree, (SELECT MAX(k) FROM (SELECT COUNT(*) AS k FROM e GROUP BY dst)) AS max_in_degree"""


def degrees(name: str) -> str:
    return f"{graph(name)} SELECT degree, COUNT(*) AS vertices FROM (SELECT COUNT(*) AS degree FROM e GROUP BY dst) GROUP BY degree"


_CAPPED = "h(id, d) AS (SELECT CAST({s} AS BIGINT), 0 UNION SELECT e.dst, h.d + 1 FROM h JOIN e ON e.src = h.id WHERE h.d < {cap}), best AS (SELECT id, MIN(d) AS d FROM h GROUP BY id)"
#: Level by level until no vertex is new: a vertex has one row.
_QUIET = "h(id, d) USING KEY (id) AS (SELECT CAST({s} AS BIGINT), 0 UNION SELECT e.dst, MIN(h.d) + 1 FROM h JOIN e ON e.src = h.id LEFT JOIN recurring.h AS k ON k.id = e.dst WHERE k.id IS NULL GROUP BY e.dst), best AS (SELECT id, d FROM h)"


def hops(name: str, cap: int | None = None, select: str = "SELECT v.id, CAST(best.d AS INTEGER) AS hops FROM v LEFT JOIN best ON best.id = v.id", source: str | None = None) -> str:
    """Without ``cap`` the search ends when nothing is new."""
    found = (_QUIET if cap is None else _CAPPED).format(s=source or SOURCE[name], cap=cap)
    return f"{graph(name, True)}, {found} {select}"


def hop_messages(name: str) -> str:
    """Messages and senders of each round: a vertex sends once, in the round after it was found."""
    return hops(name, select="SELECT CAST(d + 1 AS INTEGER) AS round, COUNT(DISTINCT best.id) AS senders, COUNT(e.dst) AS messages FROM best LEFT JOIN e ON e.src = best.id GROUP BY d")


def nearest(name: str, sources: tuple[int, ...]) -> str:
    """Hops from the nearest of several sources: the least over searches from each."""
    each = ", ".join(f"{_QUIET.format(s=x)}".replace("h(id", f"h{x}(id").replace("recurring.h ", f"recurring.h{x} ").replace("FROM h ", f"FROM h{x} h ").replace("FROM h)", f"FROM h{x})").replace("best AS", f"best{x} AS") for x in sources)
    both = " UNION ALL ".join(f"SELECT id, d FROM best{x}" for x in sources)
    return f"{graph(name, True)}, {each}, best AS (SELECT id, MIN(d) AS d FROM ({both}) GROUP BY id) SELECT v.id, CAST(best.d AS INTEGER) AS hops FROM v LEFT JOIN best ON best.id = v.id"


def distance(name: str) -> str:
    """Least weight sums: relaxed until none gets less."""
    return f"""{graph(name, True)}, h(id, d) USING KEY (id) AS (SELECT CAST({SOURCE[name]} AS BIGINT), 0.0::DOUBLE
      UNION SELECT e.dst, MIN(h.d + e.w) FROM h JOIN e ON e.src = h.id LEFT JOIN recurring.h AS k ON k.id = e.dst WHERE k.id IS NULL OR h.d + e.w < k.d GROUP BY e.dst)
      SELECT v.id, ROUND(h.d, 6) AS distance FROM v LEFT JOIN h ON h.id = v.id"""


def share_labels(ranks: str = "1, 2") -> str:
    first = ranks.split(",")[0]
    return f"""SELECT user_id AS id, SUM(CASE WHEN event_type = (SELECT tariff FROM ({_RANKS}) WHERE rank = {first}) THEN {DUR} ELSE 0 END)::DOUBLE / SUM({DUR}) AS p
      FROM events WHERE event_type IN (SELECT tariff FROM ({_RANKS}) WHERE rank IN ({ranks})) GROUP BY user_id"""


COIN = "CASE WHEN (id * 2654435761) % 4294967296 < 2147483648 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END"


def labels(name: str) -> str:
    return share_labels("3, 4" if name == "call_next" else "1, 2") if name.startswith("call") else f"SELECT id, {COIN} AS p FROM v"


def influence(name: str, seeds: str = "clamped", rounds: int = 10, mask: bool = True, activation: str = "all", select: str | None = None, prior: str | None = None) -> str:
    where = "WHERE MOD(MOD(id, 10) + 10, 10) < 7" if mask else ""
    new = {"clamped": "CASE WHEN s.seed THEN s.p ELSE COALESCE(m.lw / NULLIF(m.sw, 0), s.p) END", "overwrite": "COALESCE(m.lw / NULLIF(m.sw, 0), s.p)", "first": "COALESCE(s.p, m.lw / NULLIF(m.sw, 0))"}[seeds]
    sends = "q.p IS NOT NULL" + (" AND q.act" if activation == "messaged" else "")
    last = select or f"SELECT id, ROUND(p, 6) AS p FROM s WHERE r = {rounds}"
    return f"""{graph(name, True)}, lab AS MATERIALIZED (SELECT id, p FROM ({labels(name)}) {where}), ids AS MATERIALIZED (SELECT id FROM v UNION SELECT id FROM lab),
    s(r, id, p, seed, act) AS (
      SELECT 0, ids.id, {f"COALESCE(lab.p, {prior})" if prior else "lab.p"}, lab.p IS NOT NULL, TRUE FROM ids LEFT JOIN lab ON lab.id = ids.id
      UNION ALL SELECT s.r + 1, s.id, {new}, s.seed, m.dst IS NOT NULL FROM s
        LEFT JOIN (SELECT e.dst, SUM(q.p * e.w) AS lw, SUM(e.w) AS sw FROM s q JOIN e ON e.src = q.id WHERE {sends} GROUP BY e.dst) m ON m.dst = s.id WHERE s.r < {rounds}
    ) {last}"""


def influence_messages(name: str, rounds: int = 10) -> str:
    return influence(name, "overwrite", rounds, select=f"SELECT CAST(s.r + 1 AS INTEGER) AS round, COUNT(DISTINCT s.id) AS senders, COUNT(e.dst) AS messages FROM s LEFT JOIN e ON e.src = s.id WHERE s.p IS NOT NULL AND s.r < {rounds} GROUP BY s.r")


_CLASS = {
    "wordlink": "SELECT doc_id AS id, DENSE_RANK() OVER (ORDER BY lang) - 1 AS class FROM documents",
    "related": "SELECT p_partkey AS id, DENSE_RANK() OVER (ORDER BY p_type) - 1 AS class FROM part",
}


def classes(name: str, k: int, seeds: str = "clamped", rounds: int = 10, select: str | None = None) -> str:
    """A likelihood column per class; labelled senders share the denominator."""
    p = [f"p{i}" for i in range(k)]
    mean = [f"m.s{i} / NULLIF(m.sw, 0)" for i in range(k)]
    new = [f"CASE WHEN {'s.seed' if seeds == 'clamped' else 'FALSE'} THEN s.{a} ELSE COALESCE({b}, s.{a}) END" for a, b in zip(p, mean, strict=True)]
    last = select or " UNION ALL ".join(f"SELECT id, {i} AS class, ROUND({c}, 6) AS p FROM s WHERE r = {rounds} AND {c} > 0" for i, c in enumerate(p))
    return f"""{graph(name, True)}, truth AS MATERIALIZED ({_CLASS[name]}), ids AS MATERIALIZED (SELECT id FROM v UNION SELECT id FROM truth WHERE MOD(id, 10) < 7),
    s(r, id, seed, {', '.join(p)}) AS (
      SELECT 0, ids.id, t.id IS NOT NULL, {', '.join(f'CASE WHEN t.id IS NOT NULL THEN (CASE WHEN t.class = {i} THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) END' for i in range(k))} FROM ids LEFT JOIN (SELECT * FROM truth WHERE MOD(id, 10) < 7) t ON t.id = ids.id
      UNION ALL SELECT s.r + 1, s.id, s.seed, {', '.join(new)} FROM s
        LEFT JOIN (SELECT e.dst, SUM(e.w) AS sw, {', '.join(f'SUM(q.{c} * e.w) AS s{i}' for i, c in enumerate(p))} FROM s q JOIN e ON e.src = q.id WHERE q.p0 IS NOT NULL GROUP BY e.dst) m ON m.dst = s.id WHERE s.r < {rounds}
    ) {last}"""


def class_scores(name: str, k: int, seeds: str = "clamped", rounds: int = 10) -> str:
    best = "GREATEST(" + ", ".join(f"ROUND(p{i}, 9)" for i in range(k)) + ")"
    said = "CASE " + " ".join(f"WHEN ROUND(p{i}, 9) = {best} THEN {i}" for i in range(k)) + " END"
    return classes(
        name, k, seeds, rounds,
        f"""SELECT COUNT(*) AS hidden, COUNT(said) AS labelled, CAST(COALESCE(SUM(CASE WHEN said = class THEN 1 ELSE 0 END), 0) AS BIGINT) AS "right"
        FROM truth LEFT JOIN (SELECT id, {said} AS said FROM s WHERE r = {rounds} AND p0 IS NOT NULL) d ON d.id = truth.id WHERE MOD(truth.id, 10) >= 7""",
    )
