"""Embedding near-duplicates: int8 tile products with rigorous error bounds.

Vectors of one label are compared by cosine. Each unit vector x is kept as
scale * q + e with q of 8-bit integers; so for two vectors

    x.y = s_x s_y (q_x.q_y) + s_x (q_x.e_y) + s_y (q_y.e_x) + e_x.e_y

and by Cauchy-Schwarz |x.y - s_x s_y q_x.q_y| <= |s_x q_x| |e_y| + |s_y q_y| |e_x| + |e_x| |e_y|.
The integer products of a tile are exact (summed in double precision over steps that
float32 holds exactly), the norms of q and e are known per vector, so a pair whose
integer estimate less the bound reaches the threshold links, and one whose estimate
plus the bound stays below it cannot. Only the others are recomputed, in double
precision from the vectors as given.

Equal vectors of a label collapse first, so a very common vector is one row.
Vectors of a label are dealt to blocks; a task holds one pair of blocks, counts
links and gives a spanning forest of them, never the pairs. What is dealt to all
blocks of a label is the 8-bit codes and three numbers a vector; the vectors themselves
travel only to the tiles in which a pair of theirs is in doubt.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from netprop.llm import common

THRESHOLD = 0.98
#: Vectors in a block, about; a tile compares two blocks.
BLOCK = 2048
#: Slack for the rounding of the bounds themselves, far above double precision's.
SLACK = 1e-9


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, scale, norm of the coded part and norm of the error of each row."""
    scale = np.abs(unit).max(axis=1) / 127.0
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    coded = codes * scale[:, None]
    return codes, scale, np.linalg.norm(coded, axis=1), np.linalg.norm(unit - coded, axis=1)


def cosine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row-wise cosine in double precision. Rows are scaled by their largest component only where their squares would overflow or vanish."""
    with np.errstate(over="ignore", under="ignore"):
        xx, yy = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", y, y)
    odd = ~((xx > 1e-280) & (xx < 1e280) & (yy > 1e-280) & (yy < 1e280))
    if odd.any():
        x, y = (np.where(odd[:, None], z / np.abs(z).max(axis=1, keepdims=True), z) for z in (x, y))
    return np.einsum("ij,ij->i", x, y) / (np.sqrt(np.einsum("ij,ij->i", x, x)) * np.sqrt(np.einsum("ij,ij->i", y, y)))


Codes = tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]


def estimates(a: Codes, b: Codes) -> tuple[np.ndarray, np.ndarray]:
    """Estimated cosines of all rows of ``a`` with all of ``b``, and the bounds of their errors."""
    (qa, sa, na, ea), (qb, sb, nb, eb) = a, b
    dot, step = np.zeros((len(qa), len(qb))), 1024  # 1024 products of 127 * 127 at most: float32 holds each step's sum exactly
    for k in range(0, qa.shape[1], step):
        dot += qa[:, k : k + step].astype(np.float32) @ qb[:, k : k + step].astype(np.float32).T
    return dot * sa[:, None] * sb[None, :], na[:, None] * eb[None, :] + ea[:, None] * nb[None, :] + ea[:, None] * eb[None, :]


def sorted_out(a: Codes, b: Codes, threshold: float, same: bool) -> tuple[tuple[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]:
    """Pairs that surely link, and pairs in doubt; i < j if ``same``."""
    middle, error = estimates(a, b)
    sure = middle - error >= threshold + SLACK
    open_ = (middle + error >= threshold - SLACK) & ~sure
    if same:
        upper = np.triu(np.ones(sure.shape, bool), 1)
        sure, open_ = sure & upper, open_ & upper
    return np.nonzero(sure), np.nonzero(open_)


def unit_codes(x: np.ndarray) -> Codes:
    big = np.abs(x).max(axis=1, keepdims=True)  # lengths of very large or small components neither overflow nor vanish
    x = x / big
    return quantise(x / np.linalg.norm(x, axis=1, keepdims=True))


def tile_links(a: np.ndarray, b: np.ndarray, threshold: float, same: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """Rows (i of a, j of b) that link, i < j if ``same``; and how many pairs were recomputed."""
    ca = unit_codes(a)
    (i, j), (m, n) = sorted_out(ca, ca if same else unit_codes(b), threshold, same)
    near = recomputed(a, b, m, n, threshold)
    return np.concatenate([i, m[near]]), np.concatenate([j, n[near]]), len(m)


def recomputed(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray, threshold: float) -> np.ndarray:
    linked = np.zeros(len(i), bool)
    for k in range(0, len(i), 1 << 17):
        s = slice(k, k + (1 << 17))
        linked[s] = cosine(a[i[s]], b[j[s]]) >= threshold
    return linked


def usable(vector: str = "embedding"):
    """Not null, not empty, all components finite and not all zero."""
    v = F.col(vector)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return v.isNotNull() & F.coalesce(fine & F.exists(v, lambda x: x != 0), F.lit(False))


FOUND = "cell long, i long, j long, node long, second boolean, links long, root long, open boolean"


def coded(groups: DataFrame) -> DataFrame:
    """``(label, dim, node, copies, codes)``: a vector's scale and norms (three doubles) and its 8-bit codes as bytes."""

    def run(batches):
        for batch in batches:
            wide, out = batch.column(4), [b""] * batch.num_rows
            dims = batch.column(1).to_numpy(zero_copy_only=False)
            values, starts = wide.values.to_numpy(zero_copy_only=False), wide.offsets.to_numpy()
            for dim in np.unique(dims).tolist():
                rows = np.flatnonzero(dims == dim)
                x = values[starts[rows][:, None] + np.arange(dim)]
                codes, scale, coded_norm, error_norm = unit_codes(x)
                head = np.stack([scale, coded_norm, error_norm], axis=1)
                for r, h, c in zip(rows.tolist(), head, codes, strict=True):
                    out[r] = h.tobytes() + c.tobytes()
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(out, pa.binary())], names=["label", "dim", "node", "copies", "codes"])

    kind = groups.schema["label"].dataType.simpleString()
    return groups.select("label", "dim", "node", "copies", "v").mapInArrow(run, f"label {kind}, dim int, node long, copies long, codes binary")


def decoded(column: pa.Array) -> Codes:
    raw = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), -1)
    head = raw[:, :24].copy().view(np.float64)
    return raw[:, 24:].copy().view(np.int8), head[:, 0], head[:, 1], head[:, 2]


def _part(codes: Codes, rows: np.ndarray) -> Codes:
    return tuple(x[rows] for x in codes)


def sure_links(tile: pa.Table, threshold: float):
    """From codes alone: a function from two lists of rows to (links, doubtful pairs)."""
    codes = decoded(tile.column("codes").combine_chunks())

    def of(a, b, same):
        return sorted_out(_part(codes, a), _part(codes, b), threshold, same)

    return of


def doubtful_links(tile: pa.Table, threshold: float):
    """From codes and vectors: links among the pairs that the same codes left in doubt, none of which stays so."""
    codes = decoded(tile.column("codes").combine_chunks())
    x = tile.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(tile), -1)

    def of(a, b, same):
        _, (i, j) = sorted_out(_part(codes, a), _part(codes, b), threshold, same)
        near = recomputed(x, x, a[i], b[j], threshold)
        none = np.zeros(0, np.int64)
        return (i[near], j[near]), (none, none)

    return of


def scan(threshold: float, block: int, judge):
    """Rows sorted by tile (cell, i, j), with node, copies, second and what ``judge`` needs: per node its links, a root, and whether it is in doubt."""

    def whole_tiles(batches):
        tile, held = None, []
        for batch in batches:
            names = np.stack([batch.column(c).to_numpy() for c in range(3)], axis=1)
            cuts = np.flatnonzero(np.append(True, (names[1:] != names[:-1]).any(axis=1))) if len(names) else []
            for a, b in itertools.pairwise([*list(cuts), len(names)]):
                if tuple(names[a]) != tile and held:
                    yield tile, held
                    held = []
                tile = tuple(names[a])
                held.append(batch.slice(a, b - a))
        if held:
            yield tile, held

    def run(batches):
        for tile, held in whole_tiles(batches):
            part = pa.Table.from_batches(held).combine_chunks()
            node, copies = (part.column(c).to_numpy() for c in (3, 4))
            second = part.column(5).to_numpy().astype(bool)
            of, same = judge(part, threshold), tile[1] == tile[2]
            a, b = (np.arange(len(node)),) * 2 if same else (np.flatnonzero(~second), np.flatnonzero(second))
            links, open_, ends = np.zeros(len(node), np.int64), np.zeros(len(node), bool), []
            for k in range(0, len(a), block):
                for m in range(k if same else 0, len(b), block):
                    ra, rb = a[k : k + block], b[m : m + block]
                    (i, j), (p, q) = of(ra, rb, same and k == m)
                    np.add.at(links, ra[i], copies[rb[j]])
                    np.add.at(links, rb[j], copies[ra[i]])
                    open_[ra[p]] = open_[rb[q]] = True
                    if len(i):
                        ends.append(common.local_components(node[ra[i]], node[rb[j]]))
            some = np.flatnonzero((links > 0) | open_)
            nodes, roots = common.local_components(*map(np.concatenate, zip(*ends, strict=True))) if ends else (np.zeros(0, np.int64),) * 2
            n, none = len(some) + len(nodes), np.zeros(len(nodes), np.int64)
            columns = [*(np.full(n, x) for x in tile), np.concatenate([node[some], nodes]), np.concatenate([second[some], none.astype(bool)]), np.concatenate([links[some], none]), np.concatenate([node[some], roots]), np.concatenate([open_[some], none.astype(bool)])]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["cell", "i", "j", "node", "second", "links", "root", "open"])

    return run


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """``(vec_id, n_links, component_id, kept)``, one row per input row.

    Rows with a null label or an unusable vector link with nothing and stand for
    themselves. Vectors of different length never link. Repeated rows are
    separate vectors; of rows with one id each counts as another vector. Null
    ids never name a component unless alone.
    """
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"), F.col(label_col).alias("label"))
    rows = rows.withColumn("live", F.col("label").isNotNull() & usable("v"))
    # a vector's own name: components as exact doubles (negative zero made zero)
    clean = F.transform("v", lambda x: x + F.lit(0.0))
    keyed = rows.where("live").select("vec_id", "label", clean.alias("v")).withColumn("key", F.sha2(F.concat_ws(",", F.col("label").cast("string"), F.transform("v", lambda x: x.cast("string"))), 256))
    groups = keyed.groupBy("key").agg(F.first("label").alias("label"), F.first("v").alias("v"), F.min("vec_id").alias("low"), F.count("*").alias("copies"))
    groups = common.stored(groups.withColumn("node", F.monotonically_increasing_id()).withColumn("dim", F.size("v")), "vectors")
    sizes = groups.groupBy("label", "dim").agg(F.count("*").alias("n")).withColumn("blocks", F.ceil(F.col("n") / block).cast("long"))
    sizes = common.stored(sizes.select("label", "dim", "blocks", F.monotonically_increasing_id().alias("cell")), "cells")
    codes = common.stored(coded(groups), "codes")
    dealt = codes.join(sizes, ["label", "dim"]).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")))
    dealt = dealt.select("cell", "node", "copies", "codes", "block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    tiles = dealt.select("cell", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "node", "copies", (F.col("block") > F.col("other")).alias("second"), "codes")
    tiles = tiles.repartition("cell", "i", "j").sortWithinPartitions("cell", "i", "j")
    found = common.stored(tiles.mapInArrow(scan(threshold, block, sure_links), FOUND), "links")
    doubt = found.where("open").select("cell", "i", "j", "node", "second")
    again = doubt.join(groups.select("node", "v"), "node").join(codes.select("node", "copies", "codes"), "node").select("cell", "i", "j", "node", "copies", "second", "codes", "v")
    again = again.repartition("cell", "i", "j").sortWithinPartitions("cell", "i", "j")
    found = found.unionByName(common.stored(again.mapInArrow(scan(threshold, block, doubtful_links), FOUND), "doubtful"))
    counted = found.groupBy("node").agg(F.sum("links").alias("links"))
    roots = common.connected_components(found.where("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b"))).withColumnRenamed("id", "node")
    named = groups.select("key", "node", "low", "copies").join(counted, "node", "left").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    lows = named.groupBy("root").agg(F.min("low").alias("component_id"))
    named = named.join(lows, "root").select("key", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).cast("long").alias("n_links"), "component_id")
    live = keyed.select("vec_id", "key").join(named, "key").select("vec_id", "n_links", "component_id")
    rest = rows.where(~F.col("live")).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return live.unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


ORACLE_SQL = """
WITH RECURSIVE fine AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0
), pairs AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM fine a JOIN fine b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.v) = len(b.v)
  WHERE list_dot_product(a.v, b.v) / (sqrt(list_dot_product(a.v, a.v)) * sqrt(list_dot_product(b.v, b.v))) >= 0.98
), reach AS (
  SELECT vec_id AS a, vec_id AS b FROM embeddings
  UNION
  SELECT r.a, p.b FROM reach r JOIN pairs p ON p.a = r.b
), low AS (SELECT a, MIN(b) AS component_id FROM reach GROUP BY a),
n AS (SELECT a, COUNT(*) AS n FROM pairs GROUP BY a)
SELECT e.vec_id, CAST(COALESCE(n.n, 0) AS BIGINT) AS n_links, low.component_id, e.vec_id = low.component_id AS kept
FROM embeddings e JOIN low ON low.a = e.vec_id LEFT JOIN n ON n.a = e.vec_id
"""
