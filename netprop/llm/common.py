"""Helpers that the operators share: shared storage, components, gapless ranks.

Nothing here collects rows whose number grows with the input, and every cut of
lineage goes to the folder in ``spark.checkpoint.dir``, which all executors see.
"""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.window import Window


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one serves only where none is set and all run in one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isEmpty():
            if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="netprop-"))
            held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get()
    return found.rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: a durable cut of lineage.

    The caller's result reads it later, so it stays; who owns the folder clears it after the run.
    """
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def checkpointed(df: DataFrame) -> DataFrame:
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def is_empty(df: DataFrame) -> bool:
    return not df.take(1)


# --------------------------------------------------------------- components


def local_components(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges (a, b) and for each the smallest node reachable, in numpy."""
    nodes, inv = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = inv[: len(a)], inv[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        while not np.array_equal(new[new], new):
            new = new[new]
        if np.array_equal(new, label):
            return nodes, nodes[label]
        label = new


def local_forest(a: np.ndarray, b: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Places of the edges (a, b) that make a spanning forest of least weight ``w`` (small integers): each component takes its lightest way out, round by round."""
    nodes, inv = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = inv[: len(a)], inv[len(a) :]
    label, chosen = np.arange(len(nodes)), []
    rank = np.lexsort((np.maximum(a, b), np.minimum(a, b), w))  # ties alike in every task
    key = np.empty(len(a), np.int64)
    key[rank] = np.arange(len(a))
    while True:
        out = np.flatnonzero(label[x] != label[y])
        if not len(out):
            return np.unique(np.concatenate(chosen)) if chosen else np.zeros(0, np.int64)
        best = np.full(len(nodes), len(a), np.int64)
        np.minimum.at(best, label[x[out]], key[out])
        np.minimum.at(best, label[y[out]], key[out])
        taken = rank[np.unique(best[best < len(a)])]
        chosen.append(taken)
        held, root = local_components(label[x[taken]], label[y[taken]])
        new = np.arange(len(nodes))
        new[held] = root
        label = new[label]


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(a, b)`` links of LONG ids to ``(id, root)``, root being the smallest id reachable.

    Two alternating star contractions per round, each a partial aggregate and an
    equi-join (which adaptive execution splits where a hub is hot). A round keeps
    at most one edge per input edge, so nothing grows, and the loop ends when the
    edge set stands still, after a number of rounds logarithmic in the diameter.
    Self-loops are allowed: such a node is its own root unless linked further.
    """
    now = checkpointed(
        edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u is not null and v is not null").distinct()
    )
    loops = now.where("u = v").select(F.col("u").alias("id"), F.col("u").alias("root"))
    now, last = now.where("u <> v"), None
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        hung = large.join(low, "u")
        small = hung.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        now = checkpointed(small)
        mark = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
        if mark == last:
            break
        last = mark
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    stars = now.select(F.col("u").alias("id"), F.col("v").alias("root"))
    roots = now.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct()
    return stars.unionByName(roots).unionByName(loops).groupBy("id").agg(F.min("root").alias("root"))


# -------------------------------------------------------------------- ranks


def gapless_rank(df: DataFrame, group: str, order: str, out: str, ties: tuple[str, ...] = ()) -> DataFrame:
    """Add ``out``: 0, 1, 2, ... within each ``group``, by ``order`` (nulls first), then ``ties``. Rows equal in all of these come in any order.

    Rows are dealt to ranges of (group, order, ties, own number), so that no group, id
    or row that repeats fills a task, and are numbered range by range; what earlier ranges
    hold of a group (one row per range and group) is added. ``df`` is to be a stored table.
    """
    keys = [F.col(group), F.col(order).asc_nulls_first(), *[F.col(t).asc_nulls_first() for t in ties]]
    dealt = df.withColumn("_own", F.monotonically_increasing_id()).repartitionByRange(*keys, F.col("_own")).sortWithinPartitions(*keys, F.col("_own"))
    place = F.monotonically_increasing_id()
    dealt = stored(dealt.drop("_own").withColumn("_part", F.shiftrightunsigned(place, 33)).withColumn("_at", place.bitwiseAND(F.lit((1 << 33) - 1))), "ranges")
    counts = dealt.groupBy(group, "_part").agg(F.count("*").alias("_n"), F.min("_at").alias("_first"))
    before = Window.partitionBy(group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(group, "_part", (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_add"))
    return dealt.join(counts, [group, "_part"]).withColumn(out, (F.col("_at") + F.col("_add")).cast("long")).drop("_part", "_at", "_add")
