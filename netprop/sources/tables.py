"""Readers and writers: given tables, edge lists, adjacency records, bucketed tables, per-round storage."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop import schemas, session
from netprop.operators.graphs import Graph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", header: bool = False, weighted: bool = False) -> tuple[Graph, DataFrame]:
    """A text file of id pairs (with a weight, or weight 1) as a graph; and the lines that are none."""
    ddl = "src long, dst long" + (", w double" if weighted else "") + ", bad string"
    rows = spark.read.csv(path, sep=sep, header=header, schema=ddl, mode="PERMISSIVE", columnNameOfCorruptRecord="bad")
    rows = session.stored(rows, "edge-list")
    bad = rows.where("bad is not null or src is null or dst is null").select("bad")
    good = rows.where("bad is null and src is not null and dst is not null")
    return Graph.of(good.select("src", "dst", F.col("w") if weighted else F.lit(1.0).alias("w")), name="edge_list"), bad


def read_adjacency(spark: SparkSession, path: str, ddl: str = "id long, related array<long>") -> Graph:
    """JSON records of a vertex and the ids it points to; each edge weighs its share of them."""
    rows = spark.read.schema(ddl).json(path).where("id is not null")
    edges = rows.select(F.col("id").alias("src"), F.explode("related").alias("dst"), (F.lit(1.0) / F.size("related")).alias("w"))
    return Graph.of(edges, vertices=rows.select("id"), name="adjacency")


def write_graph(graph: Graph, path: str, fmt: str = "parquet", partition_by: list[str] | None = None) -> None:
    writer = graph.edges.write.format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def bucketed_name(prefix: str) -> str:
    return f"netprop_{prefix}_{uuid.uuid4().hex[:10]}"


def save_bucketed(df: DataFrame, name: str, partitions: int, key: str) -> DataFrame:
    """A catalogue table split by the hash of ``key`` into as many buckets as loops have partitions."""
    path = f"{session.shared_dir(df.sparkSession)}/{name}"
    df.write.bucketBy(partitions, key).sortBy(key).mode("overwrite").format("parquet").option("path", path).saveAsTable(name)
    return df.sparkSession.table(name)


def drop(spark: SparkSession, names: list[str]) -> None:
    """Tables of :func:`save_bucketed` with their files, which lie in the shared folder."""
    for name in names:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        session.remove(spark, f"{session.shared_dir(spark)}/{name}")


class RoundStore:
    """State of each round as files, of which the last two are kept."""

    def __init__(self, spark: SparkSession, name: str = "rounds", keep: int = 2):
        self.spark, self.root, self.keep, self.schema = spark, session.fresh_path(spark, name), keep, None

    def put(self, number: int, df: DataFrame) -> DataFrame:
        df.write.mode("overwrite").parquet(f"{self.root}/{number}")
        self.schema = df.schema
        if number >= self.keep:
            session.remove(self.spark, f"{self.root}/{number - self.keep}")
        return self.get(number)

    def get(self, number: int) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(f"{self.root}/{number}")


def scan_report(df: DataFrame) -> list[dict[str, str]]:
    """What each file scan of the plan reads and which filters reach it."""
    import re

    text = df._jdf.queryExecution().executedPlan().toString()
    found = []
    for line in text.split("\n"):
        if "FileScan" in line:
            found.append({k: (m[1] if (m := re.search(rf"{k}: (\S*?)(?:, [A-Z]|$)", line)) else "") for k in ("PushedFilters", "ReadSchema", "PartitionFilters")})
    return found


def stream_calls(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schemas.CALLS).option("maxFilesPerTrigger", files_per_batch).parquet(path)
