"""Declared schemas, never inferred, and a check that a frame has one."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F, types as T


def _schema(ddl: str, required: str = "") -> T.StructType:
    need, kinds = set(required.split()), {"long": T.LongType(), "int": T.IntegerType(), "double": T.DoubleType(), "string": T.StringType(), "timestamp": T.TimestampType()}
    return T.StructType([T.StructField(n, kinds[k], n not in need) for n, k in (f.split() for f in ddl.split(", "))])


EDGES = _schema("src long, dst long, w double", "src dst w")
VERTICES = _schema("id long", "id")
LABELS = _schema("id long, p double", "id")
CLASS_LABELS = _schema("id long, class int, p double", "id class p")
CLASSES = _schema("class int, name string", "class name")
CALLS = _schema("ts timestamp, src long, dst long, tariff string, dur long", "ts src dst tariff dur")
HOPS = _schema("id long, hops int", "id")
TRACE = _schema("run_id string, problem string, engine string, graph string, cores int, partitions int, round int, ms long, active long, messages long, improved long, shuffle_rows long, shuffle_bytes long, stored_rows long, stored_bytes long", "run_id round")


def conform(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` with the columns of ``schema`` in their order and types; a missing column is an error."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    return df.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in schema])
