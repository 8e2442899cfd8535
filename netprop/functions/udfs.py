"""Functions for SQL users: scalar, Arrow scalar, grouped aggregate, table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession, functions as F, types as T
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf(T.DoubleType())
def entropy(vectors: pd.Series) -> pd.Series:
    """Entropy of non-negative weights, taken as shares."""

    def one(v):
        x = np.asarray(v, float)
        x = x[x > 0] / x.sum() if x.sum() > 0 else x[:0]
        return float(-(x * np.log(x)).sum())

    return vectors.map(one, na_action="ignore")


@pandas_udf(T.DoubleType())
def weighted_mean(label: pd.Series, w: pd.Series) -> float:
    """A mean is no combiner: as a grouped aggregate it sees all rows of a key at once. Engines use the pair of sums instead."""
    return float((label * w).sum() / w.sum())


@udtf(returnType=T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())]))
class RelatedEdges:
    """A record's id and list of related ids, as edges."""

    def eval(self, id, related):
        for other in dict.fromkeys(related or []):
            yield id, other


def register(spark: SparkSession) -> None:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION coin(id BIGINT) RETURNS INT RETURN CAST((id * 2654435761) % 4294967296 < 2147483648 AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION decide_binary(p DOUBLE) RETURNS INT RETURN CAST(p >= 0.5 AS INT)")
    spark.udf.register("entropy", entropy)
    spark.udtf.register("related_edges", RelatedEdges)


def sql_surface(spark: SparkSession, graph, labels=None) -> None:
    """Temporary views ``edges``, ``vertices`` (and ``labels``) of a graph."""
    graph.edges.createOrReplaceTempView("edges")
    graph.vertices.createOrReplaceTempView("vertices")
    if labels is not None:
        labels.createOrReplaceTempView("labels")


def share_of(column, total):
    return F.col(column) / F.nullif(F.col(total), F.lit(0))
