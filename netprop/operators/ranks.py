"""Gapless numbers over sorted rows without a window that one task would have to fill."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F
from pyspark.sql.window import Window

from netprop import session


def numbered(df: DataFrame, keys: list[str], out: str, group: str | None = None) -> DataFrame:
    """Add ``out``: 0, 1, 2, ... by ``keys`` within each ``group`` (or over all rows).

    Rows are dealt to ranges of (group, keys) and numbered range by range; what earlier
    ranges hold of the group is added from a table of one row per range and group.
    """
    df = df if group else df.withColumn("_all", F.lit(0))
    by = group or "_all"
    place = F.monotonically_increasing_id()
    dealt = df.repartitionByRange(by, *keys).sortWithinPartitions(by, *keys)
    dealt = session.stored(dealt.withColumn("_part", F.shiftrightunsigned(place, 33)).withColumn("_at", place.bitwiseAND(F.lit((1 << 33) - 1))), "ranges")
    counts = dealt.groupBy(by, "_part").agg(F.count("*").alias("_n"), F.min("_at").alias("_first"))
    before = Window.partitionBy(by).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(by, "_part", (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_add"))
    return dealt.join(counts, [by, "_part"]).withColumn(out, (F.col("_at") + F.col("_add")).cast("long")).drop("_part", "_at", "_add", "_all")
