"""Assignment of documents to shards by jump consistent hashing.

Law ``key``: the id and the number of shards decide, with no ring table. A shard
number is found by jumping ahead through ever larger shard counts with a linear
congruential generator seeded by the id; from n to n + 1 shards only the share
1 / (n + 1) of all rows moves, and only into the new shard.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from netprop.llm import common

#: Fixed values of the published generator.
MULTIPLIER = 2862933555777941757
SPAN = float(1 << 31)

#: Bytes that a row counts besides its text.
ROW_OVERHEAD = 8


def jump_hash(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each key (taken as unsigned 64-bit), vectorised: a few rounds, as many as the longest chain of jumps."""
    key = keys.astype(np.int64).view(np.uint64).copy()
    at = np.full(len(key), -1, np.int64)
    ahead = np.zeros(len(key), np.int64)
    live = np.arange(len(key))
    while len(live):
        at[live] = ahead[live]
        key[live] = key[live] * np.uint64(MULTIPLIER) + np.uint64(1)
        draw = (key[live] >> np.uint64(33)).astype(np.float64) + 1.0
        ahead[live] = ((at[live] + 1).astype(np.float64) * (SPAN / draw)).astype(np.int64)
        live = live[ahead[live] < shards]
    return at


def jump_column(key: Column, shards: int) -> Column:
    """The same as a column expression (Arrow batches of ids, nothing else, go to Python); a null key counts as 0."""

    @F.pandas_udf("int")
    def shard(ids):
        import pandas as pd

        return pd.Series(jump_hash(ids.to_numpy(np.int64), shards).astype(np.int32))

    return shard(F.coalesce(key.cast("long"), F.lit(0).cast("long")))


def assign(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, size, text_crc32, law, shard, slot, grown_shard)``, one row per input row.

    A null text has size 8 and the checksum of no bytes (0). Rows of one id share
    a shard; their slots follow size and checksum. Null ids count as id 0.
    """
    body = F.col(text_col).cast("binary")
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length(body), F.lit(0)).cast("long") + ROW_OVERHEAD).alias("size"),
        F.coalesce(F.crc32(body), F.lit(0).cast("long")).alias("text_crc32"),
    )
    placed = common.stored(with_shards(rows, shards), "shards")
    ranked = common.gapless_rank(placed, "shard", "doc_id", "slot", ("size", "text_crc32"))
    return ranked.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def with_shards(rows: DataFrame, shards: int) -> DataFrame:
    """Adds ``shard`` and ``grown_shard`` (with one more) to rows of (doc_id, size, text_crc32)."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0).fill_null(0).to_numpy(zero_copy_only=False)
            both = [pa.array(jump_hash(ids, n).astype(np.int32)) for n in (shards, shards + 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *both], names=[*batch.schema.names, "shard", "grown_shard"])

    return rows.mapInArrow(run, "doc_id long, size long, text_crc32 long, shard int, grown_shard int")


ORACLE_SQL = """
WITH RECURSIVE walk AS (
  SELECT doc_id, CAST(CASE WHEN doc_id < 0 THEN CAST(doc_id AS HUGEINT) + 18446744073709551616 ELSE doc_id END AS UHUGEINT) AS k, CAST(-1 AS BIGINT) AS b, CAST(0 AS BIGINT) AS j, n AS shards
  FROM (SELECT DISTINCT COALESCE(doc_id, 0) AS doc_id FROM documents) d, (VALUES (24), (25)) s(n)
  UNION ALL
  SELECT doc_id, nk, j, CAST(FLOOR(CAST(j + 1 AS DOUBLE) * (2147483648.0::DOUBLE / (CAST(nk // 8589934592 AS DOUBLE) + 1.0))) AS BIGINT), shards
  FROM (SELECT doc_id, (k * CAST(2862933555777941757 AS UHUGEINT) + 1) % CAST(18446744073709551616 AS UHUGEINT) AS nk, j, shards FROM walk WHERE j < shards) w
), placed AS (
  SELECT doc_id, shards, CAST(MAX(b) AS INTEGER) AS shard FROM walk GROUP BY doc_id, shards
), bits AS (
  SELECT doc_id, COALESCE(octet_length(encode(text)), 0) + 8 AS size, text FROM documents
)
SELECT b.doc_id, CAST(b.size AS BIGINT) AS size, 'key' AS law, p.shard, g.shard AS grown_shard,
       CAST(ROW_NUMBER() OVER (PARTITION BY p.shard ORDER BY b.doc_id) - 1 AS BIGINT) AS slot
FROM bits b JOIN placed p ON p.doc_id = COALESCE(b.doc_id, 0) AND p.shards = 24
JOIN placed g ON g.doc_id = COALESCE(b.doc_id, 0) AND g.shards = 25
"""
