"""Queries ``opN_<name>`` of the training-data operators, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from netprop.llm import common, embed, html, packing, pieces, pii, quality, sharding, simhash, suffix, warc


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(common.table(spark, sf_dir, "documents"))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace(common.table(spark, sf_dir, "documents")).select("doc_id", "text", "n_entities")


def op3_suffix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.count_repeats(common.table(spark, sf_dir, "documents"))


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (common.table(spark, sf_dir, t) for t in ("documents", "labels"))
    return quality.score(docs, quality.train(docs, labels))


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(common.table(spark, sf_dir, "documents"), 24)


def op6_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode(common.table(spark, sf_dir, "documents"))


def op7_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.main_text(common.table(spark, sf_dir, "pages"))


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(common.table(spark, sf_dir, "pages")).drop("url")


def op9_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed.near_duplicates(common.table(spark, sf_dir, "embeddings"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(common.table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_simhash": op1_simhash,
    "op2_pii": op2_pii,
    "op3_suffix": op3_suffix,
    "op4_quality": op4_quality,
    "op5_sharding": op5_sharding,
    "op6_pieces": op6_pieces,
    "op7_html": op7_html,
    "op8_warc": op8_warc,
    "op9_embeddings": op9_embeddings,
    "op10_packing": op10_packing,
}

ORACLE_SQL: dict[str, str] = {
    "op9_embeddings": embed.ORACLE_SQL,
}
