"""A corpus pipeline of five training-data operators.

Each stage takes (spark, docs, sf_dir) and returns a frame; :func:`run` writes it
as Parquet in the shared folder and reads it again as the next stage's ``docs``.
All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop.llm import common, packing, pii, quality, simhash, suffix


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 4: documents that the base rules or the trees reject go. The trees learn from the labelled rows of ``docs``."""
    return quality.keep_good(docs, quality.train(docs, common.table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 1: of each group of near-duplicates (similarity of 0.8 or more of five-word shingles) the document of the smallest id stays.

    Rows are told apart by id and text: rows that share an id, or have none, go only as near-duplicates.
    """
    return simhash.representatives(docs).select(*docs.columns)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 3: strings of 100 bytes or more lose all occurrences but the first; ``n_chars`` is counted anew."""
    out = suffix.remove_repeats(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_n_removed") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 2: personal data get surrogates; ``n_chars`` is counted anew."""
    out = pii.replace(docs, count_col="_n_entities")
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_n_entities") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def length_buckets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Operator 10: bucket, batch and place of every document."""
    return packing.pack(docs)


STAGES = [
    ("quality rules", quality_rules),
    ("simhash near-dedup", near_duplicates),
    ("suffix-array dedup", repeated_passages),
    ("pii", personal_data),
    ("packing", length_buckets),
]

#: Trained trees, fingerprints and a transform have no SQL twin: tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = common.stored(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
