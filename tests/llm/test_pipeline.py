"""The corpus pipeline against a brute-force version of its stages."""

import importlib.util

import pytest
from pyspark.sql import functions as F

from netprop.llm import common, quality

cp = pytest.importorskip("corpus_pipeline") if importlib.util.find_spec("corpus_pipeline") else None


def test_pipeline(spark, sf):
    from .test_operators import similar_classes, slow_repeats

    docs = common.table(spark, sf, "documents")
    out, seen = docs, []
    for name, stage in cp.STAGES:
        out = common.stored(stage(spark, out, sf), "stage")
        seen.append(out)
        assert name == cp.STAGES[-1][0] or out.columns == docs.columns
    good, single, cut, clean, packed = seen
    model = quality.train(docs, common.table(spark, sf, "labels"))
    assert {r.doc_id for r in good.collect()} == {r.doc_id for r in quality.score(docs, model).where("kept").collect()}
    texts = {r.doc_id: r.text for r in good.collect()}
    root = similar_classes(texts)
    kept = sorted(k for k in texts if root[k] == k)
    assert sorted(r.doc_id for r in single.collect()) == kept
    want = slow_repeats([(k, texts[k].encode()) for k in kept], 100)
    lengths = {r.doc_id: len(r.text.encode()) for r in cut.collect()}
    for k in kept:  # a character cut at its edge stays whole: up to 3 bytes at either end of a span
        assert 0 <= lengths[k] - (want[k][0] - want[k][1]) <= 6 * want[k][2]
    assert clean.where(F.col("n_chars") != F.length("text")).count() <= docs.where(F.col("n_chars") != F.length("text")).count()
    assert sorted(r.doc_id for r in packed.collect()) == kept


def test_run_is_registered(spark):
    import __spark_entry__ as e

    assert e.queries()["pipeline"] is cp.run
    assert {n.split("_")[0] for n in e.queries() if n.startswith("op")} == {f"op{k}" for k in range(1, 11)}


def test_odd_rows(spark, sf, tmp_path):
    """Null and repeated ids, empty and very long texts, an empty table: no document is lost but by a stage's rule."""
    prose = [r.text for r in common.table(spark, sf, "documents").where("length(text) > 900 and lang = 'en'").orderBy("doc_id").limit(6).collect()]
    schema = common.table(spark, sf, "documents").schema
    rows = [(None, prose[0], "en", "s", None), (None, prose[1], "en", "s", 1), (5, prose[2], "en", "s", 1), (5, prose[3], None, None, 1), (6, None, "en", "s", 0), (7, "", "en", "s", 0), (8, prose[0] * 400, "en", "s", 1)]
    docs = spark.createDataFrame(rows, schema)
    single = cp.near_duplicates(spark, docs, sf)
    texts = sorted(r.text or "" for r in single.collect())
    assert len(texts) in (5, 6) and set(prose[1:4]) < set(texts)  # the two without words are one; the text that repeats the first may link with it
    for part in (docs, docs.limit(0)):
        out = part
        for name, stage in cp.STAGES:
            out = common.stored(stage(spark, out, sf), "stage")
        assert out.count() <= 7
