"""The stages one by one, each on its own input."""

from __future__ import annotations

import collections

import corpus_pipeline
from chronofold.llm import secrets


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language ID", "SimHash near-dedup", "secret scans", "mixing to target weights", "best-fit packing"]
    extra = spark.createDataFrame([(9001, "12345 !!", "en", "src0", 8), (9002, None, None, None, None)], docs.schema)
    spoken = stages["language ID"](spark, docs.unionByName(extra), data)
    assert spoken.columns == docs.columns and spoken.count() == docs.count()
    single = stages["SimHash near-dedup"](spark, spoken, data).cache()
    assert single.columns == docs.columns
    words = collections.Counter(tuple(r.text.lower().split()) for r in single.collect())
    assert max(words.values()) == 1 and {tuple(r.text.lower().split()) for r in docs.collect()} >= set(words)
    clean = stages["secret scans"](spark, single, data).cache()
    before, after = ({r.doc_id: r for r in x.collect()} for x in (single, clean))
    assert before.keys() == after.keys() and not any(secrets.pattern_spans(r.text) for r in after.values())
    assert all((after[d].text == r.text) == (not secrets.find_secrets(r.text)) and after[d].n_chars == len(after[d].text) for d, r in before.items())
    mixed = stages["mixing to target weights"](spark, clean, data)
    told = {r.doc_id: r.toxic for r in spark.read.parquet(f"{data}/labels.parquet").collect() if r.doc_id in after}
    toxic = {d for d, t in told.items() if t}
    kept = {r.doc_id for r in mixed.collect()}
    good = set(told) - toxic
    assert len(kept & good) >= 0.97 * len(good) and len(kept & toxic) < 0.3 * max(1, len(toxic))
    packed = stages["best-fit packing"](spark, mixed, data).collect()
    assert {r.doc_id for r in packed} == kept


def test_run_and_empty(spark, data):
    assert corpus_pipeline.run(spark, data).count() > 0
    docs = spark.read.parquet(f"{data}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, data)
    assert docs.count() == 0


def test_stages_keep_odd_columns_and_rows(spark, data):
    """Extra columns with names that stages use themselves, null and repeated ids, rows that are the same."""
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{data}/documents.parquet").limit(80)
    odd = docs.unionByName(docs.limit(3)).unionByName(docs.limit(2).withColumn("doc_id", F.lit(None).cast("long")))
    for name in ("score", "lang_pred", "_clean", "host", "rate", "root", "node"):
        odd = odd.withColumn(name, F.lit("x"))
    rows = odd.cache()
    for _, stage in corpus_pipeline.STAGES[:-1]:
        rows = stage(spark, rows, data).cache()
        assert rows.columns == odd.columns and rows.where("score = 'x' AND lang_pred = 'x' AND _clean = 'x'").count() == rows.count() > 0
    assert corpus_pipeline.STAGES[-1][1](spark, rows, data).count() >= rows.count()
