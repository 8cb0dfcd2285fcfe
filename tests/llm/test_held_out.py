"""Held-out accuracy of the learned operators on the given tables."""

import numpy as np

from crash_bucketing.llm import queries

SF = "/root/testdata/sf0.01"


def test_languages_of_held_out_documents(spark):
    lang = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang").collect()}
    rows = [r for r in queries.op1_language_id(spark, SF).where("held_out and lang_pred <> 'und'").collect() if lang[r["doc_id"]]]
    assert len(rows) > 100 and np.mean([r["lang_pred"] == lang[r["doc_id"]] for r in rows]) >= 0.98


def test_quality_of_held_out_documents(spark):
    label = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    rows = [(r["score"], label[r["doc_id"]]) for r in queries.op10_quality(spark, SF).where("held_out").collect() if r["doc_id"] in label]
    good, bad = np.array([s for s, y in rows if y == 1]), np.array([s for s, y in rows if y == 0])
    assert len(good) > 20 and len(bad) > 5
    assert (good[:, None] > bad[None, :]).mean() >= 0.98
