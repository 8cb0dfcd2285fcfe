"""The registered k-means baselines search as far as the operator's own k_max."""

import numpy as np
import pytest

from crash_bucketing.plans import catalogue
from crash_bucketing.plans import workloads as wl


@pytest.fixture
def sf_dir(spark, tmp_path):
    rng = np.random.default_rng(5)
    vectors = np.repeat(np.eye(40), 3, axis=0) + 0.01 * rng.standard_normal((120, 40))
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(vectors)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    return str(tmp_path)


def grouped(buckets):
    assert sorted(r["n"] for r in buckets.groupBy("bucket").count().withColumnRenamed("count", "n").collect()) == [3] * 40


def test_b2_kmeans_finds_forty_clusters(spark, sf_dir):
    grouped(catalogue.queries()["b2_kmeans"](spark, sf_dir))


def test_w3_kmeans_finds_forty_clusters(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(wl, "planted_points", lambda *_: (wl.vectors_of(spark, sf_dir), None))
    monkeypatch.setattr(wl, "expand", lambda buckets, _: buckets)
    monkeypatch.setattr(wl, "planted_truth", lambda *_: None)
    monkeypatch.setattr(wl.ms, "score", lambda buckets, _: buckets)
    grouped(wl.planted_clusterer(spark, sf_dir, "kmeans"))
