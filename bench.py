"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parent))
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session() -> SparkSession:
    os.environ["PYTHONPATH"] = os.pathsep.join([str(Path(__file__).resolve().parent), os.environ.get("PYTHONPATH", "")])
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.driver.memory", "16g")
        .config("spark.sql.shuffle.partitions", "16")
        .config("spark.sql.files.maxPartitionBytes", "4m")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.host", "127.0.0.1")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    from crash_bucketing.operators import embed as em
    from crash_bucketing.operators import hierarchy as hi
    from crash_bucketing.operators import measures as ms
    from crash_bucketing.operators.collapse import SOURCES, collapse_exact
    from crash_bucketing.plans import registry
    from crash_bucketing.plans import workloads as wl
    from crash_bucketing.plans.bucketer import bucket, expand
    from crash_bucketing.sources import corpus

    spark = session()
    spark.range(1000).repartition(int(CPUS)).mapInPandas(lambda it: it, "id long").count()  # workers are up
    log = ms.CostLog()

    def timed(name, run):
        with log.stage(name):
            return run()

    crashes = timed("render_crashes", lambda: wl.stored(corpus.planted(spark, SF_DIR).repartition(int(CPUS) * 4), "crashes"))
    n = crashes.count()
    prepared = timed("prepare", lambda: wl.stored(log.observe(corpus.prepared(crashes), "crashes"), "prepared"))
    points, members = collapse_exact(prepared, SOURCES)
    points, members = timed("collapse", lambda: (wl.stored(log.observe(points, "distinct_points"), "points"), wl.stored(members, "members")))
    store = f"{wl.scratch(spark)}-store"
    texts = timed("distinct_texts", lambda: wl.stored(log.observe(em.texts_by_hash(prepared, SOURCES), "texts_embedded"), "texts"))
    vectors = timed("embed", lambda: wl.stored(em.embed_with_store(texts, em.MODELS["hosted_3072"], store), "vectors"))
    timed("embed_again", lambda: log.add("texts_embedded_again", em.missing_texts(texts, spark.read.parquet(f"{store}/model=hosted_3072")).count()))
    built = timed("combine", lambda: wl.stored(em.build_points(points, vectors, SOURCES), "built"))
    buckets = timed("bucket", lambda: wl.stored(expand(bucket(built), members), "buckets"))
    scores = timed("score", lambda: ms.score(buckets, crashes.select("target", "crash_id", "label")).collect())
    for s in ("local", "tiles"):
        timed(f"tree_{s}", lambda s=s: hi.spanning_tree(wl.vectors_of(spark, SF_DIR), s).agg(F.sum("dist")).first())
    for q in ("b5_buckets", "b4_stack_hash"):
        timed(q, lambda q=q: registry.QUERIES[q](spark, SF_DIR).count())
    seconds = {k: round(v, 2) for k, v in log.seconds.items()}
    workflow = sum(seconds[k] for k in ("prepare", "collapse", "distinct_texts", "embed", "combine", "bucket", "score"))
    print(json.dumps({"metric": "planted_workflow_seconds", "value": round(workflow, 2), "unit": "sec", "queries": seconds, "sf": SF_DIR, **log.counters(), "crashes_per_second": round(n / workflow, 1), "f_measure": [round(r["f_measure"], 4) for r in scores]}))


if __name__ == "__main__":
    main()
