"""Exact collapsing of crashes, neutral names and leaks."""

from __future__ import annotations

from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SOURCES = ["full", "coarse", "report"]
SOURCE_CONFIGS = {"all": ["full", "coarse", "report"], "no_full": ["coarse", "report"], "no_coarse": ["full", "report"], "no_report": ["full", "coarse"], "report_only": ["report_all"], "full": ["full"], "coarse": ["coarse"], "report": ["report"]}


def hashed(prepared: DataFrame, sources: list[str]) -> DataFrame:
    """crash_id, target and a digest per source; a missing text has none. Texts stop here: only digests are shuffled."""
    return prepared.select("crash_id", "target", *[F.sha2(s, 256).alias(f"h_{s}") for s in sources])


def collapse_exact(prepared: DataFrame, sources: list[str] = SOURCES) -> tuple[DataFrame, DataFrame]:
    """(points, members): crashes of a target equal in all sources are one point, named by the least crash id.

    points: target, point, h_<source>..., weight. members: target, point, crash_id. Missing equals missing.
    """
    keys = [f"h_{s}" for s in sources]
    rows = hashed(prepared, sources)
    points = rows.groupBy("target", *keys).agg(F.min("crash_id").alias("point"), F.count("*").alias("weight"))
    on = [F.col(f"r.{k}").eqNullSafe(F.col(f"p.{k}")) for k in ("target", *keys)]
    members = rows.alias("r").join(points.alias("p"), on).select("p.target", "point", "crash_id")
    return points, members


def label_leaks(prepared: DataFrame, labels: DataFrame, sources: list[str] = SOURCES, block_labels: int = 20_000, block_bytes: int = 1 << 24) -> DataFrame:
    """(crash_id, source, label) where a text contains a label.

    One pass over the texts finds all labels of a block at once (multi-pattern automaton in the Arrow batches). Blocks hold about `block_labels`
    labels and `block_bytes` bytes, so what is sent round is bounded however many there are. Empty labels are in no text.
    """
    spark, names = prepared.sparkSession, labels.select(F.col("label").cast("string").alias("label")).where("label <> ''").distinct()
    held = names.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("label")), F.lit(0)).alias("b")).first()
    blocks = max(1, -(-held["n"] // block_labels), -(-held["b"] // block_bytes))
    rows, schema = prepared.select("crash_id", *sources), f"crash_id {prepared.schema['crash_id'].dataType.simpleString()}, source string, label string"
    out = None
    for b in range(blocks):
        shared = spark.sparkContext.broadcast(sorted(r["label"] for r in names.where(F.pmod(F.xxhash64("label"), F.lit(blocks)) == b).collect()))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            auto = ahocorasick.Automaton()
            for label in shared.value:
                auto.add_word(label, label)
            if shared.value:
                auto.make_automaton()
            for batch in batches:
                ids, found = batch.column("crash_id").to_pylist(), []
                for s in sources if shared.value else ():
                    for i, text in zip(ids, batch.column(s).to_pylist(), strict=True):
                        found += [(i, s, label) for label in sorted({x for _, x in auto.iter(text)})] if text else []
                yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], batch.column("crash_id").type), *[pa.array([f[k] for f in found], pa.string()) for k in (1, 2)]], names=["crash_id", "source", "label"])

        some = rows.mapInArrow(run, schema)
        out = some if out is None else out.union(some)
    return out
