"""Typed access to the given tables, and the files of a crash corpus."""

from __future__ import annotations

import re
from collections.abc import Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
from pyarrow import fs as stores
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey long, r_name string",
    "nation": "n_nationkey long, n_name string, n_regionkey long",
    "customer": "c_custkey long, c_name string, c_nationkey long, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey long, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "benchmark": "item_id long, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; the scan reads only the columns that the plan above it uses."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, *names: str) -> SparkSession:
    """Temporary views of the tables, for SQL text."""
    for name in names or SCHEMAS:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark


def read_trace_files(spark: SparkSession, folder: str, crash: str = r"([^/]+)\.txt$", target: str = r"([^/]+)/[^/]+$", written: bool = False) -> DataFrame:
    """crash_id, target, trace from text files, one a crash, by default laid out as folder/target/crash.txt.

    crash, target: patterns whose first group is the name in a file's path. One line end at the end of a file is not part of the trace. Spark lists the files on the
    driver, some kB for each. written: the folder is one of write_trace_files, whose parts the tasks list and read themselves.
    """
    if written:
        raw = spark.range(0, PARTS, 1, PARTS).mapInArrow(_reader(folder), "crash_id string, target string, value binary").withColumn("value", F.col("value").cast("string"))
        return raw.select("crash_id", "target", F.regexp_replace("value", r"\n\z", "").alias("trace"))
    path = F.col("_metadata.file_path")
    raw = spark.read.option("recursiveFileLookup", "true").text(folder, wholetext=True)
    return raw.select(F.regexp_extract(path, crash, 1).alias("crash_id"), F.regexp_extract(path, target, 1).alias("target"), F.regexp_replace("value", r"\n\z", "").alias("trace"))


#: What read_trace_files is told of a folder that write_trace_files left.
WRITTEN = {"written": True}
#: Folders of each target, by checksum of the crash's name; one task reads one of them of all targets.
PARTS = 128
#: Bytes of traces handed on at once.
HANDED = 1 << 24


def _store(folder: str) -> tuple[stores.FileSystem, str]:
    return stores.FileSystem.from_uri(re.sub(r"^file:/+", "file:///", folder))


def _reader(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _store(folder)
        names, held, size = ("crash_id", "target", "value"), [], 0

        def handed() -> pa.RecordBatch:
            kinds = (pa.string(), pa.string(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array([h[k] for h in held], kind) for k, kind in enumerate(kinds)], names=names)

        for part in (p for batch in batches for p in batch.column(0).to_pylist()):
            for place in store.get_file_info(stores.FileSelector(root, allow_not_found=True)):
                for file in store.get_file_info(stores.FileSelector(f"{place.path}/part={part}", allow_not_found=True)):
                    with store.open_input_stream(file.path) as f:
                        held.append((unquote(file.base_name[len("crash=") : -len(".txt")]), unquote(place.base_name[len("target=") :]), f.read()))
                    size += len(held[-1][2])
                    if size >= HANDED or len(held) >= 10_000:
                        yield handed()
                        held, size = [], 0
        yield handed()

    return run


def _writer(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _store(folder)
        place, last, out, n = None, None, None, 0
        for batch in batches:
            for target, part, crash, value in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (target, part) != place:
                    place, here = (target, part), f"{root}/target={quote(target, safe='')}/part={part}"
                    store.create_dir(here, recursive=True)
                if (target, crash) != last:
                    if out:
                        out.close()
                    last, out, n = (target, crash), store.open_output_stream(f"{here}/crash={quote(crash, safe='')}.txt"), n + 1
                out.write((value or b"") + b"\n")
        if out:
            out.close()
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return run


def write_trace_files(crashes: DataFrame, folder: str) -> int:
    """One text file per crash, in folders for each target; gives their number. crashes: target, crash_id, trace.

    Tasks write the files themselves, so that no file is renamed by a commit and none needs a folder of its own. A task that runs again writes the same files. Rows of
    one crash go into one file, a line end after each.
    """
    unnamed = "__HIVE_DEFAULT_PARTITION__"
    rows = crashes.select(F.coalesce(F.col("target").cast("string"), F.lit(unnamed)).alias("target"), F.coalesce(F.col("crash_id").cast("string"), F.lit(unnamed)).alias("crash"), F.col("trace").cast("binary").alias("value"))
    rows = rows.select("target", F.pmod(F.crc32("crash"), F.lit(PARTS)).alias("part"), "crash", "value").repartition("target", "part").sortWithinPartitions("target", "part", "crash")
    return rows.mapInArrow(_writer(folder), "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]


def write_points(points: DataFrame, path: str) -> None:
    """Points by target, so that a later run reads only the targets it needs."""
    points.repartition("target").write.mode("overwrite").partitionBy("target").parquet(path)
