"""Helpers shared by the corpus operators: table access, shared scratch tables, byte columns, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, by Spark's own reader (the path may be in any store)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder of `spark.checkpoint.dir`; a temporary one only where the session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        named = tempfile.mkdtemp(prefix="scratch-")
        spark.sparkContext.setCheckpointDir(named)
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


#: Tables written within each open `scope`, innermost last.
_SCOPES: list[list[DataFrame]] = []


#: With it Spark removes the shuffle files of a query at its end; else they lie there until the driver happens to collect garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_removed(spark: SparkSession) -> Iterator[None]:
    """For queries that run once: their shuffle files go with them."""
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before)


def cut(df: DataFrame, name: str = "step") -> DataFrame:
    """Write a frame once to the shared folder and read it back: lineage ends and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with shuffles_removed(spark):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    if _SCOPES:
        _SCOPES[-1].append(out)
    return out


def drop(df: DataFrame) -> None:
    """Remove a table written by `cut` that nothing reads any more."""
    path = getattr(df, "_scratch_path", None)
    if path:
        jvm = df.sparkSession._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(p, True)


@contextmanager
def scope() -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Tables that `cut` writes inside are removed at the end, but for those given to the function that it yields."""
    written: list[DataFrame] = []
    kept: set[str] = set()

    def keep(df: DataFrame) -> DataFrame:
        kept.add(df._scratch_path)
        return df

    _SCOPES.append(written)
    try:
        yield keep
    finally:
        _SCOPES.remove(written)
        for df in written:
            if df._scratch_path not in kept:
                drop(df)
            elif _SCOPES:
                _SCOPES[-1].append(df)


def join_counted(rows: DataFrame, keyed: DataFrame, key: str, count: str, share: int = 1000) -> DataFrame:
    """Inner join of rows with a table of one row per key that tells in `count` how many rows have it; the count goes.

    Keys that more than one row in `share` has are at most `share` many: they are a bounded broadcast, and their rows are not shuffled. All
    others are joined by a shuffle in which no key weighs more than that. `rows` is read twice, so it should be a written table. No null keys.
    """
    total = keyed.agg(F.sum(count)).first()[0] or 0
    hot = keyed.where(F.col(count) * share > total)
    if hot.isEmpty():
        return rows.join(keyed.drop(count), key)
    out = rows.join(F.broadcast(hot.drop(count)), key)
    cold = rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(keyed.where(F.col(count) * share <= total).drop(count), key)
    return out.unionByName(cold)


def parts_for(spark: SparkSession, n_bytes: int, most: int = 1 << 25) -> int:
    """Partitions for a shuffle of so many bytes: the session's number, more where each would get more than `most` bytes."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-n_bytes // most))


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(text, UPPER, UPPER.lower())


def held_out(doc_id: Column) -> Column:
    """True for one row in five: crc32 of the id as text, remainder 0 by five."""
    return (F.crc32(doc_id.cast("string")) % 5 == 0).alias("held_out")


def as_bytes(column: pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of a string column of an Arrow batch."""
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def id_text(docs: DataFrame, *more: str) -> DataFrame:
    """Only the columns an operator needs, so that clashing extra columns never reach it."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *more)


def _stars(e: DataFrame) -> bool:
    """Whether every upper end of the edges (u, v) has one edge and is no lower end."""
    ends = e.select("u", F.lit(1).alias("up")).union(e.select("v", F.lit(1 << 32).alias("up")))
    return ends.groupBy("u").agg(F.sum("up").alias("n")).where(f"n > 1 and n % {1 << 32} > 0").isEmpty()


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Connected components by alternating large-star and small-star contraction.

    nodes: (id long); edges: (a long, b long). Returns (id, component) with the smallest id of the component.
    Each round is two joins with an aggregate of minima; hot centres are split by the skew join. It is over when every edge leads from a node
    with no other edge straight to a least one. The driver sees one row per round, never edges or components.
    """
    e = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    while not _stars(e):
        # large star: every neighbour above u is tied to the least of u and its neighbours
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = cut(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct(), "edges")
        # small star: every neighbour below u, and u itself, is tied to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e"))
        new = cut(small.select("e.u", "e.v").where("u <> v").distinct(), "edges")
        drop(large)
        drop(e)
        e = new
    return nodes.join(e.select(F.col("u").alias("id"), F.col("v").alias("component")), "id", "left").select("id", F.coalesce("component", "id").alias("component"))
