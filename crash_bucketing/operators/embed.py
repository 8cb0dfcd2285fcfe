"""Text to vectors: pluggable models behind a content-addressed store."""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import groupby
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as vec

#: Fixed value: how much of a vector is kept.
KEPT = 64


class Embedder(Protocol):
    name: str
    dim: int

    def embed(self, texts: DataFrame, keep: int) -> DataFrame:
        """(hash, text) to (hash, vec), cut to the first `keep` coordinates."""


@lru_cache(maxsize=200_000)
def _bits(token: str, n_bytes: int, seed: int) -> bytes:
    """Random bits of a token, 64 bytes to a block, from a hash of token, block and seed; the first ones do not depend on how many there are."""
    blocks = range(-(-n_bytes // 64))
    return b"".join(hashlib.blake2b(token.encode(), digest_size=64, salt=b"%d-%d" % (seed, b)).digest() for b in blocks)[:n_bytes]


class HashProjectionEmbedder:
    """Signed random projection of token frequencies (words and character n-grams).

    Coordinates are exchangeable, so a prefix is a random projection of its own and cutting is safe.
    """

    def __init__(self, dim: int = 3072, grams: tuple[int, ...] = (3,), seed: int = 0, name: str | None = None):
        self.dim, self.grams, self.seed = dim, grams, seed
        self.name = name or f"projection-{dim}-{seed}"

    def tokens(self, text: str) -> Counter:
        # the running number of a frame says nothing: a deeper recursion shifts all numbers below it
        words = re.findall(r"[A-Za-z_][A-Za-z0-9_]*|[0-9a-fx]+", re.sub(r"#\d+", "#", text))
        out = Counter(words)
        for g in self.grams:
            for w, n in Counter(words).items():
                for i in range(len(w) - g + 1):
                    out[w[i : i + g]] += 0.2 * n
        return out

    def vector(self, text: str, keep: int) -> np.ndarray:
        keep, tokens = min(keep, self.dim), self.tokens(text)
        if not tokens:
            return np.zeros(keep)
        n_bytes = -(-keep // 8)
        bits = np.frombuffer(b"".join(_bits(t, n_bytes, self.seed) for t in tokens), dtype=np.uint8).reshape(-1, n_bytes)
        signs = np.unpackbits(bits, axis=1)[:, :keep] * 2.0 - 1
        return np.sqrt(np.fromiter(tokens.values(), dtype=np.float64, count=len(tokens))) @ signs

    def embed(self, texts: DataFrame, keep: int = KEPT) -> DataFrame:
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                yield pd.DataFrame({"hash": pdf["hash"], "vec": [self.vector(t, keep).tolist() for t in pdf["text"]]})

        return texts.select("hash", "text").mapInPandas(run, "hash string, vec array<double>")


class StoredEmbedder:
    """Ready model output in a table (hash, vec)."""

    def __init__(self, store: DataFrame, name: str = "stored", dim: int = KEPT):
        self.store, self.name, self.dim = store, name, dim

    def embed(self, texts: DataFrame, keep: int = KEPT) -> DataFrame:
        return texts.select("hash").join(self.store, "hash").select("hash", vec.truncate(F.col("vec"), keep).alias("vec"))


class BatchProviderEmbedder:
    """A remote service with asynchronous batches: `submit` takes the name and the (hash, text) rows of a batch, `poll` gives the frame of results."""

    def __init__(self, submit: Callable[[str, list[tuple[str, str]]], None], poll: Callable[[], DataFrame], name: str = "remote", dim: int = 3072, max_rows: int = 2048, max_bytes: int = 1 << 22):
        self.submit, self.poll, self.name, self.dim, self.max_rows, self.max_bytes = submit, poll, name, dim, max_rows, max_bytes

    def embed(self, texts: DataFrame, keep: int = KEPT) -> DataFrame:
        submit = self.submit

        def send(rows) -> None:
            # rows of a lane come in order, so one batch is held at a time
            for (lane, number), some in groupby(rows, key=lambda r: (r["lane"], r["batch"])):
                submit(f"{lane}-{number}", [(r["hash"], r["text"]) for r in some])

        batch_requests(texts, self.max_rows, self.max_bytes).repartition("lane").sortWithinPartitions("lane", "batch").foreachPartition(send)
        return self.poll().select("hash", vec.truncate(F.col("vec"), keep).alias("vec"))


#: Stand-ins of different width.
MODELS: dict[str, HashProjectionEmbedder] = {"hosted_3072": HashProjectionEmbedder(3072, (3,), 0, "hosted_3072"), "large_local": HashProjectionEmbedder(4096, (3, 4), 1, "large_local"), "small_local": HashProjectionEmbedder(256, (), 2, "small_local")}


def batch_requests(texts: DataFrame, max_rows: int = 2048, max_bytes: int = 1 << 22, lanes: int = 64) -> DataFrame:
    """hash, text, n_bytes, lane, batch: requests numbered so that no batch of a lane exceeds rows or bytes (a single larger text is one batch's excess)."""
    sized = texts.withColumn("n_bytes", F.octet_length("text").cast("long")).withColumn("lane", F.pmod(F.conv(F.substring(F.md5("hash"), 1, 8), 16, 10).cast("long"), F.lit(lanes)))
    w = Window.partitionBy("lane").orderBy("hash")
    before = F.sum("n_bytes").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("n_bytes")
    return sized.withColumn("batch", F.greatest(F.floor(before / max_bytes), F.floor((F.row_number().over(w) - 1) / max_rows)))


def texts_by_hash(prepared: DataFrame, sources: list[str]) -> DataFrame:
    """Distinct (hash, text) over all sources: what has to be embedded at all. prepared: one row per crash_id.

    Only digests are aggregated; the text of each is then taken from one crash that has it.
    """
    each = F.array(*[F.struct(F.sha2(s, 256).alias("hash"), F.lit(s).alias("source")) for s in sources])
    long = prepared.select("crash_id", F.explode(each).alias("x")).where("x.hash is not null")
    chosen = long.groupBy("x.hash").agg(F.min(F.struct("crash_id", "x.source")).alias("at")).select("hash", "at.crash_id", "at.source")
    text = F.coalesce(*[F.when(F.col("source") == s, F.col(s)) for s in sources])
    return prepared.select("crash_id", *sources).join(chosen, "crash_id").select("hash", text.alias("text"))


def missing_texts(texts: DataFrame, store: DataFrame) -> DataFrame:
    return texts.join(store.select("hash"), "hash", "left_anti")


def embed_with_store(texts: DataFrame, embedder: Embedder, path: str, keep: int = KEPT) -> DataFrame:
    """Embed what the store lacks, append it, and give the vectors of all texts.

    The store is Parquet under path/model=<name>; appends only, read by distinct hash, so a repeated append does no harm.
    """
    spark, place, schema = texts.sparkSession, f"{path}/model={embedder.name}", "hash string, vec array<double>"
    folder = spark._jvm.org.apache.hadoop.fs.Path(place)
    there = folder.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).exists(folder)
    store = spark.read.schema(schema).parquet(place) if there else spark.createDataFrame([], schema)
    embedder.embed(missing_texts(texts, store), keep).write.mode("append").parquet(place)
    done = spark.read.schema(schema).parquet(place).dropDuplicates(["hash"])
    return texts.select("hash").join(done, "hash")


def build_points(points: DataFrame, vectors: DataFrame, sources: list[str], how: str = "sum") -> DataFrame:
    """(target, point, weight, vec, h_<source>...): the combined unit vector of each point; one join per source on its digest."""
    out = points
    for s in sources:
        out = out.join(vectors.select(F.col("hash").alias(f"h_{s}"), F.col("vec").alias(f"v_{s}")), f"h_{s}", "left")
    cols = [F.col(f"v_{s}") for s in sources]
    combined = vec.combine_sum(cols) if how == "sum" else vec.combine_concat(cols, KEPT)
    return out.select("target", "point", "weight", combined.alias("vec"), *[f"h_{s}" for s in sources])


def variance_rotation(vectors: DataFrame) -> DataFrame:
    """(id, vec) turned so that coordinates come in order of decreasing variance; the d x d second moments are the only thing the driver sees."""
    basis = second_moments(vectors)
    values, axes = np.linalg.eigh(basis)
    axes = axes[:, np.argsort(-values)]
    axes = axes * np.sign(axes[np.abs(axes).argmax(axis=0), np.arange(axes.shape[1])])
    turned = F.array(*[vec.dot(vec.as_double(F.col("vec")), F.array(*[F.lit(float(v)) for v in axes[:, j]])) for j in range(axes.shape[1])])
    return vectors.select("id", turned.alias("vec"))


def second_moments(vectors: DataFrame) -> np.ndarray:
    """Sum of outer products: one small matrix per task, then their sum."""
    d = vectors.select(F.size("vec").alias("d")).first()["d"]

    def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros((d, d))
        for pdf in batches:
            x = np.array(pdf["vec"].tolist(), dtype=np.float64).reshape(-1, d)
            total += x.T @ x
        i, j = np.indices((d, d)).reshape(2, -1)
        yield pd.DataFrame({"i": i, "j": j, "x": total.ravel()})

    rows = vectors.select("vec").mapInPandas(part, "i int, j int, x double").groupBy("i", "j").agg(F.sum("x").alias("x")).collect()
    out = np.zeros((d, d))
    for r in rows:
        out[r["i"], r["j"]] = r["x"]
    return out


def project_2d(vectors: DataFrame) -> DataFrame:
    """(id, x, y): uncentred truncated singular vectors, signs by the largest component."""
    values, axes = np.linalg.eigh(second_moments(vectors))
    axes = axes[:, np.argsort(-values)[:2]]
    axes = axes * np.sign(axes[np.abs(axes).argmax(axis=0), [0, 1]])
    v = vec.as_double(F.col("vec"))
    return vectors.select("id", *[vec.dot(v, F.array(*[F.lit(float(a)) for a in axes[:, j]])).alias("xy"[j]) for j in (0, 1)])
