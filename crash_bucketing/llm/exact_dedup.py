"""Exact duplicates by composable polynomial fingerprints.

A text is a base-`BASE` number over its bytes, taken modulo four primes. Chunks of a text are hashed on their own
(one matrix product hashes thousands of chunks), and two neighbouring pieces combine by shifting the left value by
the length of the right: `combine`. So a document of any length is hashed in blocks of bounded memory, in any
order. Texts with equal fingerprint and length are then compared with one text of their group, segment by segment.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, ascii_lower, cut, id_text, join_counted, scope

#: The four largest primes below 2^31, a base below them all, bytes per chunk, chunks per block.
PRIMES = np.array([2147483647, 2147483629, 2147483587, 2147483579], dtype=np.int64)
BASE = 1_000_003
CHUNK = 1024
BLOCK = 2048


def power(exponent: int, primes: np.ndarray = PRIMES) -> np.ndarray:
    """BASE to an exponent, modulo each prime."""
    return np.array([pow(BASE, exponent, int(p)) for p in primes], dtype=np.int64)


def combine(left: np.ndarray, right: np.ndarray, right_bytes: int, primes: np.ndarray = PRIMES) -> np.ndarray:
    """Fingerprint of two joined pieces."""
    return (left * power(right_bytes, primes) + right) % primes


_WEIGHTS = np.array([[pow(BASE, CHUNK - 1 - i, int(p)) for p in PRIMES] for i in range(CHUNK)], dtype=np.float64)


def _shifts(n: int) -> np.ndarray:
    """Row k: BASE to k * CHUNK, modulo each prime."""
    out, step = np.ones((n, len(PRIMES)), dtype=np.int64), power(CHUNK)
    for k in range(1, n):
        out[k] = out[k - 1] * step % PRIMES
    return out


_SHIFTS = _shifts(BLOCK)


def fingerprints(texts: list[bytes]) -> np.ndarray:
    """(texts, primes) fingerprints. Leading zero bytes add nothing to the number, so chunks are filled in front."""
    out = np.zeros((len(texts), len(PRIMES)), dtype=np.int64)
    at = 0
    while at < len(texts):
        upto, chunks = at, 0
        while upto < len(texts) and (n := -(-len(texts[upto]) // CHUNK)) + chunks <= BLOCK:
            chunks += n
            upto += 1
        if upto == at:  # one text of more than a block: block by block, joined by length shifts
            value = np.zeros(len(PRIMES), dtype=np.int64)
            size = BLOCK * CHUNK
            for start in range(0, len(texts[at]), size):
                piece = texts[at][start : start + size]
                value = combine(value, fingerprints([piece])[0], len(piece))
            out[at] = value
            at += 1
            continue
        counts = np.array([-(-len(t) // CHUNK) for t in texts[at:upto]])
        if chunks:
            flat = b"".join(t.rjust(n * CHUNK, b"\0") for t, n in zip(texts[at:upto], counts, strict=True))
            values = (np.frombuffer(flat, dtype=np.uint8).reshape(chunks, CHUNK).astype(np.float64) @ _WEIGHTS).astype(np.int64) % PRIMES
            ends = np.cumsum(counts)
            back = np.repeat(ends, counts) - 1 - np.arange(chunks)
            values = values * _SHIFTS[back] % PRIMES
            some = counts > 0
            out[at:upto][some] = np.add.reduceat(values, (ends - counts)[some], axis=0) % PRIMES
        at = upto
    return out


def _hash_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [(t or b"").lower() for t in as_bytes(batch.column("text"))]
        marks = fingerprints(texts).astype(">u4")
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), pa.array([m.tobytes() + len(t).to_bytes(8, "big") for m, t in zip(marks, texts, strict=True)], pa.binary()), pa.array([len(t) for t in texts], pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in texts])],
            names=["doc_id", "mark", "n_bytes", "text_sha256"],
        )


def fingerprint_table(docs: DataFrame) -> DataFrame:
    """(doc_id, mark binary, n_bytes, text_sha256) for every row; null text counts as empty."""
    return id_text(docs).mapInArrow(_hash_batches, "doc_id long, mark binary, n_bytes long, text_sha256 string")


def _row(df: DataFrame) -> DataFrame:
    """With `row`: the id, a null one as -1. Together with the digest it names a text, so a clash with a real -1 does no harm."""
    return df.withColumn("row", F.coalesce("doc_id", F.lit(-1)))


def unequal_rows(docs: DataFrame, groups: DataFrame, marks: DataFrame, segment_chars: int, broadcast_rows: int, salted_rows: int = 1000) -> DataFrame:
    """Rows whose text differs from their group's representative although the marks agree: (row, text_sha256).

    Texts are compared segment by segment. The segments of a group's copies are dealt over one salt for each `salted_rows` copies, and those of its
    representative are repeated for each salt, so that no task gets a large group whole.
    """
    many = groups.where("n > 1").select("mark", "keep_id", "rep_sha", "n")
    salts = F.ceil(F.col("n") / salted_rows).cast("int")
    rows = _row(join_counted(marks, many.withColumn("size", F.col("n")), "mark", "size"))
    rows = rows.select("row", "text_sha256", "mark", salts.alias("salts"), ((F.col("doc_id").eqNullSafe(F.col("keep_id"))) & (F.col("text_sha256") == F.col("rep_sha"))).alias("rep")).distinct()
    rows = cut(rows, "copies")
    text = _row(id_text(docs)).select("row", F.coalesce("text", F.lit("")).alias("text"))
    ids = rows.select("row").distinct()
    # a list of at most broadcast_rows ids is a bounded broadcast; a longer one is joined by a shuffle
    text = text.join(F.broadcast(ids) if rows.count() <= broadcast_rows else ids, "row", "left_semi")
    text = text.select("row", ascii_lower(F.col("text")).alias("norm")).withColumn("text_sha256", F.sha2("norm", 256)).dropDuplicates(["row", "text_sha256"])
    parts = text.join(rows, ["row", "text_sha256"]).select(
        "mark", "row", "text_sha256", "rep", "salts",
        F.posexplode(F.transform(F.sequence(F.lit(0), F.floor((F.greatest(F.length("norm"), F.lit(1)) - 1) / segment_chars).cast("int")), lambda i: F.substring("norm", i * segment_chars + 1, segment_chars))).alias("pos", "part"),
    )
    own = parts.where("rep").select("mark", "pos", F.col("part").alias("rep_part"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    copies = parts.where("not rep").withColumn("salt", F.pmod(F.xxhash64("row"), F.col("salts")).cast("int"))
    # the mark holds the length, so a text that agrees in all its segments has no more and no fewer than the representative
    return copies.join(own, ["mark", "pos", "salt"], "left").groupBy("row", "text_sha256").agg(F.min(F.coalesce(F.col("part") == F.col("rep_part"), F.lit(False))).alias("equal")).where("not equal").select("row", "text_sha256")


def exact_duplicates(docs: DataFrame, segment_chars: int = 1 << 20, broadcast_rows: int = 500_000) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, n_bytes.

    Texts are equal when identical after lower-casing A-Z; null is empty. Of equal texts the largest doc_id stays
    (a null id is below all others). Rows repeated with the same id and text are one document twice: they share
    all values, `kept` included, and both count in group_size. An empty table gives an empty result; extra columns
    are ignored. Groups are aggregated before any join, so a text that a third of all rows carry costs one row
    per task; a mark shared by different texts (never seen with 124 bits) is told apart by the comparison, and its
    texts are grouped by digest instead.
    """
    with scope() as keep:
        marks = keep(cut(fingerprint_table(docs), "marks"))
        groups = marks.groupBy("mark").agg(F.count("*").alias("n"), F.max(F.struct("doc_id", "text_sha256")).alias("r")).select("mark", "n", F.col("r.doc_id").alias("keep_id"), F.col("r.text_sha256").alias("rep_sha"))
        groups = keep(cut(groups, "groups"))
        odd = keep(cut(unequal_rows(docs, groups, marks, segment_chars, broadcast_rows), "unequal"))
    if odd.isEmpty():
        out = join_counted(marks, groups.select("mark", "keep_id", F.col("n").alias("group_size"), "n"), "mark", "n")
    else:
        keyed = _row(marks).join(odd.withColumn("odd", F.lit(True)), ["row", "text_sha256"], "left").withColumn("key", F.when(F.col("odd"), F.col("text_sha256")).otherwise(F.lit("")))
        keyed = cut(keyed.withColumn("own", F.concat("mark", F.encode("key", "utf-8"))), "keyed")
        best = keyed.groupBy("own").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size")).withColumn("n", F.col("group_size"))
        out = join_counted(keyed, best, "own", "n")
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256", "n_bytes")
