"""Document quality by supervised subword embeddings.

A document is the mean of learned vectors of its words, of the character n-grams inside them (lengths 3 and 4, hashed)
and of hashed pairs of neighbouring words that are equal or not; a softmax layer follows. All vectors are trained by stochastic
gradient descent in numpy. The mean is linear, so for scoring each bucket is reduced to its two contributions beforehand,
and all n-gram hashes of a block of text come from one running sum over its bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, held_out, id_text

BUCKETS = 1 << 15
GRAMS = (3, 4)
#: Fixed odd multiplier of the running hash, and of the spread over buckets.
STEP, SPREAD = 0x5851F42D4C957F2D, 0x9E3779B97F4A7C15
BLOCK_BYTES = 1 << 18


def _odd_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """STEP^i and its inverse modulo 2^64, for i below n."""
    up, down = np.ones(n, dtype=np.uint64), np.ones(n, dtype=np.uint64)
    up[1:], down[1:] = np.uint64(STEP), np.uint64(pow(STEP, -1, 1 << 64))
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


class Features:
    """Buckets of all features of a block of texts, with the text that each belongs to."""

    def __init__(self, size: int = BLOCK_BYTES):
        self.up, self.down = _odd_powers(size + 1)

    def of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        flat = b"\n".join(texts) + b"\n"
        n = len(flat)
        if n + 1 > len(self.up):
            self.up, self.down = _odd_powers(n + 1)
        codes = np.frombuffer(flat, dtype=np.uint8)
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * self.up[:n], out=sums[1:])
        space = (codes == 32) | ((codes >= 9) & (codes <= 13))
        ends = np.flatnonzero(space & ~np.r_[True, space[:-1]])
        starts = np.flatnonzero(~space & np.r_[True, space[:-1]])
        bounds = np.cumsum([len(t) + 1 for t in texts])
        hash_of = lambda a, b, kind: (((sums[b] - sums[a]) * self.down[a] + np.uint64(kind)) * np.uint64(SPREAD)) >> np.uint64(64 - 15)
        words = ((sums[ends] - sums[starts]) * self.down[starts])
        buckets, places = [hash_of(starts, ends, 1)], [starts]
        last_space = np.maximum.accumulate(np.where(space, np.arange(n), -1))
        for k in GRAMS:
            b = np.flatnonzero(np.arange(n) - last_space >= k) + 1  # k letters of one word end here
            buckets.append(hash_of(b - k, b, k))
            places.append(b - k)
        if len(words) > 1:
            inside = np.searchsorted(bounds, starts[1:], side="right") == np.searchsorted(bounds, starts[:-1], side="right")
            buckets.append(np.where(words[1:] == words[:-1], np.uint64(0), np.uint64(1))[inside])
            places.append(starts[1:][inside])
        return np.concatenate(buckets).astype(np.int64), np.searchsorted(bounds, np.concatenate(places), side="right")


class SubwordClassifier:
    def __init__(self, dim: int = 8, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.vectors = rng.uniform(-1 / dim, 1 / dim, (BUCKETS, dim)).astype(np.float32)
        self.out = np.zeros((2, dim), dtype=np.float32)
        self.bias = np.zeros(2, dtype=np.float32)

    def fit(self, texts: list[bytes], labels: list[int], epochs: int = 6, batch: int = 16, rate: float = 4.0, seed: int = 9) -> None:
        rng = np.random.default_rng(seed)
        maker, docs = Features(), []
        for t in texts:
            buckets, _ = maker.of([t])
            ids, counts = np.unique(buckets, return_counts=True)
            docs.append((ids, (counts / max(1, counts.sum())).astype(np.float32)))
        y = np.array(labels)
        if not len(y):
            return
        share = np.clip(np.bincount(y, minlength=2) / len(y), 1e-3, 1)
        self.bias[:] = np.log(share)
        steps, step = epochs * -(-len(docs) // batch), 0
        for _ in range(epochs):
            order = rng.permutation(len(docs))
            for a in range(0, len(order), batch):
                some = [docs[i] for i in order[a : a + batch] if len(docs[i][0])]
                target = y[[i for i in order[a : a + batch] if len(docs[i][0])]]
                lr = rate * (1 - step / steps)
                step += 1
                if not some:
                    continue
                ids, weights = np.concatenate([s[0] for s in some]), np.concatenate([s[1] for s in some])
                starts = np.cumsum([0, *[len(s[0]) for s in some[:-1]]])
                hidden = np.add.reduceat(self.vectors[ids] * weights[:, None], starts, axis=0)
                scores = hidden @ self.out.T + self.bias
                p = np.exp(scores - scores.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                p[np.arange(len(target)), target] -= 1
                p /= len(target)
                back = np.repeat(p @ self.out, np.diff(np.r_[starts, len(ids)]), axis=0) * weights[:, None]
                self.out -= lr * 0.5 * (p.T @ hidden)
                self.bias -= lr * 0.02 * p.sum(axis=0)
                # every bucket's own number of occurrences scales its step, as in plain stochastic descent over tokens
                np.add.at(self.vectors, ids, -lr * 40 * back)

    def reduced(self) -> tuple[np.ndarray, float]:
        """For each bucket and for the bias: score of label 1 less score of label 0."""
        return (self.vectors @ (self.out[1] - self.out[0])).astype(np.float32), float(self.bias[1] - self.bias[0])


def scores(texts: list[bytes], table: np.ndarray, bias: float, maker: Features) -> np.ndarray:
    """Probability of label 1; a text without features has the prior's."""
    out, at = np.full(len(texts), 0.0), 0
    while at < len(texts):
        upto, size = at + 1, len(texts[at])
        while upto < len(texts) and size + len(texts[upto]) + 1 < BLOCK_BYTES - 1:
            size += len(texts[upto]) + 1
            upto += 1
        buckets, owner = maker.of(texts[at:upto])
        n = np.bincount(owner, minlength=upto - at)
        out[at:upto] = np.bincount(owner, weights=table[buckets], minlength=upto - at) / np.maximum(n, 1)
        at = upto
    return 1 / (1 + np.exp(-np.clip(out + bias, -60, 60)))


def fit_quality(docs: DataFrame, labels: DataFrame, max_rows: int = 1500, max_bytes: int = 1 << 26) -> tuple[np.ndarray, float]:
    """Fit on at most `max_rows` labelled rows that are not held out, half of each label where there are as many, and at most `max_bytes` of text.

    The least hashes of each label are taken. Of rows that repeat an id the least text counts. Texts go whole or not at all: first the
    lengths are read, and a text that does not fit into what is left of the bytes is passed over.
    """
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id"))).distinct().withColumn("h", F.xxhash64("doc_id"))
    # the least hashes of each label: a bounded list of ids, then their texts
    picked = [r for q in (0, 1) for r in marks.where(F.col("quality") == q).orderBy("h", "doc_id").limit(max_rows // 2).select("h", "doc_id", "quality").collect()]
    if not picked:
        return SubwordClassifier().reduced()

    def texts(some) -> DataFrame:  # of at most max_rows ids
        ids = docs.sparkSession.createDataFrame([(i,) for i in some], "doc_id long")
        return id_text(docs).where("text is not null").join(F.broadcast(ids), "doc_id").withColumn("digest", F.sha2("text", 256))

    sizes = {r["doc_id"]: (r["x"]["digest"], r["x"]["n"]) for r in texts({r["doc_id"] for r in picked}).groupBy("doc_id").agg(F.min(F.struct("digest", F.octet_length("text").alias("n"))).alias("x")).collect()}
    left, chosen = max_bytes, {}
    for r in sorted(picked, key=lambda r: (r["h"], r["doc_id"])):
        if r["doc_id"] in sizes and (r["doc_id"] in chosen or sizes[r["doc_id"]][1] <= left):
            left -= 0 if r["doc_id"] in chosen else sizes[r["doc_id"]][1]
            chosen[r["doc_id"]] = sizes[r["doc_id"]][0]
    if not chosen:
        return SubwordClassifier().reduced()
    rows = texts(chosen).dropDuplicates(["doc_id", "digest"]).where(F.concat_ws(":", "doc_id", "digest").isin([f"{i}:{d}" for i, d in chosen.items()]))
    known = {r["doc_id"]: r["text"].encode() for r in rows.select("doc_id", "text").collect()}
    sample = sorted((r["doc_id"], r["quality"]) for r in picked if r["doc_id"] in known)
    model = SubwordClassifier()
    model.fit([known[i] for i, _ in sample], [q for _, q in sample])
    return model.reduced()


def score_quality(docs: DataFrame, labels: DataFrame, max_rows: int = 1500, threshold: float = 0.3, model: tuple[np.ndarray, float] | None = None) -> DataFrame:
    """One row per document: doc_id, held_out, score (probability of label 1), predicted (1 if score >= threshold).

    Labels are learned from a bounded sample (`max_rows`) of rows that are not held out; a score reads the whole text and
    nothing else. Null, empty and blank texts get the prior's score. Repeated rows give repeated results; an empty table gives an empty result; without labels
    every score is one half.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model or fit_quality(docs, labels, max_rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, bias = shared.value
        maker = Features()
        for batch in batches:
            s = scores([t or b"" for t in as_bytes(batch.column("text"))], table, bias, maker)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32), pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    return id_text(docs, held_out(F.col("doc_id").cast("long"))).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame, max_rows: int = 1500, threshold: float = 0.3) -> DataFrame:
    """The rows of docs, all columns, whose score reaches the threshold; the score is computed beside the row, without a join."""
    shared = docs.sparkSession.sparkContext.broadcast(fit_quality(docs, labels, max_rows))

    @F.pandas_udf("boolean")
    def good(texts: pd.Series) -> pd.Series:
        # a few hundred texts at a time: the encoded copies of a whole batch are never held at once
        parts = [scores([t.encode() if t else b"" for t in texts.iloc[a : a + 256]], *shared.value, _maker()) for a in range(0, len(texts), 256)]
        return pd.Series(np.concatenate(parts) >= threshold if parts else np.zeros(0, dtype=bool))

    return docs.where(good(F.col("text").cast("string")))


_MAKERS: list[Features] = []


def _maker() -> Features:
    if not _MAKERS:
        _MAKERS.append(Features())
    return _MAKERS[0]
