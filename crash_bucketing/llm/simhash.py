"""SimHash fingerprints and all links within a Hamming radius, by meet-in-the-middle ball hashing.

Two fingerprints at distance r or less share a point at distance r/2 or less from both. So every fingerprint emits all
variants within r/2, variants are shuffled, and fingerprints that meet on a variant are verified. With 64 bits and r = 4
that is 2,081 variants a fingerprint. `parts` reduces it: of `parts` blocks of bits the one with most differences
holds at least r/parts of them, so some choice of the other blocks differs in at most r - ceil(r/parts) bits, and the ball
hashing is done on these (3 parts: 3 choices of 43 bits, radius 2, 132 variants). parts=1 is the plain form; it also takes
over for keys that many different fingerprints share, since a plain variant has at most 2,081 of them around it.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, components, cut, id_text, join_counted, parts_for, scope

SEED = 42
#: Above so many different fingerprints on one partial key, the whole-fingerprint variants take over.
CROWD = 4096


def simhash(shingles: list[bytes], seed: int = SEED) -> int:
    """Bit i is one if more than half the XXH64 values of the shingles, repeats included, have it."""
    if not shingles:
        return 0
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(s, seed) for s in shingles], dtype="<u8")
    ones = np.zeros(64, dtype=np.int64)
    for a in range(0, len(h), 1 << 16):
        ones += np.unpackbits(h[a : a + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def word_shingles(text: bytes, size: int) -> list[bytes]:
    """Runs of `size` words joined by a space; a shorter text is one run; no words give none."""
    words = text.lower().split()
    if len(words) <= size:
        return [b" ".join(words)] if words else []
    flat = b" ".join(words)
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    return [flat[a:b] for a, b in zip(starts[: len(words) - size + 1].tolist(), ends[size - 1 :].tolist(), strict=True)]


def _signed(values: np.ndarray) -> pa.Array:
    return pa.array(np.asarray(values, dtype=np.uint64).view(np.int64))


def fingerprint_rows(docs: DataFrame, shingle_words: int = 4, distinct: bool = False, seeds: tuple[int, ...] = (SEED,)) -> DataFrame:
    """(doc_id, fp0, fp1, ...): one signed 64-bit fingerprint for each seed. distinct: every shingle counts once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = np.zeros((len(seeds), batch.num_rows), dtype=np.uint64)
            for i, text in enumerate(as_bytes(batch.column("text"))):
                shingles = word_shingles(text or b"", shingle_words)
                if distinct:
                    shingles = list(set(shingles))
                for j, seed in enumerate(seeds):
                    got[j, i] = simhash(shingles, seed)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(_signed, got)], names=["doc_id", *[f"fp{j}" for j in range(len(seeds))]])

    return id_text(docs).mapInArrow(run, "doc_id long, " + ", ".join(f"fp{j} long" for j in range(len(seeds))))


def masks(parts: int, radius: int) -> list[tuple[int, int]]:
    """(bits kept, radius on them) for each choice of parts that is enough to catch all links within `radius`."""
    if parts == 1:
        return [((1 << 64) - 1, radius)]
    edges = [64 * i // parts for i in range(parts + 1)]
    block = [((1 << edges[i + 1]) - 1) ^ ((1 << edges[i]) - 1) for i in range(parts)]
    left = radius - -(-radius // parts)
    return [(((1 << 64) - 1) ^ b, left) for b in block]


def flips(mask: int, radius: int) -> np.ndarray:
    """All bit patterns inside the mask with at most radius/2 (rounded up) ones."""
    bits = [1 << i for i in range(64) if mask >> i & 1]
    return np.array([sum(c) for k in range(-(-radius // 2) + 1) for c in combinations(bits, k)], dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection on 64-bit words (fixed odd multipliers), so that keys of the different choices do not meet."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def variants(fps: DataFrame, radius: int, parts: int) -> DataFrame:
    """fps: (fp long, ...): adds nothing but (key long, fp long), a row for each variant."""
    plan = [(np.uint64(mask), flips(mask, left), np.uint64(i)) for i, (mask, left) in enumerate(masks(parts, radius))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = batch.column("fp").to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            step = max(1, (1 << 17) // max(len(f) for _, f, _ in plan))
            for a in range(0, len(fp), step):
                some = fp[a : a + step]
                for mask, flip, i in plan:
                    # a bijection of (kept bits) xor a constant far from the mask's complement names the choice
                    keys = _mix(((some & mask)[:, None] ^ flip[None, :]).ravel()) + i * np.uint64(0xD1B54A32D192ED03)
                    yield pa.RecordBatch.from_arrays([_signed(keys), _signed(np.repeat(some, len(flip)))], names=["key", "fp"])

    return fps.select("fp").mapInArrow(run, "key long, fp long")


def distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


def forest(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Verified links among different fingerprints that join all of them that are linked (no more than one fewer than they are)."""
    n = len(fps)
    if n == 2:
        return [(0, 1)] if distance(fps[0], fps[1]) <= radius else []
    left, links = np.arange(n), []
    while len(left):  # breadth first: each step compares the whole frontier with what has not been reached
        front, left = left[:1], left[1:]
        while len(front) and len(left):
            near = distance(fps[front][:, None], fps[left][None, :]) <= radius
            hit = near.any(axis=0)
            links += list(zip(front[near[:, hit].argmax(axis=0)].tolist(), left[hit].tolist(), strict=True))
            front, left = left[hit], left[~hit]
    return links


def _links(radius: int, crowd: int, every: int):
    """Streams rows sorted by key; gives (a, b, crowded): links, or (fp, fp, true) for members of a crowded key.

    Keys of at most `every` fingerprints give all their links, larger ones a forest that joins the same fingerprints.
    """

    def groups(keys: np.ndarray, fps: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, bool]]:
        first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        size = np.diff(np.r_[first, len(keys)])
        two = first[size == 2]
        a, b = fps[two], fps[two + 1]
        near = (distance(a, b) <= radius) & (a != b)
        yield a[near], b[near], False
        for f, n in zip(first[size > 2].tolist(), size[size > 2].tolist(), strict=True):
            some = np.unique(fps[f : f + n])
            if len(some) > crowd:
                yield some, some, True
            elif len(some) <= every:
                i, j = np.triu_indices(len(some), 1)
                near = distance(some[i], some[j]) <= radius
                yield some[i[near]], some[j[near]], False
            elif links := forest(some, radius):
                i = np.array(links)
                yield some[i[:, 0]], some[i[:, 1]], False

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(parts: list[tuple[np.ndarray, np.ndarray, bool]]) -> Iterator[pa.RecordBatch]:
            a, b = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
            if len(a):
                crowded = np.concatenate([np.full(len(p[0]), p[2]) for p in parts])
                yield pa.RecordBatch.from_arrays([_signed(a), _signed(b), pa.array(crowded, pa.bool_())], names=["a", "b", "crowded"])

        # the last key of a batch may go on in the next; `held` has its fingerprints, `over` says that they are already known to be a crowd
        key, held, over = None, np.empty(0, dtype=np.uint64), False
        for batch in batches:
            keys = batch.column("key").to_numpy(zero_copy_only=False)
            fps = batch.column("fp").to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            if not len(keys):
                continue
            first = int(np.searchsorted(keys, key, side="right")) if key is not None else 0
            last = int(np.searchsorted(keys, keys[-1], side="left"))
            if key is not None:
                held = np.unique(np.r_[held, fps[:first]])
                if over or len(held) > crowd:
                    yield from out([(held, held, True)])
                    held, over = held[:0], True
                if first == len(keys):
                    continue
                if len(held):
                    yield from out(list(groups(np.zeros(len(held), dtype=np.int64), held)))
            if last > first:
                yield from out(list(groups(keys[first:last], fps[first:last])))
            key, held, over = keys[-1], np.unique(fps[last:]), False
        if over:
            yield from out([(held, held, True)])
        elif len(held):
            yield from out(list(groups(np.zeros(len(held), dtype=np.int64), held)))

    return run


def links(fps: DataFrame, radius: int = 4, parts: int = 3, crowd: int = CROWD, every: int = 2) -> DataFrame:
    """(a, b) fingerprints: links within the radius that join all linked fingerprints. fps: distinct `fp long`.

    every: keys of at most so many fingerprints give all their links, for callers that verify each one further.
    """

    def meet(some: DataFrame, parts: int, crowd: int) -> DataFrame:
        rows = sum(len(flips(mask, left)) for mask, left in masks(parts, radius))
        n = parts_for(some.sparkSession, some.count() * rows * 16)
        return variants(some, radius, parts).repartition(n, "key").sortWithinPartitions("key").mapInArrow(_links(radius, crowd, every), "a long, b long, crowded boolean")

    found = cut(meet(fps, parts, crowd).distinct(), "links")
    again = found.where("crowded").select(F.col("a").alias("fp")).distinct()
    out = found.where("not crowded").select("a", "b")
    if parts > 1 and not again.isEmpty():
        # whole variants: at most 2,081 different fingerprints around one
        out = out.union(meet(cut(again, "crowd"), 1, 1 << 30).select("a", "b"))
    return out.distinct()


def near_duplicates(docs: DataFrame, shingle_words: int = 4, radius: int = 4, parts: int = 3, crowd: int = CROWD) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable).

    Words are split at space and \\x09-\\x0D after lower-casing A-Z; a text of fewer words than a shingle is one shingle;
    null, empty and blank texts have fingerprint zero and link like any other. Rows with equal fingerprint are collapsed first,
    so copies cost nothing in the search; repeated rows give repeated results. A null id is reachable but never smallest,
    unless all ids of a component are null. An empty table gives an empty result.
    """
    with scope() as keep:
        rows = keep(cut(fingerprint_rows(docs, shingle_words), "fingerprints"))
        nodes = cut(rows.groupBy(F.col("fp0").alias("fp")).agg(F.min("doc_id").alias("id"), F.count("*").alias("n")), "nodes")
        pairs = links(nodes.select("fp"), radius, parts, crowd)
        # nodes carry the fingerprint as their name; the smallest document follows by component
        comp = components(nodes.select(F.col("fp").alias("id")), pairs).select(F.col("id").alias("fp"), "component")
        named = cut(comp.join(nodes, "fp"), "named")
        least = cut(named.groupBy("component").agg(F.min("id").alias("component_id"), F.count("*").alias("size")), "least")
        named = keep(cut(join_counted(named, least, "component", "size").select(F.col("fp").alias("fp0"), "component_id", "n"), "named"))
    return join_counted(rows, named, "fp0", "n").select("doc_id", F.lpad(F.lower(F.hex("fp0")), 16, "0").alias("fingerprint"), "component_id")
