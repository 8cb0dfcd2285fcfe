"""One document of each group of near copies: ball hashing of fingerprints first, then an exact similarity join on word shingles.

Meet-in-the-middle ball hashing of SimHash fingerprints finds the closest copies; what it links is verified and tied. It cannot find all: at a
similarity of 0.8 two fingerprints differ in some ten bits. So an exact join goes over the rest. Two sets of similarity t or more share an element
among the first |x| - ceil(t |x|) + 1 of each, in any order that is the same for all sets (prefix filter). Every text is therefore listed under
these of its five-word shingles, and the texts of a list are candidates. The order puts shingles that are common in a sample last, so that a line
that many texts share heads few lists; the sample bears on the cost alone, never on the result. Candidates are verified by the exact similarity. In
each list some texts at a time, the pivots, are compared with all others that are not yet in their group; a list is left when all its texts
are in one group or every two of different groups have been compared. So the groups are those of all pairs, and a large family costs a few
comparisons a text. Lists of common shingles may hold a large share of all texts: they are never brought together, only their pivots are sent round.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, components, cut, drop, join_counted, parts_for, scope
from .simhash import SEED, fingerprint_rows, links, word_shingles

#: Texts of a list that are compared with the others in the first round; each later round takes so many times more.
PIVOTS = 8
#: Texts looked at for common shingles, and the most shingles kept of them (both only order the lists).
SAMPLE, COMMON = 10_000, 50_000
#: Up to so many rows of a narrow table are a bounded broadcast.
BROADCAST_ROWS = 500_000
SLACK = 1e-9


def shingle_similarity(a: bytes, b: bytes, size: int = 5) -> float:
    """Jaccard similarity of the sets of word shingles; two texts without words are equal."""
    x, y = set(word_shingles(a, size)), set(word_shingles(b, size))
    return len(x & y) / len(x | y) if x or y else 1.0


def _similar_pairs(similarity: float, size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, x = None, set()
        for batch in batches:
            keep = []
            for a, b in zip(as_bytes(batch.column("ta")), as_bytes(batch.column("tb")), strict=True):
                if a != last:  # rows of one text follow each other
                    last, x = a, set(word_shingles(a, size))
                y = set(word_shingles(b, size))
                both = len(x & y)
                keep.append(both >= similarity * (len(x) + len(y) - both) - SLACK)
            keep = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], names=["a", "b"])

    return run


def shingle_keys(text: bytes, size: int) -> np.ndarray:
    """The different XXH64 values of the word shingles, ascending."""
    digest, shingles = xxhash.xxh64_intdigest, word_shingles(text, size)
    return np.unique(np.fromiter((digest(s, SEED) for s in shingles), dtype=np.uint64, count=len(shingles)))


def prefix(keys: np.ndarray, similarity: float, common: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The keys, by (count where common, key), of which any set of this similarity has one in its own prefix."""
    if len(common) and len(keys):
        at = np.minimum(np.searchsorted(common, keys), len(common) - 1)
        keys = keys[np.argsort(np.where(common[at] == keys, counts[at], 0), kind="stable")]
    return keys[: max(0, len(keys) - int(np.ceil(similarity * len(keys) - SLACK)) + 1)]


def _among(keys: np.ndarray, common: np.ndarray) -> np.ndarray:
    """Which keys are common (sorted)."""
    return common[np.minimum(np.searchsorted(common, keys), len(common) - 1)] == keys if len(common) else np.zeros(len(keys), dtype=bool)


def _long(values: np.ndarray) -> pa.Array:
    return pa.array(values.astype(np.uint64).view(np.int64))


def _packed(rows: Iterator[tuple[np.ndarray, ...]], least: int = 1 << 16) -> Iterator[list[np.ndarray]]:
    """Columns of many small tables put together to tables of `least` rows or little more."""
    some, n = [], 0
    for row in rows:
        some.append(row)
        n += len(row[0])
        if n >= least:
            yield [np.concatenate(c) for c in zip(*some, strict=True)]
            some, n = [], 0
    if some:
        yield [np.concatenate(c) for c in zip(*some, strict=True)]


def common_shingles(classes: DataFrame, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(keys ascending, counts) of shingles that three or more sampled texts share."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for some in _packed((shingle_keys(text or b"", size),) for text in as_bytes(batch.column("text"))):
                yield pa.RecordBatch.from_arrays([_long(some[0])], names=["key"])

    step = max(1, classes.count() // SAMPLE)
    some = classes.where(F.pmod(F.xxhash64("id"), F.lit(step)) == 0).select("text").mapInArrow(run, "key long")
    got = some.groupBy("key").agg(F.count("*").alias("n")).where("n >= 3").orderBy(F.desc("n"), "key").limit(COMMON).toArrow()
    keys, counts = (got.column(c).to_numpy().astype(np.int64) for c in ("key", "n"))
    order = np.argsort(keys.view(np.uint64))
    return keys.view(np.uint64)[order], counts[order]


def _listed(similarity: float, size: int, common: np.ndarray, counts: np.ndarray):
    """(key, id, size, pos, comp, hot): a row for each key of a text's prefix; size of its set, place of the key in it, whether the key is common."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, ...]]:
            for i, comp, text in zip(batch.column("id").to_pylist(), batch.column("comp").to_pylist(), as_bytes(batch.column("text")), strict=True):
                keys = shingle_keys(text or b"", size)
                some = prefix(keys, similarity, common, counts)
                n = len(some)
                yield some, np.full(n, i, np.int64), np.full(n, len(keys), np.int32), np.arange(n, dtype=np.int32), np.full(n, comp, np.int64), _among(some, common)

        for batch in batches:
            for key, *more in _packed(rows(batch)):
                yield pa.RecordBatch.from_arrays([_long(key), *map(pa.array, more)], names=["key", "id", "size", "pos", "comp", "hot"])

    return run


#: Kinds of rows of a comparison: a pair to verify, a list row still to be compared, a row of a common list.
PAIR, REST, HOT = 0, 1, 2


def _compare(similarity: float, pivots: int):
    """Streams (key, id, size, pos, comp, hot) sorted by key and id. Gives (a, b, size, pos, comp, kind): pairs (a, b) of the first `pivots` texts of each key
    with those after them; as (key, id) the rows that are still to be compared with each other; rows of common lists as they are."""

    def rows(a: np.ndarray, b: np.ndarray, s: np.ndarray, p: np.ndarray, c: np.ndarray, kind: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(s.astype(np.int32)), pa.array(p.astype(np.int32)), pa.array(c), pa.array(np.full(len(a), kind, np.int32))], names=["a", "b", "size", "pos", "comp", "kind"])

    def groups(key: np.ndarray, id: np.ndarray, size: np.ndarray, pos: np.ndarray, comp: np.ndarray) -> Iterator[pa.RecordBatch]:
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        number = np.diff(np.r_[first, len(key)])
        # texts in different groups, or nothing is to be done
        open_ = np.repeat(np.minimum.reduceat(comp, first) != np.maximum.reduceat(comp, first), number)
        start, many = np.repeat(first, number), np.repeat(number, number)
        rank = np.arange(len(key)) - start
        later = np.flatnonzero(open_ & (rank > 0))
        for q in range(pivots):
            later = later[rank[later] > q]
            if not len(later):
                break
            at = start[later] + q
            x, y = size[at], size[later]
            # the first key that two sets share leaves at most the rest of the shorter tail to share
            ok = (comp[at] != comp[later]) & (np.minimum(x, y) >= similarity * np.maximum(x, y) - SLACK)
            ok &= np.minimum(x - pos[at], y - pos[later]) >= similarity / (1 + similarity) * (x + y) - SLACK
            if ok.any():
                yield rows(id[at[ok]], id[later[ok]], x[ok], pos[at[ok]], comp[at[ok]], PAIR)
        left = open_ & (rank >= pivots) & (many - pivots >= 2)
        if left.any():
            yield rows(key[left], id[left], size[left], pos[left], comp[left], REST)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, kept = ("key", "id", "size", "pos", "comp"), []
        for batch in batches:
            new = [batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in names]
            hot = batch.column("hot").to_numpy(zero_copy_only=False).astype(bool)
            if hot.any():
                yield rows(*[c[hot] for c in new], HOT)
                new = [c[~hot] for c in new]
            if not len(new[0]):
                continue
            if kept and kept[-1][0][-1] == new[0][-1]:  # one key goes on
                kept.append(new)
                continue
            # the last key may go on in the next batch
            end = int(np.searchsorted(new[0], new[0][-1], side="left"))
            whole = [np.concatenate(c) for c in zip(*kept, [c[:end] for c in new], strict=True)]
            kept = [[c[end:] for c in new]]
            if len(whole[0]):
                yield from groups(*whole)
        if kept:
            yield from groups(*[np.concatenate(c) for c in zip(*kept, strict=True)])

    return run


def _may_be_alike(similarity: float) -> str:
    """SQL for two list rows l and p: sizes and places of the shared key leave room for the similarity."""
    return f"l.comp <> p.comp and least(l.size, p.size) >= {similarity} * greatest(l.size, p.size) - {SLACK:.12f} and least(l.size - l.pos, p.size - p.pos) >= {similarity / (1 + similarity)} * (l.size + p.size) - {SLACK:.12f}"


def _compare_hot(lists: DataFrame, similarity: float, pivots: int) -> tuple[DataFrame, DataFrame]:
    """The same for lists of common shingles: (pairs, rows still to be compared). One text for each of `pivots` hash parts of a list is its pivot;
    these are sent to the list's rows wherever they are, so no task ever holds a list."""
    open_ = lists.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("key")
    part = F.pmod(F.xxhash64("id", F.lit(pivots)), F.lit(pivots))
    chosen = lists.groupBy("key", part.alias("part")).agg(F.min(F.struct("id", "size", "pos", "comp")).alias("x")).join(open_, "key", "left_semi")
    chosen = cut(chosen.select("key", "x.id", "x.size", "x.pos", "x.comp"), "pivots")
    few = F.broadcast if chosen.count() <= BROADCAST_ROWS else lambda df: df  # beyond, the skew join deals out long lists
    met = lists.alias("l").join(few(chosen).alias("p"), "key").where(_may_be_alike(similarity))
    keys = chosen.select("key").distinct()  # at most COMMON many
    rest = lists.join(F.broadcast(keys), "key", "left_semi").join(few(chosen.select("key", "id")), ["key", "id"], "left_anti")
    return met.select(F.least("l.id", "p.id").alias("a"), F.greatest("l.id", "p.id").alias("b")), rest


def verified(pairs: DataFrame, texts: DataFrame, similarity: float, size: int) -> DataFrame:
    """The pairs (a, b) whose texts are alike. texts: (id, text). Of few pairs only their own texts are shuffled."""
    if 2 * pairs.count() <= BROADCAST_ROWS:
        ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
        texts = texts.join(F.broadcast(ids), "id", "left_semi")
    both = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b").join(texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a")
    return cut(both.select("a", "b", "ta", "tb").mapInArrow(_similar_pairs(similarity, size), "a long, b long"), "pairs")


def close_pairs(classes: DataFrame, size: int) -> DataFrame:
    """(a, b), a < b: candidates by ball hashing: texts of one fingerprint with the least of them, and the least ones of linked fingerprints."""
    with scope() as keep:
        prints = cut(fingerprint_rows(classes.select(F.col("id").alias("doc_id"), "text"), size), "fingerprints")
        nodes = cut(prints.groupBy("fp0").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")), "nodes")
        same = join_counted(prints, nodes, "fp0", "n").select(F.col("least").alias("a"), F.col("doc_id").alias("b"))
        fp, least = nodes.select(F.col("fp0").alias("fp")), lambda x: nodes.select(F.col("fp0").alias(x), F.col("least").alias(f"least_{x}"))
        across = links(fp).join(least("a"), "a").join(least("b"), "b").select(F.least("least_a", "least_b").alias("a"), F.greatest("least_a", "least_b").alias("b"))
        return keep(cut(same.union(across).where("a < b").distinct(), "candidates"))


def grouped(ids: DataFrame, edges: DataFrame) -> DataFrame:
    """Components, written; nothing else is left of their search."""
    with scope() as keep:
        return keep(cut(components(ids, edges), "groups"))


def similar_groups(classes: DataFrame, similarity: float, size: int) -> DataFrame:
    """(id, component) of the graph of all pairs of texts of this similarity. classes: (id long, text), no id twice."""
    # the lists weigh about as much as the texts
    n = parts_for(classes.sparkSession, classes.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0])
    texts, ids = classes.select("id", "text"), classes.select("id")
    common, counts = common_shingles(classes, size)
    tried = close_pairs(classes, size)
    groups = grouped(ids, verified(tried, texts, similarity, size))
    tied = cut(groups.where("id <> component").withColumnRenamed("component", "comp"), "tied")
    # the rows of a list know their groups from the start
    known = texts.join(F.broadcast(tied) if tied.count() <= BROADCAST_ROWS else tied, "id", "left").select("id", "text", F.coalesce("comp", "id").alias("comp"))
    lists, pivots = known.mapInArrow(_listed(similarity, size, common, counts), "key long, id long, size int, pos int, comp long, hot boolean"), PIVOTS
    hot = None
    while True:
        # rows of common lists are dealt by id; only the first round has them here
        dealt = lists.repartition(n, "key", F.when(F.col("hot"), F.col("id"))).sortWithinPartitions("key", "id")
        got = cut(dealt.mapInArrow(_compare(similarity, pivots), "a long, b long, size int, pos int, comp long, kind int"), "lists")
        row = (F.col("a").alias("key"), F.col("b").alias("id"), "size", "pos")
        if hot is None:
            hot = got.where(F.col("kind") == HOT).select(*row, "comp")
        met, hot_rest = _compare_hot(hot, similarity, pivots)
        pairs = cut(got.where(F.col("kind") == PAIR).select("a", "b").union(met).distinct().join(tried, ["a", "b"], "left_anti"), "candidates")
        tried, true = tried.union(pairs), verified(pairs, texts, similarity, size)
        if not true.isEmpty():
            groups = grouped(ids, groups.where("id <> component").select(F.col("id").alias("a"), F.col("component").alias("b")).union(true))
        drop(true)
        rest = got.where(F.col("kind") == REST).select(*row, F.lit(False).alias("hot")).union(hot_rest.select("key", "id", "size", "pos", F.lit(True)))
        rest = cut(rest.join(groups.withColumnRenamed("component", "comp"), "id"), "rest")
        drop(got)
        if rest.isEmpty():
            return groups
        hot, lists = rest.where("hot").drop("hot"), rest.where("not hot")
        pivots *= PIVOTS


def keep_one_of_each(docs: DataFrame, similarity: float = 0.8, shingle_words: int = 5) -> DataFrame:
    """The rows of docs, all columns, without those that have a like document with a smaller id in their group.

    Groups: connected documents of similarity 0.8 or more. Texts that agree after lower-casing A-Z and splitting into words are
    collapsed first, by their SHA-256 digest. Null, empty and blank texts are copies of each other. A null id counts as the largest. Of rows with the same id and
    words the one with the least hash of its columns stays, of equal rows one. An empty table gives an empty result.
    """
    words = F.array_join(F.filter(F.split(F.translate(F.coalesce(F.col("text").cast("string"), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), r"[\x20\x09-\x0D]+"), lambda w: w != ""), " ")
    hashable = [f"`{f.name}`" for f in docs.schema if not any(t in f.dataType.simpleString() for t in ("map<", "variant"))]
    # the row stands apart in a struct, so no name of it can clash
    keyed = docs.select(F.struct("*").alias("row"), F.col("doc_id").isNull().alias("none"), F.coalesce(F.col("doc_id").cast("long"), F.lit(0)).alias("least"), F.xxhash64(*hashable).alias("tie"), words.alias("norm"))
    keyed = keyed.withColumn("digest", F.sha2("norm", 256))
    with scope() as keep:
        # one text for each class of equal word sequences; numbered as they are written, so no two classes share a number
        classes = keyed.groupBy("digest").agg(F.min("norm").alias("text"), F.min(F.struct("none", "least", "tie")).alias("first"))
        classes = cut(classes.select(F.monotonically_increasing_id().alias("id"), "digest", "text", "first"), "classes")
        groups = similar_groups(classes.select("id", "text"), similarity, shingle_words)
        best = groups.join(classes.select("id", "digest", "first"), "id").groupBy("component").agg(F.min(F.struct("first", "digest")).alias("k"))
        keepers = keep(cut(best.select("k.digest", "k.first.none", "k.first.least", "k.first.tie"), "keepers"))
    place = ["digest", "none", "least", "tie"]
    return keyed.drop("norm").join(keepers, place, "left_semi").dropDuplicates(place).select("row.*")
