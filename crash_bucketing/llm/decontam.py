"""Benchmark decontamination by pigeonhole edit matching.

A test item of m characters may occur with up to k = floor(max_error_rate * m) edits. Cut into k + 1 pieces, at least one
piece must occur unchanged, so an Aho-Corasick automaton over all pieces finds every candidate place in one pass over
the whole text. Each candidate is verified by the bit-parallel edit distance of Myers over a window of the item's length
plus k on both sides, with the item free to start anywhere in it. Items and texts have a blank on both ends, so an item matches whole words:
one that begins or ends inside a word costs an edit for each such end.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

_GAPS = re.compile(r"[\W_]+")


def normalise(text: str | None) -> str:
    """Lower case, every run of other than letters and digits one space; a space at both ends, unless nothing is left."""
    words = _GAPS.sub(" ", (text or "").lower()).strip()
    return f" {words} " if words else ""


def pieces(item: str, errors: int) -> list[tuple[int, str]]:
    """errors + 1 pieces with their offsets, lengths at most one apart."""
    n = errors + 1
    edges = [len(item) * i // n for i in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(edges, edges[1:], strict=False)]


def masks(item: str) -> dict[str, int]:
    out: dict[str, int] = {}
    for i, ch in enumerate(item):
        out[ch] = out.get(ch, 0) | 1 << i
    return out


def best_match(item: str, peq: dict[str, int], text: str) -> tuple[int, int]:
    """(least edit distance of the item to any substring, end of the first such substring), bit-parallel."""
    m = len(item)
    full, top = (1 << m) - 1, 1 << (m - 1)
    pv, mv, score = full, 0, m
    best, end = m, 0
    for j, ch in enumerate(text, 1):
        eq = peq.get(ch, 0)
        xv = eq | mv
        xh = (((eq & pv) + pv) ^ pv) | eq
        ph = mv | (full & ~(xh | pv))
        mh = pv & xh
        if ph & top:
            score += 1
        elif mh & top:
            score -= 1
        ph = ph << 1 & full  # the item may start anywhere: no cost enters at the top row
        mh = mh << 1 & full
        pv = mh | (full & ~(xv | ph))
        mv = ph & xv
        if score < best:
            best, end = score, j
    return best, end


class Matcher:
    """Automaton over the pieces of a block of items."""

    def __init__(self, items: list[tuple[int, str]], max_error_rate: float):
        self.items = [(i, t, int((len(t) - 2) * max_error_rate), masks(t)) for i, t in items if t]
        self.auto = ahocorasick.Automaton()
        at: dict[str, list[tuple[int, int]]] = {}
        for n, (_, t, k, _) in enumerate(self.items):
            for offset, piece in pieces(t, k):
                at.setdefault(piece, []).append((n, offset))
        for piece, places in at.items():
            self.auto.add_word(piece, (len(piece), places))
        if at:
            self.auto.make_automaton()
        self.empty = not at

    def find(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item_id, edits, start estimate, end) of the best place of each item that occurs in a normalised text, blanks at both ends included."""
        if self.empty or not text:
            return []
        best: dict[int, tuple[int, int, int]] = {}
        tried: set[tuple[int, int]] = set()
        for end, (size, places) in self.auto.iter(text):
            for n, offset in places:
                _, t, k, peq = self.items[n]
                start = end + 1 - size - offset
                if n in best and best[n][0] == 0:
                    continue
                if start >= 0 and text.startswith(t, start):
                    best[n] = (0, start, start + len(t))
                    continue
                # places a few characters apart share one window, wide enough for all of them
                slot = start // (k + 1)
                if k and (n, slot) not in tried:
                    tried.add((n, slot))
                    low = max(0, slot * (k + 1) - k)
                    edits, stop = best_match(t, peq, text[low : (slot + 1) * (k + 1) + len(t) + k])
                    if edits <= k and edits < best.get(n, (k + 1,))[0]:
                        best[n] = (edits, max(0, low + stop - len(t)), low + stop)
        return [(self.items[n][0], *found) for n, found in sorted(best.items())]


_BUILT: dict[int, Matcher] = {}


def contamination(docs: DataFrame, benchmark: DataFrame, max_error_rate: float = 0.05, block_items: int = 20_000, block_bytes: int = 1 << 24) -> DataFrame:
    """(doc_id, text_hash, item_id, edits, start, end): each document and test item that it holds, with the best place.

    Both sides are compared after `normalise`, whole texts only; start and end count characters of the normalised text. The benchmark goes
    through in blocks of some `block_items` items and `block_bytes` bytes, each a bounded broadcast, so it may be of any size. An item matches whole words. Null or empty texts and items
    match nothing; an item shorter than 1 / max_error_rate must occur unchanged; repeated rows give repeated results;
    empty tables give an empty result. text_hash is xxhash64 of the text (null as empty) and tells rows with one id apart.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"))
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    held = items.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()
    blocks = max(1, -(-held["n"] // block_items), -(-held["b"] // block_bytes))
    schema = "doc_id long, text_hash long, item_id long, edits int, start long, end long"
    out = None
    for b in range(blocks):
        some = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b).collect()
        shared = spark.sparkContext.broadcast(sorted(((r["item_id"], normalise(r["text"])) for r in some), key=lambda x: (x[0] is None, x[0] or 0, x[1])))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            key = id(shared.value)
            if key not in _BUILT:
                _BUILT.clear()
                _BUILT[key] = Matcher(shared.value, max_error_rate)
            matcher = _BUILT[key]
            for batch in batches:
                got = [(d, h, *m) for d, t, h in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "text", "text_hash")), strict=True) if t for m in matcher.find(normalise(t))]
                yield pa.RecordBatch.from_pylist([dict(zip(("doc_id", "text_hash", "item_id", "edits", "start", "end"), g, strict=True)) for g in got], schema=pa.schema([("doc_id", pa.int64()), ("text_hash", pa.int64()), ("item_id", pa.int64()), ("edits", pa.int32()), ("start", pa.int64()), ("end", pa.int64())]))

        found = rows.mapInArrow(run, schema)
        found = cut(found, "contamination") if blocks > 1 else found
        out = found if out is None else out.union(found)
    return out
