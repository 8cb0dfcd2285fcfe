"""Mixing sources to target weights by Sainte-Lague apportionment of equal-token blocks.

Tokens are words. The target of a source is its share of all tokens by weight, at most `repeats` times its own size;
what is above is shared again by weight. The targets are turned into whole numbers of equal-token blocks by the highest
quotients (votes over 1, 3, 5, ...), first among sources, then among the shards of each source. In each shard the
documents stand in a seeded order on one token line, and the quota is a run of blocks from a seeded block on,
going round up to `repeats` times: so at most two documents of a shard are taken in part.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

WEIGHTS = (5, 2, 1)
WORD = r"[^\x20\x09-\x0D]+"


def targets(sizes: list[int], weights: list[float], repeats: int = 3) -> list[float]:
    """Words for each source: shares by weight of the sum of sizes, capped, the excess shared again until none is above."""
    out, left, open_ = [0.0] * len(sizes), float(sum(sizes)), set(range(len(sizes)))
    while open_:
        share = left / sum(weights[i] for i in open_)
        above = {i for i in open_ if share * weights[i] > repeats * sizes[i]}
        for i in above or open_:
            out[i] = float(repeats * sizes[i]) if above else share * weights[i]
        if not above:
            break
        left -= sum(out[i] for i in above)
        open_ -= above
    return out


def highest_quotients(votes: np.ndarray, seats: int, caps: np.ndarray) -> np.ndarray:
    """Sainte-Lague with a cap for each party: the `seats` highest of votes / (2 s + 1), ties to the earlier party.

    The least winning quotient is found by bisection; what equal quotients leave open is dealt one by one.
    """
    votes, caps = np.asarray(votes, dtype=np.float64), np.asarray(caps, dtype=np.int64)
    caps = np.where(votes > 0, caps, 0)
    seats = int(min(seats, caps.sum()))
    got = lambda q: np.minimum(np.floor((votes / q + 1) / 2).astype(np.int64), caps)  # noqa: E731  quotients of at least q
    if not seats:
        return np.zeros(len(votes), dtype=np.int64)
    low, high = votes[votes > 0].min() / (2.0 * caps.max() + 2), votes.max() * 2
    for _ in range(200):
        mid = (low + high) / 2
        if mid in (low, high):
            break
        low, high = (mid, high) if got(mid).sum() >= seats else (low, mid)
    out = got(high)
    while (short := seats - int(out.sum())) > 0:
        quotient = np.where(out < caps, votes / (2 * out + 1), -1)
        for i in np.argsort(-quotient, kind="stable")[: max(1, min(short, int((quotient >= quotient.max() * (1 - 1e-12)).sum())))]:
            out[i] += 1
    return out


def mix(docs: DataFrame, weights: tuple = WEIGHTS, repeats: int = 3, block_tokens: int = 16, shards: int = 16, seed: int = 42, max_sources: int = 1_000_000) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken.

    Sources by code point, null last, weigh 5, 2, 1, repeating. Null text has no words. taken lies between 0 and
    `repeats` times size. Repeated rows are documents of their own; ties in the seeded order are broken by id and size,
    and rows equal in both are interchangeable. An empty table gives an empty result. One row per source comes to the driver,
    at most `max_sources` of them (checked).
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))
    rows = rows.withColumn("order", F.xxhash64(F.lit(seed), "doc_id", "size"))
    rows = cut(rows.withColumn("shard", F.pmod("order", F.lit(shards)).cast("int")), "sizes")
    cells = cut(rows.groupBy("source", "shard").agg(F.sum("size").alias("cell")), "cells")
    found = cells.groupBy("source").agg(F.sum("cell").alias("n")).orderBy(F.col("source").asc_nulls_last()).limit(max_sources + 1).collect()
    if len(found) > max_sources:
        raise ValueError(f"more than {max_sources} sources")
    sizes, names = [int(r["n"]) for r in found], [r["source"] for r in found]
    names_order = sorted(range(len(names)), key=lambda i: (names[i] is None, names[i] or ""))
    sizes, names = [sizes[i] for i in names_order], [names[i] for i in names_order]
    goal = targets(sizes, [weights[i % len(weights)] for i in range(len(names))], repeats)
    caps = np.array([-(-repeats * s // block_tokens) for s in sizes], dtype=np.int64)
    quota = highest_quotients(np.array(goal), round(sum(goal) / block_tokens), caps) if names else []
    plan = docs.sparkSession.createDataFrame([(s, n, g, int(q)) for s, n, g, q in zip(names, sizes, goal, quota, strict=True)], "source string, source_size long, target double, blocks long")

    def deal(cell: pd.DataFrame) -> pd.DataFrame:
        cell = cell.sort_values("shard")
        most = -(-repeats * cell["cell"].to_numpy() // block_tokens)
        cell["quota"] = highest_quotients(cell["cell"].to_numpy(), int(cell["blocks"].iloc[0]), most)
        return cell

    same = F.col("p.source").eqNullSafe(F.col("c.source"))
    cells = cells.alias("c").join(plan.alias("p"), same).select("c.source", "shard", "cell", "source_size", "target", "blocks")
    dealt = cells.groupBy("source").applyInPandas(deal, cells.schema.simpleString()[7:-1].replace(":", " ") + ", quota long")  # at most `shards` rows a source
    dealt = dealt.withColumn("tokens", F.least(F.col("quota") * block_tokens, F.col("cell") * repeats)).withColumn("start", F.when(F.col("cell") > 0, F.pmod(F.xxhash64(F.lit(seed), "source", "shard"), F.greatest(F.ceil(F.col("cell") / block_tokens), F.lit(1))) * block_tokens).otherwise(0))
    # places on the token line of each cell, from sums of 64 sub-blocks and a window inside each
    rows = rows.withColumn("sub", F.pmod(F.shiftrightunsigned("order", 20), F.lit(64)).cast("int"))
    subs = rows.groupBy("source", "shard", "sub").agg(F.sum("size").alias("n")).selectExpr("source", "shard", "sub", "sum(n) over (partition by source, shard order by sub) - n as before")
    dealt = cut(subs.alias("s").join(dealt.alias("d"), F.col("s.source").eqNullSafe(F.col("d.source")) & (F.col("s.shard") == F.col("d.shard"))).select("s.source", "s.shard", "s.sub", "before", "cell", "source_size", "target", "tokens", "start"), "quotas")
    rows = rows.selectExpr("doc_id", "source", "shard", "sub", "size", "sum(size) over (partition by source, shard, sub order by `order`, doc_id, size rows unbounded preceding) - size as inside")
    out = rows.alias("r").join(dealt.alias("q"), F.col("r.source").eqNullSafe(F.col("q.source")) & (F.col("r.shard") == F.col("q.shard")) & (F.col("r.sub") == F.col("q.sub")))
    at = F.col("before") + F.col("inside")
    whole = F.floor(F.col("tokens") / F.greatest("cell", F.lit(1)))
    rest = F.col("tokens") - whole * F.col("cell")
    # the run [start, start + rest) on a ring of `cell` tokens meets the document's [at, at + size) at most twice
    met = lambda shift: F.greatest(F.lit(0), F.least(at + F.col("size"), F.col("start") + rest - shift) - F.greatest(at, F.col("start") - shift))
    taken = whole * F.col("size") + met(F.lit(0)) + met(F.col("cell"))
    return out.select("doc_id", "r.source", "size", "source_size", "target", taken.cast("long").alias("taken"))
