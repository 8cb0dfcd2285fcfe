"""Sharding by a k-d tree over document metadata.

The tree is grown level by level. At each level every open node takes its widest dimension (range relative to the
whole table), and one distributed histogram per pass narrows down the weighted median, or the weighted quantile
that leaves whole shards on both sides. Rows are ordered by (dimension, text checksum, id hash), so equal texts lie side by side:
a cut goes round a group of equal texts on its nearer side, unless the group is too heavy for even shards.
Only SQL functions touch the rows; the driver sees at most `shards * BINS` sums per pass.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, drop

BINS = 1024
#: Whole-number ranges of the three parts of a row's position: dimension value, text checksum, id hash.
TOP = 1 << 32


@dataclass
class Node:
    shards: int
    first: int  # number of its first shard
    dim: int = 0
    cut: tuple[int, int, int] | None = None  # rows at or before this position go left
    kids: list["Node"] = field(default_factory=list)

    def leaves(self) -> list["Node"]:
        return [x for k in self.kids for x in k.leaves()] if self.kids else [self]


def _left_of(node: Node) -> Column:
    v, c, r = F.col(f"d{node.dim}"), F.col("crc"), F.col("tie")
    a, b, z = (F.lit(x) for x in node.cut)
    return (v < a) | ((v == a) & ((c < b) | ((c == b) & (r <= z))))


def _where(node: Node) -> Column:
    """Number of the first shard of the leaf that a row falls into."""
    return F.when(_left_of(node), _where(node.kids[0])).otherwise(_where(node.kids[1])) if node.kids else F.lit(node.first)


def _quantiles(rows: DataFrame, open_: list[Node], sums: dict[int, float], slack: float, whole: float) -> None:
    """Fill in `cut` of all nodes at once, by histograms of weight over ever narrower ranges.

    Each bin also tells its least and greatest position, so the next range fits what is really there, and how many rows
    it has: a bin of one row needs no further pass. Rows of one dimension value and checksum that weigh at most `whole` are not cut through.
    """
    spark, dims = rows.sparkSession, sum(c[0] == "d" and c[1:].isdigit() for c in rows.columns)
    state = {n.first: {"part": 0, "fixed": [0, 0, 0], "lo": 0, "width": TOP // BINS, "goal": sums[n.first] * (n.shards // 2) / n.shards, "node": n} for n in open_}
    value = F.coalesce(*[F.when(F.col("dim") == i, F.col(f"d{i}")) for i in range(dims)])
    x = F.when(F.col("part") == 0, F.col("v")).when(F.col("part") == 1, F.col("crc")).otherwise(F.col("tie"))
    while state:
        values = ", ".join(f"({k}, {s['node'].dim}, {s['part']}, {s['fixed'][0]}L, {s['fixed'][1]}L, {s['lo']}L, {s['width']}L)" for k, s in state.items())
        at = spark.sql(f"select * from values {values} as t(node, dim, part, f0, f1, lo, width)")  # at most one row per shard
        seen = rows.join(F.broadcast(at), "node").withColumn("v", value).withColumn("x", x)
        seen = seen.where(((F.col("part") < 1) | (F.col("v") == F.col("f0"))) & ((F.col("part") < 2) | (F.col("crc") == F.col("f1"))) & (F.col("x") >= F.col("lo")) & (F.col("x") < F.col("lo") + F.col("width") * BINS))
        bins: dict[int, list] = {}
        for r in seen.groupBy("node", F.expr("cast((x - lo) div width as int)").alias("bin")).agg(F.sum("w").alias("w"), F.count("*").alias("n"), F.min("x").alias("a"), F.max("x").alias("z")).collect():
            bins.setdefault(r["node"], []).append((r["bin"], r["w"], r["n"], r["a"], r["z"]))
        for k in list(state):
            s, before = state[k], 0
            for _, w, n, a, z in sorted(bins[k]):
                if before + w >= s["goal"] or (a, z) == max((y[3], y[4]) for y in bins[k]):
                    break
                before += w
            if w <= slack or n == 1 or (a == z and (s["part"] == 2 or s["part"] == 1 and w <= whole)):
                # near enough: the whole bin goes to the side that it overshoots less
                end = z if s["goal"] - before >= w / 2 else a - 1
                s["node"].cut = tuple([*s["fixed"][: s["part"]], end, TOP, TOP][:3])
                del state[k]
            elif a == z:
                s["fixed"][s["part"]] = a
                s |= {"part": s["part"] + 1, "lo": 0, "width": TOP // BINS, "goal": s["goal"] - before}
            else:
                s |= {"lo": a, "width": -(-(z - a + 1) // BINS), "goal": s["goal"] - before}


def kd_shards(docs: DataFrame, shards: int = 40, dimensions: dict[str, Column] | None = None, tolerance: float = 0.002, group_share: float = 0.05, slots: int = 64) -> DataFrame:
    """Every row with its shard: doc_id, size, text_crc32, shard, slot.

    size: UTF-8 bytes of the text (null: 0) plus 16. dimensions: name to numeric column over doc_id, text, lang,
    source, n_chars; by default the logarithm of the size, bytes per character, and the shares of blanks and line ends, all functions of
    the text. tolerance: how far, in parts of a shard's target bytes, a cut may be off where nothing hinders it. Equal texts stay together
    where all of them weigh no more than `group_share` of that target or than the largest document.
    Nulls in a dimension count as its least value; a null text is empty; repeated rows count each. An empty table gives
    an empty result. Slots run without gaps from 0 in each shard, counted in `slots` hash blocks per shard.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    size = F.octet_length(text).cast("long") + 16
    chars = F.greatest(F.char_length(text), F.lit(1))
    share = lambda of: 1 - F.octet_length(F.replace(text, F.lit(of), F.lit(""))) / F.greatest(F.octet_length(text), F.lit(1))
    own = {"log_size": F.log2(size), "bytes_per_char": F.octet_length(text) / chars, "blanks": share(" "), "line_ends": share("\n")}
    chosen = list((dimensions or own).values())
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), size.alias("w"), F.crc32(text).cast("long").alias("crc"), F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(TOP)).alias("tie"), *[c.cast("double").alias(f"raw{i}") for i, c in enumerate(chosen)])
    rows = cut(rows, "metadata")
    ends = rows.agg(*[f(f"raw{i}") for i in range(len(chosen)) for f in (F.min, F.max)], F.max("w"), F.sum("w")).first()
    lows, widths = ends[0:-2:2], [(b or 0) - (a or 0) for a, b in zip(ends[0:-2:2], ends[1:-2:2], strict=True)]
    scaled = [F.coalesce(((F.col(f"raw{i}") - F.lit(lows[i])) / F.lit(widths[i]) * (TOP - 1)).cast("long"), F.lit(0)) if widths[i] else F.lit(0).cast("long") for i in range(len(chosen))]
    base = rows.select("doc_id", "w", "crc", "tie", *[s.alias(f"d{i}") for i, s in enumerate(scaled)])
    root, total = Node(shards, 0), float(ends[-1] or 0)
    while total and (open_ := [n for n in root.leaves() if n.shards > 1]):
        placed = cut(base.withColumn("node", _where(root).cast("int")), "nodes")
        stats = {r["node"]: r for r in placed.groupBy("node").agg(F.sum("w").alias("w"), *[(F.max(f"d{i}") - F.min(f"d{i}")).alias(f"s{i}") for i in range(len(chosen))]).collect()}
        for n in open_:
            if n.first in stats:
                n.dim = max(range(len(chosen)), key=lambda i: (stats[n.first][f"s{i}"], -i))
        busy = [n for n in open_ if n.first in stats]
        _quantiles(placed, busy, {k: float(r["w"]) for k, r in stats.items()}, tolerance * total / shards, max(group_share * total / shards, float(ends[-2])))
        drop(placed)
        for n in open_:
            n.cut = n.cut or (TOP, TOP, TOP)
            half = n.shards // 2
            n.kids = [Node(half, n.first), Node(n.shards - half, n.first + half)]
    placed = base.select("doc_id", "w", "crc", "tie", (_where(root) if total else F.lit(0)).cast("int").alias("shard"), F.pmod("tie", F.lit(slots)).cast("int").alias("block"))
    placed = cut(placed, "placed")
    drop(rows)
    counts = placed.groupBy("shard", "block").agg(F.count("*").alias("n"))
    starts = counts.selectExpr("shard", "block", "sum(n) over (partition by shard order by block) - n as start")
    numbered = placed.selectExpr("*", "row_number() over (partition by shard, block order by tie, doc_id, crc) - 1 as k")
    # shards * slots rows at most
    return numbered.join(F.broadcast(starts), ["shard", "block"]).select("doc_id", F.col("w").alias("size"), F.col("crc").alias("text_crc32"), "shard", (F.col("start") + F.col("k")).cast("long").alias("slot"))
