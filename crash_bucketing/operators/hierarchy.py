"""Spanning tree, variable-density hierarchy and bucket selection.

The kernels below work on one target's arrays; `spanning_tree` and `hierarchies` run them over DataFrames keyed by target.
Equal distances merge at once, so no result depends on row order.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .near import kth_distance, pair_distances, tree_by_lists

NOISE = -1


#: Up to so many points all pairs are compared point by point; beyond, matrix products tell which pairs to compare.
GROWN = 2048


def core_distance(x: np.ndarray, m_pts: int) -> np.ndarray:
    """Distance to the m_pts-th nearest point, the point itself counting as the first."""
    if m_pts <= 1 or len(x) < 2:
        return np.zeros(len(x))
    if len(x) > GROWN:
        return kth_distance(x, m_pts - 1)
    out = np.empty(len(x))
    for a in range(0, len(x), 512):
        d = pair_distances(x[a : a + 512], x)
        out[a : a + 512] = np.partition(d, min(m_pts, len(x)) - 1, axis=1)[:, min(m_pts, len(x)) - 1]
    return out


def prim(x: np.ndarray, core: np.ndarray | None = None, dist: np.ndarray | None = None) -> list[tuple[int, int, float]]:
    """Minimum spanning tree in memory linear in the points (unless all distances are given); ties go to the smaller pair of positions."""
    n = len(x)
    if n < 2:
        return []
    core = np.zeros(n) if core is None else core
    best, parent = np.full(n, np.inf), np.zeros(n, dtype=np.int64)
    open_ = np.ones(n, dtype=bool)
    at, edges = 0, []
    for _ in range(n - 1):
        open_[at] = False
        row = dist[at] if dist is not None else pair_distances(x[at : at + 1], x)[0]
        d = np.maximum(np.maximum(row, core), core[at])
        closer = open_ & ((d < best) | ((d == best) & (at < parent)))
        best[closer], parent[closer] = d[closer], at
        rest = np.flatnonzero(open_)
        at = int(rest[np.argmin(best[rest])])
        edges.append((min(at, int(parent[at])), max(at, int(parent[at])), float(best[at])))
    return sorted(edges, key=lambda e: (e[2], e[0], e[1]))


def minimum_tree(x: np.ndarray, core: np.ndarray | None = None, dist: np.ndarray | None = None, lists: tuple[np.ndarray, np.ndarray] | None = None) -> list[tuple[int, int, float]]:
    """Minimum spanning tree of any number of points; of equal edges either way may take others. lists: near lists, if they are known."""
    if len(x) <= GROWN:
        return prim(x, core, dist)
    a, b, d = tree_by_lists(x, core, lists)
    return list(zip(a.tolist(), b.tolist(), d.tolist(), strict=True))


def kruskal(n: int, edges: Iterable[tuple[int, int, float]]) -> list[tuple[int, int, float]]:
    """Tree of a set of edges over points 0..n-1."""
    return joined(n, sorted(edges, key=lambda e: (e[2], e[0], e[1])))


def joined(n: int, edges: Iterable[tuple[int, int, float]]) -> list[tuple[int, int, float]]:
    """The same of edges that come by length, a, b."""
    root, out = list(range(n)), []

    def find(a: int) -> int:
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    for a, b, d in edges:
        ra, rb = find(a), find(b)
        if ra != rb:
            root[ra] = rb
            out.append((a, b, d))
    return out


@dataclass
class Cluster:
    """Points are kept as stretches of the hierarchy's order, so that clusters inside clusters cost no more than their number."""

    parent: int | None
    birth: float  # distance at which it split off; infinite for the root
    order: np.ndarray = field(repr=False)
    start: int
    size: int
    left: list[tuple[int, int, float]] = field(default_factory=list)  # (start, size, distance): points that left together, to noise or to a sub-cluster
    kids: list[int] = field(default_factory=list)

    @property
    def members(self) -> list[int]:
        return sorted(self.order[self.start : self.start + self.size].tolist())

    @property
    def exits(self) -> dict[int, float]:
        """point: distance at which it left"""
        return {p: d for start, size, d in self.left for p in self.order[start : start + size].tolist()}

    @cached_property
    def _stability(self) -> float:
        born = 0.0 if np.isinf(self.birth) else 1 / self.birth
        return float(sum(size * (1 / d - born) for _, size, d in self.left))

    def stability(self) -> float:
        return self._stability


@dataclass
class Hierarchy:
    n: int
    clusters: list[Cluster]
    _by_mass: dict[str, list[int]] = field(default_factory=dict, repr=False, compare=False)  # kept: every epsilon starts from the same

    @cached_property
    def finest(self) -> float:
        """The largest density at which a point leaves a cluster."""
        return max((1 / d for c in self.clusters for _, _, d in c.left), default=0.0)

    def chosen_by_mass(self, root_mode: str = "mass") -> list[int]:
        """Clusters of largest total stability, none inside another. 'mass': the root takes part; 'floor': only where nothing splits."""
        if root_mode in self._by_mass:
            return self._by_mass[root_mode].copy()
        value, wins = [0.0] * len(self.clusters), [False] * len(self.clusters)
        for i in range(len(self.clusters) - 1, -1, -1):
            c = self.clusters[i]
            below = sum(value[k] for k in c.kids)
            own = c.stability()
            wins[i] = (not c.kids or own >= below) if i or root_mode == "mass" else not c.kids
            value[i] = own if wins[i] else below
        out, open_ = [], [0] if self.clusters else []
        while open_:
            i = open_.pop()
            if wins[i]:
                out.append(i)
            else:
                open_ += self.clusters[i].kids
        self._by_mass[root_mode] = sorted(out)
        return self._by_mass[root_mode].copy()

    def chosen_leaves(self) -> list[int]:
        return [i for i, c in enumerate(self.clusters) if not c.kids]

    def raised(self, chosen: list[int], eps: float) -> list[int]:
        """Each chosen cluster born below epsilon gives way to its nearest ancestor that was not."""
        out, seen = set(), set()
        for i in chosen:
            while self.clusters[i].birth < eps and i not in seen:
                seen.add(i)
                i = self.clusters[i].parent
            if i not in seen:
                out.add(i)
        return sorted(out)

    def partition(self, selected: list[int], eps: float) -> np.ndarray:
        """Bucket of each point, numbered by least member. Points that left the root above epsilon are noise, at every epsilon."""
        label = np.full(self.n, NOISE)
        for i in selected:
            c = self.clusters[i]
            for start, size in ((c.start, c.size),) if i else ((start, size) for start, size, d in c.left if d <= eps):
                label[c.order[start : start + size]] = i
        return canonical(label)

    def hybrid(self, eps: float, root_mode: str = "mass", start: str = "mass") -> tuple[np.ndarray, list[int]]:
        selected = self.raised(self.chosen_leaves() if start == "leaf" else self.chosen_by_mass(root_mode), eps)
        return self.partition(selected, eps), selected


def canonical(label: np.ndarray) -> np.ndarray:
    """Buckets renumbered in order of their first point; noise stays."""
    out, real = np.full(len(label), NOISE), np.flatnonzero(label != NOISE)
    if len(real):
        _, first, index = np.unique(label[real], return_index=True, return_inverse=True)
        out[real] = np.argsort(np.argsort(first))[index]
    return out


def condense(n: int, tree: list[tuple[int, int, float]], min_size: int = 2) -> Hierarchy:
    """Merge tree with all equal distances at once, then the clusters of at least `min_size` points."""
    if n == 0:
        return Hierarchy(0, [])
    root = list(range(n))
    node_of: dict[int, int] = {i: i for i in range(n)}  # set representative: merge node
    nodes: list[tuple[float, list[int]]] = [(0.0, [])] * n
    sizes = [1] * n

    def find(a: int) -> int:
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    at = 0
    tree = sorted(tree, key=lambda e: e[2])
    while at < len(tree):
        upto = at
        while upto < len(tree) and tree[upto][2] == tree[at][2]:
            upto += 1
        touched = {r: node_of[r] for a, b, _ in tree[at:upto] for r in (find(a), find(b))}
        for a, b, _ in tree[at:upto]:
            root[find(a)] = find(b)
        merged: dict[int, list[int]] = {}
        for r, node in touched.items():
            merged.setdefault(find(r), []).append(node)
        for r, kids in merged.items():
            nodes.append((tree[at][2], kids))
            sizes.append(sum(sizes[k] for k in kids))
            node_of[r] = len(nodes) - 1
        at = upto

    top = len(nodes) - 1
    # each node's points are a stretch of `order`
    start, order, least = [-1] * len(nodes), np.zeros(n, dtype=np.int64), list(range(n))
    start[top] = 0
    for _, kids in nodes[n:]:
        least.append(min(least[k] for k in kids))
    for node in range(top, -1, -1):
        if start[node] < 0:
            continue
        if node < n:
            order[start[node]] = node
        at = start[node]
        for k in nodes[node][1]:
            start[k] = at
            at += sizes[k]
    clusters = [Cluster(None, float("inf"), order, 0, sizes[top])]
    if n == 1:
        clusters[0].left.append((0, 1, 1.0))
        return Hierarchy(n, clusters)
    stack = [(top, 0)]
    while stack:
        node, c = stack.pop()
        dist, kids = nodes[node]
        large = [k for k in kids if sizes[k] >= min_size]
        clusters[c].left += [(start[k], sizes[k], dist) for k in kids if sizes[k] < min_size]
        if len(large) == 1:
            stack.append((large[0], c))
        else:
            for k in sorted(large, key=least.__getitem__):
                clusters[c].left.append((start[k], sizes[k], dist))
                clusters.append(Cluster(c, dist, order, start[k], sizes[k]))
                clusters[c].kids.append(len(clusters) - 1)
                stack.append((k, len(clusters) - 1))
    return Hierarchy(n, clusters)


def persistence(h: Hierarchy, selected: list[int], how: str = "mean") -> float:
    """Share of the scale through which the selected clusters last: stability over size times the largest density of the tree."""
    finest = h.finest
    if not selected or not finest:
        return 0.0
    each = [h.clusters[i].stability() / (h.clusters[i].size * finest) for i in selected]
    sizes = [h.clusters[i].size for i in selected]
    return float({"mean": np.mean(each), "min": min(each), "weighted": np.average(each, weights=sizes)}[how])


def merge_equal(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct vectors in order of first occurrence, position of each row among them)."""
    seen: dict[bytes, int] = {}
    index = np.array([seen.setdefault(row.tobytes(), len(seen)) for row in np.ascontiguousarray(x)], dtype=np.int64)
    first = {k: i for i, k in reversed(list(enumerate(index.tolist())))}
    return x[[first[k] for k in range(len(seen))]], index


def _matrix(column: pd.Series) -> np.ndarray:
    return np.array(column.tolist(), dtype=np.float64)


def _local_tree(m_pts: int):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point")
        x, ids = _matrix(pdf["vec"]), pdf["point"].to_numpy()
        edges = minimum_tree(x, core_distance(x, m_pts) if m_pts > 1 else None)
        return pd.DataFrame({"target": pdf["target"].iloc[0], "a": ids[[e[0] for e in edges]], "b": ids[[e[1] for e in edges]], "dist": [e[2] for e in edges]}) if edges else pd.DataFrame({"target": pd.Series(dtype=str), "a": pd.Series(dtype="int64"), "b": pd.Series(dtype="int64"), "dist": pd.Series(dtype=float)})

    return run


def placed_tree(points: DataFrame) -> DataFrame:
    """(target, a, b, dist) of each target's tree over the places of its points in order; the row with a = b names the last one."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point")
        edges = minimum_tree(_matrix(pdf["vec"])) + [(len(pdf) - 1, len(pdf) - 1, 0.0)]
        return pd.DataFrame(edges, columns=["a", "b", "dist"]).assign(target=pdf["target"].iloc[0])[["target", "a", "b", "dist"]]

    return points.select("target", "point", "vec").groupBy("target").applyInPandas(run, EDGE)


#: A target is dealt into so many blocks at most: each point goes to all tiles of its block, so more would only be shuffled more often.
MOST_BLOCKS = 16
#: Where more are asked for, blocks have about so many points, as long as that makes no more than these.
ROOMY = 16_384
#: Partitions for the tiles: so many that two large tiles seldom share one.
APART = 256
EDGE = "target string, a long, b long, dist double"


def _union(pdf: pd.DataFrame) -> pd.DataFrame:
    """Tree of the edges of one target. Rows with a = b only name points."""
    ids = np.unique(np.concatenate([pdf["a"], pdf["b"]]))
    real = pdf[pdf["a"] != pdf["b"]].sort_values(["dist", "a", "b"])
    edges = joined(len(ids), zip(np.searchsorted(ids, real["a"]).tolist(), np.searchsorted(ids, real["b"]).tolist(), real["dist"].tolist(), strict=True))
    return pd.DataFrame({"target": pdf["target"].iloc[0], "a": ids[[e[0] for e in edges]], "b": ids[[e[1] for e in edges]], "dist": [e[2] for e in edges]}) if edges else pdf.iloc[:0][["target", "a", "b", "dist"]]


def spanning_tree(points: DataFrame, strategy: str = "local", blocks: int = 4, m_pts: int = 1) -> DataFrame:
    """(target, a, b, dist), a < b. points: (target, point, vec).

    'local': one task per target, memory linear in its points. 'tiles': points are dealt into blocks, each pair of blocks
    gives the tree of its points, and the tree of the union of these trees is the whole tree (an edge that is the largest of some
    cycle within a tile is the largest of that cycle in the whole). One shuffle of points, one of about points times blocks edges. `blocks` above
    MOST_BLOCKS count as these: tiles are larger then, their tree is the same.
    """
    keep = points.select("target", "point", "vec")
    if strategy == "local":
        return keep.groupBy("target").applyInPandas(_local_tree(m_pts), EDGE)
    if m_pts > 1:
        raise ValueError("tiles serve m_pts = 1, where reachability is the distance")
    blocks = min(blocks, MOST_BLOCKS)
    block = F.pmod(F.xxhash64("point"), F.lit(blocks)).cast("int")
    # every point goes to the tiles of its block with each other one; a block's own pairs are in all of these
    tiles = keep.withColumn("block", block).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).where(F.lit(blocks == 1) | (F.col("block") != F.col("other"))).select("target", "point", "vec", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))
    parts = tiles.repartition(APART, "target", "i", "j").groupBy("target", "i", "j").applyInPandas(_local_tree(1), EDGE).distinct()
    return parts.groupBy("target").applyInPandas(_union, EDGE)


def blocks_for(n: int, block: int) -> int:
    """How many blocks n points of a target are dealt into: of `block` points, or larger ones where these would be more than MOST_BLOCKS. Tiles
    of few points each compute a block's own pairs once more."""
    asked = -(-n // block)
    return max(2, asked if asked <= MOST_BLOCKS else min(MOST_BLOCKS, -(-n // max(ROOMY, block))))


def components_of(points: DataFrame, edges: DataFrame) -> DataFrame:
    """(target, point, comp): the least point that edges lead to. points and edges meet by target in one task, 24 bytes a row."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(np.concatenate([pdf["a"], pdf["b"]]))
        root = list(range(len(ids)))

        def find(a: int) -> int:
            while root[a] != a:
                root[a] = root[root[a]]
                a = root[a]
            return a

        for a, b in zip(np.searchsorted(ids, pdf["a"]).tolist(), np.searchsorted(ids, pdf["b"]).tolist(), strict=True):
            a, b = sorted((find(a), find(b)))
            root[b] = a
        return pd.DataFrame({"target": pdf["target"].iloc[0], "point": ids, "comp": ids[[find(i) for i in range(len(ids))]]})

    named = points.select("target", F.col("point").alias("a"), F.col("point").alias("b")).union(edges.select("target", "a", "b"))
    return named.groupBy("target").applyInPandas(run, "target string, point long, comp long")


def approximate_tree(points: DataFrame, cell_points: int = 2048, tables: int = 4, seed: int = 1, keep=None) -> DataFrame:
    """(target, a, b, dist, exact): a spanning tree over random-hyperplane neighbours, for targets too large for exact ones; `exact` is false.

    Points that share a sign pattern in one of the tables are compared within it. There are as many planes as bring the largest target's
    cells to some `cell_points` points, and a cell that is still larger is dealt into parts by hash, so no task compares more. What these
    forests leave apart is joined in rounds: the least points of the components are compared in cells of `cell_points`, which leaves one
    component for each cell, until every target is one tree. keep: writes a frame once and reads it back (rounds start from it).
    """
    keep = keep or (lambda df, _: df)
    sizes = points.groupBy("target").agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("d"))
    most = sizes.agg(F.max("n").alias("n"), F.max("d").alias("d")).first()
    if not most["n"]:
        return points.sparkSession.createDataFrame([], EDGE + ", exact boolean")
    planes = max(0, int(np.ceil(np.log2(most["n"] / cell_points))))
    normal = np.random.default_rng(seed).standard_normal((tables, max(1, planes), most["d"]))

    def cells(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if len(pdf):
                bits = (np.einsum("tpd,nd->ntp", normal, _matrix(pdf["vec"])) > 0) @ (1 << np.arange(normal.shape[1])) if planes else np.zeros((len(pdf), tables), dtype=np.int64)
                yield pd.DataFrame({"target": np.repeat(pdf["target"].to_numpy(), tables), "point": np.repeat(pdf["point"].to_numpy(), tables), "vec": [v for v in pdf["vec"] for _ in range(tables)], "cell": (bits * tables + np.arange(tables)).ravel().astype(np.int64)})

    def trees(celled: DataFrame) -> DataFrame:
        parts = celled.groupBy("target", "cell").agg(F.ceil(F.count("*") / cell_points).cast("int").alias("parts"))
        dealt = celled.join(parts, ["target", "cell"]).withColumn("part", F.pmod(F.xxhash64("point"), F.col("parts")))
        return dealt.groupBy("target", "cell", "part").applyInPandas(_local_tree(1), EDGE)

    rows = points.select("target", "point", "vec")
    celled = rows.mapInPandas(cells, "target string, point long, vec array<double>, cell long") if planes else rows.withColumn("cell", F.lit(0).cast("long"))
    forest = keep(trees(celled).distinct().groupBy("target").applyInPandas(_union, EDGE), "forest")
    while True:
        comps = keep(components_of(points, forest), "components")
        apart = comps.where("point = comp").groupBy("target").agg(F.count("*").alias("n")).where("n > 1")
        if apart.isEmpty():
            return forest.withColumn("exact", F.lit(False))
        least = comps.where("point = comp").join(apart.select("target"), "target", "left_semi").select("target", "point")
        bridges = trees(rows.join(least, ["target", "point"], "left_semi").withColumn("cell", F.lit(0).cast("long")))
        forest = keep(forest.union(bridges), "forest")


def condensed_table(tree: DataFrame, min_size: int = 2) -> DataFrame:
    """(target, node, parent, birth_dist, size, stability) of every cluster; the root's birth is null."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(np.concatenate([pdf["a"], pdf["b"]]))
        h = condense(len(ids), list(zip(np.searchsorted(ids, pdf["a"]).tolist(), np.searchsorted(ids, pdf["b"]).tolist(), pdf["dist"].tolist(), strict=True)), min_size)
        return pd.DataFrame([(pdf["target"].iloc[0], i, c.parent, None if np.isinf(c.birth) else c.birth, c.size, c.stability()) for i, c in enumerate(h.clusters)], columns=["target", "node", "parent", "birth_dist", "size", "stability"]).astype({"parent": "Int64"})

    return tree.groupBy("target").applyInPandas(run, "target string, node long, parent long, birth_dist double, size long, stability double")
