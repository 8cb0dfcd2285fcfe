"""One target's points to buckets, for all targets at once: tree, hierarchy, search, choice."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.hierarchy import NOISE, approximate_tree, blocks_for, condense, core_distance, merge_equal, minimum_tree, pair_distances, spanning_tree
from ..operators.near import LISTED, Products, edge_lengths, near_lists
from ..operators.quality import HELD
from .search import assess, choose, search


ASSIGNED = "target string, point long, bucket long, epsilon double"
RUN = "target string, turn int, epsilon double, partition_hash string, n_buckets long, validity double, persistence double"


@dataclass(frozen=True)
class Config:
    min_size: int = 2
    m_pts: int = 1
    num_steps: int = 20
    root_mode: str = "mass"
    start: str = "mass"


def furthest(x: np.ndarray) -> float:
    if len(x) > HELD:  # products tell which pairs may be the furthest
        p, most, pairs = Products(x), 0.0, []
        for a in range(0, len(x), 512):
            for b in range(a, len(x), 2048):  # a pair counts once
                d = p.block(slice(a, a + 512), slice(b, b + 2048))
                if (top := float(d.max())) >= most - 2 * p.err:
                    most = max(most, top)
                    i, j = np.nonzero(d >= most - 2 * p.err)
                    pairs.append((i + a, j + b, d[i, j]))
        i, j, d = (np.concatenate(c) for c in zip(*pairs, strict=True))
        return float(edge_lengths(x, i[d >= most - 2 * p.err], j[d >= most - 2 * p.err]).max())
    return max((float(pair_distances(x[a : a + 512], x).max()) for a in range(0, len(x), 512)), default=0.0)


def _prepare(pdf: pd.DataFrame, config: Config):
    pdf = pdf.sort_values("point")
    full = np.array(pdf["vec"].tolist(), dtype=np.float64) + 0.0  # one zero, as distances have it
    x, index = merge_equal(full)
    lists = near_lists(x, LISTED) if len(x) > HELD else None
    tree = minimum_tree(x, core_distance(x, config.m_pts) if config.m_pts > 1 else None, lists=lists)
    return pdf, x, index, tree, condense(len(x), tree, config.min_size), lists


def runs_of(pdf: pd.DataFrame, config: Config):
    pdf, x, index, tree, h, lists = _prepare(pdf, config)
    if len(x) < 2:
        return pdf, x, index, h, []
    found = search(lambda eps: h.hybrid(eps, config.root_mode, config.start), tree[0][2], furthest(x), config.num_steps)
    return pdf, x, index, h, assess(found, h, x, lists=lists)


def _run_rows(target: str, found: list) -> pd.DataFrame:
    return pd.DataFrame([(target, r.turn, r.epsilon, r.digest, r.buckets, r.validity, r.persistence) for r in found], columns=["target", "turn", "epsilon", "partition_hash", "n_buckets", "validity", "persistence"])


def search_runs(points: DataFrame, config: Config = Config()) -> DataFrame:
    """(target, turn, epsilon, partition_hash, n_buckets, validity, persistence) of every evaluation."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf, *_, found = runs_of(pdf, config)
        return _run_rows(pdf["target"].iloc[0], found)

    return points.select("target", "point", "vec").groupBy("target").applyInPandas(run, RUN)


def _named(label: np.ndarray, index: np.ndarray) -> np.ndarray:
    """Buckets of all points from those of the distinct ones: equal vectors share a bucket even where their common point is noise."""
    size, fresh, label = np.bincount(index), label.max(initial=-1) + 1, label.copy()
    for k in np.flatnonzero((label == NOISE) & (size > 1)):
        label[k] = fresh
        fresh += 1
    return label[index].astype(np.int64)


def _without_vector(points: DataFrame) -> DataFrame:
    return points.where("vec is null").select("target", "point", F.lit(NOISE).cast("long").alias("bucket"), F.lit(0.0).alias("epsilon"))


def bucket(points: DataFrame, config: Config = Config(), epsilon: float | None = None) -> DataFrame:
    """(target, point, bucket, epsilon). points: (target, point, vec). Bucket -1 is noise; null vectors come back as noise.

    With `epsilon` the floor is fixed; else it is searched for. No points give no rows, one point is one bucket. A target is one task,
    with memory linear in its distinct points; `bucket_any` sends larger targets another way.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        if epsilon is None:
            pdf, x, index, h, found = runs_of(pdf, config)
            best = choose(found) if found else None
            label, eps = (best.label, best.epsilon) if best else (np.zeros(len(x), dtype=np.int64), 0.0)
        else:
            pdf, x, index, _, h, _ = _prepare(pdf, config)
            label, eps = (h.hybrid(epsilon, config.root_mode, config.start)[0] if len(x) > 1 else np.zeros(len(x), dtype=np.int64)), epsilon
        return pd.DataFrame({"target": pdf["target"].to_numpy(), "point": pdf["point"].to_numpy(), "bucket": _named(label, index), "epsilon": float(eps)})

    good = points.where("vec is not null").select("target", "point", "vec").groupBy("target").applyInPandas(run, ASSIGNED)
    return good.unionByName(_without_vector(points))


class FromTree:
    """One target's hierarchy from the edges of its tree; validity is measured on the points whose vectors are there, all or a sample.

    Edges of length zero join equal points first, as the direct way does. The search runs up to the largest distance, of a sample up to twice the largest
    distance of its points from their mean, which is no less than any distance of the sample; above the tree's largest edge nothing changes anyway.
    """

    def __init__(self, edges: pd.DataFrame, some: pd.DataFrame, config: Config):
        self.config = config
        self.ids = np.unique(np.concatenate([edges["a"], edges["b"], some["point"]]).astype(np.int64))
        at = lambda c: np.searchsorted(self.ids, c)
        rows = list(zip(at(edges["a"]).tolist(), at(edges["b"]).tolist(), edges["dist"].tolist(), strict=True))
        root = np.arange(len(self.ids))

        def find(a: int) -> int:
            while root[a] != a:
                root[a] = root[root[a]]
                a = root[a]
            return int(a)

        for a, b, d in rows:
            if d == 0:
                a, b = sorted((find(a), find(b)))
                root[b] = a
        firsts, self.index = np.unique([find(i) for i in range(len(self.ids))], return_inverse=True)
        self.tree = sorted(((int(self.index[a]), int(self.index[b]), d) for a, b, d in rows if d > 0), key=lambda e: (e[2], e[0], e[1]))
        self.n = len(firsts)
        self.h = condense(self.n, self.tree, config.min_size)
        picked, order = np.unique(self.index[at(some["point"])], return_index=True)
        self.sampled = picked
        self.x = np.array(some["vec"].tolist(), dtype=np.float64)[order] if len(some) else np.zeros((0, 1))

    def runs(self) -> list:
        if self.n < 2:
            return []
        wide = 2 * float(np.sqrt(((self.x - self.x.mean(axis=0)) ** 2).sum(axis=1)).max()) if len(self.x) else 0.0
        high = furthest(self.x) if len(self.x) == self.n else max(wide, self.tree[-1][2])
        found = search(lambda eps: self.h.hybrid(eps, self.config.root_mode, self.config.start), self.tree[0][2], high, self.config.num_steps)
        return assess(found, self.h, self.x, self.sampled)


def _from_tree(points: DataFrame, tree: DataFrame, config: Config, sample: int | None, then, schema: str) -> DataFrame:
    """then(target, FromTree) for each target: its edges and all its points, or about `sample` of these by hash, meet in one task (24 bytes an edge)."""
    some = points
    if sample is not None:
        sizes = points.groupBy("target").agg(F.count("*").alias("n"))
        some = points.join(sizes, "target").where(F.pmod(F.xxhash64("point"), F.lit(1 << 30)) * F.col("n") < F.lit(float(sample) * (1 << 30)))

    def run(edges: pd.DataFrame, some: pd.DataFrame) -> pd.DataFrame:
        some = some.sort_values("point")
        return then((edges if len(edges) else some)["target"].iloc[0], FromTree(edges, some, config))

    return tree.select("target", "a", "b", "dist").groupBy("target").cogroup(some.select("target", "point", "vec").groupBy("target")).applyInPandas(run, schema)


def search_runs_from_tree(points: DataFrame, tree: DataFrame, config: Config = Config(), sample: int | None = None) -> DataFrame:
    """The same as search_runs, from a stored tree; with `sample` the validity is that of about so many of each target's points."""
    return _from_tree(points, tree, config, sample, lambda target, t: _run_rows(target, t.runs()), RUN)


def bucket_from_tree(points: DataFrame, tree: DataFrame, config: Config = Config(), epsilon: float | None = None, sample: int | None = None) -> DataFrame:
    """The same as bucket, for targets whose tree (target, a, b, dist) is already there.

    Validity is measured on all points, or on about `sample` of each target, chosen by hash (all, if there are no more; sizes of buckets then weigh as
    in the sample). Points without edges (a target of one point) are one bucket.
    """

    def name(target: str, t: FromTree) -> pd.DataFrame:
        if epsilon is None:
            best = choose(found) if (found := t.runs()) else None
            label, eps = (best.label, best.epsilon) if best else (np.zeros(t.n, dtype=np.int64), 0.0)
        else:
            label, eps = (t.h.hybrid(epsilon, config.root_mode, config.start)[0] if t.n > 1 else np.zeros(t.n, dtype=np.int64)), epsilon
        return pd.DataFrame({"target": target, "point": t.ids, "bucket": _named(label, t.index), "epsilon": float(eps)})

    good = points.where("vec is not null")
    return _from_tree(good, tree, config, sample, name, ASSIGNED).unionByName(_without_vector(points))


def bucket_any(points: DataFrame, config: Config = Config(), local: int = 20_000, exact: int | None = None, block: int = 5_000, sample: int | None = None, keep=None) -> DataFrame:
    """bucket for targets of any size, and the same rows for any: up to `local` counted points one task does it all, beyond the exact tree comes from
    tiles of `block` points and buckets come from the tree, chosen by the validity of all points.

    Only a caller who names them gets less: beyond `exact` points a tree from neighbours in random cells, validity on about `sample` points. Adds `exact`:
    false where the tree is approximate or the validity sampled. The driver sees the largest size of each way, no rows."""
    keep = keep or (lambda df, _: df)
    way = F.when(F.col("n") <= local, "local")
    way = way.otherwise("tiles") if exact is None else way.when(F.col("n") <= exact, "tiles").otherwise("graph")
    sizes = points.groupBy("target").agg(F.count("*").alias("n")).withColumn("way", way)
    most = {r["way"]: r["n"] for r in sizes.groupBy("way").agg(F.max("n").alias("n")).collect()}
    out = None
    for way, n in sorted(most.items()):
        some = points.join(sizes.where(F.col("way") == way).select("target"), "target", "left_semi")
        if way == "local":
            got = bucket(some, config).withColumn("exact", F.lit(True))
        else:
            good = some.where("vec is not null")
            tree = spanning_tree(good, "tiles", blocks=blocks_for(n, block)) if way == "tiles" else approximate_tree(good, keep=keep)
            got = bucket_from_tree(some, keep(tree, "tree"), config, sample=sample).withColumn("exact", F.lit(way == "tiles" and (sample is None or n <= sample)))
        out = got if out is None else out.unionByName(got)
    return out if out is not None else bucket(points, config).withColumn("exact", F.lit(True))


def own_buckets(assigned: DataFrame) -> DataFrame:
    """Noise turned into a bucket of its own: bucket as a string."""
    return assigned.withColumn("bucket", F.when(F.col("bucket") == NOISE, F.concat(F.lit("n"), F.col("point"))).otherwise(F.col("bucket").cast("string")))


def expand(assigned: DataFrame, members: DataFrame) -> DataFrame:
    """(target, crash_id, bucket): every crash takes the bucket of its point."""
    return members.join(own_buckets(assigned).select("target", "point", "bucket"), ["target", "point"]).select("target", "crash_id", "bucket")
