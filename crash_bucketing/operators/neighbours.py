"""Nearest neighbours, range search, assignment of new crashes, representatives."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .hierarchy import pair_distances

HIT = "query long, point long, dist double"
#: Points or queries of a tile at most (on average, for dealt ones): a tile's vectors are a few MB.
BLOCK = 4096

#: (ids and vectors of queries, ids and vectors of points) to the rows of a tile.
Kernel = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray], pd.DataFrame]


def _matrix(column: pd.Series) -> np.ndarray:
    return np.array(column.tolist(), dtype=np.float64)


def tiles(points: DataFrame, queries: DataFrame, kernel: Kernel, schema: str, block: int = BLOCK) -> DataFrame:
    """Every query against every point, a tile at a time; points and queries are (point, vec).

    At most `block` queries are sent to where the points are, and each batch of points is a tile. More are dealt into blocks by hash, as the points
    are, and each pair of blocks meets in a task of its own: no vector passes the driver, no task holds more than two blocks.
    """
    q = -(-queries.count() // block)
    if q <= 1:
        rows = queries.select("point", "vec").limit(block).collect()
        ids, x = np.array([r["point"] for r in rows], dtype=np.int64), np.array([r["vec"] for r in rows], dtype=np.float64)

        def stream(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf) and len(ids):
                    yield kernel(ids, x, pdf["point"].to_numpy(), _matrix(pdf["vec"]))

        return points.select("point", "vec").mapInPandas(stream, schema)
    p = -(-points.count() // block)

    def dealt(df: DataFrame, own: str, n: int, other: str, m: int) -> DataFrame:
        return df.select(F.col("point").alias(f"id_{own}"), F.col("vec").alias(f"vec_{own}"), F.pmod(F.xxhash64("point"), F.lit(n)).alias(f"{own}_{own}"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long"))).alias(f"{own}_{other}"))

    # names differ on both sides: points and queries may be one frame
    a, b = dealt(queries, "q", q, "p", p), dealt(points, "p", p, "q", q)

    def meet(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return kernel(left["id_q"].to_numpy(), _matrix(left["vec_q"]), right["id_p"].to_numpy(), _matrix(right["vec_p"])) if len(left) and len(right) else pd.DataFrame({c.split()[0]: [] for c in schema.split(", ")})

    return a.groupBy("q_q", "q_p").cogroup(b.groupBy("p_q", "p_p")).applyInPandas(meet, schema)


def _pieces(q: np.ndarray, x: np.ndarray, rows: int = 512) -> Iterator[tuple[int, np.ndarray]]:
    """Distances of some queries at a time to all points of a tile."""
    for a in range(0, len(q), rows):
        yield a, pair_distances(q[a : a + rows], x)


def _hits(parts: list[tuple]) -> pd.DataFrame:
    query, point, dist = (np.concatenate(c) for c in zip(*parts, strict=True)) if parts else ([], [], [])
    return pd.DataFrame({"query": np.asarray(query, dtype=np.int64), "point": np.asarray(point, dtype=np.int64), "dist": np.asarray(dist, dtype=np.float64)})


def _nearest(k: int) -> Kernel:
    def kernel(ids: np.ndarray, q: np.ndarray, points: np.ndarray, x: np.ndarray) -> pd.DataFrame:
        parts, k_ = [], min(k + 1, len(points))
        for a, d in _pieces(q, x):
            own = ids[a : a + len(d)]
            d[own[:, None] == points[None, :]] = np.inf
            bound = np.partition(d, k_ - 1, axis=1)[:, k_ - 1]  # ties with the last one stay: the ranking decides by id
            i, j = np.nonzero((d <= bound[:, None]) & np.isfinite(d))
            parts.append((own[i], points[j], d[i, j]))
        return _hits(parts)

    return kernel


def _ranked(hits: DataFrame, k: int) -> DataFrame:
    return hits.withColumn("rank", F.row_number().over(Window.partitionBy("query").orderBy("dist", "point"))).where(F.col("rank") <= k)


def knn(points: DataFrame, queries: DataFrame, k: int, block: int = BLOCK) -> DataFrame:
    """(query, point, dist, rank): the k nearest other points, exact; ties by id. Each tile keeps its k best, so what is ranked is small."""
    return _ranked(tiles(points, queries, _nearest(k), HIT, block), k)


def within(points: DataFrame, queries: DataFrame, eps: float, block: int = BLOCK) -> DataFrame:
    """(query, point, dist) of all other points within eps."""

    def kernel(ids: np.ndarray, q: np.ndarray, points: np.ndarray, x: np.ndarray) -> pd.DataFrame:
        parts = []
        for a, d in _pieces(q, x):
            own = ids[a : a + len(d)]
            i, j = np.nonzero((d <= eps) & (own[:, None] != points[None, :]))
            parts.append((own[i], points[j], d[i, j]))
        return _hits(parts)

    return tiles(points, queries, kernel, HIT, block)


def distance_range(points: DataFrame, block: int = BLOCK) -> DataFrame:
    """(low, high, pairs): least and greatest distance of two different points and how many pairs there are. A tile gives one row."""

    def kernel(ids: np.ndarray, q: np.ndarray, points: np.ndarray, x: np.ndarray) -> pd.DataFrame:
        low, high, n = np.inf, 0.0, 0
        for a, d in _pieces(q, x):
            other = d[ids[a : a + len(d), None] < points[None, :]]
            if len(other):
                low, high, n = min(low, float(other.min())), max(high, float(other.max())), n + len(other)
        return pd.DataFrame({"low": [low], "high": [high], "pairs": [n]})

    return tiles(points, points, kernel, "low double, high double, pairs long", block).where("pairs > 0").agg(F.min("low").alias("low"), F.max("high").alias("high"), F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"))


def _centres(x: np.ndarray, n: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    c = x[rng.choice(len(x), n, replace=False)].copy()
    for _ in range(rounds):
        own = (x @ c.T - (c * c).sum(axis=1) / 2).argmax(axis=1)
        for j in np.unique(own):
            c[j] = x[own == j].mean(axis=0)
    return c


def knn_approximate(points: DataFrame, queries: DataFrame, k: int, recall: float = 0.95, sample: int = 8192, lists: int | None = None, chunk: int = BLOCK, seed: int = 1) -> DataFrame:
    """(query, point, dist, rank) by inverted lists: every point stands in the list of its nearest centre, a query looks into the lists of its nearest centres.

    Centres are fitted on a bounded sample; how many lists a query opens is set on the same sample, as the least number that holds `recall` of the true
    neighbours there (in the whole table neighbours are nearer, so it holds no fewer). Distances are exact. Lists (square root of the
    points, 4096 at most) are dealt into chunks of some `chunk` points, so no task gets a long list whole.
    """
    n = points.count()
    rows = points.where("vec is not null").withColumn("h", F.xxhash64(F.lit(seed), "point")).orderBy("h", "point").limit(sample).select("point", "vec").collect()
    if not rows:
        return points.sparkSession.createDataFrame([], HIT + ", rank int")
    x, rng = np.array([r["vec"] for r in rows], dtype=np.float64), np.random.default_rng(seed)
    centres = _centres(x, min(lists or max(1, min(4096, int(n**0.5))), len(x)), rng)
    half = (centres * centres).sum(axis=1) / 2
    order = lambda y: np.argsort(half - y @ centres.T, axis=1, kind="stable")  # noqa: E731  nearest centre first
    # at which place of its order a query finds the list of each of its true neighbours
    asked = x[: min(len(x), 256)]
    d = pair_distances(asked, x)
    d[np.arange(len(asked)), np.arange(len(asked))] = np.inf
    near = np.argsort(d, axis=1, kind="stable")[:, : max(1, min(k, len(x) - 1))]
    place = np.argsort(order(asked), axis=1)
    opened = int(np.quantile(place[np.arange(len(asked))[:, None], order(x)[:, 0][near]], recall, method="higher")) + 1

    def listed(many: int):
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf):
                    cells = order(_matrix(pdf["vec"]))[:, :many]
                    yield pd.DataFrame({"point": np.repeat(pdf["point"].to_numpy(), many), "vec": [v for v in pdf["vec"] for _ in range(many)], "cell": cells.ravel().astype(np.int64)})

        return run

    schema = "point long, vec array<double>, cell long"
    a = points.where("vec is not null").select("point", "vec").mapInPandas(listed(1), schema)
    b = queries.where("vec is not null").select("point", "vec").mapInPandas(listed(opened), schema)
    # one row a list, at most 4096
    chunks = {r["cell"]: r["chunks"] for r in a.groupBy("cell").agg(F.ceil(F.count("*") / chunk).cast("int").alias("chunks")).collect()}
    parts = F.coalesce(F.get(F.lit([chunks.get(c, 1) for c in range(len(centres))]), F.col("cell").cast("int")), F.lit(1))
    a = a.withColumn("part", F.pmod(F.xxhash64("point"), parts).cast("int"))
    b = b.withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1)))
    kernel = _nearest(k)

    def meet(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return kernel(left["point"].to_numpy(), _matrix(left["vec"]), right["point"].to_numpy(), _matrix(right["vec"])) if len(left) and len(right) else _hits([])

    return _ranked(b.groupBy("cell", "part").cogroup(a.groupBy("cell", "part")).applyInPandas(meet, HIT), k)


def assign_new(assigned: DataFrame, points: DataFrame, new: DataFrame, eps: float) -> DataFrame:
    """(point, bucket): each new point takes the bucket of its nearest point within eps, else none."""
    nearest = knn(points, new, 1).where(F.col("dist") <= eps)
    return new.select("point").join(nearest.select(F.col("query").alias("point"), F.col("point").alias("near")), "point", "left").join(assigned.select(F.col("point").alias("near"), "bucket"), "near", "left").select("point", "bucket")


def representatives(assigned: DataFrame, points: DataFrame, rule: str = "smallest") -> DataFrame:
    """(target, bucket, point): one point per bucket, the smallest id or the one nearest to the bucket's mean."""
    if rule == "smallest":
        return assigned.groupBy("target", "bucket").agg(F.min("point").alias("point"))
    both = assigned.select("target", "bucket", "point").join(points.select("target", "point", "vec"), ["target", "point"])
    coords = both.select("target", "bucket", F.posexplode("vec").alias("j", "x")).groupBy("target", "bucket", "j").agg(F.avg("x").alias("x"))
    means = coords.groupBy("target", "bucket").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda e: e["x"]).alias("mean"))
    d = F.aggregate(F.zip_with("vec", "mean", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    return both.join(means, ["target", "bucket"]).groupBy("target", "bucket").agg(F.min_by("point", F.struct(d, "point")).alias("point"))


def triage(assigned: DataFrame, top: int | None = None) -> DataFrame:
    """Buckets by size with the crash to look at first."""
    out = assigned.groupBy("target", "bucket").agg(F.count("*").alias("n"), F.min("crash_id").alias("crash_id")).orderBy(F.desc("n"), "target", "crash_id")
    return out.limit(top) if top else out
