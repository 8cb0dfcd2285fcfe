"""The methods that the workflow is compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.frames import parse_lines, places
from ..plans.search import assess, choose, search
from .hierarchy import NOISE, canonical, condense, core_distance, merge_equal, minimum_tree, pair_distances
from .near import LISTED, near_lists
from .quality import HELD, silhouettes

ASSIGNED = "target string, point long, bucket long"


def stack_hash(crashes: DataFrame, fields: tuple[str, ...] = ("func", "site"), top_n: int | None = None) -> DataFrame:
    """(target, crash_id, bucket): equal hash of the chosen frame fields, same bucket. crashes carry `lines`, frame texts after repeats are dropped.

    Function and site are cut out of the whole trace at once; for other fields each frame is parsed.
    """
    some = F.slice("lines", 1, top_n) if top_n else F.col("lines")
    if fields == ("func", "site"):
        key = places(some)
    else:
        key = F.array_join(F.transform(parse_lines(some), lambda f: F.concat_ws("|", *[F.coalesce(f[x].cast("string"), F.lit("")) for x in fields])), "\n")
    return crashes.select("target", "crash_id", F.sha2(key, 256).alias("bucket"))


def block_scores(blocks: DataFrame, by: tuple[str, ...] = (), weight: str | None = None) -> DataFrame:
    """(by..., block, in_crash, in_healthy, mi): mutual information in nats between a block's presence and the outcome. blocks: distinct (by..., run_id, block, crashed).

    by: columns that part the runs into programs of their own, such as the target. weight: a column that tells how many equal runs a run stands for.
    """
    one = F.col(weight) if weight else F.lit(1).cast("long")
    times = lambda outcome: F.sum(F.when(outcome, one).otherwise(0))
    runs = blocks.select(*by, "run_id", "crashed", *([weight] if weight else [])).distinct().groupBy(*by).agg(times(F.col("crashed")).alias("n1"), times(~F.col("crashed")).alias("n0"))
    counts = blocks.groupBy(*by, "block").agg(times(F.col("crashed")).alias("in_crash"), times(~F.col("crashed")).alias("in_healthy"))
    counts = counts.join(runs, list(by)) if by else counts.crossJoin(F.broadcast(runs))  # one row
    n = F.col("n1") + F.col("n0")

    def term(joint, row, column):
        return F.when(joint > 0, joint / n * F.log(joint * n / (row * column))).otherwise(0.0)

    a, b = F.col("in_crash"), F.col("in_healthy")
    present, absent = a + b, n - a - b
    mi = term(a, present, F.col("n1")) + term(b, present, F.col("n0")) + term(F.col("n1") - a, absent, F.col("n1")) + term(F.col("n0") - b, absent, F.col("n0"))
    return counts.select(*by, "block", "in_crash", "in_healthy", mi.alias("mi"))


def mutual_information_buckets(blocks: DataFrame, top_m: int | None = 16, min_mi: float | None = None, by: tuple[str, ...] = (), weight: str | None = None) -> DataFrame:
    """(by..., run_id, bucket): crashing runs grouped by which of the telling blocks occur in them; the top_m blocks of each program, or all of min_mi and more."""
    scored = block_scores(blocks, by, weight)
    if min_mi is not None:
        top = scored.where(F.col("mi") >= min_mi)
    elif by:
        place = F.row_number().over(Window.partitionBy(*by).orderBy(F.desc(F.round("mi", 9)), "block"))
        top = scored.withColumn("place", place).where(F.col("place") <= top_m)
    else:
        top = scored.orderBy(F.desc(F.round("mi", 9)), "block").limit(top_m)
    top, runs = top.select(*by, "block"), blocks.where("crashed").select(*by, "run_id").distinct()
    hits = blocks.where("crashed").join(F.broadcast(top) if min_mi is None and not by else top, [*by, "block"])  # top_m rows
    sign = hits.groupBy(*by, "run_id").agg(F.array_join(F.array_sort(F.collect_set("block")), ",").alias("bucket"))
    return runs.join(sign, [*by, "run_id"], "left").select(*by, "run_id", F.coalesce("bucket", F.lit("")).alias("bucket"))


def edges_of(rows: DataFrame, order: str, node: str) -> DataFrame:
    """Distinct (target, crash_id, u, v, edge): neighbouring nodes of each crash's graph."""
    nxt = F.lead(node).over(Window.partitionBy("crash_id").orderBy(order))
    return rows.select("target", "crash_id", F.col(node).alias("u"), nxt.alias("v")).where("v is not null").distinct().withColumn("edge", F.concat_ws(">", "u", "v"))


def graphs_of(features: DataFrame, feature: str = "feature") -> tuple[DataFrame, DataFrame]:
    """(graphs, members): crashes of a target with equal feature sets are one graph. graphs: target, g, f (sorted), rep, weight. members: target, g, crash_id."""
    sets = features.groupBy("target", "crash_id").agg(F.array_sort(F.collect_set(feature)).alias("f")).withColumn("g", F.sha2(F.array_join("f", "\n"), 256))
    return sets.groupBy("target", "g").agg(F.first("f").alias("f"), F.min("crash_id").alias("rep"), F.count("*").alias("weight")), sets.select("target", "g", "crash_id")


def graph_pairs(graphs: DataFrame, threshold: float, asked: DataFrame | None = None) -> DataFrame:
    """(target, g, h, similarity) of different graphs whose feature sets have a Jaccard similarity of at least the threshold (above 0).

    A graph is listed under the first |f| - ceil(t |f|) + 1 of its features, rare ones first, so features that every crash has head no list;
    graphs of a list are candidates, then compared exactly. asked: only pairs with a g out of these (target, g), both ways; else each pair once, g < h.
    """
    rows = graphs.select("target", "g", F.size("f").alias("s"), F.explode("f").alias("x"))
    often = rows.groupBy("target", "x").agg(F.count("*").alias("often"))
    place = F.row_number().over(Window.partitionBy("target", "g").orderBy("often", "x"))
    lists = rows.join(often, ["target", "x"]).withColumn("place", place).where(F.col("place") <= F.col("s") - F.ceil(F.col("s") * threshold - 1e-9) + 1).select("target", "x", "g", "s")
    left = lists if asked is None else lists.join(asked.select("target", "g"), ["target", "g"], "left_semi")
    met = left.alias("a").join(lists.alias("b"), (F.col("a.target") == F.col("b.target")) & (F.col("a.x") == F.col("b.x")) & ((F.col("a.g") < F.col("b.g")) if asked is None else (F.col("a.g") != F.col("b.g"))))
    sized = F.least("a.s", "b.s") >= F.greatest("a.s", "b.s") * threshold - 1e-9
    pairs = met.where(sized).select("a.target", "a.g", F.col("b.g").alias("h")).distinct()
    sets = graphs.select("target", "g", "f")
    both = pairs.join(sets, ["target", "g"]).join(sets.select("target", F.col("g").alias("h"), F.col("f").alias("f2")), ["target", "h"])
    common = F.size(F.array_intersect("f", "f2"))
    return both.select("target", "g", "h", (common / (F.size("f") + F.size("f2") - common)).alias("similarity")).where(F.col("similarity") >= threshold - 1e-9)


def edge_jaccard(edges: DataFrame, asked: DataFrame, threshold: float = 1e-9) -> DataFrame:
    """(target, a, b, similarity), a < b, of the asked crashes (target, crash_id) with all others at the threshold or above.

    Similarities are found between different graphs; only the asked ones are told crash by crash.
    """
    graphs, members = graphs_of(edges, "edge")
    mine = members.join(asked.select("target", "crash_id"), ["target", "crash_id"], "left_semi")
    pairs = graph_pairs(graphs, threshold, mine.select("target", "g").distinct())
    same = mine.select("target", "g").distinct().select("target", "g", F.col("g").alias("h"), F.lit(1.0).alias("similarity"))
    told = mine.select("target", "g", F.col("crash_id").alias("a")).join(pairs.union(same), ["target", "g"])
    return told.join(members.select("target", F.col("g").alias("h"), F.col("crash_id").alias("b")), ["target", "h"]).where("a < b").select("target", "a", "b", "similarity")


def wl_labels(edges: DataFrame, rounds: int = 2) -> DataFrame:
    """(target, crash_id, feature) of neighbourhood relabelling: each round a node takes the hash of its label and its followers' labels."""
    pairs = edges.select("target", "crash_id", "u", "v")
    label = pairs.select("target", "crash_id", F.explode(F.array("u", "v")).alias("node")).distinct().withColumn("label", F.md5("node"))
    out = label.select("target", "crash_id", F.col("label").alias("feature"))
    for _ in range(rounds):
        nxt = pairs.join(label.select("crash_id", F.col("node").alias("v"), F.col("label").alias("vl")), ["crash_id", "v"]).groupBy("crash_id", F.col("u").alias("node")).agg(F.array_join(F.array_sort(F.collect_set("vl")), ",").alias("around"))
        label = label.join(nxt, ["crash_id", "node"], "left").select("target", "crash_id", "node", F.md5(F.concat_ws("|", "label", F.coalesce("around", F.lit("")))).alias("label"))
        out = out.union(label.select("target", "crash_id", F.col("label").alias("feature")))
    return out.distinct()


def average_linkage(n: int, similarity: np.ndarray, threshold: float, least: int = 2) -> np.ndarray:
    """Merge the most similar clusters while they reach the threshold and more than `least` are left. The best partner of each cluster is remembered."""
    label, size, s = np.arange(n), np.ones(n), similarity.astype(float).copy()
    np.fill_diagonal(s, -1)
    alive, partner = n, s.argmax(axis=1) if n else []
    best = s[np.arange(n), partner] if n else np.zeros(0)
    while alive > least:
        i = int(best.argmax())
        if best[i] < threshold:
            break
        i, j = sorted((i, int(partner[i])))
        row = (s[i] * size[i] + s[j] * size[j]) / (size[i] + size[j])
        row[(s[i] < 0) | (s[j] < 0)] = -1  # merged ones stay out
        s[i], s[:, i] = row, row
        s[i, i] = -1
        s[j], s[:, j] = -1, -1
        size[i] += size[j]
        label[label == j] = i
        alive -= 1
        best[j] = -1
        for k in np.flatnonzero((partner == i) | (partner == j) | (s[i] >= best)):
            if best[k] >= 0 or k == i:
                partner[k] = s[k].argmax()
                best[k] = s[k, partner[k]]
    return canonical(label)


def cfg_buckets(features: DataFrame, threshold: float = 0.5) -> DataFrame:
    """(target, crash_id, bucket) from feature sets (edges or relabelled nodes): equal sets first become one graph, then average linkage per target over distinct graphs."""
    graphs, members = graphs_of(features)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rep")
        names: dict[str, int] = {}
        held = np.zeros((len(pdf), len({x for f in pdf["f"] for x in f})), dtype=np.float32)
        for i, f in enumerate(pdf["f"]):
            held[i, [names.setdefault(x, len(names)) for x in f]] = 1
        common, size = (held @ held.T).astype(np.float64), held.sum(axis=1)
        s = common / np.maximum(1, size[:, None] + size[None, :] - common)
        return pd.DataFrame({"target": pdf["target"], "g": pdf["g"], "bucket": [f"g{k}" for k in average_linkage(len(pdf), s, threshold)]})

    named = graphs.groupBy("target").applyInPandas(run, "target string, g string, bucket string")
    return members.join(named, ["target", "g"]).select("target", "crash_id", "bucket")


def fewer_clusters(first: DataFrame, second: DataFrame) -> DataFrame:
    """Per target, whichever assignment has fewer buckets; the first on a tie."""
    count = lambda d, n: d.groupBy("target").agg(F.countDistinct("bucket").alias(n))
    pick = count(first, "n1").join(count(second, "n2"), "target", "full").select("target", (F.coalesce("n2", F.lit(1 << 60)) < F.coalesce("n1", F.lit(1 << 60))).alias("use2"))
    a = first.join(pick.where("not use2").select("target"), "target", "left_semi")
    return a.unionByName(second.join(pick.where("use2").select("target"), "target", "left_semi"))


def _cut(tree: list, n: int, eps: float) -> np.ndarray:
    root = list(range(n))

    def find(a: int) -> int:
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    for a, b, d in tree:
        if d <= eps:
            root[find(a)] = find(b)
    return np.array([find(i) for i in range(n)])


def dbscan_labels(x: np.ndarray, eps: float, min_pts: int = 1) -> np.ndarray:
    """Core points within eps are linked, border points join their nearest core point, the rest is noise."""
    n = len(x)
    core = np.ones(n, dtype=bool) if min_pts <= 1 else core_distance(x, min_pts) <= eps if n >= min_pts else np.zeros(n, dtype=bool)
    label = np.full(n, NOISE)
    at = np.flatnonzero(core)
    if len(at):
        label[at] = _cut(minimum_tree(x[at]), len(at), eps)
        for p in np.flatnonzero(~core):
            d = pair_distances(x[p : p + 1], x[at])[0]
            if d.min() <= eps:
                label[p] = label[at[np.argmin(d)]]
    return canonical(label)


def dbscan(points: DataFrame, eps: float, min_pts: int = 1) -> DataFrame:
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point")
        return pd.DataFrame({"target": pdf["target"], "point": pdf["point"], "bucket": dbscan_labels(np.array(pdf["vec"].tolist(), dtype=np.float64), eps, min_pts)})

    return points.select("target", "point", "vec").groupBy("target").applyInPandas(run, ASSIGNED)


def cut_persistence(tree: list, eps: float) -> float:
    """Share of the distances up to the tree's largest edge over which the cut at eps stays the same; a cut that joins all lasts no time."""
    edges = sorted(d for _, _, d in tree)
    below, above = max((d for d in edges if d <= eps), default=0.0), min((d for d in edges if d > eps), default=edges[-1])
    return max(0.0, above - below) / edges[-1] if edges[-1] else 0.0


def dbscan_search(points: DataFrame, num_steps: int = 20) -> DataFrame:
    """The same search over cuts of the tree, chosen by validity, persistence of the cut, number of buckets."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point")
        x, index = merge_equal(np.array(pdf["vec"].tolist(), dtype=np.float64))
        lists = near_lists(x, LISTED) if len(x) > HELD else None
        tree = minimum_tree(x, lists=lists)
        label = np.zeros(len(x), dtype=np.int64)
        if tree:

            def cut(eps: float) -> tuple[np.ndarray, list[int]]:
                own = _cut(tree, len(x), eps)
                return canonical(np.where(np.bincount(own, minlength=len(x))[own] == 1, NOISE, own)), []

            found = search(cut, tree[0][2], tree[-1][2], num_steps)
            label = choose(assess(found, condense(len(x), tree), x, lasting=lambda r: cut_persistence(tree, r.epsilon), lists=lists)).label
        return pd.DataFrame({"target": pdf["target"], "point": pdf["point"], "bucket": label[index]})

    return points.select("target", "point", "vec").groupBy("target").applyInPandas(run, ASSIGNED)


def lloyd(x: np.ndarray, k: int, seed: int, rounds: int = 30) -> np.ndarray:
    """k-means from a seeded farthest-first start."""
    rng = np.random.default_rng(seed)
    centres = [x[rng.integers(len(x))]]
    d = pair_distances(x, centres[0][None])[:, 0]
    for _ in range(k - 1):
        centres.append(x[int(np.argmax(d))])
        d = np.minimum(d, pair_distances(x, centres[-1][None])[:, 0])
    c, label = np.array(centres), None
    for _ in range(rounds):
        new = (x @ c.T - (c * c).sum(axis=1) / 2).argmax(axis=1)
        if label is not None and (new == label).all():
            break
        label = new
        for j in np.unique(label):
            c[j] = x[label == j].mean(axis=0)
    return label


def kmeans_search(points: DataFrame, k_max: int = 100, seed: int = 0, min_silhouette: float = 0.0) -> DataFrame:
    """k of the best silhouette in 2..k_max; one bucket where fewer than three points or no silhouette above the least."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point")
        x, index = merge_equal(np.array(pdf["vec"].tolist(), dtype=np.float64))
        best, label = min_silhouette, np.zeros(len(x), dtype=np.int64)
        dist = pair_distances(x, x) if len(x) <= HELD else None  # once for all k
        if len(x) >= 3:
            tried = [lloyd(x, k, seed) for k in range(2, min(k_max, len(x) - 1) + 1)]
            for got, s in zip(tried, silhouettes(x, tried, dist), strict=True):
                if s > best:
                    best, label = s, got
        return pd.DataFrame({"target": pdf["target"], "point": pdf["point"], "bucket": canonical(label)[index]})

    return points.select("target", "point", "vec").groupBy("target").applyInPandas(run, ASSIGNED)


def kmeans_large(points: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """One target too large for a task: the distributed k-means."""
    x = points.select("target", "point", array_to_vector("vec").alias("features"))
    return KMeans(k=k, seed=seed).fit(x).transform(x).select("target", "point", F.col("prediction").cast("long").alias("bucket"))
