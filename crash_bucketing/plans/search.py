"""Search for the distance floor, and the choice among its clusterings."""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.hierarchy import NOISE, Hierarchy, condense, pair_distances, persistence
from ..operators.quality import HELD, Neighbourhood, bucket_count, validity

TOP, TOLERANCE = 10, 0.2


@dataclass
class Run:
    turn: int
    epsilon: float
    label: np.ndarray
    selected: list[int]
    digest: str
    buckets: int
    validity: float = float("nan")
    persistence: float = float("nan")


def digest(label: np.ndarray) -> str:
    return hashlib.sha256(np.ascontiguousarray(label, dtype="<i8").tobytes()).hexdigest()


def search(at: Callable[[float], tuple[np.ndarray, list[int]]], low: float, high: float, num_steps: int = 20) -> list[Run]:
    """Runs in order of evaluation. An interval whose ends give one partition is left alone (partitions only coarsen with epsilon);
    else two shorter ones wait in line, set in by a step from the middle and from the ends."""
    if num_steps < 2:
        raise ValueError("num_steps must be at least 2")
    runs: list[Run] = []
    waiting, turn = [(low, high)], 0
    while waiting and turn < num_steps:
        a, b = waiting.pop(0)
        ends = []
        for eps in (a, b):
            label, selected = at(eps)
            ends.append(Run(turn, eps, label, selected, digest(label), bucket_count(label)))
        runs += ends
        turn += 1
        if ends[0].digest != ends[1].digest:
            half = (b - a) / 2
            step, middle = half / num_steps, a + half
            waiting += [(x, y) for x, y in ((a + step, middle), (middle + step, b - step)) if x < y]
    return runs


def partitions(h: Hierarchy, root_mode: str = "mass") -> Iterator[tuple[int, float, np.ndarray, list[int]]]:
    """(turn, epsilon, label, selected) of the partitions in order of epsilon, each time that one may differ from the one before."""
    for i, eps, label, selected in changes(h, root_mode):
        yield i, eps, label, sorted(selected)


def changes(h: Hierarchy, root_mode: str = "mass", share: int = 0, shares: int = 1) -> Iterator[tuple[int, float, np.ndarray, set[int]]]:
    """The same, of every `shares`-th of them; the set is told anew from one to the next.

    Partitions change at birth and exit distances only; between two marks nothing is computed unless a selected cluster was born below epsilon
    or the root is selected and loses a point to noise. Only clusters that give way are looked at, and only their points are named again.
    """
    marks = sorted({0.0, *(c.birth for c in h.clusters if np.isfinite(c.birth)), *(d for c in h.clusters for _, _, d in c.left)})
    points = sorted({*marks, *((a + b) / 2 for a, b in zip(marks, marks[1:], strict=False)), (marks[-1] if marks else 0) * 2 + 1})
    away = sorted((d, start, size) for start, size, d in h.clusters[0].left) if h.clusters else []
    # each point has the least point of its bucket, or n for noise; least points are numbered in order
    least, lead, first, back, told = {}, np.full(h.n, h.n), np.zeros(h.n + 1, dtype=np.int64), 0, 0
    selected: set[int] = set()
    births: list[tuple[float, int]] = []

    def take(i: int, start: int, size: int) -> None:
        some = h.clusters[i].order[start : start + size]
        first[lead[some[lead[some] < h.n]]] = 0
        least[i] = min(least.get(i, h.n), int(some.min()))
        lead[some] = least[i]

    def pick(i: int) -> None:
        selected.add(i)
        heapq.heappush(births, (h.clusters[i].birth, i))
        if i:
            take(i, h.clusters[i].start, h.clusters[i].size)
            first[least[i]] = 1

    for i in h.chosen_by_mass(root_mode):
        pick(i)
    before = None
    for turn, eps in enumerate(points):
        while births and births[0][0] < eps:
            i = heapq.heappop(births)[1]
            if i not in selected:
                continue
            up = i
            while h.clusters[up].birth < eps:
                up = h.clusters[up].parent
            selected.remove(i)
            if up not in selected:
                pick(up)
        if 0 in selected:
            start = back
            while back < len(away) and away[back][0] <= eps:
                back += 1
            if back > start:
                first[least.get(0, h.n)] = 0
                for _, at, size in away[start:back]:
                    before_it = least.get(0)
                    take(0, at, size)
                    if before_it is not None and least[0] != before_it:
                        lead[lead == before_it] = least[0]
                first[least[0]] = 1
        now = (len(selected), births[0][0] if births else np.inf, back if 0 in selected else -1)
        if now != before:
            before = now
            told += 1
            if (told - 1) % shares == share:
                number = np.cumsum(first)
                number -= 1
                number[h.n] = NOISE
                yield turn, eps, number[lead], selected


#: Tasks that share the partitions of a target.
SHARES = 24


def enumerated(tree: DataFrame, root_mode: str = "mass", shares: int = SHARES) -> DataFrame:
    """(target, epsilon, partition_hash, n_buckets) of each partition that any epsilon can reach, the first of equal ones. tree: as of `placed_tree`.

    Each task goes through all changes of the hierarchy, and labels every `shares`-th.
    """

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        real = pdf[pdf["a"] != pdf["b"]]
        h = condense(int(pdf["b"].max()) + 1, sorted(zip(real["a"].tolist(), real["b"].tolist(), real["dist"].tolist(), strict=True), key=lambda e: (e[2], e[0], e[1])))
        found: dict[str, tuple] = {}  # one label at a time is held
        for turn, eps, label, _ in changes(h, root_mode, int(key[1]), shares):
            if (name := digest(label)) not in found:
                found[name] = (key[0], turn, eps, name, bucket_count(label))
        return pd.DataFrame(list(found.values()), columns=["target", "turn", "epsilon", "partition_hash", "n_buckets"])

    dealt = tree.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1)))).repartition(4 * shares, "target", "share")
    told = dealt.groupBy("target", "share").applyInPandas(run, "target string, turn long, epsilon double, partition_hash string, n_buckets long")
    first = told.groupBy("target", "partition_hash").agg(F.min(F.struct("turn", "epsilon", "n_buckets")).alias("x"))
    return first.select("target", "x.epsilon", "partition_hash", "x.n_buckets")


def every_partition(h: Hierarchy, root_mode: str = "mass") -> list[Run]:
    """Each partition that any epsilon can reach."""
    out: dict[str, Run] = {}
    for i, eps, label, selected in partitions(h, root_mode):
        out.setdefault(key := digest(label), Run(i, eps, label, selected, key, bucket_count(label)))
    return list(out.values())


def assess(runs: list[Run], h: Hierarchy, x: np.ndarray, at: np.ndarray | None = None, lasting: Callable[[Run], float] | None = None, lists: tuple[np.ndarray, np.ndarray] | None = None) -> list[Run]:
    """Validity and persistence, once for each different partition.

    x: the points, or those at the positions `at` (a sample, on which validity is then measured). lasting: another persistence than that of the selected clusters. lists: near
    lists of x, if they are known.
    """
    known: dict[str, tuple[float, float]] = {}
    clusters: dict[bytes, tuple] = {}
    dist = pair_distances(x, x) if len(x) <= HELD else None
    own = lambda r: r.label if at is None else r.label[at]
    around = None
    if dist is None:
        around = Neighbourhood(x, lists)
        around.learn([own(r) for r in {r.digest: r for r in runs}.values()])
    for r in runs:
        if r.digest not in known:
            known[r.digest] = validity(x, own(r), dist, clusters, around), lasting(r) if lasting else persistence(h, r.selected)
        r.validity, r.persistence = known[r.digest]
    return runs


def choose(runs: list[Run], top: int = TOP, tolerance: float = TOLERANCE) -> Run:
    """The same as choose_best, for one target's runs in memory."""
    seen: dict[str, Run] = {}
    for r in sorted(runs, key=lambda r: r.epsilon):
        seen.setdefault(r.digest, r)
    rows = sorted(seen.values(), key=lambda r: (-r.validity, -r.persistence, r.epsilon))[:top]
    best = rows[0].validity
    rows = [r for r in rows if r.validity >= best - tolerance * abs(best)]
    lasting = max(r.persistence for r in rows)
    rows = [r for r in rows if r.persistence >= lasting - tolerance * abs(lasting)]
    return min(rows, key=lambda r: (r.buckets, -r.validity, -r.persistence, r.epsilon))


def choose_best(runs: DataFrame, top: int = TOP, tolerance: float = TOLERANCE, keep_repeats: bool = False) -> DataFrame:
    """One run per target. runs: (target, epsilon, partition_hash, n_buckets, validity, persistence).

    At most `top` best by validity and within the tolerance of the best; of these, within the tolerance of the most persistent; of
    these, the one with fewest buckets. Ties: validity, persistence, smaller epsilon.
    """
    t = Window.partitionBy("target")
    order = [F.desc("validity"), F.desc("persistence"), F.asc("epsilon")]
    if not keep_repeats:
        runs = runs.withColumn("_copy", F.row_number().over(Window.partitionBy("target", "partition_hash").orderBy("epsilon"))).where("_copy = 1").drop("_copy")
    step1 = runs.withColumn("_rank", F.row_number().over(t.orderBy(*order))).withColumn("_best", F.max("validity").over(t)).where((F.col("_rank") <= top) & (F.col("validity") >= F.col("_best") - tolerance * F.abs("_best")))
    step2 = step1.withColumn("_most", F.max("persistence").over(t)).where(F.col("persistence") >= F.col("_most") - tolerance * F.abs("_most"))
    return step2.withColumn("_pick", F.row_number().over(t.orderBy(F.asc("n_buckets"), *order))).where("_pick = 1").drop("_rank", "_best", "_most", "_pick")
