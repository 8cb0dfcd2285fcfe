"""Quality of a clustering: density-based validity, silhouette, bucket counts."""

from __future__ import annotations

import numpy as np

from .hierarchy import GROWN, NOISE, minimum_tree, pair_distances
from .near import LISTED, edge_lengths, least_apart, near_lists, rough_distances, within


def bucket_count(label: np.ndarray) -> int:
    """Clusters, each noise point counting as one of its own."""
    return int((label == NOISE).sum() + len(np.unique(label[label != NOISE])))


#: Up to so many points all distances of a target are held at once (128 MB).
HELD = 4096


def all_points_core(x: np.ndarray, dist: np.ndarray | None = None) -> np.ndarray:
    """Inverse of the mean inverse distance to the power of the dimension, within one cluster, in logarithms."""
    n = len(x)
    if n < 2:
        return np.zeros(n)
    if n > HELD and dist is None:
        return cores_of(x, [np.arange(n)])[0]
    return np.concatenate([_core_of_rows(x, np.arange(a, min(n, a + 512)), np.arange(n), dist) for a in range(0, n, 512)])


def _core_of_rows(x: np.ndarray, rows: np.ndarray, at: np.ndarray, dist: np.ndarray | None = None) -> np.ndarray:
    """The same for some rows of the cluster `at`."""
    dim = x.shape[1]
    with np.errstate(divide="ignore"):
        logs = -dim * np.log(dist[rows] if dist is not None else pair_distances(x[rows], x[at]))
    logs[rows[:, None] == at[None, :]] = -np.inf
    top = logs.max(axis=1)
    with np.errstate(invalid="ignore"):
        total = np.where(np.isinf(top), top, top + np.log(np.exp(logs - np.where(np.isinf(top), 0, top)[:, None]).sum(axis=1)))
    return np.exp(-(total - np.log(len(at) - 1)) / dim)


def families(n: int, clusters: list[np.ndarray]) -> list[list[int]]:
    """Numbers of clusters, those together that share points, straight or through others."""
    of, out = np.full(n, -1), {}
    for i in sorted(range(len(clusters)), key=lambda i: -len(clusters[i])):
        met = [int(f) for f in np.unique(of[clusters[i]]) if f >= 0]
        out[i] = [i, *(k for f in met for k in out.pop(f))]
        of[np.isin(of, met)] = i
        of[clusters[i]] = i
    return list(out.values())


#: Rows and columns of a block of distances, 4 MB.
ROWS, COLUMNS = 256, 2048


def cores_of(x: np.ndarray, clusters: list[np.ndarray]) -> list[np.ndarray]:
    """all_points_core of each of many clusters (positions, two or more each), in which a pair's distance is computed once however many hold it: points
    that the same clusters hold stand together, and a cluster's sums are those of such stretches. Memory is linear in the points."""
    out: list[np.ndarray] = [np.zeros(0)] * len(clusters)
    for family in families(len(x), clusters):
        every = np.unique(np.concatenate([clusters[i] for i in family]))
        held = np.zeros((len(family), len(every)), dtype=bool)
        for k, i in enumerate(family):
            held[k, np.searchsorted(every, clusters[i])] = True
        _, kind = np.unique(np.packbits(held, axis=0), axis=1, return_inverse=True)
        order = np.argsort(kind.ravel(), kind="stable")
        every, held = every[order], held[:, order]
        inside = held[:, np.flatnonzero(np.r_[True, np.diff(kind.ravel()[order]) != 0])]
        core = np.concatenate([some for _, some in core_rows(x[every], kind.ravel()[order], inside, np.arange(0, len(every), ROWS))], axis=1)
        for k, i in enumerate(family):
            mine = np.argsort(every[held[k]], kind="stable")
            out[i] = core[k, held[k]][mine]
    return out


def core_rows(x: np.ndarray, kind: np.ndarray, inside: np.ndarray, starts: np.ndarray):
    """(start, core (clusters, rows)) of the ROWS points from each start. Points stand by kind 0, 1, ...; inside (clusters, kinds): whether a cluster holds
    a kind. Cores of points outside a cluster mean nothing."""
    n, dim = x.shape
    c = x - x.mean(axis=0)
    norm = (c * c).sum(axis=1)
    left, right = np.hstack([-2 * c, np.ones((n, 1)), norm[:, None]]), np.vstack([c.T, norm, np.ones(n)])
    sizes, short = inside @ np.bincount(kind, minlength=inside.shape[1]), 2e-4 * norm.max(initial=0.0)
    held = np.empty(ROWS * COLUMNS)
    for a in starts:
        m = min(ROWS, n - a)
        scale, total = np.full(m, np.inf), np.zeros((m, inside.shape[1]))  # sums are kept in units of the nearest so far
        for b in range(0, n, COLUMNS):
            w = min(COLUMNS, n - b)
            d = np.matmul(left[a : a + m], right[:, b : b + w], out=held[: m * w].reshape(m, w))
            near = d.min(axis=1)
            for i in np.flatnonzero(near < short):  # products lose digits of short distances
                j = np.flatnonzero(d[i] < short)
                d[i, j] = ((x[a + i] - x[b + j]) ** 2).sum(axis=1)
                if b <= a + i < b + w:
                    d[i, a + i - b] = np.inf
                near[i] = d[i].min()
            with np.errstate(divide="ignore", invalid="ignore", over="ignore", under="ignore"):
                low = np.minimum(scale, near)
                total *= np.where(np.isinf(scale), 0.0, (low / scale) ** (dim / 2))[:, None]
                scale = low
                np.log(d, out=d)
                d -= np.log(scale)[:, None]
                d *= -dim / 2
                np.exp(d, out=d)
            first = np.flatnonzero(np.r_[True, np.diff(kind[b : b + w]) != 0])
            total[:, kind[b + first]] += np.add.reduceat(d, first, axis=1)
        with np.errstate(divide="ignore", invalid="ignore"):
            whole = inside.astype(float) @ total.T
            core = np.sqrt(scale) * np.exp(-(np.log(whole) - np.log(sizes - 1)[:, None]) / dim)
        # a neighbour far nearer than a cluster's own points, or equal points, hide their sum: these rows are looked at alone
        for k, i in zip(*np.nonzero(~(whole > 1e-200) & inside[:, kind[a : a + m]]), strict=True):
            core[k, i] = _core_of_rows(x, np.array([a + i]), np.flatnonzero(inside[k, kind]))[0]
        yield a, core


def large_clusters(label: np.ndarray, least: int) -> list[np.ndarray]:
    """Positions of each cluster of more than `least` points, of a clustering of two or more clusters."""
    names, sizes = np.unique(label[label != NOISE], return_counts=True)
    return [np.flatnonzero(label == k) for k in names[sizes > least]] if len(names) > 1 else []


class Neighbourhood:
    """What clusterings of the same many points share: near lists, and cores of their large clusters."""

    def __init__(self, x: np.ndarray, lists: tuple[np.ndarray, np.ndarray] | None = None):
        self.x, self.lists, self.core = x, near_lists(x, LISTED) if lists is None else lists, {}

    def learn(self, labels: list[np.ndarray]) -> None:
        """Cores of the clusters that are too large to be looked at one by one."""
        new = {at.tobytes(): at for label in labels for at in large_clusters(label, GROWN)}
        new = {k: at for k, at in new.items() if k not in self.core}
        self.core |= zip(new, cores_of(self.x, list(new.values())), strict=True)


def _inner(x: np.ndarray, at: np.ndarray, dist: np.ndarray | None, around: Neighbourhood | None) -> tuple[float, np.ndarray, np.ndarray]:
    """Of a cluster: its largest inner edge, its internal points and their cores."""
    if len(at) == 2 and dist is None:  # one edge
        d = float(edge_lengths(x, at[:1], at[1:])[0])
        return d, at, np.full(2, d)
    own = dist[np.ix_(at, at)] if dist is not None else pair_distances(x[at], x[at]) if len(at) <= GROWN else None
    core = around.core.get(at.tobytes()) if around and own is None else None
    core = all_points_core(x[at], own) if core is None else core
    a, b, d = (np.array(c) for c in zip(*minimum_tree(x[at], core, own, within(around.lists, at) if around and own is None else None), strict=True)) if len(at) > 1 else (np.zeros(0, dtype=np.int64),) * 3
    degree = np.bincount(np.r_[a, b], minlength=len(at))
    both = (degree[a] > 1) & (degree[b] > 1)
    some = degree > 1 if (degree > 1).any() else np.ones(len(at), dtype=bool)
    return float((d[both] if both.any() else d).max(initial=0.0)), at[some], core[some]


def validity(x: np.ndarray, label: np.ndarray, dist: np.ndarray | None = None, known: dict | None = None, around: Neighbourhood | None = None) -> float:
    """Density-based validity in [-1, 1]; noise only weighs; fewer than two clusters score 0. dist: all distances, if held. known: what is told of clusters
    of the same points, kept from one clustering to the next, as is what lies around them."""
    known = {} if known is None else known
    names, sizes = np.unique(label[label != NOISE], return_counts=True)
    if len(names) < 2:
        return 0.0
    if around is None and dist is None and len(x) > HELD:
        (around := Neighbourhood(x)).learn([label])
    inner, cores, sparse = [], [], np.zeros(len(names))
    order = np.argsort(label, kind="stable")
    ends = np.searchsorted(label[order], names, side="right")
    for i, at in enumerate(order[end - size : end] for end, size in zip(ends, sizes, strict=True)):
        if (key := at.tobytes()) not in known:
            known[key] = _inner(x, at, dist, around)
        sparse[i], points, core = known[key]
        inner.append(points)
        cores.append(core)
    # least reachability from the internal points of each cluster to those of any other
    every, core = np.concatenate(inner), np.concatenate(cores)
    owner = np.repeat(np.arange(len(names)), [len(i) for i in inner])
    if around is not None:
        apart = least_apart(x[every], core, owner, within(around.lists, every))
    else:
        apart = np.full(len(names), np.inf)
        for a in range(0, len(every), 512):  # a block of rows at a time
            rows = every[a : a + 512]
            d = dist[np.ix_(rows, every)] if dist is not None else pair_distances(x[rows], x[every])
            d = np.maximum(np.maximum(d, core[a : a + 512, None]), core[None, :])
            d[owner[a : a + 512, None] == owner[None, :]] = np.inf
            np.minimum.at(apart, owner[a : a + 512], d.min(axis=1))
    top = np.maximum(apart, sparse)
    each = np.where(top > 0, (apart - sparse) / np.where(top > 0, top, 1), 0.0)
    return float((sizes * each).sum() / len(x))


def silhouette(x: np.ndarray, label: np.ndarray, dist: np.ndarray | None = None) -> float:
    """Mean of (b - a) / max(a, b) with Euclidean distances; a point alone in its cluster has 0. dist: all distances, if held."""
    return silhouettes(x, [label], dist)[0]


def silhouettes(x: np.ndarray, labels: list[np.ndarray], dist: np.ndarray | None = None) -> list[float]:
    """The same of several clusterings; each distance is computed once for all."""
    named, totals = [np.unique(label, return_inverse=True)[1] for label in labels], [0.0] * len(labels)
    sizes = [np.bincount(index) for index in named]
    for a in range(0, len(x), 512):
        d = dist[a : a + 512] if dist is not None else rough_distances(x[a : a + 512], x)
        for k, (index, size) in enumerate(zip(named, sizes, strict=True)):
            if len(size) < 2:
                continue
            sums = d @ np.eye(len(size))[index]
            own = index[a : a + 512]
            rows = np.arange(len(own))
            near = sums[rows, own] / np.maximum(size[own] - 1, 1)
            means = sums / size
            means[rows, own] = np.inf
            far = means.min(axis=1)
            top = np.maximum(near, far)
            totals[k] += np.where((size[own] > 1) & (top > 0), (far - near) / np.where(top > 0, top, 1), 0).sum()
    return [float(t / len(x)) if len(x) else 0.0 for t in totals]
