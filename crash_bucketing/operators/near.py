"""Exact near neighbours and spanning trees of one target's points by matrix products.

Products in single precision only tell which pairs may matter, with a bound on their rounding; every distance that counts is computed again
coordinate by coordinate, so results are those of all pairs. Memory is linear in the points.
"""

from __future__ import annotations

import numpy as np

#: Neighbours listed for each point; rows and columns of a block of products (4 MB).
LISTED, ROWS, COLUMNS = 12, 512, 2048
#: Distances summed at once (256 kB, which stays in the cache).
HANDY = 1 << 15


def pair_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Euclidean, coordinate by coordinate in fixed order, so that a pair has one distance in every block."""
    out, step = np.zeros((len(x), len(y))), max(1, HANDY // max(1, len(y)))
    columns = np.ascontiguousarray(y.T)
    for a in range(0, len(x), step):
        rows, some = x[a : a + step], out[a : a + step]
        for j in range(x.shape[1]):
            d = rows[:, j, None] - columns[j]
            d *= d
            some += d
    return np.sqrt(out, out=out)


def rough_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The same by matrix products, to ten digits or so; short ones, where products lose digits, are computed as above."""
    middle = y.mean(axis=0)
    a, b = x - middle, y - middle
    p, q = (a * a).sum(axis=1)[:, None], (b * b).sum(axis=1)[None, :]
    out = a @ b.T
    out *= -2
    out += p
    out += q
    i, j = np.nonzero(out < 1e-4 * (p.max(initial=0.0) + q.max(initial=0.0)))
    for s in range(0, len(i), 1 << 18):
        r, c = i[s : s + (1 << 18)], j[s : s + (1 << 18)]
        out[r, c] = ((x[r] - y[c]) ** 2).sum(axis=1)
    return np.sqrt(out, out=out)


def edge_lengths(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances of the pairs (a, b), summed as in pair_distances: a pair has one distance everywhere."""
    out = np.zeros(len(a))
    for j in range(x.shape[1]):
        d = x[a, j] - x[b, j]
        out += d * d
    return np.sqrt(out)


class Products:
    """Squared distances but for rounding: `block` gives those of some rows to some columns, in units of `unit`, wrong by `err` at most."""

    def __init__(self, x: np.ndarray):
        c = x - x.mean(axis=0)
        norm = (c * c).sum(axis=1)
        self.unit = float(norm.max(initial=0.0)) or 1.0
        c /= np.sqrt(self.unit)
        self.own = (norm / self.unit).astype(np.float32)
        self.left = np.hstack([-2 * c, np.ones((len(x), 1))]).astype(np.float32)
        self.right = np.vstack([c.T, norm / self.unit]).astype(np.float32)
        # inputs, products and sums rounded to 24 bits; norms are 1 at most
        self.err = 8 * (x.shape[1] + 8) * 2.0**-24

    def block(self, rows: slice | np.ndarray, columns: slice) -> np.ndarray:
        return self.left[rows] @ self.right[:, columns] + self.own[rows, None]


def _true(flags: np.ndarray) -> np.ndarray:
    """Places of few true ones among many flags: eight are looked at as one."""
    if len(flags) % 8:
        return np.flatnonzero(flags)
    words = np.flatnonzero(flags.view(np.uint64))
    k = np.flatnonzero(flags.reshape(-1, 8)[words])
    return words[k >> 3] * 8 + (k & 7)


def near_lists(x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions (n, k), bound (n)): k other points for each, the nearest but for rounding; no point that is not listed is nearer than the bound."""
    n = len(x)
    k, p = min(k, n - 1), Products(x)
    at, bound = np.empty((n, k), dtype=np.int64), np.empty(n)
    held, less = np.empty(ROWS * COLUMNS, dtype=np.float32), np.empty(ROWS * COLUMNS, dtype=bool)
    for a in range(0, n, ROWS):
        m = min(ROWS, n - a)
        own, best, where = np.arange(m), np.full((m, k), np.inf, dtype=np.float32), np.zeros((m, k), dtype=np.int64)
        for c in range(0, n, COLUMNS):
            w = min(COLUMNS, n - c)
            # a row's own norm shifts all its distances alike: it is added to the bound only
            d = np.matmul(p.left[a : a + m], p.right[:, c : c + w], out=held[: m * w].reshape(m, w))
            here = own[(a + own >= c) & (a + own < c + w)]
            d[here, a + here - c] = np.inf
            if w > 4 * k and not c:
                where = np.argpartition(d, k - 1, axis=1)[:, :k]
                best = np.take_along_axis(d, where, axis=1)
                order = np.argsort(best, axis=1, kind="stable")
                best, where = np.take_along_axis(best, order, axis=1), np.take_along_axis(where, order, axis=1)
                continue
            np.less(d, best[:, -1:], out=less[: m * w].reshape(m, w))
            i, j = np.divmod(_true(less[: m * w]), w)
            if not len(i):
                continue
            rows = np.unique(i)
            row = np.concatenate([np.repeat(rows, k), i])
            value, place = np.concatenate([best[rows].ravel(), d[i, j]]), np.concatenate([where[rows].ravel(), j + c])
            order = np.lexsort((value, row))
            row, value, place = row[order], value[order], place[order]
            first = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
            pick = first[:, None] + np.arange(k)
            best[rows], where[rows] = value[pick], place[pick]
        at[a : a + m] = where
        bound[a : a + m] = np.sqrt(np.maximum(0.0, best[:, -1].astype(np.float64) + p.own[a : a + m] - 2 * p.err) * p.unit)
    if k == n - 1:
        bound[:] = np.inf
    return at, bound


def kth_distance(x: np.ndarray, k: int) -> np.ndarray:
    """Distance of each point to the k-th nearest other (the last, if there are fewer)."""
    n = len(x)
    at, bound = near_lists(x, k + LISTED)
    k = min(k, n - 1)
    out = np.empty(n)
    for a in range(0, n, 8192):
        some = np.arange(a, min(n, a + 8192))
        d = edge_lengths(x, np.repeat(some, at.shape[1]), at[some].ravel()).reshape(len(some), -1)
        out[some] = np.partition(d, k - 1, axis=1)[:, k - 1]
    for i in np.flatnonzero(out > bound):  # rounding hides which ones are nearest: all are looked at
        d = edge_lengths(x, np.full(n, i), np.arange(n))
        d[i] = np.inf
        out[i] = np.partition(d, k - 1)[k - 1]
    return out


def _outgoing(x: np.ndarray, core: np.ndarray, label: np.ndarray, asked: np.ndarray, length: dict[int, tuple[float, int, int]], p: Products, low: np.ndarray | None = None) -> None:
    """Least edges that leave the components of the asked points, put into `length` (component: length, a, b), where shorter ones may be known. low: of each
    point, what no edge of it that leaves its component is shorter than; raised for the asked ones. It holds on while components grow."""
    n = len(x)
    core2 = (core**2 / p.unit).astype(np.float32)  # only tells which edge to try first
    for s in range(0, len(asked), ROWS):
        rows = asked[s : s + ROWS]
        mine, nearest = label[rows], np.full(len(rows), np.inf)

        def told(i: np.ndarray, j: np.ndarray) -> None:
            if not len(i):
                return
            a, b = rows[i], j
            d = np.maximum(edge_lengths(x, a, b), np.maximum(core[a], core[b]))
            a, b, comp = np.minimum(a, b), np.maximum(a, b), mine[i]
            order = np.lexsort((b, a, d, comp))
            a, b, d, comp = a[order], b[order], d[order], comp[order]
            for t in np.flatnonzero(np.r_[True, comp[1:] != comp[:-1]]):
                key = (float(d[t]), int(a[t]), int(b[t]))
                if key < length.get(int(comp[t]), (np.inf, 0, 0)):
                    length[int(comp[t])] = key

        for c in range(0, n, COLUMNS):
            d = p.block(rows, slice(c, c + COLUMNS))
            w = d.shape[1]
            d[mine[:, None] == label[None, c : c + w]] = np.inf
            reach = np.maximum(np.maximum(d, core2[None, c : c + w]), core2[rows, None]) if core.any() else d
            least = reach.argmin(axis=1)
            np.minimum(nearest, reach[np.arange(len(rows)), least], out=nearest)
            some = np.flatnonzero(np.isfinite(reach[np.arange(len(rows)), least]))
            if not len(some):
                continue
            top = np.array([length.get(int(k), (np.inf,))[0] for k in mine])
            close = some[reach[some, least[some]] <= (top[some] ** 2) / p.unit + 2 * p.err]
            told(close, least[close] + c)
            top = np.array([length.get(int(k), (np.inf,))[0] for k in mine])
            ok = d <= (top**2 / p.unit + 2 * p.err).astype(np.float32)[:, None]
            if core.any():  # a core distance is exact: no edge of one that is not shorter can be shorter
                ok &= (core[rows] < top)[:, None] & (core[None, c : c + w] < top[:, None])
            i, j = np.divmod(np.flatnonzero(ok), w)
            told(i, j + c)
        if low is not None:
            low[rows] = np.maximum(low[rows], np.sqrt(np.maximum(0.0, nearest - 2 * p.err) * p.unit) * (1 - 1e-6))


def within(lists: tuple[np.ndarray, np.ndarray], at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Near lists of the points `at` among themselves, from those of all points; -1 stands for a point that is not among them."""
    place = np.full(len(lists[0]), -1)
    place[at] = np.arange(len(at))
    return place[lists[0][at]], lists[1][at]


def listed_pairs(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different pairs a < b of near lists."""
    n = len(at)
    a, b = np.repeat(np.arange(n), at.shape[1]), at.ravel()
    a, b = a[b >= 0], b[b >= 0]
    pairs = np.unique(np.minimum(a, b) * n + np.maximum(a, b))
    return pairs // n, pairs % n


def least_apart(x: np.ndarray, core: np.ndarray, label: np.ndarray, lists: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Least reachability from the points of each label 0, 1, ... to those of any other. lists: near lists of the points among themselves.

    It is that of a listed pair if no point of the label could have a shorter one to a point that is not listed; the others are compared with all.
    """
    a, b = listed_pairs(lists[0])
    a, b = a[cross := label[a] != label[b]], b[cross]
    d = np.maximum(edge_lengths(x, a, b), np.maximum(core[a], core[b]))
    known = np.full(label.max() + 1, np.inf)
    np.minimum.at(known, label[a], d)
    np.minimum.at(known, label[b], d)
    asked = np.flatnonzero(np.maximum(lists[1], core) < known[label])
    if len(asked):
        length = {int(k): (float(known[k]), -1, -1) for k in np.flatnonzero(np.isfinite(known))}
        _outgoing(x, core, label, asked[np.argsort(label[asked], kind="stable")], length, Products(x))
        for k, v in length.items():
            known[k] = v[0]
    return known


def tree_by_lists(x: np.ndarray, core: np.ndarray | None = None, lists: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a, b, length) of a minimum spanning tree, a < b, by length, a, b. core: reachability, the largest of distance and both core distances. lists: near
    lists of the points among themselves, if they are known.

    Components take their least edge until one is left. It is among the edges of the near lists if it is no longer than the bounds of all points of the
    component; where the lists can not tell that, the points in question (but for those of the largest component) are compared with all. Of equal edges the first by (a, b)
    counts; with core distances, where many are equal, any.
    """
    n, cores = len(x), np.zeros(len(x)) if core is None else core
    at, bound = near_lists(x, LISTED) if lists is None else lists
    a, b = listed_pairs(at)
    d = np.maximum(edge_lengths(x, a, b), np.maximum(cores[a], cores[b]))
    order = np.lexsort((b, a, d))
    a, b, d = a[order], b[order], d[order]
    low, label, out, products = np.maximum(bound, cores), np.arange(n), [], None
    while True:
        names, label = np.unique(label, return_inverse=True)
        m = len(names)
        if m == 1:
            break
        cross = label[a] != label[b]
        a, b, d = a[cross], b[cross], d[cross]
        best, place = np.full(m, len(d)), np.arange(len(d))
        for side in (a, b):  # edges stand in order: the last one written is the first of its component
            first = np.full(m, len(d))
            first[label[side][::-1]] = place[::-1]
            best = np.minimum(best, first)
        least = np.full(m, np.inf)
        np.minimum.at(least, label, low)
        known = np.r_[d, np.inf][best]
        sure = (known < least) if core is None else (known <= least) & (best < len(d))
        chosen = [(float(d[e]), int(a[e]), int(b[e])) for e in np.unique(best[sure])]
        if not chosen:
            products = products or Products(x)
            sizes = np.bincount(label)
            length = {int(k): (float(d[e]), int(a[e]), int(b[e])) for k, e in enumerate(best) if e < len(d)}
            large = int(sizes.argmax())
            asked = np.flatnonzero((label != large) & (low <= known[label]))  # the others have no shorter edge than the known one
            _outgoing(x, cores, label, asked[np.argsort(label[asked], kind="stable")], length, products, low)
            chosen = sorted({v for k, v in length.items() if k != large})
        root = np.arange(m)

        def find(k: int) -> int:
            while root[k] != k:
                root[k] = root[root[k]]
                k = root[k]
            return k

        for edge in sorted(chosen):
            u, v = find(int(label[edge[1]])), find(int(label[edge[2]]))
            if u != v:
                root[max(u, v)] = min(u, v)
                out.append(edge)
        label = np.array([find(k) for k in range(m)])[label]
    out.sort()
    d, a, b = (np.array(c) for c in zip(*out, strict=True)) if out else (np.zeros(0), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64))
    return a, b, d
