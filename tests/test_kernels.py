"""Hand-computed fixtures and invariants of the hierarchy, the search and the quality measures, without Spark."""

import hashlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from crash_bucketing.operators import baselines, hierarchy, quality
from crash_bucketing.operators.embed import HashProjectionEmbedder
from crash_bucketing.plans import search

LINE = np.array([[0.0], [1], [2], [10], [11], [30]])


def built(x):
    return hierarchy.condense(len(x), hierarchy.prim(x))


def test_hierarchy_on_a_line():
    h = built(LINE)
    assert [e[2] for e in hierarchy.prim(LINE)] == [1, 1, 1, 8, 19]
    assert [round(c.stability(), 4) for c in h.clusters] == [0.6776, 2.625, 1.75]
    assert h.chosen_by_mass() == [1, 2]
    assert hierarchy.persistence(h, [1, 2]) == 0.875
    assert [quality.bucket_count(h.hybrid(e)[0]) for e in (0, 8, 8.5, 18.9, 19, 50)] == [3, 3, 2, 2, 1, 1]
    assert quality.validity(LINE, h.hybrid(0)[0]) == pytest.approx(0.722222, abs=1e-6)


def test_search_order():
    seen = iter(range(100))
    runs = search.search(lambda eps: (np.arange(4) * next(seen), []), 0, 8, 4)
    assert [r.epsilon for r in runs] == [0, 8, 1, 4, 5, 7, 1.375, 2.5]
    assert [r.epsilon for r in search.search(lambda eps: (np.zeros(3), []), 0, 8, 4)] == [0, 8]


def test_choice():
    runs = [search.Run(0, i, np.array([i]), [], str(i), n, v, p) for i, (v, p, n) in enumerate([(0.8, 0.3, 9), (0.7, 0.5, 7), (0.66, 0.45, 5), (0.63, 0.9, 2)])]
    assert search.choose(runs).epsilon == 2


points = st.lists(st.tuples(st.integers(0, 40), st.integers(0, 40)), min_size=3, max_size=25, unique=True).map(lambda p: np.array(p, dtype=float))


@given(points, st.sampled_from(["mass", "floor"]))
@settings(max_examples=60, deadline=None)
def test_partitions_coarsen_as_epsilon_grows(x, mode):
    h = built(x)
    last = None
    for eps in np.linspace(0, 60, 25):
        label, _ = h.hybrid(eps, mode)
        if last is not None:
            assert quality.bucket_count(label) <= quality.bucket_count(last)
            for k in set(last.tolist()) - {-1}:
                assert len(set(label[last == k].tolist())) == 1
        last = label
    assert quality.bucket_count(h.hybrid(1000, mode)[0]) == 1


@given(points)
@settings(max_examples=40, deadline=None)
def test_tree_cut_is_density_clustering_and_order_does_not_matter(x):
    eps = 7.0
    got = hierarchy.canonical(baselines._cut(hierarchy.prim(x), len(x), eps))
    assert (got == baselines.dbscan_labels(x, eps, 1)).all()
    order = np.random.default_rng(0).permutation(len(x))
    a, b = built(x).hybrid(3.0)[0], built(x[order]).hybrid(3.0)[0]
    assert (hierarchy.canonical(a[order]) == hierarchy.canonical(b)).all()
    assert -1 <= quality.validity(x, a) <= 1 and 0 <= hierarchy.persistence(built(x), built(x).chosen_by_mass()) <= 1


@given(points)
@settings(max_examples=30, deadline=None)
def test_search_stays_within_all_partitions(x):
    h = built(x)
    every = {r.digest for r in search.every_partition(h)}
    runs = search.search(lambda e: h.hybrid(e), hierarchy.prim(x)[0][2], 60.0, 6)
    assert {r.digest for r in runs} <= every


def test_degenerate_inputs():
    assert built(np.zeros((0, 2))).clusters == []
    assert built(np.zeros((1, 2))).clusters[0].members == [0]
    assert hierarchy.merge_equal(np.ones((3, 2)))[1].tolist() == [0, 0, 0]
    assert quality.validity(LINE, np.zeros(6, dtype=int)) == 0


def test_a_prefix_of_a_projection_is_a_projection():
    e = HashProjectionEmbedder(3072)
    assert (e.vector("a b c", 64) == e.vector("a b c", 3072)[:64]).all()


@given(st.lists(st.tuples(st.integers(0, 30), st.integers(0, 30)), min_size=4, max_size=16, unique=True), st.integers(0, 10_000))
@settings(max_examples=60, deadline=None)
def test_validity_against_its_definition(rows, seed):
    x = np.array(rows, dtype=float)
    label = np.random.default_rng(seed).integers(-1, 3, len(x))
    names = sorted(set(label.tolist()) - {-1})
    if len(names) < 2:
        assert quality.validity(x, label) == 0
        return
    dist = lambda a, b: float(np.sqrt(((x[a] - x[b]) ** 2).sum()))
    members = {k: np.flatnonzero(label == k).tolist() for k in names}
    core, inner, sparse = {}, {}, {}
    for k, some in members.items():
        for a in some:
            others = [dist(a, b) ** -2 for b in some if b != a]  # two dimensions
            core[a] = (sum(others) / len(others)) ** -0.5 if others else 0.0
        edges = sorted((max(core[a], core[b], dist(a, b)), a, b) for i, a in enumerate(some) for b in some[i + 1 :])
        tree = hierarchy.kruskal(len(x), [(a, b, d) for d, a, b in edges])
        degree = {a: sum(a in e[:2] for e in tree) for a in some}
        inner[k] = [a for a in some if degree[a] > 1] or some
        sparse[k] = max([d for a, b, d in tree if degree[a] > 1 and degree[b] > 1] or [d for _, _, d in tree], default=0.0)
    if any(len({round(max(core[a], core[b], dist(a, b)), 9) for i, a in enumerate(m) for b in m[i + 1 :]}) < len(m) * (len(m) - 1) / 2 for m in members.values()):
        return  # equal edges leave the tree open, and with it which points are inside
    total = 0.0
    for k, some in members.items():
        apart = min(max(core[a], core[b], dist(a, b)) for j in names if j != k for a in inner[k] for b in inner[j])
        top = max(apart, sparse[k])
        total += len(some) * ((apart - sparse[k]) / top if top else 0.0)
    assert quality.validity(x, label) == pytest.approx(total / len(x))


def test_the_projection_is_a_signed_sum_over_tokens():
    e = HashProjectionEmbedder(1024, (3,), 5)
    text = "#3 0x1 in walk (node=0x5) at a.c:7\nwalk again"
    want = np.zeros(600)
    for token, n in e.tokens(text).items():
        bits = b"".join(hashlib.blake2b(token.encode(), digest_size=64, salt=b"5-%d" % b).digest() for b in range(2))
        want += np.sqrt(n) * np.array([1.0 if bits[i // 8] >> (7 - i % 8) & 1 else -1.0 for i in range(600)])
    assert e.vector(text, 600) == pytest.approx(want) and e.vector("", 64).tolist() == [0.0] * 64
    assert e.tokens(text) == e.tokens(text.replace("#3", "#4"))  # running numbers say nothing
