"""Ways for many points against the plain ones."""

import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from crash_bucketing.operators import baselines, near
from crash_bucketing.operators import hierarchy as hi
from crash_bucketing.operators import measures as ms
from crash_bucketing.operators import quality as qu
from crash_bucketing.plans import bucketer as bu
from crash_bucketing.plans import search
from crash_bucketing.plans import workloads as wl
from crash_bucketing.sources import corpus
from crash_bucketing.streaming import arrivals as st


def shapes():
    rng = np.random.default_rng(31)
    centres = rng.standard_normal((5, 8)) * 50
    yield rng.standard_normal((600, 8))
    yield centres[rng.integers(0, 5, 600)] + rng.standard_normal((600, 8)) * 0.1
    yield rng.integers(0, 6, (500, 3)).astype(float)
    yield 1e6 + rng.standard_normal((500, 4)) * 1e-2
    yield np.cumsum(rng.random((600, 1)), axis=0)


@pytest.mark.parametrize("rows, columns", [(512, 2048), (100, 150)])
def test_trees_and_core_distances_by_lists(monkeypatch, rows, columns):
    monkeypatch.setattr(near, "ROWS", rows)
    monkeypatch.setattr(near, "COLUMNS", columns)
    for x in shapes():
        for m_pts in (1, 2, 5):
            core = hi.core_distance(x, m_pts)
            a, b, d = near.tree_by_lists(x, core if m_pts > 1 else None)
            assert (a < b).all() and np.array_equal(d, [e[2] for e in hi.prim(x, core)])
            assert len(hi.kruskal(len(x), zip(a.tolist(), b.tolist(), d.tolist(), strict=True))) == len(x) - 1
            if m_pts > 1:
                assert np.array_equal(near.kth_distance(x, m_pts - 1), core)


def test_a_chain_of_clusters_is_kept_by_stretches():
    """Clusters inside clusters: their members, listed one by one, would be some 60 million."""
    n = 20_000
    pairs = np.repeat(np.arange(n // 2) * 10.0 + np.linspace(0, 4, n // 2) ** 2, 2) + np.tile([0, 0.5], n // 2)
    edges = sorted(((i, i + 1, float(pairs[i + 1] - pairs[i])) for i in range(n - 1)), key=lambda e: (e[2], e[0]))
    h = hi.condense(n, edges)
    assert len(h.clusters) > n // 2 and h.clusters[0].size == n
    assert sorted(h.clusters[0].exits) == h.clusters[0].members == list(range(n))
    assert sum(len(c.left) for c in h.clusters) <= 2 * n


def test_fixed_density_holds_no_table_of_all_pairs(monkeypatch):
    x = np.random.default_rng(32).standard_normal((400, 2))
    want = baselines.dbscan_labels(x, 0.3, 3)
    monkeypatch.setattr(hi, "GROWN", 100)
    assert np.array_equal(baselines.dbscan_labels(x, 0.3, 3), want)
    assert np.array_equal(baselines.dbscan_labels(x, 0.3), hi.canonical(baselines._cut(hi.prim(x), len(x), 0.3)))


def test_partitions_are_named_only_where_they_change():
    x = np.random.default_rng(33).standard_normal((300, 4))
    h = hi.condense(len(x), hi.prim(x))
    for mode in ("mass", "floor"):
        told = [search.digest(label) for _, _, label, _ in search.partitions(h, mode)]
        assert len(told) <= 2 * len(set(told))
        for r in search.every_partition(h, mode):
            assert np.array_equal(r.label, h.hybrid(r.epsilon, mode)[0])


def test_many_blocks_are_few_tiles(spark):
    x = np.random.default_rng(34).standard_normal((120, 3))
    points = spark.createDataFrame([("t", i, v.tolist()) for i, v in enumerate(x)], "target string, point long, vec array<double>")
    got = hi.spanning_tree(points, "tiles", blocks=1000)
    assert sorted((r["dist"], r["a"], r["b"]) for r in got.collect()) == [(d, a, b) for a, b, d in hi.prim(x)]


def test_methods_over_equal_stacks_once(spark):
    """Rows that stand for several crashes give the tables of all crashes."""
    sf = "/root/testdata/sf0.001"
    every = wl.stored(wl.named(spark, sf), "named")
    rows = wl.shapes(spark, sf)
    assert rows.count() < every.count() / 4 and rows.agg({"n": "sum"}).first()[0] == every.count()
    for method in wl.METHODS:
        assert sorted(wl.method_cells(rows, method).collect()) == sorted(wl.method_cells(every, method).collect())


def test_sliding_windows_take_times_to_the_second(spark, tmp_path):
    """As the SQL does: half a second before noon counts as noon; a window that ends after the last event stays open."""
    rows = [("2024-01-01 03:00:00", "a"), ("2024-01-01 11:59:59.7", "a"), ("2024-01-01 11:59:59.4", "b"), ("2024-01-02 11:59:59.6", "b")]
    events = spark.createDataFrame([(i, t, 1, k, 0.0, "{}") for i, (t, k) in enumerate(rows)], "event_id long, ts string, user_id long, event_type string, value double, props string")
    events.withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(f"{tmp_path}/parts")
    shutil.copy(next(tmp_path.glob("parts/*.parquet")), tmp_path / "events.parquet")
    got = {(r["start"], r["event_type"], r["n"]) for r in st.sliding(spark, str(tmp_path)).collect()}
    assert got == {("2023-12-31 12", "a", 1), ("2023-12-31 12", "b", 1), ("2024-01-01 00", "a", 2), ("2024-01-01 00", "b", 1)}


def test_validity_and_silhouette_of_many_points(monkeypatch):
    rng = np.random.default_rng(35)
    for x in shapes():
        label = rng.integers(-1, 4, len(x))
        want = qu.validity(x, label), qu.silhouette(x, label, hi.pair_distances(x, x)), bu.furthest(x)
        with monkeypatch.context() as m:
            m.setattr(qu, "HELD", 50)
            m.setattr(bu, "HELD", 50)
            assert np.allclose(want[:2], (qu.validity(x, label), qu.silhouette(x, label)), atol=1e-6) and bu.furthest(x) == want[2]


def test_written_traces_need_no_folder_each(spark, tmp_path):
    """Names with any sign come back, rows of a crash share a file, and folders are as many as the parts of a target."""
    from crash_bucketing.sources import tables

    rows = [("de en", f"id {i}/{i}%2F.txt", f"#0 f{i}\n\n") for i in range(300)] + [("_x", ".h", None), ("_x", "twice", "a"), ("_x", "twice", "a")]
    assert tables.write_trace_files(spark.createDataFrame(rows, "target string, crash_id string, trace string"), f"{tmp_path}/w") == 302
    folders = [p for p in (tmp_path / "w").glob("*/*") if p.is_dir()]
    assert len(folders) <= 2 * tables.PARTS and all(f.suffix == ".txt" for p in folders for f in p.iterdir())
    got = {(r["target"], r["crash_id"]): r["trace"] for r in tables.read_trace_files(spark, f"{tmp_path}/w", **tables.WRITTEN).collect()}
    assert got == {("de en", f"id {i}/{i}%2F.txt"): f"#0 f{i}\n" + "\n" for i in range(300)} | {("_x", ".h"): "", ("_x", "twice"): "a\na"}
    assert tables.write_trace_files(spark.createDataFrame([], "target string, crash_id string, trace string"), f"{tmp_path}/none") == 0
    assert tables.read_trace_files(spark, f"{tmp_path}/none", **tables.WRITTEN).isEmpty()


def test_blocks_are_roomy_and_the_choice_by_mass_is_kept(spark, monkeypatch):
    """More blocks than can be are asked for: blocks are large then. The search asks for the choice by mass once."""
    assert [hi.blocks_for(n, 100) for n in (50, 500, 1600, 102_564, 10_000_000)] == [2, 5, 16, 7, 16]
    x = np.random.default_rng(7).standard_normal((90, 6))
    h = hi.condense(90, hi.minimum_tree(x))
    first = h.chosen_by_mass("floor")
    monkeypatch.setattr(hi.Cluster, "stability", lambda self: pytest.fail("computed again"))
    assert h.chosen_by_mass("floor") == first and h.hybrid(0.5, "floor")[1] == h.raised(first, 0.5)


def test_flags_by_words_and_distances_by_rows(monkeypatch):
    rng = np.random.default_rng(3)
    for n in (0, 8, 13, 4096):
        flags = rng.random(n) < 0.05
        assert near._true(flags).tolist() == np.flatnonzero(flags).tolist()
    x = rng.standard_normal((70, 9))
    whole = near.pair_distances(x, x[:50])
    monkeypatch.setattr(near, "HANDY", 100)
    assert np.array_equal(near.pair_distances(x, x[:50]), whole) and np.array_equal(near.edge_lengths(x, np.arange(50), np.arange(50)), np.diag(whole[:50]))


def test_equal_crashes_are_parsed_once_and_differences_are_counted(spark, monkeypatch):
    """Rows are those of the plain way, with missing texts, ids that several rows have, and more kinds than may be shared; each kind is parsed once."""
    kind = "crash_id long, target string, trace string, report string"
    rows = [(i, f"t{i % 2}", f"#0 f{i % 5} (a)\n#1 main ()", None if i % 3 else "ERROR: x\nSUMMARY: x") for i in range(60)] + [(70, "t0", None, None), (71, "t1", None, "r")]
    crashes, parsed, plain = spark.createDataFrame(rows, kind), [], st._digests
    monkeypatch.setattr(st, "_digests", lambda df: parsed.append(df.count()) or plain(df))
    both = lambda df: (sorted(map(str, st.digests_once(df).collect())), sorted(map(str, plain(df).collect())))
    once, each = both(crashes)
    assert once == each and parsed == [12]
    doubled = crashes.unionAll(spark.createDataFrame([(0, "t9", "#0 other ()", None)], kind))
    once, each = both(doubled)
    assert once == each
    assert st.apart(plain(doubled), plain(crashes)).first()["different"] == 1
    assert st.apart(plain(crashes), plain(crashes.union(crashes.limit(2)))).first()["different"] == 2
    assert st.apart(plain(crashes.limit(0)), plain(crashes.limit(0))).first()["different"] == 0
    monkeypatch.setattr(st, "SHARED", 3)
    once, each = both(crashes)
    assert once == each


def test_cores_of_nested_clusters_come_from_one_look_at_each_pair(monkeypatch):
    """Clusters that share points, far and near ones, equal points; blocks that end within a cluster."""
    monkeypatch.setattr(qu, "ROWS", 50)
    monkeypatch.setattr(qu, "COLUMNS", 70)
    rng = np.random.default_rng(36)
    some = np.r_[rng.standard_normal((150, 64)), rng.standard_normal((150, 64)) * 1e-7]
    for x in (*shapes(), some, np.r_[some, some[:5]]):
        n = len(x)
        clusters = [np.arange(0, 100), np.arange(0, n, 2), np.arange(120, n), np.r_[0, n - 1], np.arange(101, 119)]
        for at, got in zip(clusters, qu.cores_of(x, clusters), strict=True):
            assert np.allclose(got, qu.all_points_core(x[at], hi.pair_distances(x[at], x[at])), rtol=1e-6)
    assert sorted(map(sorted, qu.families(200, clusters[:1] + [np.arange(90, 120), np.arange(150, 160)]))) == [[0, 1], [2]]


def test_a_search_over_many_points_shares_lists_and_cores(monkeypatch):
    """The same runs as from all distances; near lists are made once and each core pass covers all partitions."""
    x = np.random.default_rng(37).standard_normal((700, 5))
    h = hi.condense(len(x), tree := hi.prim(x))
    runs = lambda: search.search(lambda eps: h.hybrid(eps, "floor"), tree[0][2], bu.furthest(x))
    want = [(r.digest, r.validity) for r in search.assess(runs(), h, x)]
    made, plain = [], qu.cores_of
    monkeypatch.setattr(qu, "cores_of", lambda x, clusters: made.append(len(clusters)) or plain(x, clusters))
    for module, name, size in ((qu, "HELD", 50), (search, "HELD", 50), (qu, "GROWN", 20)):
        monkeypatch.setattr(module, name, size)
    got = search.assess(runs(), h, x, lists=near.near_lists(x, near.LISTED))
    assert [r.digest for r in got] == [d for d, _ in want] and len(made) == 1 and made[0] > 2
    assert np.allclose([r.validity for r in got], [v for _, v in want])


def test_least_reachability_by_lists():
    rng = np.random.default_rng(38)
    for x in shapes():
        label = np.sort(np.unique(rng.integers(0, 9, len(x)), return_inverse=True)[1])
        core = rng.random(len(x)) * np.median(hi.pair_distances(x[:50], x))
        d = np.maximum(np.maximum(hi.pair_distances(x, x), core), core[:, None])
        d[label == label[:, None]] = np.inf
        assert np.array_equal(near.least_apart(x, core, label, near.near_lists(x, 3)), [d[label == k].min() for k in range(label.max() + 1)])


def test_partitions_are_named_step_by_step_and_shared_out(spark):
    """Each label is that of the plain choice at its epsilon; shares together are the whole, the first of equal partitions stands."""
    rng = np.random.default_rng(39)
    rows = []
    for t, x in (("one", rng.standard_normal((1, 3))), ("grid", rng.integers(0, 4, (60, 3)).astype(float)), ("many", rng.standard_normal((200, 3)))):
        x, _ = hi.merge_equal(x)
        rows += [(t, 10 * i, v.tolist()) for i, v in enumerate(x)]
        h = hi.condense(len(x), hi.prim(x))
        for mode in ("mass", "floor"):
            whole = [(turn, eps, search.digest(label)) for turn, eps, label, _ in search.changes(h, mode)]
            assert all(name == search.digest(h.hybrid(eps, mode)[0]) for _, eps, name in whole)
            assert sorted((turn, eps, search.digest(label)) for k in range(3) for turn, eps, label, _ in search.changes(h, mode, k, 3)) == whole
    points = spark.createDataFrame(rows, "target string, point long, vec array<double>")
    got = search.enumerated(hi.placed_tree(points), "floor", 3)
    want = set()
    for t in ("one", "grid", "many"):
        x = np.array([v for name, _, v in rows if name == t])
        want |= {(t, r.epsilon, r.digest, r.buckets) for r in search.every_partition(hi.condense(len(x), hi.prim(x)), "floor")}
    assert {(r["target"], r["epsilon"], r["partition_hash"], r["n_buckets"]) for r in got.collect()} == want


def test_size_decides_about_the_way_and_not_about_the_buckets(spark, monkeypatch):
    """Beyond every size at which the ways once began to sample, and with a search whose choice a sample changes; equal points, missing vectors, a target of one point."""
    rng = np.random.default_rng(40)
    x = np.r_[rng.standard_normal((4400, 2)), rng.standard_normal((300, 2)) * 0.01 + 4]
    x[4000:4040] = x[:40]
    rows = [("t", i, v.tolist()) for i, v in enumerate(x)] + [("t", 9000, None), ("one", 1, [1.0, 2.0]), ("none", 5, None)]
    points = wl.stored(spark.createDataFrame(rows, "target string, point long, vec array<double>"), "points")
    config = bu.Config(root_mode="floor")
    rows_of = lambda df: sorted(map(tuple, df.select("target", "point", "bucket", "epsilon").collect()))
    by_tiles = bu.bucket_any(points, config, local=0, block=1000, keep=wl.stored)
    assert rows_of(by_tiles) == rows_of(bu.bucket_any(points, config)) == rows_of(bu.bucket(points, config))
    assert {r["exact"] for r in by_tiles.select("exact").distinct().collect()} == {True}
    # however many points there are, no way is approximate unless the caller says so
    monkeypatch.setattr(bu, "approximate_tree", lambda *a, **k: pytest.fail("approximate"))
    huge = points.where("target = 'one'").withColumn("point", F.explode(F.sequence(F.lit(1), F.lit(1_000_002)))).withColumn("point", F.col("point").cast("long"))
    assert "exact" in bu.bucket_any(huge, config).columns


def test_a_point_that_was_compared_with_all_is_not_asked_in_vain(monkeypatch):
    """Dense groups whose lists hold only their own: a point's least edge out of its component is a bound for later rounds."""
    rng = np.random.default_rng(41)
    x = np.repeat(rng.standard_normal((12, 4)) * 10, 40, axis=0) + rng.standard_normal((480, 4)) * 0.01
    asked, plain = [], near._outgoing
    monkeypatch.setattr(near, "_outgoing", lambda *a: asked.append(len(a[3])) or plain(*a))
    a, b, d = near.tree_by_lists(x)
    assert np.array_equal(d, [e[2] for e in hi.prim(x)]) and len(asked) > 1, asked
    low, label = np.zeros(480), np.repeat(np.arange(12), 40)
    plain(x, np.zeros(480), label, np.arange(480), {}, near.Products(x), low)
    out = np.where(label[:, None] == label, np.inf, hi.pair_distances(x, x)).min(axis=1)
    assert (low <= out).all() and np.allclose(low, out, rtol=1e-2)


def test_type_reports_of_all_methods_are_those_of_each(spark, monkeypatch):
    """Labels are scored once for all methods."""
    rng = np.random.default_rng(42)
    rows = {(m, f"t{rng.integers(2)}", f"l{rng.integers(6)}", f"b{rng.integers(8)}"): int(rng.integers(1, 9)) for m in ("workflow", *wl.METHODS) for _ in range(15)}
    cells = wl.stored(spark.createDataFrame([(*k, n) for k, n in rows.items()], "method string, target string, label string, bucket string, n long"), "cells")
    types = spark.createDataFrame([(f"l{i}", f"k{i % 3}", f"p{i % 2}") for i in range(6)] + [("l0", "k1", "p0")], "label string, type string, parent string")
    want = []
    for m in ("workflow", *wl.METHODS):
        own = ms.type_report(ms.label_scores(cells.where(F.col("method") == m).drop("method")), types)
        want += [(m, *r) for r in own.collect()]
    scored, plain = [], ms.label_scores
    monkeypatch.setattr(ms, "label_scores", lambda cells: scored.append(1) or plain(cells))
    got = wl.method_type_reports(cells, types)
    key = lambda r: tuple(round(x, 9) if isinstance(x, float) else x for x in r)
    assert sorted(map(key, got.collect())) == sorted(map(key, want)) and len(scored) == 1


def test_crashes_are_rendered_by_many_tasks(spark):
    """Few bytes of orders make many bytes of text: they are not left to one task, and rows stay as the SQL has them."""
    sf = "/root/testdata/sf0.001"
    got = corpus.planted(spark, sf)
    per = got.groupBy(F.spark_partition_id().alias("p")).agg(F.count("trace").alias("n")).collect()
    assert len(per) == 4 and max(r["n"] for r in per) < got.count() / 2
    plain = corpus.register(spark, sf, "orders", "lineitem").sql(corpus.planted_sql())
    assert got.exceptAll(plain).isEmpty() and plain.exceptAll(got).isEmpty()
