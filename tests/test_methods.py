"""Methods without SQL against plain versions: trees, choice, projections, baselines, neighbours, embedders, streams."""

from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from crash_bucketing.operators import baselines as base
from crash_bucketing.operators import embed as em
from crash_bucketing.operators import hierarchy as hi
from crash_bucketing.operators import neighbours as nb
from crash_bucketing.operators.collapse import label_leaks
from crash_bucketing.plans import bucketer, catalogue, search
from crash_bucketing.plans import workloads as wl
from crash_bucketing.sources import tables

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def e(spark):
    return wl.stored(wl.vectors_of(spark, "/root/testdata/sf0.01"), "e")


@pytest.fixture(scope="module")
def x(e):
    return np.array([r["vec"] for r in e.orderBy("point").select("vec").collect()])


def test_golden_trees(spark):
    golden = {"0.001": (565.722337, 1.020770, 1.198224), "0.01": (565.361534, 0.987080, 1.209722), "0.1": (2186.025953, 0.893470, 1.158087)}
    for sf, (total, low, high) in golden.items():
        r = catalogue.queries()["w13_tree_stats"](spark, f"/root/testdata/sf{sf}").first()
        assert (r["total"], r["low"], r["high"]) == pytest.approx((total, low, high), abs=5e-6)  # a sum of up to 1,999 rounded edges


def test_buckets_from_tiles_are_those_of_one_task(spark, e):
    pairs = e.withColumn("vec", F.when(F.col("point") % 50 == 1, F.array_repeat(F.lit(0.125), 64)).otherwise(F.col("vec")))  # equal vectors
    config = bucketer.Config(root_mode="floor")
    named = lambda df: sorted(map(tuple, df.select("point", "bucket").collect()))
    groups = lambda rows: sorted(sorted(p for p, k in rows if k == b) for b in {k for _, k in rows if k >= 0})
    for points in (e, pairs):
        direct, tiles = named(bucketer.bucket(points, config)), named(bucketer.bucket_any(points, config, local=100, block=120, keep=wl.stored))
        assert groups(direct) == groups(tiles) and [p for p, k in direct if k < 0] == [p for p, k in tiles if k < 0]
    assert named(bucketer.bucket(e, config, 1.1)) == named(bucketer.bucket_from_tree(e, hi.spanning_tree(e, "tiles"), config, 1.1))
    ways = bucketer.bucket_any(e.union(e.limit(30).withColumn("target", F.lit("small"))), config, local=100, exact=200, keep=wl.stored)
    assert {(r["target"], r["exact"]) for r in ways.collect()} == {("all", False), ("small", True)}


def test_runs_from_a_tree_are_those_of_one_task(e):
    config = bucketer.Config(root_mode="floor")
    direct = sorted(map(tuple, bucketer.search_runs(e, config).collect()))
    stored = sorted(map(tuple, bucketer.search_runs_from_tree(e, hi.spanning_tree(e, "tiles"), config).collect()))
    assert [r[:5] for r in direct] == [r[:5] for r in stored] and [r[5] for r in direct] == pytest.approx([r[5] for r in stored])


def test_graph_tree_spans_and_is_near_the_exact_one(e, x):
    exact = sum(d for _, _, d in hi.prim(x))
    for cell, most in ((64, 1.2), (2048, 1.0)):
        tree = hi.approximate_tree(e, cell_points=cell, keep=wl.stored).collect()
        assert len(tree) == len(x) - 1 and len(hi.kruskal(len(x), [(r["a"], r["b"], r["dist"]) for r in tree])) == len(x) - 1
        assert exact - 1e-9 <= sum(r["dist"] for r in tree) <= most * exact + 1e-9


def test_choice_in_sql_is_choice_in_memory(spark):
    rng = np.random.default_rng(4)
    runs = {t: [search.Run(0, float(i), np.array([i]), [], str(rng.integers(0, 25)), int(rng.integers(1, 9)), round(float(rng.uniform(-1 if t % 2 else 0, 0 if t % 4 == 1 else 1)), 2), round(float(rng.random()), 2)) for i in range(30)] for t in range(20)}
    for some in runs.values():  # one partition has one validity, persistence and number of buckets
        first = {}
        for r in some:
            f = first.setdefault(r.digest, r)
            r.validity, r.persistence, r.buckets = f.validity, f.persistence, f.buckets
    rows = [(str(t), r.epsilon, r.digest, r.buckets, r.validity, r.persistence) for t, some in runs.items() for r in some]
    df = spark.createDataFrame(rows, "target string, epsilon double, partition_hash string, n_buckets long, validity double, persistence double")
    assert {r["target"]: r["epsilon"] for r in search.choose_best(df).collect()} == {str(t): search.choose(some).epsilon for t, some in runs.items()}


def test_projection_and_rotation_are_those_of_numpy(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet").orderBy("vec_id").select("embedding").collect()
    v = np.array([r["embedding"] for r in rows], dtype=np.float64)
    _, _, right = np.linalg.svd(v, full_matrices=False)
    q = catalogue.queries()
    got = np.array([(r["x"], r["y"]) for r in q["p1_projection"](spark, "/root/testdata/sf0.01").orderBy("id").collect()])
    for k in (0, 1):
        want = v @ right[k] * np.sign(right[k][np.abs(right[k]).argmax()])
        assert got[:, k] == pytest.approx(want, abs=2e-6)
    turned = np.array([r["vec"] for r in q["m13_variance_rotation"](spark, "/root/testdata/sf0.01").orderBy("id").collect()])
    moments = (turned**2).sum(axis=0)
    assert (np.diff(moments) <= 1e-9).all() and np.abs(turned.T @ turned - np.diag(moments)).max() < 1e-8
    assert np.linalg.norm(turned, axis=1) == pytest.approx(np.linalg.norm(v, axis=1))


def test_neighbours_by_tiles_are_those_of_one_block(e, x):
    d = hi.pair_distances(x, x)
    np.fill_diagonal(d, np.inf)
    q = e.where("point % 3 = 0")
    for block in (4096, 70):
        got = {(r["query"], r["point"]): r["dist"] for r in nb.knn(e, q, 3, block).collect()}
        want = {(i, int(j)): d[i, j] for i in range(0, len(x), 3) for j in np.lexsort((np.arange(len(x)), d[i]))[:3]}
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)
        assert nb.within(e, q, 1.2, block).count() == int((d[::3] <= 1.2).sum())
        r = nb.distance_range(e, block).first()
        assert (r["low"], r["high"], r["pairs"]) == pytest.approx((d.min(), d[np.isfinite(d)].max(), len(x) * (len(x) - 1) / 2))


@pytest.mark.parametrize("sf", ["0.01", "0.1"])
def test_recall_of_the_index(spark, sf):
    points = wl.stored(wl.vectors_of(spark, f"/root/testdata/sf{sf}"), "points")
    asked = points.where("point % 10 = 0")
    exact = {(r["query"], r["point"]) for r in nb.knn(points, asked, 10).collect()}
    found = {(r["query"], r["point"]) for r in nb.knn_approximate(points, asked, 10, chunk=200).collect()}
    assert len(exact & found) / len(exact) >= 0.9


def test_average_linkage_against_a_plain_version():
    def plain(n, s, threshold):
        groups = [[i] for i in range(n)]
        while len(groups) > 2:
            best, i, j = max((np.mean([s[a][b] for a in p for b in q]), -i, -j) for i, p in enumerate(groups) for j, q in enumerate(groups) if i < j)
            if best < threshold:
                break
            groups[-i] += groups.pop(-j)
        label = np.zeros(n, dtype=int)
        for k, g in enumerate(groups):
            label[g] = k
        return hi.canonical(label)

    rng = np.random.default_rng(2)
    for _ in range(60):
        n = int(rng.integers(1, 12))
        s = rng.random((n, n))
        s, t = (s + s.T) / 2, rng.random()
        assert (base.average_linkage(n, s, t) == plain(n, s, t)).all()


def test_graph_pairs_are_all_pairs_at_the_threshold(spark):
    rng = np.random.default_rng(6)
    sets = [frozenset(rng.choice(14, rng.integers(1, 9), replace=False).tolist()) for _ in range(80)]
    rows = [("t", i, f"e{k}") for i, s in enumerate(sets) for k in s]
    graphs, members = base.graphs_of(spark.createDataFrame(rows, "target string, crash_id long, feature string"))
    graphs = wl.stored(graphs, "graphs")
    name = {r["crash_id"]: r["g"] for r in members.collect()}
    of = {name[i]: s for i, s in enumerate(sets)}
    like = lambda a, b: len(a & b) / len(a | b)
    for t in (0.3, 0.6, 1e-9):
        want = {(g, h): like(of[g], of[h]) for g in of for h in of if g < h and like(of[g], of[h]) >= max(t, 1e-6)}
        got = {(r["g"], r["h"]): r["similarity"] for r in base.graph_pairs(graphs, t).collect()}
        assert got == pytest.approx(want)


def test_relabelling_against_a_plain_version(spark):
    import hashlib

    md5 = lambda s: hashlib.md5(s.encode()).hexdigest()
    paths = {1: "abcab", 2: "abd", 3: "abcab"}
    rows = [("t", i, k, n) for i, p in paths.items() for k, n in enumerate(p)]
    got = defaultdict(set)
    for r in base.wl_labels(base.edges_of(spark.createDataFrame(rows, "target string, crash_id long, pos int, node string"), "pos", "node"), 2).collect():
        got[r["crash_id"]].add(r["feature"])
    for i, p in paths.items():
        label, seen = {n: md5(n) for n in p}, set()
        seen |= set(label.values())
        for _ in range(2):
            label = {n: md5(f"{label[n]}|" + ",".join(sorted({label[b] for a, b in zip(p, p[1:], strict=False) if a == n}))) for n in label}
            seen |= set(label.values())
        assert got[i] == seen


def test_cut_persistence_and_density_search(spark):
    line = [(0, 1, 1.0), (1, 2, 1.0), (2, 3, 8.0), (3, 4, 1.0), (4, 5, 19.0)]
    assert [base.cut_persistence(line, eps) for eps in (0.5, 1.0, 7.9, 8.0, 19.0)] == pytest.approx([1 / 19, 7 / 19, 7 / 19, 11 / 19, 0])
    rows = [("t", i, [float(v), 0.0]) for i, v in enumerate([0, 1, 2, 10, 11, 30])]
    got = {r["point"]: r["bucket"] for r in base.dbscan_search(spark.createDataFrame(rows, "target string, point long, vec array<double>")).collect()}
    assert got[0] == got[1] == got[2] != got[3] == got[4]


def test_kmeans_against_all_partitions_of_a_line(spark):
    values = [0.0, 0.1, 0.2, 5.0, 5.1, 9.0, 9.2]
    points = spark.createDataFrame([("t", i, [v, 0.0]) for i, v in enumerate(values)], "target string, point long, vec array<double>")
    got = {r["point"]: r["bucket"] for r in base.kmeans_search(points).collect()}
    assert [got[i] for i in range(7)] == [0, 0, 0, 1, 1, 2, 2]
    large = {r["point"]: r["bucket"] for r in base.kmeans_large(points, 3).collect()}
    assert len({large[0], large[3], large[5]}) == 3 and large[0] == large[1] == large[2] and large[3] == large[4] and large[5] == large[6]


def test_leaf_selection_takes_the_leaves():
    x = np.array([[0.0], [1], [2.5], [3.5], [20], [21]])
    h = hi.condense(len(x), hi.prim(x))
    assert h.hybrid(0, start="leaf")[0].tolist() == [0, 0, 1, 1, 2, 2]
    assert h.hybrid(1.6, start="leaf")[0].tolist() == [0, 0, 0, 0, 1, 1]


def test_embedders_by_store_and_by_batches(spark):
    texts = spark.createDataFrame([(f"h{i}", "x" * i) for i in range(20)], "hash string, text string")
    ready = spark.createDataFrame([(f"h{i}", [float(i)] * 5) for i in range(25)], "hash string, vec array<double>")
    got = {r["hash"]: r["vec"] for r in em.StoredEmbedder(ready).embed(texts, 3).collect()}
    assert got == {f"h{i}": [float(i)] * 3 for i in range(20)}
    sent = spark.sparkContext.accumulator(0)
    over = spark.sparkContext.accumulator(0)

    def submit(batch, items):  # a fake service: counts what it is sent, and batches that are too large
        sent.add(len(items))
        over.add(int(len(items) > 4 or sum(len(t) for _, t in items) > 60))

    remote = em.BatchProviderEmbedder(submit, lambda: ready, max_rows=4, max_bytes=40)
    assert remote.embed(texts, 2).count() == 25 and sent.value == 20 and over.value == 0


def test_leaks_in_blocks_are_those_of_contains(spark):
    texts = ["a label-1 here", "label-11 and label-2", "", None, "nothing", "label-2label-3"]
    prepared = spark.createDataFrame([(i, t, t and t[::-1]) for i, t in enumerate(texts)], "crash_id long, full string, coarse string")
    labels = spark.createDataFrame([("label-1",), ("label-11",), ("label-2",), ("label-3",), ("1-lebal",), ("",), (None,), ("label-2",)], "label string")
    want = sorted((i, s, k) for i, t in enumerate(texts) if t for s, u in (("full", t), ("coarse", t[::-1])) for k in ("label-1", "label-11", "label-2", "label-3", "1-lebal") if k in u)
    for how in ({}, {"block_labels": 2}, {"block_bytes": 10}):
        assert sorted(map(tuple, label_leaks(prepared, labels, ["full", "coarse"], **how).collect())) == want


def test_mutual_information_of_programs_apart(spark):
    rows = [(p, i, b, i < 4) for p in ("s", "t") for i in range(8) for b in (["k", "o"] if i in (0, 1, 2, 4) else ["o", "z"])]
    blocks = spark.createDataFrame(rows, "target string, run_id long, block string, crashed boolean")
    one = {r["block"]: r["mi"] for r in base.block_scores(blocks.where("target = 's'").drop("target")).collect()}
    for r in base.block_scores(blocks, ("target",)).collect():
        assert r["mi"] == pytest.approx(one[r["block"]])
    got = {(r["target"], r["run_id"]): r["bucket"] for r in base.mutual_information_buckets(blocks, 1, by=("target",)).collect()}
    assert got == {(p, i): "k" if i < 3 else "" for p in ("s", "t") for i in range(4)}


def test_the_workflow_wins_on_the_planted_corpus(spark):
    scores = {r["method"]: r for r in catalogue.queries()["w5_comparison_mean"](spark, SF).collect()}
    assert set(scores) == set(wl.METHODS) and scores["workflow"]["f_measure"] == max(r["f_measure"] for r in scores.values())
    # stack hashing splits bugs and joins none
    assert scores["stack_hash"]["purity"] == 100 and scores["stack_hash"]["inverse_purity"] == min(r["inverse_purity"] for r in scores.values())


def test_stream_equals_batch_and_files_come_back(spark, tmp_path):
    assert catalogue.queries()["w14_stream_equals_batch"](spark, SF).first()["different"] == 0
    crashes = spark.createDataFrame([("one", 1, "#0 a\n#1 b"), ("one", 2, "x\n"), ("two", 1, "")], "target string, crash_id long, trace string")
    tables.write_trace_files(crashes, f"{tmp_path}/written")
    got = sorted(map(tuple, tables.read_trace_files(spark, f"{tmp_path}/written", **tables.WRITTEN).collect()))
    assert got == [("1", "one", "#0 a\n#1 b"), ("1", "two", ""), ("2", "one", "x\n")]
    (tmp_path / "plain" / "t1").mkdir(parents=True)
    (tmp_path / "plain" / "t1" / "c7.txt").write_text("#0 f ()\n#1 g ()")
    assert tuple(tables.read_trace_files(spark, f"{tmp_path}/plain").first()) == ("c7", "t1", "#0 f ()\n#1 g ()")


def test_medoids_lie_nearest_to_the_mean(spark):
    rows = [("t", b, i, [v, 0.0]) for i, (b, v) in enumerate([(0, 0.0), (0, 1.0), (0, 5.0), (1, 7.0), (1, 9.0), (2, 3.0)])]
    df = spark.createDataFrame(rows, "target string, bucket long, point long, vec array<double>")
    got = {r["bucket"]: r["point"] for r in nb.representatives(df, df, "medoid").collect()}
    assert got == {0: 1, 1: 3, 2: 5}  # on a tie the least point


def test_costs_add_up(spark):
    cost = {r["counter"]: r["value"] for r in catalogue.queries()["a12_costs"](spark, SF).collect()}
    assert cost["crashes"] == spark.read.parquet(f"{SF}/orders.parquet").count() and cost["points"] <= cost["crashes"]
    assert cost["embedded_again"] == 0 and cost["store_hits_again"] == cost["texts"] <= cost["text_references"] <= 3 * cost["points"]
    assert cost["selections_made"] + cost["selections_spared"] == 2 * bucketer.Config().num_steps * 5 and cost["partitions_assessed"] <= cost["selections_made"]


def test_arrived_points_hold_all_crashes(spark):
    got = {r["target"]: r["n_crashes"] for r in catalogue.queries()["w14_arrived_buckets"](spark, SF).collect()}
    assert got == {r["o_orderpriority"]: r["count"] for r in spark.read.parquet(f"{SF}/orders.parquet").groupBy("o_orderpriority").count().collect()}
