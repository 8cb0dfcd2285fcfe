"""The near-copy stage against the components of all pairs."""

import random
from itertools import combinations

import numpy as np
import pytest

from crash_bucketing.llm import common, near_copies

VOCAB = [f"w{i}" for i in range(400)]


def components_of_all_pairs(texts):
    """The least index of each component of the graph of all pairs at 0.8, over sets of five-word shingles."""
    sets, names = [], {}
    for t in texts:
        w = t.split()
        sets.append({names.setdefault(tuple(w[i : i + 5]), len(names)) for i in range(max(len(w) - 4, min(len(w), 1)))})
    root = list(range(len(texts)))

    def find(a):
        while root[a] != a:
            root[a] = root[root[a]]
            a = root[a]
        return a

    for i, j in combinations(range(len(texts)), 2):
        if find(i) != find(j) and 5 * (both := len(sets[i] & sets[j])) >= 4 * (len(sets[i]) + len(sets[j]) - both):
            a, b = sorted((find(i), find(j)))
            root[b] = a
    return sorted({find(i) for i in range(len(texts))})


def kept(spark, texts):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    return sorted(r["doc_id"] for r in near_copies.keep_one_of_each(docs).collect())


def edited(rng, words, most):
    out = list(words)
    for i in rng.sample(range(len(out)), rng.randint(1, most)):
        out[i] = rng.choice(VOCAB)
    return " ".join(out)


def test_texts_of_the_same_words_in_another_order(spark):
    rng = random.Random(21)
    lines = [[rng.choice(VOCAB) for _ in range(12)] for _ in range(12)]
    texts = []
    for _ in range(30):  # each order of the lines is another text; its copy has two neighbouring words exchanged
        words = [w for line in rng.sample(lines, len(lines)) for w in line]
        i = rng.randrange(140)
        texts += [" ".join(words), " ".join([*words[:i], words[i + 1], words[i], *words[i + 2 :]])]
    want = components_of_all_pairs(texts)
    assert len(want) <= 30
    assert kept(spark, texts) == want


def test_a_large_family_of_edits(spark):
    rng = random.Random(22)
    base = [rng.choice(VOCAB) for _ in range(150)]
    texts = [edited(rng, base, 6) for _ in range(300)]
    assert kept(spark, texts) == components_of_all_pairs(texts)


@pytest.mark.parametrize("pivots, common", [(8, 50_000), (2, 0)])
def test_families_that_share_a_common_passage(spark, monkeypatch, pivots, common):
    """common = 0: every list is met in one task, none as the list of a common shingle."""
    monkeypatch.setattr(near_copies, "PIVOTS", pivots)
    monkeypatch.setattr(near_copies, "COMMON", common)
    rng = random.Random(23)
    passage = [rng.choice(VOCAB) for _ in range(60)]
    bases = [passage + [rng.choice(VOCAB) for _ in range(rng.randint(5, 60))] for _ in range(60)]
    texts = [edited(rng, rng.choice(bases), 4) for _ in range(300)] + ["", "one two", "one two three four five"]
    assert kept(spark, texts) == components_of_all_pairs(texts)


def test_prefixes_of_like_sets_meet():
    rng = np.random.default_rng(24)
    for _ in range(300):
        x = np.unique(rng.integers(0, 1 << 62, rng.integers(1, 60), dtype=np.uint64))
        y = np.unique(np.r_[x[rng.random(len(x)) > 0.1], rng.integers(0, 1 << 62, rng.integers(0, 6), dtype=np.uint64)])
        common = np.unique(rng.choice(x, 5))
        counts = rng.integers(3, 9, len(common))
        if len(np.intersect1d(x, y)) >= 0.8 * len(np.union1d(x, y)):
            assert len(np.intersect1d(near_copies.prefix(x, 0.8, common, counts), near_copies.prefix(y, 0.8, common, counts)))


def test_written_tables_leave_no_shuffle_files(spark):
    held = lambda: spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ").split("shuffle_")
    before = len(held())
    wide = spark.range(20_000).repartition(4, "id")
    for _ in range(3):
        common.cut(wide)
    assert len(held()) <= before
    assert spark.conf.get(common.CLEANUP) == "false"
