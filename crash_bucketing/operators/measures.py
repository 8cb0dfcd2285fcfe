"""Accuracy measures from one contingency table, and cost counters. assign: (target, crash_id, bucket); truth: (target, crash_id, label)."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F


def contingency(assign: DataFrame, truth: DataFrame, weight: str | None = None) -> DataFrame:
    """(target, label, bucket, n): the only scan of crashes; everything else is over its non-zero cells. weight: of truth, how many crashes a row stands for."""
    return assign.join(truth, ["target", "crash_id"]).groupBy("target", "label", "bucket").agg((F.sum(weight) if weight else F.count("*")).alias("n"))


def precision_recall(cells: DataFrame) -> DataFrame:
    """Per cell: sizes, precision, recall, F."""
    b, y = Window.partitionBy("target", "bucket"), Window.partitionBy("target", "label")
    sized = cells.withColumn("bucket_size", F.sum("n").over(b)).withColumn("label_size", F.sum("n").over(y))
    return sized.withColumn("precision", F.col("n") / F.col("bucket_size")).withColumn("recall", F.col("n") / F.col("label_size")).withColumn("f", 2 * F.col("n") / (F.col("bucket_size") + F.col("label_size")))


def purity(cells: DataFrame) -> DataFrame:
    total = cells.groupBy("target").agg(F.sum("n").alias("t"))
    best = cells.groupBy("target", "bucket").agg(F.max("n").alias("m")).groupBy("target").agg(F.sum("m").alias("m"))
    return best.join(total, "target").select("target", (F.col("m") / F.col("t")).alias("purity"))


def inverse_purity(cells: DataFrame) -> DataFrame:
    return purity(cells.select("target", F.col("bucket").alias("label"), F.col("label").alias("bucket"), "n")).withColumnRenamed("purity", "inverse_purity")


def f_measure(cells: DataFrame) -> DataFrame:
    per = precision_recall(cells).groupBy("target", "label").agg(F.max("f").alias("f"), F.max("label_size").alias("s"))
    return per.groupBy("target").agg((F.sum(F.col("f") * F.col("s")) / F.sum("s")).alias("f_measure"))


def bucket_counts(cells: DataFrame) -> DataFrame:
    return cells.groupBy("target").agg(F.countDistinct("label").alias("n_bugs"), F.countDistinct("bucket").alias("n_buckets"))


def score(assign: DataFrame, truth: DataFrame, over: str = "crashes", exclude: list[str] | None = None) -> DataFrame:
    """One row per target: n_bugs, n_buckets, purity, inverse_purity, f_measure. over='points': copies count once (assign and truth by point)."""
    cells = contingency(assign, truth)
    if exclude:
        cells = cells.where(~F.col("target").isin(exclude))
    if over == "points":
        cells = cells.withColumn("n", F.lit(1))
    return score_cells(cells)


def score_cells(cells: DataFrame) -> DataFrame:
    """The same from a contingency table."""
    out = bucket_counts(cells)
    for m in (purity, inverse_purity, f_measure):
        out = out.join(m(cells), "target")
    return out


def overcounting(cells: DataFrame) -> DataFrame:
    """Buckets that a label touches beyond the first."""
    return cells.groupBy("target", "label").agg((F.count("*") - 1).alias("over"))


def undercounting(cells: DataFrame) -> DataFrame:
    """Other labels that share a bucket with a label; labels per bucket are few, crashes never appear."""
    sets = cells.groupBy("target", "bucket").agg(F.collect_set("label").alias("others"))
    pairs = cells.select("target", "bucket", "label").join(sets, ["target", "bucket"]).select("target", "label", F.explode("others").alias("other"))
    return pairs.groupBy("target", "label").agg((F.countDistinct("other") - 1).alias("under"))


def label_scores(cells: DataFrame) -> DataFrame:
    return overcounting(cells).join(undercounting(cells), ["target", "label"])


def type_report(scores: DataFrame, types: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Mean and sample deviation (0 for one bug) per type, per parent, and in total over (bug, type) pairs. types: (label, type, parent), few rows. by: columns
    of scores, such as the method, that each have a report of their own."""
    rows = scores.join(F.broadcast(types), "label")
    sd = lambda c: F.coalesce(F.stddev_samp(c), F.lit(0.0))
    cells = [F.count("*").alias("n"), F.avg("over").alias("over_mean"), sd("over").alias("over_sd"), F.avg("under").alias("under_mean"), sd("under").alias("under_sd")]
    each = rows.groupBy(*by, F.lit("type").alias("level"), F.col("type").alias("name")).agg(*cells)
    per_parent = rows.select(*by, "target", "label", "parent", "over", "under").distinct()
    up = per_parent.groupBy(*by, F.lit("parent").alias("level"), F.col("parent").alias("name")).agg(*cells)
    return each.unionByName(up).unionByName(rows.groupBy(*by, F.lit("total").alias("level"), F.lit("Total").alias("name")).agg(*cells))


def macro_average(scores: DataFrame) -> DataFrame:
    """Unweighted means over targets in whole percent, rounded half up."""
    pct = lambda c: F.floor(F.avg(c) * 100 + 0.5).cast("long").alias(c)
    return scores.agg(pct("purity"), pct("inverse_purity"), pct("f_measure"))


def flag_best(scores: DataFrame, metric: str) -> DataFrame:
    """scores of several configurations: whether each is the best of its target."""
    return scores.withColumn("best", F.col(metric) == F.max(metric).over(Window.partitionBy("target")))


class CostLog:
    """Wall seconds, row counts and other counters by stage."""

    def __init__(self):
        self.seconds: dict[str, float] = {}
        self.observed: dict[str, Observation] = {}
        self.added: dict[str, int] = {}

    @contextmanager
    def stage(self, name: str):
        began = time.time()
        yield
        self.seconds[name] = self.seconds.get(name, 0) + time.time() - began

    def observe(self, df: DataFrame, name: str) -> DataFrame:
        """Counts the rows of df as they pass, in the job that uses it anyway."""
        self.observed[name] = Observation(name)
        return df.observe(self.observed[name], F.count(F.lit(1)).alias("rows"))

    def add(self, name: str, value: int) -> None:
        self.added[name] = self.added.get(name, 0) + int(value)

    def counters(self) -> dict[str, int]:
        """All counters; the observed frames must have been written."""
        return {name: o.get["rows"] for name, o in self.observed.items()} | self.added
