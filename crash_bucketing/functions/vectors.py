"""Vector arithmetic as column expressions over arrays of doubles."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def as_double(v: Column) -> Column:
    return v.cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def let(value: Column, body) -> Column:
    """body(value) with the value computed once: a name inside a lambda would be computed anew for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def norm(v: Column) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))


def l2_normalise(v: Column) -> Column:
    """Unit vector; a zero vector has no direction and gives null."""
    return let(v, lambda w: let(norm(w), lambda n: F.when(n > 0, F.transform(w, lambda x: x / n))))


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def cosine_distance(a: Column, b: Column) -> Column:
    return 1 - dot(a, b) / (norm(a) * norm(b))


def truncate(v: Column, k: int = 64) -> Column:
    return F.slice(v, 1, k)


def add(a: Column, b: Column) -> Column:
    """Sum where both are there, else the one that is there."""
    return let(a, lambda p: let(b, lambda q: F.when(p.isNull(), q).when(q.isNull(), p).otherwise(F.zip_with(p, q, lambda x, y: x + y))))


def combine_sum(vectors: list[Column]) -> Column:
    """Each source to unit length, added, the sum to unit length. Missing sources are left out; opposite ones give null."""
    return l2_normalise(reduce(add, [l2_normalise(v) for v in vectors]))


def combine_concat(vectors: list[Column], width: int) -> Column:
    """The form that is not chosen: unit vectors side by side, a missing source as zeros."""
    zeros = F.array_repeat(F.lit(0.0), width)
    return l2_normalise(F.concat(*[F.coalesce(l2_normalise(v), zeros) for v in vectors]))


def combine_long(vectors: DataFrame, sources: list[str]) -> DataFrame:
    """(target, point, source, vec) rows to (target, point, vec): the same sum for any number of sources, by one aggregation per coordinate."""
    unit = vectors.where(F.col("source").isin(sources)).select("target", "point", F.posexplode(l2_normalise(as_double(F.col("vec")))).alias("j", "x"))
    summed = unit.groupBy("target", "point", "j").agg(F.sum("x").alias("x"))
    rows = summed.groupBy("target", "point").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("p"))  # as many as the vector is long
    return rows.select("target", "point", l2_normalise(F.transform("p", lambda e: e["x"])).alias("vec"))
