"""Functions for SQL users: scalar SQL functions that the optimiser inlines, an Arrow function, a grouped one and a table function."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .frames import NESTING

#: Types as objects: a type given as text needs a running session when the module is imported.
VECTOR = T.ArrayType(T.DoubleType())
LINE = T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("line", T.StringType())])

def _without_arguments(text: str) -> str:
    """SQL of frames.without_arguments: the same guards, the same depth."""
    out = f"replace(replace({text}, 'operator()', concat('operator', chr(1))), '(anonymous namespace)', chr(2))"
    for _ in range(NESTING):
        out = f"regexp_replace({out}, ' ?\\\\([^()\\\\n]*\\\\)', '')"
    return f"replace(replace({out}, chr(1), '()'), chr(2), '(anonymous namespace)')"


#: Scalar functions as SQL; each is expanded where it is called.
SCALAR = {
    "dot_product": ("a array<double>, b array<double>", "double", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    "euclidean": ("a array<double>, b array<double>", "double", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"),
    "l2_normalise": ("v array<double>", "array<double>", "get(transform(array(sqrt(aggregate(v, 0D, (s, x) -> s + x * x))), n -> case when n > 0 then transform(v, x -> x / n) end), 0)"),
    "truncate_vec": ("v array<double>, k int", "array<double>", "slice(v, 1, k)"),
    "without_arguments": ("t string", "string", _without_arguments("t")),
    "coarse_trace": ("lines array<string>", "string", _without_arguments("array_join(lines, chr(10))")),
}


@F.udtf(returnType=LINE)
class SplitLines:
    """Lines of a text with their places."""

    def eval(self, text: str):
        for i, line in enumerate((text or "").split("\n")):
            yield i, line


FRAME = T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("idx", T.IntegerType()), T.StructField("func", T.StringType()), T.StructField("site", T.StringType())])


@F.udtf(returnType=FRAME)
class ExplodeFrames:
    """Frames of a trace with their places: index, function without arguments, site. A line without an index belongs to the frame before it."""

    def eval(self, trace: str):
        joined = re.sub(r"\n(?!\s*#\d+\s)\s*", " ", (trace or "").replace("\r", "").strip())
        for pos, line in enumerate(x for x in joined.split("\n") if x.strip()):
            bare = line.replace("operator()", "operator\x01").replace("(anonymous namespace)", "\x02")
            for _ in range(NESTING):
                bare = re.sub(r" ?\([^()]*\)", "", bare)
            bare = bare.replace("\x01", "()").replace("\x02", "(anonymous namespace)")
            m = re.match(r"\s*#(\d+)\s+(?:0x[0-9a-fA-F]+ in )?(.*?)\s*(?: at (\S+:\d+)| from \S+)?\s*$", bare)
            yield (pos, int(m[1]), m[2], m[3]) if m else (pos, None, None, None)


@F.pandas_udf(VECTOR)
def hash_embed(texts: pd.Series) -> pd.Series:
    """Small offline vector of a text: 64 coordinates."""
    from ..operators.embed import MODELS

    model = MODELS["small_local"]
    return pd.Series([model.vector(t or "", 64).tolist() for t in texts])


@F.pandas_udf(VECTOR)
def vec_mean(vectors: pd.Series) -> list:
    return np.mean(np.array(vectors.tolist(), dtype=np.float64), axis=0).tolist()


@F.pandas_udf(VECTOR)
def vec_sum(vectors: pd.Series) -> list:
    return np.sum(np.array(vectors.tolist(), dtype=np.float64), axis=0).tolist()


def register(spark: SparkSession) -> None:
    for name, (args, result, body) in SCALAR.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {result} return {body}")
    spark.udtf.register("split_lines", SplitLines)
    spark.udtf.register("explode_frames", ExplodeFrames)
    spark.udf.register("hash_embed", hash_embed)

