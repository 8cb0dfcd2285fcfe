"""Named queries over the given tables, each with SQL that any engine can check where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import frames as fr
from ..functions import vectors as vec
from ..operators import baselines as base
from ..operators import embed as em
from ..operators import hierarchy as hi
from ..operators import measures as ms
from ..operators import neighbours as nb
from ..operators import quality as qu
from ..operators.collapse import collapse_exact, label_leaks
from ..sources import corpus
from ..sources.tables import load
from . import search as se
from . import workloads as wl
from .bucketer import Config, bucket, own_buckets, search_runs

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


# ---------------------------------------------------------------- SQL fragments of the oracles

NO_ARGS = "replace(replace({x}, 'operator()', 'operator' || chr(1)), '(anonymous namespace)', chr(2))"


def _no_args(x: str) -> str:
    out = NO_ARGS.format(x=x)
    for _ in range(fr.NESTING):
        out = f"regexp_replace({out}, ' ?\\([^()]*\\)', '', 'g')"
    return f"replace(replace({out}, chr(1), '()'), chr(2), '(anonymous namespace)')"


A_SQL = f"a as ({corpus.planted_sql('duckdb')})"
LINES_SQL = f"""{A_SQL}, l as (select crash_id, target, label, unnest(x) as line, generate_subscripts(x, 1) as pos from (select *, string_split(replace(trace, chr(10) || '    ', ' '), chr(10)) as x from a)),
k as (select crash_id, target, label, pos, line from (select *, row_number() over (partition by crash_id, regexp_replace(line, '^#\\d+\\s+', '') order by pos) as copy from l) where copy = 1)"""
PARSED_SQL = f"""{LINES_SQL}, f as (select *, cast(regexp_extract(line, '^#(\\d+)\\s', 1) as int) as idx, nullif(regexp_extract(line, '\\b(0x[0-9a-f]+) in ', 1), '') as addr, regexp_replace({_no_args('line')}, '^#\\d+\\s+(0x[0-9a-f]+ in )?', '') as body from k),
p as (select *, trim(regexp_replace(body, ' (at \\S+:\\d+|from \\S+)\\s*$', '')) as func, nullif(regexp_extract(body, ' at (\\S+:\\d+)\\s*$', 1), '') as site, nullif(regexp_extract(body, ' from (\\S+)\\s*$', 1), '') as lib from f)"""
TEXTS_SQL = f"""{LINES_SQL}, t as (select crash_id, target, label, string_agg(line, chr(10) order by pos) as full_text, string_agg({_no_args('line')}, chr(10) order by pos) as coarse_text from k group by all),
rl as (select crash_id, unnest(x) as line, generate_subscripts(x, 1) as pos from (select crash_id, string_split(replace(report, chr(10) || '    ', ' '), chr(10)) as x from a where report is not null)),
r as (select crash_id, string_agg(line, chr(10) order by pos) filter (not regexp_matches(line, '^#\\d+\\s') and not regexp_matches(line, '^(Shadow bytes|Shadow byte legend|  [A-Z][A-Za-z ]*: +[0-9a-f][0-9a-f]|(=>|  )0x[0-9a-f]+:)')) as report_text from rl group by crash_id),
texts as (select t.*, report_text from t left join r using (crash_id))"""
POINTS_SQL = f"""{TEXTS_SQL}, h as (select crash_id, target, label, sha256(full_text) as hf, sha256(coarse_text) as hc, sha256(report_text) as hr from texts),
points as (select target, hf, hc, hr, min(crash_id) as point, count(*) as weight from h group by all)"""
HASH_SQL = f"""{PARSED_SQL}, assign as (select target, crash_id, label, sha256(string_agg(concat_ws('|', coalesce(func, ''), coalesce(site, '')), chr(10) order by pos)) as bucket from p group by all),
cells as (select target, label, bucket, count(*) as n from assign group by all)"""
E_SQL = "e0 as (select vec_id, cast(embedding as double[]) as v from embeddings), e as (select vec_id, list_transform(v, lambda x: x / sqrt(list_inner_product(v, v))) as v from e0)"
PAIRS_SQL = f"{E_SQL}, pairs as materialized (select a.vec_id as a, b.vec_id as b, list_distance(a.v, b.v) as d from e a join e b on a.vec_id <> b.vec_id)"


def _views(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    from ..sources.tables import register

    return register(spark, sf_dir).sql(sql)


def both(name: str, sql: str, duck: str | None = None) -> None:
    """A query that is plain SQL in both engines."""
    QUERIES[name] = lambda spark, sf_dir, sql=sql: _views(spark, sf_dir, sql)
    ORACLES[name] = duck or sql


# ---------------------------------------------------------------- preprocessing


@query("m01_parse_frames", f"with {PARSED_SQL} select crash_id, count(*) as n, max(idx) as last_idx, count(addr) as n_addr, md5(string_agg(concat_ws('|', func, site, lib), chr(10) order by pos)) as digest from p group by crash_id")
def m01(spark, sf_dir):
    key = F.md5(F.array_join(F.transform("frames", lambda f: F.concat_ws("|", f["func"], f["site"], f["lib"])), "\n"))
    return wl.framed(spark, sf_dir).select("crash_id", F.size("frames").cast("long").alias("n"), F.array_max(F.transform("frames", lambda f: f["idx"])).alias("last_idx"), F.size(F.filter("frames", lambda f: f["addr"].isNotNull())).cast("long").alias("n_addr"), key.alias("digest"))


@query("m02_collapse_repeats", f"with {LINES_SQL}, n as (select crash_id, count(*) as before from l group by 1) select crash_id, before, count(*) as after, max(pos) as last_pos from k join n using (crash_id) group by all")
def m02(spark, sf_dir):
    lines = corpus.planted(spark, sf_dir)
    n = fr.once(fr.collapse_lines(lines), all_lines=fr.frame_lines(F.col("trace")))
    return n.select("crash_id", F.size("all_lines").cast("long").alias("before"), F.size("lines").cast("long").alias("after"), F.array_position("all_lines", F.element_at("lines", -1)).alias("last_pos"))


for _name, _sql, _col in (("m03_coarse_trace", "coarse_text", "coarse"), ("m04_full_trace", "full_text", "full")):

    @query(_name, f"with {TEXTS_SQL} select crash_id, md5({_sql}) as digest, length({_sql}) as chars from texts")
    def _m(spark, sf_dir, col=_col):
        return corpus.prepared(corpus.planted(spark, sf_dir)).select("crash_id", F.md5(col).alias("digest"), F.char_length(col).cast("long").alias("chars"))


@query("m05_strip_report_trace", f"with {A_SQL}, rl as (select crash_id, unnest(x) as line, generate_subscripts(x, 1) as pos from (select crash_id, string_split(replace(report, chr(10) || '    ', ' '), chr(10)) as x from a where report is not null)) select crash_id, md5(string_agg(line, chr(10) order by pos)) as digest from rl where not regexp_matches(line, '^\\s*#\\d+\\s') group by crash_id")
def m05(spark, sf_dir):
    return corpus.planted(spark, sf_dir).where("report is not null").select("crash_id", F.md5(fr.strip_report_trace(F.col("report"))).alias("digest"))


_SHADOW = "^(Shadow bytes|Shadow byte legend|  [A-Z][A-Za-z ]*: +[0-9a-f][0-9a-f]|(=>|  )0x[0-9a-f]+:)"
for _name in ("m06_strip_shadow", "m07_report_with_trace"):

    @query(_name, f"with {A_SQL}, rl as (select crash_id, unnest(x) as line, generate_subscripts(x, 1) as pos from (select crash_id, string_split(report, chr(10)) as x from a where report is not null)) select crash_id, md5(string_agg(line, chr(10) order by pos)) as digest from rl where not regexp_matches(line, '{_SHADOW}') group by crash_id")
    def _m67(spark, sf_dir, name=_name):
        strip = fr.strip_shadow if name.startswith("m06") else fr.report_with_trace
        return corpus.planted(spark, sf_dir).where("report is not null").select("crash_id", F.md5(strip(F.col("report"))).alias("digest"))


@query("m08_neutral_names", f"with {A_SQL} select crash_id, 'input-' || crash_id || '.bin' as name from a")
def m08(spark, sf_dir):
    return corpus.planted(spark, sf_dir).select("crash_id", fr.neutral_name(F.col("input_name"), F.col("crash_id")).alias("name"))


@query("m08_label_leaks", "select doc_id as crash_id, item_id from documents join benchmark on contains(documents.text, benchmark.text)")
def m08_leaks(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("crash_id"), F.col("text").alias("full"))
    items = load(spark, sf_dir, "benchmark").select(F.col("text").alias("label"), "item_id")
    return label_leaks(docs, items, ["full"]).join(F.broadcast(items), "label").select("crash_id", "item_id")


# ---------------------------------------------------------------- collapsing and embedding


@query("m09_collapse_points", f"with {POINTS_SQL} select target, point, weight from points")
def m09(spark, sf_dir):
    return collapse_exact(corpus.prepared(corpus.planted(spark, sf_dir)))[0].select("target", "point", "weight")


@query("m09_members", f"with {POINTS_SQL} select h.target, point, crash_id from h join points p on h.target = p.target and h.hf = p.hf and h.hc = p.hc and h.hr is not distinct from p.hr")
def m09_members(spark, sf_dir):
    prepared = wl.stored(corpus.prepared(corpus.planted(spark, sf_dir)), "prepared")
    return collapse_exact(prepared)[1]


@query("m09_collapse_documents", "select lang as target, min(doc_id) as point, count(*) as weight from documents group by lang, text")
def m09_documents(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("crash_id"), F.col("lang").alias("target"), F.col("text").alias("full"))
    return collapse_exact(docs, ["full"])[0].select("target", "point", "weight")


@query("m10_hash_projection", """with w as (select doc_id, unnest(string_split(lower(text), ' ')) as token from documents), c as (select doc_id, token, count(*) as tf, md5(token) as h from w where token <> '' group by doc_id, token)
select doc_id, j, sum(case when substr(h, j, 1) >= '8' then tf else -tf end)::bigint as x from c cross join (select unnest(range(1, 9)) as j) group by doc_id, j""")
def m10(spark, sf_dir):
    words = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("token")).where("token <> ''")
    tf = words.groupBy("doc_id", "token").agg(F.count("*").alias("tf")).withColumn("h", F.md5("token"))
    signed = [F.sum(F.when(F.substring("h", j, 1) >= "8", F.col("tf")).otherwise(-F.col("tf"))).alias(f"x{j}") for j in range(1, 9)]
    wide = tf.groupBy("doc_id").agg(*signed)
    return wide.select("doc_id", F.posexplode(F.array(*[f"x{j}" for j in range(1, 9)])).alias("p", "x")).select("doc_id", (F.col("p") + 1).cast("long").alias("j"), "x")


@query("m11_store_misses", "select sha256(text) as hash from documents group by text having min(doc_id) % 2 = 1")
def m11(spark, sf_dir):
    texts = load(spark, sf_dir, "documents").groupBy("text").agg(F.min("doc_id").alias("first")).select(F.sha2("text", 256).alias("hash"), "first")
    return em.missing_texts(texts.select("hash"), texts.where("first % 2 = 0").select("hash"))


@query("m12_request_batches", """with t as (select sha256(text) as hash, any_value(text) as text from documents group by text), s as (select hash, strlen(text) as n_bytes, ('0x' || substr(md5(hash), 1, 8))::bigint % 64 as lane from t),
b as (select *, sum(n_bytes) over (partition by lane order by hash rows unbounded preceding) - n_bytes as before, row_number() over (partition by lane order by hash) as r from s)
select hash, n_bytes::bigint as n_bytes, lane::bigint as lane, greatest(floor(before / 20000), floor((r - 1) / 8))::bigint as batch from b""")
def m12(spark, sf_dir):
    texts = load(spark, sf_dir, "documents").groupBy("text").agg(F.sha2("text", 256).alias("hash"))
    return em.batch_requests(texts, 8, 20000).select("hash", "n_bytes", F.col("lane").cast("long").alias("lane"), F.col("batch").cast("long").alias("batch"))


def _digest(v) -> list:
    """Comparable numbers of a vector: its length, first coordinate and sum."""
    return [F.size(v).cast("long").alias("n"), F.round(v[0], 6).alias("first"), F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x), 6).alias("total")]


_DIGEST = "len(v)::bigint as n, round(v[1], 6) as first, round(list_sum(v), 6) as total"
_UNIT = "list_transform({v}, lambda x: x / sqrt(list_inner_product({v}, {v})))"
_SLICES = "s as (select vec_id, cast(embedding[1:16] as double[]) as a, cast(embedding[17:32] as double[]) as b, cast(embedding[33:48] as double[]) as c from embeddings), u as (select vec_id, " + ", ".join(f"{_UNIT.format(v=x)} as {x}" for x in "abc") + " from s)"


@query("m13_truncate", f"select vec_id, {_DIGEST} from (select vec_id, cast(embedding[1:16] as double[]) as v from embeddings)")
def m13(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", *_digest(vec.truncate(vec.as_double(F.col("embedding")), 16)))


@query("m13_variance_rotation")
def m13_rotation(spark, sf_dir):
    return em.variance_rotation(load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), vec.as_double(F.col("embedding")).alias("vec")))


@query("m14_normalise", f"with {_SLICES} select vec_id, {_DIGEST} from (select vec_id, a as v from u)")
def m14(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", vec.l2_normalise(vec.as_double(F.slice("embedding", 1, 16))).alias("v")).select("vec_id", *_digest(F.col("v")))


def _three(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", *[vec.as_double(F.slice("embedding", 1 + 16 * i, 16)).alias("abc"[i]) for i in range(3)])


@query("m15_combine_sum", f"with {_SLICES}, z as (select vec_id, list_transform(list_zip(a, b, c), lambda t: t[1] + t[2] + t[3]) as s from u) select vec_id, {_DIGEST} from (select vec_id, {_UNIT.format(v='s')} as v from z)")
def m15(spark, sf_dir):
    return _three(spark, sf_dir).select("vec_id", vec.combine_sum([F.col(x) for x in "abc"]).alias("v")).select("vec_id", *_digest(F.col("v")))


@query("m15_combine_concat", f"with {_SLICES}, z as (select vec_id, list_concat(list_concat(a, b), c) as s from u) select vec_id, {_DIGEST} from (select vec_id, {_UNIT.format(v='s')} as v from z)")
def m15_concat(spark, sf_dir):
    return _three(spark, sf_dir).select("vec_id", vec.combine_concat([F.col(x) for x in "abc"], 16).alias("v")).select("vec_id", *_digest(F.col("v")))


@query("m16_final", f"with {_SLICES}, z as (select vec_id, list_transform(list_zip(a, b, c), lambda t: t[1] + t[2] + t[3]) as s from u) select vec_id, round(list_inner_product(v, v), 6) as length from (select vec_id, {_UNIT.format(v='s')} as v from z)")
def m16(spark, sf_dir):
    long = _three(spark, sf_dir).select(F.lit("all").alias("target"), F.col("vec_id").alias("point"), F.explode(F.map_from_arrays(F.array(*map(F.lit, "abc")), F.array(*"abc"))).alias("source", "vec"))
    return vec.combine_long(long, list("abc")).select(F.col("point").alias("vec_id"), F.round(vec.dot(F.col("vec"), F.col("vec")), 6).alias("length"))


_ASKED = f"{PAIRS_SQL}, asked as (select * from pairs where a % 100 = 0)"


@query("m17_euclidean_pairs", f"with {_ASKED} select a, b, round(d, 6) as d from asked")
def m17(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.within(e, e.where("point % 100 = 0"), 10.0).select(F.col("query").alias("a"), F.col("point").alias("b"), F.round("dist", 6).alias("d"))


@query("m17_cosine_order", f"with {_ASKED} select a, b, row_number() over (partition by a order by d, b) as r from asked qualify r <= 10")
def m17_cosine(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    q = e.where("point % 100 = 0").select(F.col("point").alias("a"), F.col("vec").alias("va"))
    pairs = F.broadcast(q).join(e.select(F.col("point").alias("b"), F.col("vec").alias("vb")), F.col("a") != F.col("b"))  # a hundredth of the rows asks
    ranked = pairs.withColumn("c", vec.cosine_distance(F.col("va"), F.col("vb"))).withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("c", "b")))
    return ranked.where("r <= 10").select("a", "b", F.col("r").cast("long").alias("r"))


# ---------------------------------------------------------------- trees and hierarchies

for _k in (1, 2, 5):

    @query(f"m20_core_distances_k{_k}", f"with {PAIRS_SQL}, ranked as (select a, d, row_number() over (partition by a order by d) + 1 as r from pairs) select a as point, round({'0 * d' if _k == 1 else 'd'}, 6) as core from ranked where r = {max(_k, 2)}")
    def _m20(spark, sf_dir, k=_k):
        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"point": pdf["point"], "core": hi.core_distance(hi._matrix(pdf["vec"]), k)})

        return wl.vectors_of(spark, sf_dir).groupBy("target").applyInPandas(run, "point long, core double").select("point", F.round("core", 6).alias("core"))


@query("m21_reachability", f"with {PAIRS_SQL}, core as (select a as p, min(d) as c from pairs group by a) select a, b, round(greatest(x.c, y.c, d), 6) as reach from (select * from pairs where a % 100 = 0) join core x on x.p = a join core y on y.p = b")
def m21(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    core = wl.stored(nb.knn(e, e, 1).select(F.col("query").alias("p"), F.col("dist").alias("c")), "core")
    near = nb.within(e, e.where("point % 100 = 0"), 10.0)
    joined = near.join(core.select(F.col("p").alias("query"), F.col("c").alias("ca")), "query").join(core.select(F.col("p").alias("point"), F.col("c").alias("cb")), "point")
    return joined.select(F.col("query").alias("a"), F.col("point").alias("b"), F.round(F.greatest("ca", "cb", "dist"), 6).alias("reach"))


for _s in ("local", "tiles"):

    @query(f"m22_tree_{_s}")
    def _m22(spark, sf_dir, s=_s):
        return hi.spanning_tree(wl.vectors_of(spark, sf_dir), s).select("a", "b", F.round("dist", 6).alias("dist"))


@query("m22_tree_graph")
def m22_graph(spark, sf_dir):
    return hi.approximate_tree(wl.vectors_of(spark, sf_dir), cell_points=64, keep=wl.stored).withColumn("dist", F.round("dist", 6))


@query("m23_distance_range", f"with {PAIRS_SQL} select round(min(d), 6) as low, round(max(d), 6) as high, (count(*) / 2)::bigint as pairs from pairs")
def m23(spark, sf_dir):
    return nb.distance_range(wl.vectors_of(spark, sf_dir)).select(F.round("low", 6).alias("low"), F.round("high", 6).alias("high"), "pairs")


@query("b3_components_at", f"with recursive {PAIRS_SQL.replace(" as materialized", " as")}, near as (select a, b from pairs where d <= 1.08), reach(p, c) as (select vec_id, vec_id from embeddings union select b, c from reach join near on a = p) select p as point, min(c) as bucket from reach group by p")
def b3(spark, sf_dir):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = sorted({*pdf["a"], *pdf["b"]})
        at = {p: i for i, p in enumerate(ids)}
        label = base._cut([(at[a], at[b], d) for a, b, d in zip(pdf["a"], pdf["b"], pdf["dist"], strict=True)], len(ids), 1.08)
        least: dict[int, int] = {}
        for p, k in zip(ids, label, strict=True):
            least[k] = min(least.get(k, p), p)
        return pd.DataFrame({"point": ids, "bucket": [least[k] for k in label]})

    return hi.spanning_tree(wl.vectors_of(spark, sf_dir)).groupBy("target").applyInPandas(run, "point long, bucket long")


@query("m24_condensed")
def m24(spark, sf_dir):
    return hi.condensed_table(hi.spanning_tree(wl.vectors_of(spark, sf_dir)))


for _name, _config, _eps in (("m25_mass", Config(), 0.0), ("m26_hybrid_eps", Config(root_mode="floor"), 1.1), ("m27_leaf", Config(start="leaf"), 0.0), ("m28_plain", Config(root_mode="floor"), 0.0)):

    @query(_name)
    def _m25(spark, sf_dir, config=_config, eps=_eps):
        return bucket(wl.vectors_of(spark, sf_dir), config, eps).drop("epsilon")


@query("m30_search_runs")
def m30(spark, sf_dir):
    return search_runs(wl.vectors_of(spark, sf_dir), Config(root_mode="floor"))


@query("m30a_enumerated")
def m30a(spark, sf_dir):
    return se.enumerated(wl.stored(hi.placed_tree(wl.vectors_of(spark, sf_dir)), "tree"), "floor").select("epsilon", "partition_hash", "n_buckets")


RUNS_SQL = "runs as (select o_orderpriority as target, o_orderkey::double as epsilon, o_orderkey::varchar as partition_hash, o_custkey as n_buckets, (o_orderkey * 7919 % 1000) / 1000.0::double as validity, (o_orderkey * 104729 % 997) / 997.0::double as persistence from orders)"


@query("m35_choice", f"""with {RUNS_SQL}, s1 as (select *, row_number() over (partition by target order by validity desc, persistence desc, epsilon) as r, max(validity) over (partition by target) as b from runs qualify r <= 10 and validity >= b - 0.2 * abs(b)),
s2 as (select *, max(persistence) over (partition by target) as m from s1 qualify persistence >= m - 0.2 * abs(m)) select target, epsilon, n_buckets from s2 qualify row_number() over (partition by target order by n_buckets, validity desc, persistence desc, epsilon) = 1""")
def m35(spark, sf_dir):
    o = load(spark, sf_dir, "orders")
    runs = o.select(F.col("o_orderpriority").alias("target"), F.col("o_orderkey").cast("double").alias("epsilon"), F.col("o_orderkey").cast("string").alias("partition_hash"), F.col("o_custkey").alias("n_buckets"), ((F.col("o_orderkey") * 7919 % 1000) / 1000.0).alias("validity"), ((F.col("o_orderkey") * 104729 % 997) / 997.0).alias("persistence"))
    return se.choose_best(runs).select("target", "epsilon", "n_buckets")


def _with_labels(spark, sf_dir, f: Callable) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), "vec_id", vec.as_double(F.col("embedding")).alias("vec"), "label")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        return pd.DataFrame({"value": [f(hi._matrix(pdf["vec"]), pdf["label"].to_numpy())]})

    return rows.groupBy("target").applyInPandas(run, "value double").select(F.round("value", 6).alias("value"))


@query("m32_dbcv")
def m32(spark, sf_dir):
    return _with_labels(spark, sf_dir, qu.validity)


@query("m33_persistence")
def m33(spark, sf_dir):
    def value(x, _):
        h = hi.condense(len(x), hi.minimum_tree(x))
        return hi.persistence(h, h.chosen_by_mass("floor"))

    return _with_labels(spark, sf_dir, value)


@query("m34_counts", "select count(distinct label) + sum(case when label % 5 = 0 then 1 else 0 end)::bigint - count(distinct case when label % 5 = 0 then label end) as n from embeddings")
def m34(spark, sf_dir):
    noise = load(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), F.col("vec_id").alias("point"), F.when(F.col("label") % 5 == 0, -1).otherwise(F.col("label")).cast("long").alias("bucket"))
    return own_buckets(noise).agg(F.countDistinct("bucket").alias("n"))


@query("m37_silhouette", "with e as (select vec_id, label, cast(embedding as double[]) as v from embeddings), d as (select a.vec_id, a.label as own, b.label as other, avg(sqrt(list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))))) as m from e a join e b on a.vec_id <> b.vec_id group by all), s as (select vec_id, max(case when own = other then m end) as near, min(case when own <> other then m end) as far from d group by vec_id) select round(avg((far - near) / greatest(far, near)), 6) as value from s")
def m37(spark, sf_dir):
    return _with_labels(spark, sf_dir, qu.silhouette)


# ---------------------------------------------------------------- baselines


@query("b1_dbscan", ORACLES["b3_components_at"])
def b1(spark, sf_dir):
    named = base.dbscan(wl.vectors_of(spark, sf_dir), 1.08).withColumn("least", F.min("point").over(Window.partitionBy("target", "bucket")))
    return named.select("point", F.col("least").alias("bucket"))


@query("b1_dbscan_search")
def b1_search(spark, sf_dir):
    return base.dbscan_search(wl.vectors_of(spark, sf_dir))


@query("b2_kmeans")
def b2(spark, sf_dir):
    return base.kmeans_search(wl.vectors_of(spark, sf_dir))


@query("b4_stack_hash", f"with {HASH_SQL} select target, crash_id, bucket from assign")
def b4(spark, sf_dir):
    return wl.planted_stack_hash(spark, sf_dir)


@query("b4_stack_hash_top3", f"with {PARSED_SQL}, r as (select *, row_number() over (partition by crash_id order by pos) as i from p) select target, crash_id, sha256(string_agg(concat_ws('|', coalesce(func, ''), coalesce(site, '')), chr(10) order by pos)) as bucket from r where i <= 3 group by all")
def b4_top3(spark, sf_dir):
    return wl.planted_stack_hash(spark, sf_dir, 3)


_MI = """n as (select count(*) filter (crashed)::double as n1, count(*) filter (not crashed)::double as n0 from (select distinct run_id, crashed from b)),
c as (select block, count(*) filter (crashed) as in_crash, count(*) filter (not crashed) as in_healthy from b group by block),
t as (select *, n1 + n0 as n, in_crash + in_healthy as y from c, n),
scored as (select block, in_crash, in_healthy, (case when in_crash > 0 then in_crash / n * ln(in_crash * n / (y * n1)) else 0 end) + (case when in_healthy > 0 then in_healthy / n * ln(in_healthy * n / (y * n0)) else 0 end)
 + (case when n1 > in_crash then (n1 - in_crash) / n * ln((n1 - in_crash) * n / ((n - y) * n1)) else 0 end) + (case when n0 > in_healthy then (n0 - in_healthy) / n * ln((n0 - in_healthy) * n / ((n - y) * n0)) else 0 end) as mi from t)"""


@query("b5_block_scores", f"with b as ({corpus.BLOCKS_SQL}), {_MI} select block, in_crash, in_healthy, round(mi, 6) as mi from scored")
def b5(spark, sf_dir):
    return base.block_scores(corpus.blocks(spark, sf_dir)).withColumn("mi", F.round("mi", 6))


@query("b5_buckets", f"with b as ({corpus.BLOCKS_SQL}), {_MI}, top as (select block from scored order by round(mi, 9) desc, block limit 16), s as (select run_id, string_agg(block, ',' order by block) as bucket from b join top using (block) where crashed group by run_id) select r.run_id, coalesce(bucket, '') as bucket from (select distinct run_id from b where crashed) r left join s using (run_id)")
def b5_buckets(spark, sf_dir):
    return base.mutual_information_buckets(wl.stored(corpus.blocks(spark, sf_dir), "blocks"))


_EDGES = f"s as ({corpus.SESSIONS_SQL}), g as (select target, run_id as crash_id, event_type || '>' || lead(event_type) over (partition by run_id order by pos) as edge from s where crashed), ed as (select distinct target, crash_id, edge from g where edge is not null)"


def _session_edges(spark, sf_dir) -> DataFrame:
    s = corpus.sessions(spark, sf_dir).where("crashed").select("target", F.col("run_id").alias("crash_id"), "pos", "event_type")
    return base.edges_of(s, "pos", "event_type")


@query("b6_edge_jaccard", f"with {_EDGES}, z as (select crash_id, count(*) as s from ed group by 1), c as (select x.target, x.crash_id as a, y.crash_id as b, count(*) as c from ed x join ed y on x.target = y.target and x.edge = y.edge and x.crash_id < y.crash_id group by all) select target, a, b, round(c / (p.s + q.s - c), 6) as similarity from c join z p on p.crash_id = a join z q on q.crash_id = b where a % 100 = 0")
def b6(spark, sf_dir):
    edges = wl.stored(_session_edges(spark, sf_dir), "edges")
    return base.edge_jaccard(edges, edges.where("crash_id % 100 = 0").select("target", "crash_id").distinct()).withColumn("similarity", F.round("similarity", 6))


@query("b6_wl")
def b6_wl(spark, sf_dir):
    return base.wl_labels(_session_edges(spark, sf_dir))


@query("b6_cfg_buckets")
def b6_buckets(spark, sf_dir):
    return wl.planted_cfg(spark, sf_dir, fallback=False)


@query("b6a_fallback", "with a as (select n_regionkey as target, n_nationkey % 2 as bucket, n_nationkey as crash_id from nation), b as (select n_regionkey as target, n_nationkey % 3 as bucket, n_nationkey as crash_id from nation where n_regionkey > 1 union all select n_regionkey, 0, n_nationkey from nation where n_regionkey <= 1), n as (select a.target, count(distinct a.bucket) as n1, (select count(distinct b.bucket) from b where b.target = a.target) as n2 from a group by a.target) select a.target, crash_id, bucket::bigint as bucket from a join n using (target) where n1 <= n2 union all select b.target, crash_id, bucket::bigint from b join n using (target) where n2 < n1")
def b6a(spark, sf_dir):
    n = load(spark, sf_dir, "nation").select(F.col("n_regionkey").alias("target"), F.col("n_nationkey").alias("crash_id"))
    a = n.withColumn("bucket", F.col("crash_id") % 2)
    b = n.withColumn("bucket", F.when(F.col("target") > 1, F.col("crash_id") % 3).otherwise(F.lit(0)).cast("long"))
    return base.fewer_clusters(a, b)


# ---------------------------------------------------------------- measures: stack hashes against planted bugs, and label against id modulo 7 on vectors


def _cells(spark, sf_dir) -> DataFrame:
    return ms.contingency(wl.planted_stack_hash(spark, sf_dir), wl.planted_truth(spark, sf_dir))


def _cells_e(spark, sf_dir) -> DataFrame:
    e = load(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), F.col("vec_id").alias("crash_id"), (F.col("vec_id") % 7).cast("string").alias("bucket"), F.col("label").cast("string").alias("label"))
    return ms.contingency(e.select("target", "crash_id", "bucket"), e.select("target", "crash_id", "label"))


_CELLS_E = "cells as (select 'all' as target, label::varchar as label, (vec_id % 7)::varchar as bucket, count(*) as n from embeddings group by all)"
_PR = "pr as (select *, sum(n) over (partition by target, bucket)::bigint as bucket_size, sum(n) over (partition by target, label)::bigint as label_size from cells)"
_MEASURES: dict[str, tuple[Callable[[DataFrame], DataFrame], str]] = {
    "a01_contingency": (lambda c: c, "select target, label, bucket, n from cells"),
    "a02_precision": (lambda c: ms.precision_recall(c).select("target", "label", "bucket", F.round("precision", 6).alias("precision")), f", {_PR} select target, label, bucket, round(n / bucket_size, 6) as precision from pr"),
    "a03_recall": (lambda c: ms.precision_recall(c).select("target", "label", "bucket", F.round("recall", 6).alias("recall")), f", {_PR} select target, label, bucket, round(n / label_size, 6) as recall from pr"),
    "a04_purity": (lambda c: ms.purity(c).select("target", F.round("purity", 6).alias("purity")), "select target, round(sum(m) / (select sum(n) from cells c where c.target = x.target), 6) as purity from (select target, bucket, max(n) as m from cells group by all) x group by target"),
    "a05_inverse_purity": (lambda c: ms.inverse_purity(c).select("target", F.round("inverse_purity", 6).alias("inverse_purity")), "select target, round(sum(m) / (select sum(n) from cells c where c.target = x.target), 6) as inverse_purity from (select target, label, max(n) as m from cells group by all) x group by target"),
    "a06_f_measure": (lambda c: ms.f_measure(c).select("target", F.round("f_measure", 6).alias("f_measure")), f", {_PR} select target, round(sum(f * s) / sum(s), 6) as f_measure from (select target, label, max(2 * n / (bucket_size + label_size)) as f, max(label_size) as s from pr group by all) group by target"),
    "a07_counts": (ms.bucket_counts, "select target, count(distinct label) as n_bugs, count(distinct bucket) as n_buckets from cells group by target"),
    "a08_overcounting": (ms.overcounting, "select target, label, count(*) - 1 as over from cells group by target, label"),
    "a09_undercounting": (ms.undercounting, "select a.target, a.label, count(distinct b.label) - 1 as under from cells a join cells b on a.target = b.target and a.bucket = b.bucket group by all"),
}
for _name, (_f, _tail) in _MEASURES.items():

    @query(_name, f"with {HASH_SQL} {_tail}")
    def _a(spark, sf_dir, f=_f):
        return f(_cells(spark, sf_dir))

    @query(f"{_name}_vectors", f"with {_CELLS_E} {_tail}")
    def _ae(spark, sf_dir, f=_f):
        return f(_cells_e(spark, sf_dir))


_TYPED = "truth as (select distinct target, label from cells), typed as (" + corpus.BUG_TYPE_SQL.strip().removeprefix("with ").replace("bugs as", "with bugs as", 1) + ")"
_SCORES = "sc as (select * from (select target, label, count(*) - 1 as over from cells group by target, label) join (select a.target, a.label, count(distinct b.label) - 1 as under from cells a join cells b on a.target = b.target and a.bucket = b.bucket group by all) using (target, label))"
_STAT = "count(*) as n, round(avg(over), 6) as over_mean, round(coalesce(stddev_samp(over), 0), 6) as over_sd, round(avg(under), 6) as under_mean, round(coalesce(stddev_samp(under), 0), 6) as under_sd"


def _type_report(spark, sf_dir) -> DataFrame:
    cells = wl.stored(_cells(spark, sf_dir), "cells")
    cells.select("label").distinct().createOrReplaceTempView("truth")
    out = ms.type_report(ms.label_scores(cells), spark.sql(corpus.BUG_TYPE_SQL))
    return out.select("level", "name", "n", *[F.round(c, 6).alias(c) for c in ("over_mean", "over_sd", "under_mean", "under_sd")])


_REPORT_SQL = f"with {HASH_SQL}, {_TYPED}, {_SCORES}, j as (select sc.*, type, parent from sc join typed using (label)) select 'type' as level, type as name, {_STAT} from j group by type union all select 'parent', parent, {_STAT} from (select distinct target, label, parent, over, under from j) group by parent union all select 'total', 'Total', {_STAT} from j"
query("a10_type_report", _REPORT_SQL)(_type_report)
query("w6_type_report", _REPORT_SQL)(_type_report)

_SCORE_SQL = f"{_PR}, s as (select target, count(distinct label) as n_bugs, count(distinct bucket) as n_buckets, sum(n) as t from cells group by target), pu as (select target, sum(m) as m from (select target, bucket, max(n) as m from cells group by all) group by target), ip as (select target, sum(m) as m from (select target, label, max(n) as m from cells group by all) group by target), fm as (select target, sum(f * s) / sum(s) as f from (select target, label, max(2 * n / (bucket_size + label_size)) as f, max(label_size) as s from pr group by all) group by target), score as (select s.target, n_bugs, n_buckets, pu.m / t as purity, ip.m / t as inverse_purity, fm.f as f_measure from s join pu using (target) join ip using (target) join fm using (target))"
_ROUNDED = "target, n_bugs, n_buckets, round(purity, 6) as purity, round(inverse_purity, 6) as inverse_purity, round(f_measure, 6) as f_measure"


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("target", "n_bugs", "n_buckets", *[F.round(c, 6).alias(c) for c in ("purity", "inverse_purity", "f_measure")])


def _hash_score(spark, sf_dir, **how) -> DataFrame:
    return ms.score(wl.planted_stack_hash(spark, sf_dir), wl.planted_truth(spark, sf_dir), **how)


@query("a11_macro_average", f"with {HASH_SQL}, {_SCORE_SQL} select floor(avg(purity) * 100 + 0.5)::bigint as purity, floor(avg(inverse_purity) * 100 + 0.5)::bigint as inverse_purity, floor(avg(f_measure) * 100 + 0.5)::bigint as f_measure from score")
def a11(spark, sf_dir):
    return ms.macro_average(_hash_score(spark, sf_dir))


@query("a13_best_flags", f"with {HASH_SQL}, {_SCORE_SQL}, two as (select target, 'hash' as config, round(f_measure, 6) as f_measure from score union all select target, 'single', 0.5 from score) select *, f_measure = max(f_measure) over (partition by target) as best from two")
def a13(spark, sf_dir):
    s = _hash_score(spark, sf_dir).select("target", F.lit("hash").alias("config"), F.round("f_measure", 6).alias("f_measure"))
    return ms.flag_best(s.union(s.select("target", F.lit("single"), F.lit(0.5))), "f_measure")


@query("a14_excluding", f"with {HASH_SQL}, {_SCORE_SQL} select {_ROUNDED} from score where target <> '2-HIGH'")
def a14(spark, sf_dir):
    return _rounded(_hash_score(spark, sf_dir, exclude=["2-HIGH"]))


@query("a15_score", f"with {HASH_SQL}, {_SCORE_SQL} select {_ROUNDED} from score")
def a15(spark, sf_dir):
    return _rounded(_hash_score(spark, sf_dir))


@query("w5_stack_hash", f"with {HASH_SQL.replace(corpus.planted_sql('duckdb'), corpus.planted_sql('duckdb', hard=True))}, {_SCORE_SQL} select {_ROUNDED} from score")
def w5_stack_hash(spark, sf_dir):
    """On the hard corpus, as in the comparison."""
    return _rounded(ms.score(wl.planted_stack_hash(spark, sf_dir, hard=True), wl.planted_truth(spark, sf_dir, hard=True)))


# ---------------------------------------------------------------- projection


@query("p1_gram", "with x as (select unnest(embedding)::double as x, generate_subscripts(embedding, 1) - 1 as i, vec_id from embeddings) select a.i::bigint as i, b.i::bigint as j, round(sum(a.x * b.x), 5) as x from x a join x b using (vec_id) group by all")
def p1_gram(spark, sf_dir):
    m = em.second_moments(load(spark, sf_dir, "embeddings").select(F.col("embedding").alias("vec")))
    return spark.createDataFrame([(i, j, round(float(m[i, j]), 5)) for i in range(len(m)) for j in range(len(m))], "i long, j long, x double")


for _name in ("p1_projection", "w7_projection"):

    @query(_name)
    def _p1(spark, sf_dir):
        return em.project_2d(load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))).select("id", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"))


# ---------------------------------------------------------------- experiments


@query("w1_planted_buckets")
def w1(spark, sf_dir):
    return wl.planted_buckets(spark, sf_dir)


@query("w1_planted_scores")
def w1_scores(spark, sf_dir):
    return _rounded(wl.planted_scores(spark, sf_dir))


for _c in ("no_full", "no_coarse", "no_report", "report_only", "full", "coarse", "report"):

    @query(f"w2_sources_{_c}")
    def _w2(spark, sf_dir, c=_c):
        return _rounded(wl.planted_scores(spark, sf_dir, c))


for _m in ("dbscan", "kmeans"):

    @query(f"w3_{_m}")
    def _w3(spark, sf_dir, m=_m):
        return _rounded(wl.planted_clusterer(spark, sf_dir, m))


@query("w3_hybrid")
def w3_hybrid(spark, sf_dir):
    return bucket(wl.vectors_of(spark, sf_dir)).drop("epsilon")


for _m in em.MODELS:

    @query(f"w4_model_{_m}")
    def _w4(spark, sf_dir, m=_m):
        return _rounded(wl.planted_scores(spark, sf_dir, embedder=em.MODELS[m]))


_BLOCKS_A = """b as (select target, crash_id as run_id, func as block, true as crashed from p where func <> '' group by all union all select target, -crash_id - 1, func, false from p where func <> '' and idx >= 7 and func not like 'walk%' group by all),
n as (select target, count(*) filter (crashed)::double as n1, count(*) filter (not crashed)::double as n0 from (select distinct target, run_id, crashed from b) group by target),
c as (select target, block, count(*) filter (crashed) as in_crash, count(*) filter (not crashed) as in_healthy from b group by target, block),
tt as (select *, n1 + n0 as n, in_crash + in_healthy as y from c join n using (target)),
scored as (select target, block, (case when in_crash > 0 then in_crash / n * ln(in_crash * n / (y * n1)) else 0 end) + (case when in_healthy > 0 then in_healthy / n * ln(in_healthy * n / (y * n0)) else 0 end)
 + (case when n1 > in_crash then (n1 - in_crash) / n * ln((n1 - in_crash) * n / ((n - y) * n1)) else 0 end) + (case when n0 > in_healthy then (n0 - in_healthy) / n * ln((n0 - in_healthy) * n / ((n - y) * n0)) else 0 end) as mi from tt),
top as (select target, block from scored qualify row_number() over (partition by target order by round(mi, 9) desc, block) <= 16),
s as (select target, run_id, string_agg(block, ',' order by block) as bucket from b join top using (target, block) where crashed group by all),
assign as (select distinct p.target, crash_id, p.label, coalesce(bucket, '') as bucket from p left join s on s.target = p.target and run_id = crash_id),
cells as (select target, label, bucket, count(*) as n from assign group by all)"""


@query("w5_mutual_information", f"with {PARSED_SQL}, {_BLOCKS_A}, {_SCORE_SQL.replace(', s as (', ', su as (').replace('from s join', 'from su join').replace('s.target, n_bugs', 'su.target, n_bugs')} select {_ROUNDED} from score")
def w5_mutual_information(spark, sf_dir):
    return _rounded(ms.score_cells(wl.method_cells(wl.shapes(spark, sf_dir), "mutual_information")))


@query("w5_cfg")
def w5_cfg(spark, sf_dir):
    return _rounded(ms.score_cells(wl.method_cells(wl.shapes(spark, sf_dir), "cfg_similarity")))


def _all_rounded(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(f.name, 6).alias(f.name) if f.dataType.simpleString() == "double" else F.col(f.name) for f in df.schema])


for _hard in (False, True):

    @query("w5_comparison_hard" if _hard else "w5_comparison")
    def _w5(spark, sf_dir, hard=_hard):
        """Four methods side by side, target by target, the best F of each target marked; on the planted corpus and on its hard form."""
        return ms.flag_best(_all_rounded(wl.method_scores(wl.compared(spark, sf_dir, hard))), "f_measure")


@query("w5_comparison_mean")
def w5_comparison_mean(spark, sf_dir):
    """Whole percent over targets for each method."""
    scores = wl.method_scores(wl.compared(spark, sf_dir))
    return scores.groupBy("method").agg(*[F.floor(F.avg(c) * 100 + 0.5).cast("long").alias(c) for c in ("purity", "inverse_purity", "f_measure")])


@query("w6_type_report_methods")
def w6_methods(spark, sf_dir):
    """Over- and undercounting by bug type for all four methods."""
    cells = wl.compared(spark, sf_dir)
    cells.select("label").distinct().createOrReplaceTempView("truth")
    return _all_rounded(wl.method_type_reports(cells, spark.sql(corpus.BUG_TYPE_SQL)))


@query("w6_type_report_nations", "with cells as (select 'all' as target, label::varchar as label, (vec_id % 7)::varchar as bucket, count(*) as n from embeddings group by all), typed as (select n_nationkey::varchar as label, n_name as type, r_name as parent from nation join region on r_regionkey = n_regionkey)"
       + f", {_SCORES}, j as (select sc.*, type, parent from sc join typed using (label)) select 'type' as level, type as name, {_STAT} from j group by type union all select 'parent', parent, {_STAT} from (select distinct target, label, parent, over, under from j) group by parent union all select 'total', 'Total', {_STAT} from j")
def w6_nations(spark, sf_dir):
    """The same report over a real two-level hierarchy: labels of vectors as nations in regions."""
    types = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    types = types.select(F.col("n_nationkey").cast("string").alias("label"), F.col("n_name").alias("type"), F.col("r_name").alias("parent"))
    return _all_rounded(ms.type_report(ms.label_scores(_cells_e(spark, sf_dir)), types))


@query("a12_costs")
def a12(spark, sf_dir):
    return wl.planted_costs(spark, sf_dir)


@query("m22_auto")
def m22_auto(spark, sf_dir):
    """Buckets by each way: the strategy that the counted size asks for, here forced down so that the tiles serve."""
    from .bucketer import bucket_any

    return bucket_any(wl.vectors_of(spark, sf_dir), Config(root_mode="floor"), local=100, block=100, keep=wl.stored).drop("epsilon")


@query("m32_sampled")
def m32_sampled(spark, sf_dir):
    """Search runs from a stored tree with the validity of a sample of the points."""
    from .bucketer import search_runs_from_tree

    e = wl.vectors_of(spark, sf_dir)
    return search_runs_from_tree(e, wl.stored(hi.spanning_tree(e, "tiles"), "tree"), Config(root_mode="floor"), sample=200)


@query("w9_clean_truth", f"with {A_SQL}, m as (select label, min(label) over (partition by target) as first from (select distinct target, label from a)) select a.target, crash_id, case when a.label like '%#1' then m.first else a.label end as label from a join m using (label) where a.label <> '4-NOT SPECIFIED#7'")
def w9(spark, sf_dir):
    truth = wl.planted_truth(spark, sf_dir)
    labels = truth.select("target", "label").distinct()
    merges = labels.withColumn("into", F.min("label").over(Window.partitionBy("target"))).where("label like '%#1'").select("label", "into")
    return wl.clean_truth(truth, merges, spark.sql("select '4-NOT SPECIFIED#7' as label"))


query("w10_collapse_exact", ORACLES["m09_collapse_documents"])(m09_documents)


@query("w10_unique_lines", "with l as (select doc_id, unnest(x) as line, generate_subscripts(x, 1) as pos from (select doc_id, string_split(text, chr(10)) as x from documents)), f as (select doc_id, line, min(pos) as pos from l group by all) select doc_id, count(*) as n, md5(string_agg(line, chr(10) order by pos)) as digest from f group by doc_id")
def w10(spark, sf_dir):
    lines = F.array_distinct(F.split("text", "\n"))
    return load(spark, sf_dir, "documents").select("doc_id", F.size(lines).cast("long").alias("n"), F.md5(F.array_join(lines, "\n")).alias("digest"))


query("w11_strip_report", ORACLES["m06_strip_shadow"])(QUERIES["m06_strip_shadow"])


@query("w11_strip_pages", "select page_id, md5(regexp_replace(regexp_replace(html, '(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>', '', 'g'), '<[^>]*>', '', 'g')) as digest from pages")
def w11_pages(spark, sf_dir):
    inner = F.regexp_replace("html", r"(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>", "")
    return load(spark, sf_dir, "pages").select("page_id", F.md5(F.regexp_replace(inner, r"<[^>]*>", "")).alias("digest"))


query("w12_label_leaks", ORACLES["m08_label_leaks"])(m08_leaks)


@query("w13_edges", f"with {PAIRS_SQL}, r as (select a, b, d, row_number() over (partition by a order by d, b) as r from pairs) select a, b, round(d, 6) as d from r where r <= 3")
def w13_edges(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.knn(e, e, 3).select(F.col("query").alias("a"), F.col("point").alias("b"), F.round("dist", 6).alias("d"))


@query("w13_tree_stats")
def w13(spark, sf_dir):
    return hi.spanning_tree(wl.vectors_of(spark, sf_dir)).agg(F.count("*").alias("edges"), F.round(F.sum("dist"), 6).alias("total"), F.round(F.min("dist"), 6).alias("low"), F.round(F.max("dist"), 6).alias("high"))


query("w13_search_runs")(m30)
