"""Operators around the method: scans, predicates, joins, aggregates, windows, sets, scalar families, user functions, neighbours, streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import frames as fr
from ..functions import sqlfuncs
from ..functions import vectors as vec
from ..operators import neighbours as nb
from ..sources import corpus
from ..sources.tables import SCHEMAS, WRITTEN, load, read_trace_files, register, write_points, write_trace_files
from ..streaming import arrivals as st
from . import workloads as wl
from .registry import A_SQL, LINES_SQL, PAIRS_SQL, PARSED_SQL, POINTS_SQL, Query, _no_args

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def both(name: str, sql: str, duck: str | None = None) -> None:
    """A query that is plain SQL in both engines."""
    QUERIES[name] = lambda spark, sf_dir: register(spark, sf_dir).sql(sql)
    ORACLES[name] = duck or sql


def t(spark, sf_dir, name: str) -> DataFrame:
    return load(spark, sf_dir, name)


# ---------------------------------------------------------------- scans, sources, sinks


@query("o01_typed_scan", "select o_orderkey, o_orderpriority from orders where o_totalprice > 100000")
def o01(spark, sf_dir):
    return spark.read.schema(SCHEMAS["orders"]).parquet(f"{sf_dir}/orders.parquet").where("o_totalprice > 100000").select("o_orderkey", "o_orderpriority")


@query("o03_json_lines", "select event_id, event_type, round(value, 6) as value from events")
def o03(spark, sf_dir):
    path = f"{wl.scratch(spark)}-json"
    t(spark, sf_dir, "events").select("event_id", "event_type", "value").write.json(path)
    return spark.read.schema("event_id long, event_type string, value double").json(path).select("event_id", "event_type", F.round("value", 6).alias("value"))


@query("o02_trace_files", "select doc_id::varchar as crash_id, lang as target, md5(text) as digest from documents where text is not null and lang is not null")
def o02(spark, sf_dir):
    """Documents written as files of a directory, one a crash in a folder for each target, and read back."""
    folder = f"{wl.scratch(spark)}-files"
    write_trace_files(corpus.document_crashes(spark, sf_dir).where("trace is not null and target is not null"), folder)
    return read_trace_files(spark, folder, **WRITTEN).select("crash_id", "target", F.md5("trace").alias("digest"))


def _back(spark, rows: DataFrame, kind: str, **options: str) -> DataFrame:
    """Written in a format and read back with the schema given."""
    path = f"{wl.scratch(spark)}-{kind}"
    rows.write.format(kind).options(**options).save(path)
    return spark.read.schema(rows.schema).format(kind).options(**options).load(path)


for _kind in ("csv", "orc"):

    @query(f"o03_{_kind}", "select event_id, event_type, round(value, 6) as value, props from events")
    def _o03(spark, sf_dir, kind=_kind):
        rows = t(spark, sf_dir, "events").select("event_id", "event_type", "value", "props")
        return _back(spark, rows, kind, **({"header": "true", "quote": '"', "escape": '"'} if kind == "csv" else {})).withColumn("value", F.round("value", 6))


@query("o04_partitioned_sink", "select o_orderpriority as target, count(*) as n from orders where o_orderpriority = '2-HIGH' group by 1")
def o04(spark, sf_dir):
    path = f"{wl.scratch(spark)}-parts"
    write_points(t(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("target"), "o_orderkey"), path)
    return spark.read.parquet(path).where("target = '2-HIGH'").groupBy("target").agg(F.count("*").alias("n"))


@query("o04_bucketed_sink", "select c_mktsegment, count(*) as n, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey group by 1")
def o04_bucketed(spark, sf_dir):
    """Both sides written in as many buckets of the join key: the join needs no shuffle."""
    place, names = wl.scratch(spark), []
    for name, key in (("orders", "o_custkey"), ("customer", "c_custkey")):
        names.append(f"bucketed_{name}_{place.rsplit('-', 1)[1][:12]}")
        t(spark, sf_dir, name).write.bucketBy(8, key).sortBy(key).option("path", f"{place}-{name}").saveAsTable(names[-1])
    both_sides = spark.table(names[0]).hint("merge").join(spark.table(names[1]), F.col("o_custkey") == F.col("c_custkey"))
    out = wl.stored(both_sides.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total")), "joined")
    for name in names:
        spark.sql(f"drop table {name}")
    return out


@query("o05_store_compaction", "select sha256(text) as hash, count(*) as copies from documents group by 1")
def o05(spark, sf_dir):
    path = wl.scratch(spark)
    d = t(spark, sf_dir, "documents").select(F.sha2("text", 256).alias("hash"), "doc_id")
    d.where("doc_id % 2 = 0").write.parquet(f"{path}-v1")
    d.where("doc_id % 2 = 1").write.mode("append").parquet(f"{path}-v1")
    spark.read.parquet(f"{path}-v1").repartition("hash").sortWithinPartitions("hash").write.parquet(f"{path}-v2")
    return spark.read.parquet(f"{path}-v2").groupBy("hash").agg(F.count("*").alias("copies"))


@query("o06_table_function", "select conv_id, turn, x.pos::int - 1 as pos, x.line from (select conv_id, turn, unnest(list_zip(range(1, len(string_split(text, chr(10))) + 1), string_split(text, chr(10))))  as z from conversations) q, lateral (select z[1] as pos, z[2] as line) x")
def o06(spark, sf_dir):
    c = t(spark, sf_dir, "conversations")
    sqlfuncs.register(spark)
    c.createOrReplaceTempView("conversations")
    return spark.sql("select conv_id, turn, x.pos, x.line from conversations, lateral split_lines(text) x")


# ---------------------------------------------------------------- projection, predicates

both("o07_case_cast_nulls", "select l_orderkey, l_linenumber, case when l_quantity < 10 then 'low' when l_quantity < 30 then 'mid' else 'high' end as band, cast(l_quantity as bigint) as q, coalesce(nullif(l_returnflag, 'N'), 'none') as flag, l_linestatus is not distinct from 'O' as is_open from lineitem")
both("o08_ranges_and_in", "select o_orderkey from orders where o_orderdate >= timestamp '1995-01-01' and o_orderdate < timestamp '1996-01-01' and o_orderstatus in ('O', 'P')")
both("o09_patterns", "select doc_id, text like 'The%' as starts, contains(text, 'license') as has, regexp_like(text, '[0-9]{4}') as digits from documents", "select doc_id, text like 'The%' as starts, contains(text, 'license') as has, regexp_matches(text, '[0-9]{4}') as digits from documents")
both("o10_subqueries", "select o_orderkey from orders o where not exists (select 1 from lineitem l where l.l_orderkey = o.o_orderkey) and o_totalprice > (select avg(o_totalprice) from orders)")

# ---------------------------------------------------------------- joins


def _orders_customers(hint: str):
    return lambda spark, sf_dir: t(spark, sf_dir, "orders").join(t(spark, sf_dir, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


_OC = "select c_mktsegment, count(*) as n, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey group by 1"
for _name, _hint in (("o11_shuffle_hash_join", "shuffle_hash"), ("o12_sort_merge_join", "merge")):
    query(_name, _OC)(_orders_customers(_hint))


@query("o13_broadcast_join", "select r_name, count(*) as n from nation join region on n_regionkey = r_regionkey group by 1")
def o13(spark, sf_dir):
    return t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


both("o14_theta_join", "select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_nationkey < b.n_nationkey and a.n_regionkey <> b.n_regionkey")
both("o15_outer_joins", "select coalesce(l.o, c.k) as custkey, n, c_mktsegment from (select o_custkey as o, count(*) as n from orders where o_orderstatus = 'P' group by 1) l full outer join (select c_custkey as k, c_mktsegment from customer where c_acctbal > 0) c on l.o = c.k")
both("o16_semi_join", "select count(*) as n, sum(o_orderkey) as s from orders where o_orderkey in (select l_orderkey from lineitem where l_quantity > 45)", "select count(*) as n, sum(o_orderkey)::bigint as s from orders where o_orderkey in (select l_orderkey from lineitem where l_quantity > 45)")


@query("o17_range_join", "select e.event_id as error_id, o.event_id from events e join events o on o.user_id = e.user_id and o.ts >= e.ts - interval 1 hour and o.ts < e.ts where e.event_type = 'error' and o.event_type <> 'error'")
def o17(spark, sf_dir):
    """Time cut into hours; an error meets its own hour and the one before."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("us").alias("at"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) - 1)).alias("h"))
    others = e.where("event_type <> 'error'").select("event_id", "user_id", "us", F.floor(F.col("us") / hour).alias("h"))
    return errors.join(others, ["user_id", "h"]).where((F.col("us") >= F.col("at") - hour) & (F.col("us") < F.col("at"))).select("error_id", "event_id")


@query("o18_as_of_join", "select e.event_id as error_id, o.event_id as last_id from (select * from events where event_type = 'error') e asof left join (select * from events where event_type <> 'error') o on e.user_id = o.user_id and o.event_id <= e.event_id")
def o18(spark, sf_dir):
    """Union and a running last value: one shuffle by user, no pairs. Ids run in time order."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") != "error", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_id", last).where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "last_id")


both("o19_interval_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and b.ts <= a.ts + interval 10 minutes")


@query("o20_similarity_join", f"with {PAIRS_SQL} select a, b, round(d, 6) as d from pairs where d <= 1.15 and a % 100 = 0")
def o20(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.within(e, e.where("point % 100 = 0"), 1.15).select(F.col("query").alias("a"), F.col("point").alias("b"), F.round("dist", 6).alias("d"))


both("o21_lateral_explode", "select doc_id, count(*) as n from documents lateral view explode(split(text, '\\n')) x as line where line <> '' group by doc_id", "select doc_id, count(*) as n from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where line <> '' group by doc_id")


@query("o22_salted_join", "select o_orderstatus, count(*) as n, round(sum(w), 2) as w from orders join (select unnest(['O', 'F', 'P']) as s, unnest([1.0, 2.0, 3.0])::double as w) on s = o_orderstatus group by 1")
def o22(spark, sf_dir):
    """Few hot keys: the large side is dealt over 16 salts, the small side is repeated for each."""
    small = spark.createDataFrame([("O", 1.0), ("F", 2.0), ("P", 3.0)], "s string, w double").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
    big = t(spark, sf_dir, "orders").select("o_orderstatus", F.pmod(F.xxhash64("o_orderkey"), F.lit(16)).cast("int").alias("salt"))
    return big.join(small.hint("merge"), (F.col("s") == F.col("o_orderstatus")) & (big.salt == small.salt)).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("w"), 2).alias("w"))


# ---------------------------------------------------------------- aggregates

both("o23_hash_aggregate", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem group by l_returnflag, l_linestatus")
both("o24_multi_distinct", "select o_orderpriority, count(distinct o_custkey) as customers, count(distinct o_orderstatus) as states from orders group by o_orderpriority")
both("o25_grouping_sets", "select l_returnflag, l_linestatus, grouping(l_returnflag) * 2 + grouping(l_linestatus) as gid, count(*) as n from lineitem group by grouping sets ((l_returnflag, l_linestatus), (l_returnflag), ())", "select l_returnflag, l_linestatus, (grouping(l_returnflag) * 2 + grouping(l_linestatus))::bigint as gid, count(*) as n from lineitem group by grouping sets ((l_returnflag, l_linestatus), (l_returnflag), ())")


@query("o26_pivot", "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as f, count(*) filter (o_orderstatus = 'O') as o from orders group by 1")
def o26(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


both("o27_extremes_and_lists", "select o_orderpriority, max_by(o_orderkey, o_totalprice) as dearest, count_if(o_orderstatus = 'F') as done, array_join(array_sort(collect_set(o_orderstatus)), ',') as states from orders group by o_orderpriority", "select o_orderpriority, max_by(o_orderkey, o_totalprice) as dearest, count(*) filter (o_orderstatus = 'F') as done, array_to_string(list_sort(list_distinct(list(o_orderstatus))), ',') as states from orders group by o_orderpriority")
both("o28_moments", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_quantity), 6) as v, round(corr(l_quantity, l_extendedprice), 6) as c, round(percentile(l_quantity, 0.9), 6) as p90 from lineitem group by l_returnflag", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_quantity), 6) as v, round(corr(l_quantity, l_extendedprice), 6) as c, round(quantile_cont(l_quantity, 0.9), 6) as p90 from lineitem group by l_returnflag")


@query("o29_sketches")
def o29(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers"))


@query("o29_distinct_sketches", "select l_returnflag, true as parts, true as suppliers, true as median, true as top from lineitem group by l_returnflag")
def o29_checked(spark, sf_dir):
    """Sketches of three kinds and approximate most frequent items, each against the exact answer: within three per cent, and the same most frequent item."""
    lines = t(spark, sf_dir, "lineitem")
    rough = lines.groupBy("l_returnflag").agg(
        F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")).alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers"),
        F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("l_quantity"), F.lit(0.5)).alias("median"), F.expr("approx_top_k(l_linenumber, 1, 100)").alias("top"))
    exact = lines.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts0"), F.countDistinct("l_suppkey").alias("suppliers0"), F.expr("percentile(l_quantity, 0.5)").alias("median0"), F.mode("l_linenumber").alias("top0"), F.max("l_quantity").alias("most"))
    most = lines.groupBy("l_returnflag", "l_linenumber").agg(F.count("*").alias("k")).groupBy("l_returnflag").agg(F.max("k").alias("most_rows"))
    near = lambda a, b: F.abs(F.col(a) - F.col(b)) <= 0.03 * F.col(b) + 1e-9
    both_of = rough.join(exact, "l_returnflag").join(most, "l_returnflag")
    return both_of.select("l_returnflag", near("parts", "parts0").alias("parts"), near("suppliers", "suppliers0").alias("suppliers"), (F.abs(F.col("median") - F.col("median0")) <= 0.03 * F.col("most")).alias("median"), (F.col("top")[0]["count"] == F.col("most_rows")).alias("top"))


both("o30_bitmap_distinct", "select sum(n) as n from (select bitmap_bucket_number(o_custkey) as b, bitmap_count(bitmap_construct_agg(bitmap_bit_position(o_custkey))) as n from orders group by 1)", "select count(distinct o_custkey) as n from orders")

# ---------------------------------------------------------------- windows, sorts, sets

both("o31_ranks", "select c_custkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as q, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from customer window w as (partition by c_nationkey order by c_acctbal, c_custkey)")
both("o32_neighbours_in_order", "select event_id, lag(event_type) over w as before, lead(event_type) over w as after, first_value(event_type) over w as first, nth_value(event_type, 2) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by event_id)")
both("o33_frames", "select event_id, sum(case when event_type = 'error' then 1 else 0 end) over (partition by user_id order by event_id rows between unbounded preceding and current row) as errors, count(*) over (partition by user_id order by event_id rows between 3 preceding and current row) as last4 from events", "select event_id, sum(case when event_type = 'error' then 1 else 0 end) over (partition by user_id order by event_id rows between unbounded preceding and current row)::bigint as errors, count(*) over (partition by user_id order by event_id rows between 3 preceding and current row) as last4 from events")


@query("o34_sort", "select row_number() over (order by c_acctbal desc, c_custkey) as pos, c_custkey from customer")
def o34(spark, sf_dir):
    """A global sort by ranges; places from sizes of the ranges, so no single task numbers all rows."""
    rows = t(spark, sf_dir, "customer").select("c_custkey", "c_acctbal").repartitionByRange(F.desc("c_acctbal"), F.asc("c_custkey")).withColumn("part", F.spark_partition_id())
    rows = wl.stored(rows, "ranges")
    starts = rows.groupBy("part").agg(F.count("*").alias("n")).selectExpr("part", "sum(n) over (order by part) - n as before")
    local = rows.withColumn("k", F.row_number().over(Window.partitionBy("part").orderBy(F.desc("c_acctbal"), "c_custkey")))
    return local.join(F.broadcast(starts), "part").select((F.col("before") + F.col("k")).cast("long").alias("pos"), "c_custkey")  # one row a partition


both("o35_top_per_group", "select c_nationkey, c_custkey from (select *, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as r from customer) where r <= 3")
both("o36_set_operations", "(select o_custkey as k from orders where o_orderstatus = 'P' intersect select c_custkey from customer where c_acctbal > 0) union all (select c_custkey from customer where c_acctbal < 0 except select o_custkey from orders)")

# ---------------------------------------------------------------- scalar families

both("o37_strings", "select p_partkey, upper(p_name) as u, lpad(cast(p_size as string), 4, '0') as z, translate(p_brand, '#', '-') as b, substring(p_type, 1, 5) as s, levenshtein(p_name, p_type) as d, regexp_replace(p_name, '[aeiou]', '') as c from part", "select p_partkey, upper(p_name) as u, lpad(cast(p_size as varchar), 4, '0') as z, translate(p_brand, '#', '-') as b, substring(p_type, 1, 5) as s, levenshtein(p_name, p_type)::int as d, regexp_replace(p_name, '[aeiou]', '', 'g') as c from part")
both("o38_hashes", "select doc_id, md5(text) as m, sha2(text, 256) as s from documents", "select doc_id, md5(text) as m, sha256(text) as s from documents")
both("o39_dates", "select event_id, date_format(date_trunc('hour', ts), 'yyyy-MM-dd HH') as h, extract(dow from ts) as dow, cast(datediff(ts, timestamp_ntz '2024-01-01 00:00:00') as int) as days from events", "select event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H') as h, extract(dow from ts)::int + 1 as dow, date_diff('day', date '2024-01-01', ts::date)::int as days from events")
both("o40_math", "select l_orderkey, l_linenumber, round(sqrt(l_quantity) + ln(l_quantity) + exp(l_discount) + pow(l_quantity, 0.5), 6) as m, greatest(l_discount, l_tax) as g, pmod(l_partkey - 100, 7) as p from lineitem", "select l_orderkey, l_linenumber, round(sqrt(l_quantity) + ln(l_quantity) + exp(l_discount) + pow(l_quantity, 0.5), 6) as m, greatest(l_discount, l_tax) as g, (((l_partkey - 100) % 7) + 7) % 7 as p from lineitem")


@query("o41_arrays", "select vec_id, len(list_filter(v, lambda x: x > 0))::bigint as positive, round(list_sum(v[1:8]), 6) as head, len(list_distinct(list_transform(v, lambda x: floor(x * 10))))::bigint as bins from (select vec_id, embedding::double[] as v from embeddings)")
def o41(spark, sf_dir):
    v = vec.as_double(F.col("embedding"))
    return t(spark, sf_dir, "embeddings").select("vec_id", F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate(F.slice(v, 1, 8), F.lit(0.0), lambda s, x: s + x), 6).alias("head"), F.size(F.array_distinct(F.transform(v, lambda x: F.floor(x * 10)))).cast("long").alias("bins"))


@query("o42_maps", "select conv_id, count(distinct role) as roles, max(length(text)) as longest from conversations group by conv_id")
def o42(spark, sf_dir):
    by = t(spark, sf_dir, "conversations").groupBy("conv_id", "role").agg(F.max(F.char_length("text")).alias("n")).groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m"))
    return by.select("conv_id", F.size(F.map_keys("m")).cast("long").alias("roles"), F.array_max(F.map_values("m")).cast("long").alias("longest"))


both("o43_json", "select event_id, from_json(props, 'k int').k as k, variant_get(parse_json(props), '$.k', 'int') as k2 from events", "select event_id, cast(json_extract_string(props, '$.k') as int) as k, cast(json_extract_string(props, '$.k') as int) as k2 from events")
both("o44_try", "select event_id, round(try_divide(value, cast(get_json_object(props, '$.k') as int)), 6) as r, coalesce(nullif(event_type, 'error'), 'none') as e from events", "select event_id, round(case when cast(json_extract_string(props, '$.k') as int) = 0 then null else value / cast(json_extract_string(props, '$.k') as int) end, 6) as r, coalesce(nullif(event_type, 'error'), 'none') as e from events")

# ---------------------------------------------------------------- user functions


@query("o45_sql_functions", "select vec_id, round(sqrt(list_inner_product(v, v)), 6) as length from (select vec_id, embedding::double[] as v from embeddings)")
def o45(spark, sf_dir):
    sqlfuncs.register(spark)
    register(spark, sf_dir, "embeddings")
    return spark.sql("select vec_id, round(sqrt(dot_product(cast(embedding as array<double>), cast(embedding as array<double>))), 6) as length from embeddings")


@query("o45_sql_trace_functions", f"with {LINES_SQL} select crash_id, md5(string_agg({_no_args('line')}, chr(10) order by pos)) as digest from k group by crash_id")
def o45_traces(spark, sf_dir):
    """The argument-free trace by the SQL function: the same text as the column form gives."""
    sqlfuncs.register(spark)
    fr.collapse_lines(corpus.planted(spark, sf_dir)).createOrReplaceTempView("collapsed")
    return spark.sql("select crash_id, md5(coarse_trace(lines)) as digest from collapsed")


@query("o45_sql_normalise", "select vec_id, round(list_inner_product(u, u), 6) as length, round(u[1], 6) as first from (select vec_id, list_transform(v, lambda x: x / sqrt(list_inner_product(v, v))) as u from (select vec_id, embedding[1:16]::double[] as v from embeddings))")
def o45_normalise(spark, sf_dir):
    sqlfuncs.register(spark)
    register(spark, sf_dir, "embeddings")
    return spark.sql("select vec_id, round(dot_product(u, u), 6) as length, round(u[0], 6) as first from (select vec_id, l2_normalise(truncate_vec(cast(embedding as array<double>), 16)) as u from embeddings)")


@query("o46_arrow_function")
def o46(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", sqlfuncs.hash_embed(F.col("text")).alias("vec"))


@query("o47_grouped_function", "select label, round(avg(embedding[1]), 6) as first from embeddings group by label")
def o47(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").groupBy("label").agg(sqlfuncs.vec_mean(F.col("embedding")).alias("m")).select("label", F.round(F.col("m")[0], 6).alias("first"))


@query("o47_grouped_sum", "select label, round(sum(embedding[1]), 5) as first from embeddings group by label")
def o47_sum(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").groupBy("label").agg(sqlfuncs.vec_sum(F.col("embedding")).alias("m")).select("label", F.round(F.col("m")[0], 5).alias("first"))


@query("o48_explode_frames", f"with {PARSED_SQL.replace(LINES_SQL, LINES_SQL.replace('where copy = 1', ''))} select crash_id, (pos - 1)::int as pos, idx, func, site from p")
def o48(spark, sf_dir):
    sqlfuncs.register(spark)
    corpus.planted(spark, sf_dir).createOrReplaceTempView("crashes")
    return spark.sql("select crash_id, x.pos, x.idx, x.func, x.site from crashes, lateral explode_frames(trace) x")


@query("o49_apply_in_arrow", "select o_orderpriority as target, count(*) as n, round(sum(o_totalprice), 2) as total from orders group by 1")
def o49_arrow(spark, sf_dir):
    def run(group: pa.Table) -> pa.Table:
        import pyarrow.compute as pc

        return pa.table({"target": [group.column("target")[0].as_py()], "n": [group.num_rows], "total": [pc.sum(group.column("price")).as_py()]})

    orders = t(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("target"), F.col("o_totalprice").alias("price"))
    return orders.groupBy("target").applyInArrow(run, "target string, n long, total double").withColumn("total", F.round("total", 2))


@query("o49_map_in_arrow", "select doc_id, strlen(text) as n from documents")
def o49(spark, sf_dir):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.binary_length(b.column(1)).cast(pa.int64())], names=["doc_id", "n"])

    return t(spark, sf_dir, "documents").select("doc_id", "text").mapInArrow(run, "doc_id long, n long")


@query("o49_cogrouped", "select c_custkey, coalesce(n, 0) as n from customer left join (select o_custkey, count(*) as n from orders group by 1) on o_custkey = c_custkey")
def o49_cogrouped(spark, sf_dir):
    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_custkey": a["c_custkey"], "n": len(b)}) if len(a) else pd.DataFrame({"c_custkey": pd.Series(dtype="int64"), "n": pd.Series(dtype="int64")})

    a, b = t(spark, sf_dir, "customer").select("c_custkey"), t(spark, sf_dir, "orders").select("o_custkey")
    return a.groupBy("c_custkey").cogroup(b.groupBy("o_custkey")).applyInPandas(run, "c_custkey long, n long")


# ---------------------------------------------------------------- neighbours

_ASKED = f"{PAIRS_SQL}, r as (select a, b, d, row_number() over (partition by a order by d, b) as r from pairs where a % 100 = 0)"


@query("o50_knn", f"with {_ASKED} select a, b, round(d, 6) as d, r from r where r <= 10")
def o50(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.knn(e, e.where("point % 100 = 0"), 10).select(F.col("query").alias("a"), F.col("point").alias("b"), F.round("dist", 6).alias("d"), F.col("rank").cast("long").alias("r"))


@query("o51_within", f"with {_ASKED} select a, b, round(d, 6) as d from r where d <= 1.2")
def o51(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.within(e, e.where("point % 100 = 0"), 1.2).select(F.col("query").alias("a"), F.col("point").alias("b"), F.round("dist", 6).alias("d"))


@query("o52_knn_approximate")
def o52(spark, sf_dir):
    """Recall of the index against the exact search over the same queries."""
    e = wl.vectors_of(spark, sf_dir)
    q = e.where("point % 100 = 0")
    exact, near = nb.knn(e, q, 10).select("query", "point"), nb.knn_approximate(e, q, 10).select("query", "point", F.lit(1).alias("hit"))
    return exact.join(near, ["query", "point"], "left").groupBy("query").agg(F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"))


@query("o53_assign_new", f"with {_ASKED} select a as point, case when d <= 1.2 then b % 7 end as bucket from r where r = 1")
def o53(spark, sf_dir):
    e = wl.vectors_of(spark, sf_dir)
    return nb.assign_new(e.select("point", (F.col("point") % 7).alias("bucket")), e, e.where("point % 100 = 0"), 1.2)


@query("o54_representatives", "select 'all' as target, label as bucket, min(vec_id) as point from embeddings group by label")
def o54(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), F.col("label").alias("bucket"), F.col("vec_id").alias("point"))
    return nb.representatives(e, e)


@query("o54_medoids")
def o54_medoids(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), F.col("label").alias("bucket"), F.col("vec_id").alias("point"), vec.as_double(F.col("embedding")).alias("vec"))
    return nb.representatives(e, e, "medoid")


@query("o55_triage", "select o_orderpriority as target, o_orderstatus as bucket, count(*) as n, min(o_orderkey) as crash_id from orders group by all")
def o55(spark, sf_dir):
    return nb.triage(t(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("target"), F.col("o_orderstatus").alias("bucket"), F.col("o_orderkey").alias("crash_id")))


# ---------------------------------------------------------------- streams, run to the end of what is there

query("o56_arrival_half", "select crash_id, target from (select o_orderkey as crash_id, o_orderpriority as target from orders)")(st.arrival_half)
query("w14_prepare_stream", ORACLES["o56_arrival_half"])(st.arrival_half)
query("o57_first_seen", "select event_type || ':' || cast(json_extract_string(props, '$.k') as int) as key from events group by 1")(st.first_seen)
query("o58_tumbling", "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events where date_trunc('day', ts) < (select date_trunc('day', max(ts)) from events) group by all")(st.tumbling)
query("o58_sliding", "with w as (select event_type, unnest([epoch(ts)::bigint // 43200 * 43200, epoch(ts)::bigint // 43200 * 43200 - 43200]) as s from events) select strftime(make_timestamp(s * 1000000), '%Y-%m-%d %H') as start, event_type, count(*) as n from w where make_timestamp((s + 86400) * 1000000) <= (select max(ts) from events) group by all")(st.sliding)
query("o58_sessions", "with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as fresh from events), g as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as s from e) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as first, count(*) as n from g group by user_id, s having max(ts) + interval 30 minutes <= (select max(ts) from events)")(st.sessions)
query("o59_late_rows", "with m as (select make_timestamp((epoch_us(min(ts)) + epoch_us(max(ts))) // 2) as middle, max(ts) as last from events) select event_type, count(*) as rows, count(*) filter (ts >= middle and date_trunc('hour', ts) + interval 1 hour <= last - interval 1 day) as in_time, true as only_newer from events, m group by event_type")(st.late_rows)
query("o60_trace_assembly", "with e as (select event_id, user_id, event_type, event_type || ':' || cast(json_extract_string(props, '$.k') as int) as frame, coalesce(sum(case when event_type = 'error' then 1 else 0 end) over (partition by user_id order by event_id rows between unbounded preceding and 1 preceding), 0) as s from events), r as (select *, row_number() over (partition by user_id, s order by event_id desc) as r from e where event_type <> 'error'), x as (select user_id, s, string_agg(frame, chr(10) order by r) as trace from r where r <= 5 group by all) select e.user_id, event_id as error_id, coalesce(trace, '') as trace from e left join x on x.user_id = e.user_id and x.s = e.s where event_type = 'error'")(st.trace_assembly)
query("o61_stream_stream", "select e.event_id as error_id, p.event_id from events e join events p on p.user_id = e.user_id and p.ts >= e.ts - interval 1 hour and p.ts < e.ts where e.event_type = 'error' and p.event_type = 'purchase'")(st.stream_stream)
query("o56_arrival_points", f"with {POINTS_SQL} select target, point, weight, 64 as width from points")(lambda spark, sf_dir: st.planted_arrivals(spark, sf_dir).select("target", "point", "weight", F.size("vec").alias("width")))
query("w14_arrived_buckets")(st.arrived_buckets)
query("o62_assigned_at_arrival", ORACLES["o53_assign_new"])(st.assigned_at_arrival)
query("o61_stream_static", "select event_id, u.n from events e join (select user_id, count(*) as n from events group by user_id) u using (user_id) where event_type = 'error'")(st.stream_static)
query("w14_stream_equals_batch")(st.stream_equals_batch)
