"""Stand-in crash corpora as views over the given tables. Integer arithmetic and md5 only, so that any SQL engine renders the same text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import frames as fr
from .tables import load, register

#: Bugs per target, in order of the targets' first digit, and the error kinds.
BUGS = {"1": 6, "2": 1, "3": 4, "4": 8, "5": 2}
KINDS = ["heap-buffer-overflow", "stack-buffer-overflow", "heap-use-after-free", "integer-overflow", "null-dereference", "divide-by-zero"]
#: Every which order is a deep recursion, and every which has no report.
DEEP, DEPTH, UNREPORTED = 499, 2000, 160


def _joined(dialect: str, count: str, body: str) -> str:
    """SQL for `body` (over i = 1..count) joined by line ends."""
    if dialect == "spark":
        return f"array_join(transform(sequence(1, {count}), i -> {body}), chr(10))"
    return f"array_to_string(list_transform(range(1, {count} + 1), lambda i: {body}), chr(10))"


def planted_sql(dialect: str = "spark", hard: bool = False) -> str:
    """SELECT of crash_id, target, trace, report, label, input_name, bug_key over orders and lineitem.

    hard: two neighbouring bugs share their three outer frames, and the outermost two of these come in three shapes, so that one bug has several
    call paths and two bugs have nearly one.
    """
    bugs = "case substr(o_orderpriority, 1, 1) " + " ".join(f"when '{k}' then {n}" for k, n in BUGS.items()) + " end"
    kinds = "case cast((instr('0123456789abcdef', substr(md5(bug_key), 1, 1)) - 1) % 6 as int) " + " ".join(f"when {i} then '{k}'" for i, k in enumerate(KINDS)) + " end"

    def bug_frame(d: int) -> str:
        key = "bug_key" if not hard or d <= 5 else "pair_key" if d == 6 else "concat(pair_key, '/', shape)"
        h = f"md5(concat({key}, '/', {d}))"
        name = f"concat('fn_', substr({h}, 1, 6){', ' + repr('<int>') if d % 5 == 0 else ''})"
        nested = ", ', cb=(fn (*)(int))'" if d % 3 == 0 else ""
        gap = "chr(10), '    at'" if d % 4 == 0 else "' at'"
        return f"concat('#{d + 1} 0x', substr({h}, 7, 8), ' in ', {name}, ' (ctx=0x7f', seed, '0, n=', seed{nested}, ')', {gap}, ' src/', substr({h}, 15, 3), '.c:', {d * 7})"

    def driver_frame(d: int) -> str:
        return f"concat('#', {10 + d} + depth, ' 0x', substr(md5(concat(target, '/driver/', {d})), 1, 8), ' in drive_{d}_', substr(md5(target), 1, 5), ' (arg=', seed, ') at app/drive.c:{d * 11}')"

    rec = "concat('#', 9 + i, ' 0x', substr(md5(concat(bug_key, '/rec')), 1, 8), ' in walk_', substr(md5(bug_key), 1, 5), ' (node=0x5', seed, ') at src/walk.c:77')"
    frames = ", ".join(["'#0 0x10 in rt_abort () from /lib/librt.so'", "'#1 0x11 in rt_report (code=6) at rt/report.c:10'", *[bug_frame(d) for d in range(1, 9)]])
    tail = ", ".join([f"concat('#', 10 + depth, ' 0x', substr(md5(concat(target, '/entry/', variant)), 1, 8), ' in entry_', variant, ' (mode=', variant, ') at app/entry.c:', 20 + variant)", *[driver_frame(d) for d in (1, 2, 3)], "concat('#', 14 + depth, ' 0x40 in main (argc=2) at app/main.c:5')"])
    return f"""
with counted as (
    select o_orderkey, o_custkey, o_orderpriority as target, {bugs} as bugs, coalesce(n, 0) as n
    from orders left join (select l_orderkey, cast(count(*) as int) as n from lineitem group by l_orderkey) l on l_orderkey = o_orderkey
), placed as (
    select o_orderkey as crash_id, target, cast(o_custkey % bugs as int) as bug, cast(o_orderkey % 7 as int) as seed,
        cast(cast(floor(o_orderkey / 8) as bigint) % 3 as int) as variant, cast(case when o_orderkey % {DEEP} = 0 then {DEPTH} else n end as int) as depth,
        cast(cast(floor(o_orderkey / 64) as bigint) % 3 as int) as shape from counted
), keyed as (
    select *, concat(target, '#', bug) as bug_key, concat(target, '#pair', cast(floor(bug / 2) as int)) as pair_key from placed
), traced as (
    select *, concat_ws(chr(10), {frames}) as head, case when depth > 0 then {_joined(dialect, 'depth', rec)} else '' end as walk, concat_ws(chr(10), {tail}) as tail, {kinds} as kind from keyed
)
select crash_id, target, concat(head, chr(10), walk, case when depth > 0 then chr(10) else '' end, tail) as trace,
    case when crash_id % {UNREPORTED} = 0 then null else concat('==1==ERROR: Sanitizer: ', kind, ' on address 0x60', seed, '0', chr(10), 'READ of size ', 1 + bug % 4, chr(10), head, chr(10),
        'SUMMARY: Sanitizer: ', kind, chr(10), 'Shadow bytes around the buggy address:', chr(10), '  0x0c0', seed, ': fa fa 00 00', chr(10), '=>0x0c1', seed, ': fa[fa]00 00', chr(10),
        'Shadow byte legend (one shadow byte represents 8 application bytes):', chr(10), '  Addressable:           00', chr(10), '  Heap left redzone:       fa') end as report,
    bug_key as label, concat(bug_key, '/id-', crash_id, '.bin') as input_name
from traced"""


#: Orders that a task renders. They weigh a hundredth of their texts, so by their bytes alone one task would get nearly all.
RENDERED = 10_000


def planted(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """Corpus A: one crash per order; the bug of a crash is known. Orders are dealt out by key, which the join with their lines asks for anyway, to a fixed
    number of partitions, which is not lowered for small rows."""
    session = register(spark, sf_dir, "orders", "lineitem")
    orders = session.table("orders")
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-orders.count() // RENDERED))
    try:
        orders.repartition(n, "o_orderkey").createOrReplaceTempView("orders")
        return session.sql(planted_sql(hard=hard))
    finally:
        register(spark, sf_dir, "orders")


def prepared(crashes: DataFrame) -> DataFrame:
    """crash_id, target, full, coarse, report: the three texts of each crash, repeats dropped once for both traces."""
    return fr.collapse_lines(crashes).select("crash_id", "target", fr.full_trace(F.col("lines")).alias("full"), fr.coarse_trace(F.col("lines")).alias("coarse"), fr.strip_shadow(fr.strip_report_trace(F.col("report"))).alias("report"), fr.report_with_trace(F.col("report")).alias("report_all"))


#: Types of the planted bugs: each has one by the digits of its key, every third a second; two-level.
BUG_TYPE_SQL = """
with bugs as (select distinct label, cast(substr(label, instr(label, '#') + 1) as int) as bug from truth),
typed as (
    select label, case when bug % 3 = 0 then 'bounds-read' when bug % 3 = 1 then 'bounds-write' else 'arithmetic-overflow' end as type from bugs
    union all select label, 'null-pointer' as type from bugs where bug % 3 = 0
)
select label, type, case when type like 'bounds%' then 'bounds' when type like 'arithmetic%' then 'arithmetic' else type end as parent from typed
"""


def document_crashes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Corpus B: a document is a crash, its lines are frames, the language is the target."""
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("crash_id"), F.col("lang").alias("target"), F.col("text").alias("trace"), F.split("text", "\n")[0].alias("report"))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Corpus C: (run_id, user_id, target, crashed, pos, event_id, event_type, k): events of a user up to each error.

    One shuffle by user. run_id numbers sessions by their first event.
    """
    e = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = e.withColumn("session", F.coalesce(F.sum(F.when(F.col("event_type") == "error", 1).otherwise(0)).over(before), F.lit(0)))
    s = Window.partitionBy("user_id", "session")
    return e.select(F.min("event_id").over(s).alias("run_id"), "user_id", (F.col("user_id") % 14).alias("target"), (F.max(F.when(F.col("event_type") == "error", 1).otherwise(0)).over(s) == 1).alias("crashed"), F.row_number().over(s.orderBy("ts", "event_id")).alias("pos"), "event_id", "event_type", "k")


SESSIONS_SQL = """
with e as (select event_id, ts, user_id, event_type, cast(json_extract_string(props, '$.k') as int) as k from events),
c as (select *, coalesce(sum(case when event_type = 'error' then 1 else 0 end) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding), 0) as session from e)
select min(event_id) over w as run_id, user_id, user_id % 14 as target, max(case when event_type = 'error' then 1 else 0 end) over w = 1 as crashed,
    row_number() over (partition by user_id, session order by ts, event_id) as pos, event_id, event_type, k
from c window w as (partition by user_id, session)"""


def blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(run_id, block, crashed): basic blocks of runs; the error itself is left out.

    Healthy runs: the open tails, and windows of four events without an error.
    """
    s = sessions(spark, sf_dir)
    named = s.where("event_type <> 'error'").withColumn("block", F.concat_ws(":", "event_type", "k"))
    windows = named.where("crashed").withColumn("w", F.floor((F.col("pos") - 1) / 4)).withColumn("size", F.count("*").over(Window.partitionBy("run_id", "w"))).where("size = 4")
    healthy = windows.select((-(F.col("run_id") * 1000 + F.col("w")) - 1).alias("run_id"), "block", F.lit(False).alias("crashed"))
    return named.select("run_id", "block", "crashed").union(healthy).distinct()


BLOCKS_SQL = f"""
with s as ({SESSIONS_SQL}), named as (select *, concat_ws(':', event_type, k) as block from s where event_type <> 'error'),
w as (select *, cast(floor((pos - 1) / 4) as bigint) as w from named where crashed), z as (select *, count(*) over (partition by run_id, w) as size from w)
select distinct run_id, block, crashed from (select run_id, block, crashed from named union all select -(run_id * 1000 + w) - 1, block, false from z where size = 4)"""
