"""Stack traces and sanitizer reports as column expressions: parse, collapse, strip. No Python touches a row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: How a frame begins, and how deep argument lists nest at most.
FRAME_START = r"(?m)^\s*#\d+\s"
NESTING = 6

FRAME_TYPE = "array<struct<idx:int,addr:string,func:string,args:string,site:string,lib:string,raw:string>>"


def frame_lines(trace: Column) -> Column:
    """Array of frame texts: a line that starts no frame is joined to the frame before it."""
    joined = F.regexp_replace(F.regexp_replace(F.regexp_replace(trace, "\r", ""), r"^\s+|\s+$", ""), r"\n(?!\s*#\d+\s)\s*", " ")
    return F.filter(F.split(joined, "\n"), lambda x: F.trim(x) != "")


def without_arguments(text: Column) -> Column:
    """Remove every parenthesised list within a line, innermost first; call operators and unnamed namespaces are kept."""
    out = F.replace(F.replace(text, F.lit("operator()"), F.lit("operator\x01")), F.lit("(anonymous namespace)"), F.lit("\x02"))
    for _ in range(NESTING):
        out = F.regexp_replace(out, r" ?\([^()\n]*\)", "")
    return F.replace(F.replace(out, F.lit("\x01"), F.lit("()")), F.lit("\x02"), F.lit("(anonymous namespace)"))


def once(df: DataFrame, **columns: Column) -> DataFrame:
    """Add columns that are computed once per row, however often later expressions use them (a generator of one row stops inlining)."""
    held = df.select("*", F.explode(F.array(F.struct(*[c.alias(n) for n, c in columns.items()]))).alias("_once"))
    return held.select(*[F.col(c) for c in df.columns if c not in columns], *[F.col(f"_once.{n}").alias(n) for n in columns])


def parse_lines(lines: Column) -> Column:
    """Array of structs of frame texts. A text without an index is a raw frame: all null but raw."""
    empty_null = lambda c: F.nullif(c, F.lit(""))
    bodies = F.split(F.regexp_replace(without_arguments(F.array_join(lines, "\n")), r"(?m)^\s*#\d+\s+(0x[0-9a-fA-F]+ in )?", ""), "\n")
    bare = F.zip_with(lines, bodies, lambda x, y: F.struct(x.alias("raw"), F.regexp_extract(x, r"^\s*#(\d+)\s", 1).alias("idx"), y.alias("body")))

    def parse(s: Column) -> Column:
        framed = s["idx"] != ""
        return F.struct(
            empty_null(s["idx"]).cast("int").alias("idx"),
            F.when(framed, empty_null(F.regexp_extract(s["raw"], r"\b(0x[0-9a-fA-F]+) in ", 1))).alias("addr"),
            F.when(framed, F.trim(F.regexp_replace(s["body"], r" (at \S+:\d+|from \S+)\s*$", ""))).alias("func"),
            F.when(framed, empty_null(F.regexp_extract(s["raw"], r"(\(.*\))", 1))).alias("args"),
            F.when(framed, empty_null(F.regexp_extract(s["body"], r" at (\S+:\d+)\s*$", 1))).alias("site"),
            F.when(framed, empty_null(F.regexp_extract(s["body"], r" from (\S+)\s*$", 1))).alias("lib"),
            s["raw"].alias("raw"),
        )

    return F.transform(bare, parse)


def parse_frames(trace: Column) -> Column:
    return parse_lines(frame_lines(trace))


def line_key(line: Column, key: str) -> Column:
    """What makes two frames the same: their text without the index, or without index, address and arguments."""
    if key == "site":
        return F.regexp_replace(without_arguments(line), r"^\s*#\d+\s+(0x[0-9a-fA-F]+ in )?", "")
    return F.regexp_replace(line, r"^\s*#\d+\s+", "")


def collapse_lines(crashes: DataFrame, key: str = "text", scope: str = "trace") -> DataFrame:
    """crashes with `trace`, and `lines`: frame texts, repeats but the topmost left out; indices keep their gaps.

    scope 'trace': anywhere in the trace: keys are sorted with their places, so equal ones stand together and the first of each stays; frames times
    their logarithm, however many differ. scope 'run': only neighbours.
    """
    df = once(crashes, _lines=frame_lines(F.col("trace")))
    if scope == "run":
        df = once(df, _keys=F.transform("_lines", lambda x: line_key(x, key)))
        kept = F.filter("_lines", lambda x, i: (i == 0) | (F.get("_keys", i) != F.get("_keys", i - 1)))
    else:
        df = once(df, _keys=F.array_sort(F.transform("_lines", lambda x, i: F.struct(line_key(x, key).alias("k"), i.alias("i")))))
        firsts = F.filter("_keys", lambda x, i: (i == 0) | (x["k"] != F.get("_keys", i - 1)["k"]))
        kept = F.transform(F.array_sort(F.transform(firsts, lambda x: x["i"])), lambda i: F.get("_lines", i))
    return once(df, lines=kept).drop("_lines", "_keys")


def places(lines: Column) -> Column:
    """Function and site of each frame, a line `func|site` for each; both empty for a text that is no frame. All of a trace at once: no frame is parsed."""
    text = F.regexp_replace(without_arguments(F.array_join(lines, "\n")), r"(?m)^(?!\s*#\d+\s).*$", "#0 ")
    bodies = F.regexp_replace(text, r"(?m)^\s*#\d+[ \t]+(0x[0-9a-fA-F]+ in )?", "")
    return F.regexp_replace(bodies, r"(?m)^(.*?)[ \t]*(?: at (\S+:\d+)| from \S+)?[ \t]*$", "$1|$2")


def collapse_long(crashes: DataFrame, key: str = "text") -> DataFrame:
    """(crash_id, lines): the same by rows, for traces of very many different frames: map-side minima, one shuffle, no nested look-up."""
    rows = crashes.select("crash_id", F.posexplode(frame_lines(F.col("trace"))).alias("pos", "line"))
    firsts = rows.groupBy("crash_id", line_key(F.col("line"), key).alias("k")).agg(F.min(F.struct("pos", "line")).alias("x"))
    return firsts.groupBy("crash_id").agg(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["line"]).alias("lines"))


def full_trace(lines: Column) -> Column:
    return F.array_join(lines, "\n")


def coarse_trace(lines: Column) -> Column:
    """Trace without any argument list: index, address, function, library, file and line stay."""
    return without_arguments(F.array_join(lines, "\n"))


def strip_report_trace(report: Column) -> Column:
    """A sanitizer report without its copy of the stack trace, wrapped frame lines included."""
    return F.array_join(F.filter(F.split(F.regexp_replace(report, r"\n\s+at ", " at "), "\n"), lambda x: ~x.rlike(r"^\s*#\d+\s")), "\n")


def strip_shadow(report: Column) -> Column:
    """A sanitizer report without the shadow byte map and its legend."""
    kept = F.filter(F.split(report, "\n"), lambda x: ~x.rlike(r"^(Shadow bytes|Shadow byte legend|  [A-Z][A-Za-z ]*: +[0-9a-f]{2}|(=>|  )0x[0-9a-f]+:)"))
    return F.array_join(kept, "\n")


def report_with_trace(report: Column) -> Column:
    """Reports-only variant: the trace stays, the shadow map goes."""
    return strip_shadow(report)


def neutral_name(name: Column, number: Column) -> Column:
    """A generic name in place of one that may tell the bug; the extension stays."""
    return F.concat(F.lit("input-"), number.cast("string"), F.regexp_extract(name, r"(\.[A-Za-z0-9]+)$", 1))
