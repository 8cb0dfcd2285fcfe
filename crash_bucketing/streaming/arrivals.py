"""The arrival half as streams: everything up to the points runs as crashes come in; clustering waits for the batch half.

Every query here runs to the end of what is there (availableNow) and returns what its sink holds. Sinks are Parquet with a
checkpoint, so a restarted stream neither loses nor repeats rows.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.collapse import SOURCES, collapse_exact, hashed
from ..operators.embed import MODELS, Embedder, build_points, embed_with_store, texts_by_hash
from ..operators.neighbours import assign_new
from ..plans.bucketer import bucket, own_buckets
from ..plans.workloads import scratch, stored, vectors_of
from ..sources import corpus
from ..sources.tables import SCHEMAS, load


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream. Watermarks need an instant, so the local time is cast."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append", path: str | None = None) -> DataFrame:
    """Run a stream to the end of its input into a Parquet sink and read it. path: of a sink that is gone on with."""
    path = path or scratch(stream.sparkSession)
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-checkpoint").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def crash_files(spark: SparkSession, sf_dir: str) -> str:
    """A folder with the crashes of the planted corpus."""
    path = scratch(spark)
    corpus.planted(spark, sf_dir).write.parquet(path)
    return path


def arriving(spark: SparkSession, path: str) -> DataFrame:
    """Crashes of a folder as files that arrive."""
    return spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", 4).parquet(path)


def crash_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Crashes of the planted corpus as files that arrive."""
    return arriving(spark, crash_files(spark, sf_dir))


def _digests(crashes: DataFrame) -> DataFrame:
    """Stateless: parse, collapse repeats, clean, digest. The same plan serves batch and stream."""
    return hashed(corpus.prepared(crashes), SOURCES)


#: Up to so many different pairs of trace and report are parsed once each and sent round as digests (16 MB).
SHARED = 50_000


def digests_once(crashes: DataFrame) -> DataFrame:
    """The same rows as _digests, of a batch or micro-batch whose crashes often have equal texts: those are told by the digests of the raw texts, one crash of each kind is
    parsed, and all its kind take its digests. Where more than SHARED differ, every crash is parsed."""
    kind = [F.coalesce(F.sha2(c, 256), F.lit("")).alias(f"_{c}") for c in ("trace", "report")]
    keys = ["_trace", "_report"]
    raw = stored(crashes.select("crash_id", "target", *kind), "raw")
    firsts = stored(raw.groupBy(*keys).agg(F.min("crash_id").alias("crash_id")), "kinds")
    if firsts.count() > SHARED:
        return _digests(crashes)
    some = crashes.select("crash_id", "target", "trace", "report").join(F.broadcast(firsts.select("crash_id").distinct()), "crash_id", "left_semi")
    own = stored(some.select("*", *kind).dropDuplicates(keys), "firsts")
    if own.groupBy("crash_id").count().where("count > 1").count():  # an id of several crashes: kinds can not be told by it
        return _digests(crashes)
    texts = _digests(own).drop("target").join(own.select("crash_id", *keys), "crash_id")
    digests = stored(texts.select(*keys, *[f"h_{s}" for s in SOURCES]), "digests")
    return raw.join(F.broadcast(digests), keys).select("crash_id", "target", *[f"h_{s}" for s in SOURCES])


def arrival_half(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(_digests(crash_stream(spark, sf_dir))).select("crash_id", "target")


def arrived_digests(crashes: DataFrame) -> DataFrame:
    """Digests of a stream of crashes; a micro-batch that is run again replaces what it wrote."""
    sink = scratch(crashes.sparkSession)

    def arrive(batch: DataFrame, number: int) -> None:
        digests_once(batch).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    crashes.writeStream.foreachBatch(arrive).option("checkpointLocation", f"{sink}-checkpoint").trigger(availableNow=True).start().awaitTermination()
    digests = _digests(crashes)
    return crashes.sparkSession.read.schema(digests.schema).parquet(sink).select(digests.columns)


def apart(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row, `different`: rows that only one side has, each as often as it has more of them; one shuffle of both."""
    sides = [df.select("crash_id", "target", *[F.unhex(f"h_{s}").alias(f"h_{s}") for s in SOURCES], F.lit(sign).cast("long").alias("n")) for df, sign in ((a, 1), (b, -1))]
    rows = sides[0].unionAll(sides[1]).groupBy("crash_id", "target", *[f"h_{s}" for s in SOURCES]).agg(F.abs(F.sum("n")).alias("n"))
    return rows.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("different"))


def stream_equals_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row: digests that only the stream or only the batch has (none)."""
    path = crash_files(spark, sf_dir)
    return apart(arrived_digests(arriving(spark, path)), digests_once(spark.read.parquet(path)))


def arrival_points(crashes: DataFrame, embedder: Embedder, sources: list[str] = SOURCES) -> DataFrame:
    """The whole arrival half over a stream of crashes: parse, clean, collapse, embed through the store, combine. Returns (target, point, weight, vec).

    A micro-batch writes its points under its own number, so a batch that is run again replaces what it wrote, and texts already in the store are not
    embedded twice. Points that several batches have are put together at the end: the least crash names them, weights add up.
    """
    spark = crashes.sparkSession
    sink = scratch(spark)

    def arrive(batch: DataFrame, number: int) -> None:
        prepared = stored(corpus.prepared(batch).select("crash_id", "target", *sources), "prepared")
        points = stored(collapse_exact(prepared, sources)[0], "points")
        vectors = embed_with_store(texts_by_hash(prepared, sources), embedder, f"{sink}-store")
        build_points(points, vectors, sources).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    crashes.writeStream.foreachBatch(arrive).option("checkpointLocation", f"{sink}-checkpoint").trigger(availableNow=True).start().awaitTermination()
    keys = [f"h_{s}" for s in sources]
    every = spark.read.parquet(sink).groupBy("target", *keys).agg(F.min("point").alias("point"), F.sum("weight").alias("weight"), F.first("vec").alias("vec"))
    return every.select("target", "point", "weight", "vec")


def planted_arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return arrival_points(crash_stream(spark, sf_dir), MODELS["hosted_3072"])


def arrived_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(target, n_points, n_crashes, n_buckets): the batch half over the points that the stream left."""
    points = stored(planted_arrivals(spark, sf_dir), "arrived")
    named = own_buckets(bucket(points))
    return named.join(points.select("target", "point", "weight"), ["target", "point"]).groupBy("target").agg(F.count("*").alias("n_points"), F.sum("weight").alias("n_crashes"), F.countDistinct("bucket").alias("n_buckets"))


def assigned_at_arrival(spark: SparkSession, sf_dir: str, eps: float = 1.2) -> DataFrame:
    """(point, bucket): vectors as they come take the bucket of the nearest known point within eps; a batch that is run again replaces what it wrote."""
    known = stored(vectors_of(spark, sf_dir), "known")
    buckets, sink = known.select("point", (F.col("point") % 7).alias("bucket")), scratch(spark)
    known.where("point % 100 = 0").repartition(2).write.parquet(f"{sink}-new")

    def arrive(batch: DataFrame, number: int) -> None:
        assign_new(buckets, known, batch, eps).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    new = spark.readStream.schema(known.schema).option("maxFilesPerTrigger", 1).parquet(f"{sink}-new")
    new.writeStream.foreachBatch(arrive).option("checkpointLocation", f"{sink}-checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(sink).select("point", "bucket")


def first_seen(spark: SparkSession, sf_dir: str, horizon: str = "40 days") -> DataFrame:
    """Each (event type, k) once, within the horizon; beyond it the store's anti-join decides."""
    e = events(spark, sf_dir).select("ts", F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")).alias("key"))
    return drained(e.withWatermark("ts", horizon).dropDuplicatesWithinWatermark(["key"])).select("key")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per type and day. A day is put out once the watermark has passed it, so the last one stays open."""
    counts = events(spark, sf_dir).withWatermark("ts", "0 seconds").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return drained(counts.select(F.col("window.start").alias("start"), "event_type", "n")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per type in windows of a day that begin every twelve hours; a window is put out once the watermark has passed it.

    Times count to the nearest second, as in the SQL, an even one at the half. The watermark is of these, so a window that ends in the last event's own second may
    be put out early: such a one is left out.
    """
    second = F.timestamp_seconds(F.rint(F.unix_micros("ts") / 1e6).cast("long"))
    counts = events(spark, sf_dir).withColumn("at", second).withWatermark("at", "0 seconds").groupBy(F.window("at", "1 day", "12 hours"), "event_type").agg(F.count("*").alias("n"))
    last = load(spark, sf_dir, "events").agg(F.max(F.col("ts").cast("timestamp")).alias("last"))  # one row
    rows = drained(counts.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), "event_type", "n"))
    return rows.crossJoin(F.broadcast(last)).where("end <= last").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


def sessions(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """(user_id, first, n): runs of a user's events with no longer gap; a session is put out once the watermark has passed its end."""
    counts = events(spark, sf_dir).withWatermark("ts", "0 seconds").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return drained(counts.select("user_id", F.col("session_window.start").alias("first"), "n")).select("user_id", F.date_format("first", "yyyy-MM-dd HH:mm:ss").alias("first"), "n")


def late_rows(spark: SparkSession, sf_dir: str, delay: str = "1 day") -> DataFrame:
    """Events in two runs of one stream, the newer half first: per type, all rows, those put out, and whether these are of the newer half. Rows that lie more
    than the delay behind the newest row seen come too late and are dropped; windows that the last watermark has not passed stay open."""
    path, sink = scratch(spark), scratch(spark)
    e = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    ends = e.agg(F.min("ts").alias("a"), F.max("ts").alias("z")).first()
    middle = ends["a"] + (ends["z"] - ends["a"]) / 2 if ends["a"] else None
    for half in (F.col("ts") >= F.lit(middle), F.col("ts") < F.lit(middle)):  # the stream stops between the two and goes on from its checkpoint
        e.where(half).write.mode("append").parquet(path)
        rows = spark.readStream.schema(e.schema).parquet(path)
        counts = rows.withWatermark("ts", delay).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
        kept = drained(counts.select(F.col("window.start").alias("start"), "event_type", "n"), path=sink)
    every = load(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("rows"))
    return every.join(kept.groupBy("event_type").agg(F.sum("n").alias("in_time"), F.min("start").alias("first")), "event_type", "left").select("event_type", "rows", "in_time", (F.col("first") >= F.date_trunc("hour", F.lit(middle))).alias("only_newer"))


def trace_assembly(spark: SparkSession, sf_dir: str, last: int = 5, forget_days: int = 400) -> DataFrame:
    """(user_id, error_id, trace): for each error the last events of its user since the error before, newest first, at most `last`.

    State: at most `last` short texts a user, given up when a user has been silent for longer than `forget_days` behind the watermark.
    """

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        held = json.loads(state.get[0]) if state.exists else []
        rows = pd.concat(list(batches)).sort_values("event_id")  # one user's rows of one micro-batch
        out = []
        for event_id, kind, frame in zip(rows["event_id"], rows["event_type"], rows["frame"], strict=True):
            if kind == "error":
                out.append((key[0], event_id, "\n".join(held)))
                held = []
            else:
                held = [frame, *held][:last]
        state.update((json.dumps(held),))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), int(rows["ts"].max().timestamp() * 1000)) + forget_days * 86_400_000)
        yield pd.DataFrame(out, columns=["user_id", "error_id", "trace"])

    e = events(spark, sf_dir).withWatermark("ts", "1 hour").select("user_id", "event_id", "event_type", "ts", F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")).alias("frame"))
    return drained(e.groupBy("user_id").applyInPandasWithState(run, "user_id long, error_id long, trace string", "pending string", "append", GroupStateTimeout.EventTimeTimeout))


def stream_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(error_id, event_id): errors with the purchases of the same user in the hour before. Both sides are streams; their watermarks and the
    bounds of the join let old rows be forgotten."""
    e = events(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "1 hour")
    bought = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts").withWatermark("ts", "1 hour")
    return drained(errors.join(bought, F.expr("u = user_id and ts >= at - interval 1 hour and ts < at")).select("error_id", "event_id"))


def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors as they come, beside the number of events that their user has in the batch table."""
    users = load(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    return drained(events(spark, sf_dir).where("event_type = 'error'").select("event_id", "user_id").join(users, "user_id").select("event_id", "n"))
