"""The experiments as plans over the stand-in corpora: buckets, scores, ablations, comparisons."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import frames as fr
from ..functions import vectors as vec
from ..operators import baselines as base
from ..operators import measures as ms
from ..operators.collapse import SOURCE_CONFIGS, collapse_exact
from ..operators.embed import MODELS, Embedder, build_points, embed_with_store, missing_texts, texts_by_hash
from ..sources import corpus
from ..sources.tables import load
from .bucketer import Config, bucket_any, expand, search_runs


def scratch(spark: SparkSession) -> str:
    """A folder that all executors share: the session's checkpoint folder, a temporary one only where none is named."""
    return f"{spark.conf.get('spark.checkpoint.dir', None) or spark.sparkContext.getCheckpointDir() or tempfile.gettempdir()}/buckets-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Written once and read back, so that later steps start from it."""
    path = f"{scratch(df.sparkSession)}-{name}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def vectors_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Corpus E as points of one target."""
    return load(spark, sf_dir, "embeddings").select(F.lit("all").alias("target"), F.col("vec_id").alias("point"), vec.l2_normalise(vec.as_double(F.col("embedding"))).alias("vec"))


def planted_points(spark: SparkSession, sf_dir: str, config: str = "all", embedder: Embedder | None = None, how: str = "sum", store: str | None = None, hard: bool = False) -> tuple[DataFrame, DataFrame]:
    """(points with vectors, members) of corpus A for a source configuration."""
    sources = SOURCE_CONFIGS[config]
    prepared = stored(corpus.prepared(corpus.planted(spark, sf_dir, hard)).select("crash_id", "target", *sources), "prepared")
    points, members = collapse_exact(prepared, sources)
    points, members = stored(points, "points"), stored(members, "members")
    vectors = embed_with_store(texts_by_hash(prepared, sources), embedder or MODELS["hosted_3072"], store or f"{scratch(spark)}-store")
    return stored(build_points(points, vectors, sources, how).select("target", "point", "weight", "vec"), "vectors"), members


def planted_truth(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    return corpus.planted(spark, sf_dir, hard).select("target", "crash_id", "label")


def planted_buckets(spark: SparkSession, sf_dir: str, config: str = "all", embedder: Embedder | None = None, search: Config = Config(), hard: bool = False) -> DataFrame:
    points, members = planted_points(spark, sf_dir, config, embedder, hard=hard)
    return expand(bucket_any(points, search, keep=stored), members)


def planted_scores(spark: SparkSession, sf_dir: str, config: str = "all", embedder: Embedder | None = None) -> DataFrame:
    return ms.score(planted_buckets(spark, sf_dir, config, embedder), planted_truth(spark, sf_dir))


def planted_clusterer(spark: SparkSession, sf_dir: str, method: str) -> DataFrame:
    """Scores of another clustering of the same points."""
    points, members = planted_points(spark, sf_dir)
    run = {"dbscan": lambda p: base.dbscan_search(p), "kmeans": lambda p: base.kmeans_search(p)}[method]
    return ms.score(expand(run(points), members), planted_truth(spark, sf_dir))


def framed(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """Corpus A with parsed frames after repeats are dropped."""
    return fr.once(fr.collapse_lines(corpus.planted(spark, sf_dir, hard)), frames=fr.parse_lines(F.col("lines")))


def planted_stack_hash(spark: SparkSession, sf_dir: str, top_n: int | None = None, hard: bool = False) -> DataFrame:
    return base.stack_hash(fr.collapse_lines(corpus.planted(spark, sf_dir, hard)), ("func", "site"), top_n)


def named(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """(target, crash_id, label, n, names, inner): function and site of each crash's frames, a line each; for each frame 1 or 0, whether its index is 7 or
    more; n is 1. Functions are cut out of the whole trace, no frame is parsed."""
    crashes = fr.once(fr.collapse_lines(corpus.planted(spark, sf_dir, hard)), names=fr.places(F.col("lines")))
    deep = F.transform("lines", lambda x: F.coalesce(F.regexp_extract(x, r"^\s*#(\d+)\s", 1).try_cast("int") >= 7, F.lit(False)).cast("int").cast("string"))
    return crashes.select("target", "crash_id", "label", F.lit(1).cast("long").alias("n"), "names", F.array_join(deep, "").alias("inner"))


def shapes(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """The same for crashes of one target and bug that agree in names and inner, as one row: the least crash, and in n how many there are. Methods that look at
    nothing else give each of them the bucket of this row."""
    groups = named(spark, sf_dir, hard).groupBy("target", "label", "names", "inner").agg(F.min("crash_id").alias("crash_id"), F.count("*").alias("n"))
    return stored(groups.select("target", "crash_id", "label", "n", "names", "inner"), "shapes")


def functions_of(crashes: DataFrame) -> DataFrame:
    """(target, crash_id, n, pos, func, inner): functions of each crash's frames in order. crashes: as of `named`."""
    each = F.transform(F.split("names", "\n"), lambda x, i: F.struct(F.regexp_replace(x, r"\|[^|]*$", "").alias("func"), (F.substring("inner", i + 1, F.lit(1)) == "1").alias("inner")))
    return crashes.select("target", "crash_id", "n", F.posexplode(each).alias("pos", "x")).select("target", "crash_id", "n", "pos", "x.func", "x.inner")


def hashes_of(crashes: DataFrame) -> DataFrame:
    """(target, crash_id, bucket): the stack hash by function and site. crashes: as of `named`."""
    return crashes.select("target", "crash_id", F.sha2("names", 256).alias("bucket"))


def cfg_of(crashes: DataFrame, similarity: str = "edge_jaccard", fallback: bool = True) -> DataFrame:
    """Graph buckets; with fallback, whichever of these and stack hashing has fewer per target. crashes: as of `named`."""
    edges = base.edges_of(functions_of(crashes), "pos", "func")
    features = edges.select("target", "crash_id", F.col("edge").alias("feature")) if similarity == "edge_jaccard" else base.wl_labels(stored(edges, "edges"))
    own = stored(base.cfg_buckets(stored(features, "features")), "graphs")
    return base.fewer_clusters(own, stored(hashes_of(crashes), "hashes")) if fallback else own


def planted_cfg(spark: SparkSession, sf_dir: str, similarity: str = "edge_jaccard", fallback: bool = True, hard: bool = False) -> DataFrame:
    """Graph buckets of every crash."""
    return cfg_of(named(spark, sf_dir, hard), similarity, fallback)


def blocks_of(crashes: DataFrame) -> DataFrame:
    """(target, run_id, block, crashed, n), functions as blocks. A healthy run stands for each crash: it takes the same way in, down to the sixth frame of the
    bug, and never reaches the frames above. n: how many runs the row stands for."""
    frames = functions_of(crashes).where("func <> ''")
    healthy = frames.where("inner and func not like 'walk%'")
    each = lambda df, run, crashed: df.select("target", run.alias("run_id"), F.col("func").alias("block"), F.lit(crashed).alias("crashed"), "n").distinct()
    return each(frames, F.col("crash_id"), True).union(each(healthy, -F.col("crash_id") - 1, False))


def mutual_information_of(crashes: DataFrame, top_m: int = 16) -> DataFrame:
    """(target, crash_id, bucket): the top_m blocks of each target decide."""
    blocks = stored(blocks_of(crashes), "blocks")
    return base.mutual_information_buckets(blocks, top_m, by=("target",), weight="n").select("target", F.col("run_id").alias("crash_id"), "bucket")


#: The methods that the workflow is compared with: buckets (target, crash_id, bucket) of crashes, or of rows that stand for several.
METHODS = {"stack_hash": hashes_of, "mutual_information": mutual_information_of, "cfg_similarity": cfg_of}


def method_cells(crashes: DataFrame, method: str) -> DataFrame:
    """(target, label, bucket, n): the contingency table of a method on all crashes that the rows stand for."""
    return ms.contingency(METHODS[method](crashes), crashes.select("target", "crash_id", "label", "n"), weight="n")


def compared(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """(method, target, label, bucket, n): the contingency tables of the workflow and the other methods on the same crashes."""
    cells = {"workflow": ms.contingency(planted_buckets(spark, sf_dir, hard=hard), planted_truth(spark, sf_dir, hard))}
    rows, out = shapes(spark, sf_dir, hard), None
    for name, one in (cells | {name: method_cells(rows, name) for name in METHODS}).items():
        one = one.select(F.lit(name).alias("method"), "*")
        out = one if out is None else out.unionByName(one)
    return stored(out, "compared")


def method_scores(cells: DataFrame) -> DataFrame:
    """(method, target, n_bugs, n_buckets, purity, inverse_purity, f_measure) of compared methods, one plan for all."""
    named = cells.select(F.struct("method", "target").alias("target"), "label", "bucket", "n")
    return ms.score_cells(named).select("target.method", "target.target", "n_bugs", "n_buckets", "purity", "inverse_purity", "f_measure")


def method_type_reports(cells: DataFrame, types: DataFrame) -> DataFrame:
    """(method, level, name, n, over_mean, over_sd, under_mean, under_sd): the report by bug type for each method. Labels are scored once, in one plan for all."""
    named = cells.select(F.struct("method", "target").alias("target"), "label", "bucket", "n")
    scores = stored(ms.label_scores(named).select("target.method", "target.target", "label", "over", "under"), "scores")
    return ms.type_report(scores, types, by=("method",))


def planted_costs(spark: SparkSession, sf_dir: str, config: Config = Config()) -> DataFrame:
    """(counter, value) of one run of the workflow: what was embedded, what the store spared, distances, selections made and spared by the search."""
    sources = SOURCE_CONFIGS["all"]
    log = ms.CostLog()
    prepared = stored(log.observe(corpus.prepared(corpus.planted(spark, sf_dir)).select("crash_id", "target", *sources), "crashes"), "prepared")
    points, _ = collapse_exact(prepared, sources)
    points, store, model = stored(log.observe(points, "points"), "points"), f"{scratch(spark)}-store", MODELS["hosted_3072"]
    texts = stored(log.observe(texts_by_hash(prepared, sources), "texts"), "texts")
    vectors = embed_with_store(texts, model, store)
    log.add("text_bytes", texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
    log.add("text_references", points.agg(*[F.count(f"h_{s}").alias(s) for s in sources]).select(sum((F.col(s) for s in sources), F.lit(0))).first()[0])
    again = missing_texts(texts, spark.read.parquet(f"{store}/model={model.name}")).count()
    log.add("embedded_again", again)
    log.add("store_hits_again", texts.count() - again)
    built = stored(build_points(points, vectors, sources), "built")
    runs = search_runs(built, config).agg(F.count("*").alias("made"), F.countDistinct("target", "partition_hash").alias("different")).first()
    targets = built.groupBy("target").agg(F.countDistinct("vec").alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("pairs"), F.count_if(F.col("n") > 1).alias("k")).first()
    log.add("distance_evaluations", targets["pairs"])
    log.add("selections_made", runs["made"])
    log.add("selections_spared", 2 * config.num_steps * targets["k"] - runs["made"])
    log.add("partitions_assessed", runs["different"])
    return spark.createDataFrame(sorted(log.counters().items()), "counter string, value long")


def clean_truth(truth: DataFrame, merges: DataFrame, dropped: DataFrame) -> DataFrame:
    """Ground truth after merging labels of one root cause and dropping ambiguous ones; both tables are a few rows."""
    kept = truth.join(F.broadcast(dropped.select("label")), "label", "left_anti")
    return kept.join(F.broadcast(merges.select("label", "into")), "label", "left").select("target", "crash_id", F.coalesce("into", "label").alias("label"))
