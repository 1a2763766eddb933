"""Queries that train, sweep, stream, or run Python functions; most have invariants in tests
instead of SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchselect.functions import features as fe
from sketchselect.functions import udfs
from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import sketch as sk
from sketchselect.operators import theory
from sketchselect.operators.kernel import Schedule, StopRule, TrainSpec
from sketchselect.operators.trainer import Model, fit
from sketchselect.plans import relational, selection, simulation, tasks, workloads
from sketchselect.sources import gauss, sparse_text
from sketchselect.streaming import events as ev
from sketchselect.streaming import training
from sketchselect.tables import load, new_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if oracle is not None:
            ORACLES[name or f.__name__] = oracle
        return f

    return keep


# ---- trained models

WORDS_CF, WORDS_K = 10.0, 100


def _trained(task: str, method: str, cf: float = WORDS_CF, k: int = WORDS_K, mode: str = "replay", **kw):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        train, _, p = workloads.prepared(spark, sf_dir, task)
        extra = {x: kw[x] for x in ("shards", "rounds") if x in kw}
        more = {x: v for x, v in kw.items() if x not in extra}
        sketch, spec = workloads.spec_of(task, method, cf, p, k, **more)
        return fit(train, sketch, spec, mode, **extra).topk_df().select("class", "rank", "feature_id", F.round("estimate", 6).alias("estimate"))

    return run


for _name, _args in {
    "train_curvature_words": ("words", "curvature"), "train_gradient_words": ("words", "gradient"), "train_dense_sgd_words": ("words", "dense_sgd"),
    "train_dense_qn_words": ("words", "dense_qn"), "train_hashed_words": ("words", "hashed"), "train_curvature_grams": ("grams", "curvature"),
    "train_curvature_clicks": ("clicks", "curvature"), "train_curvature_pages": ("pages", "curvature"), "train_curvature_toxic": ("toxic", "curvature"),
    "train_null_control": ("null_control", "curvature"), "train_roles": ("roles", "curvature"), "train_multiclass_lang": ("kmers", "curvature"),
    "train_multiclass_gradient": ("kmers", "gradient"),
}.items():
    QUERIES[_name] = _trained(*_args)
QUERIES["train_shared_lang"] = _trained("kmers", "curvature", layout="shared")
QUERIES["train_newton_embed"] = _trained("embed", "newton", cf=1.0, k=4, eta=0.5)
QUERIES["train_curvature_embed"] = _trained("embed", "curvature", cf=1.0, k=4, eta=0.01)
QUERIES["train_sharded_words"] = _trained("words", "curvature", mode="sharded", shards=4)


@query()
def train_sync_words(spark, sf_dir):
    """Distributed vectors over a few large minibatches."""
    rows = fe.number_batches(tasks.words(spark, sf_dir).drop("split"), 400)
    train = TrainSpec(k=WORDS_K, schedule=Schedule(0.01))
    return fit(rows, SketchSpec(5, 2048, 7), train, "sync").topk_df().select("class", "rank", "feature_id", F.round("estimate", 6).alias("estimate"))


# ---- curves

# Every curve is over workloads.CURVE and every method; the selected-features study over its own k.
for _task in ("words", "grams", "kmers", "clicks", "toxic"):
    QUERIES["sweep_cf" if _task == "words" else f"sweep_cf_{_task}"] = (lambda t: lambda spark, sf_dir: workloads.compression_curve(spark, sf_dir, t, k=500))(_task)
for _task in ("words", "grams", "kmers", "clicks"):
    QUERIES["sweep_topk" if _task == "words" else f"sweep_topk_{_task}"] = (lambda t: lambda spark, sf_dir: workloads.selected_curve(spark, sf_dir, t))(_task)
QUERIES["sweep_eta"] = lambda spark, sf_dir: workloads.search_eta(spark, sf_dir, "words")
QUERIES["search_batch"] = lambda spark, sf_dir: workloads.search_batch(spark, sf_dir, "toxic")
QUERIES["sweep_tau"] = workloads.history_curve
QUERIES["ablation_words"] = workloads.ablation
QUERIES["layouts_kmers"] = workloads.layouts
QUERIES["runtime_table"] = workloads.runtime
QUERIES["word_report"] = workloads.word_report
QUERIES["convergence_words"] = workloads.convergence
QUERIES["library_ceiling"] = workloads.library_ceiling
QUERIES["scaled_ids"] = lambda spark, sf_dir: workloads.scaled_ids(spark, sf_dir, 2)
QUERIES["scaled_model"] = lambda spark, sf_dir: workloads.scaled_model(spark, sf_dir, 2)
# The simulations do not depend on the tables. All sizes and steps, but 4 and 2 of the 200 trials that
# the functions run by default (see the README for their time).
QUERIES["simulation_recovery"] = lambda spark, sf_dir: simulation.recovery_curve(spark, 4)
QUERIES["simulation_steps"] = lambda spark, sf_dir: simulation.step_curve(spark, 2)


# ---- approximate aggregates that Spark has (rows only)

for _name, _text in {
    "agg_approx_distinct": "SELECT lang, approx_count_distinct(text) AS n FROM {documents} GROUP BY lang",
    "agg_hll": "SELECT lang, hll_sketch_estimate(hll_sketch_agg(text)) AS n FROM {documents} GROUP BY lang",
    "agg_kll": "SELECT event_type, round(kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D), 3) AS mid FROM {events} GROUP BY event_type",
    "agg_theta": "SELECT lang, theta_sketch_estimate(theta_sketch_agg(text)) AS n FROM {documents} GROUP BY lang",
    "agg_cms": "SELECT length(count_min_sketch(user_id, 0.01D, 0.95D, 1)) AS bytes FROM {events}",
    "agg_percentile_approx": "SELECT event_type, percentile_approx(value, 0.9D) AS q9 FROM {events} GROUP BY event_type",
    "agg_histogram": "SELECT event_type, size(histogram_numeric(value, 10)) AS bins FROM {events} GROUP BY event_type",
    "variant_props": "SELECT event_id, try_variant_get(parse_json(props), '$.k', 'int') AS k FROM {events}",
    "strat_sample": "SELECT doc_id FROM {documents} TABLESAMPLE (10 PERCENT) REPEATABLE (1)",
}.items():
    QUERIES[_name] = (lambda text: lambda spark, sf_dir: relational.run(text, spark, sf_dir))(_text)


@query("SELECT doc_id FROM documents WHERE (CAST('0x' || substr(md5('sample:' || doc_id), 1, 13) AS BIGINT)::DOUBLE / 4503599627370496.0) < 0.1")
def hash_sample(spark, sf_dir):
    return load(spark, sf_dir, "documents").filter(fe.draw(F.lit("sample"), F.col("doc_id")) < 0.1).select("doc_id")


# ---- Python functions, against the built-in forms


@query(selection.ORACLES["sketch_query_median"])
def udf_sketch_score(spark, sf_dir):
    cells = np.zeros((selection.SPEC.rows, selection.SPEC.buckets))
    for r in selection.sketch_build_lineitem(spark, sf_dir).collect():
        cells[r["row"], r["bucket"]] = r["value"]
    ids = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("feature_id"))
    return ids.withColumn("estimate", udfs.sketch_reader(selection.SPEC, cells)("feature_id"))


@query("SELECT id, sign FROM (" + selection.ORACLES["hash_affine"] + ") WHERE j = 2")
def udf_arrow_sign(spark, sf_dir):
    return load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), udfs.signs(selection.SPEC, 2)("p_partkey").alias("sign"))


@query(selection.ORACLES["auc_topk"])
def udaf_auc(spark, sf_dir):
    rows = selection._decided(spark, sf_dir)
    return rows.groupBy(F.lit(1).alias("one")).agg(udfs.auc("score", "label").alias("auc")).select(F.round("auc", 6).alias("auc"))


@query("SELECT DISTINCT item_id, substr(text, i, 4) AS feature FROM (SELECT item_id, text, unnest(range(1, length(text) - 2)) AS i FROM benchmark)")
def udtf_features(spark, sf_dir):
    spark.udtf.register("explode_features", udfs.ExplodeFeatures)
    return spark.sql("SELECT item_id, f.feature FROM {b} b, LATERAL explode_features(b.text, 'gram', 4) f", b=load(spark, sf_dir, "benchmark"))


@query("SELECT doc_id AS id, CAST(len(string_split(text, ' ')) AS BIGINT) AS words FROM documents")
def map_in_arrow_counts(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", "text").mapInArrow(udfs.word_lengths, "id long, words long")


@query("SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY event_type")
def apply_in_pandas_stats(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").applyInPandas(udfs.value_stats, "event_type string, n long, mean double")


@query("SELECT n_nationkey AS k, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS left_rows, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS right_rows FROM nation WHERE left_rows > 0 OR right_rows > 0")
def cogroup_est_true(spark, sf_dir):
    a = load(spark, sf_dir, "customer").groupBy("c_nationkey")
    b = load(spark, sf_dir, "supplier").groupBy("s_nationkey")
    return a.cogroup(b).applyInPandas(udfs.matched, "k int, left_rows long, right_rows long")


# ---- sources and sinks


def _roundtrip(kind: str):
    def run(spark, sf_dir):
        path = new_path(spark, kind)
        rows = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice")
        writer = rows.write.option("header", True) if kind == "csv" else rows.write
        writer.format(kind).save(path)
        return spark.read.schema(rows.schema).option("header", kind == "csv").format(kind).load(path)

    return run


for _kind in ("parquet", "csv", "json", "orc"):
    QUERIES[f"{_kind}_roundtrip"] = _roundtrip(_kind)
    ORACLES[f"{_kind}_roundtrip"] = "SELECT o_orderkey, o_custkey, o_orderstatus, o_totalprice FROM orders"


@query("SELECT vec_id AS example_id, 4::INTEGER AS n, round(list_sum(list_transform(embedding[1:4], lambda x: x::DOUBLE * 8)), 4) AS total FROM embeddings")
def sparse_text_roundtrip(spark, sf_dir):
    rows = tasks.embed(spark, sf_dir).select(F.col("example_id").cast("double").alias("label"), F.slice("idx", 1, 4).alias("idx"), F.slice("val", 1, 4).alias("val"))
    path = new_path(spark, "sparse")
    sparse_text.write(rows, path)
    back = sparse_text.read(spark, path)
    total = F.aggregate("val", F.lit(0.0), lambda s, x: s + x)
    return back.select(F.col("label").cast("long").alias("example_id"), F.size("idx").alias("n"), F.round(total, 4).alias("total"))


@query()
def sparse_source(spark, sf_dir):
    """The Python data source, with its filter on the label."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", True)
    spark.dataSource.register(sparse_text.SparseLinesSource)
    names = load(spark, sf_dir, "nation")  # a table of fixed size, so its lines fit an option
    rows = fe.packed(names, "n_nationkey", F.col("n_regionkey"), fe.char_ngrams(F.col("n_name"), 3))
    lines = "\n".join(r[0] for r in sparse_text.to_lines(rows).collect())
    return spark.read.format("sparse_lines").option("lines", lines).load().filter("label = 0").select("label", F.size("idx").alias("n"))


@query()
def gauss_source(spark, sf_dir):
    """The given vectors' planted regression with noise; the data source deals one normal to each row."""
    spark.dataSource.register(gauss.GaussSource)
    rows = tasks.embed(spark, sf_dir).select("example_id", "label", "val")
    last = rows.agg(F.coalesce(F.max("example_id"), F.lit(-1))).first()[0]
    noise = spark.read.format("gauss").options(rows=str(last + 1), features="1", planted="1", partitions=str(spark.sparkContext.defaultParallelism)).load()
    noisy = rows.join(noise.select("example_id", F.col("val")[0].alias("noise")), "example_id")
    return noisy.select("example_id", F.round(F.col("label") + 0.1 * F.col("noise"), 6).alias("label"), F.round(F.col("val")[0], 6).alias("first"))


@query()
def model_roundtrip(spark, sf_dir):
    rows = fe.number_batches(tasks.toxic(spark, sf_dir).drop("split"), 64)
    path = new_path(spark, "model")
    fit(rows, SketchSpec(5, 512, 7), TrainSpec(k=50, schedule=Schedule(0.05), stop=StopRule(1))).save(path)
    return Model.load(spark, path).topk_df()


@query(
    "SELECT d.doc_id AS example_id, CAST(count(DISTINCT word) AS INTEGER) AS n FROM labels l JOIN (SELECT doc_id, text, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM documents) d ON l.doc_id = d.doc_id "
    "WHERE CAST('0x' || substr(md5(d.text), 1, 15) AS BIGINT) % 10 >= 8 GROUP BY d.doc_id"
)
def scan_pruned(spark, sf_dir):
    """Packed examples written by split and batch group; the scan opens the test files only."""
    path = new_path(spark, "packed")
    tasks.toxic(spark, sf_dir).write.partitionBy("split").parquet(path)
    return spark.read.parquet(path).filter("split = 'test' and size(idx) > 0").select("example_id", F.size("idx").alias("n"))


@query()
def theory_table(spark, sf_dir):
    """Sizes by the theory for the tasks' shapes: order of cells, not constants."""
    rows = [
        (p, k, eps, delta, *map(float, (theory.topk_cells(p, k, 1.0, 0.1, eps, delta), *theory.convergence_size(eps, delta), theory.corollary_size(p, k, 1.0, 0.1, eps, delta))))
        for p in (1000, 68_724, 54_686_452) for k in (8, 1000) for eps, delta in ((0.5, 0.1), (0.1, 0.01))
    ]
    return spark.createDataFrame(rows, "p long, k long, eps double, delta double, topk_cells double, buckets double, rows double, corollary double")


@query()
def training_log(spark, sf_dir):
    """Per step: loss, gradient norm, pairs kept, active features, heap changes, memory."""
    train, _, p = workloads.prepared(spark, sf_dir, "toxic")
    return fit(train, *workloads.spec_of("toxic", "curvature", 10.0, p, 100)).log_df()


QUERIES["search_best"] = lambda spark, sf_dir: workloads.searched(spark, sf_dir, "toxic", (0.01, 0.1), (10.0, 100.0))

# ---- streams

_TUMBLE = relational.ORACLES["win_tumbling"]


@query(_TUMBLE)
def stream_tumbling(spark, sf_dir):
    return ev.run_once(ev.tumbling(ev.source(spark, sf_dir)), "tumbling", "complete")


@query(relational.ORACLES["win_sliding"])
def stream_sliding(spark, sf_dir):
    return ev.run_once(ev.sliding(ev.source(spark, sf_dir)), "sliding", "complete")


@query(relational.ORACLES["win_session"])
def stream_session(spark, sf_dir):
    return ev.run_once(ev.sessions(ev.source(spark, sf_dir)), "session", "complete")


@query("SELECT event_id, user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return ev.run_once(ev.deduplicated(ev.source(spark, sf_dir)), "dedup")


@query(relational.ORACLES["join_interval"])
def stream_interval_join(spark, sf_dir):
    return ev.run_once(ev.purchases_after_views(ev.source(spark, sf_dir)), "interval")


@query("SELECT event_id, CASE event_type WHEN 'view' THEN 0.5 WHEN 'purchase' THEN 2.0 ELSE 0.0 END::DOUBLE AS score FROM events")
def stream_static_score(spark, sf_dir):
    weights = spark.createDataFrame([("view", 0.5), ("purchase", 2.0)], "event_type string, weight double")
    return ev.run_once(ev.scored(ev.source(spark, sf_dir), weights), "scored")


@query(
    selection._cells_sql("SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, user_id AS feature_id, 1.0::DOUBLE AS value FROM events", "start,")
)
def stream_sketch_by_hour(spark, sf_dir):
    return ev.run_once(ev.sketch_by_hour(ev.source(spark, sf_dir), selection.SPEC), "hours", "complete")


@query("SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY user_id")
def stream_stateful_user(spark, sf_dir):
    return ev.run_once(ev.user_totals(ev.source(spark, sf_dir)), "users", "update").select("user_id", "n", F.round("total", 4).alias("total"))


@query()
def stream_watermark_late(spark, sf_dir):
    """Hourly counts of files of which the third, the first hour's rows, comes weeks too late and is dropped."""
    path = new_path(spark, "late")
    rows = load(spark, sf_dir, "events")
    ends = rows.agg(F.min("ts").alias("first"), F.max("ts").alias("last")).first()
    later = rows.filter(F.col("ts") > F.lit(ends["first"]) + F.expr("INTERVAL 1 DAY"))
    for part in (0, 1):  # late rows are judged by the watermark of the batch before the last
        later.filter(F.col("event_id") % 2 == part).coalesce(1).write.mode("append").parquet(path)
    rows.filter(F.col("ts") <= F.lit(ends["first"]) + F.expr("INTERVAL 1 HOUR")).coalesce(1).write.mode("append").parquet(path)
    rows.filter(F.col("ts") == F.lit(ends["last"])).withColumn("ts", F.col("ts") + F.expr("INTERVAL 9 DAYS")).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return ev.run_once(ev.tumbling(stream), "late")


@query()
def stream_train(spark, sf_dir):
    path = new_path(spark, "examples")
    rows = fe.number_batches(tasks.toxic(spark, sf_dir).drop("split"), 64)
    training.replayable(rows, path, 3)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return training.fit_stream(stream, SketchSpec(5, 512, 7), TrainSpec(k=50, schedule=Schedule(0.05))).topk_df()


@query(selection.ORACLES["bucket_load"])
def sketch_builtin_compare(spark, sf_dir):
    """Load of the buckets; the built-in sketches have their own keys."""
    return sk.load(load(spark, sf_dir, "part").select(F.col("p_partkey").alias("feature_id")), selection.SPEC)
