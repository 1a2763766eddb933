"""The experiment workloads on the given tables: curves over compression, selected features,
history, and run time; methods share hashes, batches and step sizes."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchselect.functions import features as fe
from sketchselect.functions import grams
from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import measures
from sketchselect.operators.coded import VOCABULARY
from sketchselect.operators.kernel import Schedule, StopRule, TrainSpec
from sketchselect.operators.trainer import Ordered, compare, decided, fit, predict, predictions, run_configs
from sketchselect.plans import tasks
from sketchselect.tables import load, scoped, spread, written

#: Hash rows and history of the real-data runs; compression factors of the
#: selected-features study and of the run-time table, by task.
HASHES, HISTORY = 5, 5
TOPK_CF = {"words": 10.0, "grams": 330.0, "kmers": 330.0, "clicks": 1100.0}
RUNTIME_CF = {"words": 95.0, "grams": 332.0, "kmers": 22.0, "clicks": 1000.0}
CURVE = (1.0, 3.0, 10.0, 30.0, 100.0, 300.0, 1000.0)
SKETCHED = ("curvature", "gradient")
DENSE = ("dense_sgd", "dense_qn")
#: Step sizes found by ``search_eta``; shared by the methods of a task.
ETA = {"words": 0.1, "grams": 0.01, "pages": 0.01, "kmers": 0.02, "roles": 0.02, "toxic": 0.05, "clicks": 0.1, "null_control": 0.05}
BATCH = 64
#: Least curvature of the pairs of second-order runs. The method assumes a Hessian bounded from below, which
#: the logistic loss is not: without it, pairs from rows that are already classified well have almost no
#: curvature, and their inverse throws the weights about.
DAMPING = 10.0


def prepared(spark: SparkSession, sf_dir: str, task: str, batch: int = BATCH) -> tuple[DataFrame, DataFrame, int]:
    """Train (with batches) and test rows of a task, written, and its number of features."""
    rows = written(tasks.TASKS[task](spark, sf_dir), f"task-{task}")
    train = written(fe.number_batches(rows.filter("split = 'train'").drop("split"), batch), "train")
    test = rows.filter("split = 'test'").drop("split")
    p = rows.select(F.explode("idx").alias("f")).agg(F.count_distinct("f")).first()[0]
    return train, test, p


def prepared_reads(spark: SparkSession, sf_dir: str, batch: int = BATCH) -> tuple[DataFrame, DataFrame, int, Callable, np.ndarray | None]:
    """Train and test rows of the k-mer task as reads, its number of features, what makes the features of reads, and their ids.

    Features are many times larger than the reads, so reads are moved and stored, and features made where they are read.
    Where the 3-grams are at most ``VOCABULARY``, features are places among their ids; else ids, and there is no vocabulary.
    """
    rows = written(tasks.even_reads(spark, sf_dir), "reads")
    train = written(fe.number_batches(rows.filter("split = 'train'").drop("split"), batch), "train")
    test = rows.filter("split = 'test'").drop("split")
    found = written(grams.distinct(rows, "read"), "grams")
    if found.count() > VOCABULARY:
        p = tasks.with_kmers(rows).select(F.explode("idx").alias("f")).agg(F.count_distinct("f")).first()[0]
        return train, test, p, tasks.with_kmers, None
    keys = np.sort(np.array([r[0] for r in found.collect()], np.int64))
    ids, places = np.unique(grams.portable_ids(keys), return_inverse=True)
    return train, test, len(ids), grams.coder("read", keys, places), ids


def spec_of(task: str, method: str, cf: float, p: int, k: int, eta: float | None = None, tau: int = HISTORY, epochs: int = 1, **kw) -> tuple[SketchSpec, TrainSpec]:
    loss, classes = tasks.LOSSES.get(task, ("logistic", 1))
    if method in ("curvature", "dense_qn"):
        kw.setdefault("damping", DAMPING)
    train = TrainSpec(
        loss=loss, method=method, k=k, schedule=Schedule(ETA.get(task, 0.05) if eta is None else eta), history=tau, classes=classes,
        stop=StopRule(epochs), **kw,
    )
    return SketchSpec.from_cf(p, cf, HASHES, classes, seed=7), train


def evaluated(blocks: DataFrame, support: str) -> DataFrame:
    """config, accuracy and (for one score) auc."""
    rows = decided(predictions(blocks, support), ["config"])
    return measures.accuracy(rows, ["config"]).join(measures.auc(rows, ["config"]), "config", "left")


def sweep(spark: SparkSession, sf_dir: str, task: str, grid: list[dict], support: str = "all", batch: int = BATCH) -> DataFrame:
    """task, method, cf, k, eta, tau, accuracy, auc: one row per grid point, all in one job."""
    train, test, p = prepared(spark, sf_dir, task, batch)
    configs, about = {}, []
    for i, g in enumerate(grid):
        full = {"method": "curvature", "cf": 10.0, "k": 100, "eta": ETA.get(task, 0.05), "tau": HISTORY, "epochs": 1} | g
        configs[i] = spec_of(task, full["method"], full["cf"], p, full["k"], full["eta"], full["tau"], full["epochs"], **g.get("more", {}))
        about.append((i, task, full["method"], float(full["cf"]), int(full["k"]), float(full["eta"]), int(full["tau"]), p))
    blocks = written(run_configs(train, configs, test, (support,)), "sweep")
    named = spark.createDataFrame(about, "config long, task string, method string, cf double, k int, eta double, tau int, features long")
    return F.broadcast(named).join(evaluated(blocks, support), "config").drop("config")


def compression_curve(spark: SparkSession, sf_dir: str, task: str, cfs=CURVE, k: int = 1000, epochs: int = 1) -> DataFrame:
    """Accuracy against the compression factor with all active features, every method."""
    grid = [{"method": m, "cf": cf, "k": k, "epochs": epochs} for m in (*SKETCHED, "hashed") for cf in cfs]
    grid += [{"method": m, "cf": 1.0, "k": k, "epochs": epochs} for m in DENSE]
    return sweep(spark, sf_dir, task, grid)


def selected_curve(spark: SparkSession, sf_dir: str, task: str, ks=(8, 32, 128, 512, 2048), epochs: int = 1) -> DataFrame:
    """Accuracy with only the k selected features."""
    grid = [{"method": m, "cf": TOPK_CF.get(task, 10.0), "k": k, "epochs": epochs} for m in SKETCHED for k in ks]
    return sweep(spark, sf_dir, task, grid, "topk")


def history_curve(spark: SparkSession, sf_dir: str, task: str = "words", taus=(0, 1, 2, 5, 10, 20)) -> DataFrame:
    return sweep(spark, sf_dir, task, [{"tau": t, "k": 500} for t in taus])


def search_eta(spark: SparkSession, sf_dir: str, task: str, etas=(0.001, 0.01, 0.1, 1.0), methods=SKETCHED, batch: int = BATCH) -> DataFrame:
    return sweep(spark, sf_dir, task, [{"method": m, "eta": e, "k": 500} for m in methods for e in etas], batch=batch)


def search_batch(spark: SparkSession, sf_dir: str, task: str, batches=(16, 64, 256), **kw) -> DataFrame:
    """The step-size search for several minibatch sizes."""
    out = None
    for b in batches:
        one = search_eta(spark, sf_dir, task, batch=b, **kw).withColumn("batch", F.lit(b))
        out = one if out is None else out.unionByName(one)
    return out


def searched(
    spark: SparkSession, sf_dir: str, task: str, etas=(0.003, 0.01, 0.03, 0.1, 0.3, 1.0), cfs=(10.0, 100.0, 1000.0), methods=SKETCHED, k: int = 500, epochs: int = 1, **more
) -> DataFrame:
    """Each method at its best step size, per compression factor: task, method, cf, eta, accuracy, auc.

    Best by AUC where there is one score, else by accuracy; ties go to the smaller step.
    """
    grid = [{"method": m, "cf": c, "eta": e, "k": k, "epochs": epochs, "more": more} for m in methods for c in cfs for e in etas]
    table = sweep(spark, sf_dir, task, grid)
    best = F.max(F.struct(F.coalesce("auc", "accuracy").alias("by"), (-F.col("eta")).alias("small"), "eta", "accuracy", "auc"))
    return table.groupBy("task", "method", "cf").agg(best.alias("b")).select("task", "method", "cf", "b.eta", "b.accuracy", "b.auc").orderBy("cf", "method")


def ablation(spark: SparkSession, sf_dir: str, task: str = "words") -> DataFrame:
    """The readings of the method that its description leaves open, one at a time."""
    kinds = {
        "default": {}, "step_direction": {"step_source": "direction"}, "refresh_early": {"heap_refresh": "before_second_fetch"},
        "mean_gradient": {"grad_scale": "mean"}, "all_support": {"support": "all"}, "inverse_norm": {"first_scale": "inverse_norm"},
        "undamped": {"damping": 0.0}, "damped_by_1": {"damping": 1.0}, "damped_by_50": {"damping": 50.0},
    }
    train, test, p = prepared(spark, sf_dir, task)
    configs = {i: spec_of(task, "curvature", 10.0, p, 500, **kw) for i, kw in enumerate(kinds.values())}
    n = len(configs)
    for j, rows in enumerate((1, 3, 7)):
        sketch, spec = configs[0]
        configs[n + j] = (SketchSpec(rows=rows, buckets=max(1, sketch.cells // rows), seed=7), spec)
    sketch, spec = configs[0]
    configs[n + 3] = (sketch.with_(query="mean"), spec)
    names = [*kinds, "rows_1", "rows_3", "rows_7", "mean_query"]
    blocks = written(run_configs(train, configs, test, ("all",)), "ablation")
    table = spark.createDataFrame(list(enumerate(names)), "config long, variant string")
    return F.broadcast(table).join(evaluated(blocks, "all"), "config").drop("config")


def layouts(spark: SparkSession, sf_dir: str, task: str = "kmers", cf: float = 10.0) -> DataFrame:
    """One sketch per class against one that all classes share, with as many cells in total."""
    train, test, p, late, ids = prepared_reads(spark, sf_dir) if task == "kmers" else (*prepared(spark, sf_dir, task), None, None)
    own = spec_of(task, "curvature", cf, p, 200)
    classes = own[1].classes
    shared = (own[0].with_(buckets=own[0].buckets * classes), own[1].with_(layout="shared", k=200 * classes))
    blocks = written(run_configs(train, {0: own, 1: shared}, test, ("all",), late, ids), "layouts")
    table = spark.createDataFrame([(0, "per_class"), (1, "shared")], "config long, layout string")
    return F.broadcast(table).join(measures.accuracy(decided(predictions(blocks, "all"), ["config"]), ["config"]), "config").drop("config")


def runtime(spark: SparkSession, sf_dir: str, names=("words", "grams", "kmers", "clicks"), k: int = 500) -> DataFrame:
    """Seconds and rows per second of both sketched methods at the run-time table's factors.

    A task's examples are put in order and stored once, by the first of its replays; these are one Spark task each and run
    side by side. What was written for a task is deleted before the next task's rows are made.
    """
    out = []
    for task in names:
        with scoped(spark):
            train, _, p = prepared(spark, sf_dir, task)
            n, ordered = train.count(), Ordered(train)

            def timed(method: str, task=task, ordered=ordered, p=p) -> float:
                sketch, spec = spec_of(task, method, RUNTIME_CF[task], p, k)
                began = time.perf_counter()
                fit(ordered, sketch, spec, "ordered")
                return time.perf_counter() - began

            with ThreadPoolExecutor(len(SKETCHED)) as pool:
                took = list(pool.map(timed, SKETCHED))
            ordered.release()
        out += [(task, m, RUNTIME_CF[task], n, s, n / s) for m, s in zip(SKETCHED, took, strict=True)]
    return spark.createDataFrame(out, "task string, method string, cf double, n long, seconds double, rows_per_second double")


def word_report(spark: SparkSession, sf_dir: str, k: int = 100, cf: float = 10.0) -> DataFrame:
    """Words that each sketched method selects alone, and those that both select."""
    train, _, p = prepared(spark, sf_dir, "words")
    a, b = (fit(train, *spec_of("words", m, cf, p, k)) for m in SKETCHED)
    names = load(spark, sf_dir, "documents").select(F.explode(fe.word_set(F.col("text"))).alias("name")).distinct()
    chosen = compare(a.topk_df(), b.topk_df())
    named = names.withColumn("feature_id", fe.portable_id(F.col("name"))).join(F.broadcast(chosen), "feature_id")
    return named.select("selected_by", "name", "feature_id")


def convergence(spark: SparkSession, sf_dir: str, cf: float = 1000.0) -> DataFrame:
    """Loss and gradient norm by step at a small memory, both methods."""
    train, _, p = prepared(spark, sf_dir, "words")
    out = None
    for m in SKETCHED:
        log = fit(train, *spec_of("words", m, cf, p, 500, epochs=2)).log_df().withColumn("method", F.lit(m))
        out = log if out is None else out.unionByName(log)
    return out


def scaled_texts(spark: SparkSession, sf_dir: str, copies: int) -> DataFrame:
    """example_id, label, split, salt, text: the replicated texts, before their features."""
    docs = spread(load(spark, sf_dir, "documents")).select("doc_id", "lang", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("salt"), "text")
    return docs.select(
        (F.col("doc_id") * copies + F.col("salt")).alias("example_id"), (F.col("lang") == "en").cast("double").alias("label"), fe.split_of(F.col("text")).alias("split"), "salt", "text"
    ).filter("text is not null")


def with_scaled_features(rows: DataFrame) -> DataFrame:
    """Presence of 12-grams, ids salted per copy; needs salt and text."""
    ids = F.sort_array(F.array_distinct(F.transform(fe.char_ngrams(F.col("text"), 12), lambda g: F.xxhash64(g, F.col("salt")).bitwiseAND((1 << 60) - 1))))
    return rows.withColumn("idx", ids).drop("salt", "text").withColumn("val", F.transform("idx", lambda _: F.lit(1.0)))


def scaled(spark: SparkSession, sf_dir: str, copies: int) -> DataFrame:
    """Packed examples of a very large space: presence of 12-grams of replicated texts, ids salted per copy."""
    return with_scaled_features(scaled_texts(spark, sf_dir, copies)).select("example_id", "label", "idx", "split", "val")


def scaled_ids(spark: SparkSession, sf_dir: str, copies: int = 4) -> DataFrame:
    """The large-space question: rows, entries and ids."""
    rows = scaled(spark, sf_dir, copies).select(F.explode("idx").alias("id"))
    return rows.agg(F.count("*").alias("entries"), F.approx_count_distinct("id").alias("features"))


def scaled_model(spark: SparkSession, sf_dir: str, copies: int = 4, cells: int = 50_000, shards: int = 8, k: int = 1000) -> DataFrame:
    """A model of that space in a sketch of ``cells``, trained in shards: features, compression, rows, test accuracy."""
    # features are many times larger than the texts, so texts are moved and stored, features made where they are read
    rows = scaled_texts(spark, sf_dir, copies)
    p = with_scaled_features(rows).select(F.explode("idx").alias("id")).agg(F.approx_count_distinct("id")).first()[0]
    train = written(fe.number_batches(rows.filter("split = 'train'").drop("split"), BATCH), "train")
    sketch = SketchSpec(HASHES, max(1, cells // HASHES), 7)
    model = fit(train, sketch, TrainSpec(k=k, schedule=Schedule(0.01), history=HISTORY), "sharded", shards=shards, late=with_scaled_features)
    scored = decided(predict(with_scaled_features(rows.filter("split = 'test'")), model, "all"), [])
    return scored.agg(F.count("*").alias("test_rows"), F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("accuracy")).select(
        F.lit(p).alias("features"), F.lit(p / sketch.cells).alias("cf"), "test_rows", "accuracy"
    )


def library_ceiling(spark: SparkSession, sf_dir: str, task: str = "words", bits: int = 18) -> DataFrame:
    """Test accuracy of the library's own logistic regression on hashed features: what batch training reaches."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    rows = written(tasks.TASKS[task](spark, sf_dir), f"task-{task}")
    hashing = HashingTF(numFeatures=1 << bits, binary=True, inputCol="terms", outputCol="features")
    vectors = hashing.transform(rows.select("label", "split", F.transform("idx", lambda i: i.cast("string")).alias("terms")))
    model = LogisticRegression(maxIter=30, regParam=1e-4).fit(vectors.filter("split = 'train'"))
    found = model.transform(vectors.filter("split = 'test'"))
    return found.agg(F.count("*").alias("rows"), F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("accuracy")).select(F.lit(task).alias("task"), "rows", "accuracy")
