"""One large minibatch per round of Spark jobs, with every vector a DataFrame.

The gradient is one shuffle by feature after partial sums inside Arrow batches. The two-loop
product needs only dot products of the history and the gradient: their Gram matrix comes
from one aggregation, the recursion on it is a few numbers on the driver, and the direction
is a linear combination per feature. Weights that travel are the held ones only, at most k.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators.kernel import Batch, CountSketch, TopKHeap, Trainer, TrainSpec, residuals
from sketchselect.operators.trainer import Model, model_blocks
from sketchselect.schema import BLOCKS
from sketchselect.tables import new_path, written


def gram_direction(gram: np.ndarray) -> np.ndarray:
    """Coefficients of the direction over the basis [s_1..s_h, r_1..r_h, g], 1 the oldest."""
    h = (len(gram) - 1) // 2
    u = np.zeros(2 * h + 1)
    u[-1] = 1.0
    if not h:
        return u
    weight = [1.0 / gram[i, h + i] for i in range(h)]
    share = np.zeros(h)
    for i in reversed(range(h)):
        share[i] = weight[i] * float(gram[i] @ u)
        u[h + i] -= share[i]
    u *= gram[h - 1, 2 * h - 1] / gram[2 * h - 1, 2 * h - 1]
    for i in range(h):
        u[i] += share[i] - weight[i] * float(gram[h + i] @ u)
    return u


def gradient(batch: DataFrame, train: TrainSpec, ids: np.ndarray, weights: np.ndarray) -> DataFrame:
    """feature_id, g over the features of a minibatch, for held weights (sorted ids)."""

    def run(parts):
        for rows in parts:
            got = [rows.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
            b = Batch.of(list(got[1]), list(got[2]), got[0])
            own, at = np.unique(b.ids, return_inverse=True)
            w = np.zeros(len(own))
            if len(ids) and len(own):
                place = np.minimum(np.searchsorted(ids, own), len(ids) - 1)
                w = np.where(ids[place] == own, weights[place], 0.0)
            margin = np.bincount(b.rows, b.values * w[at], len(b.labels))[:, None]
            left, _ = residuals(train.loss, margin, b.labels)
            g = np.bincount(at, b.values * left[b.rows, 0], len(own))
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array(g, pa.float64())], names=["feature_id", "g"])

    partial = batch.select("label", "idx", "val").mapInArrow(run, "feature_id long, g double")
    return partial.groupBy("feature_id").agg(F.sum("g").alias("g"))


def basis(history: DataFrame | None, h: int, g: DataFrame) -> DataFrame:
    """feature_id, v (array over the basis), active: one row per feature of any vector.

    ``history`` holds feature_id and v over [s_1..s_h, r_1..r_h].
    """
    at, size = f"v{2 * h}", 2 * h + 1
    rows = g.selectExpr("feature_id", f"g AS {at}", *[f"0D AS v{i}" for i in range(2 * h)], "true AS active")
    if history is not None:
        rows = rows.unionByName(history.selectExpr("feature_id", f"0D AS {at}", *[f"v[{i}] AS v{i}" for i in range(2 * h)], "false AS active"))
    summed = ", ".join(f"sum(v{i})" for i in range(size))
    return rows.groupBy("feature_id").agg(F.expr(f"array({summed})").alias("v"), F.expr("max(active)").alias("active"))


def vectors(rows: pa.RecordBatch, at: int, size: int) -> np.ndarray:
    """Rows x size: the numbers of an array column of that size."""
    return rows.column(at).flatten().to_numpy(zero_copy_only=False).reshape(-1, size)


def gram(table: DataFrame, size: int) -> np.ndarray:
    """Dot products of the basis vectors: one matrix from every task, summed here."""

    def run(parts):
        out = np.zeros((size, size))
        for rows in parts:
            v = vectors(rows, 0, size)
            out += v.T @ v
        yield pa.RecordBatch.from_arrays([pa.array([out.ravel().tolist()])], names=["products"])

    found = table.select("v").mapInArrow(run, "products array<double>").collect()
    return sum((np.array(r[0]) for r in found), np.zeros(size * size)).reshape(size, size)


def sketched(table: DataFrame, u: np.ndarray, sketch: SketchSpec) -> DataFrame:
    """row, bucket, v: the sketch of the combination u of the basis over the active features."""

    def run(parts):
        store = CountSketch(sketch)
        for rows in parts:
            ids = rows.column(0).to_numpy(zero_copy_only=False)
            store.add(0, ids, vectors(rows, 1, len(u)) @ u)
        row, bucket = np.nonzero(store.cells[0])
        yield pa.RecordBatch.from_arrays([pa.array(row.astype(np.int32)), pa.array(bucket.astype(np.int32)), pa.array(store.cells[0, row, bucket])], names=["row", "bucket", "v"])

    return table.filter("active").select("feature_id", "v").mapInArrow(run, "row int, bucket int, v double").groupBy("row", "bucket").agg(F.sum("v").alias("v"))


def dots(s: DataFrame, r: DataFrame) -> tuple[float, float, float]:
    """s'r, s's and r'r of two vectors (feature_id, value), by one aggregation."""
    zero = F.lit(0.0)
    rows = s.select("feature_id", F.col("value").alias("s"), zero.alias("r")).unionByName(r.select("feature_id", zero.alias("s"), F.col("value").alias("r")))
    both = rows.groupBy("feature_id").agg(F.sum("s").alias("s"), F.sum("r").alias("r"))
    return tuple(x or 0.0 for x in both.agg(F.sum(F.col("s") * F.col("r")), F.sum(F.col("s") ** 2), F.sum(F.col("r") ** 2)).first())


def fit_sync(examples: DataFrame, sketch: SketchSpec, train: TrainSpec) -> Model:
    """Train with distributed vectors; for one weight vector (no classes), heap support.

    Follows the sequential order exactly, so it equals ``replay`` up to rounding of sums.
    """
    if train.classes != 1 or train.method not in ("curvature", "gradient"):
        raise ValueError("sync mode trains one weight vector by curvature or gradient steps")
    spark = examples.sparkSession
    store, heap = CountSketch(sketch), TopKHeap(train.k)
    # the pairs of the history side by side, one row per feature, so a round reads one table
    history, h = None, 0
    log, t = [], 0
    # one folder per minibatch: a round reads its own rows and no others
    path = new_path(spark, "batches")
    examples.select("batch_id", "label", "idx", "val").write.partitionBy("batch_id").parquet(path)
    batches = spark.read.schema("label double, idx array<bigint>, val array<double>, batch_id bigint").parquet(path)
    order = [r[0] for r in batches.select("batch_id").distinct().orderBy("batch_id").collect()]
    with ThreadPoolExecutor(1) as beside:
        for _ in range(train.stop.max_epochs):
            for number in order:
                batch = batches.filter(F.col("batch_id") == number)
                ids, weights = heap.ids, store.query(0, heap.ids)
                table = written(basis(history, h, gradient(batch, train, ids, weights)), "basis")
                products = gram(table, 2 * h + 1)
                u = gram_direction(products)
                g = table.filter("active").select("feature_id", F.col("v")[2 * h].alias("g"))
                eta = train.schedule.at(t)
                put = sketched(table, u, sketch)
                for r in put.collect():  # at most the cells of the sketch
                    store.cells[0, r["row"], r["bucket"]] -= eta * r["v"]
                # the heap is offered the features while the pair is made, which needs the cells and the ids held before
                offered = beside.submit(refresh, store, heap, g, sketch, train.k)
                kept = 0
                if train.method == "curvature" and train.history:
                    after = store.query(0, ids)
                    g2 = gradient(batch, train, ids, after).withColumnRenamed("g", "g2")
                    rows = table.join(g2, "feature_id", "left")
                    if train.step_source == "queried":
                        moved = [(int(i), float(b - a)) for i, a, b in zip(ids, weights, after, strict=True) if a != b]
                        rows = rows.join(F.broadcast(spark.createDataFrame(moved, "feature_id long, moved double")), "feature_id", "left")
                    else:
                        z = sum((F.lit(float(c)) * F.col("v")[i] for i, c in enumerate(u)), F.lit(0.0))
                        rows = rows.withColumn("moved", z * -eta)
                    s = F.when(F.col("active"), F.coalesce("moved", F.lit(0.0))).otherwise(0.0)
                    r = F.when(F.col("active"), F.col("g2") - F.col("v")[2 * h] + train.damping * s).otherwise(0.0)
                    first = int(h == train.history)  # the oldest pair goes
                    slots = F.concat(F.slice("v", first + 1, h - first), F.array("s"), F.slice("v", h + first + 1, h - first), F.array("r"))
                    made = rows.withColumn("s", s).withColumn("r", r).select("feature_id", slots.alias("v")).filter(F.exists("v", lambda x: x != 0))
                    made, n = written(made, "history"), h - first + 1
                    s_vec, r_vec = (made.select("feature_id", F.col("v")[i].alias("value")).filter("value <> 0") for i in (n - 1, 2 * n - 1))
                    both, ns, nr = dots(s_vec, r_vec)
                    if both > train.guard * np.sqrt(ns * nr):
                        history, h = made, n
                        kept = 1
                churn = offered.result()
                norm = float(np.sqrt(products[-1, -1]))
                log.append((t, 0.0, norm, kept, 0, churn, store.cells.size, 0, 0.0))
                t += 1
    final = Trainer(sketch, train, store.cells, [heap])
    final.log = log
    rows = [tuple(b.values()) for b in model_blocks(final, 0)]
    return Model(written(spark.createDataFrame(rows, BLOCKS), "model"), sketch, train)


def refresh(store: CountSketch, heap: TopKHeap, g: DataFrame, sketch: SketchSpec, k: int) -> int:
    """Offer the k best-read features of the minibatch to the heap.

    Tasks read the cells and keep k each; a feature that is not among the k best of its
    minibatch and is not held cannot enter. Held features of the minibatch are read again.
    """
    cells, held = store.cells.copy(), heap.ids

    def best(parts):
        own, top = CountSketch(sketch, 1, cells), TopKHeap(k)
        again: list[np.ndarray] = []
        for rows in parts:
            ids = rows.column(0).to_numpy(zero_copy_only=False)
            again.append(ids[np.isin(ids, held)])
            top.update(np.sort(ids), own.query(0, np.sort(ids)))
        ids = np.unique(np.concatenate([top.ids, *again]))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64())], names=["feature_id"])

    found = g.select("feature_id").mapInArrow(best, "feature_id long")
    ids = np.unique(np.array([r[0] for r in found.collect()], np.int64))
    return heap.update(ids, store.query(0, ids))


