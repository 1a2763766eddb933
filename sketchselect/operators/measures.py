"""Accuracy, area under the curve, recovery, memory and curve measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sketchselect.functions.hashing import SketchSpec


def accuracy(decided: DataFrame, keys: list[str]) -> DataFrame:
    return decided.groupBy(*keys).agg(F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("accuracy"))


def auc(scores: DataFrame, keys: list[str], score: str = "score", label: str = "label") -> DataFrame:
    """Area under the ROC curve per key: rank sum of positives with average ranks for ties.

    Scores are counted per distinct value first. Running counts come in two levels, within and
    over ranges of the score, so no task orders all rows of a key.
    """
    values = scores.groupBy(*keys, score).agg(F.count("*").alias("n"), F.sum(F.col(label)).alias("pos"))
    ends = values.groupBy(*keys).agg(F.min(score).alias("_lo"), F.max(score).alias("_hi"))
    span = F.col("_hi") - F.col("_lo")
    cut = F.when(span > 0, F.least(F.floor((F.col(score) - F.col("_lo")) / span * 1000), F.lit(999))).otherwise(0)
    at = (values.join(F.broadcast(ends), keys) if keys else values.join(F.broadcast(ends))).withColumn("_bin", cut.cast("int"))
    run = Window.partitionBy(*keys).orderBy("_bin")
    starts = at.groupBy(*keys, "_bin").agg(F.sum("n").alias("_n")).withColumn("_before", F.sum("_n").over(run) - F.col("_n")).drop("_n")
    inside = Window.partitionBy(*keys, "_bin").orderBy(score).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranked = at.withColumn("_upto", F.sum("n").over(inside)).join(starts, [*keys, "_bin"])
    rank = F.col("_before") + F.col("_upto") - F.col("n") + (F.col("n") + 1) / 2
    total = ranked.groupBy(*keys).agg(F.sum(rank * F.col("pos")).alias("_sum"), F.sum("pos").alias("_p"), F.sum(F.col("n") - F.col("pos")).alias("_q"))
    area = F.when((F.col("_p") > 0) & (F.col("_q") > 0), (F.col("_sum") - F.col("_p") * (F.col("_p") + 1) / 2) / (F.col("_p") * F.col("_q")))
    return total.select(*keys, area.alias("auc"))


def roc(scores: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """threshold, tpr, fpr at every distinct score, from the highest down.

    Running sums come in two levels, over and within ranges of the score.
    """
    values = scores.groupBy(score).agg(F.sum(label).alias("pos"), F.sum(1 - F.col(label)).alias("neg"))
    total = values.agg(F.sum("pos").alias("_p"), F.sum("neg").alias("_q"), F.min(score).alias("_lo"), F.max(score).alias("_hi"))
    span = F.col("_hi") - F.col("_lo")
    cut = F.when(span > 0, F.least(F.floor((F.col("_hi") - F.col(score)) / span * 1000), F.lit(999))).otherwise(0)
    at = values.join(F.broadcast(total)).withColumn("_bin", cut.cast("int"))
    over = Window.orderBy("_bin")  # at most 1000 ranges
    starts = at.groupBy("_bin").agg(F.sum("pos").alias("_pos"), F.sum("neg").alias("_neg")).select(
        "_bin", (F.sum("_pos").over(over) - F.col("_pos")).alias("_pos"), (F.sum("_neg").over(over) - F.col("_neg")).alias("_neg")
    )
    inside = Window.partitionBy("_bin").orderBy(F.col(score).desc())
    return at.join(F.broadcast(starts), "_bin").select(
        F.col(score).alias("threshold"),
        ((F.col("_pos") + F.sum("pos").over(inside)) / F.col("_p")).alias("tpr"),
        ((F.col("_neg") + F.sum("neg").over(inside)) / F.col("_q")).alias("fpr"),
    )


def confusion(decided: DataFrame) -> DataFrame:
    return decided.groupBy("label", "prediction").count()


def naive(examples: DataFrame) -> DataFrame:
    """Accuracy of always guessing the largest class, and of guessing uniformly."""
    return examples.groupBy("label").count().agg((F.max("count") / F.sum("count")).alias("majority"), (1 / F.count("*")).alias("uniform"))


def recovery(found: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """l2_error, success, precision, recall, f1 of selected (feature_id, estimate) against planted (feature_id, weight)."""
    if keys:
        truth = found.select(*keys).distinct().join(F.broadcast(truth))
    both = found.join(truth, [*keys, "feature_id"], "full")
    hit = (F.col("estimate").isNotNull() & F.col("weight").isNotNull()).cast("double")
    table = both.groupBy(*keys).agg(
        F.sqrt(F.sum((F.coalesce("estimate", F.lit(0.0)) - F.coalesce("weight", F.lit(0.0))) ** 2)).alias("l2_error"),
        F.sum(hit).alias("_hit"), F.count("weight").alias("_true"), F.count("estimate").alias("_got"),
    )
    precision, recall = F.col("_hit") / F.greatest("_got", F.lit(1)), F.col("_hit") / F.greatest("_true", F.lit(1))
    return table.select(
        *keys, "l2_error", (F.col("_hit") == F.col("_true")).alias("success"), precision.alias("precision"), recall.alias("recall"),
        F.coalesce(F.try_divide(2 * precision * recall, precision + recall), F.lit(0.0)).alias("f1"),
    )


def jaccard(a: DataFrame, b: DataFrame) -> DataFrame:
    x, y = a.select("feature_id").distinct(), b.select("feature_id").distinct()
    both = x.join(y, "feature_id").agg(F.count("*").alias("i"))
    return both.join(x.union(y).distinct().agg(F.count("*").alias("u"))).select((F.col("i") / F.greatest("u", F.lit(1))).alias("jaccard"))


def tail(exact: DataFrame, k: int) -> DataFrame:
    """tail_energy (squared weights outside the k largest) and zeta (the k-th magnitude).

    The k-th magnitude is found by a top-k, not by ranking every feature.
    """
    top = exact.select("feature_id", F.abs("value").alias("m")).orderBy(F.desc("m"), "feature_id").limit(k)
    edge = top.agg(F.min("m").alias("zeta"), F.sum(F.col("m") ** 2).alias("_top"))
    return exact.agg(F.sum(F.col("value") ** 2).alias("_all")).join(edge).select((F.col("_all") - F.col("_top")).alias("tail_energy"), "zeta")


def memory_model(active: DataFrame, k: int, history: int, spec: SketchSpec, classes: int = 1) -> DataFrame:
    """Cells of every vector for a minibatch of ``active`` features (the accounting of the method)."""
    a = F.col("active")
    return active.withColumns(
        {
            "weights_cells": F.lit(k), "s_cells": 2 * a, "r_cells": 2 * a, "z_cells": 2 * history * a,
            "sketch_cells": F.lit(spec.cells * classes), "gradient_cells": a,
        }
    )


def curve_gap(results: DataFrame, first: str, second: str) -> DataFrame:
    """cf, gap (first - second) and change of the gap since the next smaller cf, from (method, cf, value)."""
    x = results.filter(F.col("method") == first).select("cf", F.col("value").alias("a"))
    y = results.filter(F.col("method") == second).select("cf", F.col("value").alias("b"))
    return x.join(y, "cf").select("cf", (F.col("a") - F.col("b")).alias("gap")).withColumn("change", F.col("gap") - F.lag("gap").over(Window.orderBy("cf")))


def memory_ratio(results: DataFrame, first: str, second: str, target: float) -> DataFrame:
    """Cells that the second method needs over those of the first to reach ``target``, from (method, cells, value)."""
    need = results.filter(F.col("value") >= target).groupBy("method").agg(F.min("cells").alias("cells"))
    x = need.filter(F.col("method") == first).select(F.col("cells").alias("a"))
    y = need.filter(F.col("method") == second).select(F.col("cells").alias("b"))
    return x.join(y).select((F.col("b") / F.col("a")).alias("ratio"))


def eta_range(results: DataFrame, level: float) -> DataFrame:
    """Per method: least and largest step size that succeed at ``level``, and decades between, from (method, eta, value)."""
    good = results.filter(F.col("value") >= level).groupBy("method").agg(F.min("eta").alias("low"), F.max("eta").alias("high"))
    return good.withColumn("decades", F.log10(F.col("high") / F.col("low")))
