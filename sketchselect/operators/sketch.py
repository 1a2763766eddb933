"""Count Sketch as DataFrame operators over (row, bucket, value) cells.

Building is one pass and one shuffle of at most tasks x cells partial sums. Everything is
linear in the cells, so sketches merge, scale and subtract by sums.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sketchselect.functions.hashing import SketchSpec, places

#: Cells up to this many travel to the tasks as one array; more are joined.
BROADCAST_CELLS = 1 << 22


def build(entries: DataFrame, spec: SketchSpec, by: list[str] | None = None, value: Column | None = None) -> DataFrame:
    """Cells of all entries (feature_id, value), per key of ``by`` if given."""
    by = by or []
    value = F.col("value") if value is None else value
    put = entries.select(*by, value.alias("_v"), F.inline(places(F.col("feature_id"), spec)))
    return put.groupBy(*by, "row", "bucket").agg(F.sum(F.col("sign") * F.col("_v")).alias("value"))


def _reading(spec: SketchSpec, signed: Column) -> Column:
    """Median (mean of the middle two for an even number) or mean of d signed counters."""
    d = spec.rows
    if spec.query == "mean":
        return F.aggregate(signed, F.lit(0.0), lambda s, x: s + x) / d
    ordered = F.array_sort(signed)
    return (F.element_at(ordered, (d + 1) // 2) + F.element_at(ordered, d // 2 + 1)) / 2


def query(cells: DataFrame, ids: DataFrame, spec: SketchSpec) -> DataFrame:
    """Add ``estimate`` to every row of ``ids`` (feature_id).

    Cells of a checked size travel as one array; a larger sketch is joined by row and bucket.
    """
    if spec.cells <= BROADCAST_CELLS:
        at = (F.col("row") * spec.buckets + F.col("bucket")).cast("long")
        packed = cells.select(F.struct(at.alias("at"), F.col("value").cast("double").alias("value")).alias("c")).agg(
            F.map_from_entries(F.collect_list("c")).alias("_cells")
        )
        signed = F.transform(
            places(F.col("feature_id"), spec),
            lambda p: p["sign"] * F.coalesce(F.element_at(F.col("_cells"), (p["row"] * spec.buckets + p["bucket"]).cast("long")), F.lit(0.0)),
        )
        return ids.join(F.broadcast(packed)).withColumn("estimate", _reading(spec, signed)).drop("_cells")
    asked = ids.select("feature_id").distinct().select("feature_id", F.inline(places(F.col("feature_id"), spec)))
    found = (
        asked.join(cells, ["row", "bucket"], "left")
        .groupBy("feature_id")
        .agg(F.collect_list(F.col("sign") * F.coalesce("value", F.lit(0.0))).alias("_signed"))
        .select("feature_id", _reading(spec, F.col("_signed")).alias("estimate"))
    )
    return ids.join(found, "feature_id")


def top_k(estimates: DataFrame, k: int) -> DataFrame:
    """The k ids of largest magnitude, ties to the smaller id."""
    return estimates.select("feature_id", "estimate").orderBy(F.abs("estimate").desc(), "feature_id").limit(k)


def merge(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).groupBy("row", "bucket").agg(F.sum("value").alias("value"))


def scale(cells: DataFrame, by: float) -> DataFrame:
    return cells.withColumn("value", F.col("value") * by)


def subtract(a: DataFrame, b: DataFrame, by: float = 1.0) -> DataFrame:
    """a - by * b over the cells of either."""
    return merge(a, scale(b, -by))


def error(cells: DataFrame, exact: DataFrame, spec: SketchSpec) -> DataFrame:
    """feature_id, value, estimate, abs_error against exact sums (feature_id, value)."""
    return query(cells, exact, spec).withColumn("abs_error", F.abs(F.col("estimate") - F.col("value")))


def load(ids: DataFrame, spec: SketchSpec) -> DataFrame:
    """row, bucket, features: how many distinct ids share each bucket."""
    return (
        ids.select("feature_id")
        .distinct()
        .select(F.inline(places(F.col("feature_id"), spec)))
        .groupBy("row", "bucket")
        .agg(F.count("*").alias("features"))
    )


def collisions(ids: DataFrame, spec: SketchSpec) -> DataFrame:
    """row, bucket, a, b: pairs of a small set of ids that share a bucket."""
    put = ids.select("feature_id", F.inline(places(F.col("feature_id"), spec))).select("row", "bucket", "feature_id")
    other = put.withColumnRenamed("feature_id", "b")
    return put.withColumnRenamed("feature_id", "a").join(other, ["row", "bucket"]).filter("a < b")


def projection(ids: DataFrame, spec: SketchSpec) -> DataFrame:
    """feature_id, col, value: the projection matrix, entries of magnitude 1 / sqrt(rows)."""
    return ids.select("feature_id", F.inline(places(F.col("feature_id"), spec))).select(
        "feature_id",
        (F.col("row") * spec.buckets + F.col("bucket")).alias("col"),
        (F.col("sign") / F.sqrt(F.lit(float(spec.rows)))).alias("value"),
    )
