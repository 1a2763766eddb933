"""Helpers shared by the training-data operators."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchselect.tables import release, shared_dir, written

#: A word of a text: a run without space, tab, newline, vertical tab, form feed, return.
WORD = r"[^\x20\x09-\x0D]+"

__all__ = ["WORD", "batches_of", "free_names", "let", "load", "release", "shared_dir", "text_or_empty", "written"]


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


@contextmanager
def batches_of(spark: SparkSession, rows: int) -> Iterator[None]:
    """Jobs run inside send at most so many rows to a Python worker at a time."""
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(setting)
    spark.conf.set(setting, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(setting, before)


def text_or_empty(column: str = "text"):
    return F.coalesce(F.col(column), F.lit(""))


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """Names like those wanted that no column of ``df`` has, in any case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in wanted:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def let(value: str, name: str, body: str) -> str:
    """SQL: ``body`` with ``name`` bound to a value that is computed once, and not copied."""
    return f"aggregate(cast(array() AS array<int>), {value}, ({name}, none) -> {name}, {name} -> {body})"
