"""The same computations as Python functions of every kind, checked against the built-in forms."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from sketchselect.functions.hashing import SketchSpec, np_places
from sketchselect.operators.kernel import CountSketch


def sketch_reader(spec: SketchSpec, cells: np.ndarray):
    """Scalar UDF: the estimate of a feature id from fixed cells (rows x buckets)."""

    @pandas_udf(T.DoubleType())
    def read(ids: pd.Series) -> pd.Series:
        return pd.Series(CountSketch(spec, 1, cells[None]).query(0, ids.to_numpy(np.int64)))

    return read


def signs(spec: SketchSpec, row: int):
    """Arrow UDF: the sign hash of one row."""

    @arrow_udf(T.IntegerType())
    def sign(ids: pa.Array) -> pa.Array:
        return pa.array(np_places(ids.to_numpy(zero_copy_only=False).astype(np.int64), spec)[1][row].astype(np.int32))

    return sign


@pandas_udf(T.DoubleType())
def auc(scores: pd.Series, labels: pd.Series) -> float:
    """Grouped aggregate: area under the ROC curve with average ranks."""
    pos, neg = float((labels > 0).sum()), float((labels <= 0).sum())
    if not pos or not neg:
        return float("nan")
    return (scores.rank()[labels > 0].sum() - pos * (pos + 1) / 2) / (pos * neg)


@udtf(returnType=T.StructType([T.StructField("feature", T.StringType())]))
class ExplodeFeatures:
    """Table function: character n-grams (kind ``gram``) or lower-case tokens (kind ``word``)."""

    def eval(self, text: str, kind: str, n: int) -> Iterator[tuple[str]]:
        text = text or ""
        found = [text[i : i + n] for i in range(len(text) - n + 1)] if kind == "gram" else text.lower().split()
        for x in dict.fromkeys(found):
            yield (x,)


def word_lengths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow: id and number of space-separated words of (id, text)."""
    for b in batches:
        n = [len(t.split(" ")) if t else 0 for t in b.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64())], names=["id", "words"])


def value_stats(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    """applyInPandas: count and rounded mean of a group."""
    return pd.DataFrame({"event_type": [key[0]], "n": [len(rows)], "mean": [round(float(rows["value"].mean()), 6)]})


def matched(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
    """cogroup: rows of a key on both sides."""
    return pd.DataFrame({"k": [key[0]], "left_rows": [len(a)], "right_rows": [len(b)]})


