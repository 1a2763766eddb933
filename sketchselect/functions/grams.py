"""3-grams of short texts in numpy: whole Arrow batches at once, one hash per distinct 3-gram."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: A worker passes on the distinct 3-grams that it has found when they are more than this.
HELD = 1 << 20


def keys_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The 3-grams of all texts in order, as their three code points in one number, and the text of each."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    sizes = np.maximum(lengths - 2, 0)
    row = np.repeat(np.arange(len(texts)), sizes)
    at = np.arange(len(row)) + np.repeat(np.cumsum(lengths) - lengths - np.cumsum(sizes) + sizes, sizes)
    return points[at] << 42 | points[at + 1] << 21 | points[at + 2], row


def portable_ids(keys: np.ndarray) -> np.ndarray:
    """``hashing.portable_id`` of 3-grams."""
    texts = ("".join(chr(k >> n & 0x1FFFFF) for n in (42, 21, 0)) for k in keys.tolist())
    return np.fromiter((int(hashlib.md5(t.encode("utf-8", "surrogatepass")).hexdigest()[:15], 16) for t in texts), np.int64, len(keys))


def distinct(rows: DataFrame, column: str) -> DataFrame:
    """gram: the distinct 3-grams of a column, as ``keys_of`` writes them."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = np.empty(0, np.int64)
        for b in batches:
            found = np.union1d(found, keys_of(b.column(0).to_pylist())[0])
            if len(found) > HELD:
                yield pa.RecordBatch.from_arrays([pa.array(found)], ["gram"])
                found = np.empty(0, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(found)], ["gram"])

    return rows.select(column).mapInArrow(run, "gram long").distinct()


def coder(column: str, keys: np.ndarray, places: np.ndarray) -> Callable[[DataFrame], DataFrame]:
    """What replaces a text column by idx, the places of its 3-grams ascending, and val, how often each occurs.

    ``keys`` ascend and hold every 3-gram; ``places`` are theirs.
    """
    most = int(places.max(initial=0)) + 1

    def late(rows: DataFrame) -> DataFrame:
        kept = [f for f in rows.schema if f.name != column]
        at = rows.columns.index(column)

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                found, row = keys_of(b.column(at).to_pylist())
                both, times = np.unique(row * most + places[np.searchsorted(keys, found)], return_counts=True)
                ends = pa.array(np.searchsorted(both, np.arange(b.num_rows + 1) * most).astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (both % most, times.astype(np.float64))]
                yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index(f.name)) for f in kept] + lists, [*[f.name for f in kept], "idx", "val"])

        made = [T.StructField("idx", T.ArrayType(T.LongType())), T.StructField("val", T.ArrayType(T.DoubleType()))]
        return rows.mapInArrow(run, T.StructType(kept + made))

    return late
