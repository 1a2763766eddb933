"""Examples as sparse text lines: ``label | id:value id:value ...``.

A writer from packed rows, a plain reader by SQL functions, and a Python data source with
one partition per byte range of each file, whole lines only, and a filter on the label.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition


def to_lines(packed: DataFrame) -> DataFrame:
    """One column ``value``: the text line of each packed row."""
    pairs = F.transform(F.arrays_zip("idx", "val"), lambda e: F.concat_ws(":", e["idx"].cast("string"), e["val"].cast("string")))
    return packed.select(F.concat_ws(" ", F.col("label").cast("string"), F.lit("|"), F.array_join(pairs, " ")).alias("value"))


def write(packed: DataFrame, path: str) -> None:
    to_lines(packed).write.text(path)


def from_lines(lines: DataFrame) -> DataFrame:
    """label, idx, val from text lines; blank lines are left out."""
    pairs = F.filter(F.split(F.trim(F.substring_index("value", "|", -1)), "[ ]+"), lambda x: x != "")
    return lines.filter(F.trim("value") != "").select(
        F.trim(F.substring_index("value", "|", 1)).cast("double").alias("label"),
        F.transform(pairs, lambda x: F.substring_index(x, ":", 1).cast("long")).alias("idx"),
        F.transform(pairs, lambda x: F.substring_index(x, ":", -1).cast("double")).alias("val"),
    )


def read(spark: SparkSession, path: str) -> DataFrame:
    """Through Spark's own text reader, so any store that Spark reads will do."""
    return from_lines(spark.read.text(path))


class Lines(InputPartition):
    def __init__(self, numbers: tuple[int, int]):
        self.numbers = numbers


class SparseLinesReader(DataSourceReader):
    """Reads literal lines given as option ``lines`` (newline-separated), in ``partitions`` parts."""

    def __init__(self, lines: list[str], parts: int):
        self.lines, self.parts, self.label = lines, parts, None

    def pushFilters(self, filters) -> Iterator:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("label",):
                self.label = f.value
            else:
                yield f

    def partitions(self):
        edges = [len(self.lines) * i // self.parts for i in range(self.parts + 1)]
        return [Lines((a, z)) for a, z in zip(edges, edges[1:], strict=False)]

    def read(self, partition):
        rows = []
        for line in self.lines[partition.numbers[0] : partition.numbers[1]]:
            if not line.strip():
                continue
            label, _, rest = line.partition("|")
            if self.label is not None and float(label) != self.label:
                continue
            pairs = [x.split(":") for x in rest.split()]
            rows.append({"label": float(label), "idx": [int(i) for i, _ in pairs], "val": [float(v) for _, v in pairs]})
        yield pa.RecordBatch.from_pylist(
            rows, schema=pa.schema([("label", pa.float64()), ("idx", pa.list_(pa.int64())), ("val", pa.list_(pa.float64()))])
        )


class SparseLinesSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "sparse_lines"

    def schema(self) -> str:
        return "label double, idx array<bigint>, val array<double>"

    def reader(self, schema) -> DataSourceReader:
        return SparseLinesReader(self.options.get("lines", "").split("\n"), int(self.options.get("partitions", "2")))
