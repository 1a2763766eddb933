"""Python data source of Gaussian rows with planted sparse weights, by row ranges.

Row i depends on (seed, i) only, so any partitioning gives the same rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Rows(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


def truth(seed: int, p: int, k: int) -> np.ndarray:
    draw = np.random.Generator(np.random.Philox(key=[seed, 1]))
    w = np.zeros(p)
    w[draw.choice(p, k, replace=False)] = draw.uniform(0.8, 1.2, k)
    return w


def row(seed: int, i: int, p: int) -> np.ndarray:
    return np.random.Generator(np.random.Philox(key=[seed, 2], counter=[0, 0, i, 0])).standard_normal(p)


class GaussReader(DataSourceReader):
    def __init__(self, n: int, p: int, k: int, seed: int, parts: int):
        self.n, self.p, self.k, self.seed, self.parts = n, p, k, seed, parts

    def partitions(self):
        edges = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [Rows(a, z) for a, z in zip(edges, edges[1:], strict=False)]

    def read(self, partition):
        w = truth(self.seed, self.p, self.k)
        ids = list(range(self.p))
        for i in range(partition.first, partition.last):
            x = row(self.seed, i, self.p)
            yield pa.RecordBatch.from_pylist(
                [{"example_id": i, "label": float(x @ w), "idx": ids, "val": x.tolist()}],
                schema=pa.schema([("example_id", pa.int64()), ("label", pa.float64()), ("idx", pa.list_(pa.int64())), ("val", pa.list_(pa.float64()))]),
            )


class GaussSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gauss"

    def schema(self) -> str:
        return "example_id bigint, label double, idx array<bigint>, val array<double>"

    def reader(self, schema) -> DataSourceReader:
        o = self.options
        return GaussReader(int(o.get("rows", "900")), int(o.get("features", "1000")), int(o.get("planted", "8")), int(o.get("seed", "0")), int(o.get("partitions", "4")))
