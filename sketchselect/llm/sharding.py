"""Sharding by longest-processing-time scheduling.

Groups that must stay together (rows of one key) are placed, largest first, on the
least-loaded shard through a heap. Only groups larger than ``total / (shards * bins)``
are scheduled one by one: by arithmetic there are at most ``shards * bins`` of them.
All smaller groups first fall into ``shards * bins`` hash bins, which are scheduled as
units. So the driver's heap never holds more than ``2 * shards * bins`` units, whatever
the number of groups, and no shard exceeds the mean by more than about one unit.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sketchselect.llm.common import free_names, text_or_empty, written


def lpt(units: list[tuple[int, object]], shards: int) -> dict:
    """``(size, unit)`` pairs to shards: largest first, each to the least-loaded shard."""
    heap = [(0, s) for s in range(shards)]
    placed = {}
    for size, unit in sorted(units, key=lambda x: (-x[0], str(x[1]))):
        load, shard = heapq.heappop(heap)
        placed[unit] = shard
        heapq.heappush(heap, (load + size, shard))
    return placed


def assign_shards(rows: DataFrame, key: str, size: str, shards: int = 40, bins: int = 256) -> DataFrame:
    """Add ``shard``: rows with one ``key`` share a shard and shard sizes are near equal.

    ``key`` must not be null. A key larger than a whole shard's share still stays together
    (then sizes cannot be equal). An empty table gives an empty result.
    """
    spark = rows.sparkSession
    units = shards * bins
    total = rows.agg(F.sum(size)).first()[0] or 0
    limit = max(1, total // units)
    summed, bin_, own, shared, name = free_names(rows, "_summed", "_bin", "_own", "_shared", "_name")
    bin_of = F.pmod(F.xxhash64(F.col(key)), F.lit(units)).cast("int")
    groups = rows.groupBy(F.col(key).alias(name)).agg(F.sum(size).alias(summed))
    large = [(int(r[1]), r[0]) for r in groups.filter(F.col(summed) > limit).collect()]
    binned = groups.filter(F.col(summed) <= limit).groupBy(F.pmod(F.xxhash64(name), F.lit(units)).cast("int").alias(bin_)).agg(F.sum(summed).alias(summed))
    small = [(int(r[1]), int(r[0])) for r in binned.collect()]
    assert len(large) <= units and len(small) <= units
    placed = lpt([(s, (0, k)) for s, k in large] + [(s, (1, b)) for s, b in small], shards)
    kind = rows.schema[key].dataType.simpleString()
    alone = spark.createDataFrame([(k, placed[0, k]) for _, k in large], f"{name} {kind}, {own} int")
    together = spark.createDataFrame([(b, placed[1, b]) for _, b in small], f"{bin_} int, {shared} int")
    # both sides are at most shards * bins rows, by the arithmetic above
    return (
        rows.withColumn(bin_, bin_of)
        .join(F.broadcast(alone), F.col(key) == F.col(name), "left")
        .join(F.broadcast(together), bin_, "left")
        .select(*rows.columns, F.coalesce(own, shared).alias("shard"))
    )


def number_slots(rows: DataFrame, order: list[str], rows_per_cell: int = 1024) -> DataFrame:
    """Add ``slot``: gapless from 0 within each ``shard``, in two levels.

    Rows fall into hash cells within their shard; cell counts give offsets and rows are
    numbered within a cell, so that no task sorts a whole shard.
    """
    n = rows.groupBy("shard").count().agg(F.max("count")).first()[0] or 0
    cells = max(1, -(-n // rows_per_cell))
    cell, count, start, at = free_names(rows, "_cell", "_count", "_start", "_at")
    kept = rows.columns
    rows = rows.withColumn(cell, F.pmod(F.xxhash64(*order), F.lit(cells)).cast("int"))
    starts = (
        rows.groupBy("shard", cell)
        .agg(F.count("*").alias(count))
        .withColumn(start, F.sum(count).over(Window.partitionBy("shard").orderBy(cell)) - F.col(count))
        .drop(count)
    )
    within = Window.partitionBy("shard", cell).orderBy(*order)
    return (
        rows.withColumn(at, F.row_number().over(within) - 1)
        .join(starts, ["shard", cell])
        .select(*kept, (F.col(start) + F.col(at)).alias("slot"))
    )


def sized_documents(docs: DataFrame) -> DataFrame:
    """doc_id, size (UTF-8 bytes plus 16), text_crc32 and the digest that groups equal texts.

    A null text counts as empty; both form one group.
    """
    text = text_or_empty()
    return docs.select(
        "doc_id",
        (F.octet_length(text) + 16).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.sha2(text, 256).alias("_key"),
    )


def shard_documents(docs: DataFrame, shards: int = 40) -> DataFrame:
    """Every document with its shard and slot; equal texts share a shard; the law is ``bytes``."""
    rows = written(sized_documents(docs), "sized")
    placed = assign_shards(rows, "_key", "size", shards)
    return number_slots(placed.drop("_key"), ["doc_id", "text_crc32", "size"]).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        F.col("shard").cast("int").alias("shard"),
        F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def sharded(docs: DataFrame, shards: int = 40) -> DataFrame:
    """The documents, all columns, with shard and slot (any columns of these names are replaced).

    Rows of equal text, null as empty, share a shard; repeated rows are separate rows.
    """
    text = text_or_empty()
    docs = docs.drop("shard", "slot")
    size, crc, key = free_names(docs, "_size", "_crc", "_key")
    rows = docs.withColumns({size: (F.octet_length(text) + 16).cast("long"), crc: F.crc32(text), key: F.sha2(text, 256)})
    placed = assign_shards(rows, key, size, shards)
    return number_slots(placed, ["doc_id", crc, size]).select(*docs.columns, "shard", "slot")
