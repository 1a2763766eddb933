"""Mixing sources to target weights by a low-discrepancy schedule.

Targets: the total is shared by weight; a source stops at ``cap`` times its own size and
its excess goes to the others by weight, until none is above (water filling, solved in
closed form over the sorted ratios cap / weight).

Schedule: slot t takes the point frac((t + 1/2) / golden ratio). The cumulative target
shares cut [0, 1) into one interval per source; the interval that holds the point names the
slot's source. The rank of a slot within its source is the index of the block it takes. Ranks come
in two levels (runs of slots, then slots within a run), so no task holds all slots of a source.

Blocks: each source's documents, in a hash-shuffled order, form a token stream that repeats;
block b is the b-th run of ``block`` tokens of it. Blocks do not grow with the corpus, and
are smaller where a source's target is small: each source has a share of four blocks or
more (or blocks of one token), which no two neighbouring points of the schedule span. Prefix
sums come in two levels (hash buckets of a source, then rows within a bucket), so no task
holds a whole source. The block of every slot meets the documents that it cuts at cells of the stream.

Everything is DataFrame expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sketchselect.llm.common import WORD, free_names, text_or_empty, written

#: Fractional part of the golden ratio, as GOLDEN / CIRCLE: neighbouring Fibonacci numbers, so that
#: up to CIRCLE points lie as evenly as those of the ratio itself. Both are below 2 ** 48.
GOLDEN, CIRCLE = 117669030460994, 190392490709135
#: Tokens of a block, blocks at least in a source's target, rows of a bucket of the shuffle.
MIN_BLOCK = 16
LEAST_BLOCKS = 4
BUCKET_ROWS = 1024
#: Slots of a run in which ranks are counted, and tokens of a cell at which blocks meet documents.
RUN_SLOTS = 1 << 16
CELL_TOKENS = 64
#: Source tables up to this many rows are broadcast; larger ones are shuffled.
BROADCAST_SOURCES = 10_000
#: Documents that the mix takes, and intervals of sources, are broadcast up to this many, and shuffled beyond.
BROADCAST_ROWS = 500_000


def source_targets(sized: DataFrame, cap: int = 3, cycle: int = 3) -> DataFrame:
    """One row per source: source, ordinal, weight, source_size, source_rows, target.

    ``sized`` has source and size. Sources by code point, null last, weigh 1..cycle, repeating.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    by_ratio = Window.orderBy("_ratio", "ordinal")
    base = (
        sized.groupBy("source")
        .agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows"))
        .withColumn("ordinal", F.row_number().over(order) - 1)
        .withColumn("weight", F.col("ordinal") % cycle + 1)
        .withColumn("_cap", F.col("source_size") * cap)
        .withColumn("_ratio", F.col("_cap") / F.col("weight"))
        .withColumn("_full", F.sum("_cap").over(by_ratio) - F.col("_cap"))
        .withColumn("_left", F.sum("weight").over(by_ratio.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("_level", (F.sum("source_size").over(Window.partitionBy()) - F.col("_full")) / F.col("_left"))
    )
    level = F.min_by(
        F.when(F.col("_level") <= F.col("_ratio"), F.col("_level")),
        F.when(F.col("_level") <= F.col("_ratio"), F.struct("_ratio", "ordinal")),
    ).over(Window.partitionBy())
    return base.withColumn("target", F.least(F.col("_cap").cast("double"), level * F.col("weight"))).drop(
        "_cap", "_ratio", "_full", "_left", "_level"
    )


def points_of(slot: Column) -> Column:
    """The schedule's points: whole numbers modulo CIRCLE, exact for any slot, over CIRCLE.

    A slot is multiplied by digits of 15 bits, so no product passes 63 bits.
    """
    digits = (F.shiftright(slot, 15 * k).bitwiseAND(0x7FFF) * F.lit((GOLDEN << 15 * k) % CIRCLE) % F.lit(CIRCLE) for k in range(4))
    return sum(digits, F.lit(GOLDEN // 2)) % F.lit(CIRCLE) / F.lit(float(CIRCLE))


def block_size(least: float | None) -> int:
    """Tokens of a block, given the least positive target."""
    return max(1, min(MIN_BLOCK, int((least or 0) // LEAST_BLOCKS)))


def slot_sources(targets: DataFrame, total: int, block: int, sources: int) -> DataFrame:
    """slot, ordinal, source_size: every slot of the mix with the source that its point names."""
    spark = targets.sparkSession
    slots = -(-total // block)
    grid = max(1, min(max(4096, sources), slots))
    run = Window.orderBy("ordinal")
    spans = (
        targets.filter("target > 0")
        .withColumn("_hi", F.sum("target").over(run) / F.sum("target").over(Window.partitionBy()))
        .withColumn("_lo", F.coalesce(F.lag("_hi").over(run), F.lit(0.0)))
        .withColumn("_hi", F.when(F.lead("_hi").over(run).isNull(), F.lit(2.0)).otherwise(F.col("_hi")))
        .select(
            "ordinal",
            "_lo",
            "_hi",
            "source_size",
            F.explode(
                F.sequence(F.floor(F.col("_lo") * grid), F.floor(F.least(F.col("_hi"), F.lit(1.0)) * grid))
            ).alias("_grid"),
        )
    )
    points = spark.range(slots).select(F.col("id").alias("slot"), points_of(F.col("id")).alias("_point"))
    return (
        points.withColumn("_grid", F.floor(F.col("_point") * grid))
        .join(F.broadcast(spans) if sources <= BROADCAST_ROWS else spans, "_grid")
        .filter("_point >= _lo and _point < _hi")
        .select("slot", "ordinal", "source_size")
    )


def slot_counts(targets: DataFrame, total: int, block: int, sources: int) -> DataFrame:
    """ordinal, blocks: how many slots of the mix a source gets."""
    return slot_sources(targets, total, block, sources).groupBy("ordinal").agg(F.count("*").alias("blocks"))


def slot_blocks(slots: DataFrame, block: int, cap: int) -> DataFrame:
    """slot, ordinal, source_size, block, first, last: the block of a slot, as tokens of its source's repeating stream.

    The block's index is the slot's rank within its source. Tokens from ``first`` up to before ``last``; the
    stream ends after ``cap`` rounds, so a block there may be short or empty.
    """
    slots = slots.withColumn("_run", F.expr(f"slot div {RUN_SLOTS}"))
    bases = (
        slots.groupBy("ordinal", "_run")
        .agg(F.count("*").alias("_n"))
        .withColumn("_base", F.sum("_n").over(Window.partitionBy("ordinal").orderBy("_run")) - F.col("_n"))
        .drop("_n")
    )
    rank = F.row_number().over(Window.partitionBy("ordinal", "_run").orderBy("slot")) - 1
    return (
        slots.withColumn("_rank", rank)
        .join(bases, ["ordinal", "_run"])
        .withColumn("block", F.col("_base") + F.col("_rank"))
        .withColumn("first", F.least(F.col("block") * block, F.col("source_size") * cap))
        .withColumn("last", F.least(F.col("block") * block + block, F.col("source_size") * cap))
        .select("slot", "ordinal", "source_size", "block", "first", "last")
    )


def stream_positions(rows: DataFrame, seed: int = 42) -> DataFrame:
    """Add ``start``: the first token of each document in its source's shuffled stream.

    Needs doc_id, ordinal, size, source_rows.
    """
    draw = F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 31))
    buckets = F.ceil(F.col("source_rows") / BUCKET_ROWS)
    rows = rows.withColumn("_draw", draw).withColumn(
        "_bucket", F.floor(F.col("_draw") / float(1 << 31) * buckets).cast("long")
    )
    starts = (
        rows.groupBy("ordinal", "_bucket")
        .agg(F.sum("size").alias("_sum"))
        .withColumn("_base", F.sum("_sum").over(Window.partitionBy("ordinal").orderBy("_bucket")) - F.col("_sum"))
        .drop("_sum")
    )
    inside = Window.partitionBy("ordinal", "_bucket").orderBy("_draw", "doc_id", "size").rowsBetween(
        Window.unboundedPreceding, Window.currentRow
    )
    return (
        rows.withColumn("_run", F.sum("size").over(inside) - F.col("size"))
        .join(starts, ["ordinal", "_bucket"])
        .withColumn("start", F.col("_base") + F.col("_run"))
        .drop("_draw", "_bucket", "_base", "_run")
    )


def document_tokens(placed: DataFrame, blocks: DataFrame) -> DataFrame:
    """row_id, taken: what the blocks of the slots hold of each document; documents that they miss are left out.

    A block is no longer than its source, so it passes the end of a round once at most. Blocks and documents meet
    at cells of ``CELL_TOKENS`` tokens of the stream; a block's tokens are parted by cell, so none is counted twice.
    """
    at, size = F.col("first") % F.col("source_size"), F.col("last") - F.col("first")
    parts = F.expr(
        f"""flatten(transform(filter(array(struct(_at AS a, least(_at + _size, source_size) AS z), struct(0L AS a, _at + _size - source_size AS z)), p -> p.z > p.a),
            p -> transform(sequence(p.a div {CELL_TOKENS}, (p.z - 1) div {CELL_TOKENS}),
                c -> struct(c AS cell, greatest(p.a, c * {CELL_TOKENS}) AS a, least(p.z, (c + 1) * {CELL_TOKENS}) AS z))))"""
    )
    cut = (
        blocks.filter("last > first")
        .select("ordinal", "source_size", at.alias("_at"), size.alias("_size"))
        .select("ordinal", F.inline(parts))
    )
    cells = F.expr(f"sequence(start div {CELL_TOKENS}, (start + size - 1) div {CELL_TOKENS})")
    held = placed.filter("size > 0").select("ordinal", "row_id", "start", "size", F.explode(cells).alias("cell"))
    common = F.least(F.col("z"), F.col("start") + F.col("size")) - F.greatest(F.col("a"), F.col("start"))
    return held.join(cut, ["ordinal", "cell"]).withColumn("_common", common).filter("_common > 0").groupBy("row_id").agg(F.sum("_common").alias("taken"))


def mix(docs: DataFrame, cap: int = 3) -> DataFrame:
    """doc_id, size, source_size, target, taken, source for every document.

    Null texts and texts without words have size 0 and are never taken. Repeated rows are
    separate documents of the stream. Sources may be null.
    """
    size = F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long")
    # rows with one doc_id and size are interchangeable; row_id tells them apart
    sized = written(
        docs.select("doc_id", "source", size.alias("size")).withColumn("row_id", F.monotonically_increasing_id()), "mix"
    )
    targets = written(source_targets(sized, cap), "targets")
    totals = targets.agg(F.sum("source_size"), F.count("*"), F.min(F.when(F.col("target") > 0, F.col("target")))).first()
    total = int(totals[0] or 0)
    block = block_size(totals[2])
    small = F.broadcast if totals[1] <= BROADCAST_SOURCES else (lambda x: x)
    known = small(targets.withColumnRenamed("source", "_source"))
    placed = written(
        stream_positions(sized.join(known, sized["source"].eqNullSafe(F.col("_source"))).drop("_source")), "placed"
    )
    slots = written(slot_sources(targets, total, block, totals[1]), "slots")
    got = document_tokens(placed, slot_blocks(slots, block, cap))
    return placed.join(got, "row_id", "left").select(
        "doc_id",
        "size",
        "source_size",
        "target",
        F.coalesce("taken", F.lit(0)).cast("long").alias("taken"),
        "source",
    )


def repeated(docs: DataFrame, cap: int = 3) -> DataFrame:
    """The mix itself: every document, all columns, as often as it is taken, to the nearest whole.

    Documents that the mix does not take are left out. Rows that share doc_id, source and size share
    what is taken of them evenly.
    """
    taken = written(
        mix(docs, cap)
        .groupBy("doc_id", "source", "size")
        .agg(F.round(F.sum("taken") / F.greatest(F.sum("size"), F.lit(1))).cast("int").alias("_copies"))
        .filter("_copies > 0"),
        "taken",
    )
    few = taken.count() <= BROADCAST_ROWS
    # documents may have any columns, so helper columns get names that they do not use
    doc, origin, size, copies, words = free_names(docs, "_doc", "_origin", "_size", "_copies", "_words")
    taken = taken.toDF(doc, origin, size, copies)
    sized = docs.withColumn(words, F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long"))
    same = F.col("doc_id").eqNullSafe(F.col(doc)) & F.col("source").eqNullSafe(F.col(origin)) & (F.col(words) == F.col(size))
    return (
        sized.join(F.broadcast(taken) if few else taken, same)
        .withColumn(copies, F.explode(F.sequence(F.lit(1), F.col(copies))))
        .select(*docs.columns)
    )
