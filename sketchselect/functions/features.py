"""Sparse features of text, categories and vectors, as arrays inside the row.

Nothing is exploded here; ``entries`` does that where a long table is wanted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sketchselect.functions.hashing import portable_id

WORD = r"(\p{L}+)"


def words(text: Column) -> Column:
    """Lower-case letter runs in order, repeats included."""
    return F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(1))


def word_set(text: Column) -> Column:
    return F.array_distinct(words(text))


def substrings(text: Column, n: int) -> Column:
    """All substrings of n characters in order, in time linear in the text.

    A zero-width match at every position captures what follows it; positions inside a
    surrogate pair are left out.
    """
    return F.regexp_extract_all(text, F.lit(rf"(?s)(?![\uDC00-\uDFFF])(?=(.{{{n}}}))"), F.lit(1))


def char_ngrams(text: Column, n: int) -> Column:
    """Distinct substrings of n characters; none where the text is shorter."""
    return F.array_distinct(substrings(text, n))


def kmers(text: Column, k: int, alphabet: str) -> Column:
    """All k-mers in order whose characters lie in ``alphabet`` (a character class)."""
    return F.filter(substrings(text, k), lambda g: g.rlike(rf"^[{alphabet}]+\z"))


def kmer_code(kmer: Column, alphabet: str) -> Column:
    """A k-mer as an integer in base |alphabet|; fits a long up to 15 symbols ** 12."""
    digits = F.transform(F.split(kmer, ""), lambda c: F.instr(F.lit(alphabet), c).cast("long") - 1)
    return F.aggregate(digits, F.lit(0).cast("long"), lambda acc, d: acc * len(alphabet) + d)


def bigrams(tokens: Column) -> Column:
    """Adjacent token pairs, joined by a space."""
    n = F.size(tokens)
    pairs = F.zip_with(F.slice(tokens, F.lit(1), n - 1), F.slice(tokens, F.lit(2), n - 1), lambda a, b: F.concat_ws(" ", a, b))
    return F.when(n >= 2, pairs).otherwise(F.array().cast("array<string>"))


def one_hot(*columns: str) -> Column:
    """One category string per column: ``column=value``; nulls give no category."""
    made = F.array(*[F.when(F.col(c).isNotNull(), F.concat(F.lit(c + "="), F.col(c).cast("string"))) for c in columns])
    return F.filter(made, lambda x: x.isNotNull())


def presence(features: Column) -> tuple[Column, Column]:
    """(ids ascending, ones) of distinct string features."""
    ids = F.sort_array(F.array_distinct(F.transform(features, portable_id)))
    return ids, F.transform(ids, lambda _: F.lit(1.0))


def packed(df: DataFrame, key: str, label: Column, features: Column) -> DataFrame:
    """example_id, label, idx, val from an array of string features; presence is 1."""
    ids, ones = presence(features)
    return df.select(F.col(key).cast("long").alias("example_id"), label.cast("double").alias("label"), ids.alias("idx")).withColumn(
        "val", F.transform("idx", lambda _: F.lit(1.0))
    )


def unit_norm(df: DataFrame) -> DataFrame:
    """Scale each packed row to length 1; empty rows stay."""
    norm = F.sqrt(F.aggregate("val", F.lit(0.0), lambda s, x: s + x * x))
    return df.withColumn("val", F.when(norm > 0, F.transform("val", lambda x: x / norm)).otherwise(F.col("val")))


def with_bias(df: DataFrame, bias_id: int = -1) -> DataFrame:
    """Add a feature that is always 1; its id must be below all others."""
    return df.withColumn("idx", F.concat(F.array(F.lit(bias_id).cast("long")), "idx")).withColumn("val", F.concat(F.array(F.lit(1.0)), "val"))


def entries(packed_rows: DataFrame) -> DataFrame:
    """example_id, feature_id, value: the long form."""
    return packed_rows.select("example_id", F.explode(F.arrays_zip("idx", "val")).alias("e")).select(
        "example_id", F.col("e.idx").alias("feature_id"), F.col("e.val").alias("value")
    )


def draw(*parts: Column) -> Column:
    """A uniform number in [0, 1) from the md5 of the parts: the same in any engine and plan."""
    digest = F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / float(16**13)


def split_of(text: Column) -> Column:
    """``train`` for eight tenths of the texts, by md5, so copies of a text stay together."""
    tenth = F.pmod(portable_id(text), F.lit(10))
    return F.when(tenth < 8, F.lit("train")).otherwise(F.lit("test"))


def number_batches(df: DataFrame, batch_size: int, seed: int = 0) -> DataFrame:
    """Add ``batch_id``: rows in hash order, ``batch_size`` at a time.

    The hash space is cut into buckets whose counts give offsets, so that no task orders all
    rows.
    """
    order = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("example_id").cast("string")))
    n = df.count()
    buckets = max(1, n // 4096)
    rows = df.withColumn("_order", order).withColumn(
        "_bucket", F.floor(F.conv(F.substring("_order", 1, 8), 16, 10).cast("double") / float(1 << 32) * buckets).cast("long")
    )
    starts = rows.groupBy("_bucket").agg(F.count("*").alias("_n")).withColumn(
        "_start", F.sum("_n").over(Window.orderBy("_bucket")) - F.col("_n")
    )
    within = Window.partitionBy("_bucket").orderBy("_order", "example_id")
    return (
        rows.withColumn("_at", F.row_number().over(within) - 1)
        .join(F.broadcast(starts) if buckets <= 100_000 else starts, "_bucket")
        .withColumn("batch_id", F.floor((F.col("_start") + F.col("_at")) / batch_size).cast("long"))
        .drop("_order", "_bucket", "_n", "_start", "_at")
    )
