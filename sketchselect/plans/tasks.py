"""Learning tasks on the given tables: packed examples with a label and a split."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sketchselect.functions import features as fe
from sketchselect.functions.hashing import portable_id
from sketchselect.tables import load, spread

#: Categories of the click task: one active feature per row and column.
STAR = (
    "l_orderkey", "l_partkey", "l_suppkey", "o_custkey", "ship", "p_brand", "p_type", "c_mktsegment", "o_orderpriority",
    "c_nationkey", "l_returnflag", "l_linestatus",
)


def _text_task(df: DataFrame, key: str, text, label, features) -> DataFrame:
    named = df.withColumn("_split", fe.split_of(text)).withColumn("_label", label.cast("double"))
    ids, _ = fe.presence(features)
    return named.select(F.col(key).cast("long").alias("example_id"), F.col("_label").alias("label"), ids.alias("idx"), F.col("_split").alias("split")).withColumn(
        "val", F.transform("idx", lambda _: F.lit(1.0))
    )


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Binary news-like task: word presence, is the text English."""
    docs = spread(load(spark, sf_dir, "documents"))
    return _text_task(docs, "doc_id", F.col("text"), F.col("lang") == "en", fe.word_set(F.col("text")))


def grams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Web-spam-like task: character 5-grams, quality label."""
    docs = spread(load(spark, sf_dir, "documents")).join(load(spark, sf_dir, "labels"), "doc_id")
    return _text_task(docs, "doc_id", F.col("text"), F.col("quality"), fe.char_ngrams(F.col("text"), 5))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Second web task: 5-grams of stripped pages, is the page English."""
    rows = spread(load(spark, sf_dir, "pages")).withColumn("lang", F.regexp_extract("html", '<html lang="([a-z]+)"', 1))
    rows = rows.withColumn("body", F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ ]+", " ")))
    return _text_task(rows, "page_id", F.col("body"), F.col("lang") == "en", fe.char_ngrams(F.col("body"), 5))


#: Characters of a read of the sequence task.
READ = 100


def reads(docs: DataFrame, length: int = READ) -> DataFrame:
    """Consecutive reads of whole texts: example_id, doc_id, lang, split (by text), read.

    Reads of fewer than three characters hold no 3-gram and are left out. Texts are cut in time linear in their length.
    """
    cut = docs.select("doc_id", "lang", "text", fe.split_of(F.col("text")).alias("split")).select(
        "doc_id", "lang", "split", F.posexplode(F.regexp_extract_all("text", F.lit(f"(?s).{{1,{length}}}"), F.lit(0))).alias("at", "read")
    )
    return cut.filter(F.length("read") > 2).select((F.col("doc_id") * 1_000_000 + F.col("at")).alias("example_id"), "doc_id", "lang", "split", "read")


def even_reads(spark: SparkSession, sf_dir: str, length: int = READ) -> DataFrame:
    """example_id, label, split, read: reads of whole texts, the languages in equal shares.

    Reads are thinned by a draw per read to the size of the smallest class, so nothing is ranked.
    """
    docs = spread(load(spark, sf_dir, "documents"))
    every = reads(docs, length)
    # whole reads and the last one are counted from the length, without cutting
    size = F.length("text")
    n = F.when(F.lit(length > 2), F.floor(size / length)).otherwise(0) + F.when(size % length > 2, 1).otherwise(0)
    sizes = docs.select("lang", n.alias("_n")).filter("_n > 0").groupBy("lang").agg(F.sum("_n").alias("_n"))
    level = F.dense_rank().over(Window.orderBy("lang"))  # one row per language
    shares = sizes.join(F.broadcast(sizes.agg(F.min("_n").alias("_least")))).select("lang", (F.col("_least") / F.col("_n")).alias("_share"), (level - 1).alias("code"))
    even = every.join(F.broadcast(shares), "lang").filter(fe.draw(F.lit("kmers"), F.col("example_id")) < F.col("_share"))
    return even.select("example_id", F.col("code").cast("double").alias("label"), "split", "read")


def with_kmers(even: DataFrame) -> DataFrame:
    """idx and val, 3-gram counts, in place of read."""
    # every position counts, so a k-mer's count is its value
    last = F.length("read") - 2
    gram = F.transform(F.sequence(F.lit(1), last), lambda i: portable_id(F.substring("read", i, F.lit(3))))
    # ascending ids; where runs of equal ids start, and how long they are
    rows = even.withColumn("_all", F.sort_array(gram))
    at = F.sequence(F.lit(0), F.size("_all") - 1)
    rows = rows.withColumn("_from", F.filter(at, lambda i: (i == 0) | (F.get("_all", i) != F.get("_all", i - 1))))
    rows = rows.withColumn("idx", F.transform("_from", lambda i: F.get("_all", i)))
    ends = F.concat(F.slice("_from", F.lit(2), F.size("_from")), F.array(F.size("_all")))
    counted = F.zip_with(ends, "_from", lambda z, a: (z - a).cast("double"))
    return rows.withColumn("val", counted).drop("read", "_all", "_from")


def kmers(spark: SparkSession, sf_dir: str, length: int = READ) -> DataFrame:
    """Sequence-like task: 3-gram counts of reads of whole texts, four languages in equal shares."""
    return with_kmers(even_reads(spark, sf_dir, length)).select("example_id", "label", "idx", "split", "val")


def roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three classes: who speaks, by words."""
    rows = load(spark, sf_dir, "conversations").withColumn("key", F.col("conv_id") * 1000 + F.col("turn"))
    code = F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2)
    return _text_task(rows, "key", F.col("text"), code, fe.word_set(F.col("text")))


def toxic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skewed task for the area under the curve: words, toxic label."""
    docs = spread(load(spark, sf_dir, "documents")).join(load(spark, sf_dir, "labels"), "doc_id")
    return _text_task(docs, "doc_id", F.col("text"), F.col("toxic"), fe.word_set(F.col("text")))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star join with one row per click instance and its twelve categories."""
    return (
        spread(load(spark, sf_dir, "lineitem"))
        .join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(load(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))
        .withColumn("ship", F.date_format("l_shipdate", "yyyy-MM-dd"))
        .withColumn("row_key", F.col("l_orderkey") * 10 + F.col("l_linenumber"))
        .select("row_key", *STAR)
    )


#: Planted click rule: categories of these columns whose draw is small carry a weight.
PLANT_COLUMNS = ("p_brand", "p_type", "c_mktsegment", "o_orderpriority", "c_nationkey", "l_returnflag", "l_linestatus")
PLANT_BASE = 8.0


def planted_weight(category):
    """Weight of a category string: about half of those of low-cardinality columns have one."""
    has = fe.draw(F.lit("support"), category) < 0.5
    size = (F.lit(0.8) + fe.draw(F.lit("size"), category) * 0.4) * 2
    way = F.when(fe.draw(F.lit("way"), category) < 0.5, 1.0).otherwise(-1.0)
    return F.when(has, size * way).otherwise(0.0)


def clicks_scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    """row_key, categories, score, label of the planted click rule (most rows positive)."""
    rows = star(spark, sf_dir)
    parts = [planted_weight(F.concat(F.lit(c + "="), F.col(c).cast("string"))) for c in PLANT_COLUMNS]
    score = sum(parts[1:], parts[0]) + PLANT_BASE
    return rows.withColumn("score", score).withColumn(
        "label", (fe.draw(F.lit("click"), F.col("row_key")) < 1 / (1 + F.exp(-F.col("score")))).cast("double")
    )


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Click-like task: twelve one-hot categories of the star join, planted skewed label.

    The rows of ``clicks_scored``; categories are hashed and weighed in the tables that hold them, before these are joined to the lines.
    """

    def hashed(df: DataFrame, keys: tuple[str, ...], **columns: str) -> DataFrame:
        # id_ and weight_ of a category of a column, from the column that holds its value here
        out = [F.col(k) for k in keys]
        for c, held in columns.items():
            named = F.concat(F.lit(c + "="), F.col(held).cast("string"))
            out += [portable_id(named).alias(f"id_{c}"), *([planted_weight(named).alias(f"weight_{c}")] if c in PLANT_COLUMNS else [])]
        return df.select(*out)

    lines = load(spark, sf_dir, "lineitem")
    flags = ("l_returnflag", "l_linestatus")
    # one row per pair of flags
    marks = hashed(lines.select(*flags).distinct().select(*[F.col(c).alias(f"_{c}") for c in flags]), ("_l_returnflag", "_l_linestatus"), **{c: f"_{c}" for c in flags})
    rows = hashed(spread(lines).withColumn("_ship", F.date_format("l_shipdate", "yyyy-MM-dd")), ("l_orderkey", "l_partkey", "l_linenumber", *flags), l_suppkey="l_suppkey", ship="_ship")
    rows = (
        rows.join(hashed(load(spark, sf_dir, "orders"), ("o_orderkey", "o_custkey"), l_orderkey="o_orderkey", o_orderpriority="o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(
            hashed(load(spark, sf_dir, "customer"), ("c_custkey",), o_custkey="c_custkey", c_mktsegment="c_mktsegment", c_nationkey="c_nationkey"), F.col("o_custkey") == F.col("c_custkey")
        )
        .join(hashed(load(spark, sf_dir, "part"), ("p_partkey",), l_partkey="p_partkey", p_brand="p_brand", p_type="p_type"), F.col("l_partkey") == F.col("p_partkey"))
        .join(F.broadcast(marks), F.col("l_returnflag").eqNullSafe(F.col("_l_returnflag")) & F.col("l_linestatus").eqNullSafe(F.col("_l_linestatus")))
    )
    parts = [F.col(f"weight_{c}") for c in PLANT_COLUMNS]
    rows = rows.withColumn("row_key", F.col("l_orderkey") * 10 + F.col("l_linenumber")).withColumn("score", sum(parts[1:], parts[0]) + PLANT_BASE)
    ids = F.sort_array(F.array_distinct(F.filter(F.array(*[F.col(f"id_{c}") for c in STAR]), lambda x: x.isNotNull())))
    return rows.select(
        F.col("row_key").alias("example_id"), (fe.draw(F.lit("click"), F.col("row_key")) < 1 / (1 + F.exp(-F.col("score")))).cast("double").alias("label"),
        ids.alias("idx"), fe.split_of(F.col("row_key").cast("string")).alias("split"),
    ).withColumn("val", F.transform("idx", lambda _: F.lit(1.0)))


def null_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A label that no feature bears on: is an event a click."""
    rows = load(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k")).withColumn("hour", F.hour("ts"))
    ids, _ = fe.presence(fe.one_hot("user_id", "k", "hour"))
    return rows.select(
        F.col("event_id").alias("example_id"), (F.col("event_type") == "click").cast("double").alias("label"), ids.alias("idx"),
        fe.split_of(F.col("event_id").cast("string")).alias("split"),
    ).withColumn("val", F.transform("idx", lambda _: F.lit(1.0)))


#: Planted regression on vectors: these dimensions carry these weights.
EMBED_SUPPORT = {3: 1.1, 17: -0.9, 40: 0.8, 58: -1.2}


def embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dense regression: 64 features of unit variance, four planted weights."""
    rows = load(spark, sf_dir, "embeddings")
    x = F.transform("embedding", lambda v: v.cast("double") * 8)
    ids = F.sequence(F.lit(0).cast("long"), F.lit(63).cast("long"))
    y = sum((F.col("val")[i] * w for i, w in EMBED_SUPPORT.items()), F.lit(0.0))
    return rows.select(F.col("vec_id").alias("example_id"), ids.alias("idx"), x.alias("val"), fe.split_of(F.col("vec_id").cast("string")).alias("split")).withColumn("label", y)


TASKS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "words": words, "grams": grams, "pages": pages, "kmers": kmers, "roles": roles, "toxic": toxic, "clicks": clicks,
    "null_control": null_control, "embed": embed,
}
#: Losses and class counts of the tasks.
LOSSES = {"kmers": ("softmax", 4), "roles": ("softmax", 3), "embed": ("squared", 1)}


def statistics(examples: DataFrame, name: str) -> DataFrame:
    """task, rows, features, active per row, share of the largest class."""
    # one pass: every row gives its label once, as a null feature, and each of its features
    named = examples.select("label", F.explode(F.concat(F.array(F.lit(None).cast("long")), F.coalesce("idx", F.array().cast("array<bigint>")))).alias("f"))
    # features are counted over all labels, so only the rows keep theirs
    counted = named.groupBy(F.when(F.col("f").isNull(), F.col("label")).alias("label"), "f").agg(F.count("*").alias("c"))
    # per feature over all labels; the null feature holds the rows
    by = counted.groupBy("f").agg(F.sum("c").alias("c"), F.max("c").alias("most"))
    rows, uses = F.sum(F.when(F.col("f").isNull(), F.col("c"))), F.sum(F.when(F.col("f").isNotNull(), F.col("c")))
    largest = F.max(F.when(F.col("f").isNull(), F.col("most")))
    return by.agg(rows.alias("n"), F.count("f").alias("features"), uses.alias("u"), largest.alias("l")).select(
        F.lit(name).alias("task"), F.coalesce("n", F.lit(0).cast("long")).alias("n"), "features",
        F.round(F.coalesce("u", F.lit(0)) / F.col("n"), 4).alias("active"), F.round(F.col("l") / F.col("n"), 6).alias("largest_class"),
    )
