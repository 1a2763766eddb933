"""Queries over the feature functions, with SQL for the check engine."""

from __future__ import annotations

from pyspark.sql import functions as F

from sketchselect.functions import features as fe
from sketchselect.functions.hashing import portable_id, sql_id
from sketchselect.plans import tasks
from sketchselect.tables import load

_WORDS = r"SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM documents"


def _doc_words(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", F.explode(fe.words(F.col("text"))).alias("word"))


def feature_ids_md5(spark, sf_dir):
    return _doc_words(spark, sf_dir).select("word").distinct().withColumn("feature_id", portable_id(F.col("word")))


def word_entries(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", F.explode(fe.word_set(F.col("text"))).alias("word"))


def word_counts(spark, sf_dir):
    return _doc_words(spark, sf_dir).groupBy("doc_id", "word").agg(F.count("*").alias("tf"))


def word_logtf(spark, sf_dir):
    return word_counts(spark, sf_dir).select("doc_id", "word", F.round(1 + F.log("tf"), 6).alias("w"))


def doc_freq(spark, sf_dir):
    return word_entries(spark, sf_dir).groupBy("word").agg(F.count("*").alias("df"))


def min_df_filter(spark, sf_dir):
    return doc_freq(spark, sf_dir).filter("df >= 5")


def word_tfidf(spark, sf_dir):
    n = load(spark, sf_dir, "documents").agg(F.count("*").alias("n"))
    df = doc_freq(spark, sf_dir)
    joined = word_counts(spark, sf_dir).join(df, "word").join(F.broadcast(n))
    return joined.select("doc_id", "word", F.round(F.col("tf") * F.log(F.col("n") / F.col("df")), 5).alias("w"))


def word_bigrams(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id", F.explode(fe.bigrams(fe.words(F.col("text")))).alias("pair"))
    return rows.groupBy("pair").agg(F.count("*").alias("n")).filter("n >= 3")


def _char_ngrams(n):
    def query(spark, sf_dir):
        rows = load(spark, sf_dir, "benchmark")
        return rows.select("item_id", F.explode(fe.char_ngrams(F.col("text"), n)).alias("gram"))

    return query


def kmer_counts(spark, sf_dir):
    rows = tasks.reads(load(spark, sf_dir, "documents"))
    grams = rows.select("doc_id", F.explode(fe.kmers(F.col("read"), 3, "a-e")).alias("kmer"))
    return grams.groupBy("doc_id", "kmer").agg(F.count("*").alias("n"))


def kmer_code(spark, sf_dir):
    return kmer_counts(spark, sf_dir).select("kmer").distinct().withColumn("code", fe.kmer_code(F.col("kmer"), "abcde"))


def onehot_star(spark, sf_dir):
    rows = tasks.star(spark, sf_dir)
    return rows.select("row_key", F.explode(fe.one_hot("p_brand", "c_mktsegment", "ship", "l_returnflag")).alias("c")).withColumn("feature_id", portable_id(F.col("c"))).drop("c")


def event_onehot(spark, sf_dir):
    rows = load(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k")).withColumn("hour", F.hour("ts"))
    return rows.select("event_id", F.explode(fe.one_hot("user_id", "k", "hour")).alias("category"))


def binned_numeric(spark, sf_dir):
    return load(spark, sf_dir, "part").select("p_partkey", F.expr("width_bucket(p_retailprice, 900.0D, 2000.0D, 10)").alias("bin"))


def cross_features(spark, sf_dir):
    rows = tasks.star(spark, sf_dir)
    return rows.groupBy(F.concat_ws("&", "p_brand", "c_mktsegment").alias("pair")).agg(F.count("*").alias("n"))


def embedding_entries(spark, sf_dir):
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("feature", "v"))
    return rows.select("vec_id", "feature", F.round(F.col("v").cast("double") * 8, 5).alias("value"))


def row_norms(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x)), 5).alias("norm"))


def pack_rows(spark, sf_dir):
    rows = tasks.words(spark, sf_dir)
    check = F.aggregate("idx", F.lit(0).cast("long"), lambda s, x: s.bitwiseXOR(x))
    return rows.select("example_id", F.size("idx").alias("n"), check.alias("mark"))


def train_split(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id", fe.split_of(F.col("text")).alias("split"))


def batch_numbers(spark, sf_dir):
    return fe.number_batches(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("example_id")), 20)


def balance_classes(spark, sf_dir):
    return tasks.kmers(spark, sf_dir).select("example_id", F.col("label").cast("int").alias("code"))


def unit_norm_rows(spark, sf_dir):
    rows = fe.unit_norm(tasks.embed(spark, sf_dir))
    return rows.select("example_id", F.round(F.aggregate("val", F.lit(0.0), lambda s, x: s + x * x), 6).alias("length"))


def bias_rows(spark, sf_dir):
    return fe.with_bias(tasks.toxic(spark, sf_dir)).select("example_id", F.col("idx")[0].alias("first"), F.size("val").alias("n"))


def dedup_texts(spark, sf_dir):
    return load(spark, sf_dir, "documents").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id"))


def decontaminate(spark, sf_dir):
    """Documents that hold a benchmark passage: joined by shared five-word runs, then ``contains``."""

    def runs(df, key):
        w = F.col("w")
        n = F.size(w) - 4
        grams = F.when(n >= 1, F.transform(F.sequence(F.lit(1), n), lambda i: F.concat_ws(" ", F.slice(w, i, F.lit(5)))))
        return df.withColumn("w", fe.words(F.col("text"))).select(key, F.explode(F.array_distinct(grams)).alias("g"))

    docs, items = load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")
    near = runs(docs, "doc_id").join(runs(items, "item_id"), "g").select("doc_id", "item_id").distinct()
    both = near.join(docs.select("doc_id", "text"), "doc_id").join(items.withColumnRenamed("text", "passage"), "item_id")
    return both.filter(F.contains("text", "passage")).select("doc_id", "item_id")


_STAR_SQL = """SELECT l_orderkey * 10 + l_linenumber AS row_key, p_brand, c_mktsegment, strftime(l_shipdate, '%Y-%m-%d') AS ship, l_returnflag,
    p_type, o_orderpriority, c_nationkey, l_linestatus
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey"""


def _grams_sql(n):
    return f"SELECT DISTINCT item_id, substr(text, i, {n}) AS gram FROM (SELECT item_id, text, unnest(range(1, length(text) - {n} + 2)) AS i FROM benchmark)"


READS_SQL = "SELECT doc_id * 1000000 + r AS id, doc_id, lang, substr(text, CAST(r * 100 + 1 AS BIGINT), 100) AS cut FROM (SELECT doc_id, lang, text, unnest(range(0, (length(text) + 99) // 100)) AS r FROM documents) WHERE length(text) - r * 100 > 2"
EVEN_SQL = f"""SELECT id, lang, cut FROM (SELECT *, count(*) OVER (PARTITION BY lang) AS n FROM ({READS_SQL})), (SELECT min(n) AS least FROM (SELECT count(*) AS n FROM ({READS_SQL}) GROUP BY lang))
    WHERE CAST('0x' || substr(md5('kmers:' || id), 1, 13) AS BIGINT)::DOUBLE / 4503599627370496.0 < least / n"""
_KMERS = f"SELECT doc_id, substr(cut, i, 3) AS kmer FROM (SELECT doc_id, cut, unnest(range(1, length(cut) - 1)) AS i FROM ({READS_SQL}))"
_BATCH = "SELECT doc_id AS example_id, md5('0:' || doc_id) AS o FROM documents"

ORACLES = {
    "feature_ids_md5": f"SELECT DISTINCT word, {sql_id('word')} AS feature_id FROM ({_WORDS})",
    "word_entries": f"SELECT DISTINCT doc_id, word FROM ({_WORDS})",
    "word_counts": f"SELECT doc_id, word, count(*) AS tf FROM ({_WORDS}) GROUP BY doc_id, word",
    "word_logtf": f"SELECT doc_id, word, round(1 + ln(count(*)), 6) AS w FROM ({_WORDS}) GROUP BY doc_id, word",
    "doc_freq": f"SELECT word, count(DISTINCT doc_id) AS df FROM ({_WORDS}) GROUP BY word",
    "min_df_filter": f"SELECT word, count(DISTINCT doc_id) AS df FROM ({_WORDS}) GROUP BY word HAVING count(DISTINCT doc_id) >= 5",
    "word_tfidf": f"""WITH w AS ({_WORDS}), t AS (SELECT doc_id, word, count(*) AS tf FROM w GROUP BY doc_id, word),
        f AS (SELECT word, count(*) AS df FROM t GROUP BY word), n AS (SELECT count(*) AS n FROM documents)
        SELECT doc_id, t.word, round(tf * ln(n / df), 5) AS w FROM t JOIN f ON t.word = f.word, n""",
    "word_bigrams": r"""WITH w AS (SELECT doc_id, regexp_extract_all(lower(text), '\p{L}+') AS w FROM documents),
        p AS (SELECT w[i] || ' ' || w[i + 1] AS pair FROM (SELECT w, unnest(range(1, len(w))) AS i FROM w))
        SELECT pair, count(*) AS n FROM p GROUP BY pair HAVING count(*) >= 3""",
    "char_ngrams_3": _grams_sql(3),
    "char_ngrams_5": _grams_sql(5),
    "kmer_counts": f"SELECT doc_id, kmer, count(*) AS n FROM ({_KMERS}) WHERE regexp_matches(kmer, '^[a-e]+$') GROUP BY doc_id, kmer",
    "kmer_code": f"SELECT DISTINCT kmer, CAST((ascii(kmer[1]) - 97) * 25 + (ascii(kmer[2]) - 97) * 5 + ascii(kmer[3]) - 97 AS BIGINT) AS code FROM ({_KMERS}) WHERE regexp_matches(kmer, '^[a-e]+$')",
    "onehot_star": f"SELECT row_key, {sql_id('c')} AS feature_id FROM (SELECT row_key, unnest(['p_brand=' || p_brand, 'c_mktsegment=' || c_mktsegment, 'ship=' || ship, 'l_returnflag=' || l_returnflag]) AS c FROM ({_STAR_SQL}))",
    "event_onehot": "SELECT event_id, unnest(['user_id=' || user_id, 'k=' || json_extract_string(props, '$.k'), 'hour=' || hour(ts)]) AS category FROM events",
    "binned_numeric": "SELECT p_partkey, CASE WHEN p_retailprice < 900 THEN 0 WHEN p_retailprice >= 2000 THEN 11 ELSE CAST(floor((p_retailprice - 900) / (2000 - 900) * 10) AS BIGINT) + 1 END AS bin FROM part",
    "cross_features": f"SELECT p_brand || '&' || c_mktsegment AS pair, count(*) AS n FROM ({_STAR_SQL}) GROUP BY 1",
    "embedding_entries": "SELECT vec_id, CAST(i - 1 AS INTEGER) AS feature, round(embedding[i]::DOUBLE * 8, 5) AS value FROM (SELECT vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings)",
    "row_norms": "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) AS norm FROM embeddings",
    "pack_rows": f"SELECT doc_id AS example_id, CAST(count(*) AS INTEGER) AS n, bit_xor({sql_id('word')}) AS mark FROM (SELECT DISTINCT doc_id, word FROM ({_WORDS})) GROUP BY doc_id",
    "train_split": f"SELECT doc_id, CASE WHEN {sql_id('text')} % 10 < 8 THEN 'train' ELSE 'test' END AS split FROM documents",
    "batch_numbers": f"SELECT example_id, CAST((row_number() OVER (ORDER BY o, example_id) - 1) // 20 AS BIGINT) AS batch_id FROM ({_BATCH})",
    "balance_classes": f"SELECT id AS example_id, CAST(dense_rank() OVER (ORDER BY lang) - 1 AS INTEGER) AS code FROM ({EVEN_SQL})",
    "dedup_texts": "SELECT md5(text) AS digest, min(doc_id) AS doc_id FROM documents GROUP BY md5(text)",
    "decontaminate": "SELECT doc_id, item_id FROM documents d, benchmark b WHERE contains(d.text, b.text)",
    "unit_norm_rows": "SELECT vec_id AS example_id, 1.0::DOUBLE AS length FROM embeddings",
    "bias_rows": f"SELECT d.doc_id AS example_id, -1::BIGINT AS first, CAST(count(DISTINCT word) + 1 AS INTEGER) AS n FROM labels d JOIN ({_WORDS}) w ON d.doc_id = w.doc_id GROUP BY d.doc_id",
}

QUERIES = {
    f.__name__: f
    for f in (
        feature_ids_md5, word_entries, word_counts, word_logtf, doc_freq, min_df_filter, word_tfidf, word_bigrams, kmer_counts, kmer_code,
        onehot_star, event_onehot, binned_numeric, cross_features, embedding_entries, row_norms, pack_rows, train_split, batch_numbers,
        balance_classes, unit_norm_rows, bias_rows, dedup_texts, decontaminate,
    )
} | {"char_ngrams_3": _char_ngrams(3), "char_ngrams_5": _char_ngrams(5)}
