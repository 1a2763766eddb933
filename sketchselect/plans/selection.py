"""Queries over the sketch, the trainers and the measures, with SQL for the check engine."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from sketchselect.functions import features as fe
from sketchselect.functions import hashing as hs
from sketchselect.functions.hashing import SketchSpec, portable_id, sql_id
from sketchselect.operators import measures, sketch
from sketchselect.operators.sync import gram_direction
from sketchselect.plans import tasks
from sketchselect.plans.featurequeries import EVEN_SQL
from sketchselect.tables import load, written

#: The sketch of the SQL-checked queries: affine hashes, which any engine can compute.
SPEC = SketchSpec(rows=5, buckets=64, seed=1, family="affine")
MURMUR = SketchSpec(rows=5, buckets=64, seed=3)


# ---- hashing


def hash_buckets(spark, sf_dir):
    rows = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.inline(hs.places(F.col("p_partkey"), MURMUR)))
    return rows.select("id", F.col("row").alias("j"), "bucket")


def hash_signs(spark, sf_dir):
    rows = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.inline(hs.places(F.col("p_partkey"), MURMUR)))
    return rows.select("id", F.col("row").alias("j"), "sign")


def hash_affine(spark, sf_dir):
    rows = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.inline(hs.places(F.col("p_partkey"), SPEC)))
    return rows.select("id", F.col("row").alias("j"), "bucket", "sign")


def sql_bucket_fn(spark, sf_dir):
    """The hash as SQL functions, which the analyzer inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sk_bucket(j INT, id BIGINT, c INT) RETURNS INT RETURN pmod(hash(j, id), c)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sk_sign(j INT, id BIGINT) RETURNS INT RETURN 1 - 2 * (hash(j, id) & 1)")
    return spark.sql(
        "SELECT p_partkey AS id, j, sk_bucket(3000 + j, p_partkey, 64) AS bucket FROM {part} LATERAL VIEW explode(sequence(0, 4)) t AS j",
        part=load(spark, sf_dir, "part"),
    )


# ---- sketch


def lineitem_entries(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("feature_id"), F.col("l_quantity").alias("value"))


def word_entries(spark, sf_dir):
    """Word occurrences with portable ids."""
    rows = load(spark, sf_dir, "documents").select("doc_id", "lang", F.explode(fe.words(F.col("text"))).alias("word"))
    return rows.select("doc_id", "lang", "word", portable_id(F.col("word")).alias("feature_id"), F.lit(1.0).alias("value"))


def sketch_build_words(spark, sf_dir):
    return sketch.build(word_entries(spark, sf_dir), SPEC)


def sketch_build_lineitem(spark, sf_dir):
    return sketch.build(lineitem_entries(spark, sf_dir), SPEC)


def sketch_build_events(spark, sf_dir):
    return sketch.build(load(spark, sf_dir, "events").select(F.col("user_id").alias("feature_id"), F.lit(1.0).alias("value")), SPEC)


def sketch_by_lang(spark, sf_dir):
    return sketch.build(word_entries(spark, sf_dir), SPEC, by=["lang"])


def _parts(spark, sf_dir):
    return load(spark, sf_dir, "part").select(F.col("p_partkey").alias("feature_id"))


def sketch_query_median(spark, sf_dir):
    return sketch.query(sketch_build_lineitem(spark, sf_dir), _parts(spark, sf_dir), SPEC)


def sketch_query_mean(spark, sf_dir):
    out = sketch.query(sketch_build_lineitem(spark, sf_dir), _parts(spark, sf_dir), SPEC.with_(query="mean"))
    return out.select("feature_id", F.round("estimate", 6).alias("estimate"))


def heavy_hitters(spark, sf_dir):
    return sketch.top_k(sketch_query_median(spark, sf_dir), 20)


def heavy_hitters_exact(spark, sf_dir):
    exact = lineitem_entries(spark, sf_dir).groupBy("feature_id").agg(F.sum("value").alias("estimate"))
    return sketch.top_k(exact, 20)


def sketch_merge(spark, sf_dir):
    rows = lineitem_entries(spark, sf_dir)
    return sketch.merge(sketch.build(rows.filter("feature_id % 2 = 0"), SPEC), sketch.build(rows.filter("feature_id % 2 = 1"), SPEC))


def sketch_scale_sub(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("feature_id"), F.col("l_linenumber").cast("double").alias("value"))
    return sketch.subtract(sketch_build_lineitem(spark, sf_dir), sketch.build(rows, SPEC), 0.125)


def sketch_error(spark, sf_dir):
    exact = lineitem_entries(spark, sf_dir).groupBy("feature_id").agg(F.sum("value").alias("value"))
    return sketch.error(sketch_build_lineitem(spark, sf_dir), exact, SPEC)


def bucket_load(spark, sf_dir):
    return sketch.load(_parts(spark, sf_dir), SPEC)


def collision_pairs(spark, sf_dir):
    return sketch.collisions(heavy_hitters_exact(spark, sf_dir), SPEC)


def tail_energy(spark, sf_dir):
    exact = lineitem_entries(spark, sf_dir).groupBy("feature_id").agg(F.sum("value").alias("value"))
    out = measures.tail(exact, 50)
    return out.select(F.round("tail_energy", 3).alias("tail_energy"), "zeta")


def projection_gram(spark, sf_dir):
    """Diagonal of S'S over all parts."""
    cells = sketch.projection(_parts(spark, sf_dir), SPEC)
    return cells.groupBy("col").agg(F.round(F.sum(F.col("value") ** 2), 6).alias("norm"))


_PLACED = " UNION ALL ".join(
    f"SELECT *, {j} AS row, {hs.sql_bucket('feature_id', j, SPEC)} AS bucket, {hs.sql_sign('feature_id', j, SPEC)} AS sign FROM e" for j in range(5)
)
_LINE = "SELECT l_partkey AS feature_id, l_quantity AS value FROM lineitem"
_WORDS = rf"SELECT doc_id, lang, word, {sql_id('word')} AS feature_id, 1.0::DOUBLE AS value FROM (SELECT doc_id, lang, unnest(regexp_extract_all(lower(text), '\p{{L}}+')) AS word FROM documents)"


def _cells_sql(source: str, by: str = "", extra: str = "") -> str:
    return f"SELECT {by} CAST(row AS INTEGER) AS row, bucket, sum(sign * value) AS value {extra} FROM (WITH e AS ({source}) {_PLACED}) GROUP BY {by} row, bucket"


def _read_sql(cells: str, ids: str, how: str = "median") -> str:
    """Estimates of ids (feature_id) from cells, both as SQL."""
    placed = _PLACED.replace(" FROM e", " FROM asked")
    return f"""(WITH cells AS ({cells}), asked AS ({ids}), placed AS ({placed})
        SELECT p.feature_id, {how}(p.sign * coalesce(c.value, 0)) AS estimate FROM placed p LEFT JOIN cells c ON p.row = c.row AND p.bucket = c.bucket GROUP BY p.feature_id)"""


_PARTS = "SELECT p_partkey AS feature_id FROM part"
_EXACT = f"SELECT feature_id, sum(value) AS value FROM ({_LINE}) GROUP BY feature_id"
_READ = _read_sql(_cells_sql(_LINE), _PARTS)
_MURMUR_SOURCE = "(SELECT p_partkey AS id, j::INTEGER AS j, {seed} AS seed FROM part, range(5) r(j))"


# ---- first steps in closed form: words, is the text English, batches of 20 in hash order

ETA = 0.0625
BATCH = 20
HELD = 50


def _examples(spark, sf_dir):
    docs = load(spark, sf_dir, "documents")
    rows = fe.number_batches(docs.select(F.col("doc_id").alias("example_id"), "lang", "text"), BATCH)
    entries = rows.select("example_id", "batch_id", "lang", F.explode(fe.word_set(F.col("text"))).alias("w"))
    return entries.select("example_id", "batch_id", "lang", (F.col("lang") == "en").cast("double").alias("label"), portable_id(F.col("w")).alias("feature_id"))


def _gradient(rows, weights=None):
    """feature_id, g over the entries of a minibatch; ``weights`` (feature_id, estimate) are few."""
    if weights is None:
        return rows.groupBy("feature_id").agg(F.sum(F.lit(0.5) - F.col("label")).alias("g"))
    known = rows.join(F.broadcast(weights), "feature_id", "left")
    margin = known.groupBy("example_id").agg(F.coalesce(F.sum("estimate"), F.lit(0.0)).alias("m"))
    return rows.join(margin, "example_id").groupBy("feature_id").agg(F.sum(1 / (1 + F.exp(-F.col("m"))) - F.col("label")).alias("g"))


def _batch(spark, sf_dir, t):
    return _examples(spark, sf_dir).filter(F.col("batch_id") == t)


def first_step_gradient(spark, sf_dir):
    return _gradient(_batch(spark, sf_dir, 0))


def first_step_sketch(spark, sf_dir):
    return sketch.build(first_step_gradient(spark, sf_dir), SPEC, value=F.col("g") * -ETA)


def first_step_topk(spark, sf_dir):
    ids = first_step_gradient(spark, sf_dir).select("feature_id")
    return sketch.top_k(sketch.query(first_step_sketch(spark, sf_dir), ids, SPEC), HELD)


def first_step_multiclass(spark, sf_dir):
    rows = _batch(spark, sf_dir, 0)
    classes = F.explode(F.array(*[F.lit(c) for c in ("de", "en", "es", "fr")])).alias("class")
    each = rows.select("feature_id", "lang", classes)
    return each.groupBy("class", "feature_id").agg(F.sum(0.25 - (F.col("lang") == F.col("class")).cast("double")).alias("g"))


def _held(spark, sf_dir, cells, active):
    """Held features that are active, read from ``cells``."""
    held = first_step_topk(spark, sf_dir).select("feature_id").join(active.select("feature_id").distinct(), "feature_id")
    return sketch.query(cells, held, SPEC)


def second_step(spark, sf_dir):
    """Everything of the second step: batch, weights and gradient before, cells after, pair."""
    cells = first_step_sketch(spark, sf_dir)
    rows = _batch(spark, sf_dir, 1)
    before = _held(spark, sf_dir, cells, rows)
    g = _gradient(rows, before)
    after_cells = sketch.merge(cells, sketch.build(g, SPEC, value=F.col("g") * -ETA))
    after = _held(spark, sf_dir, after_cells, rows)
    s = after.join(before.withColumnRenamed("estimate", "old"), "feature_id").select("feature_id", (F.col("estimate") - F.col("old")).alias("s"))
    r = _gradient(rows, after).join(g.withColumnRenamed("g", "old"), "feature_id").select("feature_id", (F.col("g") - F.col("old")).alias("r"))
    return rows, g, after_cells, s, r


def second_step_sketch(spark, sf_dir):
    cells = second_step(spark, sf_dir)[2]
    return cells.select("row", "bucket", F.round("value", 6).alias("value"))


def second_step_pair(spark, sf_dir):
    _, _, _, s, r = second_step(spark, sf_dir)
    both = r.join(s, "feature_id", "left")
    return both.select("feature_id", F.round(F.coalesce("s", F.lit(0.0)), 6).alias("s"), F.round("r", 6).alias("r"))


def _second_heap(spark, sf_dir):
    """The heap after two steps: the first heap's stored values, the second batch read again."""
    rows, g, cells, *_ = second_step(spark, sf_dir)
    fresh = sketch.query(cells, g.select("feature_id"), SPEC)
    stays = first_step_topk(spark, sf_dir).join(fresh.select("feature_id"), "feature_id", "left_anti")
    return sketch.top_k(stays.unionByName(fresh), HELD)


def _third_gradient(spark, sf_dir):
    rows = _batch(spark, sf_dir, 2)
    cells = second_step(spark, sf_dir)[2]
    held = _second_heap(spark, sf_dir).select("feature_id").join(rows.select("feature_id").distinct(), "feature_id")
    return _gradient(rows, sketch.query(cells, held, SPEC)), cells


def gram_basis(spark, sf_dir):
    """Dot products of {s, r} of the second step and g of the third."""
    *_, s, r = second_step(spark, sf_dir)
    g, _ = _third_gradient(spark, sf_dir)
    table = s.join(r, "feature_id", "full").join(g, "feature_id", "full").na.fill(0.0)
    return table.agg(*[F.round(F.sum(F.col(a) * F.col(b)), 5).alias(a + b) for a, b in ("ss", "sr", "sg", "rr", "rg", "gg")])


def _direction(spark, sf_dir):
    *_, s, r = second_step(spark, sf_dir)
    g, cells = _third_gradient(spark, sf_dir)
    table = g.join(s, "feature_id", "left").join(r, "feature_id", "left").na.fill(0.0)
    every = s.join(r, "feature_id", "full").join(g, "feature_id", "full").na.fill(0.0)
    dots = every.agg(*[F.sum(F.col(a) * F.col(b)).alias(a + b) for a, b in ("ss", "sr", "sg", "rr", "rg", "gg")]).first()
    import numpy as np

    gram = np.array([[dots["ss"], dots["sr"], dots["sg"]], [dots["sr"], dots["rr"], dots["rg"]], [dots["sg"], dots["rg"], dots["gg"]]])
    u = gram_direction(gram)
    return table.select("feature_id", (F.col("s") * float(u[0]) + F.col("r") * float(u[1]) + F.col("g") * float(u[2])).alias("z")), cells


def third_step_direction(spark, sf_dir):
    return _direction(spark, sf_dir)[0].select("feature_id", F.round("z", 5).alias("z"))


def third_step_sketch(spark, sf_dir):
    z, cells = _direction(spark, sf_dir)
    out = sketch.merge(cells, sketch.build(z, SPEC, value=F.col("z") * -ETA))
    return out.select("row", "bucket", F.round("value", 5).alias("value"))


def gradient_only_third_step(spark, sf_dir):
    g, cells = _third_gradient(spark, sf_dir)
    out = sketch.merge(cells, sketch.build(g, SPEC, value=F.col("g") * -ETA))
    return out.select("row", "bucket", F.round("value", 6).alias("value"))


_EX = rf"""b AS (SELECT doc_id AS example_id, lang, text, (row_number() OVER (ORDER BY md5('0:' || doc_id), doc_id) - 1) // {BATCH} AS batch_id FROM documents),
    ex AS (SELECT DISTINCT example_id, batch_id, lang, CASE WHEN lang = 'en' THEN 1.0 ELSE 0.0 END::DOUBLE AS label, {sql_id('word')} AS feature_id
        FROM (SELECT example_id, batch_id, lang, unnest(regexp_extract_all(lower(text), '\p{{L}}+')) AS word FROM b WHERE batch_id < 3))"""


def _grad_sql(t: int, weights: str) -> str:
    return f"""SELECT x.feature_id, sum(1 / (1 + exp(-m)) - label) AS g FROM ex x JOIN (
        SELECT e.example_id, coalesce(sum(w.estimate), 0) AS m FROM ex e LEFT JOIN {weights} w ON e.feature_id = w.feature_id WHERE batch_id = {t} GROUP BY e.example_id) m
        ON x.example_id = m.example_id GROUP BY x.feature_id"""


def _merged(a: str, b: str) -> str:
    return f"SELECT row, bucket, sum(value) AS value FROM (SELECT * FROM {a} UNION ALL SELECT * FROM ({b})) GROUP BY row, bucket"


def _held_sql(cells: str, heap: str, t: int) -> str:
    return _read_sql(f"SELECT * FROM {cells}", f"SELECT feature_id FROM {heap} WHERE feature_id IN (SELECT feature_id FROM ex WHERE batch_id = {t})")[1:-1]


def _top_sql(source: str) -> str:
    return f"SELECT feature_id, estimate FROM {source} ORDER BY abs(estimate) DESC, feature_id LIMIT {HELD}"


_STEPS = f"""WITH {_EX},
    g1 AS (SELECT feature_id, sum(0.5 - label) AS g FROM ex WHERE batch_id = 0 GROUP BY feature_id),
    c1 AS ({_cells_sql(f'SELECT feature_id, g * -{ETA} AS value FROM g1')}),
    h1 AS ({_top_sql(_read_sql('SELECT * FROM c1', 'SELECT feature_id FROM g1'))}),
    w2 AS ({_held_sql('c1', 'h1', 1)}), g2 AS ({_grad_sql(1, 'w2')}),
    c2 AS ({_merged('c1', _cells_sql(f'SELECT feature_id, g * -{ETA} AS value FROM g2'))}),
    v2 AS ({_held_sql('c2', 'h1', 1)}), d2 AS ({_grad_sql(1, 'v2')}),
    s AS (SELECT v2.feature_id, v2.estimate - w2.estimate AS s FROM v2 JOIN w2 USING (feature_id)),
    r AS (SELECT d2.feature_id, d2.g - g2.g AS r FROM d2 JOIN g2 USING (feature_id)),
    f2 AS ({_read_sql('SELECT * FROM c2', 'SELECT feature_id FROM g2')[1:-1]}),
    h2 AS ({_top_sql('(SELECT * FROM f2 UNION ALL SELECT * FROM h1 WHERE feature_id NOT IN (SELECT feature_id FROM f2))')}),
    w3 AS ({_held_sql('c2', 'h2', 2)}), g3 AS ({_grad_sql(2, 'w3')}),
    every AS (SELECT feature_id, coalesce(s, 0) AS s, coalesce(r, 0) AS r, coalesce(g, 0) AS g FROM s FULL JOIN r USING (feature_id) FULL JOIN g3 USING (feature_id)),
    dots AS (SELECT sum(s * s) AS ss, sum(s * r) AS sr, sum(s * g) AS sg, sum(r * r) AS rr, sum(r * g) AS rg, sum(g * g) AS gg FROM every),
    a AS (SELECT *, sg / sr AS share, sr / rr AS theta FROM dots),
    z3 AS (SELECT g3.feature_id, theta * (g3.g - share * coalesce(r.r, 0)) + (share - theta * (rg - share * rr) / sr) * coalesce(s.s, 0) AS z
        FROM g3 LEFT JOIN s USING (feature_id) LEFT JOIN r USING (feature_id), a)"""


# ---- measures


def active_set_size(spark, sf_dir):
    return _examples(spark, sf_dir).groupBy("batch_id").agg(F.count_distinct("feature_id").alias("active"))


def memory_model(spark, sf_dir):
    return measures.memory_model(active_set_size(spark, sf_dir), 100, 5, SPEC)


def compression_factor(spark, sf_dir):
    p = word_entries(spark, sf_dir).agg(F.count_distinct("feature_id").alias("p"))
    return p.select("p", F.lit(SPEC.cells).alias("cells"), F.round(F.col("p") / SPEC.cells, 6).alias("cf"))


def hashed_projection(spark, sf_dir):
    one = SPEC.with_(rows=1, buckets=256)
    rows = word_entries(spark, sf_dir).select("doc_id", F.inline(hs.places(F.col("feature_id"), one)))
    return rows.groupBy("doc_id", "bucket").agg(F.sum("sign").alias("value"))


def hessian_pairs(spark, sf_dir):
    """Curvature at zero weights over the first batch for its 50 most frequent words."""
    rows = _batch(spark, sf_dir, 0).select("example_id", "feature_id")
    top = rows.groupBy("feature_id").count().orderBy(F.desc("count"), "feature_id").limit(50).select("feature_id")
    kept = rows.join(F.broadcast(top), "feature_id")
    pairs = kept.withColumnRenamed("feature_id", "i").join(kept.withColumnRenamed("feature_id", "j"), "example_id")
    return pairs.groupBy("i", "j").agg((F.count("*") * 0.25).alias("h"))


def planted_labels(spark, sf_dir):
    rows = tasks.clicks_scored(spark, sf_dir)
    return rows.select("row_key", F.round("score", 6).alias("score"), "label")


def planted_regression(spark, sf_dir):
    return tasks.embed(spark, sf_dir).select("example_id", F.round("label", 5).alias("y"))


def gauss_box_muller(spark, sf_dir):
    """Ten normals for every customer from md5 draws: the same in any plan and engine."""
    ids = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("i"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(9).cast("long"))).alias("j"))
    u, v = fe.draw(F.lit("u"), F.col("i"), F.col("j")), fe.draw(F.lit("v"), F.col("i"), F.col("j"))
    return ids.select("i", "j", F.round(F.sqrt(-2 * F.log(1 - u)) * F.cos(v * 6.283185307179586), 6).alias("x"))


_WEIGHTS = {"the": 0.9, "and": 0.4, "of": 0.3, "der": -0.8, "und": -0.6, "de": -0.5, "que": -0.7, "in": 0.1, "ist": -0.3, "stupid": 0.2}


def _fixed_weights(spark):
    rows = F.explode(F.array(*[F.struct(F.lit(w).alias("word"), F.lit(v).alias("estimate")) for w, v in _WEIGHTS.items()]))
    return spark.range(1).select(rows.alias("e")).select("e.word", "e.estimate")


def predict_topk_scores(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id", F.explode_outer(fe.word_set(F.col("text"))).alias("word"))
    return rows.join(F.broadcast(_fixed_weights(spark)), "word", "left").groupBy("doc_id").agg(F.round(F.coalesce(F.sum("estimate"), F.lit(0.0)), 6).alias("score"))


def predict_sketch_scores(spark, sf_dir):
    """Scores with all active features read from the cells after one step."""
    rows = _batch(spark, sf_dir, 1)
    read = sketch.query(first_step_sketch(spark, sf_dir), rows.select("feature_id").distinct(), SPEC)
    return rows.join(read, "feature_id").groupBy("example_id").agg(F.round(F.sum("estimate"), 6).alias("score"))


def softmax_scores(spark, sf_dir):
    """Class probabilities from the four classes' first step, by exact weights."""
    g = first_step_multiclass(spark, sf_dir).withColumn("w", F.col("g") * -ETA)
    rows = _batch(spark, sf_dir, 1).select("example_id", "feature_id")
    classes = g.select("class").distinct()
    scores = rows.select("example_id").distinct().join(F.broadcast(classes)).join(
        rows.join(g, "feature_id").groupBy("example_id", "class").agg(F.sum("w").alias("score")), ["example_id", "class"], "left"
    ).withColumn("score", F.coalesce("score", F.lit(0.0)))
    w = Window.partitionBy("example_id")
    e = F.exp(F.col("score") - F.max("score").over(w))
    return scores.select("example_id", "class", F.round(e / F.sum(e).over(w), 6).alias("p"))


def _decided(spark, sf_dir):
    return predict_topk_scores(spark, sf_dir).join(load(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id").select(
        "doc_id", "lang", (F.col("lang") == "en").cast("double").alias("label"), "score", (F.col("score") > 0).cast("double").alias("prediction")
    )


def accuracy_by_lang(spark, sf_dir):
    return measures.accuracy(_decided(spark, sf_dir), ["lang"]).select("lang", F.round("accuracy", 6).alias("accuracy"))


def confusion_lang(spark, sf_dir):
    return measures.confusion(_decided(spark, sf_dir))


def auc_topk(spark, sf_dir):
    return measures.auc(_decided(spark, sf_dir), []).select(F.round("auc", 6).alias("auc"))


def auc_by_source(spark, sf_dir):
    rows = _decided(spark, sf_dir).join(load(spark, sf_dir, "documents").select("doc_id", "source"), "doc_id")
    return measures.auc(rows, ["source"]).select("source", F.round("auc", 6).alias("auc"))


def roc_points(spark, sf_dir):
    rows = measures.roc(_decided(spark, sf_dir))
    return rows.select("threshold", F.round("tpr", 6).alias("tpr"), F.round("fpr", 6).alias("fpr"))


def naive_baseline(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("lang").alias("label"))
    return measures.naive(docs).select(F.round("majority", 6).alias("majority"), F.round("uniform", 6).alias("uniform"))


def _recovered(spark, sf_dir):
    """Selected parts by the sketch against planted: the 20 exact heavy hitters."""
    return measures.recovery(heavy_hitters(spark, sf_dir), heavy_hitters_exact(spark, sf_dir).withColumnRenamed("estimate", "weight"), [])


def recovery_l2(spark, sf_dir):
    return _recovered(spark, sf_dir).select(F.round("l2_error", 4).alias("l2_error"))


def success_flag(spark, sf_dir):
    return _recovered(spark, sf_dir).select("success", *[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")])


def jaccard_selected(spark, sf_dir):
    return measures.jaccard(heavy_hitters(spark, sf_dir), heavy_hitters_exact(spark, sf_dir)).select(F.round("jaccard", 6).alias("jaccard"))


#: A small fixed result table for the curve measures: method, compression factor, cells, step size, value.
CURVE = [
    ("curvature", 1.0, 4096, 0.001, 0.95), ("curvature", 10.0, 410, 0.01, 0.94), ("curvature", 100.0, 41, 0.1, 0.90),
    ("gradient", 1.0, 4096, 0.001, 0.91), ("gradient", 10.0, 410, 0.01, 0.84), ("gradient", 100.0, 41, 0.1, 0.61),
]
_CURVE_SQL = "SELECT * FROM (VALUES " + ", ".join(f"('{m}', CAST({c} AS DOUBLE), {n}, CAST({e} AS DOUBLE), CAST({v} AS DOUBLE))" for m, c, n, e, v in CURVE) + ") t(method, cf, cells, eta, value)"


def _curve(spark):
    return spark.sql(_CURVE_SQL)


#: Buckets of the sketches whose readings ``curve_gap`` compares.
READ_BUCKETS = (64, 256, 1024)


def _reading_curve(spark, sf_dir):
    """method (median or mean reading), cf, value: share of the parts' mean quantity that sketches leave right."""
    exact = written(lineitem_entries(spark, sf_dir).groupBy("feature_id").agg(F.sum("value").alias("value")), "exact")
    out = None
    for buckets in READ_BUCKETS:
        spec = SPEC.with_(buckets=buckets)
        cells = sketch.build(exact, spec)
        for how in ("median", "mean"):
            found = sketch.error(cells, exact, spec.with_(query=how))
            one = found.agg(
                F.lit(how).alias("method"), F.round(F.count("*") / spec.cells, 6).alias("cf"), (1 - F.sum("abs_error") / F.sum("value")).alias("value")
            )
            out = one if out is None else out.unionByName(one)
    return out


def _reading_sql() -> str:
    parts = []
    for buckets in READ_BUCKETS:
        spec = SPEC.with_(buckets=buckets)
        put = " UNION ALL ".join(
            f"SELECT *, {j} AS row, {hs.sql_bucket('feature_id', j, spec)} AS bucket, {hs.sql_sign('feature_id', j, spec)} AS sign FROM e" for j in range(spec.rows)
        )
        for how, call in (("median", "median"), ("mean", "avg")):
            parts.append(
                f"""SELECT '{how}' AS method, round(count(*) / {spec.cells}, 6) AS cf, 1 - sum(abs(estimate - value)) / sum(value) AS value FROM (
                WITH e AS ({_EXACT}), p AS ({put}), c AS (SELECT row, bucket, sum(sign * value) AS cell FROM p GROUP BY row, bucket)
                SELECT feature_id, any_value(value) AS value, {call}(sign * cell) AS estimate FROM p JOIN c USING (row, bucket) GROUP BY feature_id)"""
            )
    return " UNION ALL ".join(parts)


def curve_gap(spark, sf_dir):
    return measures.curve_gap(_reading_curve(spark, sf_dir), "median", "mean").select("cf", F.round("gap", 6).alias("gap"), F.round("change", 6).alias("change"))


def memory_ratio(spark, sf_dir):
    return measures.memory_ratio(_curve(spark), "curvature", "gradient", 0.9).select(F.round("ratio", 6).alias("ratio"))


#: Step sizes that ``eta_range`` tries, as texts that both engines read alike.
STEP_SIZES = tuple(f"{a}e{b}" for b in range(-5, 1) for a in ("1.0", "1.5", "2.0", "3.0", "5.0", "7.0"))


def _step_curve(spark, sf_dir):
    """method, eta, value: share of the possible fall of the squared loss after one step from 0.

    The price of a line by its quantity, one weight; by the mean gradient, and by the gradient over
    the curvature.
    """
    x, y = F.col("l_quantity"), F.col("l_extendedprice")
    sums = load(spark, sf_dir, "lineitem").agg(F.avg(x * x).alias("xx"), F.avg(x * y).alias("xy"))
    eta = F.explode(F.array(*[F.lit(e) for e in STEP_SIZES])).alias("e")
    tried = sums.select("xx", "xy", eta).withColumn("eta", F.col("e").cast("double"))
    steps = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), z.alias("z")) for m, z in (("gradient", F.col("xy")), ("newton", F.col("xy") / F.col("xx")))]))
    w = F.col("eta") * F.col("s.z")
    return tried.select("xx", "xy", "eta", steps.alias("s")).select(
        "s.method", "eta", ((2 * w * F.col("xy") - w * w * F.col("xx")) / (F.col("xy") * F.col("xy") / F.col("xx"))).alias("value")
    )


_STEP_CURVE_SQL = f"""SELECT method, eta, (2 * w * xy - w * w * xx) / (xy * xy / xx) AS value FROM (
    SELECT method, eta, xx, xy, eta * CASE method WHEN 'gradient' THEN xy ELSE xy / xx END AS w FROM
    (SELECT avg(l_quantity * l_quantity) AS xx, avg(l_quantity * l_extendedprice) AS xy FROM lineitem),
    (SELECT CAST(e AS DOUBLE) AS eta FROM (SELECT unnest([{', '.join(map(repr, STEP_SIZES))}]) AS e)), (VALUES ('gradient'), ('newton')) m(method))"""


def eta_range(spark, sf_dir):
    return measures.eta_range(_step_curve(spark, sf_dir), 0.8).select("method", "low", "high", F.round("decades", 6).alias("decades"))


def _class_top(spark, sf_dir):
    """Words by difference of document frequency between English and the rest, two ways."""
    rows = load(spark, sf_dir, "documents").select((F.col("lang") == "en").alias("en"), F.explode(fe.word_set(F.col("text"))).alias("word"))
    exact = rows.groupBy("word").agg(F.sum(F.when(F.col("en"), 1.0).otherwise(-1.0)).alias("value")).withColumn("feature_id", portable_id(F.col("word")))
    exact = written(exact, "words")  # read four times below
    spec = SPEC.with_(buckets=1024)
    cells = sketch.build(exact.select("feature_id", "value"), spec)
    first = sketch.top_k(exact.select("feature_id", F.col("value").alias("estimate")), 40).select("feature_id")
    second = sketch.top_k(sketch.query(cells, exact.select("feature_id"), spec), 40).select("feature_id")
    return first, second, exact.select("feature_id", "word")


def _named(ids, names):
    return ids.join(names, "feature_id").select("word")


def selected_only_first(spark, sf_dir):
    a, b, names = _class_top(spark, sf_dir)
    return _named(a.exceptAll(b), names)


def selected_only_second(spark, sf_dir):
    a, b, names = _class_top(spark, sf_dir)
    return _named(b.exceptAll(a), names)


def selected_shared(spark, sf_dir):
    a, b, names = _class_top(spark, sf_dir)
    return _named(a.intersect(b), names)


_SPEC2 = SPEC.with_(buckets=1024)
_PLACED2 = " UNION ALL ".join(
    f"SELECT *, {j} AS row, {hs.sql_bucket('feature_id', j, _SPEC2)} AS bucket, {hs.sql_sign('feature_id', j, _SPEC2)} AS sign FROM e" for j in range(5)
)
_TOPS = rf"""WITH w AS MATERIALIZED (SELECT DISTINCT doc_id, lang, unnest(regexp_extract_all(lower(text), '\p{{L}}+')) AS word FROM documents),
    n AS MATERIALIZED (SELECT word, sum(CASE WHEN lang = 'en' THEN 1.0 ELSE -1.0 END::DOUBLE) AS value FROM w GROUP BY word),
    e AS MATERIALIZED (SELECT word, {sql_id('word')} AS feature_id, value FROM n),
    p AS MATERIALIZED ({_PLACED2}), c AS MATERIALIZED (SELECT row, bucket, sum(sign * value) AS cell FROM p GROUP BY row, bucket),
    q AS MATERIALIZED (SELECT feature_id, median(sign * cell) AS estimate FROM p JOIN c USING (row, bucket) GROUP BY feature_id),
    a AS (SELECT feature_id FROM e ORDER BY abs(value) DESC, feature_id LIMIT 40), b AS (SELECT feature_id FROM q ORDER BY abs(estimate) DESC, feature_id LIMIT 40)
    SELECT word FROM e WHERE feature_id IN (SELECT feature_id FROM a @ SELECT feature_id FROM b)"""


def dataset_stats(spark, sf_dir):
    out = None
    for name in ("words", "kmers", "roles", "toxic", "null_control", "clicks", "grams", "pages", "embed"):
        one = tasks.statistics(tasks.TASKS[name](spark, sf_dir), name)
        out = one if out is None else out.unionByName(one)
    return out


_DRAW = "(CAST('0x' || substr(md5({}), 1, 13) AS BIGINT)::DOUBLE / 4503599627370496.0)"
_SCORES = "SELECT d.doc_id, round(coalesce(sum(v), 0), 6) AS score FROM documents d LEFT JOIN (" + _WORDS.replace("SELECT doc_id, lang, word", "SELECT DISTINCT doc_id, word", 1).split(", CAST('0x'")[0] + r" FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM documents)) x ON d.doc_id = x.doc_id LEFT JOIN (VALUES " + ", ".join(f"('{w}', CAST({v} AS DOUBLE))" for w, v in _WEIGHTS.items()) + ") t(word, v) ON x.word = t.word GROUP BY d.doc_id"
_DECIDED = f"SELECT s.doc_id, lang, source, CASE WHEN lang = 'en' THEN 1.0 ELSE 0.0 END::DOUBLE AS label, score, CASE WHEN score > 0 THEN 1.0 ELSE 0.0 END::DOUBLE AS prediction FROM ({_SCORES}) s JOIN documents d ON s.doc_id = d.doc_id"


def _auc_sql(keys: str) -> str:
    over = f"PARTITION BY {keys} ORDER BY score" if keys else "ORDER BY score"
    whole = f"PARTITION BY {keys}, score" if keys else "PARTITION BY score"
    lead, by = (f"{keys}, ", f"GROUP BY {keys}") if keys else ("", "")
    return f"""SELECT {lead}round(CASE WHEN sum(label) > 0 AND sum(1 - label) > 0 THEN (sum(label * r) - sum(label) * (sum(label) + 1) / 2) / (sum(label) * sum(1 - label)) END, 6) AS auc FROM (
        SELECT *, rank() OVER ({over}) + (count(*) OVER ({whole}) - 1) / 2.0 AS r FROM ({_DECIDED})) {by}"""


def _planted_sql() -> str:
    parts = []
    for c in tasks.PLANT_COLUMNS:
        x = f"'{c}=' || {c}"
        parts.append(
            f"CASE WHEN {_DRAW.format(repr('support:')+' || ' + x)} < 0.5 THEN (0.8 + {_DRAW.format(repr('size:')+' || ' + x)} * 0.4) * 2 * (CASE WHEN {_DRAW.format(repr('way:')+' || ' + x)} < 0.5 THEN 1.0 ELSE -1.0 END) ELSE 0.0 END"
        )
    return f"""SELECT row_key, round(score, 6) AS score, CASE WHEN {_DRAW.format("'click:' || row_key")} < 1 / (1 + exp(-score)) THEN 1.0 ELSE 0.0 END::DOUBLE AS label FROM (
        SELECT l_orderkey * 10 + l_linenumber AS row_key, ({' + '.join(parts)} + {tasks.PLANT_BASE})::DOUBLE AS score
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey)"""


_CLICK_SQL = """SELECT l_orderkey * 10 + l_linenumber AS row_key, strftime(l_shipdate, '%Y-%m-%d') AS ship, *
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey"""


def _stats_sql() -> str:
    word = r"unnest(regexp_extract_all(lower(text), '\p{L}+')) AS f"
    page = """SELECT page_id AS id, regexp_extract(html, '<html lang="([a-z]+)"', 1) = 'en' AS label, trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ ]+', ' ', 'g')) AS text FROM pages"""

    def grams(rows: str, n: int) -> str:
        # texts are cut into pieces that overlap, as positions in a long one are found from its start
        pieces = f"SELECT id, substr(text, start, {1000 + n - 1}) AS piece FROM (SELECT id, text, unnest(range(1, length(text) + 1, 1000)) AS start FROM ({rows}))"
        return f"SELECT DISTINCT id, substr(piece, i, {n}) AS f FROM (SELECT id, piece, unnest(range(1, length(piece) - {n - 2})) AS i FROM ({pieces}))"

    target = " + ".join(["0.0::DOUBLE", *[f"embedding[{i + 1}]::DOUBLE * 8 * ({w})::DOUBLE" for i, w in tasks.EMBED_SUPPORT.items()]])
    parts = {
        "words": (f"SELECT DISTINCT doc_id AS id, {word} FROM documents", "SELECT doc_id AS id, lang = 'en' AS label FROM documents"),
        "kmers": (f"SELECT DISTINCT id, substr(cut, i, 3) AS f FROM (SELECT id, cut, unnest(range(1, length(cut) - 1)) AS i FROM ({EVEN_SQL}))", f"SELECT id, lang AS label FROM ({EVEN_SQL})"),
        "roles": (f"SELECT DISTINCT conv_id * 1000 + turn AS id, {word} FROM conversations", "SELECT conv_id * 1000 + turn AS id, role AS label FROM conversations"),
        "toxic": (f"SELECT DISTINCT doc_id AS id, {word} FROM documents", "SELECT doc_id AS id, toxic AS label FROM labels"),
        "null_control": (
            "SELECT event_id AS id, unnest(['user_id=' || user_id, 'k=' || json_extract_string(props, '$.k'), 'hour=' || hour(ts)]) AS f FROM events",
            "SELECT event_id AS id, event_type = 'click' AS label FROM events",
        ),
        "clicks": (f"SELECT row_key AS id, unnest([{', '.join(repr(c + '=') + ' || ' + c for c in tasks.STAR)}]) AS f FROM ({_CLICK_SQL})", f"SELECT row_key AS id, label FROM ({_planted_sql()})"),
        "grams": (grams("SELECT doc_id AS id, text FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)", 5), "SELECT doc_id AS id, quality AS label FROM labels"),
        "pages": (grams(page, 5), f"SELECT id, label FROM ({page})"),
        "embed": ("SELECT vec_id AS id, unnest(range(64)) AS f FROM embeddings", f"SELECT vec_id AS id, {target} AS label FROM embeddings"),
    }
    return " UNION ALL ".join(
        f"""SELECT '{name}' AS task, count(*) AS n, (SELECT count(DISTINCT f) FROM ({e}) WHERE id IN (SELECT id FROM ({l}))) AS features,
            round((SELECT count(*) FROM ({e}) WHERE id IN (SELECT id FROM ({l}))) / count(*), 4) AS active,
            round((SELECT max(c) FROM (SELECT count(*) AS c FROM ({l}) GROUP BY label)) / count(*), 6) AS largest_class FROM ({l})"""
        for name, (e, l) in parts.items()
    )


ORACLES = {
    "hash_buckets": f"SELECT id, j, CAST(((h::BIGINT % 64) + 64) % 64 AS INTEGER) AS bucket FROM ({hs.sql_murmur3(_MURMUR_SOURCE.format(seed='3000 + j'), 'id, j', 'id', 'seed')})",
    "hash_signs": f"SELECT id, j, CAST(1 - 2 * (h & 1) AS INTEGER) AS sign FROM ({hs.sql_murmur3(_MURMUR_SOURCE.format(seed='3500 + j'), 'id, j', 'id', 'seed')})",
    "sql_bucket_fn": f"SELECT id, j, CAST(((h::BIGINT % 64) + 64) % 64 AS INTEGER) AS bucket FROM ({hs.sql_murmur3(_MURMUR_SOURCE.format(seed='3000 + j'), 'id, j', 'id', 'seed')})",
    "hash_affine": f"WITH e AS (SELECT p_partkey AS feature_id FROM part) SELECT feature_id AS id, CAST(row AS INTEGER) AS j, bucket, sign FROM ({_PLACED})",
    "sketch_build_words": _cells_sql(_WORDS),
    "sketch_build_lineitem": _cells_sql(_LINE),
    "sketch_build_events": _cells_sql("SELECT user_id AS feature_id, 1.0::DOUBLE AS value FROM events"),
    "sketch_by_lang": _cells_sql(_WORDS, "lang,"),
    "sketch_query_median": f"SELECT * FROM {_READ}",
    "sketch_query_mean": f"SELECT feature_id, round(estimate, 6) AS estimate FROM {_read_sql(_cells_sql(_LINE), _PARTS, 'avg')}",
    "heavy_hitters": f"SELECT * FROM {_READ} ORDER BY abs(estimate) DESC, feature_id LIMIT 20",
    "heavy_hitters_exact": f"SELECT feature_id, value AS estimate FROM ({_EXACT}) ORDER BY value DESC, feature_id LIMIT 20",
    "sketch_merge": _cells_sql(_LINE),
    "sketch_scale_sub": _cells_sql("SELECT l_partkey AS feature_id, l_quantity - 0.125::DOUBLE * l_linenumber AS value FROM lineitem"),
    "sketch_error": f"SELECT e.feature_id, e.value, q.estimate, abs(q.estimate - e.value) AS abs_error FROM ({_EXACT}) e JOIN {_READ} q ON e.feature_id = q.feature_id",
    "bucket_load": f"SELECT CAST(row AS INTEGER) AS row, bucket, count(*) AS features FROM (WITH e AS ({_PARTS}) {_PLACED}) GROUP BY row, bucket",
    "collision_pairs": f"""WITH e AS (SELECT feature_id FROM ({_EXACT}) ORDER BY value DESC, feature_id LIMIT 20), p AS ({_PLACED})
        SELECT CAST(x.row AS INTEGER) AS row, x.bucket, x.feature_id AS a, y.feature_id AS b FROM p x JOIN p y ON x.row = y.row AND x.bucket = y.bucket AND x.feature_id < y.feature_id""",
    "tail_energy": f"SELECT round(sum(value * value) FILTER (r > 50), 3) AS tail_energy, min(value) FILTER (r <= 50) AS zeta FROM (SELECT value, row_number() OVER (ORDER BY abs(value) DESC, feature_id) AS r FROM ({_EXACT}))",
    "projection_gram": f"SELECT CAST(row * 64 + bucket AS INTEGER) AS col, round(count(*) / 5, 6) AS norm FROM (WITH e AS ({_PARTS}) {_PLACED}) GROUP BY 1",
    "first_step_gradient": f"{_STEPS} SELECT * FROM g1",
    "first_step_sketch": f"{_STEPS} SELECT * FROM c1",
    "first_step_topk": f"{_STEPS} SELECT * FROM h1",
    "first_step_multiclass": f"WITH {_EX} SELECT class, feature_id, sum(0.25 - CASE WHEN lang = class THEN 1.0 ELSE 0.0 END)::DOUBLE AS g FROM ex, (VALUES ('de'), ('en'), ('es'), ('fr')) t(class) WHERE batch_id = 0 GROUP BY class, feature_id",
    "second_step_sketch": f"{_STEPS} SELECT row, bucket, round(value, 6) AS value FROM c2",
    "second_step_pair": f"{_STEPS} SELECT feature_id, round(coalesce(s, 0), 6) AS s, round(r, 6) AS r FROM r LEFT JOIN s USING (feature_id)",
    "gram_basis": f"{_STEPS} SELECT round(ss, 5) AS ss, round(sr, 5) AS sr, round(sg, 5) AS sg, round(rr, 5) AS rr, round(rg, 5) AS rg, round(gg, 5) AS gg FROM dots",
    "third_step_direction": f"{_STEPS} SELECT feature_id, round(z, 5) AS z FROM z3",
    "third_step_sketch": f"{_STEPS} SELECT row, bucket, round(value, 5) AS value FROM ({_merged('c2', _cells_sql(f'SELECT feature_id, z * -{ETA} AS value FROM z3'))})",
    "gradient_only_third_step": f"{_STEPS} SELECT row, bucket, round(value, 6) AS value FROM ({_merged('c2', _cells_sql(f'SELECT feature_id, g * -{ETA} AS value FROM g3'))})",
    "active_set_size": f"WITH {_EX.replace('WHERE batch_id < 3', '')} SELECT CAST(batch_id AS BIGINT) AS batch_id, count(DISTINCT feature_id) AS active FROM ex GROUP BY batch_id",
    "memory_model": f"WITH {_EX.replace('WHERE batch_id < 3', '')} SELECT CAST(batch_id AS BIGINT) AS batch_id, a AS active, 100 AS weights_cells, 2 * a AS s_cells, 2 * a AS r_cells, 10 * a AS z_cells, {SPEC.cells} AS sketch_cells, a AS gradient_cells FROM (SELECT batch_id, count(DISTINCT feature_id) AS a FROM ex GROUP BY batch_id)",
    "compression_factor": f"SELECT count(DISTINCT feature_id) AS p, {SPEC.cells} AS cells, round(count(DISTINCT feature_id) / {SPEC.cells}, 6) AS cf FROM ({_WORDS})",
    "hashed_projection": f"SELECT doc_id, {hs.sql_bucket('feature_id', 0, SPEC.with_(rows=1, buckets=256))} AS bucket, CAST(sum({hs.sql_sign('feature_id', 0, SPEC)}) AS BIGINT) AS value FROM ({_WORDS}) GROUP BY 1, 2",
    "hessian_pairs": f"""WITH {_EX}, t AS (SELECT feature_id FROM ex WHERE batch_id = 0 GROUP BY feature_id ORDER BY count(*) DESC, feature_id LIMIT 50),
        k AS (SELECT example_id, feature_id FROM ex WHERE batch_id = 0 AND feature_id IN (SELECT feature_id FROM t))
        SELECT a.feature_id AS i, b.feature_id AS j, count(*) * 0.25::DOUBLE AS h FROM k a JOIN k b USING (example_id) GROUP BY 1, 2""",
    "planted_labels": _planted_sql(),
    "planted_regression": "SELECT vec_id AS example_id, round(" + " + ".join(f"embedding[{i + 1}]::DOUBLE * 8 * {w}" for i, w in tasks.EMBED_SUPPORT.items()) + ", 5) AS y FROM embeddings",
    "gauss_box_muller": f"SELECT i, j, round(sqrt(-2 * ln(1 - {_DRAW.format(repr('u:')+chr(32)+'|| i || '+repr(':')+' || j')})) * cos({_DRAW.format(repr('v:')+' || i || '+repr(':')+' || j')} * 6.283185307179586), 6) AS x FROM (SELECT c_custkey AS i FROM customer), range(10) b(j)",
    "predict_topk_scores": _SCORES,
    "predict_sketch_scores": f"{_STEPS}, q AS ({_read_sql('SELECT * FROM c1', 'SELECT DISTINCT feature_id FROM ex WHERE batch_id = 1')[1:-1]}) SELECT example_id, round(sum(estimate), 6) AS score FROM ex JOIN q USING (feature_id) WHERE batch_id = 1 GROUP BY example_id",
    "softmax_scores": f"""WITH {_EX}, c AS (SELECT * FROM (VALUES ('de'), ('en'), ('es'), ('fr')) t(class)),
        g AS (SELECT class, feature_id, sum(0.25 - CASE WHEN lang = class THEN 1.0 ELSE 0.0 END)::DOUBLE * -{ETA} AS w FROM ex, c WHERE batch_id = 0 GROUP BY class, feature_id),
        n AS (SELECT example_id, c.class, coalesce(sum(w), 0) AS score FROM ex CROSS JOIN c LEFT JOIN g ON ex.feature_id = g.feature_id AND c.class = g.class WHERE batch_id = 1 GROUP BY 1, 2)
        SELECT example_id, class, round(exp(score) / sum(exp(score)) OVER (PARTITION BY example_id), 6) AS p FROM n""",
    "accuracy_by_lang": f"SELECT lang, round(avg((label = prediction)::INT), 6) AS accuracy FROM ({_DECIDED}) GROUP BY lang",
    "confusion_lang": f"SELECT label, prediction, count(*) AS count FROM ({_DECIDED}) GROUP BY label, prediction",
    "auc_topk": _auc_sql(""),
    "auc_by_source": _auc_sql("source"),
    "roc_points": f"SELECT score AS threshold, round(sum(p) OVER w / (SELECT sum(label) FROM ({_DECIDED})), 6) AS tpr, round(sum(q) OVER w / (SELECT sum(1 - label) FROM ({_DECIDED})), 6) AS fpr FROM (SELECT score, sum(label) AS p, sum(1 - label) AS q FROM ({_DECIDED}) GROUP BY score) WINDOW w AS (ORDER BY score DESC)",
    "naive_baseline": "SELECT round(max(n) / sum(n), 6) AS majority, round(1 / count(*), 6) AS uniform FROM (SELECT count(*) AS n FROM documents GROUP BY lang)",
    "recovery_l2": f"""SELECT round(sqrt(sum((coalesce(a.estimate, 0) - coalesce(b.estimate, 0)) ** 2)), 4) AS l2_error FROM (SELECT * FROM {_READ} ORDER BY abs(estimate) DESC, feature_id LIMIT 20) a
        FULL JOIN (SELECT feature_id, value AS estimate FROM ({_EXACT}) ORDER BY value DESC, feature_id LIMIT 20) b ON a.feature_id = b.feature_id""",
    "success_flag": f"""SELECT h = 20 AS success, round(h / 20, 6) AS precision, round(h / 20, 6) AS recall, round(h / 20, 6) AS f1 FROM (SELECT count(*) AS h FROM (SELECT feature_id FROM {_READ} ORDER BY abs(estimate) DESC, feature_id LIMIT 20)
        WHERE feature_id IN (SELECT feature_id FROM ({_EXACT}) ORDER BY value DESC, feature_id LIMIT 20))""",
    "jaccard_selected": f"""SELECT round(h / (40 - h), 6) AS jaccard FROM (SELECT count(*) AS h FROM (SELECT feature_id FROM {_READ} ORDER BY abs(estimate) DESC, feature_id LIMIT 20)
        WHERE feature_id IN (SELECT feature_id FROM ({_EXACT}) ORDER BY value DESC, feature_id LIMIT 20))""",
    "curve_gap": f"WITH t AS MATERIALIZED ({_reading_sql()}) SELECT cf, round(gap, 6) AS gap, round(gap - lag(gap) OVER (ORDER BY cf), 6) AS change FROM (SELECT a.cf, a.value - b.value AS gap FROM t a JOIN t b ON a.cf = b.cf AND a.method = 'median' AND b.method = 'mean')",
    "memory_ratio": f"WITH t AS ({_CURVE_SQL}), n AS (SELECT method, min(cells) AS cells FROM t WHERE value >= 0.9 GROUP BY method) SELECT round((SELECT cells FROM n WHERE method = 'gradient') / (SELECT cells FROM n WHERE method = 'curvature'), 6) AS ratio",
    "eta_range": f"SELECT method, min(eta) AS low, max(eta) AS high, round(log10(max(eta) / min(eta)), 6) AS decades FROM ({_STEP_CURVE_SQL}) WHERE value >= 0.8 GROUP BY method",
    "selected_only_first": _TOPS.replace("@", "EXCEPT"),
    "selected_only_second": _TOPS.replace("SELECT feature_id FROM a @ SELECT feature_id FROM b", "SELECT feature_id FROM b EXCEPT SELECT feature_id FROM a"),
    "selected_shared": _TOPS.replace("@", "INTERSECT"),
    "dataset_stats": _stats_sql(),
}

QUERIES = {name: globals()[name] for name in ORACLES}
