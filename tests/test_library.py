"""Modes agree, plans keep their shape, streams equal their batch twins, SQL agrees."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as driver
from sketchselect.functions import features as fe
from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import measures
from sketchselect.operators.kernel import Schedule, StopRule, TrainSpec
from sketchselect.operators.trainer import Model, decided, fit, predict, probabilities
from sketchselect.plans import simulation, tasks
from sketchselect.sources import gauss, sparse_text
from sketchselect.streaming import events as ev
from sketchselect.streaming import training
from sketchselect.tables import load, new_path


def examples(spark, n=60, p=25, seed=1):
    """Rows with values drawn apart, so that no two estimates tie."""
    rng = np.random.default_rng(seed)
    rows = []
    for i in range(n):
        ids = np.sort(rng.choice(p, 6, replace=False))
        rows.append((i, i // 15, float(ids[0] < 6), [int(x) for x in ids], [float(x) for x in rng.standard_normal(6)]))
    return spark.createDataFrame(rows, "example_id long, batch_id long, label double, idx array<bigint>, val array<double>")


def top(model):
    return {r["feature_id"]: r["estimate"] for r in model.topk_df().collect()}


@pytest.mark.parametrize("method", ["curvature", "gradient"])
@pytest.mark.parametrize("mode", ["sharded", "sync"])
def test_modes_agree_with_replay(spark, method, mode):
    rows, sketch = examples(spark), SketchSpec(3, 64, 1)
    train = TrainSpec(method=method, k=8, schedule=Schedule(0.05))
    a, b = top(fit(rows, sketch, train)), top(fit(rows, sketch, train, mode, **({"shards": 1} if mode == "sharded" else {})))
    assert a.keys() == b.keys() and all(abs(a[i] - b[i]) < 1e-8 for i in a)


def test_stream_training_equals_replay_and_is_idempotent(spark):
    rows, sketch, train = examples(spark), SketchSpec(3, 64, 1), TrainSpec(k=8, schedule=Schedule(0.05))
    path, state = new_path(spark, "examples"), new_path(spark, "state")
    training.replayable(rows, path, 2)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    model = training.fit_stream(stream, sketch, train, state)
    assert top(model) == pytest.approx(top(fit(rows, sketch, train)))
    before = training.latest(spark, state)
    training.train_batch(rows, 0, state, sketch, train)  # an old epoch again: no effect
    assert training.latest(spark, state) == before


def test_many_shards_and_rounds(spark):
    model = fit(examples(spark), SketchSpec(3, 64, 1), TrainSpec(k=8, schedule=Schedule(0.05)), "sharded", shards=3, rounds=2)
    assert model.topk_df().count() == 8


def test_model_roundtrip_and_predictions(spark):
    rows = examples(spark)
    model = fit(rows, SketchSpec(3, 256, 1), TrainSpec(k=10, schedule=Schedule(0.05), stop=StopRule(3)))
    path = new_path(spark, "model")
    model.save(path)
    again = Model.load(spark, path)
    assert top(again) == top(model) and again.train == model.train
    unseen = spark.createDataFrame([(99, 0, 1.0, [10**9], [1.0]), (98, 0, 0.0, [], [])], rows.schema)
    for support in ("topk", "all"):
        scores = predict(rows.union(unseen), again, support)
        assert scores.count() == 62
        probability = probabilities(scores).agg(F.min("probability"), F.max("probability")).first()
        assert 0 <= probability[0] <= probability[1] <= 1
        assert decided(scores, []).count() == 62


def test_auc_equals_pairwise_count(spark):
    rng = np.random.default_rng(2)
    rows = [(int(g), float(s), float(y)) for g, s, y in zip(rng.integers(0, 3, 300), rng.integers(0, 15, 300), rng.integers(0, 2, 300), strict=True)]
    got = {r["g"]: r["auc"] for r in measures.auc(spark.createDataFrame(rows, "g int, score double, label double"), ["g"]).collect()}
    for g in range(3):
        pos = [s for h, s, y in rows if h == g and y]
        neg = [s for h, s, y in rows if h == g and not y]
        assert got[g] == pytest.approx(np.mean([(a > b) + 0.5 * (a == b) for a in pos for b in neg]))
    one = spark.createDataFrame([(0, 1.0, 1.0)], "g int, score double, label double")
    assert measures.auc(one, ["g"]).first()["auc"] is None


def test_sparse_text_and_sources(spark):
    rows = examples(spark)
    back = sparse_text.from_lines(sparse_text.to_lines(rows)).collect()
    want = rows.select("label", "idx", "val").collect()
    assert sorted(map(str, back)) == sorted(map(str, want))
    spark.dataSource.register(gauss.GaussSource)
    one, many = (spark.read.format("gauss").options(rows="12", features="7", planted="2", partitions=str(n)).load().orderBy("example_id").collect() for n in (1, 5))
    assert one == many


def test_split_keeps_copies_together(spark, small):
    docs = load(spark, small, "documents").withColumn("split", fe.split_of(F.col("text")))
    assert docs.groupBy("text").agg(F.count_distinct("split").alias("n")).filter("n > 1").count() == 0


def test_ngrams_are_linear_and_right(spark):
    text = "añb😀c"
    row = spark.createDataFrame([(text,), ("ab",), (None,)], "t string").select(fe.char_ngrams(F.col("t"), 3).alias("g")).collect()
    assert row[0]["g"] == ["añb", "ñb😀", "b😀c"] and row[1]["g"] == []


def test_late_rows_are_dropped(spark, tmp_path):
    base = pd.Timestamp("2024-01-01")
    schema = load(spark, "/root/testdata/sf0.001", "events").schema
    path = str(tmp_path / "events.parquet")

    def put(hours, first):
        rows = [(first + i, (base + pd.Timedelta(hours=h)).to_pydatetime(), 1, "view", 1.0, "{}") for i, h in enumerate(hours)]
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(path)

    put([0, 1], 0)
    put([100], 10)
    put([102], 15)  # late rows are judged by the watermark of the batch before the last
    put([0, 101], 20)
    put([300], 30)
    counted = ev.tumbling(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path))
    got = {r["start"]: r["n"] for r in ev.run_once(counted, "late").collect()}
    assert got[int(base.timestamp() * 1e6)] == 1  # the late row at hour 0 is gone


def test_simulation_is_repeatable(spark):
    size = {"n": 120, "p": 60, "k": 3, "steps": 25, "batch": 60}
    a, b = (simulation.run_trials(spark, [("curvature", 2.0, 0.05, 5), ("gradient", 2.0, 1e-3, 5)], 3, **size).drop("seconds").orderBy("method", "seed", "metric").collect() for _ in range(2))
    assert a == b and len(a) == 18


def test_null_control_has_no_signal(spark):
    rows = tasks.null_control(spark, "/root/testdata/sf0.01")
    train = fe.number_batches(rows.filter("split = 'train'").drop("split"), 64)
    model = fit(train, SketchSpec(5, 512, 1), TrainSpec(k=200, schedule=Schedule(0.01)))
    test = rows.filter("split = 'test'").drop("split").withColumn("batch_id", F.lit(0).cast("long"))
    assert abs(measures.auc(predict(test, model, "all"), []).first()["auc"] - 0.5) < 0.05


# ---- plans


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans_prune_push_and_avoid_cartesian_products(spark, small):
    found = driver.queries()
    text = plan(found["filter_between"](spark, small))
    assert "PushedFilters: [IsNotNull" in text and "l_comment" not in text
    assert "ReadSchema: struct<lang:string>" in plan(load(spark, small, "documents").groupBy("lang").count())
    for name in ("sketch_build_words", "join_star", "word_tfidf", "decontaminate", "third_step_sketch"):
        assert "CartesianProduct" not in plan(found[name](spark, small)), name
    assert "BroadcastHashJoin" in plan(found["predict_topk_scores"](spark, small))
    hashed = plan(found["sql_bucket_fn"](spark, small))
    assert "hash(" in hashed and "Python" not in hashed


# ---- SQL


def test_a_sample_of_queries_agrees_with_sql(spark, small):
    con = duckdb.connect()
    for t in ("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations").split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    found, oracle = driver.queries(), driver.oracle_sql()
    assert set(oracle) <= set(found)
    for name in ("hash_buckets", "sketch_query_median", "first_step_topk", "third_step_direction", "auc_topk", "planted_labels", "cube_labels", "win_session"):
        got = found[name](spark, small).toPandas()
        want = con.sql(oracle[name]).df()
        columns = sorted(got.columns)
        assert columns == sorted(want.columns), name
        rows = [sorted(map(repr, d[columns].round(5).astype(object).where(d[columns].notna(), None).map(lambda v: float(v) + 0.0 if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else v).itertuples(index=False, name=None))) for d in (got, want)]
        assert rows[0] == rows[1], name


def test_entry(spark):
    assert driver.entry(spark).count() > 0
