"""Inputs on which queries once went wrong."""

import hashlib
import random
import threading
import tracemalloc
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as driver
from sketchselect.functions import features as fe
from sketchselect.llm import decontaminate, neardup, shingles, sketches, substrings
from sketchselect.operators import trainer
from sketchselect.plans import tasks, workloads
from sketchselect.schema import TABLES
from sketchselect.sources import gauss
from sketchselect.tables import load


def test_a_kmer_does_not_end_in_a_line_break(spark):
    row = spark.createDataFrame([("ab\n", ), ("abc\nde\n",)], "t string").select(fe.kmers(F.col("t"), 3, "a-e").alias("k")).collect()
    assert [r["k"] for r in row] == [[], ["abc"]]


def test_kmer_codes_are_of_whole_kmers(spark, tmp_path):
    from sketchselect.plans.featurequeries import kmer_code

    rows = [(1, "xea\n bad", "en", "src0", 8), (2, "abc", "de", None, 3)]
    spark.createDataFrame([r[: len(TABLES["documents"].fields)] for r in rows], TABLES["documents"]).write.parquet(str(tmp_path / "documents.parquet"))
    got = {r["kmer"]: r["code"] for r in kmer_code(spark, str(tmp_path)).collect()}
    assert got == {"bad": 1 * 25 + 0 * 5 + 3, "abc": 0 * 25 + 1 * 5 + 2}


def sql_engine(folder):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return con


def same_rows(got, want):
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    return sorted(map(repr, got[columns].itertuples(index=False, name=None))) == sorted(map(repr, want[columns].itertuples(index=False, name=None)))


@pytest.mark.parametrize("name", ["cte_recursive", "curve_gap", "eta_range", "gauss_box_muller"])
def test_queries_compute_from_the_tables(spark, small, name):
    made = driver.queries()[name](spark, small)
    assert made.inputFiles()
    assert same_rows(made.toPandas(), sql_engine(small).sql(driver.oracle_sql()[name]).df())


def test_gauss_rows_go_with_the_given_vectors(spark, small):
    got = {r["example_id"]: r for r in driver.queries()["gauss_source"](spark, small).collect()}
    want = tasks.embed(spark, small).collect()
    assert len(got) == len(want)
    for r in want[::50]:
        noise = gauss.row(0, r["example_id"], 1)[0]
        assert got[r["example_id"]]["label"] == pytest.approx(r["label"] + 0.1 * noise, abs=1e-6)
        assert got[r["example_id"]]["first"] == pytest.approx(r["val"][0], abs=1e-6)


def test_windows_are_hashed_only_where_an_item_of_their_length_may_match(monkeypatch):
    """Results equal all windows against all items; windows of other lengths than the item's are passed over."""
    rng = random.Random(8)
    words = [f"w{i}" for i in range(12)]
    items = [(i, " ".join(rng.choices(words, k=rng.randint(3, 30)))) for i in range(40)] + [(99, " ".join(f"own{i}" for i in range(25)))]
    index = decontaminate.Index(items, 5, 0.8, 16)
    texts = [" ".join(rng.choices([*words, "other"], k=rng.randint(0, 40))) + " " + rng.choice(items)[1] + " tail" * rng.randint(0, 3) for _ in range(60)]
    texts += ["w1 w2 other", "w1 w2 w3 other other other other", "", "other"]

    def sets(found):
        size = min(5, len(found))
        return Counter(tuple(found[i : i + size]) for i in range(len(found) - size + 1))

    for text in texts:
        found, want = text.split(), {}
        for i, item in items:
            n = len(item.split())
            windows = [found[a : a + n] for a in range(len(found) - n + 1)] or [found]
            if len(found) < min(5, n):
                continue
            scores = []
            for w in windows:
                a, b = sets(w), sets(item.split())
                scores.append((a & b).total() / (a | b).total())
            if max(scores) >= 0.8:
                want[i] = (scores.index(max(scores)), max(scores))
        got = {i: (start, similar) for i, start, _, similar in index.search(text)}
        assert got.keys() == want.keys() and all(got[i] == pytest.approx(want[i]) for i in want), text
        for size in (2, 3, 5):
            position, k = index.known_in([w.encode() for w in found], size)
            plain = shingles.hashes([w.encode() for w in found], size)
            assert position.tolist() == np.flatnonzero(np.isin(plain, index.known)).tolist() and index.known[k].tolist() == plain[position].tolist()
    asked = []
    monkeypatch.setattr(decontaminate, "window_codes", lambda found, starts, n: asked.append(n) or iter(()))
    index.search("start " + items[-1][1] + " end")
    assert asked == [21]


def test_the_dense_store_does_not_sort_all_features_in_each_step(monkeypatch):
    """Equal to a dictionary; of many steps with new features, few merge large runs."""
    from sketchselect.operators.kernel import ExactStore

    rng = np.random.default_rng(3)
    store, want, touched = ExactStore(2), [{}, {}], []
    plain = np.argsort
    monkeypatch.setattr(np, "argsort", lambda x, **kw: touched.append(len(x)) or plain(x, **kw))
    for _ in range(400):
        ids = np.unique(rng.integers(0, 1 << 40, 50) // rng.integers(1, 1 << 30))
        for k in range(2):
            deltas = rng.standard_normal(len(ids))
            store.add(k, ids, deltas)
            for i, d in zip(ids.tolist(), deltas.tolist(), strict=True):
                want[k][i] = want[k].get(i, 0.0) + d
            assert store.query(k, ids) == pytest.approx([want[k][i] for i in ids.tolist()])
    assert sorted(store.ids.tolist()) == sorted(want[0]) and store.weights.shape == (2, len(want[0]))
    assert sum(touched) < 20 * len(want[0])


def test_kmer_counts_of_reads_are_linear_and_right(spark, small):
    """Ids ascending with how often each occurs; no pass over all positions per k-mer."""
    rows = tasks.kmers(spark, small)
    assert "size(filter" not in rows._jdf.queryExecution().analyzed().toString()
    reads = {r["example_id"]: r["read"] for r in tasks.reads(load(spark, small, "documents")).collect()}
    for r in rows.limit(200).collect():
        read = reads[r["example_id"]]
        want = Counter(int(hashlib.md5(read[i : i + 3].encode()).hexdigest()[:15], 16) for i in range(len(read) - 2))
        assert r["idx"] == sorted(want) and r["val"] == [want[i] for i in r["idx"]]


def test_fast_readings_and_sums_equal_the_plain_ones():
    from sketchselect.functions.hashing import SketchSpec, np_places
    from sketchselect.operators.kernel import CountSketch

    rng = np.random.default_rng(4)
    ids, deltas = np.unique(rng.integers(0, 1 << 60, 300)), rng.standard_normal(300)
    passes, plain = [], np.bincount
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(np, "bincount", lambda x, w=None, n=0: passes.append(n) or plain(x, w, n))
        sketch = CountSketch(SketchSpec(5, 50_000, 3))
        sketch.add(0, ids, deltas)
    assert max(passes) <= len(ids)  # not the 50,000 buckets
    buckets, signs = np_places(ids, sketch.spec)
    want = np.zeros((5, 50_000))
    for j in range(5):
        want[j] += np.bincount(buckets[j], signs[j] * deltas, 50_000)
    assert (sketch.cells[0] == want).all()
    assert (sketch.query(0, ids) == np.median([signs[j] * want[j, buckets[j]] for j in range(5)], 0)).all()


@pytest.mark.parametrize("epochs", [1, 2])
def test_lanes_share_the_stored_examples(spark, epochs):
    """Several lanes give what single runs give, and no exchange carries the examples to them."""
    from sketchselect.functions.hashing import SketchSpec
    from sketchselect.operators.kernel import Schedule, StopRule, TrainSpec
    from sketchselect.operators.trainer import run_configs

    rng = np.random.default_rng(1)
    rows = [(i, i // 15, float(i % 2), sorted(rng.choice(25, 6, replace=False).tolist()), rng.standard_normal(6).tolist()) for i in range(150)]
    rows = spark.createDataFrame(rows, "example_id long, batch_id long, label double, idx array<bigint>, val array<double>").repartition(5)
    train = TrainSpec(k=8, stop=StopRule(epochs))
    configs = {i: (SketchSpec(3, 64, i), train.with_(schedule=Schedule(0.01 * (i + 1)))) for i in range(5)}

    def told(found, i):
        return sorted(str(tuple(r)[:1] + tuple(r)[2:]) for r in found if r["config"] == i)

    every = run_configs(rows, configs, rows, ("all",))
    assert "Exchange" not in every._jdf.queryExecution().executedPlan().toString()
    found = every.collect()
    for i in (0, 4):
        alone = told(run_configs(rows, {i: configs[i]}, rows, ("all",)).collect(), i)
        assert len(alone) > 10 * epochs and told(found, i) == alone


def test_lanes_run_side_by_side(spark):
    """Every lane is a task of its own; united single partitions would be one task."""
    from sketchselect.functions.hashing import SketchSpec
    from sketchselect.operators.kernel import TrainSpec
    from sketchselect.operators.trainer import run_configs, side_by_side

    rows = spark.createDataFrame([(i, i // 4, float(i % 2), [i % 5], [1.0]) for i in range(20)], "example_id long, batch_id long, label double, idx array<bigint>, val array<double>")
    made = run_configs(rows, {i: (SketchSpec(3, 20 + i, 7), TrainSpec(k=2)) for i in range(3)})
    assert sum(1 for part in made.rdd.glom().collect() if part) == 3
    parts = [spark.range(n).coalesce(1) for n in (3, 2)]
    assert sorted(map(len, side_by_side(parts).rdd.glom().collect())) == [0, 0, 2, 3]


def test_click_categories_are_hashed_before_the_join(spark, small):
    made = tasks.clicks(spark, small)
    scored = tasks.clicks_scored(spark, small)
    ids, _ = fe.presence(fe.one_hot(*tasks.STAR))
    want = scored.select(F.col("row_key").alias("example_id"), "label", ids.alias("idx"), fe.split_of(F.col("row_key").cast("string")).alias("split")).withColumn(
        "val", F.transform("idx", lambda _: F.lit(1.0))
    )
    assert made.schema.simpleString() == want.schema.simpleString()
    assert sorted(map(str, made.collect())) == sorted(map(str, want.collect()))
    # per line: the label's draw and the split
    assert made._jdf.queryExecution().optimizedPlan().toString().split("Join")[0].count("md5(") <= 3


def test_rows_of_the_run_time_table_are_stored_once_and_deleted(spark, small, monkeypatch):
    from sketchselect import tables
    from sketchselect.operators import trainer as replays

    tags, plain = [], tables.written
    for module in (workloads, replays):
        monkeypatch.setattr(module, "written", lambda df, tag, *a, **kw: tags.append(tag) or plain(df, tag, *a, **kw))
    before = {scope: list(paths) for scope, paths in tables._written.items()}
    made = workloads.runtime(spark, small, ("words",), 20).collect()
    assert [(r["task"], r["method"]) for r in made] == [("words", "curvature"), ("words", "gradient")]
    assert sorted(tags) == ["in-order", "model", "model", "task-words", "train"]
    after = [p for scope, paths in tables._written.items() for p in paths if p not in before.get(scope, ())]
    assert all("/model-" in p for p in after)
    train, _, p = workloads.prepared(spark, small, "words")
    args = workloads.spec_of("words", "curvature", 10.0, p, 20)
    ordered = replays.Ordered(train)
    alone, shared = (m.topk_df().collect() for m in (replays.fit(train, *args), replays.fit(ordered, *args, "ordered")))
    assert alone and sorted(map(str, alone)) == sorted(map(str, shared))
    ordered.release()


def test_dense_weights_are_read_where_new_ids_made_them_grow():
    from sketchselect.operators.kernel import ExactStore

    store = ExactStore()
    store.add(0, np.arange(1000), np.ones(1000))
    assert store.query(0, np.arange(900, 1100)).sum() == 100


def test_statistics_in_one_pass(spark):
    rows = [(1, 0.0, [5, 7], [1.0, 1.0]), (2, 1.0, [7], [1.0]), (3, 1.0, [], []), (4, 1.0, None, None)]
    examples = spark.createDataFrame(rows, "example_id long, label double, idx array<bigint>, val array<double>")
    made = tasks.statistics(examples, "t")
    assert tuple(made.first()) == ("t", 4, 2, 0.75, 0.75)
    assert made._jdf.queryExecution().optimizedPlan().toString().count("LogicalRDD") + made._jdf.queryExecution().optimizedPlan().toString().count("LocalRelation") == 1


def test_statistics_are_of_every_task(spark, small):
    made = driver.queries()["dataset_stats"](spark, small).toPandas()
    assert sorted(made["task"]) == sorted(tasks.TASKS)
    want = sql_engine(small).sql(driver.oracle_sql()["dataset_stats"]).df()
    assert same_rows(made, want[list(made.columns)].astype(made.dtypes.to_dict()))


def test_the_scaled_space_is_not_moved(spark, small):
    """Texts are dealt to the shards; their 12-grams are made after that, with the same model."""
    from sketchselect.functions.hashing import SketchSpec
    from sketchselect.operators.kernel import TrainSpec
    from sketchselect.operators.trainer import fit
    from sketchselect.plans import workloads

    texts = fe.number_batches(workloads.scaled_texts(spark, small, 2).limit(60), 10)
    args = SketchSpec(3, 500, 7), TrainSpec(k=20), "sharded"
    late, early = fit(texts, *args, late=workloads.with_scaled_features), fit(workloads.with_scaled_features(texts), *args)
    assert sorted(map(str, late.topk_df().collect())) == sorted(map(str, early.topk_df().collect()))


def test_near_duplicates_go_to_python_in_small_batches(spark, monkeypatch):
    from sketchselect.llm import neardup

    setting, seen = "spark.sql.execution.arrow.maxRecordsPerBatch", []
    before, plain = spark.conf.get(setting), neardup.written
    monkeypatch.setattr(neardup, "written", lambda *a: seen.append(int(spark.conf.get(setting))) or plain(*a))
    docs = spark.createDataFrame([(1, "a b c d e f g"), (2, "a b c d e f g"), (3, "x y z")], "doc_id long, text string")
    assert sorted(r["doc_id"] for r in neardup.drop_near_duplicates(docs).collect()) == [1, 3]
    assert seen and max(seen) <= 1000 and spark.conf.get(setting) == before


def test_dots_of_a_pair_by_one_aggregation(spark):
    from sketchselect.operators import sync

    s = spark.createDataFrame([(1, 2.0), (2, -1.0)], "feature_id long, value double")
    r = spark.createDataFrame([(2, 3.0), (5, 4.0)], "feature_id long, value double")
    assert sync.dots(s, r) == (-3.0, 5.0, 25.0)
    assert sync.dots(s.limit(0), r.limit(0)) == (0.0, 0.0, 0.0)


def test_a_round_of_large_minibatches_is_few_jobs(spark):
    """Vectors of the history are one table, so the jobs of a round do not grow with it."""
    from sketchselect.functions.hashing import SketchSpec
    from sketchselect.operators.kernel import Schedule, TrainSpec
    from sketchselect.operators.trainer import fit

    draw = random.Random(3)
    rows = [(i, i // 8, float(i % 2), sorted({i % 2, *draw.sample(range(2, 30), 4)})) for i in range(40)]
    examples = spark.createDataFrame([(*r, [1.0] * len(r[3])) for r in rows], "example_id long, batch_id long, label double, idx array<bigint>, val array<double>")
    args = SketchSpec(3, 64, 7), TrainSpec(k=6, schedule=Schedule(0.1))
    found = {}
    for mode in ("replay", "sync"):
        spark.sparkContext.setJobGroup(mode, mode)
        model = fit(examples, *args, mode)
        found[mode] = {r["feature_id"]: round(r["estimate"], 6) for r in model.topk_df().collect()}, [r["pairs_kept"] for r in model.log_df().orderBy("step").collect()]
    assert found["replay"] == found["sync"] and sum(found["sync"][1]) >= 3
    tracker = spark.sparkContext.statusTracker()
    # adaptive plans run every shuffle as a job of its own
    assert len(tracker.getJobIdsForGroup("sync")) < 14 * 5 + 10
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def join_rows(frame):
    """The most rows that a join of the plan makes, from a run with a fixed plan."""
    plan = frame._jdf.queryExecution().executedPlan()
    plan.execute().count()
    found, todo = [0], [plan]
    while todo:
        node = todo.pop()
        if "Join" in node.nodeName():
            found.append(node.metrics().apply("numOutputRows").value())
        todo += [node.children().apply(i) for i in range(node.children().size())]
    return max(found)


@pytest.mark.parametrize("own", [(9, 10, 11)])
def test_a_family_without_its_original_does_not_meet_pair_by_pair(spark, own, tmp_path):
    """600 edited copies of one text, each a component of its own, and some pairs that are near."""
    rng = random.Random(sum(own))
    base, rows = rng.sample(range(1 << 40), 100), []
    for i in range(600):
        kept = rng.sample(base, 100 - rng.choice(own))
        rows.append((i, sorted(kept + rng.sample(range(1 << 41, 1 << 50), 100 - len(kept)))))
        if i % 50 == 0:
            rows.append((1000 + i, sorted(rows[-1][1][:-5] + rng.sample(range(1 << 51, 1 << 52), rng.choice([3, 5])))))
    # sets are read from files, as the stage reads them
    spark.createDataFrame(rows, "doc_id long, shingles array<long>").write.parquet(str(tmp_path / "sets"))
    sets = spark.read.parquet(str(tmp_path / "sets"))
    members = sets.select("doc_id", F.col("doc_id").alias("component"))
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        pairs = neardup.apart_pairs(members, sets, 0.8, "test")
        assert join_rows(pairs) < 4 * len(rows) + 4 * pairs.count()
        got = {(r["a"], r["b"]) for r in neardup.verified(pairs, sets, 0.8).collect()}
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    held = [(i, set(s)) for i, s in rows]
    want = {tuple(sorted((i, j))) for k, (i, x) in enumerate(held) for j, y in held[:k] if len(x & y) >= 0.8 * len(x | y) - 1e-9}
    assert want and got == want


def test_factors_of_a_full_place_take_little_memory():
    """Two copies of 60,000 strings: 12 MB of bytes, which took over 40 times as much."""
    data = np.random.default_rng(3).integers(97, 123, (60_000, 100), np.uint8)
    both = np.concatenate([data, data])
    sizes, ids = np.full(len(both), 100), np.repeat([1, 2], len(data))
    tracemalloc.start()
    try:
        found, first = substrings.factors(both.ravel(), sizes, ids, 50, 84)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    print("peak MB", peak >> 20)
    found = found.reshape(len(both), 51)
    assert not found[: len(data)].any()
    assert (found[len(data) :] == np.minimum(100 - np.arange(51), 84)).all()
    assert peak < 400 << 20


def test_sketches_deal_digests_by_plain_masks(spark):
    """The cells are those of the places named; no digest reads its mask from a struct, which took a third of the query's time."""
    draw = random.Random(8)
    found = [draw.randrange(-(1 << 63), 1 << 63) for _ in range(300)]
    frame = spark.createDataFrame([(found,)], "h array<long>")
    for size in sketches.SIZES:
        made = sketches.sketch("h", size)
        assert "g.m" not in made and "c.m" not in made
        cells, checks = frame.select(F.expr(made).alias("c"), F.expr(f"transform(h, x -> hash(x, {sketches.CHECK_SEED}))").alias("k")).first()
        want = [[0, 0, 0] for _ in range(3 * size)]
        for x, k in zip(found, checks, strict=True):
            for j in range(3):
                cell = want[j * size + (x >> 16 * j & (size - 1))]
                cell[0], cell[1], cell[2] = cell[0] + 1, cell[1] ^ x, cell[2] ^ k
        assert [list(c) for c in cells] == want


# ---- times of the sweeps and of the run-time table


def test_lanes_of_a_sweep_have_about_equal_work():
    """The 23 runs of a compression curve on 8 cores: the dense second-order run shares no lane with a sketched one."""
    methods = [m for m in (*workloads.SKETCHED, "hashed") for _ in workloads.CURVE] + list(workloads.DENSE)
    configs = {i: workloads.spec_of("toxic", m, 10.0, 1000, 10) for i, m in enumerate(methods)}
    lanes = trainer.lanes_of(configs, 8)
    assert sorted(c for lane in lanes for c in lane) == list(configs)
    assert all(sum(methods[c] in ("curvature", "dense_qn") for c in lane) == 1 for lane in lanes)
    assert [sorted(lane) for lane in trainer.lanes_of(configs, 1)] == [list(configs)]


def test_runs_of_the_run_time_table_are_side_by_side(spark, monkeypatch):
    together = threading.Barrier(2, timeout=60)
    monkeypatch.setattr(workloads, "prepared", lambda spark, sf_dir, task: (spark.range(3), None, 10))
    monkeypatch.setattr(workloads, "fit", lambda *_: together.wait())
    rows = workloads.runtime(spark, "", ("words", "kmers")).collect()
    assert [(r["task"], r["method"], r["n"]) for r in rows] == [(t, m, 3) for t in ("words", "kmers") for m in workloads.SKETCHED]


# ---- layouts_kmers at 1 GB


@pytest.mark.parametrize("kw", [{}, {"layout": "shared"}, {"method": "hashed"}, {"support": "all", "heap_refresh": "before_second_fetch"}])
@pytest.mark.parametrize("buckets", [40, 5000])
def test_steps_over_a_vocabulary_equal_plain_steps_to_the_bit(kw, buckets, monkeypatch):
    """Places in a vocabulary give the cells, heaps, logs and scores of ids, and ids are hashed once, not in each step."""
    from sketchselect.functions.hashing import SketchSpec
    from sketchselect.operators import coded
    from sketchselect.operators.kernel import Schedule, Trainer, TrainSpec

    rng, hashed, plainly = np.random.default_rng(2), [], coded.np_places
    monkeypatch.setattr(coded, "np_places", lambda *a: hashed.append(1) or plainly(*a))
    ids = np.unique(rng.integers(0, 1 << 60, 300))
    spec = TrainSpec(loss="softmax", classes=3, k=25, schedule=Schedule(0.05), damping=1.0, **kw)
    plain, fast = (Trainer(SketchSpec(5, buckets, 7), spec), coded.CodedTrainer(SketchSpec(5, buckets, 7), spec, ids))
    at_first = len(hashed)
    for _ in range(30):
        rows = [np.sort(rng.choice(300, 20, replace=False)) for _ in range(16)]
        offsets, places, values, labels = np.arange(17) * 20, np.concatenate(rows), rng.integers(1, 4, 320).astype(float), rng.integers(0, 3, 16).astype(float)
        a, b = plain.batch(offsets, ids[places], values, labels), fast.batch(offsets, places, values, labels)
        plain.step(a), fast.step(b)
    assert len(hashed) == at_first <= 3
    assert (plain.store.cells == fast.store.cells).all() and plain.log == fast.log
    for k in range(len(plain.heaps)):
        assert all((x == y).all() for x, y in zip(plain.selected(k), fast.selected(k), strict=True))
    assert all((plain.scores(a, s) == fast.scores(b, s)).all() for s in ("all", "topk"))


def test_layouts_train_on_reads_that_are_coded_after_the_sort(spark, small, monkeypatch):
    """Only reads are moved; the models and scores are those of the stored k-mers, with and beyond a vocabulary."""
    task, train, test, p = "kmers", *workloads.prepared(spark, small, "kmers")
    own = workloads.spec_of(task, "curvature", 10.0, p, 200)
    configs = {0: own, 1: (own[0].with_(buckets=own[0].buckets * 4), own[1].with_(layout="shared", k=800))}
    told = lambda blocks: sorted(str(tuple(r)) for r in blocks.filter("kind not like 'score%'").collect())
    scores = lambda blocks: sorted(map(tuple, trainer.predictions(blocks, "all").collect()))
    want = trainer.run_configs(train, configs, test, ("all",))
    want, sure = told(want), scores(want)
    for bound in (workloads.VOCABULARY, 0):
        monkeypatch.setattr(workloads, "VOCABULARY", bound)
        train, test, features, late, ids = workloads.prepared_reads(spark, small)
        assert features == p and (ids is not None) == (bound > 0)
        assert "idx" not in train.columns and "read" in train.columns
        got = trainer.run_configs(train, configs, test, ("all",), late, ids)
        assert told(got) == want and scores(got) == sure


def test_texts_are_cut_into_reads_in_linear_time(spark):
    texts = ["a\U0001f600b\r\n\u0085c" * 40, "xy", "", None, "ab" * 50, "é" * 103, "z" * 102]
    docs = spark.createDataFrame([(i, "en", t) for i, t in enumerate(texts)], "doc_id long, lang string, text string")
    made = tasks.reads(docs)
    assert "transform(sequence(" not in made._jdf.queryExecution().analyzed().toString().lower()  # each read from the text's start
    want = {(i * 1_000_000 + at, t[at * 100 : at * 100 + 100]) for i, t in enumerate(texts) if t for at in range(len(t) // 100 + 1) if len(t[at * 100 : at * 100 + 100]) > 2}
    assert {(r["example_id"], r["read"]) for r in made.collect()} == want
