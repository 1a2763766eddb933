"""Training modes over DataFrames of packed examples.

``replay``  strictly sequential in one task, streaming minibatches: the reference semantics.
``grid``    many independent replays; each task steps several configurations on the same minibatches.
``sharded`` every partition replays from common cells, cells are averaged after a round.
``sync``    one large minibatch per Spark job, vectors distributed (operators.sync).
``stream``  micro-batches with versioned state (streaming.training).
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterable, Iterator
from dataclasses import asdict, dataclass
from threading import Lock

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import sketch as sk
from sketchselect.operators.coded import CodedTrainer
from sketchselect.operators.kernel import Batch, CountSketch, Schedule, StopRule, TopKHeap, Trainer, TrainSpec
from sketchselect.schema import BLOCKS
from sketchselect.tables import release, written

#: Numbers of one block of cells.
BLOCK = 4096
SHAPE = pa.schema(
    [("kind", pa.string()), ("config", pa.int64()), ("class", pa.int32()), ("row", pa.int32()), ("start", pa.int64()),
     ("ids", pa.list_(pa.int64())), ("vals", pa.list_(pa.float64()))]
)


def block(kind, config, k, row, start, ids, vals) -> dict:
    return {"kind": kind, "config": config, "class": k, "row": row, "start": start, "ids": ids, "vals": vals}


def model_blocks(trainer: Trainer, config: int) -> Iterator[dict]:
    """Cells, selected features and log of a trained state."""
    if isinstance(trainer.store, CountSketch):
        for k, rows in enumerate(trainer.store.cells):
            for j, cells in enumerate(rows):
                for at in range(0, len(cells), BLOCK):
                    yield block("cells", config, k, j, at, None, cells[at : at + BLOCK].tolist())
    for k in range(1 if trainer.shared else trainer.k):
        ids, values = trainer.selected(k)
        yield block("topk", config, k, None, 0, ids.tolist(), values.tolist())
    for entry in trainer.log:
        yield block("log", config, None, None, entry[0], None, [float(x) for x in entry[1:]])


def rows_of(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple]:
    for b in batches:
        yield from zip(*(b.column(i).to_numpy(zero_copy_only=False) for i in range(len(b.schema))), strict=True)


#: Test rows that are scored at a time.
SCORED = 512


def runs_of(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple]:
    """Key (lane, phase, epoch, batch_id), example ids, labels, offsets, ids and values of runs of rows with equal keys.

    A run of phase 1 has at most ``SCORED`` rows. Columns are cut, not taken apart into rows.
    """
    key, held, n = None, [], 0

    def joined():
        examples, labels, sizes, ids, values = (np.concatenate(x) if len(held) > 1 else x[0] for x in zip(*held, strict=True))
        return key, examples, labels, np.r_[0, np.cumsum(sizes)], ids, values

    for b in batches:
        if not b.num_rows:
            continue
        keys = np.stack([b.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(4)], 1)
        examples, labels = (b.column(i).to_numpy(zero_copy_only=False) for i in (4, 5))
        starts, lists = zip(*((c.offsets.to_numpy(), c.values.to_numpy(zero_copy_only=False)) for c in (b.column(6), b.column(7))), strict=True)
        sizes, ids, values = np.diff(starts[0]), lists[0].astype(np.int64, copy=False), lists[1].astype(np.float64, copy=False)
        cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(1)) + 1).tolist(), len(keys)]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            own = tuple(keys[lo].tolist())
            if own != key:
                if held:
                    yield joined()
                key, held, n = own, [], 0
            while lo < hi:
                to = min(hi, lo + SCORED - n) if own[1] == 1 else hi
                held.append((examples[lo:to], labels[lo:to].astype(np.float64), sizes[lo:to], ids[starts[0][lo] : starts[0][to]], values[starts[1][lo] : starts[1][to]]))
                n, lo = n + to - lo, to
                if own[1] == 1 and n == SCORED:
                    yield joined()
                    held, n = [], 0
    if held:
        yield joined()


def replayed(batches: Iterable[pa.RecordBatch], make: Callable[[int], dict[int, Trainer]], supports: tuple[str, ...] = ()) -> Iterator[dict]:
    """Blocks from rows (lane, phase, epoch, batch_id, example_id, label, idx, val) in that order.

    ``make`` gives the trainers of a lane by configuration; each steps on every minibatch, which is
    laid out once for all of them. Phase 0 rows train, one minibatch per (epoch, batch_id); phase 1 rows
    are scored. A trainer rests from its stop rule or its last epoch on.
    """
    trainers, lane, before, going = {}, None, None, set()

    def done():
        for config, trainer in trainers.items():
            yield from model_blocks(trainer, config)

    for key, examples, labels, offsets, ids, values in runs_of(batches):
        if key[0] != lane:
            yield from done()
            lane, before = key[0], None
            trainers = make(lane)
            going = set(trainers)
        if before is not None and key[1:] < before:
            raise ValueError("rows came out of order")
        before = key[1:]
        batch = next(iter(trainers.values())).batch(offsets, ids, values, labels)
        if key[1] == 0:
            for config in sorted(going):
                trainer = trainers[config]
                if key[2] >= trainer.train.stop.max_epochs or not trainer.step(batch):
                    going.discard(config)
            continue
        for config, trainer in trainers.items():
            for support in supports:
                scores = trainer.scores(batch, support)
                yield block(f"score_{support}", config, trainer.k, None, 0, examples.tolist(), np.column_stack([batch.labels, scores]).ravel().tolist())
    yield from done()


def as_batches(blocks: Iterable[dict]) -> Iterator[pa.RecordBatch]:
    out = []
    for b in blocks:
        out.append(b)
        if len(out) >= 256:
            yield pa.RecordBatch.from_pylist(out, schema=SHAPE)
            out = []
    if out:
        yield pa.RecordBatch.from_pylist(out, schema=SHAPE)


def with_epochs(examples: DataFrame, epochs: int) -> DataFrame:
    return examples.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1))))


ORDER = ("lane", "phase", "epoch", "batch_id", "example_id")
FIELDS = ("label", "idx", "val")


#: About how long a step of a method takes, against one of ``hashed``.
WORK = {"curvature": 3, "dense_qn": 4, "newton": 4, "gradient": 2, "dense_sgd": 2, "hashed": 1}


def lanes_of(configs: dict[int, tuple[SketchSpec, TrainSpec]], lanes: int) -> list[list[int]]:
    """The configurations of every lane: the longest first, each to the lane with the least work so far."""
    work = {c: WORK[t.method] * t.classes * t.stop.max_epochs for c, (_, t) in configs.items()}
    out, load = [[] for _ in range(lanes)], [0] * lanes
    for c in sorted(configs, key=lambda c: -work[c]):
        least = load.index(min(load))
        out[least].append(c)
        load[least] += work[c]
    return out


def run_configs(
    examples: DataFrame,
    configs: dict[int, tuple[SketchSpec, TrainSpec]],
    test: DataFrame | None = None,
    supports: tuple[str, ...] = ("topk",),
    late: Callable[[DataFrame], DataFrame] | None = None,
    vocabulary: np.ndarray | None = None,
) -> DataFrame:
    """Blocks of one independent replay per configuration.

    Every configuration sees the same minibatches in the same order. Configurations are dealt to at
    most as many lanes as there are cores, with about equal work; a lane is one task, which reads the examples once and
    holds the states of its configurations and the rows of a minibatch. Several lanes read the same
    stored files, sorted once, so that the examples are not shuffled for each. ``late`` makes idx and val of
    rows that come without them, after they have been sorted. With a ``vocabulary`` (ids ascending), idx holds places in it.
    """
    lanes = min(len(configs), examples.sparkSession.sparkContext.defaultParallelism)
    dealt_to = lanes_of(configs, lanes)
    epochs = max(t.stop.max_epochs for _, t in configs.values())
    carried = [c for c in examples.columns if c not in ("batch_id", "example_id")] if late else FIELDS
    rows = examples.select(F.lit(0).alias("phase"), "batch_id", "example_id", *carried)
    if test is not None:
        rows = rows.unionByName(test.select(F.lit(1).alias("phase"), F.lit(0).cast("long").alias("batch_id"), "example_id", *carried))
    scored = supports if test is not None else ()

    def run(batches):
        def trainer(c):
            return Trainer(*configs[c]) if vocabulary is None else CodedTrainer(*configs[c], vocabulary)

        return as_batches(replayed(batches, lambda lane: {c: trainer(c) for c in dealt_to[lane]}, scored))

    if lanes == 1:
        lasts = F.when(F.col("phase") == 0, F.lit(epochs - 1)).otherwise(0)
        dealt = rows.withColumn("epoch", F.explode(F.sequence(F.lit(0), lasts))).withColumn("lane", F.lit(0).cast("long"))
        dealt = dealt.repartition(1).sortWithinPartitions(*ORDER)
        return (late(dealt) if late else dealt).select(*ORDER, *FIELDS).mapInArrow(run, BLOCKS)
    stored = in_order(rows, epochs, late)
    return side_by_side([stored.withColumn("lane", F.lit(lane).cast("long")).select(*ORDER, *FIELDS).mapInArrow(run, BLOCKS) for lane in range(lanes)])


def side_by_side(parts: list[DataFrame]) -> DataFrame:
    """The union of parts of one task each, as so many tasks.

    Spark unites parts that are all a single partition into one partition, and then runs them one after the other in
    one task. A part without rows, of unknown partitioning, keeps it from that.
    """
    first = parts[0]
    none = first.sparkSession.range(0, 2, 1, 2).filter("id < 0").select(*[F.lit(None).cast(f.dataType).alias(f.name) for f in first.schema])
    for one in (*parts[1:], none):
        first = first.unionByName(one)
    return first


#: Files of the sorted examples that lanes share.
FILES = 8


def in_order(rows: DataFrame, epochs: int, late: Callable[[DataFrame], DataFrame] | None = None, scope: str | None = None) -> DataFrame:
    """Rows of (phase, batch_id, example_id, ...) as one partition in that order, phase 0 once per epoch.

    The rows are sorted into files of consecutive ranges, and one task reads these one after the other.
    """
    spark = rows.sparkSession
    keys = ("phase", "batch_id", "example_id")
    ordered = rows.repartitionByRange(FILES, *keys).sortWithinPartitions(*keys)
    stored = written(late(ordered) if late else ordered, "in-order", scope)
    files = [spark.read.schema(stored.schema).parquet(f) for f in sorted(stored.inputFiles(), key=lambda f: f.rsplit("/", 1)[-1])] or [stored]
    passes = [(e, "phase = 0") for e in range(epochs)] + [(0, "phase = 1")] if epochs > 1 else [(0, "true")]
    out = None
    for epoch, which in passes:
        for f in files:
            one = f.filter(which).withColumn("epoch", F.lit(epoch))
            out = one if out is None else out.unionByName(one)
    return out.coalesce(1)


@dataclass
class Model:
    """A trained model: written blocks of cells, selected features and log."""

    blocks: DataFrame
    sketch: SketchSpec
    train: TrainSpec

    def topk_df(self) -> DataFrame:
        """class, rank, feature_id, estimate."""
        found = self.blocks.filter("kind = 'topk'")
        return found.select("class", F.posexplode(F.arrays_zip("ids", "vals")).alias("rank", "e")).select(
            "class", (F.col("rank") + 1).alias("rank"), F.col("e.ids").alias("feature_id"), F.col("e.vals").alias("estimate")
        )

    def cells_df(self) -> DataFrame:
        """class, row, bucket, value."""
        found = self.blocks.filter("kind = 'cells'")
        return found.select("class", "row", "start", F.posexplode("vals").alias("pos", "value")).select(
            "class", "row", (F.col("start") + F.col("pos")).cast("int").alias("bucket"), "value"
        )

    def log_df(self) -> DataFrame:
        names = ("loss", "grad_norm", "pairs_kept", "active", "heap_churn", "cells_used", "pair_values", "stale")
        whole = {"pairs_kept": "int", "active": "long", "heap_churn": "int", "cells_used": "long", "pair_values": "long"}
        return self.blocks.filter("kind = 'log'").select(
            F.col("start").alias("step"), *[F.col("vals")[i].cast(whole.get(n, "double")).alias(n) for i, n in enumerate(names)]
        )

    def state(self) -> tuple[np.ndarray, list[TopKHeap]]:
        """Cells and heaps on the driver; the sketch bounds their size."""
        classes = 1 if self.train.layout == "shared" else self.train.classes
        cells = np.zeros((classes, self.sketch.rows, self.sketch.buckets))
        heaps = [TopKHeap(self.train.k) for _ in range(classes)]
        for r in self.blocks.filter("kind in ('cells', 'topk')").collect():
            if r["kind"] == "cells":
                cells[r["class"], r["row"], r["start"] : r["start"] + len(r["vals"])] = r["vals"]
            else:
                order = np.argsort(np.array(r["ids"], np.int64))
                heaps[r["class"]] = TopKHeap(self.train.k, np.array(r["ids"], np.int64)[order], np.array(r["vals"], np.float64)[order])
        return cells, heaps

    def save(self, path: str) -> None:
        self.blocks.coalesce(1).write.mode("overwrite").parquet(f"{path}/blocks")
        about = json.dumps({"sketch": asdict(self.sketch), "train": asdict(self.train)})
        self.blocks.sparkSession.range(1).select(F.lit(about).alias("value")).coalesce(1).write.mode("overwrite").text(f"{path}/about")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Model:
        about = json.loads(spark.read.text(f"{path}/about").first()[0])
        train = about["train"]
        train["schedule"], train["stop"] = Schedule(**train["schedule"]), StopRule(**train["stop"])
        return cls(spark.read.schema(BLOCKS).parquet(f"{path}/blocks"), SketchSpec(**about["sketch"]), TrainSpec(**train))


class Ordered:
    """Packed examples that several replays share: put in order and stored once, when the first replay asks. One epoch."""

    def __init__(self, examples: DataFrame):
        self.examples, self._lock, self._stored = examples, Lock(), None

    def rows(self) -> DataFrame:
        with self._lock:
            if self._stored is None:
                self._stored = in_order(self.examples.select(F.lit(0).alias("phase"), "batch_id", "example_id", *FIELDS), 1, scope=self.scope)
            return self._stored

    @property
    def scope(self) -> str:
        return f"ordered-{id(self)}"

    def release(self) -> None:
        release(self.examples.sparkSession, self.scope)


def fit_ordered(examples: Ordered, sketch: SketchSpec, train: TrainSpec) -> Model:
    """The model of ``replay``, without a shuffle for each."""
    if train.stop.max_epochs != 1:
        raise ValueError("rows in order are stored for one epoch")

    def run(batches):
        return as_batches(replayed(batches, lambda _: {0: Trainer(sketch, train)}))

    lane = examples.rows().withColumn("lane", F.lit(0).cast("long")).select(*ORDER, *FIELDS)
    return Model(written(lane.mapInArrow(run, BLOCKS), "model"), sketch, train)


def fit(examples: DataFrame | Ordered, sketch: SketchSpec, train: TrainSpec, mode: str = "replay", **kw) -> Model:
    """Train on packed examples (example_id, batch_id, label, idx, val)."""
    if mode == "replay":
        return Model(written(run_configs(examples, {0: (sketch, train)}), "model"), sketch, train)
    if mode == "ordered":
        return fit_ordered(examples, sketch, train)
    if mode == "sharded":
        return fit_sharded(examples, sketch, train, **kw)
    if mode == "sync":
        from sketchselect.operators.sync import fit_sync

        return fit_sync(examples, sketch, train, **kw)
    raise ValueError(f"unknown mode {mode}")


def fit_sharded(examples: DataFrame, sketch: SketchSpec, train: TrainSpec, shards: int = 4, rounds: int = 1, late: Callable[[DataFrame], DataFrame] | None = None) -> Model:
    """Each shard replays its minibatches from the common cells; cells are averaged per round.

    Not the sequential method: with one shard and one round it is the same, with more its
    accuracy is to be measured. One shuffle of shards x cells numbers per round. ``late`` makes idx and
    val of rows that come without them, after they have been dealt and sorted.
    """
    cells = heaps = None
    for _ in range(rounds):
        # the states of a round: every task holds one anyway, so it is broadcast, not pickled with each
        sent = examples.sparkSession.sparkContext.broadcast((cells, heaps))

        def run(batches, sent=sent):
            def make(_):
                cells, heaps = sent.value
                return {0: Trainer(sketch, train, None if cells is None else cells.copy(), None if heaps is None else [TopKHeap(h.k, h.ids, h.values) for h in heaps])}

            return as_batches(replayed(batches, make))

        carried = [c for c in examples.columns if c not in ("batch_id", "example_id")] if late else FIELDS
        rows = with_epochs(examples, train.stop.max_epochs).select(
            F.lit(0).cast("long").alias("lane"), F.lit(0).alias("phase"), "epoch", "batch_id", "example_id", *carried
        )
        dealt = rows.repartition(shards, F.pmod(F.col("batch_id"), F.lit(shards)).cast("int")) if shards > 1 else rows.repartition(1)
        dealt = dealt.sortWithinPartitions(*ORDER)
        packed = late(dealt) if late else dealt
        local = written(packed.select(*ORDER, *FIELDS).mapInArrow(run, BLOCKS), "shards")
        n = local.filter("kind = 'cells' and class = 0 and row = 0 and start = 0").count()
        summed = (
            local.filter("kind = 'cells'")
            .select("class", "row", "start", F.posexplode("vals").alias("pos", "v"))
            .groupBy("class", "row", "start", "pos")
            .agg((F.sum("v") / n).alias("v"))
            .groupBy("class", "row", "start")
            .agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda e: e["v"]).alias("vals"))
        )
        mean = Model(
            written(summed.select(F.lit("cells").alias("kind"), F.lit(0).cast("long").alias("config"), "class", "row", "start", F.lit(None).cast("array<bigint>").alias("ids"), "vals"), "mean"),
            sketch,
            train,
        )
        cells, _ = mean.state()
        held = local.filter("kind = 'topk'").select("class", F.explode("ids").alias("id")).distinct().collect()
        store, heaps = CountSketch(sketch, len(cells), cells), [TopKHeap(train.k) for _ in range(len(cells))]
        for k, heap in enumerate(heaps):
            ids = np.sort(np.array([r["id"] for r in held if r["class"] == k], np.int64))
            heap.update(ids, store.query(k, ids))
    final = Trainer(sketch, train, cells, heaps)
    spark = examples.sparkSession
    tops = [block("topk", 0, k, None, 0, *(x.tolist() for x in final.selected(k))) for k in range(len(heaps))]
    top = spark.createDataFrame([tuple(b.values()) for b in tops], BLOCKS)
    return Model(written(mean.blocks.unionByName(top).unionByName(local.filter("kind = 'log'")), "model"), sketch, train)


# ---- prediction


def predictions(blocks: DataFrame, support: str = "topk") -> DataFrame:
    """config, example_id, label, class, score from the scored rows of ``run_configs``."""
    found = blocks.filter(F.col("kind") == f"score_{support}").select("config", F.col("class").alias("k"), F.posexplode("ids").alias("at", "example_id"), "vals")
    width = F.col("k") + 1
    return found.select(
        "config", "example_id", F.element_at("vals", (F.col("at") * width + 1).cast("int")).alias("label"),
        F.posexplode(F.slice("vals", F.col("at") * width + 2, F.col("k"))).alias("class", "score"),
    )


def predict(examples: DataFrame, model: Model, support: str = "all") -> DataFrame:
    """example_id, label, class, score (margin) of packed examples.

    ``topk`` joins entries with the selected features (broadcast: at most k per class); ``all``
    reads every active feature from the cells, which are broadcast up to ``BROADCAST_CELLS`` numbers
    and joined with the entries beyond.
    """
    classes = model.train.classes
    if support == "all" and model.train.layout == "per_class" and model.train.method in ("curvature", "gradient", "newton") and classes * model.sketch.cells > sk.BROADCAST_CELLS:
        entry = examples.select("example_id", "label", F.explode_outer(F.arrays_zip("idx", "val")).alias("e")).select(
            "example_id", "label", F.col("e.idx").alias("feature_id"), F.col("e.val").alias("value")
        )
        ids, out = entry.select("feature_id").filter("feature_id is not null").distinct(), None
        for k in range(classes):
            read = sk.query(model.cells_df().filter(F.col("class") == k).drop("class"), ids, model.sketch)
            one = entry.join(read, "feature_id", "left").groupBy("example_id", "label").agg(F.coalesce(F.sum(F.col("value") * F.col("estimate")), F.lit(0.0)).alias("score"))
            one = one.select("example_id", "label", F.lit(k).alias("class"), "score")
            out = one if out is None else out.unionByName(one)
        return out
    if support == "topk" and model.train.layout == "per_class":
        entry = examples.select("example_id", "label", F.explode_outer(F.arrays_zip("idx", "val")).alias("e")).select(
            "example_id", "label", F.col("e.idx").alias("feature_id"), F.col("e.val").alias("value"), F.explode(F.sequence(F.lit(0), F.lit(classes - 1))).alias("class")
        )
        top = F.broadcast(model.topk_df().select("class", "feature_id", "estimate"))
        return entry.join(top, ["class", "feature_id"], "left").groupBy("example_id", "label", "class").agg(
            F.coalesce(F.sum(F.col("value") * F.col("estimate")), F.lit(0.0)).alias("score")
        )
    sent = examples.sparkSession.sparkContext.broadcast(model.state())
    sketch, train = model.sketch, model.train

    def run(batches):
        trainer = Trainer(sketch, train, *sent.value)
        for rows in batches:
            got = [rows.column(i).to_numpy(zero_copy_only=False) for i in range(4)]
            scores = trainer.scores(Batch.of(list(got[2]), list(got[3]), got[1]), support)
            n, k = scores.shape
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat(got[0], k)), pa.array(np.repeat(got[1], k)), pa.array(np.tile(np.arange(k, dtype=np.int32), n)), pa.array(scores.ravel())],
                names=["example_id", "label", "class", "score"],
            )

    return examples.select("example_id", "label", "idx", "val").mapInArrow(run, "example_id long, label double, class int, score double")


def decided(scores: DataFrame, keys: list[str]) -> DataFrame:
    """One row per example: label, score (of class 0 for two classes), prediction."""
    best = F.max_by("class", F.struct("score", -F.col("class")))
    return scores.groupBy(*keys, "example_id", "label").agg(F.count("*").alias("n"), best.alias("best"), F.min_by("score", "class").alias("score")).select(
        *keys, "example_id", "label", "score",
        F.when(F.col("n") == 1, (F.col("score") > 0).cast("double")).otherwise(F.col("best").cast("double")).alias("prediction"),
    )


def probabilities(scores: DataFrame, keys: list[str] = []) -> DataFrame:
    """Add ``probability``: sigmoid of a single score, softmax over several."""
    w = Window.partitionBy(*keys, "example_id")
    n, top = F.count("*").over(w), F.max("score").over(w)
    e = F.exp(F.col("score") - top)
    return scores.withColumn("probability", F.when(n == 1, 1 / (1 + F.exp(-F.col("score")))).otherwise(e / F.sum(e).over(w)))


def explain(model: Model, dictionary: DataFrame) -> DataFrame:
    """The selected features with their names; ``dictionary`` has feature_id and name."""
    return model.topk_df().join(dictionary, "feature_id").select("class", "rank", "feature_id", "name", "estimate")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """feature_id and where it is selected: first, second or both."""
    x = a.select("feature_id", F.lit(1).alias("x"))
    y = b.select("feature_id", F.lit(1).alias("y"))
    return x.join(y, "feature_id", "full").select(
        "feature_id", F.when(F.col("y").isNull(), "first").when(F.col("x").isNull(), "second").otherwise("both").alias("selected_by")
    )
