"""The recovery simulations: Gaussian rows, planted sparse weights, many independent trials.

Every trial is one row of a table of configurations. Data come from the trial's seed inside
the task (counter-based generator, so values do not depend on partitioning); nothing is
shipped but the configuration.
"""

from __future__ import annotations

import time
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators.kernel import Batch, Schedule, StopRule, Trainer, TrainSpec
from sketchselect.schema import SWEEP

#: Rows, features, planted features, range of planted weights, trials, shares of p.
ROWS, FEATURES, PLANTED, LOW, HIGH, TRIALS = 900, 1000, 8, 0.8, 1.2, 200
SHARES = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6)
HASHES = 3
#: Step sizes found by search (``search``), per method.
BEST_ETA = {"gradient": 3e-4, "curvature": 0.07, "newton": 0.2}
#: Rows of a minibatch and steps at most. Both matter: with all rows as one minibatch the gradient has no
#: noise to accumulate, and the first order does as well as the second; runs of 150 steps end before
#: either has found the features.
BATCH, STEPS = 30, 1500
#: Options of the trainer in the simulations.
OPTIONS = {"first_scale": "inverse_norm"}


def planted(seed: int, n: int = ROWS, p: int = FEATURES, k: int = PLANTED) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (n x p), labels and the true weights of one trial."""
    draw = np.random.Generator(np.random.Philox(seed))
    x = draw.standard_normal((n, p))
    truth = np.zeros(p)
    truth[draw.choice(p, k, replace=False)] = draw.uniform(LOW, HIGH, k)
    return x, x @ truth, truth


def trial(
    method: str, cf: float, eta: float, tau: int, seed: int, batch: int = BATCH, steps: int = STEPS, n: int = ROWS, p: int = FEATURES, k: int = PLANTED, **options
) -> tuple[bool, float, int]:
    """(all planted features found, l2 error, steps) of one run; ``options`` go to the trainer."""
    x, y, truth = planted(seed, n, p, k)
    train = TrainSpec(loss="squared", method=method, k=k, schedule=Schedule(eta), history=tau, ridge=1.0, stop=StopRule(10**6, steps, 1e-7, 3)).with_(**(OPTIONS | options))
    trainer = Trainer(SketchSpec.from_cf(p, cf, HASHES, seed=seed % 1000), train)
    order = np.random.Generator(np.random.Philox(seed + 10**9))
    whole = Batch.of_matrix(x, y, (x.T @ x, x.T @ y)) if batch >= n else None
    going = True
    while going:
        rows = order.permutation(n) if whole is None else np.arange(1)
        for at in range(0, len(rows), batch):
            own = rows[at : at + batch]
            going = trainer.step(Batch.of_matrix(x[own], y[own]) if whole is None else whole)
            if not going:
                break
    found, values = trainer.selected()
    estimate = np.zeros(p)
    estimate[found] = values
    return set(np.flatnonzero(truth)) <= set(found.tolist()), float(np.linalg.norm(estimate - truth)), trainer.t


def run_trials(spark: SparkSession, configs: Iterable[tuple[str, float, float, int]], trials: int, **size) -> DataFrame:
    """SWEEP rows (success, l2_error and steps) of (method, cf, eta, tau) configurations x trials."""
    listed = [(m, float(cf), float(eta), int(tau)) for m, cf, eta, tau in configs]
    table = spark.createDataFrame(listed, "method string, cf double, eta double, tau int").withColumn("seed", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(trials - 1).cast("long"))))

    def run(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                began = time.perf_counter()
                success, error, steps = trial(r["method"], r["cf"], r["eta"], r["tau"], r["seed"], **size)
                took = time.perf_counter() - began
                for metric, value in (("success", float(success)), ("l2_error", error), ("steps", float(steps))):
                    out.append({"workload": "simulation", "mode": "grid", "k": size.get("k", PLANTED), "metric": metric, "value": value, "seconds": took, **r})
            names = [f.name for f in SWEEP.fields]
            yield pa.RecordBatch.from_pylist([{n: o[n] for n in names} for o in out], schema=shape)

    kinds = {"string": pa.string(), "double": pa.float64(), "integer": pa.int32(), "long": pa.int64()}
    shape = pa.schema([(f.name, kinds[f.dataType.typeName()]) for f in SWEEP.fields])
    n = max(1, min(len(listed) * trials, 4 * spark.sparkContext.defaultParallelism))
    return table.repartition(n, "method", "cf", "eta", "tau", "seed").mapInArrow(run, SWEEP)


def recovery_curve(spark: SparkSession, trials: int = TRIALS, shares=SHARES, methods=("curvature", "gradient", "newton"), **size) -> DataFrame:
    """Success rate and mean l2 error against the compression factor."""
    configs = [(m, 1 / s, BEST_ETA[m], 5) for m in methods for s in shares]
    return summary(run_trials(spark, configs, trials, **size), ["method", "cf"])


def step_curve(spark: SparkSession, trials: int = TRIALS, etas=None, methods=("curvature", "gradient"), **size) -> DataFrame:
    """Success rate against the step size; the sketch is 3 x 150."""
    etas = [10.0 ** (-7 + i / 2) for i in range(13)] if etas is None else etas
    configs = [(m, FEATURES / 450, e, 5) for m in methods for e in etas]
    return summary(run_trials(spark, configs, trials, **size), ["method", "eta"])


def summary(results: DataFrame, keys: list[str]) -> DataFrame:
    return results.groupBy(*keys).pivot("metric", ["success", "l2_error", "steps"]).agg(F.avg("value")).orderBy(*keys)


def search(spark: SparkSession, method: str, etas: Iterable[float], trials: int = 8, cf: float = 3.0, **size) -> DataFrame:
    """Step-size search: best by success, then by error."""
    table = summary(run_trials(spark, [(method, cf, e, 5) for e in etas], trials, **size), ["method", "eta"])
    return table.orderBy(F.desc("success"), "l2_error")
