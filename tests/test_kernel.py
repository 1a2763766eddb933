"""Sketch, heap, two-loop product and training steps against brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sketchselect.functions import hashing as hs
from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import theory
from sketchselect.operators.kernel import (
    Batch,
    CountSketch,
    Ring,
    Schedule,
    StopRule,
    TopKHeap,
    Trainer,
    TrainSpec,
    residuals,
    two_loop,
)
from sketchselect.operators.sync import gram_direction


def draw(seed):
    return np.random.default_rng(seed)


@pytest.mark.parametrize("family", ["murmur3", "affine"])
def test_hash_columns_equal_numpy(spark, family):
    spec = SketchSpec(5, 97, 3, family)
    ids = draw(1).integers(-(2**62), 2**62, 3000) if family == "murmur3" else draw(1).integers(0, 2**60, 3000)
    df = spark.createDataFrame([(int(i), int(x)) for i, x in enumerate(ids)], "i int, id long")
    got = df.select("i", F.posexplode(hs.places(F.col("id"), spec)).alias("j", "p")).orderBy("i", "j").select("p.bucket", "p.sign").toPandas()
    buckets, signs = hs.np_places(ids, spec)
    assert (got.bucket.to_numpy().reshape(-1, 5).T == buckets).all()
    assert (got.sign.to_numpy().reshape(-1, 5).T == signs).all()


def test_sketch_is_linear_and_exact_without_collisions():
    spec = SketchSpec(5, 1 << 14, 1)
    ids, values = np.arange(50), draw(2).standard_normal(50)
    whole, a, b = CountSketch(spec), CountSketch(spec), CountSketch(spec)
    whole.add(0, ids, values)
    a.add(0, ids[:20], values[:20])
    b.add(0, ids[20:], values[20:])
    assert np.allclose(a.cells + b.cells, whole.cells)
    assert np.allclose(whole.query(0, ids), values)


def test_top_k_error_bound_over_seeds():
    values = 1 / np.arange(1, 2001)
    worst = []
    for seed in range(30):
        s = CountSketch(SketchSpec(7, 200, seed))
        s.add(0, np.arange(2000), values)
        worst.append(np.abs(s.query(0, np.arange(10)) - values[:10]).max())
    assert np.mean(np.array(worst) <= 0.3 * np.linalg.norm(values)) >= 0.9


def test_heap_equals_a_full_sort():
    rng = draw(3)
    heap, stored = TopKHeap(10), {}
    for _ in range(60):
        ids = np.unique(rng.integers(0, 60, 12))
        values = rng.integers(-5, 6, len(ids)).astype(float)
        stored.update(zip(ids.tolist(), values.tolist(), strict=True))
        heap.update(ids, values)
        best = sorted(stored, key=lambda i: (-abs(stored[i]), i))[:10]
        stored = {i: stored[i] for i in best}
        assert dict(zip(heap.ids.tolist(), heap.values.tolist(), strict=True)) == stored


def dense_inverse(s, r):
    h = float(s[-1] @ r[-1]) / float(r[-1] @ r[-1]) * np.eye(len(s[0]))
    for a, b in zip(s, r, strict=True):
        rho = 1 / (a @ b)
        left = np.eye(len(a)) - rho * np.outer(a, b)
        h = left @ h @ left.T + rho * np.outer(a, a)
    return h


@pytest.mark.parametrize("pairs", [1, 3, 5])
def test_two_loop_equals_the_dense_matrix(pairs):
    rng = draw(pairs)
    a = rng.standard_normal((20, 20))
    hessian = a @ a.T + np.eye(20)
    s = [rng.standard_normal(20) for _ in range(pairs)]
    r = [hessian @ x for x in s]
    g = rng.standard_normal(20)
    want = dense_inverse(s, r) @ g
    assert np.allclose(two_loop(g, s, r), want, atol=1e-9)
    assert np.allclose(two_loop(r[-1], s, r), s[-1])  # the secant condition
    assert np.allclose(two_loop(2 * g, s, r), 2 * want)
    assert g @ want > 0
    basis = np.array([*s, *r, g])
    assert np.allclose(gram_direction(basis @ basis.T) @ basis, want, atol=1e-8)
    assert np.allclose(two_loop(g, [], []), g)


def test_pairs_without_curvature_are_skipped():
    ring, ids = Ring(3, 1e-10), np.arange(3)
    assert not ring.push(ids, np.array([1.0, 0, 0]), ids, np.array([-1.0, 0, 0]))
    assert not ring.push(ids, np.zeros(3), ids, np.ones(3))
    assert ring.push(ids, np.ones(3), ids, np.ones(3)) and len(ring.pairs) == 1


def data(seed, n=60, p=40, active=8):
    rng = draw(seed)
    out = []
    for _ in range(n):
        ids = np.sort(rng.choice(p, active, replace=False))
        out.append((ids, np.ones(active), float(ids[0] < p / 4)))
    return out


def train(spec, sketch, rows, size=10, **kw):
    trainer = Trainer(sketch, spec, **kw)
    for at in range(0, len(rows), size):
        own = rows[at : at + size]
        trainer.step(Batch.of([r[0] for r in own], [r[1] for r in own], [r[2] for r in own]))
    return trainer


def test_no_history_is_the_first_order_method():
    rows, sketch = data(1), SketchSpec(3, 30, 1)
    a = train(TrainSpec(method="curvature", history=0, k=10), sketch, rows)
    b = train(TrainSpec(method="gradient", k=10), sketch, rows)
    assert np.array_equal(a.store.cells, b.store.cells)


def test_the_third_step_is_the_first_to_differ():
    rows, sketch = data(2, 30), SketchSpec(3, 64, 1)
    runs = {m: [train(TrainSpec(method=m, k=10), sketch, rows[: 10 * n]).store.cells for n in (1, 2, 3)] for m in ("curvature", "gradient")}
    assert np.array_equal(runs["curvature"][0], runs["gradient"][0]) and np.array_equal(runs["curvature"][1], runs["gradient"][1])
    assert not np.allclose(runs["curvature"][2], runs["gradient"][2])


@pytest.mark.parametrize("pair", [("gradient", "dense_sgd"), ("curvature", "dense_qn")])
def test_a_sketch_without_collisions_is_dense_training(pair):
    rows, sketch = data(3), SketchSpec(5, 1 << 14, 1)
    # features that are new to the heap have no second reading, so history needs full support
    a = train(TrainSpec(method=pair[0], k=40, support="all" if pair[0] == "curvature" else "heap"), sketch, rows)
    b = train(TrainSpec(method=pair[1], k=40), sketch, rows)
    ids = np.arange(40)
    assert np.allclose(a.store.query(0, ids), b.store.query(0, ids), atol=1e-8)


def test_hashed_training_is_one_row_with_full_support():
    rows = data(4)
    a = train(TrainSpec(method="hashed", k=10), SketchSpec(1, 50, 2), rows)
    b = train(TrainSpec(method="gradient", k=10, support="all"), SketchSpec(1, 50, 2), rows)
    assert np.allclose(a.store.cells, b.store.cells)


def test_sketched_descent_is_descent_on_projected_features():
    """With the mean reading and full support, cells follow gradient descent on X S."""
    rng, p, spec = draw(5), 30, SketchSpec(3, 8, 4, query="mean")
    x, y = rng.standard_normal((20, p)), rng.standard_normal(20)
    trainer = Trainer(spec, TrainSpec(loss="squared", method="gradient", support="all", k=5, schedule=Schedule(0.01)))
    s, u = theory.projection(p, spec), np.zeros(spec.cells)
    for _ in range(10):
        trainer.step(Batch(np.arange(21) * p, np.tile(np.arange(p), 20), x.ravel(), y))
        u -= 0.01 * (x @ s).T @ (x @ s @ u - y)
    assert np.allclose(trainer.store.cells.ravel() / np.sqrt(spec.rows), u, atol=1e-9)


def test_newton_solves_the_quadratic():
    rng = draw(6)
    x, w = rng.standard_normal((50, 10)), np.arange(1.0, 11)
    trainer = Trainer(SketchSpec(5, 1 << 12, 1), TrainSpec(loss="squared", method="newton", k=10, schedule=Schedule(1.0), ridge=1e-9, support="all"))
    for _ in range(3):
        trainer.step(Batch(np.arange(51) * 10, np.tile(np.arange(10), 50), x.ravel(), x @ w))
    assert np.allclose(trainer.store.query(0, np.arange(10)), w, atol=1e-4)


def test_multiclass_layouts():
    rows = [(i, v, float(i[0] % 3)) for i, v, _ in data(7, 90)]
    for layout in ("per_class", "shared"):
        t = train(TrainSpec(loss="softmax", classes=3, layout=layout, k=40), SketchSpec(5, 4096, 1), rows)
        assert len(t.heaps) == (1 if layout == "shared" else 3)
        batch = Batch.of([r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows])
        assert (t.scores(batch, "all").argmax(1) == batch.labels).mean() > 0.5
    with_gradient, _ = residuals("softmax", np.zeros((2, 4)), np.array([0.0, 3.0]))
    assert np.allclose(with_gradient.sum(1), 0)


def test_edges_of_a_step():
    sketch = SketchSpec(2, 1, 0)
    t = Trainer(sketch, TrainSpec(k=100))
    assert t.step(Batch.of([[]], [[]], [1.0]))
    assert t.step(Batch.of([[-5, 2**40]], [[1.0, 1.0]], [1.0]))
    assert t.step(Batch.of([[7, 7]], [[1.0, 2.0]], [0.0]))
    assert len(t.selected()[0]) == 3
    with pytest.raises(ValueError):
        Batch.of([[1]], [[np.nan]], [1.0])
    with pytest.raises(ValueError):
        Schedule(kind="power", power=0.4)


def test_stop_rules():
    t = Trainer(SketchSpec(3, 64), TrainSpec(k=5, stop=StopRule(max_steps=2)))
    batch = Batch.of([[1]], [[1.0]], [1.0])
    assert t.step(batch) and not t.step(batch)
    quiet = Trainer(SketchSpec(3, 64), TrainSpec(loss="squared", k=5, stop=StopRule(grad_norm=1e-7, patience=2)))
    zero = Batch.of([[1]], [[1.0]], [0.0])
    assert quiet.step(zero) and not quiet.step(zero)


def test_memory_stays_within_the_account():
    rows = data(8)
    t = train(TrainSpec(method="curvature", k=10, history=5), SketchSpec(3, 30, 1), rows)
    for entry in t.log:
        assert entry[7] <= 5 * (entry[4] * 2)


# ---- theory


def test_projection_gram_is_the_identity_on_average():
    p, spec = 400, SketchSpec(2, 10)
    mean = np.mean([theory.gram_of_projection(p, spec.with_(seed=s)) for s in range(100)], 0)
    assert np.abs(mean - np.eye(20)).max() < 0.15


def test_projected_curvature_stays_in_range():
    rng = draw(9)
    d = np.diag(rng.uniform(1, 2, 900))
    inside = 0
    for s in range(20):
        low, high, cut_low, cut_high = theory.hessian_range(d, SketchSpec(1, 20, s))
        inside += 900 / 20 * 0.5 * low <= cut_low and cut_high <= 900 / 20 * 1.5 * high
    assert inside >= 19


def test_sizes_are_monotone():
    base = theory.topk_cells(10**6, 10, 1.0, 0.1, 0.5, 0.1)
    assert theory.topk_cells(10**7, 10, 1.0, 0.1, 0.5, 0.1) > base < theory.topk_cells(10**6, 20, 1.0, 0.1, 0.5, 0.1)
    assert theory.topk_cells(10**6, 10, 1.0, 0.1, 0.4, 0.1) > base < theory.topk_cells(10**6, 10, 1.0, 0.1, 0.5, 0.01)
    assert theory.convergence_size(0.1, 0.1)[0] > theory.convergence_size(0.2, 0.1)[0]
    assert theory.corollary_size(10**6, 10, 1.0, 0.1, 0.5, 0.1) >= theory.topk_cells(10**6, 10, 1.0, 0.1, 0.5, 0.05)
    assert 0 <= theory.tail_probability(10**6, 100, 0.5) <= 1
    one, two = theory.gradient_bounds(100, 10, 2.0, 0.1, 1.0)
    assert two == pytest.approx(2 * one)
    with pytest.raises(ValueError):
        theory.rate_constant(0.1, 1, 0.1, 1.0, 1.0, 1.0)
    assert theory.rate_constant(1.0, 10, 1.0, 1.0, 1.0, 1.0) > 0
    assert SketchSpec.from_cf(68724, 95).cells == pytest.approx(68724 / 95, rel=0.01)
    assert SketchSpec.from_bytes(8000).cells == 1000 and SketchSpec.from_error(0.1, 0.01).rows % 2 == 1


def test_decaying_steps_converge_like_one_over_t():
    rng = draw(10)
    x, w = rng.standard_normal((200, 5)), np.ones(5)
    y = x @ w + 0.1 * rng.standard_normal(200)
    best = np.linalg.lstsq(x, y, rcond=None)[0]
    t = Trainer(SketchSpec(5, 1 << 12), TrainSpec(loss="squared", method="gradient", k=5, support="all", grad_scale="mean", schedule=Schedule(2.0, "inverse_time", 10)))
    gaps = []
    for _ in range(400):
        rows = rng.choice(200, 20)
        t.step(Batch(np.arange(21) * 5, np.tile(np.arange(5), 20), x[rows].ravel(), y[rows]))
        w_now = t.store.query(0, np.arange(5))
        gaps.append(0.5 * np.mean((x @ w_now - y) ** 2) - 0.5 * np.mean((x @ best - y) ** 2))
    assert np.mean(gaps[-50:]) < 0.3 * np.mean(gaps[40:90])


def test_dense_rows_and_products_give_the_same_run():
    """Entries, a matrix, and a matrix with its products: one trajectory, for each method."""
    rng = np.random.default_rng(4)
    x, w = rng.standard_normal((40, 12)), np.r_[1.0, -1.0, np.zeros(10)]
    y = x @ w
    entries = Batch(np.arange(41) * 12, np.tile(np.arange(12), 40), x.ravel(), y)
    for method, eta in (("curvature", 0.05), ("gradient", 0.003), ("newton", 0.1)):
        ends = []
        for batch in (entries, Batch.of_matrix(x, y), Batch.of_matrix(x, y, (x.T @ x, x.T @ y))):
            t = Trainer(SketchSpec(3, 16, 3), TrainSpec(loss="squared", method=method, k=4, schedule=Schedule(eta), first_scale="inverse_norm"))
            for _ in range(6):
                t.step(batch)
            ends.append(t.store.cells)
        assert np.allclose(ends[0], ends[1]) and np.allclose(ends[0], ends[2])


def test_damping_bounds_the_inverse():
    """Pairs of almost no curvature: undamped, the direction is that much longer than the gradient."""
    ring, damped = Ring(5, 1e-10), Ring(5, 1e-10)
    ids, s, r = np.arange(3), np.array([1.0, 0.5, 0.0]), np.array([1e-6, 1e-6, 0.0])
    ring.push(ids, s, ids, r)
    damped.push(ids, s, ids, r + 10 * s)
    g = np.ones(3)
    assert np.linalg.norm(ring.product(ids, g)) > 1e4 and np.linalg.norm(damped.product(ids, g)) < 1
