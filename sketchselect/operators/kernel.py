"""Sketch, heap, history and training steps in numpy: what runs inside one task.

A step is a function of the state and a minibatch. The state is the cells, the heap of
held features, the ring of curvature pairs and the step number.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import cached_property
from typing import Literal

import numpy as np

from sketchselect.functions.hashing import SketchSpec, np_places


def _middle(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum(np.minimum(a, b), np.minimum(np.maximum(a, b), c))


class CountSketch:
    """Cells of ``classes`` sketches with the same hash functions."""

    def __init__(self, spec: SketchSpec, classes: int = 1, cells: np.ndarray | None = None):
        self.spec = spec
        self.cells = np.zeros((classes, spec.rows, spec.buckets)) if cells is None else cells

    def add(self, k: int, ids: np.ndarray, deltas: np.ndarray, at: tuple | None = None) -> None:
        buckets, signs = np_places(ids, self.spec) if at is None else at
        few = 8 * len(ids) < self.spec.buckets
        for j in range(self.spec.rows):
            if few:  # the same sums, without a pass over all buckets
                own, to = np.unique(buckets[j], return_inverse=True)
                self.cells[k, j, own] += np.bincount(to, signs[j] * deltas, len(own))
            else:
                self.cells[k, j] += np.bincount(buckets[j], signs[j] * deltas, self.spec.buckets)

    def query(self, k: int, ids: np.ndarray, at: tuple | None = None) -> np.ndarray:
        if not len(ids):
            return np.empty(0)
        buckets, signs = np_places(ids, self.spec) if at is None else at
        return self.estimate([signs[j] * self.cells[k, j, buckets[j]] for j in range(self.spec.rows)])

    def estimate(self, read: list[np.ndarray]) -> np.ndarray:
        """One number from the readings of the hash rows."""
        if self.spec.query != "median":
            return np.mean(read, 0)
        if len(read) == 3:  # the same number, without a sort
            return _middle(*read)
        if len(read) == 5:  # neither the least nor the largest of four is the middle of five
            a, b, c, d, e = read
            low = np.maximum(np.minimum(a, b), np.minimum(c, d))
            high = np.minimum(np.maximum(a, b), np.maximum(c, d))
            return _middle(low, high, e)
        return np.median(read, 0)


class ExactStore:
    """The same interface with one cell per feature: for the dense trainers.

    A feature keeps the slot that it got when it first came. Slots are found in sorted runs of ids, merged
    whenever the last is half as long as the one before, so a step does not touch all features.
    """

    def __init__(self, classes: int = 1):
        self._runs: list[tuple[np.ndarray, np.ndarray]] = []
        self._n = 0
        self._ids = np.empty(1024, np.int64)
        self._weights = np.zeros((classes, 1024))

    @property
    def ids(self) -> np.ndarray:
        """Every id that was ever named, by slot."""
        return self._ids[: self._n]

    @property
    def weights(self) -> np.ndarray:
        """Classes x slots."""
        return self._weights[:, : self._n]

    def _found(self, ids: np.ndarray) -> np.ndarray:
        slots = np.full(len(ids), -1, np.int64)
        for run, at in self._runs:
            i = np.minimum(np.searchsorted(run, ids), len(run) - 1)
            same = run[i] == ids
            slots[same] = at[i[same]]
        return slots

    def places(self, ids: np.ndarray) -> np.ndarray:
        """The slots of ids; new ids get new ones."""
        slots = self._found(ids)
        fresh = slots < 0
        if fresh.any():
            new = np.unique(ids[fresh])
            n = self._n + len(new)
            if n > len(self._ids):
                size = max(n, 2 * len(self._ids))
                self._ids = np.concatenate([self.ids, np.empty(size - self._n, np.int64)])
                self._weights = np.concatenate([self.weights, np.zeros((len(self._weights), size - self._n))], 1)
            self._ids[self._n : n] = new
            self._runs.append((new, np.arange(self._n, n)))
            while len(self._runs) > 1 and 2 * len(self._runs[-1][0]) > len(self._runs[-2][0]):
                (a, x), (b, y) = self._runs[-2:]
                both, at = np.concatenate([a, b]), np.concatenate([x, y])
                order = np.argsort(both, kind="stable")
                self._runs[-2:] = [(both[order], at[order])]
            slots[fresh] = self._n + np.searchsorted(new, ids[fresh])
            self._n = n
        return slots

    def add(self, k: int, ids: np.ndarray, deltas: np.ndarray, at: np.ndarray | None = None) -> None:
        at = self.places(ids) if at is None else at
        np.add.at(self._weights[k], at, deltas)

    def query(self, k: int, ids: np.ndarray, at: np.ndarray | None = None) -> np.ndarray:
        at = self.places(ids) if at is None else at  # first, as new ids may move the weights
        return self._weights[k, at]


class TopKHeap:
    """The k ids of largest magnitude with their estimates; ties go to the smaller id."""

    def __init__(self, k: int, ids: np.ndarray | None = None, values: np.ndarray | None = None):
        self.k = k
        self.ids = np.empty(0, np.int64) if ids is None else ids
        self.values = np.empty(0) if values is None else values

    def holds(self, ids: np.ndarray) -> np.ndarray:
        if not len(self.ids):
            return np.zeros(len(ids), bool)
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1)
        return self.ids[at] == ids

    def update(self, ids: np.ndarray, values: np.ndarray) -> int:
        """Insert or refresh ``ids``; ids not named keep their stored value. Returns how many changed."""
        stays = ~np.isin(self.ids, ids)
        every, estimates = np.concatenate([self.ids[stays], ids]), np.concatenate([self.values[stays], values])
        if len(every) > self.k:
            size = np.abs(estimates)
            cut = np.partition(size, len(size) - self.k)[len(size) - self.k]
            sure, tied = np.flatnonzero(size > cut), np.flatnonzero(size == cut)
            tied = tied[np.argsort(every[tied], kind="stable")][: self.k - len(sure)]
            pick = np.concatenate([sure, tied])
            every, estimates = every[pick], estimates[pick]
        order = np.argsort(every)
        before = self.ids
        self.ids, self.values = every[order], estimates[order]
        return int(len(self.ids) - np.isin(self.ids, before, assume_unique=True).sum())


@dataclass
class Schedule:
    """Step sizes: constant, eta / (t + offset), or eta / (t + 1) ** power."""

    eta: float = 0.1
    kind: Literal["constant", "inverse_time", "power"] = "constant"
    offset: float = 1.0
    power: float = 1.0

    def __post_init__(self):
        if self.kind == "power" and not 0.5 < self.power <= 1:
            raise ValueError("the steps sum to infinity and their squares do not only for a power in (0.5, 1]")

    def at(self, t: int) -> float:
        if self.kind == "inverse_time":
            return self.eta / (t + self.offset)
        if self.kind == "power":
            return self.eta / (t + 1) ** self.power
        return self.eta


@dataclass
class StopRule:
    """Epochs at most, steps at most, gradient norm below a bound for ``patience`` steps in a row."""

    max_epochs: int = 1
    max_steps: int | None = None
    grad_norm: float = 0.0
    patience: int = 1


@dataclass
class TrainSpec:
    loss: Literal["squared", "logistic", "softmax"] = "logistic"
    method: Literal["curvature", "gradient", "newton", "dense_sgd", "dense_qn", "hashed"] = "curvature"
    k: int = 100
    batch_size: int = 20
    schedule: Schedule = field(default_factory=Schedule)
    history: int = 5
    step_source: Literal["queried", "direction"] = "queried"
    heap_refresh: Literal["end", "before_second_fetch"] = "end"
    guard: float = 1e-10
    damping: float = 0.0
    first_scale: Literal["one", "inverse_norm"] = "one"
    l2: float = 0.0
    ridge: float = 1e-3
    grad_scale: Literal["sum", "mean"] = "sum"
    classes: int = 1
    layout: Literal["per_class", "shared"] = "per_class"
    support: Literal["heap", "all"] = "heap"
    stop: StopRule = field(default_factory=StopRule)

    def with_(self, **kw) -> TrainSpec:
        return replace(self, **kw)


@dataclass
class Batch:
    """Rows of one minibatch: row offsets, ids and values of their entries, labels.

    Rows in which every feature is active may come as a matrix (``of_matrix``). A minibatch that is
    stepped on many times may carry ``products``, X'X and X'y over its sorted
    features: gradients of the squared loss then need no pass over the rows.
    """

    offsets: np.ndarray
    ids: np.ndarray
    values: np.ndarray
    labels: np.ndarray
    products: tuple[np.ndarray, np.ndarray] | None = None
    matrix: np.ndarray | None = None

    def __post_init__(self):
        if not np.isfinite(self.values).all() or not np.isfinite(self.labels).all():
            raise ValueError("values and labels must be finite")

    @cached_property
    def rows(self) -> np.ndarray:
        """The row of each entry."""
        return np.repeat(np.arange(len(self.labels)), np.diff(self.offsets))

    @classmethod
    def of_matrix(cls, matrix: np.ndarray, labels: np.ndarray, products: tuple[np.ndarray, np.ndarray] | None = None) -> Batch:
        """Dense rows of the features 0, 1, 2, ..."""
        n, p = matrix.shape
        ids = np.arange(p, dtype=np.int64)
        made = cls(np.arange(n + 1) * p, np.empty(0, np.int64), matrix, labels, products, matrix)
        made.active = ids, np.empty(0, np.int64)
        return made

    def margins(self, w: np.ndarray) -> np.ndarray:
        """Rows x classes, from weights of the active features x classes."""
        if self.matrix is not None:
            return self.matrix @ w
        return self._sums(self.rows, w, self.active[1], len(self.labels))

    def moments(self, left: np.ndarray) -> np.ndarray:
        """Active features x classes: sums of values times numbers of the rows."""
        if self.matrix is not None:
            return self.matrix.T @ left
        ids, at = self.active
        return self._sums(at, left, self.rows, len(ids))

    def _sums(self, to: np.ndarray, numbers: np.ndarray, of: np.ndarray, n: int) -> np.ndarray:
        """n x classes: where the entries go to, the sums of their values times the numbers they read."""
        out = np.empty((n, numbers.shape[1]))
        for k in range(numbers.shape[1]):
            picked = np.ascontiguousarray(numbers[:, k]).take(of)
            picked *= self.values
            out[:, k] = np.bincount(to, picked, n)
        return out

    @cached_property
    def active(self) -> tuple[np.ndarray, np.ndarray]:
        """The active features, sorted, and the place among them of each entry."""
        return np.unique(self.ids, return_inverse=True)

    def inverse(self, ridge: float) -> np.ndarray:
        """(X'X + ridge I)^-1, made once."""
        if ridge not in self._inverses:
            self._inverses[ridge] = np.linalg.inv(self.products[0] + ridge * np.eye(len(self.products[1])))
        return self._inverses[ridge]

    @cached_property
    def _inverses(self) -> dict:
        return {}

    @classmethod
    def of(cls, idx: list, val: list, labels) -> Batch:
        sizes = np.fromiter(map(len, idx), np.int64, len(idx))
        return cls(
            np.r_[0, np.cumsum(sizes)],
            np.concatenate([np.asarray(i, np.int64) for i in idx]) if len(idx) else np.empty(0, np.int64),
            np.concatenate([np.asarray(v, np.float64) for v in val]) if len(val) else np.empty(0),
            np.asarray(labels, np.float64),
        )


# ---- losses


def residuals(loss: str, margins: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, float]:
    """Derivative by margin (rows x classes), and the mean loss."""
    if loss == "squared":
        left = margins[:, 0] - labels
        return left[:, None], float(0.5 * np.mean(left**2)) if len(left) else 0.0
    if loss == "logistic":
        z = np.clip(margins[:, 0], -35, 35)
        p = 1 / (1 + np.exp(-z))
        value = np.logaddexp(0, z) - labels * z
        return (p - labels)[:, None], float(value.mean()) if len(value) else 0.0
    top = margins - margins.max(1, keepdims=True)
    p = np.exp(top)
    p /= p.sum(1, keepdims=True)
    hot = np.zeros_like(p)
    hot[np.arange(len(labels)), labels.astype(int)] = 1
    return p - hot, float(-np.log(np.maximum((p * hot).sum(1), 1e-300)).mean()) if len(labels) else 0.0


def curvature_weights(loss: str, margins: np.ndarray) -> np.ndarray:
    """Second derivative by margin, per row."""
    if loss == "squared":
        return np.ones(len(margins))
    p = 1 / (1 + np.exp(-np.clip(margins[:, 0], -35, 35)))
    return p * (1 - p)


# ---- curvature


def two_loop(g: np.ndarray, s: list[np.ndarray], r: list[np.ndarray]) -> np.ndarray:
    """The inverse-curvature product of a gradient with pairs (s, r), oldest first, on one support.

    No pair gives the gradient itself.
    """
    if not s:
        return g.copy()
    z = g.copy()
    weight = [1.0 / float(a @ b) for a, b in zip(s, r, strict=True)]
    share = [0.0] * len(s)
    for i in reversed(range(len(s))):
        share[i] = weight[i] * float(s[i] @ z)
        z -= share[i] * r[i]
    z *= float(s[-1] @ r[-1]) / float(r[-1] @ r[-1])
    for i in range(len(s)):
        z += (share[i] - weight[i] * float(r[i] @ z)) * s[i]
    return z


class Ring:
    """The last ``size`` curvature pairs as sparse vectors."""

    def __init__(self, size: int, guard: float):
        self.size, self.guard, self.pairs = size, guard, []

    def push(self, s_ids, s, r_ids, r) -> bool:
        """Keep the pair if its curvature is clearly positive."""
        keep_s, keep_r = s != 0, r != 0
        both = keep_s & keep_r if s_ids is r_ids else None
        curved = None if both is None else float(s[both] @ r[both])
        s_ids, s, r_ids, r = s_ids[keep_s], s[keep_s], r_ids[keep_r], r[keep_r]
        if not self.size or not len(s) or not len(r):
            return False
        if curved is None:
            _, i, j = np.intersect1d(s_ids, r_ids, assume_unique=True, return_indices=True)
            curved = float(s[i] @ r[j])
        size_s, size_r = float(np.linalg.norm(s)), float(np.linalg.norm(r))
        if not 1e-100 < min(size_s, size_r) <= max(size_s, size_r) < 1e100 or not curved > self.guard * size_s * size_r:
            return False
        self.pairs = [*self.pairs, (s_ids, s, r_ids, r)][-self.size :]
        return True

    def product(self, ids: np.ndarray, g: np.ndarray) -> np.ndarray:
        """The inverse-curvature product on the support ``ids`` (sorted)."""
        if not self.pairs:
            return g.copy()
        every = np.sort(np.concatenate([ids, *[x for p in self.pairs for x in (p[0], p[2])]]))
        every = every[np.r_[True, every[1:] != every[:-1]]]

        def dense(at, values):
            out = np.zeros(len(every))
            out[np.searchsorted(every, at)] = values
            return out

        z = two_loop(dense(ids, g), [dense(p[0], p[1]) for p in self.pairs], [dense(p[2], p[3]) for p in self.pairs])
        return z[np.searchsorted(every, ids)]

    @property
    def stored(self) -> int:
        return sum(len(p[1]) + len(p[3]) for p in self.pairs)


def mixed_id(k: int, ids: np.ndarray) -> np.ndarray:
    """Ids of (class, feature) for a sketch that all classes share."""
    return (ids ^ np.int64(k * 0x5851F42D4C957F2D % (1 << 62))) & np.int64((1 << 62) - 1)


# ---- one training run


class Trainer:
    """Sequential training of every method; the reference semantics of all modes."""

    def __init__(self, sketch: SketchSpec, train: TrainSpec, cells: np.ndarray | None = None, heaps: list | None = None):
        self.sketch, self.train = sketch, train
        self.k = train.classes
        self.shared = train.layout == "shared" and self.k > 1
        self.dense = train.method in ("dense_sgd", "dense_qn")
        stores = 1 if self.shared else self.k
        if self.dense:
            self.store = ExactStore(self.k)
        elif train.method == "hashed":
            self.store = CountSketch(sketch.with_(rows=1, buckets=sketch.cells), self.k, cells)
        else:
            self.store = CountSketch(sketch, stores, cells)
        self.full = self.dense or train.method == "hashed" or train.support == "all"
        self.heaps = heaps or [TopKHeap(train.k) for _ in range(stores)]
        ring = train.history if train.method in ("curvature", "dense_qn") else 0
        self.rings = [Ring(ring, train.guard) for _ in range(self.k)]
        self.t = 0
        self.log: list[tuple] = []
        self._quiet = 0
        self._seen: tuple = (None, None)

    def state(self) -> dict:
        """The state as plain arrays, for storage; sketched methods only."""
        return {
            "cells": self.store.cells, "heaps": [(h.ids, h.values) for h in self.heaps], "rings": [r.pairs for r in self.rings],
            "t": self.t, "log": self.log, "quiet": self._quiet,
        }

    @classmethod
    def restored(cls, sketch: SketchSpec, train: TrainSpec, state: dict) -> Trainer:
        out = cls(sketch, train, state["cells"], [TopKHeap(train.k, i, v) for i, v in state["heaps"]])
        for ring, pairs in zip(out.rings, state["rings"], strict=True):
            ring.pairs = pairs
        out.t, out.log, out._quiet = state["t"], state["log"], state["quiet"]
        return out

    def batch(self, offsets: np.ndarray, ids: np.ndarray, values: np.ndarray, labels: np.ndarray) -> Batch:
        """Rows as this trainer steps on them."""
        return Batch(offsets, ids, values, labels)

    def _slot(self, k: int, ids: np.ndarray) -> tuple[int, np.ndarray]:
        return (0, mixed_id(k, ids)) if self.shared else (k, ids)

    def _places(self, ids: np.ndarray):
        """Hash places of the active set, per class; computed once a step."""
        if isinstance(self.store, ExactStore):
            return [self.store.places(ids)] * self.k
        if self.shared:
            return [np_places(mixed_id(k, ids), self.store.spec) for k in range(self.k)]
        return [np_places(ids, self.store.spec)] * self.k

    def fetch(self, ids: np.ndarray, places, held: list[np.ndarray]) -> np.ndarray:
        """Weights (ids x classes): estimates where held, 0 elsewhere; all where support is full."""
        out = np.zeros((len(ids), self.k))
        for k in range(self.k):
            slot, names = self._slot(k, ids)
            out[:, k] = self.store.query(slot, names, places[k])
            if not self.full:
                out[~held[k], k] = 0.0
        return out

    def _move(self, ids: np.ndarray, places, deltas: np.ndarray) -> None:
        """Add deltas (ids x classes) to the cells."""
        for k in range(self.k):
            slot, names = self._slot(k, ids)
            self.store.add(slot, names, deltas[:, k], places[k])

    def gradient(self, batch: Batch, w: np.ndarray):
        n = len(batch.labels)
        if batch.products is not None and self.train.loss == "squared":
            square, moment = batch.products
            used = np.flatnonzero(w[:, 0])
            fitted = square[:, used] @ w[used, 0]
            loss = 0.5 * float(w[used, 0] @ (fitted[used] - 2 * moment[used]) + batch.labels @ batch.labels) / n
            g = (fitted - moment)[:, None]
            return (g / n if self.train.grad_scale == "mean" else g) + self.train.l2 * w, loss, None
        margins = batch.margins(w)
        left, loss = residuals(self.train.loss, margins, batch.labels)
        g = batch.moments(left)
        if self.train.grad_scale == "mean" and n:
            g /= n
        return g + self.train.l2 * w, loss, margins

    def newton(self, batch: Batch, g: np.ndarray, margins: np.ndarray) -> np.ndarray:
        """(X' D X + ridge I)^-1 g by the rows' own small system."""
        n, ridge = len(batch.labels), self.train.ridge
        if margins is None:
            scale = n if self.train.grad_scale == "mean" else 1
            return scale * batch.inverse(ridge * scale) @ g
        weight = curvature_weights(self.train.loss, margins)
        if self.train.grad_scale == "mean":
            weight = weight / n
        ids, at = batch.active
        n_ids = len(ids)
        if batch.matrix is not None:
            x = batch.matrix * np.sqrt(weight)[:, None]
        else:
            x = np.zeros((n, n_ids))
            np.add.at(x, (batch.rows, at), batch.values)
            x *= np.sqrt(weight)[:, None]
        if n < n_ids:
            inner = np.linalg.solve(ridge * np.eye(n) + x @ x.T, x @ g[:, 0])
            return ((g[:, 0] - x.T @ inner) / ridge)[:, None]
        return np.linalg.solve(ridge * np.eye(n_ids) + x.T @ x, g[:, 0])[:, None]

    def step(self, batch: Batch) -> bool:
        """One minibatch; False when the stop rule says that training is over."""
        train, eta = self.train, self.train.schedule.at(self.t)
        ids = batch.active[0]
        if not len(ids):
            self.t += 1
            return not self._over()
        if batch is not self._seen[0]:
            self._seen = (batch, self._places(ids))
        places = self._seen[1]
        held = [np.ones(len(ids), bool)] * self.k if self.full else [self.heaps[0 if self.shared else k].holds(self._slot(k, ids)[1]) for k in range(self.k)]
        w = self.fetch(ids, places, held)
        g, loss, margins = self.gradient(batch, w)
        if train.method == "newton":
            z = self.newton(batch, g, margins)
        else:
            z = np.stack([self.rings[k].product(ids, g[:, k]) for k in range(self.k)], 1)
            if train.first_scale == "inverse_norm" and self.rings[0].size:
                for k in range(self.k):
                    if not self.rings[k].pairs:
                        z[:, k] /= max(float(np.linalg.norm(g[:, k])), 1e-300)
        self._move(ids, places, -eta * z)
        churn = kept = 0
        if train.heap_refresh == "before_second_fetch" and not self.dense:
            churn = self._refresh(ids, places)
            held = held if self.full else [self.heaps[0 if self.shared else k].holds(self._slot(k, ids)[1]) for k in range(self.k)]
        if self.rings[0].size:
            after = self.fetch(ids, places, held)
            g2, _, _ = self.gradient(batch, after)
            moved = after - w if train.step_source == "queried" else -eta * z
            for k in range(self.k):
                kept += self.rings[k].push(ids, moved[:, k], ids, g2[:, k] - g[:, k] + train.damping * moved[:, k])
        if train.heap_refresh == "end" and not self.dense:
            churn = self._refresh(ids, places)
        norm = float(np.linalg.norm(g))
        self.t += 1
        self._quiet = self._quiet + 1 if norm < train.stop.grad_norm else 0
        cells = self.store.weights.size if self.dense else self.store.cells.size
        self.log.append((self.t - 1, loss, norm, kept, len(ids), churn, cells, sum(r.stored for r in self.rings), 0.0))
        return not self._over()

    def _over(self) -> bool:
        stop = self.train.stop
        return self._quiet >= stop.patience or stop.max_steps is not None and self.t >= stop.max_steps

    def _refresh(self, ids: np.ndarray, places) -> int:
        changed = 0
        for k in range(self.k):
            slot, names = self._slot(k, ids)
            changed += self.heaps[slot].update(names, self.store.query(slot, names, places[k]))
        return changed

    def selected(self, k: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Held ids of a class by magnitude, all read again; for dense runs the k largest weights."""
        if self.dense:
            heap = TopKHeap(self.train.k)
            heap.update(self.store.ids, self.store.weights[k])
            ids, values = heap.ids, heap.values
        else:
            heap = self.heaps[0 if self.shared else k]
            ids = heap.ids
            values = self.store.query(0 if self.shared else k, ids)
        order = np.lexsort((ids, -np.abs(values)))
        return ids[order], values[order]

    def scores(self, batch: Batch, support: str = "topk") -> np.ndarray:
        """Margins (rows x classes) with the selected features only, or with all active ones."""
        ids = batch.active[0]
        weights = np.zeros((len(ids), self.k))
        for k in range(self.k):
            slot, names = self._slot(k, ids)
            w = self.store.query(slot, names) if len(ids) else np.empty(0)
            if support == "topk":
                top, values = self.selected(k)
                w = np.where(np.isin(names, top), w, 0.0)
            weights[:, k] = w
        return batch.margins(weights)
