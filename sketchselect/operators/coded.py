"""The training step where all feature ids are known beforehand.

Minibatches name a feature by its place among the sorted ids of a vocabulary. Hashes are then
computed once, not in every step, and memberships and unions are marks over the vocabulary instead of sorts
and searches. Places ascend with ids, so every sum runs in the same order and every tie goes
the same way as in ``Trainer``: the numbers are equal to the last bit.
"""

from __future__ import annotations

import numpy as np

from sketchselect.functions.hashing import SketchSpec, np_places
from sketchselect.operators.kernel import Batch, CountSketch, Ring, TopKHeap, Trainer, TrainSpec, mixed_id, two_loop

#: Most ids of a vocabulary: a lane holds about 0.7 kB for each with four classes that share a sketch.
VOCABULARY = 1 << 17


class CodedHeap(TopKHeap):
    """Held names below ``size``, with a mark for each."""

    def __init__(self, k: int, size: int):
        super().__init__(k)
        self._held, self._named = np.zeros(size, bool), np.zeros(size, bool)

    def holds(self, ids: np.ndarray) -> np.ndarray:
        return self._held[ids]

    def update(self, ids: np.ndarray, values: np.ndarray) -> int:
        self._named[ids] = True
        stays = ~self._named[self.ids]
        self._named[ids] = False
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
        fresh = int((~self._held[self.ids]).sum())
        self._held[before] = False
        self._held[self.ids] = True
        return fresh


class CodedRing(Ring):
    """Curvature pairs of features below ``size``."""

    def __init__(self, size: int, guard: float, features: int):
        super().__init__(size, guard)
        self._mark, self._at = np.zeros(features, bool), np.empty(features, np.int64)

    def product(self, ids: np.ndarray, g: np.ndarray) -> np.ndarray:
        if not self.pairs:
            return g.copy()
        for some in (ids, *[x for p in self.pairs for x in (p[0], p[2])]):
            self._mark[some] = True
        every = np.flatnonzero(self._mark)
        self._mark[every] = False
        self._at[every] = np.arange(len(every))

        def dense(at, values):
            out = np.zeros(len(every))
            out[self._at[at]] = values
            return out

        z = two_loop(dense(ids, g), [dense(p[0], p[1]) for p in self.pairs], [dense(p[2], p[3]) for p in self.pairs])
        return z[self._at[ids]]


class CodedTrainer(Trainer):
    """``Trainer`` of a sketched method over minibatches of places in a vocabulary (ids ascending, no repeats)."""

    def __init__(self, sketch: SketchSpec, train: TrainSpec, vocabulary: np.ndarray):
        super().__init__(sketch, train)
        if not isinstance(self.store, CountSketch):
            raise ValueError("dense methods have no sketch to code")
        self.features = len(vocabulary)
        spec = self.store.spec
        named = np.stack([mixed_id(k, vocabulary) for k in range(self.k)]) if self.shared else vocabulary[None]
        # names of (class, feature): the places among all hashed ids, which ascend with them
        self.ids, names = np.unique(named, return_inverse=True)
        self._names = names.reshape(named.shape)
        # cells and signs (features x hash rows), of all classes or of each; those of a feature lie side by side
        hashed = [np_places(one, spec) for one in named]
        self._hashed = [(np.ascontiguousarray(b.T + spec.buckets * np.arange(spec.rows)), np.ascontiguousarray(s.T)) for b, s in hashed]
        self.heaps = [CodedHeap(train.k, len(self.ids)) for _ in self.heaps]
        self.rings = [CodedRing(r.size, r.guard, self.features) for r in self.rings]
        self._mark, self._at = np.zeros(self.features, bool), np.empty(self.features, np.int64)
        self._now, self._moved = None, False
        self._named: tuple = (None, [])

    def batch(self, offsets: np.ndarray, places: np.ndarray, values: np.ndarray, labels: np.ndarray) -> Batch:
        made = Batch(offsets, places, values, labels)
        self._mark[places] = True
        active = np.flatnonzero(self._mark)
        self._mark[active] = False
        self._at[active] = np.arange(len(active))
        made.active = active, self._at[places]
        return made

    def _slot(self, k: int, ids: np.ndarray) -> tuple[int, np.ndarray]:
        if not self.shared:
            return k, ids
        if self._named[0] is not ids:
            self._named = ids, [names.take(ids) for names in self._names]
        return 0, self._named[1][k]

    def _places(self, ids: np.ndarray):
        self._now, self._moved = None, False
        found = [(c.take(ids, 0), s.take(ids, 0)) for c, s in self._hashed]
        return found if self.shared else found * self.k

    def _read(self, places, k: int) -> np.ndarray:
        """Estimates of hash places of a class."""
        cell, sign = places
        found = self.store.cells[0 if self.shared else k].ravel().take(cell)
        found *= sign
        return self.store.estimate(list(found.T))

    def _all(self, places) -> list[np.ndarray]:
        """Estimates of all active features by class, read once until the cells move."""
        if self._now is None:
            self._now = [self._read(places[k], k) for k in range(self.k)]
        return self._now

    def fetch(self, ids: np.ndarray, places, held: list[np.ndarray]) -> np.ndarray:
        out = np.zeros((len(ids), self.k))
        for k in range(self.k):
            if self.full:
                out[:, k] = self._all(places)[k]
                continue
            at = np.flatnonzero(held[k])
            if self._moved:  # all are read anyway, for the heap
                out[at, k] = self._all(places)[k][at]
            elif len(at):
                cell, sign = places[k]
                out[at, k] = self._read((cell.take(at, 0), sign.take(at, 0)), k)
        return out

    def _move(self, ids: np.ndarray, places, deltas: np.ndarray) -> None:
        few = 8 * len(ids) < self.store.spec.buckets
        for k in range(self.k):
            cell, sign = places[k]
            cells = self.store.cells[0 if self.shared else k].reshape(-1)
            weights, cell = (sign * deltas[:, k, None]).ravel(), cell.ravel()
            if few:  # the same sums, without a pass over all buckets
                own, to = np.unique(cell, return_inverse=True)
                cells[own] += np.bincount(to, weights, len(own))
            else:
                cells += np.bincount(cell, weights, len(cells))
        self._now, self._moved = None, True

    def _refresh(self, ids: np.ndarray, places) -> int:
        changed, values = 0, self._all(places)
        for k in range(self.k):
            slot, names = self._slot(k, ids)
            changed += self.heaps[slot].update(names, values[k])
        return changed

    def selected(self, k: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Held ids, not places, by magnitude, all read again."""
        heap = self.heaps[0 if self.shared else k]
        ids = self.ids[heap.ids]
        values = self.store.query(0 if self.shared else k, ids)
        order = np.lexsort((ids, -np.abs(values)))
        return ids[order], values[order]

    def scores(self, batch: Batch, support: str = "topk") -> np.ndarray:
        ids = batch.active[0]
        weights = np.zeros((len(ids), self.k))
        for k in range(self.k if len(ids) else 0):
            cell, sign = self._hashed[k if self.shared else 0]
            weights[:, k] = self._read((cell.take(ids, 0), sign.take(ids, 0)), k)
        if support == "topk":
            for k in range(self.k):
                slot, names = self._slot(k, ids)
                weights[~self.heaps[slot].holds(names), k] = 0.0
        return batch.margins(weights)
