"""Benchmark decontamination by SimHash of item-sized windows.

Every benchmark item has the SimHash of its weighted word shingles (weight: how often a
shingle occurs). A document is read in windows of each item's number of words. Window
fingerprints come from running sums of shingle bits, so overlapping windows cost no
rehashing. Item fingerprints lie in a multi-index: the 64 bits are cut into ``BLOCKS`` blocks,
one table per block; any fingerprint within the radius of an item is within radius // BLOCKS
bits of it in at least one block, so looking up each block with all such flips finds every
item within the radius. Short windows of the similarity asked may lie further apart, so items that share enough shingles
with a window are candidates too, by the lists of items of each shingle. All candidates are
verified by the exact weighted similarity of shingles, sum of smaller weights / sum of
larger weights. A document of fewer words than an item is one window, itself.

A window that shares no shingle with an item has similarity 0, so only windows that hold
enough shingles of items of their length for the similarity asked are hashed: for n shingles each,
similarity s needs 2 s n / (1 + s) common ones. Shingles that hold a word, or two words in a
row, that no item holds are unknown without being hashed.
"""

from __future__ import annotations

import math
import uuid
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from sketchselect.llm import shingles

SIZE = 5
SIMILARITY = 0.8
#: Differing bits within which the multi-index guarantees to find an item.
RADIUS = 16
#: Tables of the multi-index.
BLOCKS = 6
#: Benchmark bytes that go to the executors at a time; a larger benchmark goes in blocks.
BLOCK_BYTES = 16 << 20
#: Windows that are looked up at a time.
STEP = 1024
#: Distinct words of a block of the benchmark up to which its words rule out shingles before they are hashed.
VOCABULARY = 500_000


def window_codes(found: np.ndarray, starts: np.ndarray, n: int) -> Iterator[tuple[int, int]]:
    """(start, SimHash of the n shingles from it), by running sums over stretches of starts."""
    stretch = np.cumsum(np.r_[True, np.diff(starts) > n]) * (1 << 32) + starts // shingles.STEP
    for own in np.split(starts, np.flatnonzero(np.diff(stretch)) + 1):
        rows = shingles.bits(found[own[0] : own[-1] + n])
        sums = np.concatenate([np.zeros((1, 64), np.int32), np.cumsum(rows, axis=0, dtype=np.int32)])
        over = 2 * (sums[own - own[0] + n] - sums[own - own[0]]) > n
        yield from zip(own.tolist(), np.packbits(over, axis=1).view(">u8").ravel().tolist(), strict=True)


class Block:
    """One table of the multi-index: the items of one length by the value of some of their bits."""

    def __init__(self, codes: np.ndarray, members: np.ndarray, shift: int, width: int, reach: int):
        self.shift, self.mask, self.reach = np.uint64(shift), np.uint64((1 << width) - 1), reach
        own = codes[members] >> self.shift & self.mask
        order = np.argsort(own, kind="stable")
        self.members, (self.values, first) = members[order], np.unique(own[order], return_index=True)
        self.ends = np.r_[first, len(own)]
        flips = [sum(1 << b for b in bits) for n in range(reach + 1) for bits in combinations(range(width), n)]
        self.flips = np.array(flips, np.uint64)

    def near(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of a code, item) for all items whose value here is within ``reach`` bits of the code's."""
        own = codes >> self.shift & self.mask
        if len(self.values) <= len(self.flips):  # fewer values than flips: they are tried instead
            at, slot = np.nonzero(np.bitwise_count(own[:, None] ^ self.values[None, :]) <= self.reach)
        else:
            probes = own[:, None] ^ self.flips[None, :]
            slot = np.minimum(np.searchsorted(self.values, probes), len(self.values) - 1)
            at, flip = np.nonzero(self.values[slot] == probes)
            slot = slot[at, flip]
        count = self.ends[slot + 1] - self.ends[slot]
        step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        return np.repeat(at, count), self.members[np.repeat(self.ends[slot], count) + step]


class Index:
    """The items of one block of the benchmark, ready for lookups; arrays only, of bounded size."""

    def __init__(self, items: list[tuple[int, str]], size: int, similarity: float, radius: int):
        self.size, self.similarity, self.radius = size, similarity, radius
        self.ids, self.lengths, self.keys, self.counts, codes = [], [], [], [], []
        self.vocabulary: dict[bytes, int] = {}
        pairs = [np.empty(0, np.int64)]
        for item, text in items:
            words = shingles.words(text)
            found = shingles.hashes(words, size)
            if not len(found):
                continue  # an item without words matches nothing
            self.ids.append(item)
            self.lengths.append(len(words))
            keys, counts = np.unique(found, return_counts=True)
            self.keys.append(keys)
            self.counts.append(counts)
            codes.append(shingles.simhash(found))
            own = np.array([self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words], np.int64)
            pairs.append(own[:-1] << 32 | own[1:])
        self.pairs = np.unique(np.concatenate(pairs))
        if len(self.vocabulary) > VOCABULARY:
            self.vocabulary = {}
        self.codes = np.array(codes, np.uint64)
        every = np.concatenate([*self.keys, np.empty(0, np.uint64)])
        self.known = np.unique(every)
        held = np.searchsorted(self.known, every)
        owner = np.repeat(np.arange(len(self.keys)), [len(k) for k in self.keys])
        # items of shingle k of known: owners[ends[k] : ends[k + 1]]
        self.owners = owner[np.argsort(held, kind="stable")]
        self.ends = np.r_[0, np.cumsum(np.bincount(held, minlength=len(self.known)))]
        by = defaultdict(list)
        for i, n in enumerate(self.lengths):
            by[n].append(i)
        self.items_of = {n: np.array(members) for n, members in by.items()}
        self.sorted_lengths = sorted(by)
        # lengths of the items of shingle k of known: spans[span_ends[k] : span_ends[k + 1]]
        place = np.searchsorted(self.sorted_lengths, np.array(self.lengths, np.int64))
        width = max(1, len(self.sorted_lengths))
        both = np.unique(held * width + place[owner]) if len(owner) else np.empty(0, np.int64)
        self.spans = both % width
        self.span_ends = np.r_[0, np.cumsum(np.bincount(both // width, minlength=len(self.known)))]
        edges = [64 * i // BLOCKS for i in range(BLOCKS + 1)]
        self.of_length = {
            n: [Block(self.codes, members, a, z - a, radius // BLOCKS) for a, z in zip(edges, edges[1:], strict=False)] for n, members in self.items_of.items()
        }

    def within(self, length: int, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of a code, item of this many words) for all items within the radius, by every block."""
        found = [block.near(codes) for block in self.of_length[length]]
        at, item = (np.concatenate(x) for x in zip(*found, strict=True))
        pairs = np.unique(at * len(self.ids) + item)
        at, item = pairs // len(self.ids), pairs % len(self.ids)
        good = np.bitwise_count(codes[at] ^ self.codes[item]) <= self.radius
        return at[good], item[good]

    def common(self, keys: np.ndarray, counts: np.ndarray, item: int) -> int:
        """Sum of the smaller weights of a window's shingles (distinct, sorted) and an item's."""
        at = np.minimum(np.searchsorted(self.keys[item], keys), len(self.keys[item]) - 1)
        same = self.keys[item][at] == keys
        return int(np.minimum(counts[same], self.counts[item][at[same]]).sum())

    def known_in(self, words: list[bytes], size: int) -> tuple[np.ndarray, np.ndarray]:
        """(position, index in ``known``) of the shingles of a text that the benchmark holds."""
        n = len(words) - size + 1
        if not self.vocabulary or n < 2 or size < 2:
            found = shingles.hashes(words, size)
            may = np.arange(len(found))
        else:
            own = np.fromiter(map(self.vocabulary.get, words, repeat(-1)), np.int64, len(words))
            near = np.flatnonzero((own[:-1] >= 0) & (own[1:] >= 0))
            pair = own[near] << 32 | own[near + 1]
            at = np.minimum(np.searchsorted(self.pairs, pair), len(self.pairs) - 1)
            good = near[self.pairs[at] == pair] if len(self.pairs) else near[:0]
            # a shingle needs size - 1 known pairs in a row
            may = good[: max(0, len(good) - size + 2)]
            may = may[good[size - 2 :][: len(may)] - may == size - 2]
            found = np.array([shingles.digest(words[i : i + size]) for i in may.tolist()], np.uint64)
        if not len(found):
            return may[:0], np.empty(0, np.int64)
        at = np.minimum(np.searchsorted(self.known, found), len(self.known) - 1)
        same = self.known[at] == found
        return may[same], at[same]

    def sharing(self, found: np.ndarray, least: int) -> np.ndarray:
        """Items of which at least this many of the given shingles, repeats included, are known."""
        at = np.minimum(np.searchsorted(self.known, found), len(self.known) - 1)
        at = at[self.known[at] == found]
        lists = [self.owners[self.ends[k] : self.ends[k + 1]] for k in at.tolist()]
        owners, counts = np.unique(np.concatenate([*lists, np.empty(0, np.int64)]), return_counts=True)
        return owners[counts >= least].astype(np.int64)

    def windows_sharing(self, found: np.ndarray, starts: np.ndarray, n: int, length: int, need: int) -> Iterator[tuple[int, int]]:
        """(start, item of this many words) where at least ``need`` shingles of the window are the item's."""
        for own in np.split(starts, np.flatnonzero(np.diff(starts) > n) + 1):
            stretch = found[own[0] : own[-1] + n]
            for i in np.intersect1d(self.sharing(stretch, need), self.items_of[length]).tolist():
                sums = np.r_[0, np.cumsum(np.isin(stretch, self.keys[i]))]
                enough = sums[own - own[0] + n] - sums[own - own[0]] >= need
                yield from ((start, i) for start in own[enough].tolist())

    def longer(self, words: list[bytes]) -> Iterator[tuple[int, float]]:
        """(item, similarity) of the items of more words that the whole text matches."""
        m = len(words) - self.size + 1
        if m < 1:
            return  # fewer words than a shingle, so none in common with a longer item
        lengths = self.sorted_lengths[bisect_right(self.sorted_lengths, len(words)) :]
        if not lengths or self.similarity * (lengths[0] - self.size + 1) > m + 1e-9:
            return
        found = self.known[self.known_in(words, self.size)[1]]  # others are in no item
        keys, counts = np.unique(found, return_counts=True)
        for i in self.sharing(found, math.ceil(self.similarity * m)).tolist():
            n = self.lengths[i] - self.size + 1
            if n > m and self.similarity * n <= m + 1e-9:
                common = self.common(keys, counts, i)
                if common / (n + m - common) >= self.similarity:
                    yield i, common / (n + m - common)

    def search(self, text: str | None) -> list[tuple[int, int, int, float]]:
        """(item, first word, words, similarity) of the best window of each matching item."""
        words = shingles.words(text)
        if not words or not len(self.ids):
            return []
        best: dict[int, tuple[float, int]] = {}
        places: dict[int, tuple] = {}
        every: dict[int, np.ndarray] = {}
        for which, length in enumerate(self.sorted_lengths):
            if length > len(words):
                break
            size = min(self.size, length)
            if size not in places:
                position, k = self.known_in(words, size)
                count = self.span_ends[k + 1] - self.span_ends[k]
                step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
                places[size] = np.repeat(position, count), self.spans[np.repeat(self.span_ends[k], count) + step]
            position, span = places[size]
            n = length - size + 1
            need = math.ceil(2 * self.similarity * n / (1 + self.similarity) - 1e-9)
            shared = position[span == which] if len(position) >= need else position[:0]
            if len(shared) < need:
                continue
            counts = np.bincount(shared + 1, minlength=len(words) - size + 2).cumsum()
            starts = np.flatnonzero(counts[n:] - counts[:-n] >= need)
            if not len(starts):
                continue
            if size not in every:
                every[size] = shingles.hashes(words, size)
            found = every[size]
            near = defaultdict(set)
            coded = list(window_codes(found, starts, n))
            for at in range(0, len(coded), STEP):
                part = coded[at : at + STEP]
                for j, i in zip(*self.within(length, np.array([c for _, c in part], np.uint64)), strict=True):
                    near[part[j][0]].add(int(i))
            for start, i in self.windows_sharing(found, starts, n, length, need):
                near[start].add(i)
            for start in starts.tolist():
                if not near[start]:
                    continue
                keys, counts = np.unique(found[start : start + n], return_counts=True)
                for i in near[start]:
                    common = self.common(keys, counts, i)
                    similar = common / (2 * n - common)
                    if similar >= self.similarity and similar > best.get(i, (0.0, 0))[0]:
                        best[i] = (similar, start)
        hits = [(self.ids[i], start, self.lengths[i], similar) for i, (similar, start) in best.items()]
        return hits + [(self.ids[i], 0, len(words), similar) for i, similar in self.longer(words)]


def item_blocks(benchmark: DataFrame, block_bytes: int):
    """The benchmark's distinct items in blocks of bounded size, one block in memory at a time."""
    block, size = [], 0
    for row in benchmark.select("item_id", "text").filter("text is not null").distinct().orderBy("item_id", "text").toLocalIterator():
        own = len(row["text"].encode())
        if block and size + own > block_bytes:
            yield block
            block, size = [], 0
        block.append((row["item_id"], row["text"]))
        size += own
    if block:
        yield block


#: The index that this worker built last, by the name of its block.
_built: dict[str, Index] = {}


def index_of(name: str, sent, size: int, similarity: float, radius: int) -> Index:
    """The index of a broadcast block, built once per worker process."""
    if name not in _built:
        _built.clear()
        _built[name] = Index(sent.value, size, similarity, radius)
    return _built[name]


def sent_blocks(benchmark: DataFrame, block_bytes: int):
    for block in item_blocks(benchmark, block_bytes):
        yield uuid.uuid4().hex, benchmark.sparkSession.sparkContext.broadcast(block)


def leaks(
    docs: DataFrame,
    benchmark: DataFrame,
    size: int = SIZE,
    similarity: float = SIMILARITY,
    radius: int = RADIUS,
    block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """One row per document and benchmark item that it holds a window of.

    doc_id, item_id, first_word, n_words, similarity (of the best window, the first on ties).
    Null and blank texts on either side match nothing; an item of fewer words than a shingle
    is one shingle; repeated rows give repeated results; doc_id may be null or repeat. An empty table
    on either side gives an empty result. Each block of the benchmark is matched against all documents.
    """
    schema = "doc_id long, item_id long, first_word long, n_words long, similarity double"
    shape = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("first_word", pa.int64()), ("n_words", pa.int64()), ("similarity", pa.float64())])
    out = None
    for name, sent in sent_blocks(benchmark, block_bytes):

        def run(batches, name=name, sent=sent):
            index = index_of(name, sent, size, similarity, radius)
            for batch in batches:
                rows = [
                    (doc, *hit)
                    for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)
                    for hit in index.search(text)
                ]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), shape, strict=True)], schema=shape)

        found = docs.select("doc_id", "text").mapInArrow(run, schema)
        out = found if out is None else out.unionByName(found)
    return docs.sparkSession.createDataFrame([], schema) if out is None else out


def decontaminated(
    docs: DataFrame,
    benchmark: DataFrame,
    size: int = SIZE,
    similarity: float = SIMILARITY,
    radius: int = RADIUS,
    block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """The documents, all columns, without those that hold a window of a benchmark item.

    Every row is judged by its own text, where it lies: nothing is shuffled, and rows that share a
    doc_id or have none stay or go each on its own. Null and blank texts stay; so do all rows
    where the benchmark is empty. Of repeated rows all stay or all go.
    """
    at = docs.columns.index("text")
    for name, sent in sent_blocks(benchmark, block_bytes):

        def run(batches, name=name, sent=sent):
            index = index_of(name, sent, size, similarity, radius)
            for batch in batches:
                clean = pa.array([not index.search(text) for text in batch.column(at).to_pylist()], pa.bool_())
                yield batch.filter(clean)

        docs = docs.mapInArrow(run, docs.schema)
    return docs
