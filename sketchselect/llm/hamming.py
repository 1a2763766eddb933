"""Links between 64-bit fingerprints within a small Hamming radius.

Fingerprints are cut into ``radius + 2`` blocks. Two within the radius agree on at least
two blocks, so they share one of the masked patterns that keep two blocks; these patterns
are the upper nodes of the index and are what rows are dealt by. Below such a node the
fingerprints lie in Gray order, in a balanced hierarchy whose nodes hold the bits on which
all their members agree. Two nodes whose agreed bits already differ in more than
the radius are pruned together with everything below them.

A pattern with very many members is dealt again by a third block of the bits left over
(of ``radius + 1``, one must agree), which bounds what one task can get whatever the skew.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Members from which a pattern is dealt again by another block.
LARGE = 512
#: Pairs of nodes looked at in one step.
STEP = 1 << 19


def cuts(bits: list[int], parts: int) -> list[int]:
    """Masks of ``parts`` near-equal runs of the given bit positions."""
    edges = [len(bits) * i // parts for i in range(parts + 1)]
    return [sum(1 << b for b in bits[a:z]) for a, z in zip(edges, edges[1:], strict=False)]


def patterns(radius: int) -> list[tuple[int, list[int]]]:
    """Masks that keep two blocks, each with the masks of a third block of what is left."""
    if radius == 0:
        return [((1 << 64) - 1, [])]
    blocks = cuts(list(range(64)), radius + 2)
    out = []
    for pair in combinations(blocks, 2):
        mask = pair[0] | pair[1]
        rest = [b for b in range(64) if not mask >> b & 1]
        out.append((mask, [mask | m for m in cuts(rest, radius + 1)]))
    return out


def signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Position of a code in the reflected Gray sequence."""
    out = codes.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        out ^= out >> np.uint64(shift)
    return out


class Roots:
    """Union by smallest index, on arrays."""

    def __init__(self, n: int):
        self.of = np.arange(n)

    def flatten(self) -> None:
        while True:
            up = self.of[self.of]
            if (up == self.of).all():
                return
            self.of = up

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            ra, rb = self.of[a], self.of[b]
            apart = ra != rb
            if not apart.any():
                return
            a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
            np.minimum.at(self.of, np.maximum(ra, rb), np.minimum(ra, rb))
            self.flatten()


def levels(codes: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> list[tuple[np.ndarray, ...]]:
    """The hierarchy from its roots down to single fingerprints.

    Each level tiles the array: (agreed bits, their values, first child, second child or -1,
    is single).
    """
    out = []
    lo, hi = starts, stops
    while True:
        ones, any_ = np.bitwise_and.reduceat(codes, lo), np.bitwise_or.reduceat(codes, lo)
        single = hi - lo == 1
        if single.all():
            return [*out, (~(ones ^ any_), ones, lo, np.full(len(lo), -1), single)]
        width = np.where(single, 1, 2)
        first = np.cumsum(width) - width
        out.append((~(ones ^ any_), ones, first, np.where(single, -1, first + 1), single))
        mid = (lo + hi) // 2
        new_lo, new_hi = np.empty(width.sum(), lo.dtype), np.empty(width.sum(), lo.dtype)
        new_lo[first], new_hi[first] = lo, np.where(single, hi, mid)
        new_lo[first[~single] + 1], new_hi[first[~single] + 1] = mid[~single], hi[~single]
        lo, hi = new_lo, new_hi


def linked(codes: np.ndarray, starts: np.ndarray, stops: np.ndarray, radius: int) -> np.ndarray:
    """Root index of each fingerprint: those within the radius, directly or by others, share one.

    ``codes`` are in Gray order within each run [start, stop); runs tile the array.
    """
    roots = Roots(len(codes))
    tree = levels(codes, starts, stops)
    every = np.arange(len(starts))
    todo = [(0, every, every)]
    while todo:
        depth, a, b = todo.pop()
        if len(a) > STEP:
            todo += [(depth, a[:STEP], b[:STEP]), (depth, a[STEP:], b[STEP:])]
            continue
        agreed, value, first, second, single = tree[depth]
        apart = np.bitwise_count((value[a] ^ value[b]) & agreed[a] & agreed[b])
        near = apart <= radius
        a, b = a[near], b[near]
        if depth == len(tree) - 1:
            roots.join(a[a != b], b[a != b])
            continue
        own = a == b
        mine = a[own & ~single[a]]
        x, y = a[~own], b[~own]
        x2, y2 = second[x] >= 0, second[y] >= 0
        left = [first[mine], second[mine], first[mine], first[x], first[x[y2]], second[x[x2]], second[x[x2 & y2]]]
        right = [first[mine], second[mine], second[mine], first[y], second[y[y2]], first[y[x2]], second[y[x2 & y2]]]
        a, b = np.concatenate(left), np.concatenate(right)
        if len(a):
            todo.append((depth + 1, a, b))
    return roots.of


def stars(groups: np.ndarray, codes: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Indices (member, root) of the links found in groups; groups are any equal numbers."""
    order = np.lexsort((gray_rank(codes), groups))
    groups, sorted_codes = groups[order], codes[order]
    edge = np.flatnonzero(np.r_[True, groups[1:] != groups[:-1]])
    root = linked(sorted_codes, edge, np.r_[edge[1:], len(groups)], radius)
    member = np.flatnonzero(root != np.arange(len(root)))
    return order[member], order[root[member]]


def links(prints: DataFrame, radius: int) -> DataFrame:
    """Edges (a, b) that connect the ids of fingerprints within ``radius``; stars, not all pairs.

    ``prints`` has id (long) and code (long), each code once. Ids of linked codes are in one
    connected component of the edges and no others are.
    """
    kept = patterns(radius)
    shared = F.array(
        *[F.struct(F.lit(i).alias("pattern"), F.col("code").bitwiseAND(F.lit(signed(m))).alias("node")) for i, (m, _) in enumerate(kept)]
    )
    dealt = prints.select("id", "code", F.inline(shared))
    full = dealt.groupBy("pattern", "node").agg(F.count("*").alias("members")).filter("members > 1")
    live = dealt.join(full, ["pattern", "node"])
    if radius:
        third = F.lit(None)
        for i, (_, more) in enumerate(kept):
            again = F.array(*[F.struct(F.lit(j + 1).alias("part"), F.col("code").bitwiseAND(F.lit(signed(m))).alias("at")) for j, m in enumerate(more)])
            third = F.when(F.col("pattern") == i, again).otherwise(third)
        whole = F.array(F.struct(F.lit(0).alias("part"), F.col("node").alias("at")))
        live = live.select("id", "code", "pattern", F.inline(F.when(F.col("members") > LARGE, third).otherwise(whole)))
    else:
        live = live.select("id", "code", "pattern", F.lit(0).alias("part"), F.col("node").alias("at"))
    keyed = live.select("id", "code", F.xxhash64("pattern", "part", "at").alias("key")).repartition("key")

    def run(batches):
        ids, codes, keys = [], [], []
        for batch in batches:
            for into, column in zip((ids, codes, keys), batch.columns, strict=True):
                into.append(column.to_numpy(zero_copy_only=False))
        if not ids:
            return
        ids, codes, keys = np.concatenate(ids), np.concatenate(codes).astype(np.int64).view(np.uint64), np.concatenate(keys)
        a, b = stars(keys, codes, radius)
        # two keys with one hash only widen a group: every link is still checked
        edges = np.unique(np.stack([ids[a], ids[b]], 1), axis=0)
        for at in range(0, len(edges), 1 << 16):
            part = edges[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(part[:, 0]), pa.array(part[:, 1])], names=["a", "b"])

    return keyed.mapInArrow(run, "a long, b long")
