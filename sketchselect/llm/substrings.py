"""Removal of repeated byte strings by longest-previous-factor arrays over suffix order.

A byte goes if a string of ``length`` bytes around it also starts in a document with a
smaller id. Every string of that length (a window) must meet its equals in other documents
without shuffling a row for each position:

1. A window's least hashed ``GRAM``-byte piece is its minimiser. Consecutive windows with
   one minimiser form a run; equal windows always have equal minimisers. Documents lie in
   hash buckets of a bounded size, and each bucket sends its set of minimisers, packed.
   Minimisers that only one document has are dropped there: no window of them can repeat.
2. For the others the buckets send the bytes of the runs, each different string once with
   its smallest doc_id, to the place of the minimiser. There the suffixes of these strings are put
   in order and get their longest previous factors: the nearest suffixes before and behind in
   that order which belong to a smaller document (previous and next smaller positions) are
   the earlier texts that agree with it longest, and the larger of the two common prefixes is its
   factor. A factor of ``length`` bytes or more is a later copy.
3. Which windows have such a factor goes back to the bucket, and they are cut out. Copies within a
   bucket's own string are later where their document is not the smallest that holds it.

Buckets see the text three times; the plan shuffles it once and reuses that exchange. Rows
between buckets and places are one for each pair that has anything to say, so buckets and
places grow with the table up to ``BUCKET_BYTES`` to keep these rows few and full.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sketchselect.llm.common import text_or_empty

GRAM = 16
#: Text of a bucket, least and most, places for each bucket, and bytes of a piece of a bucket
#: that is looked at in one step.
LEAST_BYTES, BUCKET_BYTES = 2 << 20, 16 << 20
PLACES = 3
PIECE = 2 << 20
#: Windows that are hashed or put in order, and runs whose windows are looked up, in one step.
WINDOWS, RUNS = 1 << 17, 1 << 14
#: Multipliers of the hash; odd numbers with well-spread bits.
MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xD6E8FEB86659FD93))
LAST = np.iinfo(np.int64).max


def eights(data: np.ndarray, kind: str = "<u8") -> np.ndarray:
    """The 8-byte word that starts at each position of a byte array."""
    return np.ndarray((len(data) - 7,), kind, data.tobytes(), strides=(1,)).astype(np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(32))
    x *= MIX[2]
    x ^= x >> np.uint64(29)
    return x


def minimisers(data: np.ndarray, length: int) -> np.ndarray:
    """The least hash of the pieces of the window that starts at each position."""
    words = eights(data)
    low = mixed(words[:-8] * MIX[0] + words[8:] * MIX[1])
    width, have = length - GRAM + 1, 1
    while 2 * have <= width:
        low = np.minimum(low[:-have], low[have:])
        have *= 2
    if have < width:
        low = np.minimum(low[: have - width], low[width - have :])
    return low


def pieces(docs: list[bytes], length: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(bytes, document of each, offset in it of each start) of joined documents, in bounded steps.

    Windows across documents are included and must be left out by the caller; documents
    longer than a step continue with the overlap that keeps every window.
    """
    parts, owner, offset, size = [], [], [], 0

    def out():
        return (
            np.frombuffer(b"".join(parts), np.uint8),
            np.repeat(np.array(owner), list(map(len, parts))),
            np.concatenate([np.arange(o, o + len(p)) for o, p in zip(offset, parts, strict=True)]),
        )

    for i, doc in enumerate(docs):
        if len(doc) < length:
            continue
        for at in range(0, len(doc) - length + 1, PIECE):
            part = doc[at : at + PIECE + length - 1]
            if size and size + len(part) > PIECE:
                yield out()
                parts, owner, offset, size = [], [], [], 0
            parts.append(part)
            owner.append(i)
            offset.append(at)
            size += len(part)
    if size:
        yield out()


def window_runs(docs: list[bytes], length: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(bytes, hash, document, offset, first, windows) per step: runs of windows by minimiser."""
    for data, owner, offset in pieces(docs, length):
        low = minimisers(data, length)
        n = len(low)
        inside = offset[:n] + (length - 1) == offset[length - 1 :]
        inside &= owner[:n] == owner[length - 1 :]
        new = np.r_[True, (low[1:] != low[:-1]) | (owner[1:n] != owner[: n - 1]) | (inside[1:] != inside[:-1])]
        first = np.flatnonzero(new)
        count = np.diff(np.r_[first, n])
        good = inside[first]
        first, count = first[good], count[good]
        yield data, low[first], owner[first], offset[first], first, count


def pack(values: np.ndarray) -> bytes:
    """Sorted or clustered 64-bit numbers: differences, byte planes, zstandard."""
    step = np.diff(values.view(np.int64), prepend=np.int64(0))
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(step.view(np.uint8).reshape(-1, 8).T).tobytes())


def unpack(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).reshape(-1).view(np.int64))


def dealt(hashes: np.ndarray, places: int) -> np.ndarray:
    return (mixed(hashes) % np.uint64(places)).astype(np.int64)


def grouped(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, list[pa.RecordBatch]]]:
    """Rows sorted by their first column, as (value, slices)."""
    now, kept = None, []
    for batch in batches:
        keys = batch.column(0).to_numpy(zero_copy_only=False)
        if not len(keys):
            continue
        edge = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        for a, z in zip(edge, np.r_[edge[1:], len(keys)], strict=True):
            if keys[a] != now and kept:
                yield now, kept
                kept = []
            now = keys[a]
            kept.append(batch.slice(a, z - a))
    if kept:
        yield now, kept


def texts(parts: Iterable) -> tuple[np.ndarray, list[bytes]]:
    """ids and texts of (bucket, doc_id, data) batches, in order of doc_id then text."""
    rows = sorted(
        ((LAST if d is None else d), t) for p in parts for d, t in zip(p.column(1).to_pylist(), p.column(2).to_pylist(), strict=True)
    )
    return np.array([d for d, _ in rows], np.int64), [t for _, t in rows]


def spread(order: np.ndarray, places: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(place, members of it in ``order``) for each place."""
    if not len(order):
        return
    by = order[np.argsort(places[order], kind="stable")]
    found = places[by]
    edge = np.flatnonzero(np.r_[True, found[1:] != found[:-1]])
    for a, z in zip(edge, np.r_[edge[1:], len(found)], strict=True):
        yield int(found[a]), by[a:z]


def run_strings(docs: list[bytes], ids: np.ndarray, wanted: np.ndarray, length: int):
    """Different strings of the runs with a wanted minimiser, and where each run is.

    Returns (strings, hash of each, least id of each), (string, document, offset, windows) of runs.
    """
    index: dict[bytes, int] = {}
    hashes, least, where = [], [], array("q")
    wanted = np.sort(wanted)
    for data, low, owner, offset, first, count in window_runs(docs, length):
        hit = wanted[np.minimum(np.searchsorted(wanted, low), len(wanted) - 1)] == low
        raw = data.tobytes()
        for h, o, f, a, c in zip(low[hit], owner[hit].tolist(), offset[hit].tolist(), first[hit].tolist(), count[hit].tolist(), strict=True):
            i = index.setdefault(raw[a : a + c + length - 1], len(index))
            if i == len(hashes):
                hashes.append(h)
                least.append(ids[o])  # documents come in order of id
            where.extend((i, o, f, c))
    return (list(index), np.array(hashes, np.uint64), np.array(least, np.int64)), np.array(where, np.int64).reshape(-1, 4)


def smaller_before(values: np.ndarray, common: np.ndarray, least: int) -> np.ndarray:
    """Common prefix of each suffix with the nearest one before it whose value is smaller; 0 under ``least``.

    ``common[r]`` is the common prefix of the suffixes of ranks r - 1 and r. All suffixes look at once:
    one that meets no smaller value jumps to where the suffix that it met has got to, since none
    between them is smaller either, and keeps the least common prefix on its way.
    """
    at, low = np.arange(len(values)) - 1, common.copy()
    low[:1] = 0
    live = np.flatnonzero(low >= least)
    low[low < least] = 0
    while len(live):
        live = live[values[at[live]] >= values[live]]
        met = at[live]
        low[live] = np.minimum(low[live], low[met])
        at[live] = at[met]
        live = live[low[live] > 0]
    return low


def factors(data: np.ndarray, sizes: np.ndarray, ids: np.ndarray, length: int, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """Longest previous factors at the windows of strings that lie one after the other in ``data``.

    For every start with ``length`` bytes left in its string: how many bytes from it, up to
    ``reach`` and the string's end, also begin a suffix of a string with a smaller id; 0 where
    under ``length``. A longer repeat goes on in the factors of the next starts.
    Also returned: where the windows of each string begin.
    """
    start = np.cumsum(sizes) - sizes
    count = sizes - length + 1
    first = np.cumsum(count) - count
    every = np.repeat(start - first, count)
    every += np.arange(len(every))
    out = np.zeros(len(every), np.int32)
    # a window whose hash is alone has no equal; the suffixes of the others are put in order
    padded = np.concatenate([data, np.zeros(reach + 8, np.uint8)])
    words = np.ndarray((len(padded) - 7,), "<u8", padded.tobytes(), strides=(1,))
    hashed = np.zeros(len(every), np.uint64)
    for at in range(0, len(every), WINDOWS):
        part = hashed[at : at + WINDOWS]
        for shift in [*range(0, length - 8, 8), length - 8]:
            part ^= words[every[at : at + WINDOWS] + shift]
            part *= MIX[0]
            part ^= part >> np.uint64(31)
    order = np.argsort(hashed)
    hashed = hashed[order]
    same = hashed[1:] == hashed[:-1]
    del hashed, words
    alike = np.r_[False, same] | np.r_[same, False] if len(order) else np.zeros(0, bool)
    order, fresh = order[alike], np.flatnonzero(~np.r_[False, same][alike]) if len(order) else order
    # only windows of one hash can agree over their length, so groups of hashes are ordered by themselves
    edge = np.unique(np.r_[fresh[np.searchsorted(fresh, np.arange(0, len(order), WINDOWS), side="right") - 1], len(order)])
    for a, z in zip(edge[:-1], edge[1:], strict=True):
        live = np.sort(order[a:z])
        string = np.searchsorted(first, live, side="right") - 1
        left = np.minimum(sizes[string] + start[string] - every[live], reach)
        suffixes = np.lib.stride_tricks.sliding_window_view(padded, reach)[every[live]]
        for n in np.unique(left[left < reach]):
            suffixes[left == n, n:] = 0
        by = np.argsort(suffixes.view(f"S{reach}").ravel())
        live, left, owner, suffixes = live[by], left[by], ids[string[by]], suffixes[by]
        differ = suffixes[1:] != suffixes[:-1]
        common = np.zeros(len(live), np.int32)
        common[1:] = np.where(differ.any(1), differ.argmax(1), reach)
        common[1:] = np.minimum(common[1:], np.minimum(left[1:], left[:-1]))
        before = smaller_before(owner, common, length)
        behind = smaller_before(owner[::-1], np.r_[np.int32(0), common[:0:-1]], length)[::-1]
        out[live] = np.maximum(before, behind)
    return out, first


def spans_of(owner: np.ndarray, start: np.ndarray, length: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Windows to cut, by document, as maximal byte ranges."""
    order = np.lexsort((start, owner))
    owner, start = owner[order], start[order]
    out = []
    edge = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]]) if len(owner) else []
    for a, z in zip(edge, np.r_[edge[1:], len(owner)].astype(int) if len(owner) else [], strict=True):
        s = start[a:z]
        gap = np.flatnonzero(np.r_[True, s[1:] > s[:-1] + length])
        last = np.r_[gap[1:] - 1, len(s) - 1]
        out.append((int(owner[a]), list(zip(s[gap].tolist(), (s[last] + length).tolist(), strict=True))))
    return out


def remove_repeats(docs: DataFrame, length: int = 50, bucket_bytes: int | None = None) -> DataFrame:
    """doc_id, n_bytes, spans (array of start, end), kept (binary) for every row of ``docs``.

    Texts are UTF-8 bytes, null is empty. Rows with one doc_id are never earlier than each
    other; a null doc_id is later than all others. An empty table gives an empty result. Buckets
    are dealt by id and text, so rows that repeat an id or lack one spread as others do.
    """
    if length < GRAM + 8:
        raise ValueError(f"length must be at least {GRAM + 8}")
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if bucket_bytes is None:
        bucket_bytes = min(BUCKET_BYTES, max(LEAST_BYTES, total // (4 * docs.sparkSession.sparkContext.defaultParallelism)))
    buckets = max(1, -(-total // bucket_bytes))
    places = buckets * PLACES
    # a run of windows with one minimiser is no longer than this, unless its pieces repeat
    reach = 2 * length - GRAM
    text = docs.select(
        F.pmod(F.xxhash64("doc_id", "text", F.lit(3)), F.lit(buckets)).alias("bucket"), "doc_id", text_or_empty().cast("binary").alias("data")
    ).repartition("bucket")

    def send_minimisers(batches):
        for bucket, parts in grouped(batches):
            ids, docs_ = texts(parts)
            seen, owners = [np.empty(0, np.uint64)], [np.empty(0, np.int64)]
            for _, low, owner, *_ in window_runs(docs_, length):
                seen.append(low)
                owners.append(ids[owner])
            pairs_h, pairs_d = np.concatenate(seen), np.concatenate(owners)
            order = np.lexsort((pairs_d, pairs_h))
            h, d = pairs_h[order], pairs_d[order]
            if not len(h):
                continue
            edge = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            many = d[edge] != d[np.r_[edge[1:], len(h)] - 1]
            h = h[edge]
            place = dealt(h, places)
            rows = [(p, bucket, pack(h[m[~many[m]]]) if (~many[m]).any() else None, pack(h[m[many[m]]]) if many[m].any() else None) for p, m in spread(np.arange(len(h)), place)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)],
                names=["place", "bucket", "one", "many"],
            )

    def pick_shared(batches):
        for _, parts in grouped(batches):
            hashes, buckets, many = [], [], []
            for p in parts:
                for b, one, more in zip(*(p.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                    for data, flag in ((one, False), (more, True)):
                        if data is not None:
                            h = unpack(data).view(np.uint64)
                            hashes.append(h)
                            buckets.append(np.full(len(h), b))
                            many.append(np.full(len(h), flag))
            h, b, f = np.concatenate(hashes), np.concatenate(buckets), np.concatenate(many)
            order = np.argsort(h, kind="stable")
            h, b, f = h[order], b[order], f[order]
            edge = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            size = np.diff(np.r_[edge, len(h)])
            keep = np.repeat((size > 1) | f[edge], size)
            h, b = h[keep], b[keep]
            rows = [(k, pack(h[m])) for k, m in spread(np.arange(len(h)), b)]
            if rows:
                yield pa.RecordBatch.from_arrays(
                    [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["bucket", "wanted"]
                )

    def wanted_of(table: pa.Table) -> np.ndarray:
        got = [unpack(x.as_py()) for x in table.column("wanted") if x.is_valid]
        return np.concatenate(got).view(np.uint64) if got else np.empty(0, np.uint64)

    sent_shape = pa.schema([("place", pa.int64()), ("bucket", pa.int64()), ("which", pa.binary()), ("ids", pa.binary()), ("sizes", pa.binary()), ("data", pa.binary())])

    def send_strings(left: pa.Table, right: pa.Table) -> pa.Table:
        if not right.num_rows or not left.num_rows:
            return sent_shape.empty_table()
        ids, docs_ = texts([left])
        (strings, hashes, least), _ = run_strings(docs_, ids, wanted_of(right), length)
        bucket = left.column(0)[0].as_py()
        press = zstandard.ZstdCompressor(level=3)
        rows = []
        for p, m in spread(np.arange(len(strings)), dealt(hashes, places)):
            own = [strings[i] for i in m]
            rows.append((p, bucket, pack(m), pack(least[m]), pack(np.fromiter(map(len, own), np.int64, len(own))), press.compress(b"".join(own))))
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), sent_shape, strict=True)], schema=sent_shape) if rows else sent_shape.empty_table()

    def resolve(batches):
        for _, parts in grouped(batches):
            raw, sizes, ids, sources = [], [], [], []
            for p in parts:
                for b, which, least, size, data in zip(*(p.column(i).to_pylist() for i in range(1, 6)), strict=True):
                    raw.append(zstandard.ZstdDecompressor().decompress(data))
                    sizes.append(unpack(size))
                    ids.append(unpack(least))
                    sources.append((b, unpack(which)))
            lengths = np.concatenate(sizes)
            found, first = factors(np.frombuffer(b"".join(raw), np.uint8), lengths, np.concatenate(ids), length, reach)
            count = lengths - length + 1
            late = found >= length
            # only strings with a later copy in them have anything to tell
            told = np.logical_or.reduceat(late, first)
            rows, at = [], 0
            for b, which in sources:
                own = np.flatnonzero(told[at : at + len(which)])
                if len(own):
                    every = np.repeat(told[at : at + len(which)], count[at : at + len(which)])
                    bits = np.packbits(late[first[at] : first[at] + len(every)][every])
                    rows.append((b, pack(which[own]), pack(count[at + own]), zstandard.ZstdCompressor(level=1).compress(bits.tobytes())))
                at += len(which)
            if not rows:
                continue
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), *[pa.binary()] * 3), strict=True)],
                names=["bucket", "which", "sizes", "late"],
            )

    cut_shape = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), ("kept", pa.binary())])

    def cut(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return cut_shape.empty_table()
        ids, docs_ = texts([left])
        gone: dict[int, list] = {}
        if right.num_rows:
            (strings, _, first_id), where = run_strings(docs_, ids, wanted_of(right), length)
            begin, parts, at = np.full(len(strings), -1, np.int64), [np.empty(0, np.uint8)], 0
            for which, sizes, late in zip(*(right.column(c).to_pylist() for c in ("which", "sizes", "late")), strict=True):
                if which is not None:
                    sizes = unpack(sizes)
                    begin[unpack(which)] = at + np.cumsum(sizes) - sizes
                    bits = np.frombuffer(zstandard.ZstdDecompressor().decompress(late), np.uint8)
                    parts.append(np.unpackbits(bits, count=int(sizes.sum())))
                    at += len(parts[-1])
            told = np.concatenate(parts)
            owners, starts = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
            for run in range(0, len(where), RUNS):
                string, owner, offset, count = where[run : run + RUNS].T
                step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
                owner = np.repeat(owner, count)
                string = np.repeat(string, count)
                later = first_id[string] < ids[owner]
                known = np.flatnonzero(begin[string] >= 0)
                later[known] |= told[begin[string[known]] + step[known]] > 0
                owners.append(owner[later])
                starts.append((np.repeat(offset, count) + step)[later])
            gone = dict(spans_of(np.concatenate(owners), np.concatenate(starts), length))
        kept = []
        for i, doc in enumerate(docs_):
            at, out = 0, []
            for a, z in gone.get(i, ()):
                out.append(doc[at:a])
                at = z
            kept.append(b"".join([*out, doc[at:]]))
        return pa.Table.from_arrays(
            [
                pa.array([None if d == LAST else d for d in ids.tolist()], pa.int64()),
                pa.array(list(map(len, docs_)), pa.int64()),
                pa.array([[{"start": a, "end": z} for a, z in gone.get(i, ())] for i in range(len(docs_))], cut_shape.field("spans").type),
                pa.array(kept, pa.binary()),
            ],
            schema=cut_shape,
        )

    minimal = text.sortWithinPartitions("bucket").mapInArrow(send_minimisers, "place long, bucket long, one binary, many binary")
    shared = minimal.repartition("place").sortWithinPartitions("place").mapInArrow(pick_shared, "bucket long, wanted binary")
    sent = text.groupBy("bucket").cogroup(shared.groupBy("bucket")).applyInArrow(
        send_strings, "place long, bucket long, which binary, ids binary, sizes binary, data binary"
    )
    found = sent.repartition("place").sortWithinPartitions("place").mapInArrow(resolve, "bucket long, which binary, sizes binary, late binary")
    nothing = F.lit(None).cast("binary")
    back = found.withColumn("wanted", nothing).unionByName(
        shared.select("bucket", nothing.alias("which"), nothing.alias("sizes"), nothing.alias("late"), "wanted")
    )
    return text.groupBy("bucket").cogroup(back.groupBy("bucket")).applyInArrow(
        cut, "doc_id long, n_bytes long, spans array<struct<start: long, end: long>>, kept binary"
    )
