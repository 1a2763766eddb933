"""Near-duplicate documents by SimHash and a Gray-order hierarchical index."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sketchselect.llm import shingles
from sketchselect.llm.common import batches_of, written
from sketchselect.llm.components import components
from sketchselect.llm.hamming import links


def fingerprints(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and code: the 64-bit SimHash of the whole text's word shingles, as a long.

    Null, empty and blank texts have code 0.
    """

    def run(batches):
        for batch in batches:
            codes = [shingles.signed(shingles.simhash(shingles.hashes(shingles.words(t.as_py()), size))) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(codes, pa.int64())], names=["doc_id", "code"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, code long")


def fingerprint_components(docs: DataFrame, size: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of ``docs``.

    Documents link where fingerprints differ in at most ``radius`` bits; component_id is the
    smallest doc_id that links reach. Equal fingerprints are one node of the index, so copies
    cost nothing there. Null ids count as larger than all others.
    """
    prints = written(fingerprints(docs, size), "prints")
    nodes = written(prints.groupBy("code").agg(F.min("doc_id").alias("id")), "nodes")
    joined = components(links(nodes.filter("id is not null"), radius))
    named = nodes.join(joined, nodes["id"] == joined["node"], "left").select(
        "code", F.coalesce("component", "id").alias("component_id")
    )
    return prints.join(named, "code").select(
        "doc_id", F.lower(F.lpad(F.hex("code"), 16, "0")).alias("fingerprint"), "component_id"
    )


#: Sub-document fingerprints of a document, and shingles in each.
BANDS, PICKS = 24, 4
#: Ids up to this many are broadcast; more are joined by a shuffle.
BROADCAST_IDS = 500_000
#: Rows of a batch that goes to a Python worker: whole texts, or pairs of shingle sets, which a batch holds
#: several times, in the worker and outside the heap of the JVM.
BATCH_ROWS = 1000
#: Ratio of the sizes at the two ends of a size class of shingle sets.
SIZE_STEP = 1.05


def _multipliers() -> tuple[np.ndarray, np.ndarray]:
    draw = np.random.default_rng(20240229)
    n = BANDS * PICKS
    return draw.integers(1 << 62, size=(n, 1), dtype=np.uint64) * np.uint64(2) + np.uint64(1), draw.integers(1 << 63, size=(n, 1), dtype=np.uint64)


def band_codes(found: np.ndarray) -> list[int]:
    """SimHashes of BANDS sub-documents: each is the PICKS shingles least under as many orders.

    Two documents of shingle similarity s pick the same shingles, and so the same code, in
    a band with probability s ** PICKS.
    """
    odd, plus = _multipliers()
    best = np.full(BANDS * PICKS, ~np.uint64(0))
    pick = np.zeros(BANDS * PICKS, np.uint64)
    for at in range(0, len(found), 4096):
        part = found[at : at + 4096]
        order = part * odd + plus
        order ^= order >> np.uint64(32)
        order *= np.uint64(0xD6E8FEB86659FD93)
        least = order.argmin(1)
        value = np.take_along_axis(order, least[:, None], 1)[:, 0]
        new = value <= best
        best[new], pick[new] = value[new], part[least[new]]
    ones = shingles.bits(pick).reshape(BANDS, PICKS, 64).sum(1)
    return np.packbits(2 * ones > PICKS, axis=1).view(">u8").ravel().astype(np.uint64).view(np.int64).tolist()


def signatures(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, digest of the word sequence, code of the whole text, codes of its sub-documents."""

    def run(batches):
        for batch in batches:
            digests, codes, bands = [], [], []
            for t in batch.column(1):
                words = shingles.words(t.as_py())
                found = shingles.hashes(words, size)
                digests.append(xxhash.xxh128_digest(b" ".join(words)))
                codes.append(shingles.signed(shingles.simhash(found)))
                bands.append(band_codes(np.unique(found)) if len(found) else [])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(digests, pa.binary()), pa.array(codes, pa.int64()), pa.array(bands, pa.list_(pa.int64()))],
                names=["doc_id", "digest", "code", "bands"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, digest binary, code long, bands array<long>")


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and shingles: the sorted distinct shingle hashes of each text."""

    def run(batches):
        for batch in batches:
            sets = [np.unique(shingles.hashes(shingles.words(t.as_py()), size)).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["doc_id", "shingles"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, shingles array<long>")


def shared_codes(unique: DataFrame) -> DataFrame:
    """doc_id, band, at, n: the sub-document codes that n > 1 documents share."""
    dealt = unique.select("doc_id", F.posexplode("bands").alias("band", "at"))
    shared = dealt.groupBy("band", "at").agg(F.count("*").alias("n")).filter("n > 1")
    return dealt.join(shared, ["band", "at"])


def candidate_pairs(unique: DataFrame, live: DataFrame, radius: int) -> DataFrame:
    """Distinct pairs (a, b), a < b, of documents that may be near copies.

    From the Gray-order index over whole-text codes, and from groups that share a
    sub-document code. A group is linked to three of its members, not to all pairs of them:
    the one that shares most codes with others (the likely original of many edited copies),
    the smallest id, and one by hash that differs from group to group.
    """
    nodes = unique.groupBy("code").agg(F.min("doc_id").alias("id"), F.max("doc_id").alias("other"))
    whole = links(nodes.select("code", "id"), radius)
    # equal whole-text codes of different texts
    twins = unique.join(nodes.filter("id < other").select("code", "id"), "code").filter("doc_id <> id").select(F.col("doc_id").alias("a"), F.col("id").alias("b"))
    ranked = live.join(live.groupBy("doc_id").agg(F.sum("n").alias("degree")), "doc_id")
    hubs = ranked.groupBy("band", "at").agg(
        F.max(F.struct("degree", "doc_id")).alias("top"),
        F.min("doc_id").alias("least"),
        F.min(F.struct(F.xxhash64("doc_id", "band"), "doc_id")).alias("drawn"),
    )
    hub = F.explode(F.array_distinct(F.array("top.doc_id", "least", "drawn.doc_id")))
    grouped = live.join(hubs, ["band", "at"]).select(F.col("doc_id").alias("a"), hub.alias("b"))
    every = whole.unionByName(twins).unionByName(grouped).filter("a <> b")
    return every.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def apart(live: DataFrame, joined: DataFrame, scope: str) -> DataFrame:
    """doc_id and component of all members of groups, by sub-document code, of several components."""
    named = live.select("doc_id", "band", "at").join(joined.withColumnRenamed("node", "doc_id"), "doc_id", "left")
    named = named.withColumn("component", F.coalesce("component", "doc_id"))
    mixed = named.groupBy("band", "at").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("n"))
    # the two members of a group of two have been compared
    return written(named.join(mixed.filter("lo < hi and n > 2").select("band", "at"), ["band", "at"]).select("doc_id", "component").distinct(), "apart", scope)


def apart_pairs(members: DataFrame, sets: DataFrame, similarity: float, scope: str) -> DataFrame:
    """Distinct pairs (a, b) of members of different components that may be near copies, by prefixes.

    The shingles of each set are ordered by how many members hold them, the rarest first. If
    the first shingle that two sets of nx >= ny share lies at px and py, they share at most
    min(nx - px, ny - py), of which the similarity s asks s (nx + ny) / (1 + s). So only the
    first (1 - s) nx shingles of the larger set and (1 - s) / (1 + s) ny of the smaller can be
    first, and the other pairs are ruled out. Shared wording of a family is frequent and comes late.

    The same bound says, from n and p of one set alone, how large the other may be. Entries meet by
    shingle and size class of the larger set, the smaller set being dealt to all classes that its bound
    allows: sets that lie deep in their prefixes only meet sets of nearly their own size.
    """
    held = members.join(sets, "doc_id").select("doc_id", "component", F.size("shingles").alias("n"), F.explode("shingles").alias("shingle"))
    # a shingle that one member holds is shared by none, but comes first
    common = held.groupBy("shingle").agg(F.count("*").alias("df")).filter("df > 1")
    least = f"{similarity} * n - 1e-9"
    prefixes = (
        held.join(common, "shingle")
        .groupBy("doc_id", "component", "n")
        .agg(F.sort_array(F.collect_list(F.struct("df", "shingle"))).alias("found"))
        .select("doc_id", "component", "n", (F.col("n") - F.size("found")).alias("alone"), F.posexplode("found").alias("at", "entry"))
        .select("doc_id", "component", "n", (F.col("alone") + F.col("at")).alias("p"), "entry.shingle")
        .filter(f"n - p >= {least}")
    )
    entries = written(prefixes, "prefixes", scope)
    part = similarity / (1 + similarity)

    def size_class(n: str):
        return F.floor(F.log(n) / math.log(SIZE_STEP)).cast("int")

    # the largest size that the other set may have; a little more, for rounding
    entries = entries.withColumn("most", F.expr(f"least((n - p) / {part} - n, n) + 1e-6")).withColumn("class", size_class("n"))
    small = (
        entries.filter(f"n - p >= {2 * part} * n - 1e-9")
        .select("shingle", F.col("component").alias("other"), F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("p").alias("pb"))
        .withColumn("most_b", F.expr(f"least((nb - pb) / {part} - nb, nb / {similarity}) + 1e-6"))
        .withColumn("class", F.explode(F.sequence(size_class("nb"), size_class("most_b"))))
    )
    # members of one component are never paired: pairs of components meet first
    groups = entries.groupBy("shingle", "class", "component").agg(F.min("n").alias("least_n"), F.max("most").alias("most_n"))
    others = small.groupBy("shingle", "class", "other").agg(F.min("nb").alias("least_nb"), F.max("most_b").alias("most_nb"))
    met = (
        groups.join(others, ["shingle", "class"])
        .filter("component <> other and least_nb <= most_n and least_n <= most_nb")
        .select("shingle", "class", "component", "other")
    )
    fit = f"""n >= nb and nb >= {least}
        and least(n - p, nb - pb) >= {part} * (n + nb) - 1e-9"""
    near = entries.join(met, ["shingle", "class", "component"]).join(small, ["shingle", "class", "other"]).filter(fit)
    return near.select(F.least("doc_id", "b").alias("a"), F.greatest("doc_id", "b").alias("b")).distinct()


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs whose shingle sets have at least the Jaccard similarity asked."""

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = x.values.to_numpy(), y.values.to_numpy()
                common = len(np.intersect1d(x, y, assume_unique=True))
                union = len(x) + len(y) - common
                keep.append(union > 0 and common >= similarity * union - 1e-9)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x"), F.size("shingles").alias("nx"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y"), F.size("shingles").alias("ny"))
    # sets whose sizes alone rule the similarity out are not compared
    fit = F.expr(f"least(nx, ny) >= {similarity} * greatest(nx, ny) - 1e-9")
    return pairs.join(left, "a").join(right, "b").filter(fit).select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def among(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Semi or anti join of documents with a written table of ids (column ``_id``)."""
    small = ids.count() <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if small else ids, docs["doc_id"] == ids["_id"], how)


def drop_near_duplicates(
    docs: DataFrame, size: int = 5, similarity: float = 0.8, radius: int = 2, scope: str = "query"
) -> DataFrame:
    """The documents, all columns, with one of each group of near copies: its smallest doc_id.

    Near copies have a Jaccard similarity of word shingles of at least ``similarity``, or are
    linked by such pairs. Texts of equal words are one group whatever their length; texts
    without words form one. Repeated rows of one doc_id and text become one; rows without
    doc_id always stay.
    """
    with batches_of(docs.sparkSession, BATCH_ROWS):
        return _dropped(docs, size, similarity, radius, scope)


def _dropped(docs: DataFrame, size: int, similarity: float, radius: int, scope: str) -> DataFrame:
    marks = written(signatures(docs.filter("doc_id is not null"), size), "marks", scope)
    unique = written(
        marks.groupBy("digest").agg(F.min(F.struct("doc_id", "code", "bands")).alias("first")).select("first.*"), "unique", scope
    )
    live = written(shared_codes(unique), "live", scope)
    pairs = written(candidate_pairs(unique, live, radius), "pairs", scope)
    ends = written(pairs.select(F.explode(F.array("a", "b")).alias("_id")).distinct(), "ends", scope)
    sets = written(shingle_sets(among(docs, ends, "left_semi"), size), "sets", scope)
    linked = written(verified(pairs, sets, similarity), "linked", scope)
    members = apart(live, components(linked, scope), scope)
    rest = verified(apart_pairs(members, sets, similarity, scope), sets, similarity)
    joined = components(linked.unionByName(rest), scope)
    gone = written(
        marks.select("doc_id")
        .join(unique.select("doc_id"), "doc_id", "left_anti")
        .union(joined.filter("node <> component").select("node"))
        .select(F.col("doc_id").alias("_id"))
        .distinct(),
        "gone",
        scope,
    )
    kept = among(docs, gone, "left_anti")
    counted = marks.agg(F.count("*"), F.count_distinct("doc_id")).first()
    if counted[0] == counted[1]:
        return kept
    return kept.filter("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(kept.filter("doc_id is null"))
