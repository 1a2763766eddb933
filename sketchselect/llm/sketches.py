"""Document fingerprints as invertible Bloom lookup sketches.

A text is cut into paragraphs and these into sentences or parts of them: at line breaks, at white space after a
character of ``CUT``, and after full-width stops. Those longer than ``LONG`` characters are cut
further after the words whose hash ends in three zero bits. All cuts depend on nothing but the characters
beside them, so an edit changes only the pieces that it touches. A piece's digest is the hash of it
and of how often it occurs, so digests form a set.

Every digest lies in one cell of each of three subtables. A cell keeps how many digests it
holds and the exclusive or of the digests and of their check hashes. Subtracting
the sketches of two texts cell by cell leaves only the digests in which they differ, and
peeling recovers these: a cell with one digest whose check agrees names it, it is taken
out of its other cells, and so on. When cells are left over, larger sketches are peeled until
peeling ends; nothing is estimated. Likeness of two sketches is shared / all digests, from the
two set sizes and the recovered digests.

Sketches of ``SIZES`` are dense arrays of cells; the larger of them is the fingerprint, and the
difference of two is folded to the smaller size. An estimate from the cell counts passes over sizes that
cannot hold the difference. What these do not hold retries in sketches of any size, kept sparse
and ordered by place, whose work grows with the digests and not with the cells: there subtables
have ``ROOM`` cells for every digest of the difference, about, so that few rounds empty them. Everything
is SQL expressions over columns of one row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sketchselect.llm.common import let, text_or_empty

#: Characters after which white space ends a piece, and those that end one themselves.
CUT = ".!?;:"
STOPS = "。！？；："
#: Characters of a piece from which it is cut by words, and of the longest word that is kept whole.
LONG, WORD_CHARS = 100, 32
#: Cells of each of the three subtables, by retry (powers of two), and peeling rounds.
SIZES = (8, 32)
ROUNDS = 16
#: Digests that the sketches of ``SIZES`` may hold; larger differences are not peeled there in vain.
HOLD = (17, 80)
#: Cells of a larger subtable for each digest of the difference, and larger sizes tried, each four times the one before.
ROOM = 16
RETRIES = 8
CHECK_SEED = 77
#: Rows of a range of doc_id in the search for the next document, and ranges at most.
RANGE_ROWS = 1024
MAX_RANGES = 1 << 16
CELL = "struct<n:int,keys:bigint,checks:int>"


def clause_hashes(text: str) -> Column:
    ends = "filter(sequence(1, size(w)), i -> i = size(w) OR (xxhash64(w[i - 1]) & 7) = 0)"
    cut = "transform(e, (z, k) -> xxhash64(slice(w, coalesce(get(e, k - 1), 0) + 1, z - coalesce(get(e, k - 1), 0))))"
    words = let(f"regexp_extract_all(x, '[^ ]{{1,{WORD_CHARS}}}', 0)", "w", f"if(size(w) = 0, array(xxhash64(x)), {let(ends, 'e', cut)})")
    clauses = f"filter(split({text}, '(?<=[{CUT}])[ ]+|[\\n\\r]+|(?<=[{STOPS}])'), x -> x <> '')"
    return F.expr(f"flatten(transform({clauses}, x -> if(length(x) <= {LONG}, array(xxhash64(x)), {words})))")


def starts(ordered: str, key: str) -> str:
    """SQL: where runs of equal keys begin in an ordered array that is not empty."""
    return f"filter(sequence(0, size({ordered}) - 1), i -> i = 0 OR {ordered}[i]{key} <> {ordered}[i - 1]{key})"


def digests(hashes: str) -> Column:
    """Distinct digests from the hashes of pieces: each hash with the number of its occurrences."""
    counted = "transform(b, (a, k) -> xxhash64(s[a], coalesce(get(b, k + 1), size(s)) - a))"
    return F.expr(f"if(size({hashes}) = 0, {hashes}, {let(f'sort_array({hashes})', 's', let(starts('s', ''), 'b', counted))})")


def layout(size: int) -> str:
    """SQL literal: where digests lie, as masks and values of their bits.

    Subtable j reads its place from the bits from 16 j on. Cells come in groups that share the
    high bits of the place; each group has its first cell's index, its mask and value, and
    those of its cells.
    """
    part = max(1, size // 4)
    groups = []
    for j in range(3):
        for at in range(0, size, part):
            cells = ", ".join(f"named_struct('m', {(size - 1) << 16 * j}L, 'v', {(at + c) << 16 * j}L)" for c in range(part))
            mask = ((size - 1) & ~(part - 1)) << 16 * j
            groups.append(f"named_struct('i', {j * size + at + 1}, 'm', {mask}L, 'v', {at << 16 * j}L, 'c', array({cells}))")
    return f"array({', '.join(groups)})"


def sketch(found: str, size: int) -> str:
    """SQL: cells (n, keys, checks) of an array of distinct digests.

    Digests are dealt to groups of cells first, by the high bits of their place, then to the cells of
    each by the low ones. Masks are literals and values plain array elements, which cost least for each digest.
    """
    part = max(1, size // 4)

    def values(at: range, j: int) -> str:
        return f"array({', '.join(f'{x << 16 * j}L' for x in at)})"

    tables = [
        f"""transform({values(range(0, size, part), j)}, g -> transform(
            array(filter({found}, h -> (h & {((size - 1) & ~(part - 1)) << 16 * j}L) = g)),
            few -> transform({values(range(part), j)}, c -> aggregate(
                filter(few, h -> (h & {(part - 1) << 16 * j}L) = c),
                cast(struct(0 AS n, 0L AS keys, 0 AS checks) AS {CELL}),
                (acc, h) -> struct(acc.n + 1 AS n, acc.keys ^ h AS keys, acc.checks ^ hash(h, {CHECK_SEED}) AS checks))))[0])"""
        for j in range(3)
    ]
    return f"flatten(concat({', '.join(tables)}))"


def difference(a: str, b: str) -> str:
    return f"zip_with({a}, {b}, (x, y) -> struct(x.n - y.n AS n, x.keys ^ y.keys AS keys, x.checks ^ y.checks AS checks))"


def peeled(cells: str, size: int) -> str:
    """SQL: the number of digests that peeling recovers, null where cells are left over."""
    pure = f"""array_distinct(filter(acc.cells, c -> abs(c.n) = 1 AND hash(c.keys, {CHECK_SEED}) = c.checks))"""
    part = max(1, size // 4)
    taken = f"""flatten(transform({layout(size)}, g -> transform(
        array(filter(one, p -> (p.keys & g.m) = g.v)),
        few -> if(size(few) = 0, slice(acc.cells, g.i, {part}),
            zip_with(slice(acc.cells, g.i, {part}), g.c, (c, q) -> aggregate(filter(few, p -> (p.keys & q.m) = q.v), c,
                (left, p) -> struct(left.n - p.n AS n, left.keys ^ p.keys AS keys, left.checks ^ p.checks AS checks)))))[0]))"""
    step = f"""if(acc.going, aggregate(array({pure}), acc, (acc, one) ->
        struct({taken} AS cells, acc.took + size(one) AS took, size(one) > 0 AS going)), acc)"""
    return f"""aggregate(sequence(1, {ROUNDS}), struct({cells} AS cells, 0 AS took, true AS going), (acc, i) -> {step},
        acc -> if(forall(acc.cells, c -> c.n = 0 AND c.keys = 0), acc.took, null))"""


def folded(cells: str, large: int, small: int) -> str:
    """SQL: the sketch with smaller subtables, from one with larger: places keep their low bits."""

    def added(parts: list[str]) -> str:
        if len(parts) == 1:
            return parts[0]
        half = len(parts) // 2
        return f"""zip_with({added(parts[:half])}, {added(parts[half:])},
            (x, y) -> struct(x.n + y.n AS n, x.keys ^ y.keys AS keys, x.checks ^ y.checks AS checks))"""

    tables = [added([f"slice({cells}, {t * large + k * small + 1}, {small})" for k in range(large // small)]) for t in range(3)]
    return f"concat({', '.join(tables)})"


def merged(entries: str) -> str:
    """SQL: entries (place i, n, keys, checks) summed by place, in order of place, without those that cancel out."""
    run = """aggregate(slice(s, a + 1, coalesce(get(b, k + 1), size(s)) - a), struct(s[a].i AS i, 0 AS n, 0L AS keys, 0 AS checks),
        (acc, c) -> struct(acc.i AS i, acc.n + c.n AS n, acc.keys ^ c.keys AS keys, acc.checks ^ c.checks AS checks))"""
    cells = f"transform(b, (a, k) -> if(coalesce(get(b, k + 1), size(s)) = a + 1, s[a], {run}))"
    summed = let("sort_array(entries)", "s", let(starts("s", ".i"), "b", f"filter({cells}, c -> c.n <> 0 OR c.keys <> 0 OR c.checks <> 0)"))
    return let(entries, "entries", f"if(size(entries) = 0, entries, {summed})")


def places(digest: str, n: str, size: str) -> str:
    """SQL: the three entries of a digest, counted n times; subtable j reads its place from the bits from 21 j on."""
    cells = [
        f"named_struct('i', int({j} * {size} + (shiftrightunsigned({digest}, {21 * j}) & ({size} - 1))), 'n', {n}, 'keys', {digest}, 'checks', hash({digest}, {CHECK_SEED}))"
        for j in range(3)
    ]
    return f"array({', '.join(cells)})"


def peeled_wide(cells: str, size: str) -> str:
    """SQL: (ours, theirs) digests that peeling recovers from sparse cells, null where cells are left over."""
    good = f"abs(c.n) = 1 AND hash(c.keys, {CHECK_SEED}) = c.checks"
    pure = f"sort_array(transform(filter(acc.cells, c -> {good}), c -> struct(c.keys AS digest, c.n AS n, c.i AS i)))"
    # a digest that is alone in all three of its cells takes them with it; the others are taken out of theirs
    rest = "flatten(transform(filter(b, (a, k) -> coalesce(get(b, k + 1), size(pure)) - a < 3), a -> "
    rest += f"{places('pure[a].digest', '-pure[a].n', size)}))"
    held = "flatten(transform(b, (a, k) -> if(coalesce(get(b, k + 1), size(pure)) - a = 3, slice(pure, 1, 0), slice(pure, a + 1, coalesce(get(b, k + 1), size(pure)) - a))))"
    kept = f"transform({held}, p -> named_struct('i', p.i, 'n', p.n, 'keys', p.digest, 'checks', hash(p.digest, {CHECK_SEED})))"
    left = merged(f"concat(filter(acc.cells, c -> NOT ({good})), {kept}, {rest})")
    ours = "concat(acc.ours, transform(filter(b, a -> pure[a].n = 1), a -> pure[a].digest))"
    theirs = "concat(acc.theirs, transform(filter(b, a -> pure[a].n = -1), a -> pure[a].digest))"
    took = f"struct({left} AS cells, {ours} AS ours, {theirs} AS theirs, true AS going)"
    stuck = "struct(acc.cells AS cells, acc.ours AS ours, acc.theirs AS theirs, false AS going)"
    none = "cast(array() AS array<bigint>)"
    round_ = let(pure, "pure", f"if(size(pure) = 0, {stuck}, {let(starts('pure', '.digest'), 'b', took)})")
    return f"""aggregate(sequence(1, {ROUNDS}), struct({cells} AS cells, {none} AS ours, {none} AS theirs, true AS going),
        (acc, r) -> if(acc.going AND size(acc.cells) > 0, {round_}, acc),
        acc -> if(size(acc.cells) = 0, struct(acc.ours AS ours, acc.theirs AS theirs), null))"""


def wide(a: str, b: str, guess: str) -> str:
    """SQL: (ours, theirs) digests of two sets by sparse sketches, the first sized for a guess, until peeling ends.

    Digests alike in the bits of every place of the largest size, if there are any, are told apart by themselves.
    """
    first = f"int(pow(2, ceil(log2({ROOM} * greatest({guess}, {SIZES[-1]}.0D)))))"
    both = f"concat(flatten(transform({a}, h -> {places('h', '1', 't.size')})), flatten(transform({b}, h -> {places('h', '-1', 't.size')})))"
    tried = let(merged(both), "cells", peeled_wide("cells", "t.size"))
    again = let(tried, "found", f"struct(if(found IS NULL AND r < {RETRIES}, 4 * t.size, t.size) AS size, found AS found)")
    return f"""aggregate(sequence(1, {RETRIES}), struct({first} AS size, cast(null AS struct<ours:array<bigint>,theirs:array<bigint>>) AS found),
        (t, r) -> if(t.found IS NOT NULL, t, {again}),
        t -> struct(coalesce(t.found.ours, array_except({a}, {b})) AS ours, coalesce(t.found.theirs, array_except({b}, {a})) AS theirs))"""


def estimated(cells: str, size: int, a: str, b: str) -> str:
    """SQL: about how many digests differ, from cell counts; a and b are the two set sizes.

    Over a subtable of m cells the squares of the count differences sum, on average, to
    d (1 - 1/m) + (a - b)^2 / m for d differing digests. It only chooses the size of a retry.
    """
    squares = f"aggregate({cells}, 0D, (s, c) -> s + double(c.n) * c.n) / 3"
    raw = f"({squares} - double({a} - {b}) * ({a} - {b}) / {size}) / (1 - 1D / {size})"
    return f"greatest(double(abs({a} - {b})), least(double({a} + {b}), {raw}))"


def wide_count(frame: DataFrame, a: str, b: str, guess: str, some: str, name: str) -> DataFrame:
    """Add column ``name``: ``some``, or where that is null how many digests ``wide`` recovers.

    The first round of the first size is made of sorted numbers (place, digest's index in both sets), which cost
    far less than cells. A place that comes once is a cell with one digest, whose check is that digest's own. Two
    equal digests alone at a place cancel out. All other cells are summed, the digests found are taken out of those,
    and peeling goes on there.
    """
    size, both, at, lone, rest, left, found, partly = (f"{name}_{c}" for c in ("size", "both", "at", "lone", "rest", "left", "found", "partly"))
    index, other = "int(x & 4294967295L)", 4294967296

    def placed(digest: str, i: str, j: int) -> str:
        return f"(shiftleft({j}L * {size} + (shiftrightunsigned({digest}, {21 * j}) & ({size} - 1L)), 32) | {i})"

    def apart_from(entries: str, k: int) -> str:
        return f"coalesce((get({entries}, i + {k}) ^ x) >= {other}L, true)"

    def digest_at(k: int) -> str:
        return f"get({both}, int(get({rest}, i + {k}) & {other - 1}L))"

    def cells(entries: str, ours: int) -> str:
        return f"""transform({entries}, x -> named_struct('i', int(shiftright(x, 32)), 'n', if({index} < size({a}), {ours}, {-ours}),
            'keys', get({both}, {index}), 'checks', hash(get({both}, {index}), {CHECK_SEED})))"""

    cancel = f"""if({apart_from(rest, -1)}, {apart_from(rest, 2)} AND {digest_at(1)} = get({both}, {index}),
        {apart_from(rest, 1)} AND {apart_from(rest, -2)} AND {digest_at(-1)} = get({both}, {index}))"""
    gone = f"array_except(concat({', '.join(f'transform({partly}, q -> {placed(f"get({both}, q)", "q", j)})' for j in range(3))}), {lone})"
    steps = {
        size: f"if({some} IS NULL, coalesce(int(pow(2, ceil(log2({ROOM} * greatest({guess}, {SIZES[-1]}.0D))))), 0), 0)",
        both: f"if({size} = 0, cast(array() AS array<bigint>), concat({a}, {b}))",
        at: f"sort_array(concat({', '.join(f'transform({both}, (h, i) -> {placed("h", "i", j)})' for j in range(3))}))",
        lone: f"filter({at}, (x, i) -> {apart_from(at, -1)} AND {apart_from(at, 1)})",
        rest: f"array_except({at}, {lone})",
        left: f"filter({rest}, (x, i) -> NOT ({cancel}))",
        found: f"array_distinct(transform({lone}, x -> {index}))",
        partly: f"array_intersect({found}, transform({left}, x -> {index}))",
    }
    for column, made in steps.items():
        frame = frame.withColumn(column, F.expr(made))
    going = let(merged(f"concat({cells(left, 1)}, {cells(gone, -1)})"), "cells", peeled_wide("cells", size))
    more = let(going, "p", "if(p IS NULL, null, size(p.ours) + size(p.theirs))")
    count = f"if(size({left}) = 0, size({found}), size({found}) + {more})"
    again = let(wide(a, b, f"(4 * {guess})"), "found", "size(found.ours) + size(found.theirs)")
    # through explode no filter on the result is pushed, which would copy all of this into itself many times
    return frame.select("*", F.explode(F.array(F.expr(f"cast(coalesce({some}, {count}, {again}) AS long)"))).alias(name)).drop(*steps)


def apart_small(frame: DataFrame, a: str, b: str, name: str) -> DataFrame:
    """Add ``<name>_some``, how many digests differ as the fingerprints say, or null, and ``<name>_guess``."""
    small, large = SIZES
    cells, guess, some = f"{name}_cells", f"{name}_guess", f"{name}_some"
    few = f"if({guess} > {HOLD[0]}, null, {peeled(folded(cells, large, small), small)})"
    many = f"if({guess} > {HOLD[1]}, null, {peeled(cells, large)})"
    return (
        frame.withColumn(cells, F.expr(difference(f"{a}_large", f"{b}_large")))
        .withColumn(guess, F.expr(estimated(cells, large, f"size({a})", f"size({b})")))
        .withColumn(some, F.expr(f"coalesce({few}, {many})"))
        .drop(cells)
    )


def apart(frame: DataFrame, a: str, b: str, name: str) -> DataFrame:
    """Add column ``name``: how many digests differ between two sets.

    Columns ``a`` and ``b`` hold the digests, ``<a>_large`` and ``<b>_large`` their fingerprints.
    """
    guess, some = f"{name}_guess", f"{name}_some"
    return wide_count(apart_small(frame, a, b, name), a, b, guess, some, name).drop(guess, some)


def apart_each(frame: DataFrame, pairs: dict[str, tuple[str, str]], done: list[str | Column]) -> DataFrame:
    """Columns ``done`` and, for each name of ``pairs``, how many digests differ between its two sets.

    Sets ``a`` are columns of digests, and ``<a>_large`` their fingerprints. These are dropped before larger
    sketches are made, since every step there carries its row along.
    """
    for name, (a, b) in pairs.items():
        frame = apart_small(frame, a, b, name)
    sets = list(dict.fromkeys(c for pair in pairs.values() for c in pair))
    frame = frame.select(*done, *sets, *[f"{name}_{c}" for name in pairs for c in ("guess", "some")])
    for name, (a, b) in pairs.items():
        frame = wide_count(frame, a, b, f"{name}_guess", f"{name}_some", name).drop(f"{name}_guess", f"{name}_some")
    return frame


def likeness(a: str, b: str, parted: str) -> Column:
    """Shared / all digests of two sets and the number that differ; two empty sets are alike (1)."""
    n = f"(size({a}) + size({b}))"
    return F.expr(f"if({n} = 0, 1D, double({n} - {parted}) / ({n} + {parted}))")


def printed(cells: str) -> Column:
    """A sketch as text: count, digest and check sums of every cell in hexadecimal."""
    return F.expr(f"lower(array_join(transform({cells}, c -> if(c.n = 0, '-', concat_ws(':', hex(c.n), hex(c.keys), hex(c.checks)))), ','))")


def id_ranges(docs: DataFrame) -> list[int]:
    """Upper ends of ranges of doc_id with about equal numbers of rows; at most MAX_RANGES."""
    n = docs.count()
    ranges = max(1, min(MAX_RANGES, n // RANGE_ROWS))
    if ranges == 1:
        return []
    at = [i / ranges for i in range(1, ranges)]
    ends = docs.agg(F.percentile_approx("doc_id", at, max(10_000, 20 * ranges))).first()[0] or []
    return sorted(set(ends))


def range_of(ends: list[int]) -> Column:
    """The number of the range that holds doc_id, by bisection."""
    if not ends:
        return F.lit(0)
    held = "array(" + ",".join(f"{e}L" for e in ends) + ")"
    return F.expr(f"""aggregate(sequence(1, {len(ends).bit_length() + 1}), struct(0 AS lo, {len(ends)} AS hi),
        (s, i) -> if(s.lo >= s.hi, s, if(element_at({held}, int((s.lo + s.hi) div 2) + 1) < doc_id,
            struct(int((s.lo + s.hi) div 2) + 1 AS lo, s.hi AS hi), struct(s.lo AS lo, int((s.lo + s.hi) div 2) AS hi))),
        s -> int(s.lo))""")


def with_next(docs: DataFrame, columns: list[str], derived: dict[str, Column] | None = None) -> DataFrame:
    """Add ``next_<column>``: of the next row by descending doc_id; after the last, the first.

    Columns ``derived`` are added too, with their ``next_<column>``. They are made where the rows lie in
    order, so that none is moved and each is made once for both rows that need it.

    Rows lie in ranges of doc_id and are ordered within them. The first row of a range is
    also the successor of the last row of the range above, so that row is dealt to both, and
    the first of all also to the lowest range. Equal ids are ordered by text; null ids are last.
    """
    placed = docs.withColumn("_range", F.coalesce(range_of(id_ranges(docs)), F.lit(0)).cast("int"))
    order = Window.orderBy("_range")
    # at most MAX_RANGES rows
    tops = (
        placed.groupBy("_range")
        .agg(F.max("doc_id").alias("_top"))
        .withColumn("_above", F.coalesce(F.lead("_range").over(order), F.first("_range").over(order)))
    )
    dealt = placed.join(F.broadcast(tops), "_range").withColumn(
        "_to", F.when(F.col("doc_id").eqNullSafe(F.col("_top")), F.array("_range", F.col("_above"))).otherwise(F.array("_range"))
    )
    rows = dealt.select(*docs.columns, F.posexplode("_to").alias("_copy", "_to"))
    seen = Window.partitionBy("_to").orderBy("_copy", F.col("doc_id").desc_nulls_last(), *[c for c in columns if c == "text"])
    followed = rows.select("*", *[F.lead(c).over(seen).alias(f"next_{c}") for c in columns])
    if derived:
        followed = followed.withColumns(derived).select("*", *[F.lead(c).over(seen).alias(f"next_{c}") for c in derived])
    return followed.filter("_copy = 0").drop("_copy", "_to")


def sketch_columns(sets: list[str]) -> dict[str, Column]:
    """Columns ``<set>_large``, the fingerprints of arrays of digests."""
    return {f"{c}_large": F.expr(sketch(c, SIZES[-1])) for c in sets}


def sketched(rows: DataFrame, sets: list[str]) -> DataFrame:
    """Add ``<set>_large``, the fingerprint of each array of digests."""
    return rows.withColumns(sketch_columns(sets))


def parted(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Rows with two texts in columns ``a`` and ``b``: add ``ours`` and ``theirs``.

    These are the digests that only the first or only the second text has, recovered from the
    difference of two sketches, retrying larger ones. Null texts count as empty.
    """
    x, y = (F.expr(f"coalesce({c}, '')") for c in (a, b))
    rows = pairs.withColumns({"_x": x, "_y": y}).withColumns({"_x": clause_hashes("_x"), "_y": clause_hashes("_y")})
    rows = rows.withColumns({"_x": digests("_x"), "_y": digests("_y")})
    guess = "double(abs(size(_x) - size(_y)))"
    rows = rows.withColumn("_parts", F.expr(wide("_x", "_y", guess)))
    return rows.select(*pairs.columns, "_parts.ours", "_parts.theirs")


def fingerprint(docs: DataFrame) -> DataFrame:
    """Sketches of every text and its edited text, and their likenesses.

    The edited text is the text with its last third (rounded down) replaced by the first as
    many code points of the next document. Null texts count as empty. Also returned: how many digests
    only the text or only the edited text has.
    Repeated rows are documents of their own, ordered by text where ids are equal or null; the only
    document of a table is its own next. An empty table gives an empty result.
    """
    rows = (
        docs.select("doc_id", text_or_empty().alias("text"))
        .withColumn("hashes", clause_hashes("text"))
        .withColumn("own", digests("hashes"))
        .drop("hashes")
    )
    near = (
        with_next(rows, ["text", "own"], sketch_columns(["own"]))
        .withColumn("n_chars", F.length("text").cast("long"))
        .withColumn("edited", F.concat(F.expr("substr(text, 1, length(text) - length(text) div 3)"), F.expr("substr(next_text, 1, length(text) div 3)")))
        .drop("text", "next_text")
        .withColumn("edited_sha256", F.sha2("edited", 256))
        .withColumn("hashes", clause_hashes("edited"))
        .withColumn("changed", digests("hashes"))
        .drop("edited", "hashes")
    )
    prints = [printed("own_large").alias("fingerprint"), printed("changed_large").alias("edited_fingerprint")]
    done = ["doc_id", "n_chars", "edited_sha256", *prints]
    near = apart_each(sketched(near, ["changed"]), {"_edited": ("own", "changed"), "_next": ("own", "next_own")}, done)
    return near.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        "fingerprint",
        "edited_fingerprint",
        likeness("own", "changed", "_edited").alias("near_edited"),
        likeness("own", "next_own", "_next").alias("near_next"),
        F.expr("(_edited + size(own) - size(changed)) div 2").alias("edited_gone"),
        F.expr("(_edited + size(changed) - size(own)) div 2").alias("edited_new"),
    )
