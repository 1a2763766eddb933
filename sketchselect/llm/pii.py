r"""Personal data by weak supervision.

Strict patterns give the base spans, which always stay. Looser patterns give further
candidates. Labelers vote +1, 0 or -1 on every candidate: the strict pattern, the form
(checksum, digit count, octet range), a gazetteer (top-level domains, issuer digits,
country codes) and the words before it. Expectation-maximisation over the counted vote
patterns estimates each labeler's reliability without labels. Its posteriors are the soft
labels of a final span classifier (naive Bayes over votes-free features of the span and
its surroundings), and a loose candidate is kept where the classifier and the posterior
agree on more than one half.

Positions come from pairing what a pattern matches with what lies between: the running
sum of both lengths is the code-point offset. Everything on the executors is SQL
expressions; the driver sees only counted vote patterns, whose number is bounded by the
product of the vote and feature values.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sketchselect.llm.common import let, text_or_empty, written

#: Kinds in the order of results.
KINDS = ("email", "ip", "card", "phone")
#: Base patterns. Each is written so that no start inside a run that has
#: failed is tried again (a lookbehind, or the end of the last match), which keeps the
#: leftmost matches and makes long runs linear.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){11,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Patterns of further candidates.
LOOSE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++\x20?[\[(](?:at|AT)[\])]\x20?[A-Za-z0-9-]+(?:\x20?(?:[\[(](?:dot|DOT)[\])]|\.)\x20?[A-Za-z0-9-]+)+",
    "ip": r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])",
    "phone": r"(?<![0-9A-Za-z+(.-])(?:\([0-9]{3}\)\x20?|[0-9]{3}[\x20.-])[0-9]{3}[\x20.-][0-9]{4}(?![0-9A-Za-z-])",
}
#: Cheap tests without which a pattern can't match.
NEEDS = {"email": r"@", "ip": r"[0-9]\.[0-9]+\.", "card": r"[0-9](?:[\x20-]?[0-9]){11}", "phone": r"\+[0-9]"}
LOOSE_NEEDS = {"email": r"[\[(](?:at|AT)[\])]", "ip": r"[0-9A-Fa-f]:[0-9A-Fa-f]+:", "phone": r"[0-9]{3}[)\x20.-]\x20?[0-9]{3}[\x20.-][0-9]{4}"}
#: Gazetteers and cue words.
DOMAINS = "com|org|net|edu|gov|mil|info|biz|io|de|fr|es|it|uk|nl|eu|ch|at|us|ca|jp|cn|br|in|ru"
CUES = {
    "email": r"(?i)mail|contact|write|kontakt|correo|courriel|e-post",
    "ip": r"(?i)\bip\b|host|server|address|adresse|dirección|serveur|login",
    "card": r"(?i)card|visa|master|amex|karte|carte|tarjeta|credit|payment",
    "phone": r"(?i)phone|tel\b|tel[.:]|call|mobile|fax|telefon|téléphone|teléfono|whatsapp",
}
AGAINST = r"(?i)token|version|\bv\.?$|serial|sku|order|isbn|hash|uuid|[\"'=#/_A-Za-z]$"
PART = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
BEFORE = 30
SPAN = "struct<start:int,end:int,said:string,before:string>"


def quoted(text: str) -> str:
    """A SQL string literal."""
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def scanned(values: str, joined: str) -> str:
    """SQL: running folds of an array by an associative operation of x (later) and y (earlier).

    Each pass joins every entry with the one 2 ** t places before it, so n entries take n log n
    steps: folding with an accumulated array copies that array for every entry.
    """
    return f"""aggregate(sequence(0, 30), {values}, (v, t) -> if(shiftleft(1, t) >= size(v), v,
        transform(v, (x, i) -> if(i < shiftleft(1, t), x, {let("v[i - shiftleft(1, t)]", "y", joined)}))))"""


def located(pattern: str, needs: str) -> str:
    """SQL: the matches of a pattern in ``text`` as (start, end, said, before)."""
    p, n = quoted(pattern), quoted(needs)
    ends = scanned("transform(found, f -> length(f.p) + length(f.m))", "x + y")
    spans = f"transform(found, (f, i) -> struct(ends[i] - length(f.m) AS start, ends[i] AS end, f.m AS said, right(f.p, {BEFORE}) AS before))"
    found = f"filter(zip_with(regexp_extract_all(text, {p}, 0), split(text, {p}, -1), (a, b) -> struct(a AS m, b AS p)), x -> x.m IS NOT NULL)"
    return f"""CASE WHEN NOT (text RLIKE {n}) THEN cast(array() AS array<{SPAN}>) ELSE {let(found, "found", let(ends, "ends", spans))} END"""


def apart(good: str, loose: str) -> str:
    """SQL: the spans of ``loose`` that touch none of ``good``, in order of start.

    Both are merged by start; a loose span is clear if no good one before it ends after its
    start and none behind it starts before its end.
    """
    merged = f"""array_sort(concat(
        transform({good}, x -> struct(x.start AS start, 0 AS loose, x.end AS end, x AS span)),
        transform({loose}, x -> struct(x.start AS start, 1 AS loose, x.end AS end, x AS span))),
        (a, b) -> CASE WHEN a.start < b.start THEN -1 WHEN a.start > b.start THEN 1 ELSE a.loose - b.loose END)"""
    last = scanned("transform(every, e -> if(e.loose = 0, e.end, 0))", "greatest(x, y)")
    first = f"reverse({scanned('reverse(transform(every, e -> if(e.loose = 0, e.start, 2147483647)))', 'least(x, y)')})"
    clear = "filter(transform(every, (e, i) -> if(e.loose = 1 AND last[i] <= e.start AND first[i] >= e.end, e.span, null)), x -> x IS NOT NULL)"
    return f"if(size({loose}) = 0 OR size({good}) = 0, {loose}, {let(merged, 'every', let(last, 'last', let(first, 'first', clear)))})"


def luhn(digits: str) -> str:
    """SQL: whether a string of digits passes the checksum."""
    d = f"int(substr({digits}, -i, 1))"
    return f"""aggregate(sequence(1, length({digits})), 0, (s, i) ->
        s + CASE WHEN i % 2 = 1 THEN {d} WHEN {d} < 5 THEN 2 * {d} ELSE 2 * {d} - 9 END) % 10 = 0"""


DIGITS = "regexp_replace(x.said, '[^0-9]', '')"


def valid(kind: str) -> str:
    """SQL over a span ``x``: whether a match of the base pattern is a base span."""
    return {
        "email": "true",
        "ip": f"x.said RLIKE {quoted(rf'^{PART}[.]{PART}[.]{PART}[.]{PART}$')}",
        "card": f"length({DIGITS}) BETWEEN 12 AND 19 AND {luhn(DIGITS)}",
        "phone": f"length({DIGITS}) BETWEEN 9 AND 15",
    }[kind]


def votes(kind: str, base: bool) -> str:
    """SQL over a span ``x``: the span with its key of votes and features."""
    form = {
        "email": f"if(lower(x.said) RLIKE {quoted(r'[.) ][a-z]{2,12}$')}, 1, -1)",
        "ip": f"if(x.said RLIKE {quoted(r'^(?:0+|255)[.]')}, -1, 1)",
        "card": "1" if base else "-1",
        "phone": f"if(length({DIGITS}) BETWEEN 10 AND 13, 1, 0)",
    }[kind]
    gazetteer = {
        "email": f"if(lower(x.said) RLIKE {quoted(rf'[.) ](?:{DOMAINS})$')}, 1, 0)",
        "ip": f"if(x.said RLIKE {quoted(r'^(?:[1-9]|[1-9][0-9]|1[0-9][0-9]|2[01][0-9]|22[0-3])[.]|:')}, 1, -1)",
        "card": f"if(x.said RLIKE {quoted(r'^[3-6]')}, 1, -1)",
        "phone": f"if(x.said RLIKE {quoted(r'^[+]?[(]?(?:1|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|7|8[1246]|9[0-58])')}, 1, 0)",
    }[kind]
    context = f"CASE WHEN x.before RLIKE {quoted(CUES[kind])} THEN 1 WHEN x.before RLIKE {quoted(AGAINST)} THEN -1 ELSE 0 END"
    features = ", ".join(
        (
            f"least(length({DIGITS}), 20)",
            "int(x.said RLIKE '[A-Za-z]')",
            "int(x.said RLIKE '[ ().-]')",
            "least(length(x.said) div 8, 4)",
            f"int(x.before RLIKE {quoted('^$|[ ' + chr(92) + 'n]$')})",
        )
    )
    key = f"concat_ws('|', '{kind}', {int(base)}, {form}, {gazetteer}, {context}, concat_ws('/', {features}))"
    return f"struct(x.start AS start, {KINDS.index(kind)} AS kind, x.end AS end, {'true' if base else 'false'} AS base, {key} AS key)"


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id and spans: array of (start, kind, end, base, key) in order, base and loose ones."""
    out = docs.select("doc_id", text_or_empty().alias("text"))
    for kind in KINDS:
        out = out.withColumn(f"_{kind}", F.expr(located(BASE[kind], NEEDS[kind])))
        if kind in LOOSE:
            out = out.withColumn(f"_{kind}_loose", F.expr(located(LOOSE[kind], LOOSE_NEEDS[kind])))
    parts = []
    for kind in KINDS:
        good = f"filter(_{kind}, x -> {valid(kind)})"
        parts.append(f"transform({good}, x -> {votes(kind, True)})")
        if kind in LOOSE:
            clear = let(good, "good", apart("good", f"_{kind}_loose"))
            parts.append(f"transform({clear}, x -> {votes(kind, False)})")
    failed = f"filter(_card, x -> length({DIGITS}) BETWEEN 12 AND 19 AND NOT ({valid('card')}))"
    parts.append(f"transform({failed}, x -> {votes('card', False)})")
    return out.select("doc_id", F.expr(f"array_sort(concat({', '.join(parts)}))").alias("spans"))


def _split(key: str) -> tuple[str, tuple[int, ...], tuple[str, ...]]:
    kind, *found, features = key.split("|")
    return kind, tuple(map(int, found)), tuple(features.split("/"))


def estimate(counts: dict[str, int], rounds: int = 50) -> dict[str, float]:
    """Posterior that a candidate is personal data, for each counted key.

    Labelers are taken as independent given the truth; rates start from the sign of the
    vote sum, are smoothed by one, and are shared by all candidates of a kind.
    """
    keys = {k: _split(k) for k in counts}
    belief = {k: 0.9 if sum(v) > 0 else 0.1 for k, (_, v, _) in keys.items()}
    for _ in range(rounds):
        prior: dict = {}
        rate: dict = {}
        for k, (kind, found, _) in keys.items():
            for truth, p in ((1, belief[k]), (0, 1 - belief[k])):
                prior[kind, truth] = prior.get((kind, truth), 1.0) + p * counts[k]
                for i, v in enumerate(found):
                    rate[kind, truth, i, v] = rate.get((kind, truth, i, v), 1.0) + p * counts[k]
        new = {}
        for k, (kind, found, _) in keys.items():
            odds = math.log(prior[kind, 1] / prior[kind, 0])
            for i, v in enumerate(found):
                odds += math.log(rate[kind, 1, i, v] / (prior[kind, 1] + 2)) - math.log(rate[kind, 0, i, v] / (prior[kind, 0] + 2))
            new[k] = 1 / (1 + math.exp(-max(-50.0, min(50.0, odds))))
        moved = max((abs(new[k] - belief[k]) for k in new), default=0.0)
        belief = new
        if moved < 1e-9:
            break
    return belief


def classify(counts: dict[str, int], belief: dict[str, float]) -> dict[str, float]:
    """The final classifier's probability by key: naive Bayes on span features, soft labels."""
    keys = {k: _split(k) for k in counts}
    mass: dict = {}
    for k, (kind, _, features) in keys.items():
        for truth, p in ((1, belief[k]), (0, 1 - belief[k])):
            mass[kind, truth] = mass.get((kind, truth), 1.0) + p * counts[k]
            for i, f in enumerate(features):
                mass[kind, truth, i, f] = mass.get((kind, truth, i, f), 1.0) + p * counts[k]
    out = {}
    for k, (kind, _, features) in keys.items():
        odds = math.log(mass[kind, 1] / mass[kind, 0])
        for i, f in enumerate(features):
            odds += math.log(mass[kind, 1, i, f] / (mass[kind, 1] + 1)) - math.log(mass[kind, 0, i, f] / (mass[kind, 0] + 1))
        out[k] = 1 / (1 + math.exp(-max(-50.0, min(50.0, odds))))
    return out


def accepted(found: DataFrame) -> list[str]:
    """Keys of loose candidates that belief and classifier accept; ``found`` has spans."""
    rows = found.select(F.explode("spans.key").alias("key")).groupBy("key").count().collect()
    counts = {r["key"]: r["count"] for r in rows}
    belief = estimate(counts)
    final = classify(counts, belief)
    return sorted(k for k in counts if k.split("|")[1] == "0" and belief[k] > 0.5 and final[k] > 0.5)


def find(docs: DataFrame) -> DataFrame:
    """doc_id and spans: array of (start, kind, end, base), base spans and the accepted others.

    Offsets are code points, end exclusive, in order of start, then kind (its place in
    ``KINDS``). Null texts count as empty. An empty table gives an empty result.
    """
    found = written(candidates(docs), "pii")
    keys = accepted(found)
    ok = F.array(*map(F.lit, keys)) if keys else F.lit(None).cast("array<string>")
    kept = F.filter("spans", lambda x: x["base"] | F.coalesce(F.array_contains(ok, x["key"]), F.lit(False)))
    return found.select(
        "doc_id", F.transform(kept, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end"), x["base"].alias("base"))).alias("spans")
    )


def listed(spans: Column) -> Column:
    """``kind:start:end`` of spans, comma-joined."""
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", names[x["kind"]], x["start"], x["end"])), ",")


def report(docs: DataFrame) -> DataFrame:
    """Counts and digest of the base spans, and all spans, of every document."""
    found = find(docs)
    base = F.filter("spans", lambda x: x["base"])
    counts = [F.expr(f"cast(size(filter(spans, x -> x.base AND x.kind = {i})) AS long) AS n_{k}") for i, k in enumerate(KINDS)]
    return found.select("doc_id", *counts, F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"))
