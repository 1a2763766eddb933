"""Language identification by compression.

Per language a bounded sample of labelled texts becomes a raw-content zstandard
dictionary. A text is encoded with every dictionary; the smallest result names the
language, and a tie goes to the language with more learned documents. A narrow margin
between the two smallest means that the text is rejected. Texts are lower-cased and runs
of anything but letters become one space first, on both sides. A long text is encoded in
windows, each from the dictionaries alone, and its sizes are sums over all of them: a
dictionary saves a fixed number of bytes, so over one long stretch its margin would vanish.
"""

from __future__ import annotations

import re
from zlib import crc32

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bounds of the fit: bytes of dictionary for a language and for all of them, texts sampled for a
#: language, passages taken from a text, evenly over all of it.
DICTIONARY_BYTES = 1 << 16
ALL_BYTES = 1 << 26
SAMPLE_TEXTS = 400
PASSAGES = 4
#: Bytes of a text that are encoded at a time.
WINDOW_BYTES = 1 << 14
LETTER = re.compile(r"[^\W\d_]")
GAP = re.compile(r"[\W\d_]+")


def letters(text: str) -> bytes:
    return GAP.sub(" ", text.lower()).encode()


def held_out(doc_id: str = "doc_id") -> Column:
    """True for the documents that learning never sees: crc32 of the id's digits mod 3 is 1."""
    return F.crc32(F.col(doc_id).cast("string")) % 3 == 1


def passages(chars: int) -> Column:
    """At most ``chars`` characters of the text: all of it, or passages at even steps from its start to its end."""
    part = max(1, chars // PASSAGES)
    spread = F.concat_ws(" ", *[F.expr(f"substr(text, 1 + int((length(text) - {part}) * {i}L / {PASSAGES - 1}), {part})") for i in range(PASSAGES)])
    return F.when(F.length("text") <= chars, F.col("text")).otherwise(spread)


def learn(docs: DataFrame, texts: int = SAMPLE_TEXTS, size: int = DICTIONARY_BYTES) -> dict[str, bytes]:
    """Dictionaries by language, the most frequent language first, from a bounded, hash-ordered sample of the labelled texts.

    Needs columns doc_id, text, lang. Rows with null text or lang teach nothing; repeated rows teach
    once. A language is learned from about ``texts`` to 2 ``texts`` rows, drawn over the whole
    table by a hash of id and text, and each gives passages of its whole length. With very many languages
    the dictionaries shrink, so that all of them stay within ``ALL_BYTES``.
    """
    known = docs.filter(~held_out() & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r["lang"]: r["count"] for r in known.groupBy("lang").count().collect()}
    if not counts:
        return {}
    size = max(64, min(size, ALL_BYTES // len(counts)))
    texts = max(1, min(texts, size // 64))
    span = 1 << 40
    rates = docs.sparkSession.createDataFrame([(lang, int(min(span, span * 2 * texts / n + 1))) for lang, n in counts.items()], "_lang string, _rate long")
    drawn = known.select("lang", "doc_id", "text", F.pmod(F.xxhash64("doc_id", "text", F.lit(7)), F.lit(span)).alias("draw"))
    picked = (
        drawn.join(F.broadcast(rates), F.col("lang") == F.col("_lang"))
        .filter("draw < _rate")
        .groupBy("lang", "draw")
        .agg(F.min(F.struct("doc_id", passages(max(PASSAGES, 4 * size // texts)).alias("text"))).alias("row"))
        .select("lang", "row.doc_id", "row.text")
        .collect()
    )
    by: dict[str, list] = {}
    for r in sorted(picked, key=lambda r: (r["lang"], crc32(str(r["doc_id"]).encode()), r["text"])):
        by.setdefault(r["lang"], []).append(r["text"])
    return {
        lang: b"\n".join(map(letters, by.get(lang, [])))[:size]
        for lang in sorted(counts, key=lambda x: (-counts[x], x))
    }


def scorer(dictionaries: dict[str, bytes], level: int = 9):
    """``text -> (language, score)``; score is the margin of the smallest size over the next."""
    langs = list(dictionaries)
    packs = []
    for lang in langs:
        d = zstandard.ZstdCompressionDict(dictionaries[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=level)
        packs.append(
            zstandard.ZstdCompressor(dict_data=d, level=level, write_content_size=False, write_checksum=False, write_dict_id=False)
        )

    def score(text: str | None) -> tuple[str, float]:
        if not text or not langs or not LETTER.search(text):
            return "und", 0.0
        data = letters(text)
        parts = [data[at : at + WINDOW_BYTES] for at in range(0, len(data), WINDOW_BYTES)]
        sizes = sorted((sum(len(p.compress(x)) for x in parts), i) for i, p in enumerate(packs))
        if len(sizes) == 1:
            return langs[0], 1.0
        return langs[sizes[0][1]], (sizes[1][0] - sizes[0][0]) / sizes[1][0]

    return score


def predict(
    docs: DataFrame, dictionaries: dict[str, bytes], keep: list[str], names: tuple[str, str] = ("lang_pred", "score")
) -> DataFrame:
    """``keep`` columns of ``docs`` plus the predicted language and its score, from the text alone.

    ``und`` with score 0 where the text is null or has no letter, or nothing was learned.
    Dictionaries are bounded (``ALL_BYTES``) and broadcast.
    """
    sent = docs.sparkSession.sparkContext.broadcast(dictionaries)
    schema = docs.select(*keep).withColumns({names[0]: F.lit(""), names[1]: F.lit(0.0)}).schema
    read = list(dict.fromkeys([*keep, "text"]))
    at = read.index("text")

    def run(batches):
        score = scorer(sent.value)
        for batch in batches:
            found = [score(t.as_py()) for t in batch.column(at)]
            columns = [batch.column(read.index(k)) for k in keep]
            yield pa.RecordBatch.from_arrays(
                [*columns, pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())],
                names=[*keep, *names],
            )

    return docs.select(*read).mapInArrow(run, schema)


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document, repeated rows included.

    Null texts, texts without a letter and tables that teach nothing give ``und`` with score 0; of
    equally small encodings the language with more learned documents wins. Rows without doc_id are
    never learned from and have a null ``held_out``.
    """
    out = predict(docs, learn(docs), ["doc_id"])
    return out.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
