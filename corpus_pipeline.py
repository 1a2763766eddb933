"""A corpus pipeline of five stages over the documents table.

Each stage gets what the one before it kept, read again from Parquet. All but the last
return the columns of documents.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sketchselect.llm import decontaminate, langid, mixing, neardup, sharding
from sketchselect.llm.common import load, release, written

#: Margins below this are too narrow to name a language.
MIN_MARGIN = 0.005
#: SQL cannot express the stages; tests compare them with brute force.
ORACLE_SQL = None

SCOPE = "pipeline-stage"


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the compression classifier names; the rejected ones go.

    Rejected are texts that are null or have no letter, and those with too narrow a margin.
    Without any labelled text to learn from, nothing can be named and nothing is rejected.
    """
    known = langid.learn(docs)
    if not known:
        return docs
    lang, score = (name + "_" * len(docs.columns) for name in ("lang_pred", "lang_score"))
    found = langid.predict(docs, known, docs.columns, (lang, score))
    return found.filter((F.col(lang) != "und") & (F.col(score) >= MIN_MARGIN)).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8)."""
    return neardup.drop_near_duplicates(docs, size=5, similarity=0.8, scope=SCOPE)


def decontaminate_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    release(spark, SCOPE)
    return decontaminate.decontaminated(docs, load(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it (whole texts: taken words / size, rounded)."""
    return mixing.repeated(docs)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with their shard and slot; equal texts share a shard."""
    return sharding.sharded(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language_id", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", decontaminate_benchmark),
    ("mixing", mix_sources),
    ("sharding", shard),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs
