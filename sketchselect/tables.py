"""Loading tables and writing intermediate results where all executors see them."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession

from sketchselect.schema import TABLES

_own_dirs: dict[str, tempfile.TemporaryDirectory] = {}
_written: dict[str, list[str]] = {}


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A given table with its declared schema; columns that it lacks would read as null."""
    return spark.read.schema(TABLES[table]).parquet(f"{sf_dir}/{table}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """The rows over all cores where their files make fewer parts than that; else unchanged.

    Features of text cost far more than moving a small table once.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``.

    Where the setting is absent (tests on one machine) a temporary folder stands in;
    on a cluster without the setting this raises, since a machine-local folder would
    lose rows.
    """
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder shared by driver and executors")
    if "own" not in _own_dirs:
        _own_dirs["own"] = tempfile.TemporaryDirectory(prefix="sketchselect-")
    return "file://" + _own_dirs["own"].name


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


_scope: ContextVar[str] = ContextVar("scope", default="query")


@contextmanager
def scoped(spark: SparkSession) -> Iterator[None]:
    """What ``written`` makes in the block, in this thread and without a scope of its own, is deleted at its end."""
    token = _scope.set(uuid.uuid4().hex)
    try:
        yield
    finally:
        release(spark, _scope.get())
        _scope.reset(token)
        # shuffle files stay until the driver's collector finds that no plan needs them
        gc.collect()
        spark.sparkContext._jvm.System.gc()


def written(df: DataFrame, tag: str, scope: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage reliably."""
    spark = df.sparkSession
    scope = _scope.get() if scope is None else scope
    path = new_path(spark, tag)
    df.write.parquet(path)
    _written.setdefault(scope, []).append(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession, scope: str = "query") -> None:
    """Delete the tables that ``written`` made under ``scope``; call once results are stored."""
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for path in _written.pop(scope, []):
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(conf).delete(p, True)
