"""Bucket and sign hashes of feature ids: as columns, as numpy, and as portable SQL.

Two families. ``murmur3`` is 32-bit Murmur3 of the row's seed and the id, which is what
Spark's ``hash`` computes, so it stays in generated code. ``affine`` is (a x + b) mod
(2^31 - 1), pairwise independent and the same in any engine.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import Literal

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


@dataclass(frozen=True)
class SketchSpec:
    """Shape and hashing of a Count Sketch: ``rows`` hash functions of ``buckets`` each."""

    rows: int = 5
    buckets: int = 64
    seed: int = 0
    family: Literal["murmur3", "affine"] = "murmur3"
    query: Literal["median", "mean"] = "median"

    def __post_init__(self):
        if self.rows < 1 or self.buckets < 1:
            raise ValueError("a sketch needs at least one row and one bucket")

    @property
    def cells(self) -> int:
        return self.rows * self.buckets

    @classmethod
    def from_cf(cls, p: int, cf: float, rows: int = 5, classes: int = 1, **kw) -> SketchSpec:
        """The sketch whose cells, of all classes together, are p / cf."""
        return cls(rows=rows, buckets=max(1, round(p / cf / rows / classes)), **kw)

    @classmethod
    def from_error(cls, eps: float, delta: float, **kw) -> SketchSpec:
        """Cells of order 1/eps^2 per row, rows of order log(1/delta)."""
        return cls(rows=max(1, 2 * round(np.log(1 / delta) / 2) + 1), buckets=max(1, int(np.ceil(np.e / eps**2))), **kw)

    @classmethod
    def from_bytes(cls, size: int, rows: int = 5, **kw) -> SketchSpec:
        return cls(rows=rows, buckets=max(1, size // 8 // rows), **kw)

    def compression(self, p: int, classes: int = 1) -> float:
        return p / (self.cells * classes)

    def with_(self, **kw) -> SketchSpec:
        return replace(self, **kw)


def bucket_seed(spec: SketchSpec, row: int) -> int:
    return spec.seed * 1000 + row


def sign_seed(spec: SketchSpec, row: int) -> int:
    return spec.seed * 1000 + 500 + row


def affine_terms(seed: int) -> tuple[int, int]:
    """Multiplier and offset of one affine hash: fixed by the seed, multiplier not zero."""
    return (seed * 48271 + 1103515245) % (PRIME - 1) + 1, (seed * 69621 + 12345) % PRIME


# ---- columns


def bucket(col: Column, row: int, spec: SketchSpec) -> Column:
    if spec.family == "murmur3":
        return F.pmod(F.hash(F.lit(bucket_seed(spec, row)), col), F.lit(spec.buckets))
    return (_affine(col, bucket_seed(spec, row)) % spec.buckets).cast("int")


def sign(col: Column, row: int, spec: SketchSpec) -> Column:
    if spec.family == "murmur3":
        return F.lit(1) - F.lit(2) * F.hash(F.lit(sign_seed(spec, row)), col).bitwiseAND(F.lit(1))
    return (F.lit(1) - F.lit(2) * (_affine(col, sign_seed(spec, row)) % 2)).cast("int")


def _affine(col: Column, seed: int) -> Column:
    a, b = affine_terms(seed)
    # both factors are below 2^31, so the product stays a long
    return F.pmod(F.pmod(col, F.lit(PRIME)) * F.lit(a) + F.lit(b), F.lit(PRIME))


def places(col: Column, spec: SketchSpec) -> Column:
    """Array of (row, bucket, sign) of an id."""
    return F.array(
        *[
            F.struct(F.lit(j).alias("row"), bucket(col, j, spec).alias("bucket"), sign(col, j, spec).alias("sign"))
            for j in range(spec.rows)
        ]
    )


def feature_id(col: Column) -> Column:
    """64-bit id of a string feature, fast."""
    return F.xxhash64(col)


def portable_id(col: Column) -> Column:
    """60-bit id of a string feature, the same in any engine: leading digits of its md5."""
    return F.conv(F.substring(F.md5(col), 1, 15), 16, 10).cast("long")


# ---- numpy


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint32(n)) | (x >> np.uint32(32 - n))


def _round(h: np.ndarray, k: np.ndarray) -> np.ndarray:
    k = _rotl(k * np.uint32(0xCC9E2D51), 15) * np.uint32(0x1B873593)
    return _rotl(h ^ k, 13) * np.uint32(5) + np.uint32(0xE6546B64)


def _finish(h: np.ndarray, size: int) -> np.ndarray:
    h = h ^ np.uint32(size)
    h = (h ^ (h >> np.uint32(16))) * np.uint32(0x85EBCA6B)
    h = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
    return h ^ (h >> np.uint32(16))


def murmur3(ids: np.ndarray, seed: int) -> np.ndarray:
    """Signed 32-bit hash of int64 ids, equal to Spark's ``hash(int seed, bigint id)``."""
    return murmur3_all(ids, [seed])[0]


def murmur3_all(ids: np.ndarray, seeds: list[int]) -> np.ndarray:
    """One row of hashes per seed."""
    with np.errstate(over="ignore"):
        start = _finish(_round(np.array([42], np.uint32), np.array([s & 0xFFFFFFFF for s in seeds], np.uint32)), 4)[:, None]
        x = ids.astype(np.int64).view(np.uint64)
        h = _round(start, (x & np.uint64(0xFFFFFFFF)).astype(np.uint32))
        h = _round(h, (x >> np.uint64(32)).astype(np.uint32))
        return _finish(h, 8).view(np.int32)


def np_affine(ids: np.ndarray, seed: int) -> np.ndarray:
    a, b = affine_terms(seed)
    return (np.mod(ids.astype(np.int64), PRIME) * a + b) % PRIME


def np_places(ids: np.ndarray, spec: SketchSpec) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and signs, one row per hash function."""
    rows = range(spec.rows)
    if spec.family == "murmur3":
        h = murmur3_all(ids, [bucket_seed(spec, j) for j in rows] + [sign_seed(spec, j) for j in rows])
        return np.mod(h[: spec.rows].astype(np.int64), spec.buckets), 1.0 - 2.0 * (h[spec.rows :] & 1)
    buckets = [np_affine(ids, bucket_seed(spec, j)) % spec.buckets for j in rows]
    signs = [1 - 2 * (np_affine(ids, sign_seed(spec, j)) % 2) for j in rows]
    return np.array(buckets), np.array(signs, np.float64)


# ---- portable SQL (no engine's own hash function)


def sql_affine(x: str, seed: int) -> str:
    a, b = affine_terms(seed)
    return f"((({x}) % {PRIME}) * {a} + {b}) % {PRIME}"


def sql_bucket(x: str, row: int, spec: SketchSpec) -> str:
    """Affine bucket of a non-negative id."""
    return f"CAST(({sql_affine(x, bucket_seed(spec, row))}) % {spec.buckets} AS INTEGER)"


def sql_sign(x: str, row: int, spec: SketchSpec) -> str:
    return f"CAST(1 - 2 * (({sql_affine(x, sign_seed(spec, row))}) % 2) AS INTEGER)"


def sql_id(x: str) -> str:
    """The portable id of a string, in DuckDB's dialect."""
    return f"CAST('0x' || substr(md5({x}), 1, 15) AS BIGINT)"


def sql_murmur3(source: str, keep: str, x: str, seed: str) -> str:
    """DuckDB: ``keep`` columns and ``h`` (signed 32-bit) for ids ``x`` and seeds ``seed`` of a source."""
    m = 4294967295
    steps = []

    def word(value: str) -> None:
        steps.append(f"(({value}) * 3432918353) & {m} AS k")
        steps.append(f"((k << 15) | (k >> 17)) & {m} AS k")
        steps.append(f"(k * 461845907) & {m} AS k")
        steps.append("xor(h, k) AS h")
        steps.append(f"((h << 13) | (h >> 19)) & {m} AS h")
        steps.append(f"(h * 5 + 3864292196) & {m} AS h")

    def finish(size: int) -> None:
        steps.append(f"xor(h, {size}::UBIGINT) AS h")
        steps.append("xor(h, h >> 16) AS h")
        steps.append(f"(h * 2246822507) & {m} AS h")
        steps.append("xor(h, h >> 13) AS h")
        steps.append(f"(h * 3266489909) & {m} AS h")
        steps.append("xor(h, h >> 16) AS h")

    word("s")
    finish(4)
    word(f"u & {m}")
    word("u >> 32")
    finish(8)
    names = keep
    sql = f"SELECT {names}, ({x})::UBIGINT AS u, ({seed})::UBIGINT AS s, 42::UBIGINT AS h, 0::UBIGINT AS k FROM {source}"
    for step in steps:
        body, name = step.rsplit(" AS ", 1)
        others = [c for c in ("u", "s", "h", "k") if c != name]
        sql = f"SELECT {names}, {', '.join(others)}, ({body})::UBIGINT AS {name} FROM ({sql})"
    return f"SELECT {names}, CAST(CASE WHEN h >= 2147483648 THEN h::BIGINT - 4294967296 ELSE h::BIGINT END AS INTEGER) AS h FROM ({sql})"
