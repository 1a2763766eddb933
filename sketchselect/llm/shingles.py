"""Words and hashed word shingles of whole texts."""

from __future__ import annotations

import numpy as np
import xxhash

SEED = 42
#: Hashes whose bits are laid out at a time.
STEP = 1 << 16


def words(text: str | None) -> list[bytes]:
    """Words of a text with A-Z lower-cased; bytes of UTF-8, cut at ASCII white space only."""
    return text.encode().lower().split() if text else []


def hashes(found: list[bytes], size: int) -> np.ndarray:
    """XXH64 (seed 42) of every run of ``size`` words, repeats included.

    Fewer words make one shingle of them all; none make none.
    """
    n = len(found)
    if not n:
        return np.empty(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    if n <= size:
        return np.array([digest(b" ".join(found), SEED)], np.uint64)
    whole = b" ".join(found)
    ends = np.cumsum(np.fromiter(map(len, found), np.int64, n) + 1)
    starts = (ends[: n - size + 1] - np.fromiter(map(len, found[: n - size + 1]), np.int64) - 1).tolist()
    stops = (ends[size - 1 :] - 1).tolist()
    return np.array([digest(whole[a:b], SEED) for a, b in zip(starts, stops, strict=True)], np.uint64)


def digest(found: list[bytes]) -> int:
    """The hash of one shingle."""
    return xxhash.xxh64_intdigest(b" ".join(found), SEED)


def bits(found: np.ndarray) -> np.ndarray:
    """One row per hash, one column per bit, the highest first."""
    return np.unpackbits(found.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)


def simhash(found: np.ndarray) -> int:
    """Bit i is 1 where it is set in over half of the hashes; zero for none."""
    if not len(found):
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, len(found), STEP):
        ones += bits(found[at : at + STEP]).sum(0, dtype=np.int64)
    over = 2 * ones > len(found)
    return int.from_bytes(np.packbits(over).tobytes(), "big")


def signed(value: int) -> int:
    """An unsigned 64-bit number as the long with the same bits."""
    return value - (1 << 64) if value >> 63 else value
