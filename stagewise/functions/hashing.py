"""One hash family, as Spark expressions and in numpy: what a task builds, any expression can probe."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of XXH64.
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
_START = 42
SEGMENT_SALT = 7


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def _hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = seed + _P5 + np.uint64(8)
    h = h ^ (_rotl(value * _P2, 31) * _P1)
    h = _rotl(h, 27) * _P1 + _P4
    h ^= h >> np.uint64(33)
    h *= _P2
    h ^= h >> np.uint64(29)
    h *= _P3
    return h ^ (h >> np.uint64(32))


def hash_np(seed, keys: np.ndarray) -> np.ndarray:
    """Unsigned 64-bit hashes of 64-bit keys; ``seed`` is a number or one number a key."""
    with np.errstate(over="ignore"):
        s = np.atleast_1d(np.asarray(seed, np.int64)).view(np.uint64)
        return _hash_long(keys.astype(np.int64, copy=False).view(np.uint64), _hash_long(s, np.full(1, _START, np.uint64)))


def hash_col(seed: Column | int, key: Column) -> Column:
    """The same hash as a signed long."""
    return F.xxhash64(seed if isinstance(seed, Column) else F.lit(seed).cast("long"), key)


def below_np(h: np.ndarray, n, part: int = 0) -> np.ndarray:
    """A number below ``n`` from one half of the hash, by multiplying; ``n`` is below 2**31."""
    half = h >> np.uint64(33) if part == 0 else h & np.uint64(0x7FFFFFFF)
    return ((half * np.asarray(n, np.uint64)) >> np.uint64(31)).astype(np.int64)


def below_col(h: Column, n: Column, part: int = 0) -> Column:
    half = F.shiftrightunsigned(h, 33) if part == 0 else h.bitwiseAND(F.lit(0x7FFFFFFF))
    return F.shiftrightunsigned(half * n.cast("long"), 31)


def segment_col(key: Column, parts: int) -> Column:
    return below_col(hash_col(SEGMENT_SALT, key), F.lit(parts)).cast("int")


def portable_hash(key: Column, seed: int) -> Column:
    """31 bits equal in any SQL engine that has md5: its first 8 hex digits as a number."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), key.cast("string"))), 1, 8), 16, 10).cast("long")


def portable_sql(key: str, seed: int) -> str:
    return f"CAST('0x' || substr(md5('{seed}:' || CAST({key} AS VARCHAR)), 1, 8) AS BIGINT)"


def key64(df: DataFrame, keys: Sequence[str]) -> Column:
    """One 64-bit key of a row: a single integer column as it is, anything else digested; null if any part is null."""
    kinds = dict(df.dtypes)
    if len(keys) == 1 and kinds[keys[0]] in ("tinyint", "smallint", "int", "bigint"):
        return F.col(keys[0]).cast("long")
    known = F.lit(True)
    for c in keys:
        known = known & F.col(c).isNotNull()
    parts = [F.to_json(c) if kinds[c].startswith("map") else F.col(c) for c in keys]  # maps have no hash of their own
    return F.when(known, F.xxhash64(*parts))
