"""Counter-based randomness: a draw is a hash of its keys, so a retried task, another partitioning or another engine repeats it.

Back ends: `xx` (Spark's xxhash64 over longs, and the same in numpy) for work, `md5` for draws that DuckDB repeats.
Draws are integers in [0, 2**48). Never rand(): it depends on the partitioning.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 48
#: Streams keep draws of different purposes apart.
ROOT, STEP, NEGATIVE, PRUNE, SPLIT, INIT, AUGMENT, ALIAS = range(1, 9)

_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def draw(seed: int, stream: int, *keys: Column | str | int, backend: str = "xx") -> Column:
    """A LONG column in [0, 2**48)."""
    columns = [F.lit(seed).cast("long"), F.lit(stream).cast("long"), *((F.lit(k) if isinstance(k, int) else F.col(k) if isinstance(k, str) else k).cast("long") for k in keys)]
    if backend == "xx":
        return F.pmod(F.xxhash64(*columns), F.lit(SPAN))
    if backend == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws("|", *(c.cast("string") for c in columns))), 1, 12), 16, 10).cast("long")
    raise ValueError(f"unknown back end {backend!r}")


def draw_sql(seed: int, stream: int, *keys: str) -> str:
    """The md5 draw as DuckDB text."""
    return f"('0x' || substr(md5(concat_ws('|', {seed}, {stream}, {', '.join(keys)})), 1, 12))::BIGINT"


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def draw_numpy(seed: int, stream: int, *keys: np.ndarray | int, backend: str = "xx") -> np.ndarray:
    """The same draws over arrays of longs."""
    shape = np.broadcast(*(np.asarray(k) for k in keys)).shape if keys else ()
    if backend == "md5":
        rows = np.broadcast_arrays(*(np.atleast_1d(np.asarray(k)) for k in keys))
        out = [int(hashlib.md5("|".join(map(str, (seed, stream, *(int(v) for v in row)))).encode()).hexdigest()[:12], 16) for row in zip(*rows, strict=True)]
        return np.array(out, dtype=np.int64).reshape(shape)
    with np.errstate(over="ignore"):
        h = np.full(shape, 42, dtype=np.uint64)
        for k in (seed, stream, *keys):
            x = np.broadcast_to(np.asarray(k, dtype=np.int64), shape).astype(np.uint64)
            h = h + _P5 + np.uint64(8)
            h = h ^ (_rotl(x * _P2, 31) * _P1)
            h = _rotl(h, 27) * _P1 + _P4
            h = (h ^ (h >> np.uint64(33))) * _P2
            h = (h ^ (h >> np.uint64(29))) * _P3
            h = h ^ (h >> np.uint64(32))
    return (h & np.uint64(SPAN - 1)).astype(np.int64)
