"""Counter-based uniforms: a draw depends on its key only, never on partitions or retries."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def u01_md5(*parts: Column | int | str) -> Column:
    """Uniform in (0, 1) from the first 12 hex digits of an md5; DuckDB can do the same."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    key = F.concat_ws("|", *[c.cast("string") for c in cols])
    return (F.conv(F.substring(F.md5(key), 1, 12), 16, 10).cast("double") + 0.5) / float(1 << 48)


def u01_md5_np(*parts: np.ndarray | int) -> np.ndarray:
    """The numpy twin of u01_md5 for whole numbers, one digest an element."""
    rows = np.broadcast_arrays(*[np.atleast_1d(p) for p in parts])
    keys = ("|".join(map(str, key)) for key in zip(*(r.tolist() for r in rows)))
    return np.array([(int(hashlib.md5(k.encode()).hexdigest()[:12], 16) + 0.5) / float(1 << 48) for k in keys])


def duck_u01(*parts: str) -> str:
    """The DuckDB text of u01_md5; parts are SQL expressions."""
    key = "concat_ws('|', " + ", ".join(parts) + ")"
    return f"((('0x' || substr(md5({key}), 1, 12))::BIGINT + 0.5) / 281474976710656.0)"


def u01_fast(*parts: Column | int) -> Column:
    """Uniform in (0, 1) from a 64-bit hash; stays in generated code."""
    cols = [p.cast("long") if isinstance(p, Column) else F.lit(p).cast("long") for p in parts]
    return (F.shiftrightunsigned(F.xxhash64(*cols), 11).cast("double") + 0.5) / float(1 << 53)


_P = [np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]


def _rotl(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint64(k)) | (x >> np.uint64(64 - k))


def xxhash64_np(*parts: np.ndarray | int) -> np.ndarray:
    """Spark's xxhash64 of a sequence of longs, for arrays."""
    with np.errstate(over="ignore"):
        shape = np.broadcast_shapes(*[np.shape(p) for p in parts])
        h = np.full(shape, 42, dtype=np.uint64)
        for p in parts:
            x = np.broadcast_to(np.asarray(p, dtype=np.int64), shape).view(np.uint64)
            h = h + _P[4] + np.uint64(8)
            h = h ^ (_rotl(x * _P[1], 31) * _P[0])
            h = _rotl(h, 27) * _P[0] + _P[3]
            h = (h ^ (h >> np.uint64(33))) * _P[1]
            h = (h ^ (h >> np.uint64(29))) * _P[2]
            h = h ^ (h >> np.uint64(32))
        return h


def u01_np(*parts: np.ndarray | int) -> np.ndarray:
    """The numpy twin of u01_fast."""
    return ((xxhash64_np(*parts) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)
