"""Keyed uniform numbers: the same for the same key in Spark, DuckDB and Python, on any partitioning and on every retry."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def u01(*parts) -> Column:
    """Uniform in [0, 1) from the first 32 bits of md5 over the parts, joined by |. Parts are columns or constants."""
    key = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def u01_sql(*parts: str) -> str:
    """The same as DuckDB SQL; parts are SQL expressions."""
    key = " || '|' || ".join(f"({p})::VARCHAR" for p in parts)
    return f"(('0x' || substr(md5({key}), 1, 8))::BIGINT / 4294967296.0)"


def u01_py(*parts) -> float:
    return int(hashlib.md5("|".join(str(p) for p in parts).encode()).hexdigest()[:8], 16) / 4294967296.0


#: What a number is drawn for: edges, edges of the upper graph, picks, labels, acceptances, starts.
TAGS = {t: i for i, t in enumerate("eckplai", 1)}
#: The primes of the 64-bit hash that Spark's xxhash64 computes.
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x, r: int):
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def fast01_np(seed: int, step: int, tag: str, *parts) -> np.ndarray:
    """Uniform in [0, 1) for arrays of whole numbers: the same as fast01() gives in Spark."""
    h = np.uint64(42)
    with np.errstate(over="ignore"):
        for x in (seed, step, TAGS[tag], *parts):
            x = np.asarray(x, np.int64).astype(np.uint64)
            h = h + _P5 + np.uint64(8)
            h = _turn(h ^ (_turn(x * _P2, 31) * _P1), 27) * _P1 + _P4
            h = (h ^ (h >> np.uint64(33))) * _P2
            h = (h ^ (h >> np.uint64(29))) * _P3
            h = h ^ (h >> np.uint64(32))
    return (h >> np.uint64(11)).astype(np.float64) * 2.0**-53


def fast01(seed: int, step: int, tag: str, *parts: Column) -> Column:
    """As u01(), by Spark's 64-bit hash: for chains, whose draws no SQL has to repeat."""
    h = F.xxhash64(*[F.lit(x).cast("long") for x in (seed, step, TAGS[tag])], *[p.cast("long") for p in parts])
    return F.shiftrightunsigned(h, 11).cast("double") * F.lit(2.0**-53)
