"""Deterministic randomness: uniforms are hashes of what they are for, so a task that runs again draws the same.

A uniform is (the first 13 hexadecimal digits of the MD5 of the parts, joined by |, plus a half) / 2^52: strictly
between 0 and 1, and the same in Spark, Python and any SQL engine with MD5.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def _part(x) -> Column:
    return x.cast("string") if isinstance(x, Column) else F.lit(str(x))


def u01(*parts) -> Column:
    digest = F.md5(F.concat_ws("|", *map(_part, parts)).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(SCALE)


def u01_value(*parts) -> float:
    return (int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) + 0.5) / SCALE


def u01_sql(*parts: str) -> str:
    """The same in DuckDB's SQL; parts are SQL expressions."""
    return f"((CAST('0x' || substr(md5(concat_ws('|', {', '.join(f'CAST({p} AS VARCHAR)' for p in parts)})), 1, 13) AS BIGINT) + 0.5e0) / {SCALE:.1f}e0)"


def mixed_uniforms(seed: int, streams: np.ndarray, turn: int) -> np.ndarray:
    """Bulk uniforms without MD5: for each stream number the turn-th draw, by a 64-bit mixing function."""
    x = streams.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64((seed * 0xD1342543DE82EF95 + turn * 0xA0761D6478BD642F) & 0xFFFFFFFFFFFFFFFF)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    x = x ^ (x >> np.uint64(31))
    return ((x >> np.uint64(12)).astype(np.float64) + 0.5) / SCALE


def geometric(u: Column, p: Column, most: Column) -> Column:
    """Failures before the first success at probability p, at most `most`; p = 1 gives 0, p = 0 gives most."""
    gap = F.floor(F.least(most.cast("double"), F.ln(u) / F.log1p(-p)))
    return F.when(p >= 1, F.lit(0).cast("long")).when(p <= 0, most.cast("long")).otherwise(gap)


def truncated_geometric(u: Column, p: Column, n: Column) -> Column:
    """The same under the condition that a success comes among n trials."""
    q = nonempty_probability(p, n)
    place = F.floor(F.log1p(-q * u) / F.log1p(-p))
    return F.when(p >= 1, F.lit(0).cast("long")).otherwise(F.least(place, n.cast("long") - 1))


def nonempty_probability(p: Column, n: Column) -> Column:
    """1 - (1 - p)^n, also for tiny p."""
    return F.when(p >= 1, F.lit(1.0)).otherwise(-F.expm1(n.cast("double") * F.log1p(-p)))


def geometric_value(u: float, p: float, most: int) -> int:
    return 0 if p >= 1 else most if p <= 0 else int(min(float(most), math.log(u) / math.log1p(-p)))


def truncated_geometric_value(u: float, p: float, n: int) -> int:
    if p >= 1:
        return 0
    q = -math.expm1(n * math.log1p(-p))
    return min(n - 1, int(math.log1p(-q * u) / math.log1p(-p)))
