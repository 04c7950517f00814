"""Uniforms and normals as functions of keys: equal in every engine, under retries and at any partitioning.

For tests and simulation. A release whose seed is known has no privacy: ``privacy.SystemNoise`` draws from the
operating system instead.
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def _text(keys: tuple) -> Column:
    return F.concat_ws("|", *[k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in keys])


def _part(md5: Column, at: int) -> Column:
    return (F.conv(F.substring(md5, at, 8), 16, 10).cast("long") + 0.5) / F.lit(4294967296.0)


def uniform(*keys: Column | str | int) -> Column:
    """In (0, 1), from the first 32 bits of md5 over the keys joined by '|'."""
    return _part(F.md5(_text(keys)), 1)


def normal(*keys: Column | str | int) -> Column:
    """Standard normal by Box-Muller over the first 64 bits."""
    m = F.md5(_text(keys))
    return F.sqrt(-2 * F.ln(_part(m, 1))) * F.cos(F.lit(2 * math.pi) * _part(m, 9))


def py_uniform(*keys: object) -> float:
    return (int(hashlib.md5("|".join(map(str, keys)).encode()).hexdigest()[:8], 16) + 0.5) / 4294967296.0


def py_normal(*keys: object) -> float:
    m = hashlib.md5("|".join(map(str, keys)).encode()).hexdigest()
    u, v = ((int(m[i : i + 8], 16) + 0.5) / 4294967296.0 for i in (0, 8))
    return math.sqrt(-2 * math.log(u)) * math.cos(2 * math.pi * v)


def sql_uniform(*keys: str) -> str:
    """DuckDB SQL; keys are SQL expressions."""
    return f"((CAST('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 8) AS BIGINT) + 0.5) / 4294967296.0)"


def sql_normal(*keys: str) -> str:
    m = f"md5(concat_ws('|', {', '.join(keys)}))"
    u, v = (f"((CAST('0x' || substr({m}, {i}, 8) AS BIGINT) + 0.5) / 4294967296.0)" for i in (1, 9))
    return f"(sqrt(-2 * ln({u})) * cos({2 * math.pi!r} * {v}))"
