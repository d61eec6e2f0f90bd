"""Keyed randomness: the same key draws the same number in any task, retry or partitioning, and in SQL."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(salt: str, *key: Column | str) -> Column:
    """In (0, 1): the first 52 bits of SHA-256 over salt|key, plus a half."""
    parts = [F.col(k) if isinstance(k, str) else k for k in key]
    text = F.concat_ws("|", F.lit(salt), *[p.cast("string") for p in parts])
    return (F.conv(F.substring(F.sha2(text, 256), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def laplace(scale: float | Column, salt: str, *key: Column | str) -> Column:
    """Laplace noise of mean 0 by the inverse of its distribution."""
    u = uniform(salt, *key)
    b = F.lit(scale) if isinstance(scale, (int, float)) else scale
    return -b * F.signum(u - 0.5) * F.ln(1 - 2 * F.abs(u - 0.5))


def uniform_value(salt: str, *key) -> float:
    """The same draw on the driver."""
    import hashlib

    h = hashlib.sha256("|".join([salt, *map(str, key)]).encode()).hexdigest()[:13]
    return (int(h, 16) + 0.5) / float(1 << 52)


def laplace_value(scale: float, salt: str, *key) -> float:
    u = uniform_value(salt, *key)
    return -scale * math.copysign(1, u - 0.5) * math.log(1 - 2 * abs(u - 0.5)) if u != 0.5 else 0.0


def uniform_sql(text: str) -> str:
    """DuckDB expression of uniform() for a SQL string expression that holds salt|key."""
    return f"((('0x' || substr(sha256({text}), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"


def laplace_sql(scale: str, text: str) -> str:
    u = uniform_sql(text)
    return f"(-({scale}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"
