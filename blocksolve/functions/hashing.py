"""Numbers that a seed and keys fix, the same in any SQL engine with md5."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(seed: int, *keys: Column | int | str) -> Column:
    """In (0, 1): the first eight hexadecimal digits of md5(seed|key|...)."""
    parts = [F.lit(str(seed)), *[(k if isinstance(k, Column) else F.lit(str(k))).cast("string") for k in keys]]
    return (F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") + 0.5) / float(2**32)


def uniform_of(seed: int, *keys: int | str) -> float:
    """The same number on the driver."""
    text = "|".join(str(k) for k in (seed, *keys))
    return (int(hashlib.md5(text.encode()).hexdigest()[:8], 16) + 0.5) / 2**32


def gaussian(seed: int, *keys: Column | int | str) -> Column:
    """Standard normal, by the Box-Muller transform of two uniforms."""
    return F.sqrt(-2.0 * F.log(uniform(seed, *keys, 1))) * F.cos(2 * math.pi * uniform(seed, *keys, 2))


def block_of(key: Column, parts: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(parts)).cast("int")
