"""Random numbers that any engine with md5 can repeat: no dependence on partitions, order or retries."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def _part(x: Column | str | int) -> Column:
    return x if isinstance(x, Column) else F.lit(str(x))


def hash_uniform(seed: int, key: Column, draw: Column | int) -> Column:
    """Uniform in (0, 1): the first 8 hex digits of md5(seed|key|draw), plus a half, over 2**32."""
    digits = F.substring(F.md5(F.concat_ws("|", _part(seed), key.cast("string"), _part(draw).cast("string"))), 1, 8)
    return (F.conv(digits, 16, 10).cast("double") + 0.5) / 4294967296.0


def uniform(seed: int, key: int, draw: int) -> float:
    """The same number in Python."""
    return (int(hashlib.md5(f"{seed}|{key}|{draw}".encode()).hexdigest()[:8], 16) + 0.5) / 4294967296.0


def race_key(seed: int, key: Column, draw: Column | int, weight: Column) -> Column:
    """Least for an item drawn with probability proportional to its weight; null where the weight is not positive."""
    return F.when(weight > 0, -F.ln(hash_uniform(seed, key, draw)) / weight)
