"""Reproducible pseudo-random columns: md5 of seed and keys, the same in any engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def word(seed: object, *keys: Column | str) -> Column:
    """The leading 32 bits of md5("seed|key|...") as a long."""
    cols = [F.lit(str(seed)), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 8), 16, 10).cast("long")


def uniform(seed: object, *keys: Column | str) -> Column:
    """In [0, 1)."""
    return word(seed, *keys) / F.lit(float(1 << 32))


def bucket(n: int, seed: object, *keys: Column | str) -> Column:
    return (word(seed, *keys) % n).cast("int")
