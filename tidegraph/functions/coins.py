"""Coins that are functions of a key, so a retried task or a re-evaluated plan draws the same values."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def coin01(key: Column, *salt, kind: str = "xx") -> Column:
    """A uniform value in [0, 1) from key and salt (seed, iteration, purpose ...). kind: xx (fast) or md5 (also computable in other engines)."""
    if kind == "xx":
        return F.pmod(F.xxhash64(key, *[F.lit(str(s)) for s in salt]), F.lit(1 << 52)).cast("double") / float(1 << 52)
    if kind != "md5":
        raise ValueError(f"unknown coin: {kind}")
    text = F.concat_ws(":", *[F.lit(str(s)) for s in salt], key.cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") / float(1 << 52)
