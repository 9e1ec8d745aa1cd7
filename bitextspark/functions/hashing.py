"""Deterministic pseudo-random numbers from content, equal on every engine that has MD5."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def uniform(*parts) -> Column:
    """Uniform in [0, 1) from the parts joined by colons: the first 32 bits of their MD5."""
    key = F.concat_ws(":", *(_c(p).cast("string") for p in parts))
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def bucket(n: int, *parts) -> Column:
    """Integer in [0, n) from the parts."""
    return F.floor(uniform(*parts) * n).cast("int")


def pair_id(src: Column, tgt: Column) -> Column:
    """Content-stable id of a sentence pair."""
    return F.md5(F.concat(src, F.lit("\x01"), tgt))
