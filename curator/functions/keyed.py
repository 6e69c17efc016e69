"""Keyed draws: the same number for an id on any partitioning, and in SQL engines.

Draws for different purposes are independent: the purpose is part of what is hashed, so that a subset is not made of the
rows that its centres were fitted on.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SEED = 42


def key32(column: str | Column, seed: int = SEED, purpose: str = "") -> Column:
    """First eight hex digits of md5(seed:purpose:id) as an integer."""
    c = F.col(column) if isinstance(column, str) else column
    salt = f"{seed}:{purpose}:" if purpose else f"{seed}:"
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), c.cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")


def draw(column: str | Column, seed: int = SEED, purpose: str = "") -> Column:
    """Uniform in [0, 1)."""
    return key32(column, seed, purpose) / F.lit(float(2**32))
