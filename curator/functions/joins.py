"""Joins against tables whose size is counted first, and against keys that very many rows share."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A side is broadcast up to this many bytes, by its counted rows and stated width; beyond, it is shuffled.
BROADCAST_BYTES = 32 << 20
#: A value that more than one in so many rows have is joined apart from the others.
SHARES = 4096


def small(df: DataFrame, row_bytes: int) -> DataFrame:
    """``df`` (a written table: counting it is cheap), marked for broadcast if it is proven to be small."""
    return F.broadcast(df) if df.count() * row_bytes <= BROADCAST_BYTES else df


def spread(rows: DataFrame, table: DataFrame, on: list[str], how: str = "inner", n: str = "n") -> DataFrame:
    """``rows`` joined (inner or left) with ``table``: a row for each value of ``on``, with ``n``, how many of ``rows`` have it.

    ``table`` is a written one.  Values that more than 1/SHARES of the counted rows have are fewer than SHARES, so that
    part of the table is broadcast; the rows of other values are shuffled, and none of those fills a task by itself.
    """
    total = table.agg(F.sum(n)).first()[0]
    if total is None:
        return rows.join(table, on, how)
    hot, rest = table.where(F.col(n) * SHARES > total), table.where(F.col(n) * SHARES <= total)
    if hot.isEmpty():
        return rows.join(rest, on, how)
    cold = rows.join(F.broadcast(hot.select(*on)), on, "left_anti").join(rest, on, how)
    return rows.join(F.broadcast(hot), on).unionByName(cold)
