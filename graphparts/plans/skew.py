"""Joins of rows with one value for each key, where a few keys may hold a large share of all rows.

Keys of more than ``HUB`` rows, and of more than one row in ``SHARES`` of all, meet their value by a
broadcast of those keys alone. By that bound there are at most ``SHARES`` of them, however large the
table. All other keys are joined by a shuffle, in which no key is large.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HUB, SHARES = 1000, 10_000
#: The most rows of a few numbers that go to every executor whole, some 100 MB; larger tables are joined by a shuffle.
SMALL = 2_000_000


def hub_limit(total: int) -> int:
    """The most rows of a key that is joined by a shuffle, of ``total`` rows."""
    return max(HUB, total // SHARES)


def join_per_key(rows: DataFrame, values: DataFrame, key: str, count: str, most: int) -> DataFrame:
    """``rows`` with the columns of ``values(key, count, ...)`` but ``count``; ``values`` is read twice, so it should be written."""
    wanted = [c for c in values.columns if c != count]
    hubs = F.broadcast(values.where(F.col(count) > most).select(*wanted))
    rest = rows.join(hubs.select(key), key, "left_anti").join(values.where(F.col(count) <= most).select(*wanted), key)
    return rows.join(hubs, key).unionByName(rest)


def hashed(values: DataFrame, rows: int) -> DataFrame:
    """``values``, of ``rows`` rows, as the side of a join that is hashed, so that the other side is not sorted, and where ``values`` are few stays where it is."""
    return F.broadcast(values) if rows <= SMALL else values.hint("shuffle_hash")
