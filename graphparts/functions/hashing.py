"""A portable integer hash: the same bits in Spark, in plain Python and in any SQL engine.

It stays below 2**53 in every step, so it cannot overflow 64-bit arithmetic, and stands for
every random draw of the library: results do not depend on how rows are partitioned.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# The Mersenne prime 2**31 - 1 and two multipliers of full period.
PRIME, FIRST, SECOND = 2147483647, 48271, 16807


def portable_hash(x: Column | str, seed: int | Column = 0) -> Column:
    """A whole number in [0, PRIME) for a non-negative whole number ``x``."""
    x = F.col(x) if isinstance(x, str) else x
    s = seed if isinstance(seed, Column) else F.lit(int(seed)).cast("bigint")
    return ((x.cast("bigint") % PRIME) * FIRST + s % PRIME) % PRIME * SECOND % PRIME


def portable_hash_of(x: int, seed: int = 0) -> int:
    return (x % PRIME * FIRST + seed % PRIME) % PRIME * SECOND % PRIME


def portable_draw(x: Column | str, seed: int = 0) -> Column:
    """Like :func:`portable_hash`, but squared in between: draws of different seeds are not shifts of each other."""
    h = portable_hash(x, seed)
    return portable_hash(h * h % PRIME, seed + 1)
