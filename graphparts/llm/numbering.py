"""Gapless numbers within groups of any size.

A group is dealt into parts; a row's number is the count of rows in the earlier parts plus
its place in its own. Only counts are summed across parts, so no group, however large, is
gathered in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def numbered(df: DataFrame, group: list[str], part: str, order: list[Column], name: str) -> DataFrame:
    """``df`` with ``name``, a long from 0 without gaps within each ``group``.

    ``part`` is a column of non-null whole numbers, equal for rows that may be sorted together;
    rows are numbered by part and then by ``order``.
    """
    keys = [*group, part]
    counts = df.groupBy(*keys).agg(F.count("*").alias("_n"))
    before = Window.partitionBy(*group).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*keys, F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("_place", place.cast("bigint")).join(offsets, keys).withColumn(name, F.col("_place") - 1 + F.col("_before")).drop("_place", "_before")
