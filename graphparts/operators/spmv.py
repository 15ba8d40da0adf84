"""Sparse matrix times vector, and what its one- and two-dimensional layouts send.

``matrix(i, j, a)``, ``vector(i, x)``. In one dimension a nonzero lives with the part of its row. In
two, parts form a grid of ``pr`` by ``pc`` processes and nonzero (i, j) lives at
``(part(i) mod pr, part(j) div pr)``, so vector entries travel along a column, partial sums along a row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph
from graphparts.plans.scratch import written


def symmetric(g: Graph) -> DataFrame:
    return g.arcs.select(F.col("v").alias("i"), F.col("u").alias("j"), F.col("w").cast("double").alias("a"))


def multiply(matrix: DataFrame, vector: DataFrame) -> DataFrame:
    x = vector.select(F.col("i").alias("j"), "x")
    return matrix.join(x, "j").groupBy("i").agg(F.sum(F.col("a") * F.col("x")).alias("x"))


def power(matrix: DataFrame, vector: DataFrame, times: int, normalise: bool = True) -> DataFrame:
    """``times`` products in a row, each divided by its largest entry where ``normalise``."""
    for _ in range(times):
        vector = written(multiply(matrix, vector), "vector")
        if normalise:
            top = vector.agg(F.max(F.abs("x"))).first()[0] or 1.0
            vector = vector.select("i", (F.col("x") / top).alias("x"))
    return vector


def layout_1d(matrix: DataFrame, parts: DataFrame) -> DataFrame:
    """``(i, j, a, process, part_i, part_j)``."""
    x = matrix.join(parts.select(F.col("v").alias("i"), F.col("part").alias("part_i")), "i").join(parts.select(F.col("v").alias("j"), F.col("part").alias("part_j")), "j")
    return x.select("i", "j", "a", F.col("part_i").alias("process"), "part_i", "part_j")


def layout_2d(matrix: DataFrame, parts: DataFrame, pr: int, pc: int) -> DataFrame:
    x = layout_1d(matrix, parts)
    return x.withColumn("process", (F.col("part_i") % pr + pr * F.floor(F.col("part_j") / pr)).cast("int"))


def grid(p: int) -> tuple[int, int]:
    """The squarest grid of p processes."""
    pr = next(k for k in range(int(p**0.5), 0, -1) if p % k == 0)
    return pr, p // pr


def comm_stats(laid: DataFrame) -> DataFrame:
    """One row: entries of x to send (expand), partial sums of y to send (fold), the most partners of a process, and its most nonzeros.

    The owner of entry k is the process with number ``part(k)``.
    """
    expand = laid.where("part_j <> process").select("process", "j", F.col("part_j").alias("other")).distinct()
    fold = laid.where("part_i <> process").select("process", "i", F.col("part_i").alias("other")).distinct()
    partners = expand.select("process", "other").unionByName(fold.select("process", "other")).distinct().groupBy("process").agg(F.count("*").alias("k"))
    load = laid.groupBy("process").agg(F.count("*").alias("z"))
    one = lambda df, c: df.agg(c)
    return (
        one(expand, F.count("*").alias("expand"))
        .crossJoin(one(fold, F.count("*").alias("fold")))
        .crossJoin(one(partners, F.coalesce(F.max("k"), F.lit(0)).alias("max_partners")))
        .crossJoin(load.agg(F.coalesce(F.sum("z"), F.lit(0)).alias("nonzeros"), F.coalesce(F.max("z"), F.lit(0)).alias("max_nonzeros")))
    )  # one row each
