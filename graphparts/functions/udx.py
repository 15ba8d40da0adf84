"""User-defined functions for SQL: aggregate, table function, views."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph


def gini():
    """A grouped-aggregate pandas function: inequality of part sizes, 0 for equal ones."""

    @F.pandas_udf("double")
    def inequality(x: pd.Series) -> float:
        s = x.sort_values().to_numpy(float)
        n = len(s)
        if not n or not s.sum():
            return 0.0
        return float(((2 * (pd.Series(range(1, n + 1))).to_numpy() - n - 1) * s).sum() / (n * s.sum()))

    return inequality


@F.udtf(returnType="part int, row int, col int")
class GridCells:
    """The process of every part in a grid of ``pr`` rows: ``grid_cells(p, pr)``."""

    def eval(self, p: int, pr: int):
        for k in range(p):
            yield k, k % pr, k // pr


def register(spark: SparkSession, g: Graph | None = None, parts: DataFrame | None = None) -> None:
    """Make the functions, and views ``gp_edges``, ``gp_arcs``, ``gp_vertices``, ``gp_parts``, known to SQL."""
    spark.udf.register("gini", gini())
    spark.udtf.register("grid_cells", GridCells)
    if g is not None:
        g.edges.createOrReplaceTempView("gp_edges")
        g.arcs.createOrReplaceTempView("gp_arcs")
        g.vertices.createOrReplaceTempView("gp_vertices")
    if parts is not None:
        parts.createOrReplaceTempView("gp_parts")
