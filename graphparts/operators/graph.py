"""Undirected graphs as DataFrames.

``edges(src, dst, w)`` holds each edge once with ``src < dst``; ``vertices(v, deg, w)`` holds every
vertex, isolated ones included; ``arcs(v, u, w)`` is both directions. Weights are 1 unless given.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.plans.scratch import written


@dataclass(frozen=True)
class Graph:
    edges: DataFrame
    vertices: DataFrame
    kept: bool = False
    #: Where vertices follow from the edges: makes them of the stored edges, so that edges are computed once.
    follows: Callable[[DataFrame], DataFrame] | None = None

    @property
    def arcs(self) -> DataFrame:
        """Both directions of every edge, by one pass over the edges."""
        both = F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u"))))
        return self.edges.select(both.alias("x"), "w").select("x.v", "x.u", "w")

    def stored(self) -> Graph:
        """The same graph written once in the shared folder, for plans that read it many times; a graph that is ``kept`` there already is itself."""
        if self.kept:
            return self
        edges = written(self.edges, "edges")
        return Graph(edges, written(self.follows(edges) if self.follows else self.vertices, "vertices"), True)

    def sizes(self) -> tuple[int, int]:
        """Numbers of vertices and edges."""
        return self.vertices.count(), self.edges.count()


def canonical(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Loops and nulls removed, both directions and repeats merged; a column ``w`` is summed over repeats."""
    a, b = F.col(src).cast("bigint"), F.col(dst).cast("bigint")
    w = F.col("w") if "w" in edges.columns else F.lit(1).cast("bigint")
    pairs = edges.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"), w.alias("w"))
    return pairs.groupBy("src", "dst").agg(F.sum("w").alias("w") if "w" in edges.columns else F.lit(1).cast("bigint").alias("w"))


def degrees(edges: DataFrame) -> DataFrame:
    ends = edges.select(F.explode(F.array("src", "dst")).alias("v"))
    return ends.groupBy("v").agg(F.count("*").alias("deg"))


def graph_of(edges: DataFrame, vertices: DataFrame | None = None) -> Graph:
    """A graph from any edge list; ``vertices(v[, w])`` adds isolated vertices and vertex weights."""
    edges = canonical(edges)
    if vertices is None:
        ends = lambda e: degrees(e).withColumn("w", F.lit(1).cast("bigint"))
        return Graph(edges, ends(edges), follows=ends)
    w = F.col("w") if "w" in vertices.columns else F.lit(1).cast("bigint")
    given = vertices.where("v is not null").select(F.col("v").cast("bigint").alias("v"), w.cast("bigint").alias("w")).groupBy("v").agg(F.max("w").alias("w"))
    full = lambda e: given.join(degrees(e), "v", "full").select("v", F.coalesce("deg", F.lit(0)).cast("bigint").alias("deg"), F.coalesce("w", F.lit(1)).cast("bigint").alias("w"))
    return Graph(edges, full(edges), follows=full)


def stats(g: Graph) -> DataFrame:
    """``n, m, d_avg_arcs`` (2m/n), ``d_avg_edges`` (m/n), ``d_max`` in one row."""
    d = g.vertices.agg(F.count("*").alias("n"), (F.coalesce(F.sum("deg"), F.lit(0)) / 2).cast("bigint").alias("m"), F.coalesce(F.max("deg"), F.lit(0)).alias("d_max"))
    ratio = lambda k: F.when(F.col("n") > 0, F.round(F.lit(k) * F.col("m") / F.col("n"), 6))
    return d.select("n", "m", ratio(2).alias("d_avg_arcs"), ratio(1).alias("d_avg_edges"), "d_max")


def degree_histogram(g: Graph) -> DataFrame:
    return g.vertices.groupBy("deg").agg(F.count("*").alias("n"))


def hubs(g: Graph, k: int) -> DataFrame:
    """The ``k`` vertices of the highest degree, ties by id."""
    return g.vertices.select("v", "deg").orderBy(F.desc("deg"), "v").limit(k)


def induced(g: Graph, keep: DataFrame) -> Graph:
    """The subgraph on the vertices of ``keep(v)``."""
    s, d = keep.select(F.col("v").alias("src")), keep.select(F.col("v").alias("dst"))
    return graph_of(g.edges.join(s, "src", "left_semi").join(d, "dst", "left_semi"), keep.select("v"))
