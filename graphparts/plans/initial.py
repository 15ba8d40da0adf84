"""First partitions: growth from random roots, label propagation, breadth-first growth, random and block labels."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash
from graphparts.operators.distribution import labels
from graphparts.operators.graph import Graph
from graphparts.plans.scratch import dropped, written
from graphparts.plans.skew import hashed


def draw_roots(g: Graph, p: int, seed: int) -> DataFrame:
    """``(v, part)``: the p vertices of the smallest hash, parts in drawing order."""
    drawn = g.vertices.select("v", portable_hash("v", seed).alias("h")).orderBy("h", "v").limit(p)
    return drawn.select("v", (F.row_number().over(Window.orderBy("h", "v")) - 1).cast("int").alias("part"))


def _spread(g: Graph, roots: DataFrame, seed: int, max_sweeps: int, choose) -> DataFrame:
    """Grow from ``roots`` until all vertices are reached or no more can be; only those reached in the last sweep are looked at in the next.

    A vertex is unassigned only while none of its neighbours was assigned before, so all
    assigned neighbours it has were reached in the sweep just ended.
    """
    arcs = g.arcs.select("v", "u")
    frontier = written(roots, "grow")
    reached, tables, sweep = frontier, [frontier], 0
    count = frontier.count()
    left = g.vertices.count() - count
    while left and (not max_sweeps or sweep < max_sweeps):
        seen = arcs.join(hashed(frontier.select(F.col("v").alias("u"), "part"), count), "u").select("v", "part")
        offers = seen.groupBy("v", "part").agg(F.count("*").alias("c")).join(reached.select("v"), "v", "left_anti")
        frontier = written(choose(offers, seed + sweep), "grow")
        count = frontier.count()
        if not count:
            break
        left -= count
        tables.append(frontier)
        reached = reached.unionByName(frontier)
        sweep += 1
        if sweep % 16 == 0:  # keep the union short
            reached = written(reached, "grow")
            dropped(reached.sparkSession, *tables[:-1])
            tables = [reached, frontier]
    return reached


def _any_part(offers: DataFrame, seed: int) -> DataFrame:
    """A uniformly random one of the distinct parts offered to each vertex."""
    return offers.groupBy("v").agg(F.min_by("part", F.struct(portable_hash(portable_hash("v", seed) + F.col("part"), seed + 1), F.col("part"))).alias("part"))


def _lowest_part(offers: DataFrame, seed: int) -> DataFrame:
    return offers.groupBy("v").agg(F.min("part").alias("part"))


def _most_part(offers: DataFrame, seed: int) -> DataFrame:
    """The part offered most often, the lowest of equals: what the random choice is compared with."""
    return offers.groupBy("v").agg(F.max_by("part", F.struct(F.col("c"), -F.col("part"))).alias("part"))


def _filled(g: Graph, reached: DataFrame, p: int, seed: int) -> DataFrame:
    """Vertices that no root reaches get a random part."""
    rest = (portable_hash("v", seed + 9) % p).cast("int")
    return g.vertices.select("v").join(reached, "v", "left").select("v", F.coalesce("part", rest).alias("part"))


def grow(g: Graph, p: int, seed: int = 42, max_sweeps: int = 0, choose=_any_part) -> DataFrame:
    """The hybrid start: spread from p random roots; a vertex takes any part among its neighbours', or by ``choose`` another one."""
    if g.vertices.count() < p:
        raise ValueError("growth needs at least as many vertices as parts")
    return _filled(g, _spread(g, draw_roots(g, p, seed), seed, max_sweeps, choose), p, seed)


def bfs(g: Graph, p: int, seed: int = 42, max_sweeps: int = 0) -> DataFrame:
    """Level by level from p random roots; a vertex takes the lowest part that reaches it first."""
    if g.vertices.count() < p:
        raise ValueError("growth needs at least as many vertices as parts")
    return _filled(g, _spread(g, draw_roots(g, p, seed), seed, max_sweeps, _lowest_part), p, seed)


def majority_sweep(g: Graph, labels_now: DataFrame) -> DataFrame:
    """Every vertex takes the label most frequent among its neighbours; ties keep its own, else the smallest."""
    seen = g.arcs.join(labels_now.select(F.col("v").alias("u"), F.col("part").alias("theirs")), "u").groupBy("v", "theirs").agg(F.sum("w").alias("n"))
    own = labels_now.select("v", F.col("part").alias("own"))
    best = seen.join(own, "v").groupBy("v").agg(F.max_by("theirs", F.struct("n", F.col("theirs") == F.col("own"), -F.col("theirs"))).alias("best"))
    return own.join(best, "v", "left").select("v", F.coalesce("best", "own").alias("part"))


def label_prop(g: Graph, p: int, seed: int = 42, sweeps: int = 3) -> DataFrame:
    """Unconstrained label propagation from one label a vertex, labels folded into p parts at the end."""
    now = g.vertices.select("v", F.col("v").alias("part"))
    for _ in range(sweeps):
        now = written(majority_sweep(g, now), "labels")
    return now.select("v", (portable_hash("part", seed) % p).cast("int").alias("part"))


def start(g: Graph, p: int, how: str, seed: int = 42, max_sweeps: int = 0) -> DataFrame:
    """``(v, part)`` by the named method."""
    if how == "grow":
        return grow(g, p, seed, max_sweeps)
    if how == "grow_majority":
        return grow(g, p, seed, max_sweeps, _most_part)
    if how == "bfs":
        return bfs(g, p, seed, max_sweeps)
    if how == "label_prop":
        return label_prop(g, p, seed)
    return labels(g.vertices, p, how, seed).withColumnRenamed("label", "part")
