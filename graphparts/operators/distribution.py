"""Which worker owns which vertex, what each worker has to know, and what is sent between them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash
from graphparts.operators.graph import Graph

RANDOM_SEED = 7


def running(df: DataFrame, order: str, value: Column, name: str, slices: int = 256) -> DataFrame:
    """``df`` with ``name``: the sum of ``value`` over all rows with a smaller ``order``.

    Sums of slices of the id range come first and offsets are added to running sums within a
    slice, so no task sees all rows, as it would in one window over the whole table.
    """
    low, high = df.agg(F.min(order), F.max(order)).first()
    if low is None:
        return df.withColumn(name, F.lit(0).cast("bigint"))
    width = (high - low) // slices + 1
    cut = df.withColumn("_slice", F.floor((F.col(order) - low) / width).cast("int")).withColumn("_value", value.cast("bigint"))
    sums = cut.groupBy("_slice").agg(F.sum("_value").alias("_sum"))  # at most ``slices`` rows
    before = Window.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("_slice", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_offset"))
    inside = Window.partitionBy("_slice").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    own = F.coalesce(F.sum("_value").over(inside), F.lit(0))
    return cut.withColumn("_own", own).join(F.broadcast(offsets), "_slice").withColumn(name, F.col("_own") + F.col("_offset")).drop("_slice", "_value", "_own", "_offset")


def random_labels(vertices: DataFrame, k: int, seed: int) -> DataFrame:
    return vertices.select("v", (portable_hash("v", seed) % k).cast("int").alias("label"))


def vertex_block_labels(vertices: DataFrame, k: int) -> DataFrame:
    """``k`` runs of ids with equal numbers of vertices."""
    n = vertices.count()
    ranked = running(vertices.select("v"), "v", F.lit(1), "rank")
    return ranked.select("v", F.expr(f"cast((rank * {k}) div {max(n, 1)} as int)").alias("label"))


def edge_block_labels(vertices: DataFrame, k: int) -> DataFrame:
    """``k`` runs of ids with equal sums of degrees."""
    total = vertices.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
    ranked = running(vertices.select("v", "deg"), "v", F.col("deg"), "mass")
    return ranked.select("v", F.expr(f"cast(least((mass * {k}) div {max(total, 1)}, {k - 1}) as int)").alias("label"))


def labels(vertices: DataFrame, k: int, how: str, seed: int = RANDOM_SEED) -> DataFrame:
    if k < 1:
        raise ValueError("the number of parts or workers must be at least 1")
    if how == "random":
        return random_labels(vertices, k, seed)
    if how == "vertex_block":
        return vertex_block_labels(vertices, k)
    if how == "edge_block":
        return edge_block_labels(vertices, k)
    raise ValueError(f"unknown distribution: {how}")


def owners(g: Graph, n_workers: int, how: str = "random", seed: int = RANDOM_SEED) -> DataFrame:
    """``(v, owner)``."""
    return labels(g.vertices, n_workers, how, seed).withColumnRenamed("label", "owner")


def _owned_arcs(g: Graph, own: DataFrame) -> DataFrame:
    left = own.select("v", F.col("owner").alias("owner_v"))
    right = own.select(F.col("v").alias("u"), F.col("owner").alias("owner_u"))
    return g.arcs.join(left, "v").join(right, "u")


def ghosts(g: Graph, own: DataFrame) -> DataFrame:
    """``(owner, u)``: vertices of other workers that are neighbours of a worker's own."""
    return _owned_arcs(g, own).where("owner_v <> owner_u").select(F.col("owner_v").alias("owner"), "u").distinct()


def subscribers(g: Graph, own: DataFrame) -> DataFrame:
    """``(u, owner)``: for each vertex the other workers that must learn its label."""
    return ghosts(g, own).select("u", "owner")


def boundary_pairs(g: Graph, own: DataFrame) -> DataFrame:
    """``(owner_v, owner_u, edges)``: edges between each pair of workers."""
    x = _owned_arcs(g, own).where("owner_v <> owner_u")
    return x.groupBy("owner_v", "owner_u").agg(F.count("*").alias("edges"))


def route(changed: DataFrame, subs: DataFrame) -> DataFrame:
    """Every changed ``(v, part)`` once to each worker that holds ``v`` as a ghost: ``(owner, v, part)``."""
    return changed.join(subs.select(F.col("u").alias("v"), "owner"), "v").select("owner", "v", "part")


def exchange_matrix(changed: DataFrame, own: DataFrame, subs: DataFrame) -> DataFrame:
    """``(source, target, messages, values)`` of one exchange; a message is a vertex and its part."""
    sent = route(changed, subs).withColumnRenamed("owner", "target").join(own.withColumnRenamed("owner", "source"), "v")
    return sent.groupBy("source", "target").agg(F.count("*").alias("messages"), (F.count("*") * 2).alias("values"))


def placed(g: Graph, parts: DataFrame, n_parts: int) -> DataFrame:
    """The adjacency laid out by part: the rows of a part lie in one partition, sorted."""
    x = g.arcs.join(parts.select("v", "part"), "v")
    return x.repartitionById(n_parts, F.col("part")).sortWithinPartitions("v", "u")


