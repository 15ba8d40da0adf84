"""Sizes, cuts, balance and validity of a partition, and measures over many runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph
from graphparts.plans.skew import hashed


def max_vertices(n: int, p: int, rat: float) -> float:
    """The most vertices a part may hold."""
    return (1.0 + rat) * n / p


def vertex_limit(n: int, p: int, rat: float) -> int:
    """The most vertices a part may hold as a whole number; never fewer than ``p`` equal parts need."""
    return max(int(max_vertices(n, p, rat) + 1e-9), -(-n // p))


def max_edges(m: int, p: int, rat: float) -> float:
    """The most edges a part may hold."""
    return (1.0 + rat) * m / p


def _every_part(spark: SparkSession, p: int) -> DataFrame:
    return spark.range(p).select(F.col("id").cast("int").alias("part"))


def edge_parts(g: Graph, parts: DataFrame) -> DataFrame:
    """Edges with the parts of both ends."""
    s, d = parts.select(F.col("v").alias("src"), F.col("part").alias("part_s")), parts.select(F.col("v").alias("dst"), F.col("part").alias("part_d"))
    if g.kept:  # counted in the stored tables at no cost
        n = g.vertices.count()
        s, d = hashed(s, n), hashed(d, n)
    return g.edges.join(s, "src").join(d, "dst").select("src", "dst", "w", "part_s", "part_d")


def part_vertices(parts: DataFrame, p: int) -> DataFrame:
    """``(part, vertices)``, empty parts included."""
    sizes = parts.groupBy("part").agg(F.count("*").alias("vertices"))
    return _every_part(parts.sparkSession, p).join(sizes, "part", "left").select("part", F.coalesce("vertices", F.lit(0)).alias("vertices"))


def part_sizes(g: Graph, parts: DataFrame, p: int) -> DataFrame:
    """``(part, vertices, internal, incident, cut)``: edges inside, edge ends in, and cut edges at each part, in one pass over the edges."""
    e = edge_parts(g, parts)
    ends = e.select(F.explode(F.array(F.struct(F.col("part_s").alias("part"), (F.col("part_s") != F.col("part_d")).alias("cut")), F.struct(F.col("part_d").alias("part"), (F.col("part_s") != F.col("part_d")).alias("cut")))).alias("x"))
    sums = ends.groupBy("x.part").agg(F.count("*").alias("incident"), F.sum(F.col("x.cut").cast("bigint")).alias("cut"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("bigint")
    full = part_vertices(parts, p).join(sums, "part", "left")
    return full.select("part", "vertices", ((zero("incident") - zero("cut")) / 2).cast("bigint").alias("internal"), zero("incident").alias("incident"), zero("cut").alias("cut"))


def part_edges(g: Graph, parts: DataFrame, p: int, measure: str = "internal") -> DataFrame:
    if measure not in ("internal", "incident"):
        raise ValueError(f"unknown measure: {measure}")
    return part_sizes(g, parts, p).select("part", F.col(measure).alias("edges"))


def cut_edges(g: Graph, parts: DataFrame) -> DataFrame:
    return edge_parts(g, parts).where("part_s <> part_d").select("src", "dst", "part_s", "part_d")


def part_cut(g: Graph, parts: DataFrame, p: int) -> DataFrame:
    return part_sizes(g, parts, p).select("part", "cut")


def quality(g: Graph, parts: DataFrame, p: int) -> DataFrame:
    """All quality measures in one row: cuts, ratios, and imbalance as the largest part over the mean."""
    sums = part_sizes(g, parts, p).agg(
        F.sum("vertices").alias("n"),
        (F.sum("incident") / 2).cast("bigint").alias("m"),
        (F.sum("cut") / 2).cast("bigint").alias("cut"),
        F.max("cut").alias("max_cut"),
        F.max("vertices").alias("max_vertices"),
        F.max("internal").alias("max_internal"),
        F.max("incident").alias("max_incident"),
        F.sum("internal").alias("internal"),
    )
    over = lambda a, b: F.when(b > 0, F.round(a / b, 6)).otherwise(F.lit(0.0))
    c = F.col
    return sums.select(
        "n",
        "m",
        "cut",
        "max_cut",
        over(c("cut"), c("m")).alias("edge_cut_ratio"),
        over(c("max_cut") * p, c("m")).alias("scaled_max_cut"),
        over(c("max_vertices") * p, c("n")).alias("vertex_imbalance"),
        over(c("max_internal") * p, c("internal")).alias("internal_imbalance"),
        over(c("max_incident") * p, c("m") * 2).alias("incident_imbalance"),
        over(c("max_cut") * p, c("cut") * 2).alias("cut_balance"),
    )


def limits(g: Graph, parts: DataFrame, p: int, rat_v: float = 0.1, rat_e: float = 0.1) -> DataFrame:
    """One row: the largest part by vertices and by edges, its limits, and the largest cut of a part."""
    n, m = g.sizes()
    top = part_sizes(g, parts, p).agg(F.max("vertices").alias("max_vertices"), F.max("internal").alias("max_edges"), F.max("cut").alias("max_cut"))
    return top.select("max_vertices", F.lit(vertex_limit(n, p, rat_v)).alias("vertex_limit"), "max_edges", F.lit(max_edges(m, p, rat_e)).alias("edge_limit"), "max_cut")


def validate(g: Graph, parts: DataFrame, p: int) -> DataFrame:
    """``(missing, strangers, repeated, outside)``: all zero for a valid partition."""
    v = g.vertices.select("v")
    counts = [
        v.join(parts, "v", "left_anti").agg(F.count("*").alias("missing")),
        parts.join(v, "v", "left_anti").agg(F.count("*").alias("strangers")),
        parts.groupBy("v").count().where("count > 1").agg(F.count("*").alias("repeated")),
        parts.where(f"part is null or part < 0 or part >= {p}").agg(F.count("*").alias("outside")),
    ]
    out = counts[0]
    for c in counts[1:]:
        out = out.crossJoin(c)  # one row each
    return out


def random_cut_expectation(p: int) -> float:
    return (p - 1) / p


def quotient(g: Graph, parts: DataFrame) -> DataFrame:
    """``(a, b, edges)``: edges inside and between parts, ``a <= b``."""
    e = edge_parts(g, parts)
    return e.select(F.least("part_s", "part_d").alias("a"), F.greatest("part_s", "part_d").alias("b")).groupBy("a", "b").agg(F.count("*").alias("edges"))


def performance_ratio(runs: DataFrame, value: str, only_complete: bool = False) -> DataFrame:
    """Per method the geometric mean, over tests, of its value over the best value of the test.

    ``runs(test, method, <value>)``; a missing or null value is a failure and leaves the method out of that test, or with
    ``only_complete`` the test out for all. Values of 0 count as the smallest positive number that rounds to them.
    """
    done = runs.where(F.col(value).isNotNull()).select("test", "method", F.greatest(F.col(value).cast("double"), F.lit(1e-9)).alias("x"))
    best = done.groupBy("test").agg(F.min("x").alias("best"), F.count("*").alias("k"))
    if only_complete:
        best = best.where(F.col("k") == runs.select("method").distinct().count())
    return done.join(best, "test").groupBy("method").agg(F.round(F.exp(F.avg(F.log(F.col("x") / F.col("best")))), 6).alias("ratio"), F.count("*").alias("tests"))


def speedups(runs: DataFrame) -> DataFrame:
    """``runs(graph, method, workers, seconds)`` with the speedup over the method's smallest run and the efficiency."""
    base = runs.groupBy("graph", "method").agg(F.min_by("seconds", "workers").alias("base"), F.min("workers").alias("least"))
    x = runs.join(base, ["graph", "method"])
    return x.select("graph", "method", "workers", "seconds", F.round(F.col("base") / F.col("seconds"), 6).alias("speedup"), F.round(F.col("base") * F.col("least") / (F.col("seconds") * F.col("workers")), 6).alias("efficiency"))


def per_core_ratio(speedup_over_single: float, workers: int) -> float:
    """How many times more core seconds the distributed run takes than the single-node one."""
    return workers / speedup_over_single


def absolute_speedups(runs: DataFrame, single: DataFrame) -> DataFrame:
    """``runs(graph, workers, seconds)`` against ``single(graph, single)``: the speedup over the single-node predecessor, and core seconds over its own."""
    x = runs.join(single, "graph").withColumn("absolute_speedup", F.col("single") / F.col("seconds"))
    return x.select("graph", "workers", "seconds", F.round("absolute_speedup", 6).alias("absolute_speedup"), F.round(F.col("workers") / F.col("absolute_speedup"), 6).alias("per_core_ratio"))


def communication(g: Graph, parts: DataFrame) -> DataFrame:
    """One superstep of a vertex program laid out by part: vertices to send, to how many parts, and edges cut."""
    pairs = edge_parts(g, parts).where("part_s <> part_d")
    sent = pairs.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("part_d").alias("to")), F.struct(F.col("dst").alias("v"), F.col("part_s").alias("to")))).alias("x")).select("x.v", "x.to").distinct()
    return sent.agg(F.count("*").alias("messages"), F.countDistinct("v").alias("senders")).crossJoin(pairs.agg(F.count("*").alias("cut")))
