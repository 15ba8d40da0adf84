"""Graph analytics that a good partition speeds up. Every loop cuts its lineage in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash
from graphparts.operators.components import connected_components
from graphparts.operators.graph import Graph
from graphparts.plans.initial import majority_sweep
from graphparts.plans.scratch import dropped, written
from graphparts.plans.skew import hashed


def bfs_levels(arcs: DataFrame, sources: DataFrame, max_levels: int = 0) -> DataFrame:
    """``(source, v, dist)`` of everything reached from ``sources(source)`` along ``arcs(v, u)``."""
    frontier = written(sources.select("source", F.col("source").alias("v"), F.lit(0).alias("dist")).distinct(), "bfs")
    seen, tables, level = frontier, [frontier], 0
    out = arcs.select("v", "u")
    while not max_levels or level < max_levels:
        level += 1
        step = frontier.select("source", "v").join(out, "v").select("source", F.col("u").alias("v")).distinct()
        frontier = written(step.join(seen.select("source", "v"), ["source", "v"], "left_anti").withColumn("dist", F.lit(level)), "bfs")
        if not frontier.take(1):
            break
        tables.append(frontier)
        seen = seen.unionByName(frontier)
        if level % 16 == 0:
            seen = written(seen, "bfs")
            dropped(seen.sparkSession, *tables[:-1])
            tables = [seen, frontier]
    return seen


def reach_counts(g: Graph, sources: DataFrame, max_levels: int = 0) -> DataFrame:
    """``(source, dist, n)``: how many vertices each of ``sources(source)`` reaches at each distance.

    All searches go on together: a vertex has a bit for each source, in numbers of 64, so a level reads the arcs once however many sources there are.
    """
    spark, ids = sources.sparkSession, [r.source for r in sources.distinct().orderBy("source").collect()]  # the sources alone
    words = [f"b{k}" for k in range(-(-len(ids) // 64))]
    if not words:
        return spark.createDataFrame([], f"source {sources.schema['source'].dataType.simpleString()}, dist int, n bigint")
    bit = lambda k: -(1 << 63) if k == 63 else 1 << k
    rows = [(v, *((bit(k % 64) if k // 64 == w else 0) for w in range(len(words)))) for k, v in enumerate(ids)]
    frontier = written(spark.createDataFrame(rows, "v bigint, " + ", ".join(f"{w} bigint" for w in words)), "reach")
    seen, tables, level, count, out = frontier, [frontier], 0, len(ids), [(k, 0, 1) for k in range(len(ids))]
    while count and (not max_levels or level < max_levels):
        level += 1
        around = g.arcs.select("v", "u").join(hashed(frontier.withColumnRenamed("v", "u"), count), "u").groupBy("v").agg(*(F.bit_or(w).alias(w) for w in words))
        known = seen.groupBy("v").agg(*(F.bit_or(w).alias(f"{w}_") for w in words))
        fresh = around.join(known, "v", "left").select("v", *(F.col(w).bitwiseAND(F.bitwise_not(F.coalesce(f"{w}_", F.lit(0)))).alias(w) for w in words))
        frontier = written(fresh.where(" or ".join(f"{w} <> 0" for w in words)), "reach")
        bits = F.concat(*(F.expr(f"transform(filter(sequence(0, 63), k -> (shiftrightunsigned({w}, k) & 1) = 1), k -> k + {64 * i})") for i, w in enumerate(words)))
        found = frontier.select(F.explode(bits).alias("k")).groupBy("k").agg(F.count("*").alias("n")).collect()  # a row for each source
        out += [(r.k, level, r.n) for r in found]
        count = frontier.count()
        tables.append(frontier)
        seen = seen.unionByName(frontier)
        if level % 16 == 0:
            seen = written(seen.groupBy("v").agg(*(F.bit_or(w).alias(w) for w in words)), "reach")
            dropped(spark, *tables[:-1])
            tables = [seen, frontier]
    dropped(spark, *tables)
    return spark.createDataFrame([(ids[k], dist, n) for k, dist, n in out], "source bigint, dist int, n bigint")


def harmonic(g: Graph, k: int = 100, seed: int = 13) -> DataFrame:
    """``(v, harmonic)`` of ``k`` vertices drawn by hash: the sum of 1 / distance to all others."""
    drawn = g.vertices.orderBy(portable_hash("v", seed), "v").limit(k).select(F.col("v").alias("source"))
    per = reach_counts(g, drawn)
    return per.groupBy(F.col("source").alias("v")).agg(F.round(F.coalesce(F.sum(F.when(F.col("dist") > 0, F.col("n") / F.col("dist"))), F.lit(0.0)), 6).alias("harmonic"))


def approx_diameter(g: Graph, rounds: int = 10, seed: int = 17) -> int:
    """The longest distance over BFS rounds, each from a random vertex of the last level of the one before."""
    first = g.vertices.orderBy(portable_hash("v", seed), "v").limit(1).select(F.col("v").alias("source"))
    source, longest = first, 0
    for k in range(rounds):
        levels = bfs_levels(g.arcs, source)
        far = levels.agg(F.max("dist")).first()[0]
        if far is None:
            return 0
        longest = max(longest, far)
        source = levels.where(F.col("dist") == far).orderBy(portable_hash("v", seed + k), "v").limit(1).select(F.col("v").alias("source"))
    return longest


def kcore(g: Graph, ks: list[int] | None = None, approximate: bool = True, max_rounds: int = 0) -> DataFrame:
    """``(v, core)``: the largest threshold at which v survives peeling; thresholds double, or with ``approximate=False`` grow by one."""
    d_max = g.vertices.agg(F.coalesce(F.max("deg"), F.lit(0))).first()[0]
    ks = ks or ([1 << k for k in range(d_max.bit_length())] if approximate else list(range(1, d_max + 1)))
    edges = written(g.edges.select("src", "dst"), "core")
    out = g.vertices.select("v", F.lit(0).alias("core"))
    for k in ks:
        rounds = 0
        while True:
            deg = edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").count().where(F.col("count") >= k).select("v")
            kept = written(edges.join(deg.withColumnRenamed("v", "src"), "src", "left_semi").join(deg.withColumnRenamed("v", "dst"), "dst", "left_semi"), "core")
            before, after = edges.count(), kept.count()
            edges, rounds = kept, rounds + 1
            if before == after or max_rounds and rounds >= max_rounds:
                break
        if not after:
            break
        alive = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct().withColumn("now", F.lit(k))
        out = written(out.join(alive, "v", "left").select("v", F.coalesce("now", "core").alias("core")), "core")
    return out


def label_propagation(g: Graph, sweeps: int = 5) -> DataFrame:
    """``(v, community)`` after a fixed number of majority sweeps from one label a vertex."""
    now = g.vertices.select("v", F.col("v").alias("part"))
    for _ in range(sweeps):
        now = written(majority_sweep(g, now), "labels")
    return now.withColumnRenamed("part", "community")


def pagerank(g: Graph, iterations: int = 10, damping: float = 0.85) -> DataFrame:
    """``(v, rank)``; what vertices without edges hold is shared out among all."""
    n = g.vertices.count()
    ranks = g.vertices.select("v", "deg", F.lit(1.0 / max(n, 1)).alias("rank"))
    arcs = g.arcs.select("v", "u")
    for k in range(iterations):
        loose = ranks.where("deg = 0").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
        given = ranks.where("deg > 0").select("v", (F.col("rank") / F.col("deg")).alias("share")).join(arcs, "v").groupBy(F.col("u").alias("v")).agg(F.sum("share").alias("got"))
        base = (1 - damping) / n + damping * loose / n if n else 0.0
        ranks = ranks.select("v", "deg").join(given, "v", "left").select("v", "deg", (F.lit(base) + damping * F.coalesce("got", F.lit(0.0))).alias("rank"))
        ranks = written(ranks, "ranks")
    return ranks.select("v", F.round("rank", 9).alias("rank"))


def wcc(g: Graph) -> DataFrame:
    """``(v, component)``, the smallest id of each component, isolated vertices included."""
    return g.vertices.select("v").join(connected_components(g.edges), "v", "left").select("v", F.coalesce("component", "v").alias("component"))


def largest_scc(arcs: DataFrame, max_trims: int = 20) -> DataFrame:
    """``(v)`` of the largest strongly connected component of directed ``arcs(src, dst)``; ties go to the one found first.

    Vertices that no cycle passes are trimmed; then what the vertex of the largest product of degrees reaches and is
    reached from is one component, and the search goes on in the rest while it could hold a larger one: a strong component
    lies within a weak one, so only weak components of more vertices than the largest found so far are kept.
    """
    now = written(arcs.select("src", "dst").where("src <> dst").distinct(), "scc")
    best, size = now.select(F.col("src").alias("v")).limit(0), 0
    anything = arcs.agg(F.min(F.least("src", "dst")).alias("v")).where("v is not null")
    while True:
        for _ in range(max_trims):
            kept = written(now.join(now.select(F.col("dst").alias("src")).distinct(), "src", "left_semi").join(now.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi"), "scc")
            same = kept.count() == now.count()
            now = kept
            if same:
                break
        vertices = now.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
        if vertices.count() <= size:
            return best if size else anything
        out, into = now.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("o")), now.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("i"))
        degrees = vertices.join(out, "v", "left").join(into, "v", "left").select("v", (F.coalesce("o", F.lit(0)) * F.coalesce("i", F.lit(0))).alias("d"))
        pivot = written(degrees.orderBy(F.desc("d"), "v").limit(1).select(F.col("v").alias("source")), "scc")
        forward = bfs_levels(now.select(F.col("src").alias("v"), F.col("dst").alias("u")), pivot).select("v")
        back = bfs_levels(now.select(F.col("dst").alias("v"), F.col("src").alias("u")), pivot).select("v")
        found = written(forward.intersect(back), "scc")
        k = found.count()
        if k > size:
            best, size = found, k
        now = written(now.join(found.withColumnRenamed("v", "src"), "src", "left_anti").join(found.withColumnRenamed("v", "dst"), "dst", "left_anti"), "scc")
        weak = connected_components(now)
        large = weak.join(weak.groupBy("component").agg(F.count("*").alias("n")).where(F.col("n") > size).select("component"), "component", "left_semi")
        now = written(now.join(large.select(F.col("v").alias("src")), "src", "left_semi"), "scc")


def directed(g: Graph) -> DataFrame:
    """Both directions of an undirected graph as directed arcs."""
    return g.arcs.select(F.col("v").alias("src"), F.col("u").alias("dst"))
