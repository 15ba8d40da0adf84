"""Random graphs from counters and the portable hash: no state, any partitioning, same edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.functions.hashing import FIRST, PRIME, portable_draw, portable_hash
from graphparts.operators.graph import canonical


def erdos_renyi(spark: SparkSession, n: int, d_avg: int, seed: int = 42, counters: DataFrame | None = None) -> DataFrame:
    """``n * d_avg`` draws of two uniform ends, or one for each row of ``counters(id)``, as in the other generators."""
    e = spark.range(n * d_avg) if counters is None else counters
    return canonical(e.select((portable_hash("id", seed) % n).alias("src"), (portable_draw("id", seed + 1) % n).alias("dst")))


def high_diameter(spark: SparkSession, n: int, d_avg: int, seed: int = 42, counters: DataFrame | None = None) -> DataFrame:
    """Every vertex k draws ``d_avg`` ends within ``d_avg`` of itself; ends outside or at k are dropped."""
    e = (spark.range(n * d_avg) if counters is None else counters).select(F.floor(F.col("id") / d_avg).cast("bigint").alias("src"), "id")
    dst = F.col("src") - (d_avg - 1) + portable_draw("id", seed) % (2 * d_avg - 1)
    return canonical(e.select("src", dst.alias("dst")).where(f"dst >= 0 and dst < {n}"))


def rmat(spark: SparkSession, scale: int, d_avg: int, seed: int = 42, quadrants: tuple[int, int, int] = (57, 19, 19), counters: DataFrame | None = None) -> DataFrame:
    """Recursive quadrants chosen with ``quadrants`` in 100, the rest for the last one."""
    a, b, c = quadrants
    h = portable_hash("id", seed)
    e = (spark.range((1 << scale) * d_avg) if counters is None else counters).withColumn("x", h * h % PRIME)
    src: Column = F.lit(0).cast("bigint")
    dst: Column = F.lit(0).cast("bigint")
    for bit in range(scale):
        draw = F.col("x") * pow(FIRST, bit + 1, PRIME) % PRIME * 100 / F.lit(PRIME)
        src = src * 2 + F.when(draw < a + b, 0).otherwise(1)
        dst = dst * 2 + F.when((draw < a) | ((draw >= a + b) & (draw < a + b + c)), 0).otherwise(1)
    return canonical(e.select(src.alias("src"), dst.alias("dst")))


def mesh3d(spark: SparkSession, nx: int, ny: int, nz: int, points: DataFrame | None = None) -> DataFrame:
    """Every point of a grid with its up to 26 neighbours; with ``points(id)`` only those, numbered from 0."""
    p = (spark.range(nx * ny * nz) if points is None else points).select("id", (F.col("id") % nx).alias("x"), (F.floor(F.col("id") / nx).cast("bigint") % ny).alias("y"), F.floor(F.col("id") / (nx * ny)).cast("bigint").alias("z"))
    steps = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.lit(k).alias("k")) for i in (-1, 0, 1) for j in (-1, 0, 1) for k in (-1, 0, 1) if (k, j, i) > (0, 0, 0)))
    s = p.withColumn("s", F.explode(steps)).select("id", (F.col("x") + F.col("s.i")).alias("x"), (F.col("y") + F.col("s.j")).alias("y"), (F.col("z") + F.col("s.k")).alias("z"))
    inside = s.where(f"x >= 0 and x < {nx} and y >= 0 and y < {ny} and z < {nz}")
    out = inside.select(F.col("id").alias("src"), (F.col("x") + nx * (F.col("y") + ny * F.col("z"))).alias("dst"))
    return canonical(out if points is None else out.join(points.select(F.col("id").alias("dst")), "dst", "left_semi"))


def planted(spark: SparkSession, blocks: int, size: int, inside: int, across: int, seed: int = 42, counters: DataFrame | None = None) -> DataFrame:
    """``blocks`` of ``size`` vertices: every vertex draws ``inside`` ends in its block and ``across`` anywhere."""
    n, k = blocks * size, inside + across
    e = (spark.range(n * k) if counters is None else counters).select(F.floor(F.col("id") / k).cast("bigint").alias("src"), (F.col("id") % k).alias("nth"), "id")
    draw = portable_draw("id", seed)
    dst = F.when(F.col("nth") < inside, F.floor(F.col("src") / size).cast("bigint") * size + draw % size).otherwise(draw % n)
    return canonical(e.select("src", dst.alias("dst")))
